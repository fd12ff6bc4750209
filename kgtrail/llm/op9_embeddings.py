"""Near-duplicate vectors by sorted projection passes.

In each pass the vectors of a label are sorted by a concatenation of random sign hashes, and every
vector is compared with the block it stands in and the block before, also where these lie in
different tasks. The verified links of all passes give the components. As links lie within
components, the links of each vector are then counted exactly by comparing the blocks of its
component.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, LongType, StructField, StructType

from kgtrail.llm.common import stored, table
from kgtrail.llm.components import components
from kgtrail.llm.kernels import vectors as kernel

LEAST = 0.98
#: Sign hashes in a sort key, and vectors in a block of the sorted list.
BITS, BLOCK = 48, 512
#: Passes at least; more as labels grow, so that MISSED of the links or fewer stay apart in all.
PASSES, MISSED = 6, 0.005
#: Vectors in a block when links are counted inside a component.
COUNT_BLOCK = 4096


def passes_for(largest: int, least: float = LEAST, block: int = BLOCK) -> int:
    """Passes for a label of `largest` vectors. Two vectors of cosine `least` differ in a sign with
    probability acos(least) / pi, and meet if the leading signs agree that tell two blocks apart:
    log2 of the blocks, half as many again for labels that are not spread evenly."""
    signs = 1.5 * math.log2(max(2.0, largest / block))
    meet = (1 - math.acos(least) / math.pi) ** signs
    return max(PASSES, math.ceil(math.log(MISSED) / math.log(1 - meet)))


def _keys(passes: int, bits: int, seed: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        planes: dict[int, np.ndarray] = {}
        for batch in batches:
            vecs = batch.column(batch.schema.get_field_index("vec"))
            codes = []
            for v in vecs:
                x = np.array(v.as_py(), np.float64)
                x = x / np.abs(x).max()
                if len(x) not in planes:
                    planes[len(x)] = np.random.default_rng([seed, len(x)]).standard_normal((passes * bits, len(x)))
                signs = (planes[len(x)] @ x > 0).reshape(passes, bits)
                codes.append((signs @ (1 << np.arange(bits)[::-1])).tolist())
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(codes, pa.list_(pa.int64()))], [*batch.schema.names, "codes"])

    return run


FOUND = "a long, b long, task int, head boolean, grp string, node long, vec array<double>"


def _links(nodes: list, rows: list, groups: list, least: float) -> list[tuple[int, int]]:
    found = []
    for w in {len(r) for r in rows}:  # vectors of different length are never alike
        mine = [k for k in range(len(rows)) if len(rows[k]) == w]
        _, group = np.unique([groups[k] for k in mine], return_inverse=True)
        found += kernel.forest(np.array([nodes[k] for k in mine]), kernel.unit(np.array([rows[k] for k in mine])), least, group)
    return found


def _windows(block: int, least: float):
    """Links inside two neighbouring blocks of a task's part of the list, and the part's first and
    last block, which meet those of the tasks beside it later."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        task, nodes, rows, groups = TaskContext.get().partitionId(), [], [], []
        kinds = [pa.int64(), pa.int64(), pa.int32(), pa.bool_(), pa.string(), pa.int64(), pa.list_(pa.float64())]
        names = ["a", "b", "task", "head", "grp", "node", "vec"]

        def links(n: int):
            found = _links(nodes[:n], rows[:n], groups[:n], least)
            none = [None] * len(found)
            return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(([a for a, _ in found], [b for _, b in found], none, none, none, none, none), kinds, strict=True)], names)

        def border(head: bool, part: slice):
            own, n = nodes[part], len(nodes[part])
            cols = ([None] * n, [None] * n, [task] * n, [head] * n, groups[part], own, rows[part])
            return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], names)

        first = True
        for batch in batches:
            for group, node, vec in zip(*(batch.column(c) for c in ("grp", "node", "vec")), strict=True):
                nodes.append(node.as_py())
                rows.append(vec.as_py())
                groups.append(group.as_py())
                if len(nodes) == 2 * block:
                    if first:
                        yield border(True, slice(0, block))
                        first = False
                    yield links(2 * block)
                    del nodes[:block], rows[:block], groups[:block]
        if nodes:
            if first:
                yield border(True, slice(0, block))
            yield links(len(nodes))
            yield border(False, slice(max(0, len(nodes) - block), None))

    return run


def _across(least: float):
    import pandas as pd

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        found = _links(pdf["node"].tolist(), [list(v) for v in pdf["vec"]], pdf["grp"].tolist(), least)
        return pd.DataFrame(found, columns=["a", "b"], dtype=np.int64)

    return run


def _counted(least: float):
    import pandas as pd

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        """Rows of the blocks i and j of a component: links between them (or inside, if i = j)."""
        x = kernel.unit(np.stack(pdf["vec"].to_numpy()))
        m, b = pdf["m"].to_numpy(np.int64), pdf["b"].to_numpy()
        inside = pdf["i"].iloc[0] == pdf["j"].iloc[0]
        links = np.zeros(len(x), np.int64)
        for lo in range(0, len(x), 512):
            alike = (x[lo : lo + 512] @ x.T) >= least
            if inside:
                alike[np.arange(len(alike)), np.arange(lo, lo + len(alike))] = False
            else:
                alike &= b[lo : lo + 512, None] != b[None, :]
            links[lo : lo + 512] = alike @ m
        return pd.DataFrame({"node": pdf["node"].to_numpy(np.int64), "links": links})

    return run


def found_links(reps: DataFrame, *, least: float, passes: int, bits: int, block: int, seed: int) -> DataFrame:
    """(a, b): nodes of verified links that join what the windows of all passes join."""
    plain = reps.select(F.col("label").cast("string").alias("label"), "node", "vec")
    coded = plain.mapInArrow(_keys(passes, bits, seed), StructType([*plain.schema.fields, StructField("codes", ArrayType(LongType()))]))
    each = coded.select(F.posexplode("codes").alias("pass", "code"), "label", "node", "vec")
    each = each.withColumn("grp", F.concat_ws("/", F.col("pass").cast("string"), "label"))
    order = ["grp", "code", "node"]
    listed = each.repartitionByRange(*order).sortWithinPartitions(*order)
    got = stored(listed.select("grp", "node", "vec").mapInArrow(_windows(block, least), FOUND), "vector-windows")
    # the last block of a task's part meets the first block of the next part that has rows
    tasks = got.filter("task is not null").select("task").distinct()
    turn = tasks.select("task", F.row_number().over(Window.orderBy("task")).alias("turn"))  # a row for each task
    ends = got.filter("task is not null").join(F.broadcast(turn), "task").withColumn("border", F.col("turn") - F.col("head").cast("int"))
    across = ends.select("border", "grp", "node", "vec").groupBy("border").applyInPandas(_across(least), "a long, b long")
    return got.filter("a is not null").select("a", "b").unionByName(across)


def near_vectors(rows: DataFrame, *, least: float = LEAST, passes: int | None = None, bits: int = BITS, block: int = BLOCK, count_block: int = COUNT_BLOCK, seed: int = 7) -> DataFrame:
    """vec_id, n_links, component_id, kept for every row of (vec_id, embedding, label).

    Only vectors of one label are compared, by cosine in double precision. A row links with nothing
    (no links, its own component, kept) if its vec_id, label or vector is null or the vector is
    empty, zero or holds null or non-finite components; vectors of different length are never
    alike. Rows with equal label and vector are compared once and count as often as they occur; a
    vec_id that names several vectors names several nodes. An empty table gives no rows; other
    columns are ignored. passes: as passes_for the largest label, unless given.
    """
    real = F.transform("embedding", lambda x: x.cast("double"))
    rows = rows.select(F.col("vec_id").cast("long").alias("vec_id"), "label", real.alias("vec"))
    fine = F.col("vec_id").isNotNull() & F.col("label").isNotNull() & (F.size("vec") > 0)
    fine = fine & F.forall("vec", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists("vec", lambda x: x != 0)
    rows = rows.withColumn("fine", F.coalesce(fine, F.lit(False)))
    good = rows.filter("fine")
    # a vector and its copies are one node from here on
    reps = good.groupBy("label", "vec").agg(F.min("vec_id").alias("rep"), F.count("*").alias("m"))
    reps = stored(reps.withColumn("node", F.monotonically_increasing_id()), "vectors")
    if passes is None:
        passes = passes_for(reps.groupBy("label").agg(F.count("*").alias("n")).agg(F.max("n")).first()[0] or 0, least, block)
    found = stored(components(found_links(reps, least=least, passes=passes, bits=bits, block=block, seed=seed)), "vector-components")
    inside = stored(reps.join(found, reps["node"] == found["id"]).select("component", "rep", "node", "m", "vec"), "linked-vectors")
    sizes = stored(inside.groupBy("component").agg(F.ceil(F.count("*") / count_block).cast("int").alias("blocks"), F.min("rep").alias("name")), "component-sizes")
    placed = inside.join(sizes, "component").withColumn("b", F.pmod(F.xxhash64("node"), F.col("blocks")).cast("int"))
    placed = placed.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    placed = placed.select("component", "node", "m", "vec", "b", F.least("b", "other").alias("i"), F.greatest("b", "other").alias("j"))
    # dealt out by all three: the blocks of one component go to many tasks
    counts = placed.repartition("component", "i", "j").groupBy("component", "i", "j").applyInPandas(_counted(least), "node long, links long").groupBy("node").agg(F.sum("links").alias("links"))
    named = inside.select("node", "component").join(sizes.select("component", "name"), "component").drop("component")
    per_node = reps.join(counts, "node", "left").join(named, "node", "left")
    per_node = per_node.select(F.col("label").alias("l"), F.col("vec").alias("v"), (F.coalesce("links", F.lit(0)) + F.col("m") - 1).alias("n_links"), F.coalesce("name", "rep").alias("component_id"))
    linked = good.join(stored(per_node, "vector-links"), (F.col("label") == F.col("l")) & (F.col("vec") == F.col("v"))).select("vec_id", "n_links", "component_id")
    alone = rows.filter("not fine").select("vec_id", F.lit(0).cast("long").alias("n_links"), F.col("vec_id").alias("component_id"))
    return linked.unionByName(alone).withColumn("kept", F.col("vec_id").eqNullSafe(F.col("component_id")))


def op9_embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_vectors(table(spark, sf_dir, "embeddings"))
