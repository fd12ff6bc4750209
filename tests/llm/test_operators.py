import collections
import hashlib
import random
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from kgtrail.llm import op1_bpe, op2_decontaminate, op3_token_files, op4_chat_views, op5_reshard, op6_pii, op7_repeats, op8_near_copies, op9_embeddings, op10_toxicity
from kgtrail.llm.common import new_path
from kgtrail.llm.components import components

DOCS = "doc_id long, text string, lang string, source string, n_chars long, ids string, row string, spans string"
LONG = "lorem ipsum dolor " * 20_000


def docs(spark, rows):
    """Documents with extra columns whose names clash with those the operators make."""
    return spark.createDataFrame([(i, t, "en", "s", len(t or ""), "x", "y", "z") for i, t in rows], DOCS)


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls, empty and very long texts, repeated rows."""
    return docs(spark, [(1, None), (2, ""), (3, LONG), (4, "one two"), (4, "one two"), (None, "three words here"), (5, "!!! ...")]).cache()


@pytest.fixture(scope="module")
def none(odd):
    return odd.limit(0)


def by_id(df):
    return {r["doc_id"]: r for r in df.collect()}


def test_odd_rows_pass_every_operator(spark, odd, none):
    bench = spark.createDataFrame([(1, "one two"), (2, None), (None, "three words here"), (3, "")], "item_id long, text string")
    labels = spark.createDataFrame([(1, 0, 1), (3, 1, 0), (None, 0, 1), (4, None, None)], "doc_id long, quality int, toxic int")
    path = op1_bpe.tokenizer_file()
    runs = [
        lambda d: op1_bpe.encode_documents(d, path),
        lambda d: op2_decontaminate.decontaminate(d, bench),
        lambda d: op5_reshard.reshard(d, old_shards=3, new_shards=4)[0],
        lambda d: op6_pii.find(d),
        lambda d: op7_repeats.without_repeats(d),
        lambda d: op8_near_copies.near_copies(d),
        lambda d: op10_toxicity.score(d, op10_toxicity.learn(d, labels)),
    ]
    for run in runs:
        assert run(odd).count() == 7
        assert run(none).count() == 0


def test_bpe_forms(spark, odd):
    path = op1_bpe.tokenizer_file()
    full, digest = by_id(op1_bpe.encode_documents(odd, path)), by_id(op1_bpe.encode_documents(odd, path, form="digest"))
    assert full[1]["ids"] == [] and full[2]["decoded"] == "" and digest[1]["n_tokens"] == 0
    for k in (3, 4, 5):
        assert digest[k]["ids_sha256"] == hashlib.sha256(" ".join(map(str, full[k]["ids"])).encode()).hexdigest()
        assert digest[k]["decoded_sha256"] == hashlib.sha256(full[k]["decoded"].encode()).hexdigest()


def test_decontaminate(spark, odd):
    bench = spark.createDataFrame([(1, "one two"), (2, None), (None, "three words here"), (3, "")], "item_id long, text string")
    got = by_id(op2_decontaminate.decontaminate(odd, bench))
    assert (got[4]["n_words"], got[4]["n_hit"], got[4]["contaminated"]) == (2, 2, True)
    assert got[None]["n_hit"] == 3 and got[None]["items_sha256"] == hashlib.sha256(b"null").hexdigest()
    assert (got[5]["n_words"], got[5]["contaminated"]) == (0, False)
    assert op2_decontaminate.decontaminate(odd, bench.limit(0)).filter("contaminated").count() == 0
    left = op2_decontaminate.clean(odd, bench)
    assert left.columns == odd.columns and left.count() == 4


def test_decontaminate_overlaps_and_case(spark):
    words = [f"w{i}" for i in range(30)]
    item = " ".join(words[:20])
    text = "x " + " ".join(words[:16]).upper() + " y " + " ".join(words[5:18]) + " É " + " ".join(words[:12])
    bench = spark.createDataFrame([(7, item), (8, "É"), (9, "é")], "item_id long, text string")
    r = op2_decontaminate.decontaminate(docs(spark, [(1, text)]), bench).first()
    assert (r["n_words"], r["n_hit"], r["n_items"]) == (1 + 16 + 1 + 13 + 1 + 12, 16 + 13 + 1, 2)
    near = op2_decontaminate.proximity_matches(docs(spark, [(1, "a b zz c d"), (2, "d c b a"), (3, "a b")]), spark.createDataFrame([(1, "a b c d")], "item_id long, text string"), slop=2)
    assert {x["doc_id"] for x in near.collect()} == {1, 2}


def test_token_files(spark, odd):
    path = new_path(spark, "test-files")
    tok = op1_bpe.tokenizer_file("byte_bpe_50k.json")
    op3_token_files.write_token_files(odd, path, tok, block_ids=100)
    got = op3_token_files.read_token_files(spark, path).orderBy("start").collect()
    assert [r["doc_id"] for r in got] == [None, 1, 2, 3, 4, 4, 5]
    assert [r["start"] for r in got] == np.cumsum([0, *[r["n_tokens"] for r in got[:-1]]]).tolist()
    ids = {r["doc_id"]: r["ids"] for r in op3_token_files.read_ids(spark, path).collect()}
    assert ids[1] == ids[2] == [0]
    assert {r["doc_id"]: r["ids_crc32"] for r in got}[4] == zlib.crc32(np.array(ids[4], "<u4").tobytes())
    empty = new_path(spark, "test-files")
    op3_token_files.write_token_files(odd.limit(0), empty, tok)
    assert op3_token_files.read_token_files(spark, empty).count() == 0


def test_chat_views(spark):
    turns = [(1, 0, "system", "be kind"), (1, 1, "ann", "hi <|assistant|>"), (1, 2, "bob", None), (1, 2, "bob", None), (2, 0, "system", "x"), (None, 0, None, "alone"), *[(3, i, "ab"[i % 2], f"t{i}") for i in range(150)]]
    t = spark.createDataFrame([(*x, "z") for x in turns], "conv_id long, turn long, role string, text string, speaker string")
    rows = op4_chat_views.rotate(t).collect()
    ann = next(r for r in rows if r["conv_id"] == 1 and r["speaker"] == "ann")
    assert ann["text"] == "<|system|>\nbe kind<|end|>\n<|assistant|>\nhi < |assistant|><|end|>\n<|user name=bob|>\n<|end|>\n<|user name=bob|>\n<|end|>\n"
    a, b = map(int, ann["mask"].split(":"))
    assert ann["text"][a:b] == "hi < |assistant|><|end|>\n" and ann["n_trained"] == b - a
    assert {r["speaker"] for r in rows if r["conv_id"] is None} == {"unknown"} and not [r for r in rows if r["conv_id"] == 2]
    long = sorted((r["piece"], r["part"], r["n_turns"]) for r in rows if r["conv_id"] == 3 and r["speaker"] == "a")
    assert long == [(0, 0, 64), (1, 0, 64), (2, 0, 22)]
    assert op4_chat_views.rotate(t.limit(0)).count() == 0


def test_reshard_law_and_least_bytes(spark):
    rng = random.Random(3)
    rows = [(i, "x" * rng.randint(0, 400)) for i in range(500)]
    shards, plan = op5_reshard.reshard(docs(spark, rows), old_shards=5, new_shards=8)
    got = shards.collect()
    assert sorted((r["doc_id"], r["text"]) for r in got) == rows
    by = collections.defaultdict(list)
    for r in got:
        by[r["shard"]].append(r["slot"])
    assert max(map(len, by.values())) - min(map(len, by.values())) <= 1 and len(by) == 8
    assert all(sorted(s) == list(range(len(s))) for s in by.values())
    old = lambda i: zlib.crc32(str(i).encode()) % 5
    moved = sum(len(r["text"]) + 8 for r in got if old(r["doc_id"]) != r["shard"])
    sizes = collections.defaultdict(list)
    for i, t in rows:
        sizes[old(i)].append(len(t) + 8)
    least = sum(sum(sorted(v)[: max(0, len(v) - 63)]) for v in sizes.values())
    assert moved <= 1.1 * least and sum(t[2] for t in plan.transfers) == sum(old(r["doc_id"]) != r["shard"] for r in got)
    fewer, _ = op5_reshard.reshard(docs(spark, rows), old_shards=5, new_shards=3)
    assert sorted(r["n"] for r in fewer.groupBy("shard").agg(F.count("*").alias("n")).collect()) == [166, 167, 167]


def test_redact(spark, odd):
    d = docs(spark, [(1, "a@b.co x"), (2, None)])
    got = by_id(op6_pii.redact(d))
    assert (got[1]["text"], got[1]["n_chars"], got[2]["text"]) == ("[EMAIL] x", 9, None)
    assert op6_pii.redact(odd).columns == odd.columns


def brute_repeats(rows, w):
    blobs = [(t or "").encode() for _, t in rows]
    count = collections.Counter(b[k : k + w] for b in blobs for k in range(len(b) - w + 1))
    out = []
    for (i, _), b in zip(rows, blobs, strict=True):
        m = bytearray(len(b))
        for k in range(len(b) - w + 1):
            if count[b[k : k + w]] > 1:
                m[k : k + w] = b"\1" * w
        runs = sum(1 for k in range(len(m)) if m[k] and not (k and m[k - 1]))
        out.append((str(i), len(b), sum(m), runs, hashlib.sha256(bytes(x for x, y in zip(b, m, strict=True) if not y)).hexdigest()))
    return sorted(out)


@pytest.mark.parametrize(("width", "options"), [(40, {}), (40, {"hot": 1}), (24, {"chunk": 5})])
def test_repeats_against_brute_force(spark, width, options):
    rng = random.Random(width)
    rows = []
    for i in range(80):
        t = "".join(rng.choice(["abc", "ab", "x", "yz", "hello world ", "é"]) for _ in range(rng.randint(0, 80)))
        t += "q" * rng.randint(0, 150) * (i % 5 == 0)
        if i % 7 == 0 and rows:
            t += (rows[-1][1] or "")[:90]
        if i % 11 == 0 and rows:
            t = rows[-1][1]
        rows.append((i, t if i % 13 else None))
    if options:
        rows += [(7, rows[7][1]), (None, rows[3][1])]
    got = op7_repeats.without_repeats(docs(spark, rows), width=width, **options)
    assert sorted((str(r["doc_id"]), r["n_bytes"], r["n_removed"], r["n_spans"], r["kept_sha256"]) for r in got.collect()) == brute_repeats(rows, width)


def test_near_copies_against_brute_force(spark):
    rng = random.Random(8)
    vocab = [f"w{i}" for i in range(400)]
    base = [[rng.choice(vocab) for _ in range(rng.randint(3, 120))] for _ in range(60)]
    rows = [(i, " ".join(b)) for i, b in enumerate(base)]
    for i in range(60, 160):  # copies of copies with a few words changed
        w = list(rng.choice(base))
        for _ in range(rng.randint(0, 3)):
            w[rng.randrange(len(w))] = rng.choice(vocab)
        base.append(w)
        rows.append((i, " ".join(w)))
    got = by_id(op8_near_copies.near_copies(docs(spark, rows)))

    def grams(t):
        w = t.split()
        k = min(5, len(w))
        return collections.Counter(tuple(w[i : i + k]) for i in range(len(w) - k + 1))

    sets = [grams(t) for _, t in rows]
    comp = list(range(len(rows)))

    def find(i):
        while comp[i] != i:
            i = comp[i]
        return i

    for i, a in enumerate(sets):
        for j in range(i):
            common = sum((a & sets[j]).values())
            if common >= 0.8 * (sum(a.values()) + sum(sets[j].values()) - common):
                x, y = find(i), find(j)
                comp[max(x, y)] = min(x, y)
    assert {i: got[i]["class_id"] for i in got} == {i: find(i) for i in got}
    assert {i for i in got if got[i]["kept"]} == {i for i in got if find(i) == i}


def test_large_buckets_are_linked_in_blocks(spark, monkeypatch):
    rng = random.Random(9)
    origin = [f"w{i}" for i in range(150)]
    rows = []
    for i in range(120):
        w = list(origin)
        for _ in range(rng.randint(2, 6)):
            w[rng.randrange(len(w))] = f"n{i}_{rng.random()}"
        rows.append((i, " ".join(w)))
    d = docs(spark, rows)
    want = sorted((r["doc_id"], r["class_id"]) for r in op8_near_copies.near_copies(d).collect())
    monkeypatch.setattr(op8_near_copies, "SMALL", 2)
    monkeypatch.setattr(op8_near_copies, "BLOCK", 20)
    monkeypatch.setattr(op8_near_copies, "HUB_ROUNDS", 1)
    assert sorted((r["doc_id"], r["class_id"]) for r in op8_near_copies.near_copies(d).collect()) == want


def test_one_of_each_class_stays(spark, odd):
    left = op8_near_copies.without_near_copies(odd)
    assert left.columns == odd.columns
    assert sorted(str(r["doc_id"]) for r in left.collect()) == ["1", "2", "3", "4", "5", "None"]


def test_components(spark):
    links = spark.createDataFrame([(1, 2), (2, 3), (3, 4), (10, 9), (5, 5), (None, 1), *[(100 + i, 101 + i) for i in range(40)]], "a long, b long")
    got = {r["id"]: r["component"] for r in components(links).collect()}
    assert got[4] == 1 and got[10] == 9 and got[140] == 100 and 5 not in got
    assert components(links.limit(0)).count() == 0


def test_vectors(spark):
    rng = np.random.default_rng(2)
    base = rng.standard_normal((4, 8))
    rows = [(i, (base[i % 4] + 0.05 * rng.standard_normal(8)).tolist(), i % 2) for i in range(60)]
    rows += [(60, rows[0][1], 0), (61, None, 0), (62, [0.0] * 8, 0), (63, [float("nan")] + [1.0] * 7, 0), (64, rows[0][1], None), (65, [1.0], 0), (66, [], 0), (None, rows[0][1], 0), (67, [None] + [1.0] * 7, 0)]
    df = spark.createDataFrame([(*r, "q") for r in rows], "vec_id long, embedding array<float>, label int, rep string")
    got = {r["vec_id"]: r for r in op9_embeddings.near_vectors(df, block=8).collect()}
    good = [(i, np.array(v, np.float32).astype(float), c) for i, v, c in rows if i is not None and i <= 60]
    for i, v, c in good:
        want = sum(1 for j, u, e in good if j != i and e == c and u @ v / np.linalg.norm(u) / np.linalg.norm(v) >= 0.98)
        assert got[i]["n_links"] == want
    for i in (61, 62, 63, 64, 65, 66, 67):
        assert (got[i]["n_links"], got[i]["component_id"], got[i]["kept"]) == (0, i, True)
    assert got[60]["component_id"] == got[0]["component_id"] == 0
    assert op9_embeddings.near_vectors(df.limit(0)).count() == 0


def test_toxicity_on_held_out_rows(spark):
    t = lambda n: spark.read.parquet(f"/root/testdata/sf0.1/{n}.parquet")
    model = op10_toxicity.learn(t("documents"), t("labels"))
    rows = op10_toxicity.score(t("documents"), model).filter("held_out").join(t("labels"), "doc_id").collect()
    hit = sum(r["predicted"] for r in rows if r["toxic"])
    wrong = sum(r["predicted"] for r in rows if not r["toxic"])
    assert hit / sum(r["toxic"] for r in rows) >= 0.85 and wrong / len(rows) <= 0.01
    d = docs(spark, [(1, "you idiot loser moron"), (2, "the and of")])
    assert [r["doc_id"] for r in op10_toxicity.reject(d, model).collect()] == [2]
