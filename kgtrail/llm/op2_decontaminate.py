"""Benchmark decontamination through a positional inverted index, in DataFrame functions only.

Of each test window the terms that the corpus has least often are looked up. The index stores the
postings of these terms (term, document row, position) over all training texts, with the words
around each. The list of a window's rarest term and that of its second rarest, both shifted by the
term's place in the window, are intersected; what is left is checked word by word on the stored
words. The same index answers which places hold a window's words closely, in any order.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from kgtrail.llm.common import BETWEEN_WORDS, ascii_lower, stored, table

#: Consecutive words of a test item that make a window.
WIDTH = 13
#: Rows of a table up to which it is broadcast; terms beyond it are looked up in several scans.
BROADCAST_ROWS = 500_000
#: Words by which a close place may be longer than the window.
SLOP = 3


@dataclass(frozen=True)
class Index:
    """postings: term, row, pos, around (the lowered words from pos - reach to pos + reach, fewer
    where the text begins or ends). lengths: row, doc_id, the kept columns, n_words."""

    postings: DataFrame
    lengths: DataFrame
    reach: int


def words(text: Column) -> Column:
    """The words of a text in their own case; none for null. Split at what stands between them, as
    matching each word on its own takes several times as long."""
    return F.array_remove(F.split(F.coalesce(text, F.lit("")), BETWEEN_WORDS), "")


def sized(df: DataFrame, most: int | None = None) -> DataFrame:
    """df, to be broadcast if it has at most `most` rows."""
    most = BROADCAST_ROWS if most is None else most
    return F.broadcast(df) if df.limit(most + 1).count() <= most else df


def windows(items: DataFrame, width: int = WIDTH) -> DataFrame:
    """phrase (long id), terms (array), items (array of ids as strings): the distinct windows."""
    terms = items.select(F.coalesce(F.col("item_id").cast("string"), F.lit("null")).alias("item"), words(ascii_lower(F.col("text"))).alias("all"))
    terms = terms.withColumn("n", F.least(F.size("all"), F.lit(width))).filter("n > 0")
    each = terms.select("item", "n", "all", F.explode(F.sequence(F.lit(1), F.size("all") - F.col("n") + 1)).alias("at"))
    each = each.select("item", F.slice("all", F.col("at"), F.col("n")).alias("terms"))
    found = each.groupBy("terms").agg(F.collect_set("item").alias("items"))
    return found.withColumn("phrase", F.monotonically_increasing_id())


def _scans(terms: DataFrame) -> list[DataFrame]:
    """terms (key, ...) in parts of at most about BROADCAST_ROWS rows, each to be broadcast."""
    parts = -(-terms.count() // max(1, BROADCAST_ROWS))
    if parts <= 1:
        return [F.broadcast(terms)]
    return [F.broadcast(terms.filter(F.pmod(F.xxhash64("key"), F.lit(parts)) == i)) for i in range(parts)]


def term_counts(docs: DataFrame, terms: DataFrame) -> DataFrame:
    """key, n: how often each key of `terms` occurs in all documents (0 included). Words are counted
    where they are read: what is shuffled is a row for each term and task at most."""
    seen = docs.select(F.explode(words(F.col("text"))).alias("w")).select(F.lower("w").alias("key"))
    counts = reduce(DataFrame.unionByName, [seen.join(part, "key").groupBy("key").agg(F.count("*").alias("n")) for part in _scans(terms)])
    return terms.join(counts, "key", "left").fillna(0, ["n"])


def rarest_pairs(found: DataFrame, counts: DataFrame) -> DataFrame:
    """For each window that can occur at all: its two rarest terms, as keys with offsets."""
    places = found.select("phrase", F.size("terms").alias("len"), F.posexplode("terms").alias("off", "w")).withColumn("key", F.lower("w"))
    order = Window.partitionBy("phrase").orderBy("n", "off")
    ranked = places.join(counts, "key").withColumn("k", F.row_number().over(order))
    pairs = ranked.groupBy("phrase", "len").agg(
        F.min("n").alias("least"),
        F.max(F.when(F.col("k") == 1, F.struct("key", "off"))).alias("a"),
        F.max(F.when(F.col("k") == F.least("len", F.lit(2)), F.struct("key", "off"))).alias("b"),
    )
    return pairs.filter("least > 0").select("phrase", "len", F.col("a.key").alias("key"), F.col("a.off").alias("off"), F.col("b.key").alias("key2"), F.col("b.off").alias("off2"))


def build_index(docs: DataFrame, terms: DataFrame, reach: int, keep: tuple[str, ...] = ()) -> Index:
    """The index of docs for the given terms (key, distinct), written to the shared folder.

    Every document ends with an empty word, whose posting tells its length; it is read in the first
    scan only. No word leaves the scan but the postings, so texts are never shuffled.
    """
    end = docs.sparkSession.range(1).select(F.lit("").alias("key"))
    scans = _scans(terms)
    rows = docs.select(F.monotonically_increasing_id().alias("row"), F.col("doc_id").cast("long").alias("doc_id"), *keep, "text")
    if len(scans) > 1:  # all scans must name the rows alike
        rows = stored(rows, "index-rows")
    scans[0] = F.broadcast(scans[0].unionByName(end))
    each = rows.select("row", "doc_id", *keep, F.concat(words(F.col("text")), F.array(F.lit(""))).alias("ws"))
    each = each.select("row", "doc_id", *keep, "ws", F.posexplode("ws").alias("pos", "w")).withColumn("key", F.lower("w"))
    first = F.greatest(F.col("pos") - reach, F.lit(0))
    around = F.transform(F.filter(F.slice("ws", first + 1, F.col("pos") - first + reach + 1), lambda w: w != ""), ascii_lower)
    columns = ["row", "doc_id", *keep, F.col("key").alias("term"), "pos", F.when(F.col("key") != "", around).alias("around")]
    all_ = stored(reduce(DataFrame.unionByName, [each.join(part, "key").select(*columns) for part in scans]), "postings")
    lengths = all_.filter("term = ''").select("row", "doc_id", *keep, F.col("pos").cast("long").alias("n_words"))
    return Index(all_.filter("term <> ''").select("term", "row", "pos", "around"), lengths, reach)


def _lists(index: Index, pairs: DataFrame) -> tuple[DataFrame, DataFrame]:
    """The posting lists of each window's rarest and second rarest term."""
    thin = index.postings.select("term", "row", "pos")
    one = thin.join(sized(pairs.select("phrase", "len", "off", "off2", F.col("key").alias("term"))), "term")
    two = thin.join(sized(pairs.select("phrase", F.col("off2"), F.col("key2").alias("term"))), "term")
    return one, two


def _with_words(index: Index, places: DataFrame) -> DataFrame:
    """places (row, pos, term, ...) with the stored words around them."""
    few = index.postings.join(sized(places.select("row", "pos").distinct()), ["row", "pos"], "left_semi")
    return places.join(few.select("row", "pos", "around"), ["row", "pos"])


def exact_matches(index: Index, found: DataFrame, pairs: DataFrame) -> DataFrame:
    """row, phrase, start, len, items: every place where a window stands word for word."""
    one, two = _lists(index, pairs)
    one = one.select("phrase", "len", "row", "pos", "off", (F.col("pos") - F.col("off")).alias("start")).filter("start >= 0")
    two = two.select("phrase", "row", (F.col("pos") - F.col("off2")).alias("start"))
    both = stored(one.join(two, ["phrase", "row", "start"], "left_semi"), "intersections")
    at = F.least("pos", F.lit(index.reach)) - F.col("off")  # where the window begins among the stored words
    full = _with_words(index, both).withColumn("said", F.slice("around", at + 1, F.col("len")))
    return full.join(sized(found), "phrase").filter(F.col("said") == F.col("terms")).select("row", "phrase", "start", "len", "items")


def close_matches(index: Index, found: DataFrame, pairs: DataFrame, slop: int = SLOP) -> DataFrame:
    """row, phrase, start, items: stretches of len + slop words, or fewer at the end of a text, that
    hold a window's words in any order, as often as the window does. One row for each place of the
    rarest term; start is that of the first such stretch."""
    one, two = _lists(index, pairs)
    extent = index.reach  # places further apart than this are in no stretch
    one = one.select("phrase", "len", "row", "pos", "off", "off2", F.floor(F.col("pos") / extent).alias("cell"))
    near = F.explode(F.sequence(F.floor(F.col("pos") / extent) - 1, F.floor(F.col("pos") / extent) + 1))
    two = two.select("phrase", "row", F.col("pos").alias("pos2"), near.alias("cell"))
    apart = F.abs(F.col("pos") - F.col("pos2"))
    fits = (apart < F.col("len") + slop) & ((F.col("off") == F.col("off2")) | (apart > 0))
    both = stored(one.join(two, ["phrase", "row", "cell"]).filter(fits).select("phrase", "len", "row", "pos").distinct(), "close-places")
    full = _with_words(index, both).join(sized(found), "phrase")
    at = F.least("pos", F.lit(index.reach))
    often = lambda ws, t: F.size(F.filter(ws, lambda w: w == t))
    held = lambda s: F.forall("terms", lambda t: often(F.slice("around", s + 1, F.col("len") + slop), t) >= often(F.col("terms"), t))
    starts = F.filter(F.sequence(F.greatest(at - F.col("len") - slop + 1, F.lit(0)), at), held)
    full = full.withColumn("starts", starts).filter(F.size("starts") > 0)
    return full.select("row", "phrase", (F.col("pos") - at + F.col("starts")[0]).alias("start"), "terms", "items")


def proximity_matches(docs: DataFrame, items: DataFrame, *, width: int = WIDTH, slop: int = SLOP) -> DataFrame:
    """doc_id, start, phrase text, items of all close_matches of the windows of items in docs."""
    found, pairs = prepared(docs, items, width)
    index = build_index(docs, _keys(pairs), width - 1 + slop)
    close = close_matches(index, found, pairs, slop).join(index.lengths.select("row", "doc_id"), "row")
    return close.select("doc_id", "start", F.concat_ws(" ", "terms").alias("phrase"), "items").distinct()


def _keys(pairs: DataFrame) -> DataFrame:
    return pairs.select(F.explode(F.array("key", "key2")).alias("key")).distinct()


def prepared(docs: DataFrame, items: DataFrame, width: int) -> tuple[DataFrame, DataFrame]:
    found = stored(windows(items, width), "windows")
    terms = stored(found.select(F.explode("terms").alias("w")).select(F.lower("w").alias("key")).distinct(), "terms")
    return found, stored(rarest_pairs(found, term_counts(docs, terms)), "rare-pairs")


def clean(docs: DataFrame, items: DataFrame, **options) -> DataFrame:
    """The rows of docs that are not contaminated, with all their columns; rows that agree in
    doc_id and text are judged alike."""
    judged = decontaminate(docs.withColumn("_mark", F.xxhash64("text")), items, marks=("_mark",), **options)
    bad = sized(stored(judged.filter("contaminated").select(F.col("doc_id").alias("bad_id"), F.col("_mark").alias("bad_mark")).distinct(), "contaminated"))
    same = F.col("doc_id").cast("long").eqNullSafe(F.col("bad_id")) & (F.xxhash64("text") == F.col("bad_mark"))
    return docs.join(bad, same, "left_anti")


def decontaminate(docs: DataFrame, items: DataFrame, *, width: int = WIDTH, marks: tuple[str, ...] = ()) -> DataFrame:
    """One row for each row of docs: doc_id, n_words, n_hit, n_items, items_sha256, contaminated,
    and the columns of docs named in `marks`.

    Null text has no words; a document without words has no hit; rows with the same doc_id are
    judged each on its own; a test item with null text or without words makes no window, one with
    a null id goes by the name "null"; empty tables give no rows (docs) or no hits (items); other
    columns are ignored.
    """
    found, pairs = prepared(docs, items, width)
    index = build_index(docs, _keys(pairs), width - 1, marks)
    hits = exact_matches(index, found, pairs)
    reach = F.max(F.col("start") + F.col("len")).over(Window.partitionBy("row").orderBy("start", F.desc("len")).rowsBetween(Window.unboundedPreceding, -1))
    new = F.greatest(F.lit(0), F.col("start") + F.col("len") - F.greatest("start", F.coalesce(reach, F.lit(0))))
    covered = hits.select("row", "start", "len").withColumn("new", new).groupBy("row").agg(F.sum("new").alias("hit"))
    named = hits.select("row", "items").distinct().select("row", F.explode("items").alias("item")).distinct()
    named = named.groupBy("row").agg(F.sort_array(F.collect_list("item")).alias("ids"))
    ids = F.coalesce("ids", F.array().cast("array<string>"))
    n_hit = F.coalesce("hit", F.lit(0)).cast("long")
    return index.lengths.join(covered, "row", "left").join(named, "row", "left").select(
        "doc_id",
        "n_words",
        n_hit.alias("n_hit"),
        F.size(ids).cast("long").alias("n_items"),
        F.sha2(F.concat_ws(",", ids), 256).alias("items_sha256"),
        ((n_hit > 0) & (20 * n_hit >= F.col("n_words"))).alias("contaminated"),
        *marks,
    )


def decontamination_proximity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, n_close, n_items: places and items of the benchmark that documents hold closely."""
    close = proximity_matches(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    each = close.select("doc_id", "start", F.explode("items").alias("item"))
    return each.groupBy("doc_id").agg(F.countDistinct("start").alias("n_close"), F.countDistinct("item").alias("n_items"))


def op2_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


SQL = r"""
with words as (
  select doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') ws
  from documents),
items as (
  select item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+') ws
  from benchmark),
wins as (
  select distinct item_id, least(len(ws), 13) n, array_to_string(ws[s : s + least(len(ws), 13) - 1], ' ') phrase
  from items, unnest(range(1, len(ws) - least(len(ws), 13) + 2)) r(s) where len(ws) > 0),
lengths as (select distinct n from wins),
spots as (
  select doc_id, s, n, array_to_string(ws[s : s + n - 1], ' ') phrase
  from words, lengths, unnest(range(1, len(ws) - n + 2)) r(s) where len(ws) >= n),
hits as (select doc_id, s, spots.n, item_id from spots join wins using (phrase)),
covered as (select doc_id, count(distinct p) n_hit from hits, unnest(range(s, s + n)) r(p) group by doc_id),
named as (select doc_id, count(distinct item_id) n_items, string_agg(distinct cast(item_id as varchar), ',' order by cast(item_id as varchar)) ids from hits group by doc_id)
select doc_id, cast(len(ws) as bigint) n_words, cast(coalesce(n_hit, 0) as bigint) n_hit, cast(coalesce(n_items, 0) as bigint) n_items,
  sha256(coalesce(ids, '')) items_sha256, coalesce(n_hit, 0) > 0 and 20 * coalesce(n_hit, 0) >= len(ws) contaminated
from words left join covered using (doc_id) left join named using (doc_id)
"""
