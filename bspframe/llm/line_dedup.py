"""Line deduplication by range-partitioned hashes, returning compressed keep bitmaps instead of text.

Every line whose key (stripped of ``[\\x20\\x09-\\x0D]``, A-Z lower-cased) has ``min_chars`` code points or
more becomes a row (key hash, document, position); texts are not shuffled for the decision. Rows are range
partitioned by hash and sorted by (hash, document descending, position), and one streaming pass marks
which lines are first occurrences, that is in the largest doc_id holding the key. Keys of ``min_docs``
documents or more lose all other lines. A heavy-hitter sketch of fixed size names up to ``HOT`` frequent
hashes first; their counts are pre-aggregated and joined by broadcast, so no frequent line meets in a task. A hash that
the sketch does not name holds a share of about 1 / ``HOT`` of the lines at most, which bounds the groups of the pass.
The result for a document is its list of dropped runs (start, length): a run-length compressed bitmap.

Only DataFrame and SQL functions are used.

Defined results: a null or empty text is one empty line; rows that repeat a doc_id count as one document
for the support of a key; rows with a null doc_id lose nothing and support nothing; keys are compared by
two independent 64-bit hashes.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window, functions as F

from bspframe.session import materialise

BLANKS = " \t\n\x0b\f\r"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: Frequent hashes that are handled by pre-aggregation, at most; bounds what is broadcast.
HOT = 1000


def ascii_lower(c: Column) -> Column:
    """Lower-case A-Z only; a pure ASCII value takes the quick way."""
    return F.when(F.octet_length(c) == F.char_length(c), F.lower(c)).otherwise(F.translate(c, UPPER, LOWER))


def line_key(line: Column) -> Column:
    return ascii_lower(F.btrim(line, F.lit(BLANKS)))


def _rows(docs: DataFrame, min_chars: int) -> DataFrame:
    """(h1, h2, doc, print, pos) of every line that is long enough; ``print`` tells texts of one id apart."""
    long_lines = F.filter(
        F.transform(F.split("text", "\n", -1), lambda line, i: F.struct(F.when(F.char_length(line) >= min_chars, line_key(line)).alias("key"), i.alias("pos"))),
        lambda x: F.char_length(x["key"]) >= min_chars,
    )
    hashed = F.transform(long_lines, lambda x: F.struct(F.xxhash64(x["key"]).alias("h1"), F.xxhash64(F.lit(7), x["key"]).alias("h2"), x["pos"].alias("pos")))
    return docs.where("doc_id is not null").select("doc_id", "print", F.inline(hashed))


def keep_bitmaps(docs: DataFrame, min_chars: int = 40, min_docs: int = 5) -> DataFrame:
    """``docs(doc_id, text)`` → (doc_id, print, dropped): runs of dropped lines of each text that loses any.

    ``dropped`` is ``array<struct<start int, len int>>`` with positions from 0; ``print`` is xxhash64(text).
    """
    base = docs.select("doc_id", F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    rows = materialise(_rows(base.withColumn("print", F.xxhash64("text")), min_chars), "line-hashes")
    hot = rows.select(F.explode(F.expr(f"approx_top_k(h1, {HOT}, {HOT * 10})")).alias("x")).select(F.col("x.item").alias("h1"))
    # the join below keeps at most HOT values of h1; a key of them needs its second hash as well
    stats = (
        rows.join(F.broadcast(hot), "h1", "left_semi")
        .groupBy("h1", "h2", "doc_id").agg(F.lit(1).alias("one"))
        .groupBy("h1", "h2").agg(F.count("*").alias("hot_docs"), F.max("doc_id").alias("hot_keeper"))
    )
    stats = materialise(stats, "line-hot")
    seen = rows.join(F.broadcast(stats), ["h1", "h2"], "left")
    hot_drops = seen.where(f"hot_docs >= {min_docs} and doc_id <> hot_keeper").select("doc_id", "print", "pos")

    cold = seen.where("hot_docs is null").select("h1", "h2", "doc_id", "print", "pos")
    ranged = cold.repartitionByRange("h1", "h2").sortWithinPartitions("h1", "h2", F.desc("doc_id"), "pos")
    group = Window.partitionBy("h1", "h2").orderBy(F.desc("doc_id"), "pos").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    order = Window.partitionBy("h1", "h2").orderBy(F.desc("doc_id"))
    marked = ranged.withColumn("rank", F.dense_rank().over(order)).withColumn("docs", F.max("rank").over(group))
    cold_drops = marked.where(f"rank > 1 and docs >= {min_docs}").select("doc_id", "print", "pos")

    positions = hot_drops.union(cold_drops).groupBy("doc_id", "print").agg(F.array_sort(F.collect_set("pos")).alias("p"))
    starts = F.filter("p", lambda x, i: (i == 0) | (F.get("p", i - 1) < x - 1))
    ends = F.filter("p", lambda x, i: F.coalesce(F.get("p", i + 1) > x + 1, F.lit(True)))
    return positions.withColumn("s", starts).withColumn("e", ends).select("doc_id", "print", F.zip_with("s", "e", lambda a, b: F.struct(a.alias("start"), (b - a + 1).alias("len"))).alias("dropped"))


def apply_bitmaps(docs: DataFrame, bitmaps: DataFrame) -> DataFrame:
    """``docs`` with n_lines, n_dropped, dropped and the kept text; all other columns stay as they are."""
    base = docs.withColumn("_text", F.coalesce(F.col("text").cast("string"), F.lit(""))).withColumn("_print", F.xxhash64("_text"))
    marks = bitmaps.select(F.col("doc_id").alias("_id"), F.col("print").alias("_p"), F.col("dropped").alias("_runs"))
    joined = base.join(marks, (base["doc_id"] == marks["_id"]) & (base["_print"] == marks["_p"]), "left")
    lines = F.split("_text", "\n", -1)
    n = F.size("_lines")
    number = F.size("_runs")
    after = lambda i: F.when(i == 0, F.lit(0)).otherwise(F.get("_runs", i - 1)["start"] + F.get("_runs", i - 1)["len"])
    before = lambda i: F.when(i == number, n).otherwise(F.get("_runs", i)["start"])
    parts = F.transform(F.sequence(F.lit(0), number), lambda i: F.slice("_lines", after(i) + 1, before(i) - after(i)))
    kept = F.when(F.col("_runs").isNull(), F.col("_text")).otherwise(F.array_join(F.flatten(parts), "\n"))
    gone = F.when(F.col("_runs").isNull(), F.lit(0)).otherwise(F.aggregate("_runs", F.lit(0), lambda a, r: a + r["len"]))
    return (
        joined.withColumn("_lines", lines)
        .withColumn("n_lines", n.cast("long"))
        .withColumn("n_dropped", gone.cast("long"))
        .withColumn("kept_text", kept)
        .withColumn("dropped", F.coalesce("_runs", F.array().cast("array<struct<start:int,len:int>>")))
        .drop("_text", "_print", "_id", "_p", "_runs", "_lines")
    )


def dedup_lines(docs: DataFrame, min_chars: int = 40, min_docs: int = 5) -> DataFrame:
    """Both steps: ``docs`` plus n_lines, n_dropped, dropped and kept_text."""
    return apply_bitmaps(docs, keep_bitmaps(docs, min_chars, min_docs))


ORACLE = r"""
WITH lines AS (
  SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS line,
         generate_subscripts(string_split(coalesce(text, ''), chr(10)), 1) AS pos
  FROM documents),
keyed AS (
  SELECT *, translate(trim(line, ' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)),
                      'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS key
  FROM lines),
often AS (
  SELECT key, max(doc_id) AS keeper FROM keyed WHERE length(key) >= 40
  GROUP BY key HAVING count(DISTINCT doc_id) >= 5),
marked AS (
  SELECT k.doc_id, k.line, k.pos, coalesce(k.doc_id <> o.keeper, false) AS gone
  FROM keyed k LEFT JOIN often o USING (key))
SELECT doc_id, count(*) AS n_lines, count(*) FILTER (WHERE gone) AS n_dropped,
       sha256(coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (WHERE NOT gone), '')) AS kept_sha256
FROM marked GROUP BY doc_id
"""
