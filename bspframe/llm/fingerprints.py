"""Document fingerprints: bottom-k sketches of word-shingle hashes.

A sketch is the sorted array of the k least distinct 64-bit hashes of a document's shingles. Two sketches
merge into the sketch of the union of their shingles, so parts of a document or whole corpora can be
sketched apart. From sketches come estimates of resemblance (Jaccard), containment and the number of
distinct shingles. Everything is a native column expression.

Defined results: texts are compared by words (runs outside ``[\\x20\\x09-\\x0D]``), A-Z lower-cased; fewer
words than the width make one shingle; null, empty and blank texts have the empty sketch, which resembles
only itself (1.0 with another empty one, 0.0 with any other).
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window, functions as F

from bspframe.llm.line_dedup import ascii_lower

#: Hashes kept and words in a shingle.
K, WIDTH = 128, 5
#: Hash values run over 2**64, offset by 2**63.
SPAN = float(2**64)
#: Documents in a range bucket, about, and buckets at most.
BUCKET_DOCS, MAX_BUCKETS = 2000, 4096


def word_hashes(text: Column) -> Column:
    """Hashes of a text's words, in order."""
    parts = F.split(ascii_lower(F.btrim(F.coalesce(text, F.lit("")), F.lit(" \t\n\x0b\f\r"))), "[ \\t\\n\\x0B\\f\\r]+", -1)
    return F.transform(F.filter(parts, lambda w: w != ""), lambda w: F.xxhash64(w))


def sketch_of_words(words: str, k: int = K, width: int = WIDTH) -> Column:
    """Sketch from the column ``words`` of word hashes."""
    n = F.size(words)
    many = F.transform(F.sequence(F.lit(0), F.greatest(n - width, F.lit(0))), lambda i: F.xxhash64(*[F.get(words, i + j) for j in range(width)]))
    few = F.array(F.xxhash64(F.col(words)))
    return F.slice(F.sort_array(F.array_distinct(F.when(n >= width, many).when(n > 0, few).otherwise(F.array().cast("array<bigint>")))), 1, k)


def add_sketch(df: DataFrame, text: str, out: str, k: int = K, width: int = WIDTH) -> DataFrame:
    """``df`` with the sketch of column ``text`` as column ``out``."""
    return df.withColumn("_words", word_hashes(F.col(text))).withColumn(out, sketch_of_words("_words", k, width)).drop("_words")


def merged(a: str, b: str, k: int = K) -> Column:
    """Sketch of the union of what two sketches stand for."""
    return F.slice(F.sort_array(F.array_union(a, b)), 1, k)


def merge_sketches(df: DataFrame, keys: list[str], sketch: str, k: int = K) -> DataFrame:
    """One sketch for each value of ``keys``: the k least of all hashes, by a bounded ranking."""
    flat = df.select(*keys, F.explode(sketch).alias("_h")).distinct()
    rank = Window.partitionBy(*keys).orderBy("_h")
    return flat.withColumn("_r", F.row_number().over(rank)).where(f"_r <= {int(k)}").groupBy(*keys).agg(F.sort_array(F.collect_list("_h")).alias(sketch))


def resemblance(a: str, b: str, k: int = K) -> Column:
    """Estimate of the Jaccard similarity, from the share of the merged sketch that both hold."""
    u = merged(a, b, k)
    both = F.size(F.array_intersect(F.array_intersect(u, F.col(a)), F.col(b)))
    return F.when((F.size(a) == 0) & (F.size(b) == 0), F.lit(1.0)).otherwise(both / F.size(u))


def distinct_count(a: str, k: int = K) -> Column:
    """Estimate of the number of distinct shingles; exact while the sketch is not full."""
    share = (F.element_at(a, -1).cast("double") + 2.0**63) / SPAN
    return F.when(F.size(a) < k, F.size(a).cast("double")).otherwise((k - 1) / share)


def containment(a: str, b: str, k: int = K) -> Column:
    """Estimate of the share of a's shingles that b holds as well."""
    j = resemblance(a, b, k)
    common = j / (1 + j) * (distinct_count(a, k) + distinct_count(b, k))
    return F.when(F.size(a) == 0, F.lit(1.0)).otherwise(F.least(F.lit(1.0), common / distinct_count(a, k)))


def as_text(a: str) -> Column:
    """A sketch as a string: 16 hexadecimal digits for each hash."""
    return F.array_join(F.transform(a, lambda h: F.lpad(F.lower(F.hex(h)), 16, "0")), "")


def with_next(df: DataFrame, id_col: str, carried: list[str]) -> DataFrame:
    """Each row with ``next_<c>`` of the row that follows in descending ``id_col``; after the last comes the first.

    A global ``lead`` without a single task: rows are dealt to ranges of the id by approximate quantiles, and
    the first row of each range is dealt to the range above as well (that of the highest to the lowest). Nulls
    come last, ties follow the first carried column. Ranges only steer the work; they do not change results.
    """
    spark = df.sparkSession
    base = df.withColumn("_k", F.coalesce(F.col(id_col).cast("long"), F.lit(-(1 << 63))))
    n = base.count()
    parts = max(1, min(MAX_BUCKETS, n // BUCKET_DOCS))
    bounds: list[int] = []
    if parts > 1:
        shares = [i / parts for i in range(1, parts)]
        bounds = sorted(set(base.select(F.percentile_approx("_k", shares, 100 * parts)).first()[0]))
    base = base.withColumn("_b", _bucket(F.col("_k"), bounds))
    heads = sorted(tuple(r) for r in base.groupBy("_b").agg(F.max("_k")).collect())  # one row for each range
    above = [(head, up) for (_, head), (up, _) in zip(heads, heads[1:] + heads[:1])]
    second = F.broadcast(spark.createDataFrame(above or [(0, 0)], "_k long, _up int"))
    place = lambda to, x: F.struct(F.col(to).alias("to"), F.lit(x).alias("x"))
    places = F.when(F.col("_up").isNull(), F.array(place("_b", 0))).otherwise(F.array(place("_b", 0), place("_up", 1)))
    dealt = base.join(second, "_k", "left").withColumn("_d", F.explode(places)).withColumn("_to", F.col("_d.to")).withColumn("_x", F.col("_d.x"))
    order = Window.partitionBy("_to").orderBy("_x", F.desc("_k"), carried[0])
    for c in carried:
        dealt = dealt.withColumn(f"next_{c}", F.lead(c).over(order))
    return dealt.where("_x = 0").drop("_k", "_b", "_up", "_d", "_to", "_x")


def _bucket(value: Column, bounds: list[int]) -> Column:
    """How many of the sorted bounds are below ``value``, by binary search."""
    if not bounds:
        return F.lit(0)
    table = F.from_json(F.lit("[" + ",".join(map(str, bounds)) + "]"), "array<bigint>")  # folded to a literal
    steps, step = [], 1
    while step <= len(bounds):
        steps.insert(0, F.lit(step))
        step *= 2
    return F.aggregate(F.array(*steps), F.lit(0), lambda at, s: F.when(F.coalesce(F.get(table, at + s - 1) < value, F.lit(False)), at + s).otherwise(at))


def compare_with_edits(docs: DataFrame, k: int = K, width: int = WIDTH) -> DataFrame:
    """Sketches of each text and of its edited form, and likeness to the edit and to the next document.

    The edited text has its last floor(n/3) code points replaced by the first as many (or all) of the
    next document, in descending doc_id. Adds n_chars, edited, sketch, edited_sketch, near_edited, near_next.
    """
    base = docs.select("doc_id", F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    base = add_sketch(base, "text", "sketch", k, width)
    both = with_next(base, "doc_id", ["text", "sketch"])
    n = F.char_length("text")
    third = F.floor(n / 3).cast("int")
    both = both.withColumn("n_chars", n.cast("long")).withColumn("edited", F.concat(F.substring(F.col("text"), F.lit(1), n - third), F.substring(F.col("next_text"), F.lit(1), third)))
    both = add_sketch(both.drop("next_text"), "edited", "edited_sketch", k, width)
    return both.withColumn("near_edited", resemblance("sketch", "edited_sketch", k)).withColumn("near_next", resemblance("sketch", "next_sketch", k)).withColumn("distinct_shingles", distinct_count("sketch", k)).drop("next_sketch")
