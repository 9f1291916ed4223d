"""Exact nearest neighbours, block by block."""

from __future__ import annotations

from collections.abc import Iterator
from decimal import ROUND_HALF_UP, Decimal
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window, functions as F

from bspframe.session import materialise, ship

#: Vectors of one block, and queries compared with a block at once.
BLOCK, QUERIES = 8_192, 256
#: Numbers in a block at most, whatever the width of the vectors.
CELLS = 1 << 20
#: Similarity of a pair that has none (a null or zero vector, unequal lengths): after all others.
NONE = np.iinfo(np.int64).min
_SCHEMA = "ids binary, vectors binary, width int"


def knn_edges(df: DataFrame, k: int) -> DataFrame:
    """``df(id, embedding)`` → (src, dst, rank): the k most similar others by cosine in DOUBLE, ties by id.

    Blocks of queries meet blocks of vectors; each meeting keeps k for a query, and the kept ones are merged.
    Work is quadratic in the vectors, memory is bounded by the blocks. Rows without id are left out.
    """
    spark = df.sparkSession
    ship(spark)
    v = materialise(df.where("id is not null").select(F.col("id").cast("long").alias("id"), F.transform("embedding", lambda x: x.cast("double")).alias("v")), "vectors")
    n = v.count()
    cores = spark.sparkContext.defaultParallelism
    packed = lambda size, parts: v.repartition(parts, "id").mapInArrow(partial(_pack, size=size), _SCHEMA)
    asked = packed(QUERIES, max(1, min(-(-n // QUERIES), 4 * cores), -(-n // (4 * QUERIES)))).toDF("qi", "qv", "qw")
    pairs = asked.hint("shuffle_replicate_nl").crossJoin(packed(BLOCK, max(1, -(-n // BLOCK))))
    kept = pairs.mapInArrow(partial(_nearest, k=k), "src long, dst long, s long")
    best = Window.partitionBy("src").orderBy(F.desc("s"), "dst")
    return kept.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k).select("src", "dst", "rank")


def _pack(batches: Iterator[pa.RecordBatch], size: int) -> Iterator[pa.RecordBatch]:
    """Rows (id, v) → blocks of at most ``size`` vectors of one width; a null or incomplete vector has width -1."""
    held: dict[int, tuple[list, list]] = {}

    def block(width: int) -> pa.RecordBatch:
        ids, vectors = held.pop(width)
        return pa.RecordBatch.from_arrays([pa.array([np.array(ids, "<i8").tobytes()], pa.binary()), pa.array([b"".join(vectors)], pa.binary()), pa.array([width], pa.int32())], ["ids", "vectors", "width"])

    for batch in batches:
        for i, x in zip(batch.column(0).to_pylist(), batch.column(1)):
            values = x.values if x.is_valid else None
            width = -1 if values is None or values.null_count else len(values)
            ids, vectors = held.setdefault(width, ([], []))
            ids.append(i)
            vectors.append(b"" if width < 0 else values.to_numpy(zero_copy_only=False).astype("<f8").tobytes())
            if len(ids) >= min(size, CELLS // max(width, 1)):
                yield block(width)
    for width in list(held):
        yield block(width)


def _dot(a: np.ndarray, b: np.ndarray, i=slice(None), j=slice(None)) -> np.ndarray:
    """Products of rows ``i`` of a and ``j`` of b, summed in the order of the components as SQL does."""
    s = 0.0
    for c in range(a.shape[1]):
        s = s + a[i, c] * b[j, c]
    return s


def _digits(s: np.ndarray) -> np.ndarray:
    """``s`` to 9 digits, half away from zero on the decimal form, as whole numbers; NaN before all others."""
    with np.errstate(all="ignore"):
        y = s * 1e9
        out = np.where(np.isfinite(s), np.floor(y + 0.5), 0).astype(np.int64)
        near = np.flatnonzero(np.isfinite(s) & (np.abs(y - np.floor(y) - 0.5) < 1e-5))
    if len(near):
        values, where = np.unique(s[near], return_inverse=True)
        exact = [int(Decimal(repr(float(x))).scaleb(9).to_integral_value(ROUND_HALF_UP)) for x in values]
        out[near] = np.array(exact, np.int64)[where]
    out[~np.isfinite(s)] = np.iinfo(np.int64).max
    return out


def _best(src: np.ndarray, va: np.ndarray, na: np.ndarray, dst: np.ndarray, vb: np.ndarray, nb: np.ndarray, k: int):
    """The k most similar for each query: a quick product finds who can be among them, exact sums decide."""
    with np.errstate(all="ignore"):
        about = va @ vb.T / na[:, None] / nb
        own = src[:, None] == dst
        about[own] = -np.inf
        least = np.partition(about, about.shape[1] - min(k, about.shape[1]), axis=1)[:, -min(k, about.shape[1])]
        i, j = np.nonzero(((about >= least[:, None] - 1e-8) | ~np.isfinite(about)) & ~own)
        s = _digits(_dot(va, vb, i, j) / na[i] / nb[j])
    order = np.lexsort((dst[j], -s, i))
    i, j, s = i[order], j[order], s[order]
    first = np.arange(len(i)) - np.searchsorted(i, i) < k
    return src[i[first]], dst[j[first]], s[first]


def _nearest(batches: Iterator[pa.RecordBatch], k: int) -> Iterator[pa.RecordBatch]:
    """Pairs of blocks → (src, dst, s): at most k of the vectors' block for each query."""
    for batch in batches:
        for r in batch.to_pylist():
            src, dst, width = np.frombuffer(r["qi"], "<i8"), np.frombuffer(r["ids"], "<i8"), r["qw"]
            a, b, s = [src[:0]], [src[:0]], [src[:0]]
            blank, dark = np.ones(len(src), bool), np.ones(len(dst), bool)
            if width == r["width"] and width > 0:
                va, vb = np.frombuffer(r["qv"], "<f8").reshape(len(src), width), np.frombuffer(r["vectors"], "<f8").reshape(len(dst), width)
                na, nb = np.sqrt(_dot(va, va)), np.sqrt(_dot(vb, vb))
                blank, dark = na == 0, nb == 0
                if not (blank.all() or dark.all()):
                    a, b, s = ([x] for x in _best(src[~blank], va[~blank], na[~blank], dst[~dark], vb[~dark], nb[~dark], k))
            every, empty = np.sort(dst), np.sort(dst[dark])
            for i, none in zip(src, blank) if len(empty) or blank.any() else ():
                rest = every if none else empty
                rest = rest[rest != i][:k]
                a.append(np.full(len(rest), i))
                b.append(rest)
                s.append(np.full(len(rest), NONE))
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(x), pa.int64()) for x in (a, b, s)], ["src", "dst", "s"])
