"""Toxicity: a counterfactual-regularised classifier.

Features of a text are the presence of its words and of word beginnings. A logistic model is fitted to labelled
texts; for each that mentions an identity term a counterfactual copy has the term swapped for another one, and
the squared change of its log-odds is penalised, so that a neutral mention of a group does not move the score.
The model is a bounded table of feature weights that every task gets; scoring is one pass over whole texts.

Defined results: null and empty texts have the score of the bias alone; labels that are null are ignored; without
any usable label every score is 0; with labels of one class every score is near that class; repeated rows are scored
alike, and one labelled doc_id with several texts teaches with each of them; an empty table gives no rows.
"""

from __future__ import annotations

import math
import re
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from bspframe.llm import text as K
from bspframe.session import ship

#: Labelled rows that the model is fitted on, at most, and features that it keeps, at most.
TRAIN_ROWS, MAX_FEATURES = 12_000, 20_000
#: Lengths of word beginnings that are features.
STEMS = (3, 4, 5, 6, 7, 8)
#: Weight of the penalty on score changes under swaps, and of the ridge.
SWAP_PENALTY, RIDGE = 1.0, 1e-3
#: Share of a text's features that a step of the fit does not see.
BLANKED = 0.3
# Identity terms by kind; a swap stays within a kind.
IDENTITIES = (
    ("women", "men", "girls", "boys"),
    ("woman", "man", "girl", "boy"),
    ("muslim", "christian", "jewish", "hindu", "buddhist", "atheist"),
    ("muslims", "christians", "jews", "hindus", "buddhists", "atheists"),
    ("black", "white", "asian", "latino", "arab", "african", "european"),
    ("gay", "lesbian", "straight", "bisexual", "transgender"),
    ("immigrants", "refugees", "foreigners", "natives"),
    ("frauen", "männer"), ("muslime", "christen", "juden"),
    ("femmes", "hommes"), ("musulmans", "chrétiens", "juifs"),
    ("mujeres", "hombres"), ("musulmanes", "cristianos", "judíos"),
)
_SWAPS = {w: group[(i + 1) % len(group)] for group in IDENTITIES for i, w in enumerate(group)}
_words = re.compile(r"[^\W\d_]+").findall


def features_of(word: str) -> list[str]:
    return [word, *[f"{word[:k]}*" for k in STEMS if len(word) >= k]]


def swapped(words: set[str]) -> set[str] | None:
    """The words with identity terms swapped, or None if there are none."""
    hit = words & _SWAPS.keys()
    return (words - hit) | {_SWAPS[w] for w in hit} if hit else None


class Sample:
    """Labelled texts as arrays of word numbers; the words themselves are kept once."""

    def __init__(self):
        self.words: dict[str, int] = {}
        self.docs: list[np.ndarray] = []
        self.copies: list[tuple[int, np.ndarray]] = []
        self.labels: list[int] = []

    def _numbers(self, words: set[str]) -> np.ndarray:
        known = self.words
        return np.array([known.setdefault(w, len(known)) for w in words], np.int32)

    def add(self, words: set[str], label: int) -> None:
        self.docs.append(self._numbers(words))
        self.labels.append(label)
        other = swapped(words)
        if other is not None:
            self.copies.append((len(self.docs) - 1, self._numbers(other)))

    def features(self) -> tuple[list[str], np.ndarray]:
        """Names of the kept features, and (features of a word, word) → kept feature or -1."""
        y = np.array(self.labels)
        n1 = int(y.sum())
        n0 = len(y) - n1
        vocabulary = list(self.words)
        names: list[str] = []
        columns = []
        for cut in (None, *STEMS):
            seen: dict[str, int] = {}
            of = np.array([seen.setdefault(w[:cut], len(seen)) if cut is None or len(w) >= cut else -1 for w in vocabulary], np.int64)
            counts = np.zeros((2, len(seen) + 1))
            for d, label in zip(self.docs, self.labels):
                counts[label, np.unique(of[d])] += 1  # -1 falls on the spare last cell
            counts = counts[:, :-1]
            total = counts.sum(0)
            # evidence that a feature's label rate is not the common one, against the number of features tried
            rate, base = counts[1] / np.maximum(total, 1), n1 / (n1 + n0)
            with np.errstate(divide="ignore", invalid="ignore"):
                pull = total * (np.where(rate > 0, rate * np.log(rate / base), 0) + np.where(rate < 1, (1 - rate) * np.log((1 - rate) / (1 - base)), 0))
            kept = np.flatnonzero((pull > math.log(len(seen) + 1)) & (total >= 3))
            kept = kept[np.argsort(-pull[kept], kind="stable")[: MAX_FEATURES // (1 + len(STEMS))]]
            slot = np.full(len(seen) + 1, -1)
            slot[kept] = len(names) + np.arange(len(kept))
            plain = list(seen)
            names += [plain[i] if cut is None else f"{plain[i]}*" for i in kept.tolist()]
            columns.append(slot[of])
        return names, np.stack(columns) if vocabulary else np.zeros((1 + len(STEMS), 0), np.int64)


def fit(sample: Sample, penalty: float = SWAP_PENALTY, rounds: int = 1200, blanked: float = BLANKED) -> dict[str, float]:
    """Weights by feature (the bias under ``""``).

    Each step leaves out another random share of every text's features, so that one telling word has to do where the
    labelled texts hold several; the draws are seeded. The penalty sees all features. The weights are the mean of the last
    third of the steps, which evens out the draws.
    """
    y = np.array(sample.labels, np.float64)
    n1, n0 = y.sum(), len(y) - y.sum()
    if not len(y):
        return {"": -40.0}
    if min(n0, n1) == 0:
        return {"": 10.0 if n1 else -10.0}
    names, of = sample.features()
    k = len(names)

    def matrix(docs: list[np.ndarray]):
        cols = []
        for d in docs:
            f = np.unique(of[:, d])
            cols.append(f[f >= 0])
        return np.concatenate([*cols, np.zeros(0, np.int64)]).astype(np.int64), np.repeat(np.arange(len(cols)), [len(c) for c in cols])

    col, row = matrix(sample.docs)
    pairs = len(sample.copies)
    ca, ra = matrix([sample.docs[i] for i, _ in sample.copies])
    cb, rb = matrix([c for _, c in sample.copies])
    w, bias = np.zeros(k), math.log(n1 / n0)
    m, v = np.zeros(k + 1), np.zeros(k + 1)
    draw, total, last = np.random.default_rng(11), np.zeros(k + 1), rounds - rounds // 3
    for step in range(1, rounds + 1):
        seen = draw.random(len(col), dtype=np.float32) >= blanked
        c, r = col[seen], row[seen]
        z = bias + np.bincount(r, w[c], len(y))
        p = 1 / (1 + np.exp(-np.clip(z, -40, 40)))
        error = (p - y) / len(y)
        grad = np.append(np.bincount(c, error[r], k) + RIDGE / 10 * w, error.sum())
        if pairs:
            change = (np.bincount(ra, w[ca], pairs) - np.bincount(rb, w[cb], pairs)) * (2 * penalty / pairs)
            grad[:k] += np.bincount(ca, change[ra], k) - np.bincount(cb, change[rb], k)
        m = 0.9 * m + 0.1 * grad
        v = 0.999 * v + 0.001 * grad * grad
        move = 0.05 * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.999**step)) + 1e-10)
        w -= move[:k]
        bias -= move[k]
        if step > last:
            total += np.append(w, bias)
    w, bias = total[:k] / (rounds - last), total[k] / (rounds - last)
    return {"": float(bias)} | dict(zip(names, w.tolist()))


def _fit_rows(batches, penalty: float):
    sample = Sample()
    for batch in batches:
        for part in K.slices(batch, "text"):
            for t, label in zip(part.column(0), part.column(1).to_pylist()):
                sample.add(set(_words((t.as_py() or "").lower())), int(label > 0))
    model = fit(sample, penalty)
    yield pa.RecordBatch.from_arrays([pa.array(list(model)), pa.array(list(model.values()))], ["feature", "weight"])


def train(docs: DataFrame, labels: DataFrame, rows: int = TRAIN_ROWS, penalty: float = SWAP_PENALTY) -> dict[str, float]:
    """Model from ``docs(doc_id, text)`` and ``labels(doc_id, toxic)``, on at most ``rows`` labelled documents.

    Which documents is settled by a hash of doc_id. The fit runs in one task over that bounded sample.
    """
    ship(docs.sparkSession)
    marked = labels.where("doc_id is not null and toxic is not null").groupBy("doc_id").agg(F.max(F.col("toxic").cast("int")).alias("toxic"))
    marked = marked.join(docs.select("doc_id").distinct(), "doc_id", "left_semi")
    sample = marked.withColumn("_o", F.xxhash64("doc_id")).orderBy("_o", "doc_id").limit(rows).select("doc_id", "toxic")
    joined = docs.select("doc_id", F.col("text").cast("string").alias("text")).join(F.broadcast(sample), "doc_id").select("text", "toxic")
    model = joined.repartition(1).mapInArrow(partial(_fit_rows, penalty=penalty), "feature string, weight double").collect()
    return {r[0]: r[1] for r in model} or {"": -40.0}


class Scorer:
    """Scores texts by a model; a word's weighted features are looked up once."""

    def __init__(self, model: dict[str, float]):
        self.bias, self.model, self.known = model.get("", 0.0), {k: v for k, v in model.items() if k}, {}

    def score(self, text: str) -> float:
        known, hits = self.known, {}
        for w in set(_words(text.lower())):
            f = known.get(w, 0)
            if f == 0:
                f = known[w] = {x: self.model[x] for x in features_of(w) if x in self.model} or None
            if f:
                hits.update(f)
        if len(known) > 150_000:
            known.clear()
        z = self.bias + math.fsum(hits.values())
        return 1 / (1 + math.exp(-min(max(z, -40.0), 40.0)))


def _score(batches, model, keep: list[str], text: str):
    scorer = Scorer(model.value)
    for batch in batches:
        for part in K.slices(batch, text):
            column = part.column(part.schema.get_field_index(text))
            scores = pa.array([scorer.score(t.as_py() or "") for t in column], pa.float64())
            yield pa.RecordBatch.from_arrays([*(part.column(i) for i in range(len(keep))), scores], [*keep, "score"])


def score(docs: DataFrame, model: dict[str, float], keep: list[str] | None = None, text: str = "text") -> DataFrame:
    """``docs`` → the columns ``keep`` (doc_id) and score of its string column ``text``."""
    spark = docs.sparkSession
    ship(spark)
    keep = keep or ["doc_id"]
    held = spark.sparkContext.broadcast(model)  # MAX_FEATURES entries at most
    source = docs.withColumn(text, F.col(text).cast("string")).select(*keep, *([] if text in keep else [text]))
    schema = ", ".join(f"`{n}` {t}" for n, t in source.dtypes[: len(keep)]) + ", score double"
    return source.mapInArrow(partial(_score, model=held, keep=keep, text=text), schema)


def held_out(doc_id):
    """Rows whose labels are never learned from."""
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 5 == 0, F.lit(False))


def judge(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """doc_id, held_out, score, predicted of every document, learned from labels outside the held-out fold."""
    model = train(docs, labels.where(~held_out(F.col("doc_id"))))
    scored = score(docs, model)
    return scored.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
