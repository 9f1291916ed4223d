"""Best-fit packing by exact-complement hashing.

Documents become token sequences with an end token; longer ones than the capacity are cut into whole pieces with
a shorter first piece. How many pieces of each length exist is a table of ``capacity`` numbers, whatever the
corpus. Sums of one, two and three of its lengths are indexed by sum and looked up to fill the gap beside each length
exactly, and combinations are consumed as often as their lengths are available; what is left goes into the
fullest bin that takes it (best fit, longest first). The outcome is a short list of recipes with counts.
Pieces get gapless numbers within their length, and a number names the recipe, the sequence and the offset.

Defined results: a null or empty text is the end token alone; repeated rows are packed as often as they occur;
an empty table gives no rows.
"""

from __future__ import annotations

import base64
import re
import zlib
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from bspframe.llm import text as K
from bspframe.llm.numbering import number_in_groups
from bspframe.session import materialise, ship

CAPACITY, END = 1024, 2
_loaded: dict = {}
#: Unicode white space, as both encoders' patterns know it.
_BLANKS = re.compile("[\t-\r \x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000]+")
#: Runs of more white space are kept from the rank encoder, whose regex engine gives up at about a million.
LONG_RUN = 100_000


def _tokenizer(path: str):
    """The file's tokenizer. A byte-level BPE file is run by its equal rank table, which is quicker."""
    if path not in _loaded:
        _loaded[path] = _rank_encoder(path) or _plain_encoder(path)
    return _loaded[path]


def _plain_encoder(path: str):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(path)
    return lambda text: np.array(t.encode(text, add_special_tokens=False).ids, "<u4")


def _rank_encoder(path: str):
    """Encoder by ranks where the file is byte-level BPE without normaliser and with ids in merge order."""
    import json

    with open(path, encoding="utf-8") as f:
        spec = json.load(f)
    model, pre = spec["model"], spec.get("pre_tokenizer") or {}
    if model.get("type") != "BPE" or pre.get("type") != "ByteLevel" or pre.get("add_prefix_space") or not pre.get("use_regex", True) or spec.get("normalizer") or model.get("dropout") or model.get("ignore_merges"):
        return None
    import public_tokenizers
    import tiktoken

    shown = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b <= 255]
    letters = {chr(b): b for b in shown} | {chr(256 + i): b for i, b in enumerate(b for b in range(256) if b not in shown)}
    added = spec.get("added_tokens") or []
    if any(a.get(k) for a in added for k in ("single_word", "lstrip", "rstrip", "normalized")):
        return None
    special = {a["content"]: a["id"] for a in added}
    ranks = {bytes(letters[c] for c in t): i for t, i in model["vocab"].items() if t not in special}
    order = [m if isinstance(m, list) else m.split(" ") for m in model["merges"]]
    made = [model["vocab"]["".join(m)] for m in order]
    if made != sorted(made):
        return None
    enc = tiktoken.Encoding("by-rank", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens=special)
    encode = lambda text: enc.encode_to_numpy(text, allowed_special="all")
    plain: list = []

    def checked(text: str) -> np.ndarray:
        try:
            return encode(text)
        except ValueError:  # the engine's stack is full
            plain.extend([] if plain else [_plain_encoder(path)])
            whole = re.split("(" + "|".join(map(re.escape, special)) + ")", text) if special else [text]  # no match goes across an added token
            return np.concatenate([(plain[0] if run else encode)(part) for segment in whole for part, run in _around_runs(segment)])

    return checked


def _around_runs(text: str):
    """Parts of a text and whether each is a long run of white space, cut where matches of the pattern end.

    A run is one match, less its last character where more text follows.
    """
    at = 0
    for m in _BLANKS.finditer(text):
        if m.end() - m.start() > LONG_RUN:
            end = m.end() - (m.end() < len(text))
            yield text[at : m.start()], False
            yield text[m.start() : end], True
            at = end
    yield text[at:], False


def _pieces(batches, path: str, capacity: int, end: int):
    encode = _tokenizer(path)
    tail = np.array([end], "<u4")
    for batch in batches:
        for part in K.slices(batch, "text", 2 << 20):
            ids, numbers, starts, lengths, sums = [], [], [], [], []
            for doc, text in zip(part.column(0).to_pylist(), part.column(1).to_pylist()):
                tokens = np.concatenate([encode(text or ""), tail]).astype("<u4")
                n, at, number = len(tokens), 0, 0
                while at < n:
                    size = (n - 1) % capacity + 1 if at == 0 else capacity
                    ids.append(doc)
                    numbers.append(number)
                    starts.append(at)
                    lengths.append(size)
                    sums.append(zlib.crc32(tokens[at : at + size].tobytes()))
                    at, number = at + size, number + 1
            yield pa.RecordBatch.from_arrays([pa.array(ids, part.column(0).type), pa.array(numbers, pa.int32()), pa.array(starts, pa.int64()), pa.array(lengths, pa.int64()), pa.array(sums, pa.int64())], ["doc_id", "piece", "start", "length", "ids_crc32"])


def pieces(docs: DataFrame, path: str, capacity: int = CAPACITY, end: int = END) -> DataFrame:
    """``docs(doc_id, text)`` → doc_id, piece, start, length, ids_crc32."""
    ship(docs.sparkSession)
    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", F.col("text").cast("string").alias("text")).mapInArrow(partial(_pieces, path=path, capacity=capacity, end=end), f"doc_id {kind}, piece int, start long, length long, ids_crc32 long")


def plan(counts: dict[int, int], capacity: int = CAPACITY) -> list[tuple[tuple[int, ...], int]]:
    """Recipes (lengths of one sequence) and how many sequences follow each; uses every piece once."""
    left = np.zeros(capacity + 1, np.int64)
    for size, n in counts.items():
        left[size] += n
    out: list[tuple[tuple[int, ...], int]] = []

    def use(recipe: tuple[int, ...]) -> int:
        """Consume a combination as often as it is available."""
        need: dict[int, int] = {}
        for x in recipe:
            need[x] = need.get(x, 0) + 1
        times = min(int(left[x]) // k for x, k in need.items())
        if times:
            for x, k in need.items():
                left[x] -= k * times
            out.append((recipe, times))
        return times

    if left[capacity]:
        use((capacity,))
    index = SumIndex(left, capacity)
    for parts in (1, 2, 3):
        for size in range(capacity - 1, 0, -1):
            if not left[size]:
                continue
            for rest in index.fills(capacity - size, parts, size):
                use((size, *rest))
                if not left[size]:
                    break
    return out + _best_fit(left, capacity)


class SumIndex:
    """Sums of one, two and three available lengths, by sum: ``pairs[s]`` and ``triples[s]`` list the longest members.

    The index is made once, as lengths only ever run out; ``fills`` checks what is left when it looks a sum up.
    """

    def __init__(self, left: np.ndarray, capacity: int):
        self.left = left
        here = left > 0
        here[0] = False
        lengths = np.flatnonzero(here)
        self.pairs: list[np.ndarray] = []
        least = np.full(capacity + 1, capacity + 1)  # the least longest member of a pair with that sum
        for s in range(capacity + 1):
            a = lengths[(lengths < s) & (2 * lengths >= s)]
            a = a[here[s - a]][::-1]
            self.pairs.append(a)
            if len(a):
                least[s] = a[-1]
        self.triples = []
        for s in range(capacity + 1):
            x = lengths[lengths < s]
            self.triples.append(x[least[s - x] <= x][::-1])

    def fills(self, gap: int, parts: int, most: int):
        """Combinations of ``parts`` lengths that are left, longest first and none over ``most``, that sum to ``gap``."""
        left = self.left
        if parts == 1:
            if 0 < gap <= most and left[gap]:
                yield (gap,)
        elif parts == 2:
            for x in self.pairs[gap].tolist():
                if x <= most and left[x] and left[gap - x]:
                    yield (x, gap - x)
        else:
            for x in self.triples[gap].tolist():
                if x <= most and left[x]:
                    for pair in self.fills(gap - x, 2, x):
                        if left[x]:
                            yield (x, *pair)


def _best_fit(left: np.ndarray, capacity: int) -> list[tuple[tuple[int, ...], int]]:
    """Best fit, longest first, over bins grouped by content."""
    by_gap: list[dict[tuple[int, ...], int]] = [{} for _ in range(capacity + 1)]
    for size in range(capacity, 0, -1):
        todo = int(left[size])
        gap = size
        while todo and gap <= capacity:
            if not by_gap[gap]:
                gap += 1
                continue
            recipe, n = by_gap[gap].popitem()
            took = min(n, todo)
            if n > took:
                by_gap[gap][recipe] = n - took
            fuller = by_gap[gap - size]
            key = (*recipe, size)
            fuller[key] = fuller.get(key, 0) + took
            todo -= took
            gap = max(size, gap - size) if gap - size >= size else gap
        if todo:
            fit = capacity // size  # new bins take as many of this length as fit
            whole, rest = divmod(todo, fit)
            for k, n in ((fit, whole), (rest, 1 if rest else 0)):
                if n:
                    key = (size,) * k
                    bins = by_gap[capacity - size * k]
                    bins[key] = bins.get(key, 0) + n
    return [(recipe, n) for bins in by_gap for recipe, n in bins.items()]


def slots(recipes: list[tuple[tuple[int, ...], int]]) -> list[tuple[int, int, int, int, int]]:
    """(length, first number, last number + 1, sequence of the first, offset) of every place in a recipe."""
    used: dict[int, int] = {}
    out, sequence = [], 0
    for recipe, times in recipes:
        offset = 0
        for size in recipe:
            a = used.get(size, 0)
            out.append((size, a, a + times, sequence, offset))
            used[size] = a + times
            offset += size
        sequence += times
    return out


def pack(docs: DataFrame, path: str, capacity: int = CAPACITY, end: int = END) -> DataFrame:
    """``docs(doc_id, text)`` → doc_id, piece, start, length, ids_crc32, sequence_id, offset."""
    spark = docs.sparkSession
    cut = materialise(pieces(docs, path, capacity, end), "pieces")
    counts = {r[0]: r[1] for r in cut.groupBy("length").count().collect()}  # capacity rows at most
    rows = slots(plan(counts, capacity))
    table = spark.createDataFrame(rows or [(0, 0, 0, 0, 0)], "size long, low long, high long, first long, offset long")
    numbered = number_in_groups(cut, "length", ["doc_id", "piece", "ids_crc32"], "number", sum(counts.values()))
    place = F.broadcast(table)  # places of recipes: bounded by the lengths, not by the pieces
    placed = numbered.join(place, (F.col("length") == F.col("size")) & (F.col("number") >= F.col("low")) & (F.col("number") < F.col("high")))
    return placed.select("doc_id", "piece", "start", "length", "ids_crc32", (F.col("first") + F.col("number") - F.col("low")).alias("sequence_id"), "offset")
