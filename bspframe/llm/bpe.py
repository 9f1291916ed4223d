"""Byte-level BPE encoding and decoding with segment trees.

Each match of the splitting pattern is encoded apart. Over the byte positions of a match lies a segment tree
whose leaves hold the rank of the pair that starts there (position breaks ties); the root is the leftmost
pair of least rank. A merge updates the leaves of the merged pair and of its live neighbours, each along one
path to the root, so it costs the logarithm of the length. Trees of many distinct matches of like length are
run side by side in arrays; the matches of a partition are encoded once and kept in a bounded table.

Defined results: a null text is empty; the empty text has no ids and decodes to nothing; special tokens are
ordinary text; any text decodes to its own UTF-8 bytes; repeated rows give as many rows; an empty table gives none;
columns beyond doc_id and text are not read. A match of any length is encoded whole.
"""

from __future__ import annotations

import base64
import hashlib
from array import array
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from bspframe.llm import text as K
from bspframe.session import ship

NONE = np.int64(1) << 40
#: Matches kept encoded, and array cells of a run of trees, at most.
KEPT, CELLS = 300_000, 1 << 21
#: Matches beyond so many bytes have a tree of their own in flat arrays.
ALONE = 1 << 9
_loaded: dict[tuple[str, str], "Encoder"] = {}


class Encoder:
    """Ranks of a vocabulary file with ``base64(token) rank`` lines, and a splitting pattern."""

    def __init__(self, path: str, pattern: str):
        import regex

        with open(path, "rb") as f:
            self.ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
        self.split = regex.compile(pattern).findall
        self.tokens = {str(r): t for t, r in self.ranks.items()}
        self.single = np.array([self.ranks[bytes([b])] for b in range(256)], np.int64)
        pairs = {}
        for token, rank in self.ranks.items():
            for i in range(1, len(token)):
                left, right = self.ranks.get(token[:i]), self.ranks.get(token[i:])
                if left is not None and right is not None:
                    pairs[left << 20 | right] = rank
        order = sorted(pairs)
        self.pair_keys = np.array(order, np.int64)
        self.pair_ranks = np.array([pairs[k] for k in order], np.int64)
        self.pairs = pairs
        self.known: dict[str, str] = {}

    @classmethod
    def load(cls, path: str, pattern: str) -> "Encoder":
        if (path, pattern) not in _loaded:
            _loaded[path, pattern] = cls(path, pattern)
        return _loaded[path, pattern]

    def _ranks(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        key = left << 20 | right
        at = np.searchsorted(self.pair_keys, key)
        at[at == len(self.pair_keys)] = 0
        return np.where(self.pair_keys[at] == key, self.pair_ranks[at], NONE)

    def encode_matches(self, matches: list[bytes]) -> list[list[int]]:
        """Ids of each match."""
        out: list[list[int]] = [[]] * len(matches)
        by_size: dict[int, list[int]] = {}
        for i, m in enumerate(matches):
            if m in self.ranks:  # the whole match is one token
                out[i] = [self.ranks[m]]
            elif m:
                by_size.setdefault(max(1, (len(m) - 1).bit_length()), []).append(i)
        for bits, members in by_size.items():
            if 1 << bits > ALONE:
                for i in members:
                    out[i] = self._merge_one(matches[i], 1 << bits)
                continue
            step = max(1, CELLS >> bits)
            for a in range(0, len(members), step):
                part = members[a : a + step]
                for i, ids in zip(part, self._merge([matches[i] for i in part], 1 << bits)):
                    out[i] = ids
        return out

    def _merge_one(self, match: bytes, width: int) -> list[int]:
        """Run the tree of one long match: some 50 bytes for each byte of it, and a merge without array calls."""
        n = len(match)
        first = self.single[np.frombuffer(match, np.uint8)]
        leaf = np.full(width, NONE)
        leaf[: n - 1] = self._ranks(first[:-1], first[1:])
        levels = [leaf * width + np.arange(width)]
        while len(levels[-1]) > 1:
            levels.append(np.minimum(levels[-1][::2], levels[-1][1::2]))
        tree = array("q", np.concatenate([np.zeros(1, np.int64), *levels[::-1]]).tobytes())
        token, nxt, prev = array("q", first.tobytes()), array("q", range(1, n + 1)), array("q", range(-1, n - 1))
        none, bound, pairs = int(NONE), int(NONE) * width, self.pairs

        def put(at: int, rank: int) -> None:
            node = at + width
            tree[node] = rank * width + at
            node >>= 1
            while node:
                a, b = tree[2 * node], tree[2 * node + 1]
                least = a if a < b else b
                if tree[node] == least:
                    return
                tree[node] = least
                node >>= 1

        while tree[1] < bound:
            rank, at = divmod(tree[1], width)
            gone = nxt[at]
            token[at], token[gone] = rank, -1
            after = nxt[at] = nxt[gone]
            fresh = none
            if after < n:
                prev[after] = at
                fresh = pairs.get(rank << 20 | token[after], none)
            put(gone, none)
            put(at, fresh)
            before = prev[at]
            if before >= 0:
                put(before, pairs.get(token[before] << 20 | rank, none))
        return [t for t in token if t >= 0]

    def _merge(self, matches: list[bytes], width: int) -> list[list[int]]:
        """Run the segment trees of matches of at most ``width`` bytes side by side."""
        n = len(matches)
        size = np.array([len(m) for m in matches], np.int64)
        flat = np.zeros(n * width, np.uint8)
        where = np.arange(int(size.sum())) + np.repeat(np.arange(n) * width - np.cumsum(size) + size, size)
        flat[where] = np.frombuffer(b"".join(matches), np.uint8)
        token = self.single[flat].reshape(n, width)
        column = np.arange(width)
        nxt = np.broadcast_to(column + 1, (n, width)).copy()
        prev = np.broadcast_to(column - 1, (n, width)).copy()
        live = column < size[:, None]
        leaf = np.full((n, width), NONE)
        both = column[:-1] + 1 < size[:, None]
        leaf[:, :-1] = np.where(both, self._ranks(token[:, :-1], token[:, 1:]), NONE)
        # a node holds rank * width + position: the least is the leftmost pair of least rank
        tree = np.empty((n, 2 * width), np.int64)
        tree[:, width:] = leaf * width + column
        level = width
        while level > 1:
            tree[:, level // 2 : level] = np.minimum(tree[:, level : 2 * level : 2], tree[:, level + 1 : 2 * level : 2])
            level //= 2
        bound = NONE * width
        rows = np.flatnonzero(tree[:, 1] < bound)
        while len(rows):
            at = tree[rows, 1] % width
            gone = nxt[rows, at]
            token[rows, at] = tree[rows, 1] // width
            live[rows, gone] = False
            after = nxt[rows, gone]
            nxt[rows, at] = after
            inner = after < size[rows]
            prev[rows[inner], after[inner]] = at[inner]
            fresh = np.full(len(rows), NONE)
            if inner.any():
                fresh[inner] = self._ranks(token[rows[inner], at[inner]], token[rows[inner], after[inner]])
            self._update(tree, rows, at, fresh, width)
            self._update(tree, rows, gone, np.full(len(rows), NONE), width)
            before = prev[rows, at]
            has = before >= 0
            if has.any():
                r, b, a = rows[has], before[has], at[has]
                self._update(tree, r, b, self._ranks(token[r, b], token[r, a]), width)
            rows = rows[tree[rows, 1] < bound]
        return [t[m].tolist() for t, m in zip(token, live)]

    @staticmethod
    def _update(tree: np.ndarray, rows: np.ndarray, at: np.ndarray, rank: np.ndarray, width: int) -> None:
        node = at + width
        tree[rows, node] = rank * width + at
        node >>= 1
        while node[0]:
            tree[rows, node] = np.minimum(tree[rows, 2 * node], tree[rows, 2 * node + 1])
            node >>= 1

    def learn(self, matches: set[str]) -> None:
        """Keep the encoding of matches not seen before; the table is emptied when full."""
        new = [m for m in matches if m not in self.known]
        if len(self.known) + len(new) > KEPT:
            self.known.clear()
            new = list(matches)
        for m, ids in zip(new, self.encode_matches([m.encode() for m in new])):
            self.known[m] = ",".join(map(str, ids))

    def encode_texts(self, texts: list[str]) -> list[str]:
        """Decimal ids joined by commas, for each text."""
        split = [self.split(t) for t in texts]
        self.learn(set().union(*split))
        known = self.known
        return [",".join([known[m] for m in ms]) for ms in split]

    def decode(self, ids: str) -> bytes:
        tokens = self.tokens
        return b"".join([tokens[i] for i in ids.split(",")]) if ids else b""


def _texts(batches):
    for batch in batches:
        for part in K.slices(batch, "text", 2 << 20):
            yield part, [t or "" for t in part.column(1).to_pylist()]


def _encode(batches, path: str, pattern: str):
    enc = Encoder.load(path, pattern)
    for part, texts in _texts(batches):
        ids = [[int(x) for x in e.split(",")] if e else [] for e in enc.encode_texts(texts)]
        yield pa.RecordBatch.from_arrays([part.column(0), pa.array(ids, pa.list_(pa.int32()))], ["doc_id", "ids"])


def _decode(batches, path: str, pattern: str):
    enc = Encoder.load(path, pattern)
    for batch in batches:
        out = [enc.decode(",".join(map(str, ids or []))) for ids in batch.column(1).to_pylist()]
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out, pa.binary())], ["doc_id", "bytes"])


def _digest(batches, path: str, pattern: str):
    enc = Encoder.load(path, pattern)
    for part, texts in _texts(batches):
        ids = enc.encode_texts(texts)
        cols = [
            part.column(0),
            pa.array([e.count(",") + 1 if e else 0 for e in ids], pa.int64()),
            pa.array([hashlib.sha256(e.encode()).hexdigest() for e in ids]),
            pa.array([hashlib.sha256(enc.decode(e)).hexdigest() for e in ids]),
        ]
        yield pa.RecordBatch.from_arrays(cols, ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])


def _run(df: DataFrame, kernel, path: str, pattern: str, schema: str) -> DataFrame:
    ship(df.sparkSession)
    kind = df.schema["doc_id"].dataType.simpleString()
    return df.mapInArrow(partial(kernel, path=path, pattern=pattern), f"doc_id {kind}, {schema}")


def encode(docs: DataFrame, path: str, pattern: str) -> DataFrame:
    """``docs(doc_id, text)`` → doc_id, ids array<int>."""
    return _run(docs.select("doc_id", F.col("text").cast("string").alias("text")), _encode, path, pattern, "ids array<int>")


def decode(encoded: DataFrame, path: str, pattern: str) -> DataFrame:
    """``encoded(doc_id, ids)`` → doc_id, bytes binary."""
    return _run(encoded.select("doc_id", "ids"), _decode, path, pattern, "bytes binary")


def round_trip_digests(docs: DataFrame, path: str, pattern: str) -> DataFrame:
    """``docs(doc_id, text)`` → doc_id, n_tokens, ids_sha256, decoded_sha256 of the same encoder and decoder."""
    return _run(docs.select("doc_id", F.col("text").cast("string").alias("text")), _digest, path, pattern, "n_tokens long, ids_sha256 string, decoded_sha256 string")
