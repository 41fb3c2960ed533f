"""Byte-level BPE encoding and decoding over a file of token ranks.

A pre-token is a run of byte positions.  Leaf ``i`` of a segment tree holds the
rank of the pair that starts at live position ``i`` (infinite where there is
none); inner nodes hold the least ``(rank, position)`` below them, so the root
is the leftmost pair of minimum rank.  A merge rewrites at most three leaves -
the merged position, its dead right half and its live left neighbour - and
walks each up in logarithmic time.

Short pre-tokens run in lock-step: many trees of one size are rows of a matrix,
and a round performs the next merge of all of them.  Long pre-tokens (a page of
blanks, base64) use one tree each, O(n log n) whatever the length.

Null texts are empty; an empty text has no tokens and decodes to empty bytes.
Rows are independent, so ties and repeated rows need no rule.
"""

from __future__ import annotations

import base64
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pandas as pd
import pyarrow as pa
import regex
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf

INF = np.int64(1) << 62
#: Pre-tokens up to this many bytes run in lock-step.
LOCKSTEP_BYTES = 64
#: Entries of a worker's pre-token cache; it is emptied when full.
CACHE_ENTRIES = 200_000
#: Characters cut into pre-tokens at a time, which bounds a worker's memory.
CHUNK_CHARS = 1 << 19
#: Rows encoded between two batches that a worker hands on.
SLICE_ROWS = 256


class Ranks:
    """Token bytes by id, and the rank of every mergeable pair of ids as a sorted table."""

    def __init__(self, lines: list[bytes]):
        pairs = [line.split() for line in lines if line.strip()]
        self.ids = {base64.b64decode(a): int(b) for a, b in pairs}
        self.vocab: list[bytes] = [b""] * (max(self.ids.values(), default=-1) + 1)
        for token, i in self.ids.items():
            self.vocab[i] = token
        self.byte = np.array([self.ids.get(bytes([b]), -1) for b in range(256)], dtype=np.int64)
        if (self.byte < 0).any():
            raise ValueError("a rank file needs all 256 single bytes")
        left, right, merged = [], [], []
        get = self.ids.get
        for token, i in self.ids.items():
            for cut in range(1, len(token)):
                a = get(token[:cut])
                if a is not None and (b := get(token[cut:])) is not None:
                    left.append(a), right.append(b), merged.append(i)
        key = (np.array(left, dtype=np.int64) << 24) | np.array(right, dtype=np.int64)
        self.pair_dict = dict(zip(key.tolist(), merged, strict=True))
        # The same pairs as an open-addressed table, a tenth full, for whole arrays at once.
        self.bits = max(8, (10 * len(key)).bit_length())
        self.pair_key = np.full(1 << self.bits, -1, dtype=np.int64)
        self.pair_rank = np.full(1 << self.bits, INF)
        todo, at = np.arange(len(key)), self._slot(key)
        while len(todo):
            free = self.pair_key[at] < 0
            self.pair_key[at[free]] = key[todo[free]]  # of rivals for a slot, the last stays
            won = self.pair_key[at] == key[todo]
            self.pair_rank[at[won]] = np.array(merged, dtype=np.int64)[todo[won]]
            todo, at = todo[~won], (at[~won] + 1) & ((1 << self.bits) - 1)

    def _slot(self, key: np.ndarray) -> np.ndarray:
        return ((key.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - self.bits)).astype(np.int64)

    def rank_of(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        """Rank of each pair, INF where it cannot merge (also for dead ids below zero)."""
        shape, a, b = a.shape, a.ravel(), b.ravel()
        out = np.full(len(a), INF)
        todo = np.flatnonzero((a >= 0) & (b >= 0))
        key = (a[todo] << 24) | b[todo]
        at = self._slot(key)
        while len(todo):
            found = self.pair_key[at]
            hit = found == key
            out[todo[hit]] = self.pair_rank[at[hit]]
            more = ~hit & (found >= 0)
            todo, key, at = todo[more], key[more], (at[more] + 1) & ((1 << self.bits) - 1)
        return out.reshape(shape)

    # -- one long pre-token ------------------------------------------------
    def merge_long(self, piece: bytes) -> list[int]:
        n = len(piece)
        size = 1 << max(1, (n - 1).bit_length())
        tok = [int(self.byte[b]) for b in piece]
        nxt, prv = list(range(1, n + 1)), list(range(-1, n - 1))
        top, get = int(INF), self.pair_dict.get
        tree = [top] * (2 * size)

        def leaf(i: int) -> int:
            j = nxt[i]
            r = get((tok[i] << 24) | tok[j]) if j < n else None
            return top if r is None else (r << 32) | i

        for i in range(n - 1):
            tree[size + i] = leaf(i)
        for node in range(size - 1, 0, -1):
            tree[node] = min(tree[2 * node], tree[2 * node + 1])

        def put(i: int, value: int) -> None:
            node = size + i
            tree[node] = value
            node >>= 1
            while node:
                a, b = tree[2 * node], tree[2 * node + 1]
                least = a if a < b else b
                if tree[node] == least:
                    break
                tree[node] = least
                node >>= 1

        while tree[1] != top:
            i, rank = tree[1] & 0xFFFFFFFF, tree[1] >> 32
            j = nxt[i]
            tok[i], tok[j] = rank, -1
            nxt[i] = k = nxt[j]
            if k < n:
                prv[k] = i
            put(j, top)
            put(i, leaf(i))
            if prv[i] >= 0:
                put(prv[i], leaf(prv[i]))
        return [t for t in tok if t >= 0]

    # -- many short pre-tokens, one tree a row -------------------------------
    def merge_rows(self, pieces: list[bytes], size: int) -> list[bytes]:
        rows = len(pieces)
        length = np.fromiter(map(len, pieces), dtype=np.int64, count=rows)
        raw = np.frombuffer(b"".join(p.ljust(size, b"\0") for p in pieces), dtype=np.uint8).reshape(rows, size)
        cols = np.arange(size)
        tok = np.where(cols < length[:, None], self.byte[raw], -1)
        tok = np.concatenate([tok, np.full((rows, 1), -1)], axis=1)  # column `size`: past the end
        nxt = np.minimum(np.broadcast_to(cols + 1, (rows, size)), length[:, None]).copy()
        nxt = np.where(nxt >= length[:, None], size, nxt)
        prv = np.concatenate([np.broadcast_to(cols - 1, (rows, size)), np.zeros((rows, 1), dtype=np.int64)], axis=1).copy()
        tree = np.full((rows, 2 * size), INF)
        first = self.rank_of(tok[:, :-1], tok[:, 1:])
        tree[:, size:] = np.where(first < INF, (first << 32) | cols, INF)
        node = size
        while node > 1:
            node >>= 1
            tree[:, node : 2 * node] = np.minimum(tree[:, 2 * node : 4 * node : 2], tree[:, 2 * node + 1 : 4 * node : 2])

        def put(r: np.ndarray, i: np.ndarray, value: np.ndarray) -> None:
            node = size + i
            tree[r, node] = value
            node = node >> 1
            while node[0]:
                tree[r, node] = np.minimum(tree[r, 2 * node], tree[r, 2 * node + 1])
                node = node >> 1

        live = np.flatnonzero(tree[:, 1] < INF)
        while len(live):
            root = tree[live, 1]
            i, rank = root & 0xFFFFFFFF, root >> 32
            j = nxt[live, i]
            k = nxt[live, j]
            tok[live, i], tok[live, j] = rank, -1
            nxt[live, i] = k
            prv[live, k] = i
            put(live, j, np.full(len(live), INF))
            r = self.rank_of(rank, tok[live, k])
            put(live, i, np.where(r < INF, (r << 32) | i, INF))
            p = prv[live, i]
            has = p >= 0
            if has.any():
                lr, lp = live[has], p[has]
                r = self.rank_of(tok[lr, lp], rank[has])
                put(lr, lp, np.where(r < INF, (r << 32) | lp, INF))
            live = live[tree[live, 1] < INF]
        tok = tok[:, :-1]
        packed = tok[tok >= 0].astype("<u4").tobytes()
        ends = np.cumsum((tok >= 0).sum(axis=1) * 4).tolist()
        return [packed[a:b] for a, b in zip([0, *ends], ends, strict=False)]

    def encode_pieces(self, pieces: list[bytes]) -> list[bytes]:
        """Ids of each pre-token as packed little-endian unsigned 32-bit integers."""
        out: list[bytes] = [b""] * len(pieces)
        by_size: dict[int, list[int]] = {}
        for at, piece in enumerate(pieces):
            whole = self.ids.get(piece)
            if whole is not None:
                out[at] = whole.to_bytes(4, "little")
            elif len(piece) > LOCKSTEP_BYTES:
                out[at] = np.array(self.merge_long(piece), dtype="<u4").tobytes()
            elif piece:
                by_size.setdefault(1 << (len(piece) - 1).bit_length(), []).append(at)
        for size, ats in by_size.items():
            for lo in range(0, len(ats), 4096):
                part = ats[lo : lo + 4096]
                for at, ids in zip(part, self.merge_rows([pieces[a] for a in part], size), strict=True):
                    out[at] = ids
        return out


@lru_cache(maxsize=4)
def load_ranks(path: str) -> Ranks:
    with open(path, "rb") as f:
        return Ranks(f.read().splitlines())


class Encoder:
    """Whole texts to packed ids, with a bounded cache of pre-tokens."""

    def __init__(self, ranks: Ranks, pattern: str):
        self.ranks, self.find, self.cache = ranks, regex.compile(pattern), {}

    def pieces_of(self, text: str) -> Iterator[list[str]]:
        if len(text) <= CHUNK_CHARS:
            yield self.find.findall(text)
            return
        part: list[str] = []
        for m in self.find.finditer(text):
            part.append(m.group())
            if len(part) >= CHUNK_CHARS // 4:
                yield part
                part = []
        yield part

    def encode(self, texts: list[str]) -> list[bytes]:
        out: list[bytes] = []
        at = 0
        while at < len(texts):
            group, chars = [], 0
            while at < len(texts) and (not group or chars + len(texts[at]) <= CHUNK_CHARS):
                group.append(texts[at])
                chars += len(texts[at])
                at += 1
            if len(group) == 1:
                out.append(b"".join(self._pack([p])[0] for p in self.pieces_of(group[0])))
            else:
                out += self._pack([self.find.findall(t) for t in group])
        return out

    def _pack(self, lists: list[list[str]]) -> list[bytes]:
        if len(self.cache) > CACHE_ENTRIES:
            self.cache.clear()
        cache = self.cache
        new = [p for p in set().union(*lists) if p not in cache]
        cache.update(zip(new, self.ranks.encode_pieces([p.encode() for p in new]), strict=True))
        return [b"".join(map(cache.__getitem__, pieces)) for pieces in lists]


@lru_cache(maxsize=4)
def _encoder(path: str, pattern: str) -> Encoder:
    return Encoder(load_ranks(path), pattern)


def encode_column(text: Column, path: str, pattern: str) -> Column:
    """Packed ids (binary, four little-endian bytes a token) of a string column."""

    @pandas_udf("binary")
    def encode(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        encoder = _encoder(path, pattern)
        for s in batches:
            yield pd.Series(encoder.encode(s.fillna("").tolist()), dtype=object)

    return encode(text)


def decode_ids(ranks: Ranks, packed: bytes) -> bytes:
    vocab = ranks.vocab
    return b"".join([vocab[i] for i in np.frombuffer(packed, dtype="<u4").tolist()])


def decode_column(ids: Column, path: str) -> Column:
    """The bytes that packed ids stand for."""

    @pandas_udf("binary")
    def decode(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        ranks = load_ranks(path)
        for s in batches:
            yield pd.Series([decode_ids(ranks, b or b"") for b in s], dtype=object)

    return decode(ids)


def bpe_documents(docs: DataFrame, path: str, pattern: str) -> DataFrame:
    """``(doc_id, n_tokens, ids binary, decoded binary)`` for ``docs(doc_id, text)``.

    One worker encodes and decodes, a few rows at a time, so that a task holds
    one rank table and no more than a slice of its Arrow batch in Python.
    """

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder = _encoder(path, pattern)
        for batch in batches:
            for lo in range(0, batch.num_rows, SLICE_ROWS):
                part = batch.slice(lo, SLICE_ROWS)
                ids = encoder.encode([t or "" for t in part.column("text").to_pylist()])
                columns = {
                    "doc_id": part.column("doc_id"),
                    "n_tokens": pa.array([len(b) // 4 for b in ids], pa.int64()),
                    "ids": pa.array(ids, pa.binary()),
                    "decoded": pa.array([decode_ids(encoder.ranks, b) for b in ids], pa.binary()),
                }
                yield pa.RecordBatch.from_pydict(columns)

    return docs.select("doc_id", "text").mapInArrow(work, "doc_id long, n_tokens long, ids binary, decoded binary")
