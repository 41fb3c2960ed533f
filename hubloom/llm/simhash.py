"""SimHash near-duplicates by bit-sliced comparison.

A text's word shingles vote on the bits of a fingerprint.  Equal fingerprints
form one class at once, so exact copies cost nothing further.  Classes meet in
band tables: bands of bit positions on which two fingerprints agree.  With
``radius + 2`` blocks and bands of two blocks each the search is exact (at most
``radius`` blocks can differ, so two agree); wide fingerprints use sampled bands
with a stated recall.

The members of a band bucket are stored vertically: plane ``b`` holds bit ``b``
of 64 fingerprints in a word.  A query is compared with 64 others per word: the
differing bits of each plane are added into carry-save counters (one word per
binary digit of the count, and a sticky overflow), and words all of whose lanes
exceed the radius are abandoned.  Buckets return the stars of their components
only, never all pairs; a bucket of over ``CELL`` classes is cut into cells, and
every pair of cells is compared in its own group, so no task holds a whole hot
bucket.

Null texts are empty; a text without words has fingerprint zero and links like
any other.  Repeated rows are equal fingerprints.  Rows with a null id take part
through their text but never name a component.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf

from hubloom.llm.common import connected_components, saved

SEED = 42
CELL = 2048
_ALL = np.uint64(0xFFFFFFFFFFFFFFFF)


def _mixed(h: np.ndarray, lane: int) -> np.ndarray:
    """An independent-looking hash for each further 64 bits of a wide fingerprint."""
    if lane == 0:
        return h
    with np.errstate(over="ignore"):
        x = h + np.uint64(lane) * np.uint64(0x9E3779B97F4A7C15)
        x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def fingerprint(text: str, shingle: int, lanes: int = 1) -> bytes:
    """Big-endian fingerprint of ``64 * lanes`` bits: a bit is set when over half the shingles set it."""
    words = text.encode().lower().split()  # of bytes: A-Z only, and exactly space and 09-0D
    if not words:
        return bytes(8 * lanes)
    joined = b" ".join(words)
    ends = np.cumsum(np.fromiter(map(len, words), dtype=np.int64, count=len(words)) + 1) - 1
    k = min(shingle, len(words))
    starts = [0, *(ends[: len(words) - k] + 1).tolist()]
    votes, n = np.zeros(64 * lanes, dtype=np.int64), len(starts)
    digest = xxhash.xxh64_intdigest
    stops = ends[k - 1 :].tolist()
    for lo in range(0, n, 16384):
        h = np.array([digest(joined[a:b], SEED) for a, b in zip(starts[lo : lo + 16384], stops[lo : lo + 16384], strict=True)], dtype=np.uint64)
        for lane in range(lanes):
            bits = np.unpackbits(_mixed(h, lane).astype(">u8").view(np.uint8).reshape(-1, 8), axis=1)
            votes[64 * lane : 64 * lane + 64] += bits.sum(axis=0, dtype=np.int64)
    return np.packbits(2 * votes > n).tobytes()


def fingerprint_column(text: Column, shingle: int, lanes: int = 1) -> Column:
    @pandas_udf("binary")
    def prints(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        for s in batches:
            yield pd.Series([fingerprint(t or "", shingle, lanes) for t in s], dtype=object)

    return prints(text)


def exact_bands(bits: int, radius: int) -> list[list[int]]:
    """Bands that any two fingerprints within ``radius`` share at least one of."""
    blocks = np.array_split(np.arange(bits), radius + 2)
    return [np.concatenate([a, b]).tolist() for a, b in combinations(blocks, 2)]


def sampled_bands(bits: int, width: int, tables: int, seed: int = 7) -> list[list[int]]:
    rng = np.random.default_rng(seed)
    return [sorted(rng.choice(bits, width, replace=False).tolist()) for _ in range(tables)]


# -- comparison ---------------------------------------------------------------
def within_radius(bits: np.ndarray, query: np.ndarray, word: np.ndarray, planes: np.ndarray, radius: int) -> np.ndarray:
    """Lanes within ``radius`` for each (query, word) pair, as a 64-bit mask.

    ``bits`` (n, B) of 0/1 are the queries; ``planes`` (B, words) the vertical store.
    """
    digits = int(radius).bit_length() + 1
    out = np.zeros(len(query), dtype=np.uint64)
    live = np.arange(len(query))
    q, w = query, word
    count = [np.zeros(len(query), dtype=np.uint64) for _ in range(digits)]
    over = np.zeros(len(query), dtype=np.uint64)
    flip = np.where(bits.T.astype(bool), _ALL, np.uint64(0))  # (B, n)
    limit = [bool(radius >> d & 1) for d in range(digits)]

    def exceeding() -> np.ndarray:
        above, equal = over.copy(), np.full(len(over), _ALL)
        for d in reversed(range(digits)):
            if limit[d]:
                equal &= count[d]
            else:
                above |= equal & count[d]
                equal &= ~count[d]
        return above

    total = planes.shape[0]
    for b in range(0, total, 3):
        x = [planes[c, w] ^ flip[c, q] for c in range(b, min(b + 3, total))]
        if len(x) == 3:  # a full adder: three planes become one digit and one carry
            ab = x[0] ^ x[1]
            carries = [(0, ab ^ x[2]), (1, (x[0] & x[1]) | (ab & x[2]))]
        else:
            carries = [(0, y) for y in x]
        for d, carry in carries:
            while d < digits:
                count[d], carry = count[d] ^ carry, count[d] & carry
                d += 1
                if not carry.any():
                    break
            else:
                over |= carry
        if b % 24 == 21:
            keep = exceeding() != _ALL
            if not keep.all():
                live, q, w, over = live[keep], q[keep], w[keep], over[keep]
                count = [c[keep] for c in count]
                if not len(live):
                    return out
    out[live] = ~exceeding()
    return out


def _lowest_lane(mask: np.ndarray) -> np.ndarray:
    return np.bitwise_count((mask & (~mask + np.uint64(1))) - np.uint64(1)).astype(np.int64)


def component_stars(prints: np.ndarray, run_of: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray]:
    """Star edges (member, centre) of the components inside each run of rows.

    ``prints`` (n, bytes) uint8, ``run_of`` (n,) non-decreasing run numbers.
    """
    n = len(prints)
    first = np.flatnonzero(np.r_[True, run_of[1:] != run_of[:-1]])
    size = np.diff(np.r_[first, n])
    words = -(-size // 64)
    word0 = np.cumsum(words) - words
    run = np.repeat(np.arange(len(first)), size)
    lane = np.arange(n) - first[run]
    bits = np.unpackbits(prints, axis=1)
    planes = np.zeros((bits.shape[1], int(words.sum())), dtype=np.uint64)
    at_word, at_bit = word0[run] + lane // 64, np.uint64(1) << (lane % 64).astype(np.uint64)
    used = np.zeros(planes.shape[1], dtype=np.uint64)
    np.bitwise_or.at(used, at_word, at_bit)
    for b in range(bits.shape[1]):
        on = bits[:, b] == 1
        np.bitwise_or.at(planes[b], at_word[on], at_bit[on])
    edges_a: list[np.ndarray] = []
    edges_b: list[np.ndarray] = []

    small = np.flatnonzero(words[run] == 1)  # runs of up to 64: closure of all of them together
    if len(small):
        reach = within_radius(bits[small], np.arange(len(small)), at_word[small], planes, radius) & used[at_word[small]]
        index = np.full(n, -1)
        index[small] = np.arange(len(small))
        start, top = first[run[small]], size[run[small]]
        for k in range(int(top.max())):  # Warshall over lanes
            has = np.flatnonzero((top > k) & ((reach >> np.uint64(k)) & np.uint64(1) == 1))
            reach[has] |= reach[index[start[has] + k]]
        centre = start + _lowest_lane(reach)
        tied = centre != small
        edges_a.append(small[tied]), edges_b.append(centre[tied])

    for r in np.flatnonzero(words > 1):
        rows = np.arange(first[r], first[r] + size[r])
        nw = int(words[r])
        links = within_radius(bits[rows], np.repeat(np.arange(len(rows)), nw), np.tile(np.arange(nw) + word0[r], len(rows)), planes, radius).reshape(-1, nw)
        left = used[word0[r] : word0[r] + nw].copy()
        links &= left
        for i in range(len(rows)):
            if not left[i // 64] >> np.uint64(i % 64) & np.uint64(1):
                continue
            reached = np.zeros(nw, dtype=np.uint64)
            front = np.array([i])
            while len(front):
                grown = np.bitwise_or.reduce(links[front], axis=0) & ~reached
                reached |= grown
                front = np.flatnonzero(np.unpackbits(grown.astype("<u8").view(np.uint8), bitorder="little"))
            left &= ~reached
            members = np.flatnonzero(np.unpackbits(reached.astype("<u8").view(np.uint8), bitorder="little"))
            members = members[members != i]
            edges_a.append(rows[members]), edges_b.append(np.full(len(members), rows[i]))
    empty = np.zeros(0, dtype=np.int64)
    return np.concatenate([empty, *edges_a]), np.concatenate([empty, *edges_b])


def near_links(classes: DataFrame, bands: list[list[int]], radius: int) -> DataFrame:
    """Links ``(a, b)`` that span the near-duplicate components of ``classes(rep long, fp binary)``."""

    def place(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        weights = [np.int64(1) << np.arange(len(b), dtype=np.int64) for b in bands]
        for pdf in batches:
            if not len(pdf):
                continue
            bits = np.unpackbits(np.frombuffer(b"".join(pdf["fp"]), dtype=np.uint8).reshape(len(pdf), -1), axis=1)
            for t, (band, weight) in enumerate(zip(bands, weights, strict=True)):
                key = bits[:, band].astype(np.int64) @ weight
                yield pd.DataFrame({"key": (np.int64(t) << 48) | key, "rep": pdf["rep"], "fp": pdf["fp"]})

    placed = classes.select("rep", "fp").mapInPandas(place, "key long, rep long, fp binary")
    # Buckets of over CELL classes, and into how many cells each is cut.
    hot = saved(placed.groupBy("key").agg(F.count("*").alias("n")).where(F.col("n") > CELL), "hot").select(
        "key", F.ceil(F.col("n") / (CELL // 2)).cast("int").alias("cells")
    )
    cut = placed.join(hot, "key", "left").withColumn("cell", F.expr("if(cells is null, 0, pmod(xxhash64(fp, 11), cells))"))
    paired = cut.withColumn("other", F.explode(F.expr("if(cells is null, array(0), sequence(0, cells - 1))"))).select(
        "key", F.least("cell", "other").cast("int").alias("lo"), F.greatest("cell", "other").cast("int").alias("hi"), "rep", "fp"
    )

    def compare(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held: pd.DataFrame | None = None

        def stars(pdf: pd.DataFrame) -> pd.DataFrame:
            mark = pdf[["key", "lo", "hi"]].to_numpy()
            run = np.cumsum(np.r_[True, (mark[1:] != mark[:-1]).any(axis=1)]) - 1
            keep = np.bincount(run)[run] > 1
            run, rep, fps = run[keep], pdf["rep"].to_numpy()[keep], pdf["fp"].to_numpy()[keep]
            if not len(run):
                return pd.DataFrame({"a": [], "b": []}, dtype="int64")
            a, b = component_stars(np.frombuffer(b"".join(fps), dtype=np.uint8).reshape(len(fps), -1), run, radius)
            return pd.DataFrame({"a": rep[a], "b": rep[b]})

        for pdf in batches:
            if held is not None:
                pdf = pd.concat([held, pdf], ignore_index=True)
            if not len(pdf):
                continue
            last = pdf[["key", "lo", "hi"]].iloc[-1]
            tail = ((pdf["key"] == last["key"]) & (pdf["lo"] == last["lo"]) & (pdf["hi"] == last["hi"])).to_numpy()
            held, done = pdf[tail], pdf[~tail]  # a run may go on in the next batch
            if len(done):
                yield stars(done)
        if held is not None and len(held):
            yield stars(held)

    return (
        paired.repartition("key", "lo", "hi")
        .sortWithinPartitions("key", "lo", "hi")
        .mapInPandas(compare, "a long, b long")
    )


def simhash_components(docs: DataFrame, shingle: int = 4, lanes: int = 1, radius: int = 4, bands: list[list[int]] | None = None) -> DataFrame:
    """``(doc_id, fp binary, component_id)`` for ``docs(doc_id, text)``; components by links within ``radius`` bits."""
    if bands is None:
        bands = exact_bands(64 * lanes, radius)
    marked = saved(docs.select("doc_id", fingerprint_column(F.col("text"), shingle, lanes).alias("fp")), "prints")
    classes = marked.groupBy("fp").agg(F.min("doc_id").alias("rep"))
    links = near_links(classes.where("rep is not null"), bands, radius)
    roots = connected_components(links)
    named = classes.join(roots, F.col("rep") == F.col("node"), "left").select("fp", F.coalesce("root", "rep").alias("component_id"))
    return marked.join(named, "fp").select("doc_id", "fp", "component_id")
