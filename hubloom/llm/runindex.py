"""Long repeats across documents with a run-length index.

A string of ``length`` bytes that stands in two documents contains the same
least-hashed inner k-mer in both.  So each document falls into pieces: maximal
runs of windows with one such anchor.  Equal windows lie in pieces of equal
anchor, and the corpus is searched anchor by anchor, in partitions by hash:

1. anchors seen in one document only are set aside (packed keys per batch and
   partition; one bit comes back);
2. the distinct pieces of the other anchors go to their partition, each with the
   least id of its documents.  An anchor with one distinct piece is settled by
   that id.  Where pieces differ, a run-length index is built over them: the
   Burrows-Wheeler transform of the collection as runs, with the suffix array
   sampled at run ends.  Every piece is streamed through it backwards, which
   yields the rank of each of its windows; classes of ranks that agree on
   ``length`` bytes carry the least document, and so match statistics of
   ``length`` or more against smaller documents;
3. the least document of each window goes back to the batches, which mark, cut
   and digest their texts.

Anchors met in very many batches are searched by single windows dealt by their
own hash, so no key gathers in one task.  All rows are packed numpy arrays in
binary columns.

Null texts are empty; null ids count as the smallest.  Rows that repeat an id
are no smaller document for each other.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hubloom.llm.common import even_homes, first_batch, release_shuffles, saved, saved_in_place, trimmed, with_answers
from hubloom.llm.katz import _deltas, _keys, _pack, _unpack

LENGTH = 50
ANCHOR = 26
BATCH_BYTES = 2 << 20
#: Packed bytes of a count partition.
PARTITION_BYTES = 4 << 20
#: An anchor of more pieces than this in all is searched by single windows.
HOT_PIECES = 20_000
#: Bytes indexed together.
INDEX_BYTES = 256 << 10
#: Bytes whose pieces are found together.
CACHED_BYTES = 96 << 10
NO_DOC = -(2**63)


class RunIndex:
    """Run-length Burrows-Wheeler index of a collection of byte strings (no byte above 0xFE)."""

    def __init__(self, units: list[bytes], length: int):
        self.length, self.n_units = length, len(units)
        self.sizes = np.array([len(u) for u in units], dtype=np.int64)
        ends = np.cumsum(self.sizes + 1) - 1
        text = np.frombuffer(b"\xff".join(units) + b"\xff", dtype=np.uint8) + np.uint8(1)  # terminators become 0
        n = len(text)
        rank = self._ranks(text.astype(np.uint64), int(self.sizes.max(initial=0)))
        order = np.argsort(rank, kind="stable")  # equal suffixes: by unit
        before = np.where(order > 0, text[order - 1], 0)
        first = np.flatnonzero(np.r_[True, before[1:] != before[:-1]])
        self.run_start, self.run_char = first, before[first].astype(np.int64)
        sizes = np.diff(np.r_[first, n])
        # LF of a run's first place: characters below it, and as many of its own as stand in earlier runs.
        totals = np.bincount(self.run_char, weights=sizes, minlength=257).astype(np.int64)
        below = np.cumsum(totals) - totals
        by_char = np.argsort(self.run_char, kind="stable")
        cum = np.cumsum(sizes[by_char]) - sizes[by_char]
        start_of_char = np.searchsorted(self.run_char[by_char], self.run_char[by_char])
        self.run_base = np.empty(len(first), dtype=np.int64)
        self.run_base[by_char] = below[self.run_char[by_char]] + cum - cum[start_of_char]
        self.run_end_sample = order[np.r_[first[1:], n] - 1]
        # Classes of ranks that agree on ``length`` bytes; suffixes shorter than that are alone.
        unit_of = np.repeat(np.arange(len(units)), self.sizes + 1)
        left = ends[unit_of] - np.arange(n)
        self.class_start, least = self._classes(rank, text, order, left, unit_of)
        self.class_least = least

    @staticmethod
    def _ranks(text: np.ndarray, longest: int) -> np.ndarray:
        """Ranks of suffixes up to their terminators, by doubling from 8-byte words."""
        word, span = text, 1
        while span < 8:
            more = np.r_[word[span:], np.zeros(span, np.uint64)]
            word = (word << np.uint64(8 * span)) | np.where(word & np.uint64(0xFF), more, np.uint64(0))
            span *= 2
        open_end = (word & np.uint64(0xFF)) != 0  # no terminator among the bytes so far
        rank = np.unique(word, return_inverse=True)[1].astype(np.uint64) + np.uint64(1)
        while span <= longest:
            more = np.where(open_end, np.r_[rank[span:], np.zeros(span, np.uint64)], np.uint64(0))
            open_end = open_end & np.r_[open_end[span:], np.zeros(span, bool)]
            rank = np.unique((rank << np.uint64(32)) | more, return_inverse=True)[1].astype(np.uint64) + np.uint64(1)
            span *= 2
        return rank

    def _classes(self, rank: np.ndarray, text: np.ndarray, order: np.ndarray, left: np.ndarray, unit_of: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Starts of the classes in rank order, and the least unit of each."""
        long = left[order] >= self.length
        fresh = np.ones(len(order), dtype=bool)
        both = np.flatnonzero(long[1:] & long[:-1])  # neighbours in rank that both have a window
        a, b = order[both], order[both + 1]
        same = rank[a] == rank[b]
        todo = np.flatnonzero(~same)
        for lo in range(0, len(todo), 1 << 16):
            t = todo[lo : lo + (1 << 16)]
            span = np.arange(self.length)
            same[t] = (text[a[t][:, None] + span] == text[b[t][:, None] + span]).all(axis=1)
        fresh[both[same] + 1] = False
        start = np.flatnonzero(fresh)
        return start, np.minimum.reduceat(unit_of[order], start)

    def step_back(self, rank: np.ndarray) -> np.ndarray:
        """LF mapping: the rank of each suffix with the byte before it."""
        run = np.searchsorted(self.run_start, rank, side="right") - 1
        return self.run_base[run] + rank - self.run_start[run]

    def locate(self, rank: int) -> int:
        """Text position of a rank: steps back to the nearest run end, where the sample lies."""
        at, steps = rank, 0
        while True:
            run = int(np.searchsorted(self.run_start, at, side="right")) - 1
            end = (self.run_start[run + 1] if run + 1 < len(self.run_start) else int((self.sizes + 1).sum())) - 1
            if at == end:
                return int(self.run_end_sample[run]) + steps
            if self.run_char[run] == 0:  # a unit's start: its place is that of its number
                unit = int(self.run_base[run] + at - self.run_start[run])
                return self._start_of(unit) + steps
            at, steps = int(self.run_base[run] + at - self.run_start[run]), steps + 1

    def _start_of(self, unit: int) -> int:
        # Terminators sort by unit; the one before a unit is that of its forerunner, the last one before the first.
        unit = (unit + 1) % self.n_units
        return int((self.sizes[:unit] + 1).sum())

    def stream(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """All windows of all units, by matching statistics: (unit, start, least unit that has the window)."""
        unit = np.arange(self.n_units)
        rank, left = unit.copy(), self.sizes.copy()  # terminators have the least ranks, in unit order
        units, starts, least = [], [], []
        taken = 0
        while len(unit):
            live = left > 0
            unit, rank, left = unit[live], self.step_back(rank[live]), left[live] - 1
            taken += 1
            if taken >= self.length and len(unit):
                at = np.searchsorted(self.class_start, rank, side="right") - 1
                units.append(unit), starts.append(left.copy()), least.append(self.class_least[at])
        none = np.zeros(0, dtype=np.int64)
        return np.concatenate([none, *units]), np.concatenate([none, *starts]), np.concatenate([none, *least])


# -- pieces -------------------------------------------------------------------
def pieces(data: np.ndarray, doc: np.ndarray, length: int, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(anchor hash, first window, last window) of each run of windows with one anchor, in one byte array."""
    n, w = len(data), length - k + 1
    none = np.zeros(0, dtype=np.int64)
    if n < length:
        return none.astype(np.uint64), none, none
    with np.errstate(over="ignore"):
        one = (data.astype(np.uint64) + np.uint64(1)) * np.uint64(0x9E3779B97F4A7C15)
        one ^= one >> np.uint64(29)
        by = {1: one}
        for span, factor in ((1, 0xD6E8FEB86659FD93), (2, 0xA0761D6478BD642F), (4, 0xE7037ED1A0B428DB), (8, 0x8EBC6AF09C88C6E3)):
            by[2 * span] = by[span][:-span] * np.uint64(factor) + by[span][span:]
        h, done = by[16], 16
        for span in (8, 4, 2, 1):
            if k - done >= span:
                m = n - done - span + 1
                h = h[:m] * np.uint64(0xBF58476D1CE4E5B9) + by[span][done : done + m]
                h = h ^ (h >> np.uint64(31))
                done += span
        h = h * np.uint64(0x94D049BB133111EB)
        h ^= h >> np.uint64(33)
    low = np.uint64((1 << 32) - 1)  # positions of up to 4 GB below 32 bits of hash, in every batch alike
    key = (h & ~low) | np.arange(len(h), dtype=np.uint64)
    span, least = 1, key
    while 2 * span <= w:
        least = np.minimum(least[:-span], least[span:])
        span *= 2
    if span < w:
        least = np.minimum(least[: len(least) - (w - span)], least[w - span :])
    at = (least & low).astype(np.int64)  # the anchor of each window
    inside = doc[: len(at)] == doc[length - 1 : length - 1 + len(at)]
    fresh = np.r_[True, (at[1:] != at[:-1]) | (inside[1:] != inside[:-1]) | (doc[1 : len(at)] != doc[: len(at) - 1])]
    first = np.flatnonzero(fresh)
    last = np.r_[first[1:], len(at)] - 1
    real = inside[first]
    return h[at[first[real]]], first[real], last[real]


class TextBatch:
    """Whole documents as one byte array, with their pieces."""

    def __init__(self, blob: bytes, length: int, anchor: int, cut_bits: int = 0):
        ids, sizes, data = _unpack(blob)
        self.ids, self.sizes, self.data = ids, sizes, data
        self.doc = np.repeat(np.arange(len(ids), dtype=np.int32), sizes)
        # Some documents at a time, so that the arrays of the search stay in the processor's cache.
        ends = np.cumsum(sizes)
        found, lo = [], 0
        while lo < len(data):
            hi = int(ends[max(np.searchsorted(ends, lo + CACHED_BYTES, side="right") - 1, np.searchsorted(ends, lo, side="right"))])
            a, f, e = pieces(data[lo:hi], self.doc[lo:hi], length, anchor)
            found.append((a, f + lo, e + lo))
            lo = hi
        none = np.zeros(0, dtype=np.int64)
        self.anchor = np.concatenate([none.astype(np.uint64), *[x[0] for x in found]]) >> np.uint64(cut_bits)
        self.first, self.last = (np.concatenate([none, *[x[i] for x in found]]) for i in (1, 2))
        self.keys, self.key_of = np.unique(self.anchor, return_inverse=True)
        self.raw, self.length = data.tobytes(), length

    def multi(self) -> np.ndarray:
        """Whether an anchor occurs in several documents here; and its number of pieces."""
        d = self.ids[self.doc[self.first]]
        lo, hi = np.full(len(self.keys), np.iinfo(np.int64).max), np.full(len(self.keys), np.iinfo(np.int64).min)
        np.minimum.at(lo, self.key_of, d)
        np.maximum.at(hi, self.key_of, d)
        return lo < hi

    def units(self, state: np.ndarray) -> tuple[list[bytes], np.ndarray, list[np.ndarray], np.ndarray]:
        """Distinct units to search for: bytes, group key, and (unit number, first window, document) of all occurrences.

        ``state`` of each anchor: 1 shared, searched by pieces; 2 hot, by windows.
        """
        number: dict[bytes, int] = {}
        group: list[int] = []
        of, starts = [], []
        raw, length = self.raw, self.length
        s = state[self.key_of]
        keep = np.flatnonzero(s == 1)
        for a, f, e in zip(self.anchor[keep].tolist(), self.first[keep].tolist(), (self.last[keep] + length).tolist(), strict=True):
            unit = raw[f:e]
            n = number.get(unit)
            if n is None:
                n = number[unit] = len(group)
                group.append(a)
            of.append(n), starts.append(f)
        for f, e in zip(self.first[s == 2].tolist(), self.last[s == 2].tolist(), strict=True):
            for i in range(f, e + 1):
                unit = raw[i : i + length]
                n = number.get(unit)
                if n is None:
                    n = number[unit] = len(group)
                    group.append(xxhash.xxh64_intdigest(unit, 9))
                of.append(n), starts.append(i)
        of, starts = np.array(of, dtype=np.int64), np.array(starts, dtype=np.int64)
        return list(number), np.array(group, dtype=np.uint64), of, starts


def _slots(keys: np.ndarray, parts: int) -> tuple[np.ndarray, np.ndarray]:
    slot = (keys % np.uint64(parts)).astype(np.int64)
    order = np.argsort(slot, kind="stable")
    return order, np.searchsorted(slot[order], np.arange(parts + 1))


def text_batches(docs: DataFrame, homes: list[int]) -> DataFrame:
    """``(batch, coded)`` of ``docs(doc_id, text)``: ids, sizes and bytes of whole documents."""

    def code(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        n, size = first_batch(homes), 0
        ids: list[int] = []
        texts: list[bytes] = []

        def row() -> pd.DataFrame:
            data = np.frombuffer(b"".join(texts), dtype=np.uint8)
            return pd.DataFrame({"batch": [n], "coded": [_pack(np.array(ids, dtype=np.int64), np.array([len(t) for t in texts], dtype=np.int64), data)]})

        for pdf in frames:
            for i, text in zip(pdf["doc_id"], pdf["text"], strict=True):
                raw = text.encode()
                if ids and size + len(raw) > BATCH_BYTES:
                    yield row()
                    ids, texts, size, n = [], [], 0, n + 1
                ids.append(int(i)), texts.append(raw)
                size += len(raw)
        if ids:
            yield row()

    keyed = docs.select(F.coalesce("doc_id", F.lit(NO_DOC)).alias("doc_id"), "text")
    return keyed.mapInPandas(code, "batch long, coded binary")


def least_documents(units: list[bytes], group: np.ndarray, doc: np.ndarray, length: int) -> list[np.ndarray]:
    """For each distinct unit, the least document of each of its windows among units of its group."""
    out: list[np.ndarray] = [np.array([d]) for d in doc.tolist()]
    order = np.lexsort((doc, group))
    g = group[order]
    first = np.flatnonzero(np.r_[True, g[1:] != g[:-1]])
    size = np.diff(np.r_[first, len(g)])
    chosen: list[int] = []
    held = 0

    def search() -> None:
        rows = np.array(chosen)
        rows = rows[np.argsort(doc[rows], kind="stable")]  # units in order of their documents
        index = RunIndex([units[i] for i in rows.tolist()], length)
        unit, start, least = index.stream()
        by_unit = np.lexsort((start, unit))
        cuts = np.flatnonzero(np.diff(unit[by_unit])) + 1
        for i, docs_of in zip(rows[unit[by_unit][np.r_[0, cuts]]].tolist(), np.split(doc[rows[least[by_unit]]], cuts), strict=True):
            out[i] = docs_of

    for f, s in zip(first[size > 1].tolist(), size[size > 1].tolist(), strict=True):
        members = order[f : f + s].tolist()
        chosen += members
        held += sum(len(units[i]) for i in members)
        if held > INDEX_BYTES:
            search()
            chosen, held = [], 0
    if chosen:
        search()
    return out


def remove_repeats(docs: DataFrame, length: int = LENGTH, anchor: int = ANCHOR) -> DataFrame:
    """Each of ``docs(doc_id, text)`` without the bytes of long strings that a smaller document has.

    ``(doc_id, n_bytes, n_removed, n_spans, spans array<struct<start,end>>, kept binary)``.
    """
    spark = docs.sparkSession
    # Written where they were read and never shuffled: answers come to them by the task that wrote them.
    homes = even_homes(docs)
    batches = saved_in_place(text_batches(docs, homes), homes, "texts")
    size = batches.agg(F.coalesce(F.sum(F.octet_length("coded")), F.lit(0))).first()[0]
    parts = max(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-size // PARTITION_BYTES))
    shape = "slot int, batch long, blob binary"
    # Anchors that agree by chance are only searched together, so their hashes need few bits beyond the number of anchors.
    cut_bits = max(0, 64 - 12 - int(size).bit_length())

    def dealt(rows: DataFrame) -> DataFrame:
        """As many tasks as the partitions that the size of the texts asks for."""
        return rows.repartition(parts, "slot").groupBy("slot")

    def anchors_of(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in frames:
            for batch, blob in zip(pdf["batch"], pdf["coded"], strict=True):
                b = TextBatch(blob, length, anchor, cut_bits)
                order, cut = _slots(b.keys, parts)
                multi, count = b.multi(), np.bincount(b.key_of, minlength=len(b.keys)).astype(np.uint32)
                rows = [(p, batch, _pack(_deltas(b.keys[at]), multi[at], count[at])) for p in range(parts) if len(at := order[cut[p] : cut[p + 1]])]
                yield pd.DataFrame(rows, columns=["slot", "batch", "blob"])

    def shared(pdf: pd.DataFrame) -> pd.DataFrame:
        asked = [_unpack(b) for b in pdf["blob"]]
        keys = [_keys(a[0]) for a in asked]
        _, of, met = np.unique(np.concatenate(keys), return_inverse=True, return_counts=True)
        many = np.bincount(of, weights=np.concatenate([a[1] for a in asked])) > 0
        count = np.bincount(of, weights=np.concatenate([a[2] for a in asked]))
        state = np.where(many | (met > 1), np.where(count > HOT_PIECES, 2, 1), 0).astype(np.uint8)[of]
        ends = np.cumsum([len(k) for k in keys])[:-1]
        return pd.DataFrame({"slot": pdf["slot"], "batch": pdf["batch"], "blob": [_pack(s) for s in np.split(state, ends)]})

    states = saved(dealt(batches.select("batch", "coded").mapInPandas(trimmed(anchors_of), shape)).applyInPandas(trimmed(shared), shape), "states")
    release_shuffles(spark)
    # One row a batch: at most one packed answer a partition.
    answers = states.groupBy("batch").agg(F.collect_list(F.struct("slot", "blob")).alias("states"))

    def state_of(b: TextBatch, got: list) -> np.ndarray:
        state = np.zeros(len(b.keys), dtype=np.uint8)
        order, cut = _slots(b.keys, parts)
        for a in got:
            state[order[cut[a["slot"]] : cut[a["slot"] + 1]]] = _unpack(a["blob"])[0]
        return state

    def units_of(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in frames:
            for batch, blob, got in zip(pdf["batch"], pdf["coded"], pdf["states"], strict=True):
                b = TextBatch(blob, length, anchor, cut_bits)
                units, group, of, starts = b.units(state_of(b, got))
                least = np.full(len(units), np.iinfo(np.int64).max)
                np.minimum.at(least, of, b.ids[b.doc[starts]])
                order, cut = _slots(group, parts)
                # Below zero: where the units occur, for the batch itself; it only passes through.
                size = np.array([len(u) for u in units], dtype=np.uint32)
                rows = [(-1 - int(batch) % parts, batch, _pack(of.astype(np.uint32), starts.astype(np.uint32), size, order.astype(np.uint32), cut.astype(np.uint32)))]
                for p in range(parts):
                    at = order[cut[p] : cut[p + 1]]
                    if len(at):
                        part = [units[i] for i in at.tolist()]
                        rows.append((p, batch, _pack(group[at], least[at], np.array([len(u) for u in part], dtype=np.uint32), np.frombuffer(b"".join(part), dtype=np.uint8))))
                yield pd.DataFrame(rows, columns=["slot", "batch", "blob"])

    def search(pdf: pd.DataFrame) -> pd.DataFrame:
        if pdf["slot"].iloc[0] < 0:
            return pdf
        number: dict[bytes, int] = {}
        groups: list[int] = []
        docs_of: list[int] = []
        per_row = []
        for blob in pdf["blob"]:
            group, least, sizes, data = _unpack(blob)
            ends = np.cumsum(sizes.astype(np.int64))
            raw, mine, a = data.tobytes(), [], 0
            for g, d, e in zip(group.tolist(), least.tolist(), ends.tolist(), strict=True):
                unit, a = raw[a:e], e
                n = number.get(unit)
                if n is None:
                    n = number[unit] = len(groups)
                    groups.append(g), docs_of.append(d)
                elif d < docs_of[n]:
                    docs_of[n] = d
                mine.append(n)
            per_row.append(mine)
        found = least_documents(list(number), np.array(groups, dtype=np.uint64), np.array(docs_of, dtype=np.int64), length)
        out = []
        for mine in per_row:
            lists = [found[n] for n in mine]
            out.append(_pack(np.array([len(x) for x in lists], dtype=np.uint32), np.concatenate([np.zeros(0, np.int64), *lists]).astype(np.int64)))
        return pd.DataFrame({"slot": pdf["slot"], "batch": pdf["batch"], "blob": out})

    least = saved(dealt(with_answers(batches, answers).select("batch", "coded", "states").mapInPandas(trimmed(units_of), shape)).applyInPandas(trimmed(search), shape), "least")
    release_shuffles(spark)
    settled = least.groupBy("batch").agg(F.collect_list(F.struct("slot", "blob")).alias("least"))

    def cut_texts(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in frames:
            for blob, leasts in zip(pdf["coded"], pdf["least"], strict=True):
                ids, sizes, data = _unpack(blob)
                doc, raw = np.repeat(np.arange(len(ids)), sizes), data.tobytes()
                gone = np.zeros(len(data) + 1, dtype=np.int32)
                if leasts is not None:
                    by_slot = {a["slot"]: a["blob"] for a in leasts}
                    of, starts, size, order, cut = (x.astype(np.int64) for x in _unpack(by_slot.pop(min(by_slot))))
                    known: list = [None] * len(size)
                    for p, answer in by_slot.items():
                        n, values = _unpack(answer)
                        for i, v in zip(order[cut[p] : cut[p + 1]].tolist(), np.split(values, np.cumsum(n.astype(np.int64))[:-1]), strict=True):
                            known[i] = v
                    size = size - length + 1
                    # Every occurrence spreads its unit's least documents over its windows.
                    n_win = size[of] if len(of) else of
                    one = np.array([len(v) == 1 for v in known], dtype=bool)
                    flat = np.concatenate([np.zeros(0, np.int64), *known])
                    base = np.cumsum([len(v) for v in known]) - np.array([len(v) for v in known], dtype=np.int64) if len(known) else np.zeros(0, np.int64)
                    occ = np.repeat(np.arange(len(of)), n_win)
                    shift = np.arange(len(occ)) - np.repeat(np.cumsum(n_win) - n_win, n_win)
                    if len(occ):
                        u = of[occ]
                        least_doc = flat[base[u] + np.where(one[u], 0, shift)]
                        at = starts[occ] + shift
                        hit = at[least_doc < ids[doc[starts[occ]]]]
                        np.add.at(gone, hit, 1)
                        np.add.at(gone, hit + length, -1)
                removed = np.cumsum(gone[:-1]) > 0
                rows, at = [], 0
                for i, n in zip(ids.tolist(), sizes.tolist(), strict=True):
                    r = removed[at : at + n]
                    edge = np.diff(np.r_[0, r.view(np.int8), 0])
                    spans = list(zip(np.flatnonzero(edge == 1).tolist(), np.flatnonzero(edge == -1).tolist(), strict=True))
                    kept = data[at : at + n][~r].tobytes() if spans else raw[at : at + n]
                    rows.append((None if i == NO_DOC else i, n, int(r.sum()), len(spans), [{"start": x, "end": y} for x, y in spans], kept))
                    at += n
                    if len(rows) >= 2000:
                        yield _frame(rows)
                        rows = []
                yield _frame(rows)

    def _frame(rows: list) -> pd.DataFrame:
        out = pd.DataFrame(rows, columns=["doc_id", "n_bytes", "n_removed", "n_spans", "spans", "kept"])
        return out.astype({"doc_id": "Int64"})

    return with_answers(batches, settled, "left").select("coded", "least").mapInPandas(
        trimmed(cut_texts), "doc_id long, n_bytes long, n_removed long, n_spans long, spans array<struct<start:long,end:long>>, kept binary"
    )
