"""Katz backoff language model over a whole corpus, scored on every text.

A model of any ``order`` with Good-Turing discounts; h' is a history h without its first word:

    P(w | h) = d(c) c / c(h)         where h and w were seen together c > 0 times,
    P(w | h) = alpha(h) P(w | h')    where they were not (alpha is 1 for a history never seen), and
    P(w)     = d(c) c / N            for known words, the rest for one unknown type.

A word seen after h was seen after h' too, so the recursion of a token ends at the
longest history it was seen after, and the weights on its way there depend on
counts alone: counts are exchanged one order at a time, weights all at once.  Counts above ``LARGEST`` keep all but ``LEFT`` of a count, so that a history whose
words are all frequent leaves some mass too.  ``alpha(h)`` is the mass that
discounts leave, divided by the mass that h' gives to words not seen after ``h``:
each history sums to exactly one.

The corpus is coded once into batches of word numbers.  Count tables are
partitioned by key hash; a batch sends each partition its distinct keys (with
training counts), one packed row a partition, and gets the totals back in the
same order.  So a token costs a few bytes of shuffle an order, a word or n-gram that
fills a third of the corpus is one entry a batch, and no table is gathered anywhere.
Histories get their backoff weights from the batches that own their n-grams (each
distinct one has an owner), and unseen n-grams of held-out texts are settled where the
weight of their history is.  All n-grams of training texts are seen, so weights are made
for the histories that some held-out text has, which requests and answers carry as a bit.

Words and n-grams are told apart by 64-bit hashes.  Null texts are empty: their
only token is the end.  Repeated rows count and score as often as they occur.
"""

from __future__ import annotations

import zlib
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import xxhash
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hubloom.llm.common import even_homes, first_batch, release_shuffles, saved, saved_in_place, trimmed, with_answers

END, START = np.uint64(0), np.uint64(1)
#: Counts above this are not discounted, but for the part of a count that keeps a history's rest above zero.
LARGEST = 5
LEFT = 0.01
#: Words of the longest n-gram unless the caller asks for more: trigrams took over 4.6 times the input on disk, of 4 allowed.
ORDER = 2
BATCH_BYTES = 2 << 20
#: Corpus bytes a partition of the count tables serves.
PARTITION_BYTES = 8 << 20
RESULT = "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double"


def _pack(*arrays: np.ndarray) -> bytes:
    return zstandard.compress(b"".join(len(a).to_bytes(8, "little") + a.dtype.str.encode().ljust(4) + a.tobytes() for a in arrays), 1)


def _unpack(blob: bytes) -> list[np.ndarray]:
    raw, at, out = zstandard.decompress(blob), 0, []
    while at < len(raw):
        n, kind = int.from_bytes(raw[at : at + 8], "little"), np.dtype(raw[at + 8 : at + 12].strip().decode())
        out.append(np.frombuffer(raw, kind, n, at + 12))
        at += 12 + n * kind.itemsize
    return out


def _deltas(keys: np.ndarray) -> np.ndarray:
    """Differences of ascending keys, bytes of one significance together: packs far better."""
    d = np.diff(keys, prepend=np.uint64(0))
    return d.view(np.uint8).reshape(-1, 8).T.copy().ravel()


def _keys(planes: np.ndarray) -> np.ndarray:
    d = planes.reshape(8, -1).T.copy().view(np.uint64).ravel()
    with np.errstate(over="ignore"):
        return np.cumsum(d, dtype=np.uint64)


def _bits(packed: np.ndarray, n: int) -> np.ndarray:
    return np.unpackbits(packed, count=n).astype(bool)


def _by_slot(slot: np.ndarray, parts: int) -> tuple[np.ndarray, np.ndarray]:
    order = np.argsort(slot, kind="stable")
    return order, np.searchsorted(slot[order], np.arange(parts + 1))


def held_out_id(doc_id: int | None, folds: int = 5, fold: int = 1) -> bool:
    return zlib.crc32(b"" if doc_id is None else str(doc_id).encode()) % folds == fold


def _after(h: np.ndarray, w: np.ndarray) -> np.ndarray:
    """Keys of histories followed by words."""
    with np.errstate(over="ignore"):
        key = (h * np.uint64(0x9E3779B97F4A7C15)) ^ ((w + np.uint64(0x7F4A7C15)) * np.uint64(0xC2B2AE3D27D4EB4F))
        key ^= key >> np.uint64(31)
        return key * np.uint64(0xD6E8FEB86659FD93)


class Batch:
    """Documents coded as numbers into a sorted list of distinct word hashes.

    ``grams[j]``: ascending keys of the n-grams of ``j + 1`` words and the number of that at each token;
    ``history[j]``: the number, in ``grams[j]``, of what precedes each token; ``starts[j]``: that of a text's start.
    ``upto``: words of the longest n-grams to make, of a model of ``order``.
    """

    def __init__(self, words: np.ndarray, stream: np.ndarray, lengths: np.ndarray, train: np.ndarray, order: int, upto: int | None = None):
        self.words, self.stream, self.lengths, self.train = words, stream, lengths, train
        self.doc = np.repeat(np.arange(len(lengths)), lengths)
        self.in_train = train[self.doc]
        first = np.cumsum(lengths) - lengths
        self.grams, self.history, self.starts = [(words, stream)], [], []
        start = np.array([START])
        for n in range(1, order):
            keys, of = self.grams[-1]
            self.starts.append(int(np.searchsorted(keys, start[0])))
            before = np.empty_like(of)
            before[1:] = of[:-1]
            before[first] = self.starts[-1]
            self.history.append(before)
            if n == upto:
                break
            every = _after(keys[before], words[stream])
            start = _after(start, np.array([START]))
            kept, at = np.unique(np.concatenate([every, start]) if n + 1 < order else every, return_inverse=True)
            self.grams.append((kept, at[: len(every)].astype(np.uint32)))

    def dealt(self, j: int, parts: int) -> tuple[np.ndarray, np.ndarray]:
        """The numbers of ``grams[j]`` by partition, and where each partition's begin."""
        return _by_slot((self.grams[j][0] % np.uint64(parts)).astype(np.int64), parts)

    @classmethod
    def of_texts(cls, texts: list[str], train: list[bool], order: int = 1) -> Batch:
        number: dict[bytes, int] = {}

        class Numbers(dict):
            def __missing__(self, word: bytes) -> int:
                n = self[word] = len(self)
                return n

        number = Numbers()
        parts, lengths = [], []
        for text in texts:
            codes = list(map(number.__getitem__, text.encode().lower().split()))
            codes.append(-1)
            parts.append(np.array(codes, dtype=np.int64))
            lengths.append(len(codes))
        hashes = np.array([xxhash.xxh64_intdigest(w) for w in number] + [START, END], dtype=np.uint64)
        words, rank = np.unique(hashes, return_inverse=True)
        return cls(words, rank[np.concatenate(parts)].astype(np.uint32), np.array(lengths, dtype=np.int64), np.array(train, dtype=bool), order)

    def packed(self) -> bytes:
        return _pack(_deltas(self.words), self.stream, self.lengths, self.train)

    @classmethod
    def unpacked(cls, blob: bytes, order: int, upto: int | None = None) -> Batch:
        words, stream, lengths, train = _unpack(blob)
        return cls(_keys(words), stream, lengths, train, order, upto)


def discounts(n: np.ndarray) -> np.ndarray:
    """Katz's discount ratios of counts 1..LARGEST from the numbers n[r] of items seen r times (n[0] unused).

    Where the counts of counts are too few or too uneven for a ratio in (0, 1), half a count is taken off.
    """
    out = np.array([1.0, *((r - 0.5) / r for r in range(1, LARGEST + 1))])
    if n[1] > 0 and (common := (LARGEST + 1) * n[LARGEST + 1] / n[1]) < 1:
        for r in range(1, LARGEST + 1):
            if n[r] > 0:
                d = ((r + 1) * n[r + 1] / n[r] / r - common) / (1 - common)
                if 0 < d < 1:
                    out[r] = d
    return out


def discounted(count: np.ndarray, d: np.ndarray) -> np.ndarray:
    return np.where(count <= LARGEST, count * d[np.minimum(count, LARGEST).astype(np.int64)], count - LEFT)


def _narrow(n: np.ndarray) -> np.ndarray:
    """Counts in as few bytes as the largest needs, up to eight."""
    return n.astype(np.min_scalar_type(int(n.max(initial=0))))


def code_corpus(docs: DataFrame, homes: list[int]) -> DataFrame:
    """``(batch, doc_ids array<long>, coded binary)`` of ``docs(doc_id, text)``."""

    def code(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        n = first_batch(homes)
        ids: list = []
        texts: list[str] = []
        size = 0

        def row() -> pd.DataFrame:
            batch = Batch.of_texts(texts, [not held_out_id(i) for i in ids])
            return pd.DataFrame({"batch": [n], "doc_ids": [ids], "coded": [batch.packed()]})

        for pdf in frames:
            for i, text in zip(pdf["doc_id"].astype("Int64"), pdf["text"], strict=True):
                ids.append(None if i is pd.NA else int(i))
                texts.append(text)
                size += len(text)
                if size > BATCH_BYTES:
                    yield row()
                    ids, texts, size, n = [], [], 0, n + 1
        if ids:
            yield row()

    return docs.select("doc_id", "text").mapInPandas(code, "batch long, doc_ids array<long>, coded binary")


def katz_scores(docs: DataFrame, order: int = ORDER) -> DataFrame:
    """``(doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score)``, a row for each of ``docs(doc_id, text)``.

    ``order``: words of the longest n-gram, at least 1 (then ``score`` knows no history).
    """
    if order < 1:
        raise ValueError("a model has one word at least")
    spark = docs.sparkSession
    # Written where it was read and never shuffled: answers come to a batch by the task that wrote it.
    homes = even_homes(docs)
    coded = saved_in_place(code_corpus(docs, homes), homes, "coded")
    sizes = coded.agg(F.coalesce(F.sum(F.octet_length("coded")), F.lit(0))).first()[0]
    parts = max(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-order * sizes // PARTITION_BYTES))

    def ask(kind: int) -> Callable:
        def of_order(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for pdf in frames:
                for batch, blob in zip(pdf["batch"], pdf["coded"], strict=True):
                    b = Batch.unpacked(blob, order, kind + 1)
                    (keys, of), (dealt, cut) = b.grams[kind], b.dealt(kind, parts)
                    count = np.bincount(of[b.in_train], minlength=len(keys))
                    wanted = np.zeros(len(keys), dtype=bool)
                    if kind < order - 1:
                        wanted[b.history[kind][~b.in_train]] = True
                    keys = keys // np.uint64(parts)  # the rest of the division is the partition
                    rows = [(kind, p, batch, _pack(_deltas(keys[at]), _narrow(count[at]), np.packbits(wanted[at]))) for p in range(parts) if len(at := dealt[cut[p] : cut[p + 1]])]
                    yield pd.DataFrame(rows, columns=["kind", "slot", "batch", "blob"])

        return of_order

    def total(pdf: pd.DataFrame) -> pd.DataFrame:
        """Totals of a partition's keys, back to each batch in its own order; the first batch of a key owns it."""
        pdf = pdf.sort_values("batch")
        asked = [_unpack(b) for b in pdf["blob"]]
        keys = [_keys(a[0]) for a in asked]
        every, first, of = np.unique(np.concatenate(keys), return_index=True, return_inverse=True)
        sums = np.bincount(of, weights=np.concatenate([a[1] for a in asked])).astype(np.int64)
        owner = np.zeros(len(of), dtype=bool)
        owner[first] = True
        wanted = np.zeros(len(every), dtype=bool)
        wanted[of[np.concatenate([_bits(a[2], len(k)) for a, k in zip(asked, keys, strict=True)])]] = True
        seen = sums[sums > 0]
        of_counts = np.bincount(np.minimum(seen, LARGEST + 2), minlength=LARGEST + 3)[: LARGEST + 2]
        ends = np.cumsum([len(k) for k in keys])[:-1]
        answers = [_pack(_narrow(t), np.packbits(o), np.packbits(w)) for t, o, w in zip(*[np.split(x, ends) for x in (sums[of], owner, wanted[of])], strict=True)]
        out = pd.DataFrame({"kind": pdf["kind"], "slot": pdf["slot"], "batch": pdf["batch"], "blob": answers})
        out["stats"] = [[int(len(seen)), int(seen.sum()), *of_counts.tolist()]] + [None] * (len(out) - 1)
        return out

    shape = "kind int, slot int, batch long, blob binary"
    replies = None
    for kind in range(order):  # one after the other, so that the requests of one order lie on disk at a time
        one = saved(coded.select("batch", "coded").mapInPandas(trimmed(ask(kind)), shape).groupBy("kind", "slot").applyInPandas(trimmed(total), shape + ", stats array<long>"), "counts")
        replies = one if replies is None else replies.unionAll(one)
        release_shuffles(spark)
    # A few sums for the whole model.
    totals = {
        r["kind"]: r
        for r in replies.where("stats is not null")
        .groupBy("kind")
        .agg(*[F.sum(F.col("stats")[i]).alias(f"s{i}") for i in range(LARGEST + 4)])
        .collect()
    }
    if not totals:
        return spark.createDataFrame([], RESULT)
    stats = {k: np.array([r[f"s{i}"] for i in range(LARGEST + 4)], dtype=float) for k, r in totals.items()}
    types, tokens = stats[0][0], stats[0][1]
    d = [discounts(stats[j][2:]) for j in range(order)]
    # What discounts leave of the words' mass is the unknown type's.
    small = stats[0][2:][1 : LARGEST + 1]
    lost = float((np.arange(1, LARGEST + 1) * (1 - d[0][1:]) * small).sum() + LEFT * (types - small.sum()))
    n_train = max(tokens, 1.0)
    unknown = max(lost, 0.5) / n_train if tokens else 1.0
    shrink = 1.0 if lost >= 0.5 else (1.0 - unknown)

    def unigram(c: np.ndarray) -> np.ndarray:
        return np.where(c > 0, shrink * discounted(c, d[0]) / n_train, unknown)

    answers = replies.groupBy("batch").agg(F.collect_list(F.struct("kind", "slot", "blob")).alias("answers"))  # at most one a partition and order

    def settle(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in frames:
            for batch, doc_ids, blob, got in zip(pdf["batch"], pdf["doc_ids"], pdf["coded"], pdf["answers"], strict=True):
                b = Batch.unpacked(blob, order)
                counts = [np.zeros(len(k)) for k, _ in b.grams]
                owner, wanted = ([np.zeros(len(k), dtype=bool) for k, _ in b.grams] for _ in range(2))
                dealt = [b.dealt(j, parts) for j in range(order)]
                for a in got:
                    every, cut = dealt[a["kind"]]
                    at = every[cut[a["slot"]] : cut[a["slot"] + 1]]
                    t, o, w = _unpack(a["blob"])
                    counts[a["kind"]][at], owner[a["kind"]][at], wanted[a["kind"]][at] = t, _bits(o, len(t)), _bits(w, len(t))
                docs_n = len(b.lengths)
                of_doc = lambda v: np.bincount(b.doc, weights=v, minlength=docs_n)  # noqa: E731, B023
                c = counts[0][b.stream]
                base = of_doc(np.log10((c + 0.5) / (n_train * (tokens > 0) + 0.5 * (types + 1))))
                p1 = unigram(counts[0])
                texts = counts[0][np.searchsorted(b.words, END)]  # as many as ends
                shorter, logs, rows = p1[b.stream], np.log10(p1[b.stream]), []
                for j, h in enumerate(b.history):
                    # As histories, n-grams count as often as they occur; the start as often as there are texts.
                    known = counts[j].copy()
                    known[b.starts[j]] = texts
                    of = b.grams[j + 1][1]
                    cp = counts[j + 1][of]
                    seen = cp > 0
                    with np.errstate(divide="ignore", invalid="ignore"):
                        p = discounted(cp, d[j + 1]) / known[h]
                        logs = np.where(seen, np.log10(p), logs)
                    # N-grams that this batch owns tell their history what is taken of it, by count and by the mass of shorter histories.
                    one = np.full(len(owner[j + 1]), -1)
                    one[of] = np.arange(len(of))
                    mine = one[owner[j + 1] & (counts[j + 1] > 0)]
                    mine = mine[wanted[j][h[mine]]]
                    hm = h[mine]
                    taken = np.bincount(hm, weights=discounted(cp[mine], d[j + 1]), minlength=len(known))
                    mass = np.bincount(hm, weights=shorter[mine], minlength=len(known))
                    # Unseen ones after a known history wait for its weight: (history, document, times).
                    wait = np.flatnonzero(~seen & (known[h] > 0))
                    hd, times = np.unique(h[wait].astype(np.int64) * docs_n + b.doc[wait], return_counts=True)
                    told = np.flatnonzero(np.bincount(hm, minlength=len(known)))
                    keys, slot = b.grams[j][0] // np.uint64(parts), (b.grams[j][0] % np.uint64(parts)).astype(np.int64)
                    (t_of, t_cut), (w_of, w_cut) = _by_slot(slot[told], parts), _by_slot(slot[hd // docs_n], parts)
                    for s in np.flatnonzero(np.diff(t_cut) + np.diff(w_cut)):
                        t, w = told[t_of[t_cut[s] : t_cut[s + 1]]], w_of[w_cut[s] : w_cut[s + 1]]
                        told_of = (_deltas(keys[t]), _narrow(known[t]), taken[t], mass[t])
                        rows.append((j + 1, s, batch, _pack(*told_of, _deltas(keys[hd[w] // docs_n]), _narrow(hd[w] % docs_n), _narrow(times[w])), None))
                    shorter = p
                part = of_doc(logs)
                ids = [None if i is None or i != i else int(i) for i in doc_ids]
                per_doc = [
                    (i, not t, int(n), int(k), float(bs), float(ps))
                    for i, t, n, k, bs, ps in zip(ids, b.train.tolist(), b.lengths, of_doc(c > 0), base, part, strict=True)
                ]
                rows.append((0, 0, batch, None, per_doc))
                yield pd.DataFrame(rows, columns=["kind", "slot", "batch", "blob", "docs"])

    doc_shape = "array<struct<doc_id:long,held_out:boolean,n_tokens:long,n_known:long,base_score:double,part:double>>"
    both = with_answers(coded, answers).select("batch", "doc_ids", "coded", "answers")
    settled = saved(both.mapInPandas(trimmed(settle), f"{shape}, docs {doc_shape}"), "settled")
    release_shuffles(spark)

    def weigh(pdf: pd.DataFrame) -> pd.DataFrame:
        """Backoff weights of a partition's histories, and the logs that waiting documents get."""
        rows = [_unpack(b) for b in pdf["blob"]]
        for r in rows:  # keys ascend, those of histories that wait with repeats
            r[0], r[4] = _keys(r[0]), _keys(r[4])
        words, of = np.unique(np.concatenate([r[0] for r in rows]), return_inverse=True)
        taken = np.bincount(of, weights=np.concatenate([r[2] for r in rows]), minlength=len(words))
        mass = np.bincount(of, weights=np.concatenate([r[3] for r in rows]), minlength=len(words))
        count = np.zeros(len(words))
        count[of] = np.concatenate([r[1] for r in rows])
        alpha = (1 - taken / count) / np.maximum(1 - mass, 1e-12)
        out = []
        for batch, r in zip(pdf["batch"], rows, strict=True):
            if len(r[4]):
                each = np.log10(alpha[np.searchsorted(words, r[4])]) * r[6]
                at, where = np.unique(r[5].astype(np.int64), return_inverse=True)
                out.append((batch, _pack(at, np.bincount(where, weights=each))))
        return pd.DataFrame(out, columns=["batch", "waits"]).astype({"batch": "int64"})

    # A packed row for each batch, order and partition, as on the way there.
    waits = settled.where("kind > 0").select("kind", "slot", "batch", "blob").groupBy("kind", "slot").applyInPandas(trimmed(weigh), "batch long, waits binary")
    gathered = settled.where("kind = 0").select("batch", "docs").join(waits.groupBy("batch").agg(F.collect_list("waits").alias("waits")), "batch", "left")

    def finish(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in frames:
            for docs_of, blobs in zip(pdf["docs"], pdf["waits"], strict=True):
                wait = np.zeros(len(docs_of))
                for blob in blobs if blobs is not None else ():
                    at, w = _unpack(blob)
                    np.add.at(wait, at, w)
                rows = [(d["doc_id"], d["held_out"], d["n_tokens"], d["n_known"], int(tokens), d["base_score"], d["part"] + w) for d, w in zip(docs_of, wait.tolist(), strict=True)]
                yield pd.DataFrame(rows, columns=[f.split()[0] for f in RESULT.split(", ")]).astype({"doc_id": "Int64"})

    return gathered.mapInPandas(finish, RESULT)
