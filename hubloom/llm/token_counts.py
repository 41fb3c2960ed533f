"""Token counts by a two-tier lookup of pre-token lengths, all map-side.

Tier one is a table of the corpus's frequent pre-tokens and their token counts,
found by mergeable frequent-item summaries (one bounded row a task, merged in a
tree of fixed fan-in) and broadcast: at most ``TABLE_ENTRIES`` short strings, a
bound that does not depend on the data.  Tier two is a bounded cache in each
worker that encodes what tier one misses.  No pre-token is ever shuffled, and
the counts are exact whatever the table holds.

Null texts are empty and count zero; special strings in a text count one token
each, as the library's defaults have it.
"""

from __future__ import annotations

import json
import unicodedata
from collections import Counter
from collections.abc import Iterator
from functools import lru_cache

import pandas as pd
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from tokenizers import Tokenizer

#: Counters of a summary, and entries of the broadcast table.
TABLE_ENTRIES = 32_768
#: Longest pre-token in the table, which bounds its bytes.
TABLE_CHARS = 32
FAN_IN = 32
CACHE_ENTRIES = 400_000


def _printable_bytes() -> list[str]:
    """The character that stands for each byte in a byte-level vocabulary."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    out, extra = [], 0
    for b in range(256):
        if b in plain:
            out.append(chr(b))
        else:
            out.append(chr(256 + extra))
            extra += 1
    return out


class PreTokens:
    """The library's own steps up to pre-tokens, with a fast path where Python's agree."""

    def __init__(self, path: str):
        self.tok = Tokenizer.from_file(path)
        spec = json.load(open(path, encoding="utf-8"))
        specials = sorted((t["content"] for t in spec["added_tokens"]), key=len, reverse=True)
        self.special = regex.compile("|".join(map(regex.escape, specials))) if specials else None
        self.find = regex.compile(spec["pre_tokenizer"]["pretokenizers"][0]["pattern"]["Regex"])
        self.chars = _printable_bytes()
        self.lengths: dict[str, int] = {}

    def segments(self, text: str) -> tuple[list[str], int]:
        if self.special is None or "<|" not in text:
            return [text], 0
        parts = self.special.split(text)
        return parts, len(parts) - 1

    def cut(self, segment: str) -> list[str]:
        if segment.isascii():
            s = segment.lower()
        elif "Σ" in segment:  # a final sigma: Python lowers by context, the library by character
            s = self.tok.normalizer.normalize_str(segment)
        else:
            s = unicodedata.normalize("NFC", segment).lower()
        return self.find.findall(s)

    def length(self, word: str) -> int:
        return len(self.tok.model.tokenize("".join([self.chars[b] for b in word.encode()])))


@lru_cache(maxsize=2)
def _pretokens(path: str) -> PreTokens:
    return PreTokens(path)


def _shrunk(counts: Counter, size: int) -> Counter:
    """A frequent-items summary with at most ``size`` counters: the rest is paid off by all."""
    if len(counts) <= size:
        return counts
    top = counts.most_common(size + 1)
    pay = top[-1][1]
    return Counter({w: n - pay for w, n in top[:-1] if n > pay})


def frequent_pretokens(docs: DataFrame, path: str, size: int = TABLE_ENTRIES) -> list[str]:
    """The corpus's frequent pre-tokens, from every text, as a bounded list."""
    tasks = max(1, docs.rdd.getNumPartitions())

    def summarise(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        from pyspark import TaskContext

        pre, counts = _pretokens(path), Counter()
        for pdf in batches:
            for text in pdf["text"]:
                for segment in pre.segments(text)[0]:
                    counts.update(pre.cut(segment))
                if len(counts) > 4 * size:
                    counts = _shrunk(counts, size)
        counts = _shrunk(Counter({w: n for w, n in counts.items() if len(w) <= TABLE_CHARS}), size)
        yield pd.DataFrame({"slot": [TaskContext.get().partitionId()], "words": [list(counts)], "counts": [list(counts.values())]})

    def merge(pdf: pd.DataFrame) -> pd.DataFrame:
        total: Counter = Counter()
        for words, counts in zip(pdf["words"], pdf["counts"], strict=True):
            for w, n in zip(words, counts, strict=True):
                total[w] += int(n)
        total = _shrunk(total, size)
        return pd.DataFrame({"slot": [int(pdf["slot"].iloc[0])], "words": [list(total)], "counts": [list(total.values())]})

    shape = "slot long, words array<string>, counts array<long>"
    level = docs.select("text").mapInPandas(summarise, shape)
    while tasks > 1:
        level = level.withColumn("slot", F.expr(f"slot div {FAN_IN}")).groupBy("slot").applyInPandas(merge, shape)
        tasks = -(-tasks // FAN_IN)
    rows = level.toPandas()  # one bounded summary
    if rows.empty:
        return []
    return list(merge(rows)["words"].iloc[0])


def token_counts(docs: DataFrame, path: str, limit: int = 2048) -> DataFrame:
    """``(doc_id, n_bytes, n_tokens, over_limit)`` for ``docs(doc_id, text)``."""
    spark = docs.sparkSession
    pre = _pretokens(path)
    table = spark.sparkContext.broadcast({w: pre.length(w) for w in frequent_pretokens(docs, path)})

    def count(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        frequent, pre = table.value, _pretokens(path)

        class Lengths(dict):
            def __missing__(self, word: str) -> int:
                n = frequent.get(word)
                if n is None:
                    if len(self) >= CACHE_ENTRIES:
                        self.clear()
                    n = pre.length(word)
                self[word] = n
                return n

        cache = pre.lengths if isinstance(pre.lengths, Lengths) else Lengths(pre.lengths)
        pre.lengths = cache
        look = cache.__getitem__
        for pdf in batches:
            n_tokens = []
            for text in pdf["text"]:
                parts, n = pre.segments(text)
                for part in parts:
                    n += sum(map(look, pre.cut(part)))
                n_tokens.append(n)
            yield pd.DataFrame({"doc_id": pdf["doc_id"], "n_bytes": pdf["n_bytes"], "n_tokens": n_tokens})

    counted = docs.select("doc_id", "text", F.octet_length("text").cast("long").alias("n_bytes")).mapInPandas(
        count, "doc_id long, n_bytes long, n_tokens long"
    )
    return counted.withColumn("over_limit", F.col("n_tokens") > limit)
