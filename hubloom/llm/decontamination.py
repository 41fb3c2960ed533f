"""Benchmark decontamination by template canonicalisation, in DataFrame functions only.

Numbers, names and units give way to typed placeholders, so a question asked
again with other values has the same template.  Windows of canonical tokens of
the benchmark meet those of the documents in a hash join that carries two
numbers a window; matches gather by document, item and alignment.  The few rows
that match well are canonicalised once more with the values of their slots:
windows are compared word by word, and in them each value of the item must go
with one value of the document, as it does when a question is re-parameterised
and not when templates agree by chance.

Matched windows add up over a band of alignments, so that words put in or left
out on the way cost only the windows they stand in.  Items of under 23 tokens take
narrower windows, of which one changed word leaves half; those of under eight
are one window as a whole.  Windows of fewer than two ordinary words tell
nothing and don't count.  Items of under five tokens, or without a telling
window, are found only in documents that are the item as a whole, word by word.

A name is a capitalised word inside a sentence.  A capitalised word elsewhere (at
the start of a sentence) may be one: windows are tried both ways.

Items of one template are one while windows are joined, and texts that are equal
are one row, so neither copies of a document nor variants of a question multiply
each other before values are compared.  Null texts are empty and match nothing;
null item ids are left out; a repeated row counts once; rows that repeat an id
are reported if one of them is.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from hubloom.llm.common import saved

WINDOW = 8
#: Widths of windows by the tokens that an item needs at least; one changed word leaves half of ``3 * w - 1`` tokens' windows.
WIDTHS = ((8, 3), (14, 5), (23, WINDOW))
#: Items of fewer tokens are looked for as whole documents only.
LEAST_TOKENS = 5
#: Ordinary words (no placeholders) without which a window tells nothing.
LEAST_WORDS = 2
#: Share of an item's windows that one document must match on one band of alignments.
COVERAGE = 0.5
#: Share of slots that must agree with a one-to-one renaming.
CONSISTENCY = 0.8
#: Rows (of at most a few hundred bytes) up to which a join broadcasts its small side.
BROADCAST_ROWS = 200_000

# Unit words that become a placeholder after a number.
UNITS = (
    "mm cm m km in inch inches ft foot feet yd yard yards mi mile miles mg g kg t lb lbs oz ml l litre litres liter liters gallon gallons "
    "s sec second seconds min minute minutes h hr hour hours day days week weeks month months year years "
    "cent cents dollar dollars euro euros pound pounds usd eur gbp percent kmh mph"
).split()

# Each pattern starts with what is rare in prose, and looks around only there.
_NAME = r"\p{Lu}(?<=[^.!?:\s][ \t]\p{Lu})\p{Ll}+(?![\p{L}\p{N}])"
_INITIAL = r"\p{Lu}(?<![\p{L}\p{N}]\p{Lu})\p{Ll}+(?![\p{L}\p{N}])"
_NUMBER = r"\p{N}(?<![\p{L}\p{N}]\p{N})\p{N}*(?:[.,:/-]\p{N}+)*(?![\p{L}\p{N}])"
_UNIT = r"<num> (" + "|".join(UNITS) + r")(?![\p{L}\p{N}])"


def _steps(text: Column) -> tuple[Column, Column, Column, Column]:
    """The text before names, numbers and units are replaced, and after: each a string of its own."""
    own = F.contains(text, F.lit("<")) | F.contains(text, F.lit(">"))
    clean = F.when(own, F.regexp_replace(text, "[<>]", " ")).otherwise(text)  # so that placeholders are ours
    # Capitalised words left over keep their letters behind a mark of their own.
    named = F.regexp_replace(F.regexp_replace(clean, _NAME, "<name>"), _INITIAL, "<<$0")
    counted = F.lower(F.regexp_replace(named, _NUMBER, "<num>"))
    return clean, named, counted, F.regexp_replace(counted, _UNIT, "<num> <unit>")


def _tokens(final: Column) -> Column:
    return F.filter(F.split(final, r"[^\p{L}\p{N}<>]+"), lambda w: w != "")


MEASURES = ["matched", "item_windows", "slots", "slots_consistent"]


def text_key() -> Column:
    """What stands for a text; a null text is empty."""
    return F.xxhash64(F.coalesce("text", F.lit("")))


def canonical(docs: DataFrame, *keys: str) -> DataFrame:
    """``(keys.., words, names array<string>)``: canonical tokens of ``text``, with capitalised words at a start as words and as names."""
    final = docs.select(*keys, _steps(F.col("text"))[3].alias("final"))
    return final.select(*keys, _tokens(F.replace("final", F.lit("<<"), F.lit(""))).alias("words"), _tokens(F.regexp_replace("final", r"<<\p{L}+", "<name>")).alias("names"))


def with_lists(docs: DataFrame, *keys: str) -> DataFrame:
    """Canonical tokens, and what the placeholders of each kind stand for, in order."""
    clean, named, counted, final = _steps(F.col("text"))
    return docs.select(
        *keys,
        _tokens(final).alias("canon"),
        F.regexp_extract_all(clean, F.lit(_NAME), 0).alias("names"),
        F.regexp_extract_all(named, F.lit(_NUMBER), 0).alias("numbers"),
        F.regexp_extract_all(counted, F.lit(_UNIT), 1).alias("units"),
    )


_KINDS = (("<name>", "names"), ("<num>", "numbers"), ("<unit>", "units"))


def _plain(part: Column, before: Column, lists: dict[str, Column]) -> Column:
    """The words and values of a part of the tokens: the n-th placeholder of a kind stands for the n-th match of its pattern."""
    met = [F.size(_only(before, k)).alias(n) for k, n in _KINDS]
    start = F.struct(F.array().cast("array<string>").alias("out"), *met)

    def step(acc: Column, word: Column) -> Column:
        value = reduce(lambda rest, kn: F.when(word == kn[0], F.get(lists[kn[1]], acc[kn[1]])).otherwise(rest), _KINDS, _as_word(word))
        return F.struct(F.concat(acc["out"], F.array(F.lower(value))).alias("out"), *[(acc[n] + F.when(word == k, 1).otherwise(0)).alias(n) for k, n in _KINDS])

    return F.aggregate(part, start, step, lambda acc: acc["out"])


def _only(tokens: Column, kind: str) -> Column:
    return F.filter(tokens, lambda w: w == kind)


def _as_name(word: Column) -> Column:
    return F.when(F.startswith(word, F.lit("<<")), F.lit("<name>")).otherwise(word)


def _as_word(word: Column) -> Column:
    return F.when(F.startswith(word, F.lit("<<")), F.regexp_replace(word, "[<>]", "")).otherwise(word)


def _width(n: Column) -> Column:
    """Window width of an item of ``n`` tokens."""
    return reduce(lambda rest, w: F.when(n >= w[0], F.lit(w[1])).otherwise(rest), WIDTHS, n).cast("int")


def _windows(tokens: DataFrame, keys: list[str], widths: Column) -> DataFrame:
    """``(keys.., width, at, hash)`` of every window of ``widths`` (an array), with initial words as names and as words."""
    each = tokens.select(*keys, "words", "names", F.explode(widths).alias("width"))
    # No filter: pushed below, it would canonicalise every text twice.
    last = F.size("words") - F.col("width")
    placed = each.select(*keys, "words", "names", "width", F.explode(F.when(last >= 0, F.sequence(F.lit(0), last))).alias("at"))
    hashed = lambda c: F.xxhash64("width", F.slice(c, F.col("at") + 1, F.col("width")))
    both = placed.select(*keys, "width", "at", hashed("words").alias("w"), hashed("names").alias("n"))
    return both.select(*keys, "width", "at", F.explode(F.when(F.col("w") == F.col("n"), F.array("w")).otherwise(F.array("w", "n"))).alias("hash"))


def _small(df: DataFrame) -> DataFrame:
    return F.broadcast(df) if df.count() <= BROADCAST_ROWS else df


def contaminated(docs: DataFrame, benchmark: DataFrame, width: int = WINDOW, coverage: float = COVERAGE, consistency: float = CONSISTENCY) -> DataFrame:
    """``(doc_id, item_id, matched, item_windows, slots, slots_consistent)`` of documents that hold a benchmark item.

    ``docs(doc_id, text)`` and ``benchmark(item_id, text)``.
    """
    found = saved(contaminated_texts(docs, benchmark, width, coverage, consistency), "found")
    named = docs.select("doc_id", text_key().alias("row")).join(_small(found), "row").groupBy("doc_id", "item_id")
    return named.agg(F.max(F.struct(*MEASURES)).alias("m")).select("doc_id", "item_id", "m.*")


def contaminated_texts(docs: DataFrame, benchmark: DataFrame, width: int = WINDOW, coverage: float = COVERAGE, consistency: float = CONSISTENCY) -> DataFrame:
    """The same by text: ``(row, item_id, ..)``, ``row`` being the ``text_key()``."""
    items = benchmark.where("item_id is not null").groupBy("item_id").agg(F.min("text").alias("text"))
    plain = _plain(F.col("canon"), F.array().cast("array<string>"), {n: F.col(n) for _, n in _KINDS})
    items = with_lists(items, "item_id").select("item_id", "canon", plain.alias("plain"), F.xxhash64("canon").alias("template"))
    items = saved(items.where(F.size("canon") > 0).withColumn("width", _width(F.size("canon"))), "items")
    templates = items.where(F.size("canon") >= LEAST_TOKENS).groupBy("template").agg(F.first("canon").alias("canon"), F.first("width").alias("width"))
    known = saved(_known_windows(templates), "windows")
    sizes = known.groupBy("template").agg(F.countDistinct("item_at").alias("item_windows"))
    sizes = saved(templates.join(sizes, "template").select("template", "item_windows", "width", (8 + F.floor(F.size("canon") / 8)).cast("int").alias("half")), "sizes")
    widths = sorted(r[0] for r in sizes.select("width").distinct().collect())  # at most WINDOW numbers
    whole = _whole_documents(docs, items.join(sizes, "template", "left_anti"))
    if not widths:
        return whole
    shift = (F.col("at") - F.col("item_at")).alias("shift")
    tokens = canonical(docs.select(text_key().alias("row"), "text"), "row")
    hits = _windows(tokens, ["row"], F.array(*map(F.lit, widths))).join(_small(known), ["width", "hash"]).select("row", "template", shift, "item_at")
    # Bands of alignments overlap by half, so what lies within ``half`` shifts is whole in one of them.
    band = F.floor(F.col("shift") / F.col("half"))
    hits = saved(hits.distinct(), "hits").join(_small(sizes), "template").withColumn("band", F.explode(F.array(band, band - 1)))
    who = ["row", "template", "band"]
    enough = F.col("matched") >= F.ceil(coverage * F.col("item_windows"))
    runs = hits.select(*who, "item_windows", "item_at").distinct().groupBy(*who, "item_windows").agg(F.count("*").alias("matched"))
    likely = saved(runs.where(enough).select(*who), "likely")

    # From here on, only documents with a likely item.  A window that matches on several alignments takes that of most matches.
    held = hits.join(_small(likely), who)
    often = held.groupBy(*who, "item_windows", "shift").agg(F.count("*").alias("n"), F.collect_list("item_at").alias("ats")).withColumn("item_at", F.explode("ats"))
    taken = often.groupBy(*who, "item_windows", "item_at").agg(F.max_by("shift", F.struct("n", "shift")).alias("shift"))
    listed = taken.groupBy(*who, "item_windows").agg(
        F.collect_list(F.struct("item_at", (F.col("item_at") + F.col("shift")).alias("at"))).alias("hits"), F.min(F.col("item_at") + F.col("shift")).alias("start")
    )
    # Bands of the same matches are one; then every item of the template is looked at with its own values.
    listed = listed.groupBy("row", "template", "item_windows", "start", F.sort_array("hits").alias("hits")).agg(F.min("band").alias("band"))
    some = docs.select(text_key().alias("row"), "text").join(_small(likely.select("row").distinct()), "row", "left_semi").dropDuplicates(["row"])
    valued = saved(with_lists(some, "row").withColumnRenamed("canon", "tokens"), "slots")
    both = listed.join(valued, "row").join(_small(items.select("item_id", "template", "canon", "plain", "width")), "template")
    # Only the part of the document that the band covers gets its values back.
    span = F.array_max(F.transform("hits", lambda h: h["at"])) + F.col("width") - F.col("start")
    both = both.withColumn("dc", F.slice("tokens", F.col("start") + 1, span))
    both = both.withColumn("dp", _plain(F.col("dc"), F.slice("tokens", F.lit(1), F.col("start")), {n: F.col(n) for _, n in _KINDS}))
    # Written down, so that the expressions below read arrays and don't make them anew for each use.
    aligned = saved(both.select("row", "item_id", "band", "item_windows", "width", "hits", "start", "canon", "plain", "dc", "dp"), "aligned")
    each = lambda h: F.transform(
        F.sequence(F.lit(0), F.col("width") - 1), lambda k: F.struct((h["item_at"] + k).alias("i"), (h["at"] - F.col("start") + k).alias("d"))
    )
    ic, dc = (lambda x: F.get("canon", x["i"])), (lambda x: F.get("dc", x["d"]))
    same = lambda x: _as_name(ic(x)).eqNullSafe(_as_name(dc(x))) | _as_word(ic(x)).eqNullSafe(_as_word(dc(x)))
    # Windows all of whose tokens agree (the hash said so; this is exact).
    checked = aligned.withColumn("full", F.filter("hits", lambda h: F.forall(each(h), same))).withColumn("matched", F.size("full").cast("long"))
    met = F.array_distinct(F.flatten(F.transform("full", each)))
    slots = F.transform(
        F.filter(met, lambda x: _as_name(ic(x)).eqNullSafe(_as_name(dc(x))) & _as_name(ic(x)).isin("<num>", "<name>", "<unit>")),
        lambda x: F.struct(F.get("plain", x["i"]).alias("ip"), F.get("dp", x["d"]).alias("dp")),
    )
    key = ["row", "item_id", "band", "matched", "item_windows"]
    judged = checked.where(enough).select(*key, slots.alias("s"))
    # A slot agrees when the item's value there goes with the value it goes with most often.
    pairs = judged.select(*key, F.explode_outer("s").alias("x")).groupBy(*key, F.col("x.ip").alias("theirs"), F.col("x.dp").alias("mine")).agg(F.count("x").alias("n"))
    agreed = pairs.groupBy(*key, "theirs").agg(F.max("n").alias("best"), F.sum("n").alias("n")).groupBy(*key).agg(F.sum("best").alias("slots_consistent"), F.sum("n").alias("slots"))
    best = F.max(F.struct(*MEASURES)).alias("m")
    found = agreed.where(F.col("slots_consistent") >= consistency * F.col("slots")).groupBy("row", "item_id").agg(best)
    return found.select("row", "item_id", "m.*").unionByName(whole)


def _known_windows(templates: DataFrame) -> DataFrame:
    """``(width, hash, template, item_at)`` of the telling windows of ``templates(template, canon, width)``."""
    ordinary = F.filter(F.slice("canon", F.col("at") + 1, F.col("width")), lambda w: ~w.isin(*[k for k, _ in _KINDS]))
    tokens = templates.select("template", "width", "canon", F.transform("canon", _as_word).alias("words"), F.transform("canon", _as_name).alias("names"))
    at = _windows(tokens.withColumnRenamed("width", "w"), ["template", "canon"], F.array("w"))
    return at.where(F.size(ordinary) >= LEAST_WORDS).select("width", "hash", "template", F.col("at").alias("item_at")).distinct()


def _whole_documents(docs: DataFrame, items: DataFrame) -> DataFrame:
    """Documents that are an item of ``items(item_id, plain)`` word by word; an item is one window."""
    few = saved(items.select("item_id", F.xxhash64("plain").alias("whole")), "short")
    one = [F.lit(n).cast("long").alias(c) for c, n in zip(MEASURES, (1, 1, 0, 0), strict=True)]
    if few.isEmpty():
        return docs.sparkSession.createDataFrame([], "row long, item_id long, matched long, item_windows long, slots long, slots_consistent long")
    words = F.filter(F.split(F.lower("text"), r"[^\p{L}\p{N}]+"), lambda w: w != "")
    return docs.select(text_key().alias("row"), F.xxhash64(words).alias("whole")).join(_small(few), "whole").select("row", "item_id", *one).distinct()
