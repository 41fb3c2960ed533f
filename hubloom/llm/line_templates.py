"""Line deduplication with a log-template tree, in DataFrame functions only.

Each line walks a tree of fixed depth: its token count, then its leading tokens,
with tokens that hold a digit standing for a variable field.  In a leaf that
several documents reach, the fields that vary are found by position: a position
where one token has most of the weight is constant, others are wildcards.  A leaf
of several templates is split first, ``SPLITS`` times, at the position whose
heaviest token has a fair share of the weight, and not most of it.  Lines that
agree with enough of the constants after the leading tokens share a template; the
others are templates of their own.

A template that recurs is dropped wherever it stands, but for its first place
(least document id, then line).  It recurs when ``min_documents`` different texts
have it; a template of ``LONG_TOKENS`` tokens already when ``LONG_DOCUMENTS`` texts
have it, of which some differ in their first line and some in their last.  So
copies of one text don't make its lines recur, nor do a few near copies: those
are for near-duplicate removal.

Lines of fewer than ``min_tokens`` tokens are never dropped.  Null texts are
empty; a row's identity is its id with its text, so repeated rows lose the same
lines; null ids sort first; an empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from hubloom.llm.common import saved

DEPTH = 3
MIN_TOKENS = 4
MIN_DOCUMENTS = 10
#: Lines of so many tokens recur in so many texts.
LONG_TOKENS, LONG_DOCUMENTS = 8, 3
#: Splits of a leaf, and the share of a position's weight from which a token is split off.
SPLITS, FAIR_SHARE = 3, 0.25
#: Weight of one token at a position that makes it constant.
CONSTANT_SHARE = 0.6
#: Share of a line's tokens after the leading ones that must be its template's constants.
AGREEMENT = 0.75
#: Rows of leaves, templates or recurring lines (at most 48 bytes each) up to which a join broadcasts them.
BROADCAST_ROWS = 500_000


def _row_key() -> Column:
    return F.xxhash64(F.coalesce(F.col("doc_id"), F.lit(-(2**63))), F.col("text"))


def _lines(docs: DataFrame, min_tokens: int) -> DataFrame:
    """``(row, doc_id, words, head, tail, pos, tokens, leaf, sig)`` of the lines long enough; digits make a token a field.

    ``words``, ``head`` and ``tail`` stand for the text, its first and its last line.
    """
    body = F.trim("text", F.lit(" \t\r\n"))
    edge = lambda at: F.xxhash64(F.substring_index(body, "\n", at))
    known = docs.select(_row_key().alias("row"), "doc_id", F.xxhash64("text").alias("words"), edge(1).alias("head"), edge(-1).alias("tail"), "text")
    split = known.select("row", "doc_id", "words", "head", "tail", F.posexplode(F.split("text", "\n")).alias("pos", "line"))
    # Every token that holds a digit becomes the field mark; most lines have none.
    marked = F.regexp_replace("line", r"(?<!\S)(?=\S*\d)\S+", "<*>")
    masked = F.when(F.col("line").rlike(r"\d"), marked).otherwise(F.col("line"))
    words = F.filter(F.split(masked, r"[ \t\r\f\x0B]+"), lambda w: w != "")
    cut = split.select("row", "doc_id", "words", "head", "tail", "pos", words.alias("tokens")).where(F.size("tokens") >= min_tokens)
    n = F.size("tokens")
    return cut.select(
        "row", "doc_id", "words", "head", "tail", "pos", "tokens", n.alias("n"), F.xxhash64(n, F.slice("tokens", 1, DEPTH)).alias("leaf"), F.xxhash64(n, F.col("tokens")).alias("sig")
    )


def _small(df: DataFrame) -> DataFrame:
    """A saved table with a broadcast hint where it has few enough rows (of a few numbers); else the join shuffles."""
    return F.broadcast(df) if df.count() <= BROADCAST_ROWS else df


def leaf_templates(docs: DataFrame, narrow: DataFrame, min_documents: int, min_tokens: int) -> DataFrame:
    """``(leaf, sig, template)`` of the lines (``narrow``: without their tokens) that share a leaf's generalised template."""
    counted = narrow.select("leaf", "sig", "row").distinct().groupBy("leaf", "sig").agg(F.count("*").alias("docs"))
    busy = saved(
        counted.groupBy("leaf").agg(F.sum("docs").alias("docs"), F.count("*").alias("sigs")).where((F.col("docs") >= min_documents) & (F.col("sigs") > 1)).select("leaf"),
        "leaves",
    )
    # Tokens of the distinct lines in leaves with branches, read from one text each; weights are lines, pre-aggregated.
    place = F.struct("row", "pos").alias("place")
    read = saved(narrow.join(_small(busy), "leaf", "left_semi").groupBy("leaf", "sig").agg(F.min(place).alias("place"), F.count("*").alias("w")).select("leaf", "sig", "w", "place.*"), "places")
    some = docs.join(_small(read.select("row").distinct()), _row_key() == F.col("row"), "left_semi")
    variants = saved(
        _lines(some, min_tokens)
        .select("row", "pos", "tokens")
        .join(_small(read), ["row", "pos"])
        .groupBy("leaf", "sig", "w")
        .agg(F.first("tokens").alias("tokens"))
        .select("leaf", F.col("leaf").alias("branch"), "sig", "tokens", "w"),
        "variants",
    )
    for _ in range(SPLITS):
        heavy, every = F.col("top.w"), F.col("every")
        uneven = _tops(variants).where((heavy >= FAIR_SHARE * every) & (heavy < CONSTANT_SHARE * every))
        cuts = saved(uneven.groupBy("branch").agg(F.max(F.struct(heavy.alias("w"), (-F.col("at")).alias("before"), F.col("top.token").alias("token"))).alias("cut")), "cuts")
        if cuts.isEmpty():
            break
        same = F.get("tokens", -F.col("cut.before")) == F.col("cut.token")
        branch = F.when(F.col("cut").isNull(), F.col("branch")).otherwise(F.xxhash64("branch", F.col("cut.before"), same))
        variants = saved(variants.join(_small(cuts), "branch", "left").select("leaf", branch.alias("branch"), "sig", "tokens", "w"), "variants")
    constant = F.when(F.col("top.w") >= CONSTANT_SHARE * F.col("every"), F.col("top.token"))
    shape = _tops(variants).groupBy("branch").agg(F.transform(F.sort_array(F.collect_list(F.struct("at", constant.alias("token")))), lambda s: s["token"]).alias("shape"))
    shape = saved(shape, "shapes")
    rest = lambda c: F.slice(c, DEPTH + 1, F.size("tokens"))
    agree = F.size(F.filter(F.zip_with(rest("tokens"), rest("shape"), lambda a, b: a == b), lambda x: x))
    return (
        variants.join(_small(shape), "branch")
        .where(agree >= AGREEMENT * (F.size("tokens") - DEPTH))
        .select("leaf", "sig", F.xxhash64(F.lit("leaf"), F.col("branch")).alias("template"))
    )


def _tops(variants: DataFrame) -> DataFrame:
    """``(branch, at, top struct<w,token>, every)``: the heaviest token of each position of a branch, and the weight of all."""
    fields = variants.select("branch", "w", F.posexplode("tokens").alias("at", "token"))
    votes = fields.groupBy("branch", "at", "token").agg(F.sum("w").alias("w"))
    return votes.groupBy("branch", "at").agg(F.max(F.struct("w", "token")).alias("top"), F.sum("w").alias("every"))


def recurring_lines(docs: DataFrame, min_documents: int = MIN_DOCUMENTS, min_tokens: int = MIN_TOKENS) -> DataFrame:
    """``(row, dropped array<int>)``: the line numbers that each row of ``docs(doc_id, text)`` loses."""
    lines = _lines(docs, min_tokens)
    narrow = saved(lines.select("row", "doc_id", "words", "head", "tail", "pos", "n", "leaf", "sig"), "lines")  # a few numbers a line
    shared = saved(leaf_templates(docs, narrow, min_documents, min_tokens), "templates")
    named = narrow.join(_small(shared), ["leaf", "sig"], "left")
    placed = named.select("row", "doc_id", "words", "head", "tail", "pos", "n", F.coalesce("template", "sig").alias("template"))
    place = F.struct(F.coalesce("doc_id", F.lit(-(2**63))).alias("d"), F.col("row").alias("r"), F.col("pos").alias("p"))
    # A row a (template, text) before the count, so a template in all documents is spread over tasks.
    by_text = placed.groupBy("template", "words").agg(F.min(place).alias("first"), F.min("head").alias("head"), F.min("tail").alias("tail"), F.min("n").alias("n"))
    unlike = (F.min("head") != F.max("head")) & (F.min("tail") != F.max("tail"))
    counts = by_text.groupBy("template").agg(F.count("*").alias("texts"), F.min("first").alias("first"), (unlike & (F.min("n") >= LONG_TOKENS)).alias("long"))
    often = saved(counts.where((F.col("texts") >= min_documents) | (F.col("long") & (F.col("texts") >= LONG_DOCUMENTS))).select("template", "first"), "often")
    gone = placed.join(_small(often), "template").where(~((F.col("row") == F.col("first.r")) & (F.col("pos") == F.col("first.p"))))
    return gone.groupBy("row").agg(F.collect_set("pos").alias("dropped"))


def drop_recurring_lines(docs: DataFrame, min_documents: int = MIN_DOCUMENTS, min_tokens: int = MIN_TOKENS) -> DataFrame:
    """``(doc_id, text, n_lines, n_dropped, row)``: every row of ``docs(doc_id, text)`` without its recurring lines."""
    gone = saved(recurring_lines(docs, min_documents, min_tokens), "dropped")
    joined = docs.withColumn("row", _row_key()).join(gone.hint("merge"), "row", "left")  # grows with the documents: never broadcast
    parts = F.split("text", "\n")
    kept = F.when(F.col("dropped").isNull(), F.col("text")).otherwise(
        F.concat_ws("\n", F.filter(parts, lambda _, i: ~F.array_contains(F.col("dropped"), i)))
    )
    return joined.select(
        "doc_id",
        kept.alias("text"),
        F.size(parts).cast("long").alias("n_lines"),
        F.when(F.col("dropped").isNull(), 0).otherwise(F.size("dropped")).cast("long").alias("n_dropped"),
        "row",
    )
