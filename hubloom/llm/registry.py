"""Queries of the corpus operators over the given tables, and their SQL where it can say the same."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hubloom.llm.bpe import bpe_documents
from hubloom.llm.common import sha256_hex, table, texts
from hubloom.llm.decontamination import contaminated
from hubloom.llm.katz import katz_scores
from hubloom.llm.line_templates import drop_recurring_lines
from hubloom.llm.quality import resample
from hubloom.llm.runindex import remove_repeats
from hubloom.llm.simhash import simhash_components
from hubloom.llm.syncmers import syncmer_fingerprints
from hubloom.llm.token_counts import token_counts
from hubloom.llm.warc import archive_and_read


def op1_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = public_tokenizers.path("byte_bpe_multi_50k.tiktoken")
    coded = bpe_documents(texts(table(spark, sf_dir, "documents")), path, public_tokenizers.PATTERN)
    return coded.select("doc_id", "n_tokens", sha256_hex(F.col("ids")).alias("ids_sha256"), sha256_hex(F.col("decoded")).alias("decoded_sha256"))


def op2_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    read = archive_and_read(table(spark, sf_dir, "pages"))
    return read.select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


def op3_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The documents that importance resampling keeps."""
    kept = resample(texts(table(spark, sf_dir, "documents")), table(spark, sf_dir, "labels"))
    return kept.select("doc_id", F.lit(True).alias("kept"), "log_ratio", "log_weight", F.col("key").alias("gumbel_key"))


def op4_run_index(spark: SparkSession, sf_dir: str) -> DataFrame:
    cut = remove_repeats(texts(table(spark, sf_dir, "documents")), length=50)
    return cut.select("doc_id", "n_bytes", "n_removed", "n_spans", sha256_hex(F.col("kept")).alias("kept_sha256"))


def op5_katz(spark: SparkSession, sf_dir: str) -> DataFrame:
    return katz_scores(texts(table(spark, sf_dir, "documents")))


def op6_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    grouped = simhash_components(texts(table(spark, sf_dir, "documents")), shingle=4, lanes=1, radius=4)
    return grouped.select("doc_id", F.lower(F.hex("fp")).alias("fingerprint"), "component_id")


def op7_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts(texts(table(spark, sf_dir, "documents")), public_tokenizers.path("word_bpe_49k.json"), limit=2048)


def op8_line_templates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return drop_recurring_lines(texts(table(spark, sf_dir, "documents"))).select("doc_id", "n_lines", "n_dropped", "text")


def op10_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    items = table(spark, sf_dir, "benchmark").select(F.col("item_id").cast("long").alias("item_id"), F.coalesce("text", F.lit("")).alias("text"))
    return contaminated(texts(table(spark, sf_dir, "documents")), items)


def op9_syncmers(spark: SparkSession, sf_dir: str) -> DataFrame:
    return syncmer_fingerprints(texts(table(spark, sf_dir, "documents")))


QUERIES = {
    "op1_byte_bpe": op1_byte_bpe,
    "op2_warc": op2_warc,
    "op3_quality": op3_quality,
    "op4_run_index": op4_run_index,
    "op5_katz": op5_katz,
    "op6_simhash": op6_simhash,
    "op7_token_counts": op7_token_counts,
    "op8_line_templates": op8_line_templates,
    "op9_syncmers": op9_syncmers,
    "op10_decontamination": op10_decontamination,
}

OP2_SQL = """
WITH p AS (SELECT page_id, COALESCE(html, '') AS h, sha1(COALESCE(html, '')) AS hx FROM pages),
d AS (SELECT page_id, CAST(strlen(h) AS BIGINT) AS payload_bytes,
             array_to_string(list_transform(range(0, 32), lambda i: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567',
               1 + CAST((CAST('0x' || substr(hx, 1 + 5 * CAST(i // 4 AS INTEGER), 5) AS BIGINT) >> CAST(15 - 5 * (i % 4) AS INTEGER)) & 31 AS INTEGER), 1)), '') AS payload_digest
      FROM p)
SELECT page_id, payload_bytes, payload_digest, CASE WHEN page_id = first THEN 'response' ELSE 'revisit' END AS record_type,
       CASE WHEN page_id = first THEN NULL ELSE first END AS refers_to
FROM (SELECT *, MIN(page_id) OVER (PARTITION BY payload_digest) AS first FROM d)
"""

def _splits(rounds: int) -> str:
    """Common table expressions that split the branches of ``v0(leaf, tokens, w, branch)``."""
    tops = """
fields{r} AS (SELECT branch, w, UNNEST(tokens) AS token, generate_subscripts(tokens, 1) AS place FROM v{r}),
votes{r} AS (SELECT branch, place, token, SUM(w) AS w FROM fields{r} GROUP BY 1, 2, 3),
tops{r} AS (SELECT branch, place, token, w, SUM(w) OVER (PARTITION BY branch, place) AS total, ROW_NUMBER() OVER (PARTITION BY branch, place ORDER BY w DESC, token DESC) AS rn FROM votes{r}),"""
    cut = """
cut{r} AS (SELECT branch, place, token FROM (SELECT *, ROW_NUMBER() OVER (PARTITION BY branch ORDER BY w DESC, place) AS k FROM tops{r} WHERE rn = 1 AND w >= 0.25 * total AND w < 0.6 * total) WHERE k = 1),
v{n} AS (SELECT v.leaf, v.tokens, v.w, CASE WHEN c.branch IS NULL THEN v.branch ELSE list_concat(v.branch, ['{r}', CAST(v.tokens[c.place] = c.token AS VARCHAR)]) END AS branch FROM v{r} v LEFT JOIN cut{r} c USING (branch)),"""
    return "".join(tops.format(r=r) + (cut.format(r=r, n=r + 1) if r < rounds else "") for r in range(rounds + 1))


OP8_SQL = f"""
WITH raw AS (SELECT doc_id, COALESCE(text, '') AS text, string_split(COALESCE(text, ''), chr(10)) AS ls, string_split(trim(COALESCE(text, ''), ' ' || chr(9) || chr(13) || chr(10)), chr(10)) AS body FROM documents),
lines AS (SELECT doc_id, text, body[1] AS head, body[-1] AS tail, UNNEST(ls) AS line, generate_subscripts(ls, 1) AS pos FROM raw),
cut AS (SELECT doc_id, text, head, tail, pos, list_transform(list_filter(regexp_split_to_array(line, '[ \\t\\r\\f\\v]+'), lambda w: w <> ''),
               lambda w: CASE WHEN regexp_matches(w, '[0-9]') THEN '<*>' ELSE w END) AS tokens FROM lines),
sigs AS (SELECT doc_id, text, head, tail, pos, tokens, len(tokens) AS n, list_concat([CAST(len(tokens) AS VARCHAR)], tokens[1:3]) AS leaf FROM cut WHERE len(tokens) >= 4),
counted AS (SELECT leaf, tokens, COUNT(DISTINCT doc_id) AS docs, COUNT(*) AS w FROM sigs GROUP BY 1, 2),
busy AS (SELECT leaf FROM counted GROUP BY leaf HAVING SUM(docs) >= 10 AND COUNT(*) > 1),
v0 AS (SELECT leaf, tokens, w, leaf AS branch FROM counted WHERE leaf IN (SELECT leaf FROM busy)),{_splits(3)}
shape AS (SELECT branch, list(CASE WHEN w >= 0.6 * total THEN token END ORDER BY place) AS shape FROM tops3 WHERE rn = 1 GROUP BY branch),
agreed AS (SELECT v.leaf, v.tokens, v.branch FROM v3 v JOIN shape s USING (branch)
           WHERE len(list_filter(range(4, len(v.tokens) + 1), lambda i: v.tokens[i] = s.shape[i])) >= 0.75 * (len(v.tokens) - 3)),
named AS (SELECT g.*, CASE WHEN a.leaf IS NULL THEN list_concat(['line'], g.tokens) ELSE list_concat(['leaf'], a.branch) END AS template
          FROM sigs g LEFT JOIN agreed a ON a.leaf = g.leaf AND a.tokens = g.tokens),
often AS (SELECT template, MIN((doc_id, pos)) AS first FROM named GROUP BY template
          HAVING COUNT(DISTINCT text) >= 10 OR (MIN(n) >= 8 AND COUNT(DISTINCT text) >= 3 AND MIN(head) <> MAX(head) AND MIN(tail) <> MAX(tail))),
gone AS (SELECT DISTINCT n.doc_id, n.pos FROM named n JOIN often o USING (template) WHERE (n.doc_id, n.pos) <> o.first)
SELECT r.doc_id, CAST(len(r.ls) AS BIGINT) AS n_lines, COUNT(g.pos) AS n_dropped,
       COALESCE(string_agg(l.line, chr(10) ORDER BY l.pos) FILTER (WHERE g.pos IS NULL), '') AS text
FROM raw r JOIN lines l USING (doc_id) LEFT JOIN gone g ON g.doc_id = l.doc_id AND g.pos = l.pos GROUP BY r.doc_id, r.ls
"""

#: Tokenizers, XXH64, regular expressions that look behind, and fitted models are beyond SQL; tests hold those queries against brute force.
SQL: dict[str, str] = {"op2_warc": OP2_SQL, "op8_line_templates": OP8_SQL}
