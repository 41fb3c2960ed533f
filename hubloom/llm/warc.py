"""WARC archives with a two-level capture index.

Writing: a record is text (headers and an HTML payload in UTF-8), so Spark's
text writer with the record terminator as its line separator lays down archive
files, under the usual commit protocol.  Records with equal payloads: the one of
the smallest page id is a response, the others revisit it and hold no payload.

Index: every archive is streamed once; capture lines are sorted by reversed-host
URL key and packed into compressed blocks, and a sparse directory keeps the
first key of each block.  A look-up finds its block by binary search in the
directory, its line by binary search in the block, and reads just that byte
range of the archive.

Null html is an empty payload.  Rows with a null page id are written too: they
revisit an equal payload that has an id and else are responses.  Rows that
repeat the smallest page id are responses as it is.  A null url gets a key of
its own.
"""

from __future__ import annotations

import base64
import hashlib
import zlib
from bisect import bisect_left, bisect_right
from collections.abc import Iterator

import pandas as pd
import pyarrow.fs as pafs
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from hubloom.llm.common import saved, scratch_dir

END = "\r\n\r\n"
VERSION = "WARC/1.1"
#: Capture lines of a block, and blocks under one entry of the top directory.
BLOCK_LINES = 512
FAN_OUT = 256
#: Entries of the top directory that may be broadcast (about 100 bytes each).
TOP_LIMIT = 2_000_000
#: Ranges of one archive that lie this near are read together.
GAP_BYTES = 1 << 16
READ_BYTES = 8 << 20


def base32_sha1(payload: Column) -> Column:
    """Upper-case base32 of the SHA-1 of a string's bytes, from built-in functions."""
    alphabet = "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567"
    digest = F.sha1(payload.cast("binary"))
    chars = []
    for part in range(8):  # five hex digits are four base32 digits
        value = F.conv(F.substring(digest, 5 * part + 1, 5), 16, 10).cast("int")
        for shift in (15, 10, 5, 0):
            chars.append(F.substring(F.lit(alphabet), F.shiftright(value, shift).bitwiseAND(31) + 1, F.lit(1)))
    return F.concat(*chars)


def url_key(url: Column) -> Column:
    """``org,example,www)/path?query`` in lower-case host order, without fragment, port and user."""
    pattern = r"(?i)^[a-z][a-z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:]*)(?::\d*)?([^#]*)"
    host = F.lower(F.regexp_extract(url, pattern, 1))
    turned = F.concat_ws(",", F.reverse(F.split(host, r"\.")))
    clean = F.regexp_replace(F.concat(turned, F.lit(")"), F.regexp_extract(url, pattern, 2)), r"[\x00-\x20\x7f]", "%20")
    return F.when(url.isNull() | (host == ""), F.concat(F.lit("-)"), F.regexp_replace(F.coalesce(url, F.lit("")), r"[\x00-\x20\x7f]", "%20"))).otherwise(clean)


def write_warc(pages: DataFrame, path: str, date: str = "2024-01-01T00:00:00Z") -> None:
    """One record a row of ``pages(page_id, url, html)``, as archive files under ``path``."""
    base = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), F.coalesce(F.col("html").cast("string"), F.lit("")).alias("html"))
    base = base.withColumn("digest", base32_sha1(F.col("html")))
    # Only digests that occur more than once need a look-up; a row a digest, pre-aggregated map-side.
    shared = saved(
        base.groupBy("digest").agg(F.min("page_id").alias("first"), F.count("*").alias("n")).where("n > 1 and first is not null").select("digest", "first"),
        "dups",
    )
    joined = base.join(shared, "digest", "left")
    revisit = F.col("first").isNotNull() & ~F.col("first").eqNullSafe(F.col("page_id"))
    record_id = lambda c: F.concat(F.lit("<urn:x-page:"), F.coalesce(c.cast("string"), F.lit("none")), F.lit(">"))
    size = F.octet_length("html").cast("string")
    http = F.concat(F.lit("HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: "), size, F.lit(END))
    block = F.when(revisit, http).otherwise(F.concat(http, F.col("html")))
    target = F.regexp_replace(F.coalesce("url", F.concat(F.lit("urn:x-page:"), F.coalesce(F.col("page_id").cast("string"), F.lit("none")))), r"[\x00-\x20\x7f]", "%20")
    head = F.concat_ws(
        "\r\n",
        F.lit(VERSION),
        F.concat(F.lit("WARC-Type: "), F.when(revisit, "revisit").otherwise("response")),
        F.concat(F.lit("WARC-Target-URI: "), target),
        F.lit(f"WARC-Date: {date}"),
        F.concat(F.lit("WARC-Record-ID: "), record_id(F.col("page_id"))),
        F.concat(F.lit("WARC-Payload-Digest: sha1:"), F.col("digest")),
        F.when(revisit, F.concat(F.lit("WARC-Refers-To: "), record_id(F.col("first")))),
        F.when(revisit, F.lit("WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest")),
        F.concat(F.lit("X-URL-Key: "), url_key(F.col("url"))),
        F.lit("Content-Type: application/http; msgtype=response"),
        F.concat(F.lit("Content-Length: "), F.octet_length(block).cast("string")),
    )
    joined.select(F.concat(head, F.lit(END), block).alias("value")).write.option("lineSep", END).option("compression", "none").text(path)


# -- reading -------------------------------------------------------------------
def _headers(raw: bytes) -> dict[str, str]:
    lines = raw.decode("utf-8", "replace").split("\r\n")
    return {k.lower(): v.strip(" \t") for k, _, v in (x.partition(":") for x in lines[1:])} | {"": lines[0]}


def parse_record(raw: bytes) -> tuple[dict[str, str], dict[str, str], bytes]:
    """WARC headers, HTTP headers and payload of one record."""
    head, _, rest = raw.partition(b"\r\n\r\n")
    headers = _headers(head)
    block = rest[: int(headers["content-length"])]
    http, _, payload = block.partition(b"\r\n\r\n")
    return headers, _headers(http), payload


def stream_records(path: str) -> Iterator[tuple[int, int, dict[str, str]]]:
    """Offset, length and WARC headers of each record of an archive, in bounded memory."""
    fs, inner = pafs.FileSystem.from_uri(path)
    with fs.open_input_file(inner) as f:
        end, at, base, held = f.size(), 0, 0, b""
        while at < end:
            while (cut := held.find(b"\r\n\r\n", at - base)) < 0:
                more = f.read(READ_BYTES)
                if not more:
                    return
                held, base = held[at - base :] + more, at
            headers = _headers(held[at - base : cut])
            length = cut + 4 - (at - base) + int(headers["content-length"])
            yield at, length, headers
            at += length + len(END)
            if at - base > len(held):  # the block goes on beyond what is held
                f.seek(at)
                held, base = b"", at
            elif at - base > READ_BYTES:
                held, base = held[at - base :], at


def _page_of(record_id: str) -> int | None:
    inner = record_id.removeprefix("<urn:x-page:").removesuffix(">")
    return None if inner in ("", "none") else int(inner)


def archive_files(spark: SparkSession, path: str) -> DataFrame:
    """Names and sizes only: the listing reads no content."""
    return spark.read.format("binaryFile").load(path).select("path", "length")


def build_index(spark: SparkSession, archives: str, index: str) -> None:
    """Capture lines of all archives, sorted by URL key, as compressed blocks under ``index``."""
    files = archive_files(spark, archives)
    n = max(1, files.count())

    def capture(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            for path in pdf["path"]:
                rows = []
                for offset, length, h in stream_records(path):
                    page = _page_of(h["warc-record-id"])
                    stamp = "".join(c for c in h["warc-date"] if c.isdigit())
                    key = f"{h['x-url-key']} {stamp} {'' if page is None else page:0>20}"
                    rows.append((key, path, offset, length))
                    if len(rows) >= 10_000:
                        yield pd.DataFrame(rows, columns=["key", "path", "offset", "length"])
                        rows = []
                yield pd.DataFrame(rows, columns=["key", "path", "offset", "length"])

    # One task a few files; the listing itself is tiny.
    lines = files.repartition(min(n, 10_000), "path").mapInPandas(capture, "key string, path string, offset long, length long")
    lines = saved(lines, "captures")
    parts = max(1, min(10_000, lines.count() // (64 * BLOCK_LINES) + 1))

    def pack(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held: list[tuple[str, str]] = []

        def block(rows: list[tuple[str, str]]) -> pd.DataFrame:
            return pd.DataFrame({"first_key": [rows[0][0]], "n": [len(rows)], "block": [zlib.compress("\n".join(x for _, x in rows).encode())]})

        for pdf in batches:
            held += [(k, f"{k}\t{o}\t{n}\t{p}") for k, p, o, n in zip(pdf["key"], pdf["path"], pdf["offset"], pdf["length"], strict=True)]
            while len(held) >= BLOCK_LINES:
                yield block(held[:BLOCK_LINES])
                held = held[BLOCK_LINES:]
        if held:
            yield block(held)

    ordered = lines.repartitionByRange(parts, "key").sortWithinPartitions("key", "path", "offset")
    ordered.mapInPandas(pack, "first_key string, n int, block binary").write.parquet(index)


class CaptureIndex:
    """Look-ups by URL key in a packed index."""

    def __init__(self, spark: SparkSession, index: str):
        self.spark = spark
        self.blocks = spark.read.parquet(index)
        directory = self.blocks.select("first_key")  # sparse: one key a block
        n = directory.count()
        step = max(1, -(-n // FAN_OUT)) if n else 1
        top = min(step, TOP_LIMIT)
        if step > TOP_LIMIT:
            raise ValueError("the top directory is over its size limit: raise FAN_OUT")
        # Evenly spread keys of the directory, found by a sort of first keys only.
        cuts = directory.repartitionByRange(max(1, min(200, top)), "first_key").sortWithinPartitions("first_key")

        def sparse(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            seen = 0
            for pdf in batches:
                yield pdf.iloc[(-seen) % FAN_OUT :: FAN_OUT]
                seen += len(pdf)

        self.top = sorted(r[0] for r in cuts.mapInPandas(sparse, "first_key string").collect())  # n / FAN_OUT keys and one a partition

    def _group(self, keys: DataFrame, column: str) -> DataFrame:
        top = self.spark.sparkContext.broadcast(self.top)

        def find(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for pdf in batches:
                yield pdf.assign(region=[max(0, bisect_right(top.value, k) - 1) for k in pdf[column]])

        fields = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in keys.schema.fields)
        return keys.mapInPandas(find, f"{fields}, region int")

    def locate(self, keys: DataFrame) -> DataFrame:
        """``(key, path, offset, length)`` of the captures that ``keys(key string)`` ask for.

        Both sides meet by region of the top directory; a region's directory
        part (at most a few times FAN_OUT keys) is searched for the block, and
        each wanted block is unpacked once a task and searched for the line.
        """
        directory = self._group(self.blocks.select("first_key"), "first_key").groupBy("region").agg(F.sort_array(F.collect_list("first_key")).alias("firsts"))
        # A key below its region's first block belongs to the block before it.
        # Equal keys may go on over blocks, from the last one that starts below the key: that may be of an earlier region.
        top = self.spark.sparkContext.broadcast(self.top)

        def regions(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for pdf in batches:
                places = [sorted({max(0, bisect_left(top.value, k) - 1), max(0, bisect_right(top.value, k) - 1)}) for k in pdf["key"]]
                yield pdf.assign(region=places).explode("region").astype({"region": "int32"})

        wanted = keys.select("key").mapInPandas(regions, "key string, region int").join(directory, "region")

        def block_of(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for pdf in batches:
                rows = []
                for k, f in zip(pdf["key"], map(list, pdf["firsts"]), strict=True):
                    rows += [(k, x) for x in dict.fromkeys(f[max(0, bisect_left(f, k) - 1) : max(1, bisect_right(f, k))])]
                yield pd.DataFrame(rows, columns=["key", "first_key"])

        placed = wanted.mapInPandas(block_of, "key string, first_key string")
        asked = placed.groupBy("first_key").agg(F.collect_set("key").alias("keys"))  # keys name single captures: about BLOCK_LINES of them

        def read(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for pdf in batches:
                rows = []
                for keys, block in zip(pdf["keys"], pdf["block"], strict=True):
                    lines = zlib.decompress(block).decode().split("\n")
                    heads = [x.split("\t", 1)[0] for x in lines]
                    for key in keys:
                        i = bisect_right(heads, key) - 1
                        while i >= 0 and heads[i] == key:
                            k, offset, length, path = lines[i].split("\t", 3)
                            rows.append((k, path, int(offset), int(length)))
                            i -= 1
                yield pd.DataFrame(rows, columns=["key", "path", "offset", "length"])

        return asked.join(self.blocks, "first_key").mapInPandas(read, "key string, path string, offset long, length long")


def fetch(captures: DataFrame) -> DataFrame:
    """Range-read ``captures(path, offset, length)`` and parse them.

    Captures are dealt by archive region, so a task reads an archive's ranges in
    ascending order and joins near ones into one read.
    """

    def read(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        open_path, file = None, None
        for pdf in batches:
            rows = []
            ranges = list(zip(pdf["path"], pdf["offset"], pdf["length"], strict=True))
            at = 0
            while at < len(ranges):
                path, start, size = ranges[at]
                stop, to = start + size, at + 1
                while to < len(ranges) and ranges[to][0] == path and 0 <= ranges[to][1] - stop <= GAP_BYTES and ranges[to][1] + ranges[to][2] - start <= READ_BYTES:
                    stop, to = ranges[to][1] + ranges[to][2], to + 1
                if path != open_path:
                    fs, inner = pafs.FileSystem.from_uri(path)
                    open_path, file = path, fs.open_input_file(inner)
                raw = file.read_at(stop - start, start)
                for _, offset, length in ranges[at:to]:
                    h, http, payload = parse_record(raw[offset - start : offset - start + length])
                    digest = h["warc-payload-digest"].removeprefix("sha1:")
                    revisit = h["warc-type"] == "revisit"
                    if not revisit and base64.b32encode(hashlib.sha1(payload).digest()).decode() != digest:
                        raise ValueError(f"payload of {h['warc-record-id']} does not match its digest")
                    rows.append((_page_of(h["warc-record-id"]), h["warc-target-uri"], int(http["content-length"]), digest, h["warc-type"], _page_of(h["warc-refers-to"]) if revisit else None, None if revisit else payload.decode()))
                at = to
            out = pd.DataFrame(rows, columns=["page_id", "url", "payload_bytes", "payload_digest", "record_type", "refers_to", "payload"])
            yield out.astype({"page_id": "Int64", "refers_to": "Int64"})

    dealt = captures.withColumn("region", F.expr("offset div 67108864"))
    return (
        dealt.repartition("path", "region")
        .sortWithinPartitions("path", "offset")
        .select("path", "offset", "length")
        .mapInPandas(read, "page_id long, url string, payload_bytes long, payload_digest string, record_type string, refers_to long, payload string")
    )


def archive_and_read(pages: DataFrame, label: str = "warc") -> DataFrame:
    """Write ``pages`` to archives, index them, and read every capture back through the index."""
    spark = pages.sparkSession
    archives, index = scratch_dir(spark, label), scratch_dir(spark, label + "-index")
    write_warc(pages, archives)
    build_index(spark, archives, index)
    stamp = "20240101000000"
    page = F.col("page_id").cast("long").cast("string")
    keys = pages.select(
        F.concat_ws(" ", url_key(F.col("url").cast("string")), F.lit(stamp), F.when(page.isNull(), F.lit("0" * 20)).otherwise(F.lpad(page, 20, "0"))).alias("key")
    ).distinct()
    return fetch(CaptureIndex(spark, index).locate(keys))
