"""Web archives (WARC) and their merged capture index.

Writing: payloads are digested, the smallest page_id of equal payloads is the response and the
others are revisits that refer to it.  Each record is one string whose terminator is the
format's own (two line ends), so Spark's text writer produces the archive files: any store
Spark can write, its commit protocol, gzip.

Reading: archives are parsed by content length; payloads are digested again and must match.
Each archive gives a run of captures sorted by URL key and time.  Runs are cut at common key
bounds (a range exchange) and each range's slices are merged by a loser tree, so the ranges
together are one globally ordered capture history.

Null html is an empty payload, a null URL an empty key.  A null page_id is never referred to
(it is a revisit if an equal payload has an id, else a response); rows that repeat the smallest
page_id are all responses.  A table without rows gives an empty index.  Extra columns are ignored.
"""

from __future__ import annotations

import base64
import hashlib
import re
import uuid
import zlib
from collections.abc import Iterator
from urllib.parse import urlsplit

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import cut, shared_dir, table

#: Fixed values of the format.
END = "\r\n\r\n"
HTTP_HEAD = "HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n\r\n"
PROFILE = "http://netpreserve.org/warc/1.0/revisit/identical-payload-digest"


def base32(sha1_hex: Column) -> Column:
    """Base-32 (A-Z2-7) of a 40-digit hexadecimal digest: four groups of 40 bits."""
    groups = [F.lpad(F.conv(F.substring(sha1_hex, 10 * i + 1, 10), 16, 32), 8, "0") for i in range(4)]
    return F.translate(F.concat(*groups), "0123456789ABCDEFGHIJKLMNOPQRSTUV", "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567")


def classified(pages: DataFrame, least: int = 0) -> DataFrame:
    """page_id, url, payload, n, digest and refers_to (null for responses).  Payloads of fewer
    than `least` bytes are always responses."""
    p = pages.select("page_id", F.coalesce("url", F.lit("")).alias("url"), F.coalesce("html", F.lit("")).alias("payload"))
    p = p.withColumn("n", F.octet_length("payload").cast("long")).withColumn("digest", base32(F.sha1(F.col("payload").cast("binary"))))
    first = p.filter(F.col("n") >= least).groupBy("digest").agg(F.min("page_id").alias("first"))
    other = (F.col("n") >= least) & F.col("first").isNotNull() & ~F.col("page_id").eqNullSafe(F.col("first"))
    return p.join(first, "digest", "left").withColumn("refers_to", F.when(other, F.col("first"))).drop("first")


def records(pages: DataFrame, least: int = 0) -> DataFrame:
    """One `record` string for each page, without its terminator."""
    c = classified(pages, least)
    revisit = F.col("refers_to").isNotNull()
    name = lambda x: F.concat(F.lit("<urn:page:"), F.coalesce(x.cast("string"), F.lit("none")), F.lit(">"))
    line = lambda key, value: F.concat(F.lit(f"{key}: "), value, F.lit("\r\n"))
    date = F.date_format(F.timestamp_seconds(F.lit(1_704_067_200) + F.pmod(F.coalesce("page_id", F.lit(0)), F.lit(1 << 30))), "yyyy-MM-dd'T'HH:mm:ss'Z'")
    head = F.concat(
        F.lit("WARC/1.0\r\n"),
        line("WARC-Type", F.when(revisit, "revisit").otherwise("response")),
        line("WARC-Record-ID", name(F.col("page_id"))),
        line("WARC-Date", date),
        line("WARC-Target-URI", F.translate("url", "\r\n", "")),
        line("WARC-Payload-Digest", F.concat(F.lit("sha1:"), F.col("digest"))),
        F.when(revisit, F.concat(line("WARC-Profile", F.lit(PROFILE)), line("WARC-Refers-To", name(F.col("refers_to"))), line("X-Payload-Length", F.col("n").cast("string")))).otherwise(F.lit("")),
        F.lit("Content-Type: application/http; msgtype=response\r\n"),
        line("Content-Length", (F.lit(len(HTTP_HEAD)) + F.when(revisit, F.lit(0)).otherwise(F.col("n"))).cast("string")),
        F.lit("\r\n"),
    )
    return c.select(F.concat(head, F.lit(HTTP_HEAD), F.when(revisit, F.lit("")).otherwise(F.col("payload"))).alias("record"))


def write_archives(pages: DataFrame, path: str, least: int = 0) -> None:
    records(pages, least).write.option("lineSep", END).option("compression", "gzip").text(path)


def parse(content: bytes) -> Iterator[tuple[int, int, dict[str, str], memoryview]]:
    """(offset, length, header, block) of each record."""
    at, whole = 0, memoryview(content)
    while at < len(content):
        stop = content.index(b"\r\n\r\n", at) + 4
        lines = content[at : stop - 4].decode().split("\r\n")
        if not lines[0].startswith("WARC/"):
            raise ValueError(f"no record at {at}")
        header = dict(x.split(": ", 1) if ": " in x else (x.rstrip(":"), "") for x in lines[1:])
        end = stop + int(header["Content-Length"])
        if content[end : end + 4] != b"\r\n\r\n":
            raise ValueError(f"the record at {at} doesn't end where its length says")
        yield at, end + 4 - at, header, whole[stop:end]
        at = end + 4


def url_key(url: str) -> str:
    """Host labels from the right, then the path: captures of a site stand together."""
    try:
        u = urlsplit(url.strip().lower())
        host = ",".join(reversed((u.hostname or "").split(".")))
        port = f":{u.port}" if u.port and u.port not in (80, 443) else ""
    except ValueError:  # not a URL; its own text is its key
        return url.lower()
    host = re.sub(r",www$", "", host)
    return f"{host}{port}){u.path or '/'}" + (f"?{'&'.join(sorted(u.query.split('&')))}" if u.query else "")


CAPTURE = "run string, seq long, url_key string, captured string, page_id long, url string, record_type string, refers_to long, payload_digest string, payload_bytes long, at long, length long"
_KINDS = [("run", pa.string()), ("seq", pa.int64()), ("url_key", pa.string()), ("captured", pa.string()), ("page_id", pa.int64()), ("url", pa.string()), ("record_type", pa.string()), ("refers_to", pa.int64()), ("payload_digest", pa.string()), ("payload_bytes", pa.int64()), ("at", pa.int64()), ("length", pa.int64())]
KEY = ("url_key", "captured", "page_id")


def _number(name: str | None) -> int | None:
    text = (name or "").removeprefix("<urn:page:").removesuffix(">")
    return None if text in ("", "none") else int(text)


def _sort_key(c: dict) -> tuple:
    return c["url_key"], c["captured"], -(1 << 63) if c["page_id"] is None else c["page_id"]


def _captures(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for b in batches:
        for path, content in zip(b.column("path"), b.column("content")):
            raw = content.as_py()
            raw = zlib.decompress(raw, 47) if raw[:2] == b"\x1f\x8b" else raw
            run = []
            for at, length, h, block in parse(raw):
                payload = bytes(block[bytes(block).index(b"\r\n\r\n") + 4 :])
                digest = h["WARC-Payload-Digest"].removeprefix("sha1:")
                if h["WARC-Type"] == "response" and base64.b32encode(hashlib.sha1(payload).digest()).decode() != digest:
                    raise ValueError(f"{path}: the payload at {at} isn't what its digest says")
                url, kind = h.get("WARC-Target-URI", ""), h["WARC-Type"]
                run.append({"run": path.as_py(), "url_key": url_key(url), "captured": h["WARC-Date"], "page_id": _number(h["WARC-Record-ID"]), "url": url, "record_type": kind, "refers_to": _number(h.get("WARC-Refers-To")), "payload_digest": digest, "payload_bytes": int(h.get("X-Payload-Length", len(payload))), "at": at, "length": length})
            run.sort(key=_sort_key)
            yield pa.RecordBatch.from_arrays([pa.array(range(len(run)) if n == "seq" else [c[n] for c in run], k) for n, k in _KINDS], [n for n, _ in _KINDS])


def loser_tree(runs: list[list], key) -> Iterator:
    """Merge sorted lists; each item costs one walk from a leaf to the root of a tree of losers."""
    k = len(runs)
    if not k:
        return
    at = [0] * k
    heads = [key(r[0]) if r else None for r in runs]
    beats = lambda a, b: heads[b] is None or heads[a] is not None and (heads[a], a) < (heads[b], b)
    loser = [-1] * k

    def play(i: int) -> int:
        node = (i + k) // 2
        while node:
            if loser[node] == -1:  # the first at an inner node waits for its rival
                loser[node] = i
                return -1
            if beats(loser[node], i):
                loser[node], i = i, loser[node]
            node //= 2
        return i

    winner = -1
    for i in range(k):
        winner = max(winner, play(i)) if winner == -1 else winner
    while heads[winner] is not None:
        yield runs[winner][at[winner]]
        at[winner] += 1
        own = runs[winner]
        heads[winner] = key(own[at[winner]]) if at[winner] < len(own) else None
        winner = play(winner)


def _merged(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    names = [n for n, _ in _KINDS]
    runs: dict[str, list] = {}
    for b in batches:
        for c in b.to_pylist():
            runs.setdefault(c["run"], []).append(c)
    out: list[dict] = []
    for c in loser_tree(list(runs.values()), _sort_key):
        out.append(c)
        if len(out) == 5000:
            yield pa.RecordBatch.from_pylist(out, pa.schema(_KINDS))
            out = []
    yield pa.RecordBatch.from_pylist(out, pa.schema(_KINDS)).select(names)


def read_captures(spark: SparkSession, path: str) -> DataFrame:
    """A sorted run of captures for each archive."""
    return spark.read.format("binaryFile").option("pathGlobFilter", "part-*").load(path).select("path", "content").mapInArrow(_captures, CAPTURE)


def merged_index(captures: DataFrame) -> DataFrame:
    """All runs as one history: range partitions in order of KEY, each merged from its slices."""
    return captures.repartitionByRange(*KEY).sortWithinPartitions("run", "seq").mapInArrow(_merged, CAPTURE)


def op9_web_archive(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = f"{shared_dir(spark).rstrip('/')}/warc-{uuid.uuid4().hex}"
    write_archives(table(spark, sf_dir, "pages"), path)
    captures = cut(read_captures(spark, path))  # the range exchange samples its input: archives are read once
    return merged_index(captures).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


ORACLE = r"""
WITH p AS (SELECT page_id, coalesce(html, '') h, sha1(coalesce(html, '')) d FROM pages),
f AS (SELECT d, min(page_id) first FROM p GROUP BY d),
b AS (SELECT d, first, array_to_string(list_transform(range(32), lambda i: substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567',
  ((CAST('0x' || substr(d, CAST(i * 5 // 4 + 1 AS BIGINT), 2) AS INTEGER) >> CAST(3 - i * 5 % 4 AS INTEGER)) & 31) + 1, 1)), '') payload_digest FROM f)
SELECT page_id, CAST(strlen(h) AS BIGINT) payload_bytes, payload_digest,
  CASE WHEN page_id = first THEN 'response' ELSE 'revisit' END record_type,
  CASE WHEN page_id <> first THEN first END refers_to
FROM p JOIN b ON p.d = b.d
"""

QUERIES = {"op9_web_archive": op9_web_archive}
ORACLES = {"op9_web_archive": ORACLE}
