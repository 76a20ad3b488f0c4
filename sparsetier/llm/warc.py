"""WARC archives with deduplicated payloads, and their index by an external merge.

Writing: of records with equal payloads the one with the smallest page_id is the response, the others are revisits that
refer to it. Archives are byte blobs of bounded size, one gzip member per record, stored as a binary column of Parquet
(only Spark's writers reach every shared store). Reading: each archive gives a locally sorted run of captures;
runs are dealt by ranges of (URL key, timestamp, page_id) and the pieces of the runs in a range are merged by a loser
tree, so the whole is ordered. Null html: empty payload. A null url has an empty key. Rows that repeat the smallest
page_id are all responses. Payloads are whole, however long; one is held at a time. Other input
columns are ignored. The capture time is ``EPOCH`` plus page_id seconds, as the table has none.
"""

from __future__ import annotations

import base64
import gzip
import hashlib
import zlib
from datetime import datetime, timedelta, timezone
from urllib.parse import urlsplit

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from sparsetier.llm.common import arrow_rows, materialize

EPOCH = datetime(2024, 1, 1, tzinfo=timezone.utc)
SALTS = 16
_MISSING = -1


def url_key(url: str | None) -> str:
    """Host labels reversed, then path and query, lower case."""
    try:
        parts = urlsplit((url or "").strip().lower())
    except ValueError:
        return (url or "").strip().lower()
    host = ",".join(reversed((parts.hostname or "").split("."))) if parts.netloc else ""
    return f"{host}){parts.path or '/'}{'?' + parts.query if parts.query else ''}" if host else parts.path


def capture_time(page_id: int | None) -> str:
    return (EPOCH + timedelta(seconds=(page_id or 0) % 10**9)).strftime("%Y-%m-%dT%H:%M:%SZ")


def with_references(pages: DataFrame, min_bytes: int = 0) -> DataFrame:
    """Add sha and ``first_id`` (the response's page_id, null where the record is alone). Only digests that occur twice
    or more are joined, and these by salted keys, so that a payload with a third of the rows is spread."""
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.coalesce("url", F.lit("")).alias("url"), F.coalesce("html", F.lit("")).alias("html"))
    rows = rows.withColumns({"sha": F.sha1(F.col("html").cast("binary")), "n": F.octet_length("html").cast("long")})
    several = rows.where(F.col("n") >= min_bytes).groupBy("sha").agg(F.min("page_id").alias("first_id"), F.count("*").alias("c")).where("c > 1")
    spread = several.select("sha", "first_id", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))).alias("salt"))
    return rows.withColumn("salt", F.pmod(F.xxhash64("page_id", "url"), F.lit(SALTS)).cast("int")).join(spread, ["sha", "salt"], "left").drop("salt")


def record_bytes(page_id, url, payload: bytes, sha_hex: str, first_id) -> bytes:
    digest = base64.b32encode(bytes.fromhex(sha_hex)).decode()
    revisit = first_id is not None and first_id != page_id
    body = b"" if revisit else b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % len(payload) + payload
    safe = "".join(c for c in url if c not in "\r\n")
    head = ["WARC/1.1", f"WARC-Type: {'revisit' if revisit else 'response'}", f"WARC-Record-ID: <urn:page:{_MISSING if page_id is None else page_id}>",
            f"WARC-Date: {capture_time(page_id)}", f"WARC-Target-URI: {safe}", f"WARC-Payload-Digest: sha1:{digest}", f"X-Payload-Length: {len(payload)}"]
    if revisit:
        head += [f"WARC-Refers-To: <urn:page:{first_id}>", "WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"]
    head += ["Content-Type: application/http; msgtype=response", f"Content-Length: {len(body)}"]
    return ("\r\n".join(head) + "\r\n\r\n").encode() + body + b"\r\n\r\n"


def write_archives(pages: DataFrame, archive_bytes: int = 4 << 20) -> DataFrame:
    """Archive rows (archive, blob) in the shared folder."""

    def run(batches):
        from pyspark import TaskContext

        part, number, members, size = TaskContext.get().partitionId(), 0, [], 0

        def pack():
            return pa.RecordBatch.from_arrays([pa.array([f"{part:06d}-{number:06d}"]), pa.array([b"".join(members)], pa.binary())], names=["archive", "blob"])

        for batch in batches:
            for at in range(0, batch.num_rows, 64):
                c = batch.slice(at, 64).to_pydict()
                for page_id, url, html, sha, first in zip(c["page_id"], c["url"], c["html"], c["sha"], c["first_id"]):
                    member = gzip.compress(record_bytes(page_id, url, html.encode(), sha, first), compresslevel=5, mtime=0)
                    members.append(member)
                    size += len(member)
                    if size >= archive_bytes:
                        yield pack()
                        number, members, size = number + 1, [], 0
        if members:
            yield pack()

    return materialize(with_references(pages).mapInArrow(run, "archive string, blob binary"), "warc")


def read_records(blob: bytes):
    """(offset, headers, payload) of each gzip member."""
    at = 0
    while at < len(blob):
        stream = zlib.decompressobj(31)
        plain = stream.decompress(blob[at:]) + stream.flush()
        head, body = plain.split(b"\r\n\r\n", 1)
        headers = dict(line.split(": ", 1) if ": " in line else (line.rstrip(":"), "") for line in head.decode().split("\r\n")[1:])
        body = body[:int(headers["Content-Length"])]
        yield at, headers, body.split(b"\r\n\r\n", 1)[1] if headers["WARC-Type"] == "response" else None
        at = len(blob) - len(stream.unused_data)


_RUN = ("archive string, seq int, url_key string, captured string, page_id long, offset long, "
        "payload_bytes long, payload_digest string, record_type string, refers_to long")


def _page(value: str):
    number = int(value.removeprefix("<urn:page:").removesuffix(">"))
    return None if number == _MISSING else number


def sorted_runs(archives: DataFrame) -> DataFrame:
    """The captures of each archive, sorted by (URL key, timestamp, page_id) inside it; payload digests are checked."""

    def start():
        def work(cols):
            for archive, blob in zip(cols["archive"], cols["blob"]):
                run = []
                for offset, h, payload in read_records(blob):
                    digest, length = h["WARC-Payload-Digest"].removeprefix("sha1:"), int(h["X-Payload-Length"])
                    if payload is not None and (len(payload) != length or base64.b32encode(hashlib.sha1(payload).digest()).decode() != digest):
                        raise ValueError(f"damaged record in {archive} at {offset}")
                    page_id = _page(h["WARC-Record-ID"])
                    run.append((url_key(h["WARC-Target-URI"]), h["WARC-Date"], page_id, offset, length, digest, h["WARC-Type"], _page(h["WARC-Refers-To"]) if "WARC-Refers-To" in h else None))
                run.sort(key=lambda r: (r[0], r[1], -1 if r[2] is None else r[2], r[3]))
                for seq, r in enumerate(run):
                    yield archive, seq, *r

        return work

    return arrow_rows(archives, _RUN, start)


class LoserTree:
    """k-way merge of sorted sequences of (key, value): inner nodes hold the loser of their match."""

    def __init__(self, runs):
        self.runs = [iter(r) for r in runs]
        self.k = max(1, len(self.runs))
        self.heads = [next(r, None) for r in self.runs] + [None] * (self.k - len(self.runs))
        self.loser = [0] * self.k
        self.top = self._build(1)

    def _before(self, a: int, b: int) -> bool:
        x, y = self.heads[a], self.heads[b]
        return x is not None and (y is None or (x[0], a) < (y[0], b))

    def _build(self, node: int) -> int:
        if node >= self.k:
            return node - self.k
        left, right = self._build(2 * node), self._build(2 * node + 1)
        won, lost = (left, right) if self._before(left, right) else (right, left)
        self.loser[node] = lost
        return won

    def __iter__(self):
        while self.heads[self.top] is not None:
            won = self.top
            yield self.heads[won][1]
            self.heads[won] = next(self.runs[won], None)
            node = (won + self.k) // 2
            while node >= 1:
                if self._before(self.loser[node], won):
                    self.loser[node], won = won, self.loser[node]
                node //= 2
            self.top = won


def merge_runs(runs: DataFrame, rows_per_range: int = 100_000) -> DataFrame:
    """Globally ordered capture histories. A range has about ``rows_per_range`` captures of fixed small size; a URL
    with very many captures is split, since timestamp and page_id are part of the range key."""
    parts = max(int(runs.sparkSession.conf.get("spark.sql.shuffle.partitions")), runs.count() // rows_per_range + 1)
    ranged = runs.repartitionByRange(parts, "url_key", "captured", "page_id", "archive").sortWithinPartitions("archive", "seq")

    def run(batches):
        pieces: dict[str, list] = {}
        schema = None
        for batch in batches:
            schema = batch.schema
            for row in zip(*batch.to_pydict().values()):
                pieces.setdefault(row[0], []).append(((row[2], row[3], -1 if row[4] is None else row[4]), row))
        out = []
        for row in LoserTree(pieces.values()):
            out.append(row)
            if len(out) == 4096:
                yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*out), schema)], schema=schema)
                out = []
        if out:
            yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*out), schema)], schema=schema)

    return ranged.mapInArrow(run, runs.schema)


def warc_roundtrip(pages: DataFrame) -> DataFrame:
    """(page_id, payload_bytes, payload_digest, record_type, refers_to, url_key, captured, archive, offset) in index order."""
    runs = materialize(sorted_runs(write_archives(pages)), "cdx_runs")
    return merge_runs(runs).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", "url_key", "captured", "archive", "offset")
