"""WARC archives with a two-level capture index.

Writing: equal payloads of at least `least_bytes` share one response, the others become revisits of it. Every record is
a gzip member of its own. Spark's text sink commits the members as raw bytes; its line separator is an empty gzip member,
so a file is a plain concatenation of members and any offset in the index can be read alone. Lost tasks are
redone by the sink's committer, and the folder can be in any store Spark writes to. Members go to the sink in runs of about `run_bytes`, and a
file takes as many runs as the largest payload allows, so that no file is longer than about `file_bytes`.

Index: level one, the captures sorted by reversed-host URL key and packed into compressed, numbered blocks of `block_lines`
lines; level two, a sparse directory with the first keys of at most about `directory_rows` blocks, which a reader holds sorted. A lookup bisects the
directory, reads the numbered blocks between two of its entries (the numbers are in Parquet's statistics), bisects their lines, and
reads only the record's byte range. A revisit names its response's URL, so following it is one more lookup.

Defined cases: a null html is an empty payload; a null url has the empty key; a null page_id is kept (it never is the
response of a group with ids; records of a group without any id are all responses); of rows that repeat the smallest page_id and payload, the
first by url is the response and all others revisit it; empty tables write an archive without records; extra columns are ignored; very long
pages are written whole, one run each.
"""

from __future__ import annotations

import bisect
import hashlib
import json
import zlib
from collections.abc import Iterator
from urllib.parse import urlsplit

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

from .common import Scratch

#: Fixed value: gzip of nothing.
EMPTY_MEMBER = bytes([31, 139, 8, 0, 0, 0, 0, 0, 0, 255, 3, 0, 0, 0, 0, 0, 0, 0, 0, 0])
ENTRY = "surt string, page_id long, url string, file string, offset long, length long, record_type string, payload_bytes long, payload_digest string, refers_to long, refers_to_url string"
FIELDS = [x.split()[0] for x in ENTRY.split(", ")]


def surt(url: str | None) -> str:
    """Reversed-host key: http://m.a.org:80/x?y#z gives org,a,m)/x?y"""
    if not url:
        return ""
    try:
        at = urlsplit(url.strip())
        host, port = (at.hostname or "").lower(), at.port
    except ValueError:
        return url
    if not host:
        return url
    gate = f":{port}" if port and (at.scheme, port) not in (("http", 80), ("https", 443)) else ""
    return ",".join(reversed(host.split("."))) + gate + ")" + (at.path or "/") + (f"?{at.query}" if at.query else "")


def clean(url: str) -> str:
    return url.replace("\r", "%0D").replace("\n", "%0A")


def record(page_id, url, payload: bytes, digest: str, refers_to, revisit: bool, date: str, refers_to_url: str | None = None) -> bytes:
    """One uncompressed record; a revisit keeps the full payload's length and digest in its header."""
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % len(payload)
    block = http if revisit else http + payload
    ident = lambda x: f"<urn:page:{'none' if x is None else x}>"
    lines = ["WARC/1.1", f"WARC-Type: {'revisit' if revisit else 'response'}", f"WARC-Record-ID: {ident(page_id)}", f"WARC-Date: {date}", "Content-Type: application/http;msgtype=response", f"WARC-Payload-Digest: sha256:{digest}"]
    if url:
        lines.append("WARC-Target-URI: " + clean(url))
    if revisit:
        lines += ["WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", f"WARC-Refers-To: {ident(refers_to)}"]
        if refers_to_url:
            lines.append("WARC-Refers-To-Target-URI: " + clean(refers_to_url))
    lines.append(f"Content-Length: {len(block)}")
    return "\r\n".join(lines).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


def gzipped(data: bytes, level: int = 6) -> bytes:
    z = zlib.compressobj(level, zlib.DEFLATED, 31)
    return z.compress(data) + z.flush()


def members(data, step: int = 1 << 16) -> Iterator[tuple[int, int, bytes]]:
    """(offset, length, content) of the gzip members of a file; empty ones are skipped."""
    view, at, n = memoryview(data), 0, len(data)
    while at < n:
        z, out, pos = zlib.decompressobj(31), [], at
        while not z.eof and pos < n:
            out.append(z.decompress(view[pos : pos + step]))
            pos += step
        end = min(pos, n) - len(z.unused_data)
        if not z.eof:
            raise ValueError(f"cut off at byte {at}")
        if any(out):
            yield at, end - at, b"".join(out)
        at = end


def parsed(content: bytes) -> tuple[dict[str, str], bytes]:
    """Header fields and payload (behind the HTTP header) of one record."""
    head, _, rest = content.partition(b"\r\n\r\n")
    fields = dict(x.split(": ", 1) for x in head.decode().split("\r\n")[1:])
    block = rest[: int(fields["Content-Length"])]
    http, _, payload = block.partition(b"\r\n\r\n")
    fields["HTTP-Content-Length"] = http.decode().rsplit("Content-Length: ", 1)[1].split("\r\n")[0]
    return fields, payload


def _page(ident: str) -> int | None:
    x = ident.removeprefix("<urn:page:").removesuffix(">")
    return None if x == "none" else int(x)


def deduplicated(pages: DataFrame, scratch: Scratch, least_bytes: int = 100) -> tuple[DataFrame, int]:
    """((page_id, url, payload, digest, refers_to, refers_to_url, revisit), bytes of the largest payload)"""
    payload = F.coalesce(F.col("html"), F.lit("")).cast("binary")
    own = pages.select("page_id", "url", payload.alias("payload")).withColumn("digest", F.sha2("payload", 256))
    seen = Observation()
    slim = own.observe(seen, F.max(F.octet_length("payload")).alias("longest")).where(F.octet_length("payload") >= least_bytes).select("page_id", "url", "digest")
    # digests are summed up before the join; only those with several records stay
    by_page = F.struct(F.col("page_id").isNull().alias("none"), "page_id", "url")
    firsts = slim.groupBy("digest").agg(F.min(by_page).alias("m"), F.count("*").alias("n"), F.count_if(F.col("page_id").isNotNull()).alias("named"))
    firsts = firsts.where((F.col("n") > 1) & (F.col("named") > 0))
    firsts = scratch.store(firsts.select(F.col("digest").alias("d"), F.col("m.page_id").alias("first"), F.col("m.url").alias("first_url")), "firsts")
    longest = int(seen.get["longest"] or 0)
    joined = own.join(firsts, F.col("digest") == F.col("d"), "left")
    at_first = F.col("page_id").eqNullSafe(F.col("first")) & F.col("url").eqNullSafe(F.col("first_url"))
    again = slim.join(firsts, F.col("digest") == F.col("d")).where(at_first).groupBy("digest").count().where("count > 1")
    keeps = at_first
    if not again.isEmpty():  # whole rows repeat: stored row numbers tell them apart
        joined = scratch.store(joined.withColumn("row", F.monotonically_increasing_id()), "numbered")
        least = joined.where(F.col("first").isNotNull() & at_first).groupBy("d").agg(F.min("row").alias("least")).withColumnRenamed("d", "d2")
        joined = joined.join(least, F.col("digest") == F.col("d2"), "left")
        keeps = F.col("row") == F.col("least")
    revisit = F.col("first").isNotNull() & ~keeps
    columns = [F.when(revisit, F.col("first")).alias("refers_to"), F.when(revisit, F.col("first_url")).alias("refers_to_url"), F.coalesce(revisit, F.lit(False)).alias("revisit")]
    return joined.select("page_id", "url", "payload", "digest", *columns), longest


def write(pages: DataFrame, folder: str, scratch: Scratch, least_bytes: int = 100, date: str = "2024-01-01T00:00:00Z", run_bytes: int = 1 << 20, file_bytes: int = 128 << 20) -> None:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        row: list[bytes] = []
        have = 0
        for batch in batches:
            for at in range(0, batch.num_rows, 64):
                for p, u, x, d, r, v, w in zip(*(c.to_pylist() for c in batch.slice(at, 64).columns), strict=True):
                    member = gzipped(record(p, u, x, d, r, v, date, w))
                    if row and have + len(member) > run_bytes:
                        yield pa.RecordBatch.from_arrays([pa.array([b"".join(row)], pa.binary())], ["record"])
                        row, have = [], 0
                    row.append(member)
                    have += len(member)
        if row:
            yield pa.RecordBatch.from_arrays([pa.array([b"".join(row)], pa.binary())], ["record"])

    rows, longest = deduplicated(pages, scratch, least_bytes)
    out = rows.select("page_id", "url", "payload", "digest", "refers_to", "revisit", "refers_to_url").mapInArrow(run, "record binary").select(F.col("record").cast("string").alias("value"))
    runs = max(1, file_bytes // max(run_bytes, longest))
    out.write.mode("overwrite").option("encoding", "ISO-8859-1").option("lineSep", EMPTY_MEMBER.decode("latin-1")).option("compression", "none").option("maxRecordsPerFile", runs).text(folder)
    scratch.drop("numbered", "firsts")


def read(spark: SparkSession, folder: str) -> DataFrame:
    """Index entries from the archives; the digest of a response is taken from its payload again and must agree."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        schema = pa.schema([(f, pa.string() if kind == "string" else pa.int64()) for f, kind in (x.split() for x in ENTRY.split(", "))])
        for batch in batches:
            for path, content in zip(batch.column(0), batch.column(1), strict=True):
                rows = []
                for offset, length, raw in members(content.as_buffer() if content.is_valid else b""):
                    h, payload = parsed(raw)
                    digest = h["WARC-Payload-Digest"].removeprefix("sha256:")
                    kind = h["WARC-Type"]
                    if kind == "response" and hashlib.sha256(payload).hexdigest() != digest:
                        raise ValueError(f"digest differs in {path} at {offset}")
                    url = h.get("WARC-Target-URI")
                    refers = _page(h["WARC-Refers-To"]) if kind == "revisit" else None
                    at_url = h.get("WARC-Refers-To-Target-URI")
                    rows.append((surt(url), _page(h["WARC-Record-ID"]), url, path.as_py(), offset, length, kind, len(payload) if kind == "response" else int(h["HTTP-Content-Length"]), digest, refers, at_url))
                for at in range(0, len(rows), 4096):
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows[at : at + 4096], strict=True), schema.types, strict=True)], schema=schema)

    files = spark.read.format("binaryFile").option("pathGlobFilter", "part-*").load(folder).select("path", "content")
    return files.mapInArrow(run, ENTRY)


def build_index(entries: DataFrame, block_lines: int = 1024) -> DataFrame:
    """Blocks (block, place, first_key, last_key, lines, data) in key order. `block` grows with the keys: the number of the sorted
    partition, then the block's place in it. data is a compressed run of sorted lines."""
    names = ["block", "place", "first_key", "last_key", "lines", "data"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, place = TaskContext.get().partitionId(), 0

        def block(rows: list[dict]) -> pa.RecordBatch:
            nonlocal place
            data = zlib.compress("\n".join(json.dumps([r[f] for f in FIELDS]) for r in rows).encode())
            place += 1
            row = ([(part << 32) + place - 1], [place - 1], [rows[0]["surt"]], [rows[-1]["surt"]], [len(rows)], [data])
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(row, (pa.int64(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.binary()), strict=True)], names)

        have: list[dict] = []
        for batch in batches:
            have += batch.to_pylist()
            while len(have) >= block_lines:
                yield block(have[:block_lines])
                have = have[block_lines:]
        if have:
            yield block(have)

    # page_id behind the key lets the range partitioner split a very common URL
    return entries.orderBy("surt", "page_id", "file", "offset").mapInArrow(run, "block long, place long, first_key string, last_key string, lines long, data binary")


def decode(blocks: DataFrame) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        schema = pa.schema([(f, pa.string() if kind == "string" else pa.int64()) for f, kind in (x.split() for x in ENTRY.split(", "))])
        for batch in batches:
            for data in batch.column(0):
                rows = read_block(data.as_py())
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), schema.types, strict=True)], schema=schema)

    return blocks.select("data").mapInArrow(run, ENTRY)


def read_block(data: bytes) -> list[list]:
    return [json.loads(x) for x in zlib.decompress(data).decode().split("\n")]


class Archive:
    """Archives in a folder with their index."""

    def __init__(self, spark: SparkSession, scratch: Scratch, folder: str, blocks: DataFrame, directory_rows: int = 100_000):
        self.spark, self.scratch, self.folder, self.blocks, self.directory_rows = spark, scratch, folder, blocks, directory_rows
        self._directory: tuple[list[str], list[int]] | None = None

    @staticmethod
    def create(pages: DataFrame, least_bytes: int = 100, block_lines: int = 1024, directory_rows: int = 100_000) -> Archive:
        spark, scratch = pages.sparkSession, Scratch(pages.sparkSession)
        folder = scratch.path("warc")
        write(pages, folder, scratch, least_bytes)
        blocks = scratch.store(build_index(read(spark, folder), block_lines), "blocks")
        return Archive(spark, scratch, folder, blocks, directory_rows)

    def captures(self) -> DataFrame:
        return decode(self.blocks)

    def directory(self) -> tuple[list[str], list[int]]:
        """First keys and numbers of some blocks in key order: every `stride`-th of each sorted partition, about `directory_rows` in all."""
        if self._directory is None:
            stride = max(1, -(-self.blocks.count() // self.directory_rows))
            rows = self.blocks.where(F.col("place") % stride == 0).select("first_key", "block").orderBy("block").collect()
            self._directory = [r["first_key"] for r in rows], [r["block"] for r in rows]
        return self._directory

    def lookup(self, url: str) -> list[dict]:
        """Captures of one URL: the directory is bisected for the first and last block that can hold its key, then each block's lines are."""
        keys, numbers = self.directory()
        key, out = surt(url), []
        low, high = max(0, bisect.bisect_left(keys, key) - 1), bisect.bisect_right(keys, key)
        if not high:
            return out
        there = F.col("block") >= numbers[low]
        if high < len(numbers):
            there = there & (F.col("block") < numbers[high])
        for row in self.blocks.where(there & (F.col("first_key") <= key) & (F.col("last_key") >= key)).select("block", "data").orderBy("block").toLocalIterator():
            lines = read_block(bytes(row["data"]))
            at = bisect.bisect_left(lines, key, key=lambda x: x[0])
            while at < len(lines) and lines[at][0] == key:
                out.append(dict(zip(FIELDS, lines[at], strict=True)))
                at += 1
        return out

    def fetch(self, entry: dict) -> bytes:
        """The payload at an entry, by a range read; a revisit is followed to its response."""
        fields, payload = parsed(next(iter(members(self._range(entry["file"], entry["offset"], entry["length"]))))[2])
        if fields["WARC-Type"] == "revisit":
            said = (entry["refers_to"], "response", entry["payload_digest"])
            return self.fetch(next(x for x in self.lookup(entry["refers_to_url"] or "") if (x["page_id"], x["record_type"], x["payload_digest"]) == said))
        return payload

    def _range(self, file: str, offset: int, length: int) -> bytes:
        jvm = self.spark._jvm
        path = jvm.org.apache.hadoop.fs.Path(file)
        stream = path.getFileSystem(self.spark._jsc.hadoopConfiguration()).open(path)
        try:
            stream.seek(offset)
            return bytes(jvm.org.apache.commons.io.IOUtils.toByteArray(stream, length))
        finally:
            stream.close()

