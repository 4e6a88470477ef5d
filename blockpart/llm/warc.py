"""WARC: a deterministic sharded writer, and a reader of what it committed.

A digest table (page_id, SHA-1, length) is made first. From it come the order: boundaries between ranges of
(page_id, digest) taken from the rows whose hash falls under a threshold, so that the same rows always give the same shards;
and the responses that later equal payloads refer to. Each range is sorted and written by one task, which rolls files by
compressed size, makes headers and digests anew, writes under a temporary name and renames. Names and contents follow from
the rows, so a retried task writes the same files again. The manifest, a table of names, sizes, records and digests, is written last;
readers open nothing that it does not list.

Results for odd input: a null html is an empty payload; a null page_id sorts first and is never the page referred to unless all
of equal payload are null, when the first is the response; repeated rows are one response and revisits of it; an empty table gives
an empty manifest; other columns are not read.
"""

from __future__ import annotations

import base64
import hashlib
import json
import re
import uuid
import zlib
from collections.abc import Iterator

import pyarrow as pa
import pyarrow.fs as pafs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from blockpart.llm.common import mapped, materialise, scratch_dir

#: Fixed value of the format.
VERSION = "WARC/1.1"
ROLL_BYTES = 256 << 20
RANGE_BYTES = 64 << 20
SAMPLES = 64
#: Ranges at most; beyond it they hold more bytes, and roll more files each. Their boundaries are literals in the plan, looked up in two steps of FAN.
RANGES, FAN = 65_536, 256
LEVEL = 4
#: References up to this many rows (some 50 bytes each) are broadcast; more are joined.
BROADCAST_ROWS = 200_000
DATE = "1970-01-01T00:00:00Z"
MANIFEST = "page_file string, n_records bigint, compressed_bytes bigint, sha256 string"


def b32(sha1: bytes) -> str:
    return base64.b32encode(sha1).decode()


def record(kind: str, uri: str, payload: bytes, digest: str, page: int | None, refers: int | None) -> bytes:
    """One record: headers, then the HTTP block, which for a revisit has no body."""
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    block = http if kind == "revisit" else http + payload
    name = uuid.uuid5(uuid.NAMESPACE_URL, f"{page}|{uri}|{digest}")
    head = [VERSION, f"WARC-Type: {kind}", f"WARC-Record-ID: <urn:uuid:{name}>", f"WARC-Date: {DATE}", f"WARC-Target-URI: {uri}", f"WARC-Payload-Digest: sha1:{digest}", f"WARC-Block-Digest: sha1:{b32(hashlib.sha1(block).digest())}"]
    if page is not None:
        head.append(f"WARC-Page-Number: {page}")
    if kind == "revisit":
        head += ["WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"] + ([f"WARC-Refers-To-Page-Number: {refers}"] if refers is not None else [])
    head += ["Content-Type: application/http; msgtype=response", f"Content-Length: {len(block)}"]
    return ("\r\n".join(head) + "\r\n\r\n").encode() + block + b"\r\n\r\n"


def member(raw: bytes, level: int = LEVEL) -> bytes:
    """A gzip member with no time in its header."""
    packer = zlib.compressobj(level, zlib.DEFLATED, 31)
    return packer.compress(raw) + packer.flush()


class Roller:
    """Files of one range: temporary names while open, final names when closed."""

    def __init__(self, root: str, part: int, roll_bytes: int):
        self.fs, self.root = pafs.FileSystem.from_uri(root)
        self.part, self.roll, self.number, self.out, self.rows = part, roll_bytes, 0, None, []

    def write(self, raw: bytes) -> None:
        if self.out is None:
            self.name = f"range-{self.part:06d}-{self.number:04d}.warc.gz"
            self.temporary = f"{self.root}/_temporary-{uuid.uuid4().hex}"
            self.out, self.size, self.records, self.sum = self.fs.open_output_stream(self.temporary, compression=None), 0, 0, hashlib.sha256()
        self.out.write(raw)
        self.sum.update(raw)
        self.size += len(raw)
        self.records += 1
        if self.size >= self.roll:
            self.close()

    def close(self) -> None:
        if self.out is not None:
            self.out.close()
            self.fs.move(self.temporary, f"{self.root}/{self.name}")
            self.rows.append((self.name, self.records, self.size, self.sum.hexdigest()))
            self.out, self.number = None, self.number + 1


def digests(pages: DataFrame) -> DataFrame:
    payload = F.coalesce(F.col("html"), F.lit(""))
    return pages.select("page_id", F.sha1(payload).alias("digest"), F.octet_length(payload).cast("long").alias("payload_bytes"))


def boundaries(table: DataFrame, range_bytes: int) -> list[tuple[int | None, str]]:
    """Least keys of all ranges but the first, from a sample by hash, of a size that follows the number of ranges."""
    rows, total = table.agg(F.count(F.lit(1)), F.sum("payload_bytes")).first()
    parts = min(RANGES, max(1, -(-(total or 0) // range_bytes)))
    if parts == 1:
        return []
    share = min(1.0, SAMPLES * parts / rows)
    drawn = table.where((F.pmod(F.xxhash64("page_id", "digest"), F.lit(1 << 30)) < int(share * (1 << 30))) & F.col("page_id").isNotNull())
    keys = sorted(map(tuple, drawn.select("page_id", "digest").collect()))
    return sorted({keys[len(keys) * k // parts] for k in range(1, parts)}) if keys else []


def range_of(edges: list[tuple[int | None, str]]) -> F.Column:
    """The number of edges at or below (page_id, digest)."""
    if not edges:
        return F.lit(0)
    kind, key = "struct<page_id:bigint,digest:string>", F.struct(F.col("page_id"), F.col("digest"))
    own = [[{"page_id": p, "digest": d} for p, d in edges[k : k + FAN]] for k in range(0, len(edges), FAN)]
    below = lambda held: F.size(F.filter(held, lambda x: x <= key))
    group = below(F.from_json(F.lit(json.dumps([g[0] for g in own])), f"array<{kind}>"))
    within = below(F.element_at(F.from_json(F.lit(json.dumps(own)), f"array<array<{kind}>>"), group))
    return F.when(group == 0, 0).otherwise((group - 1) * FAN + within)


def lanes(spark: SparkSession, n: int) -> list[int]:
    """For each of n partitions a number that Spark's hash deals to it: then repartition gives each range a task of its own."""
    found: dict[int, int] = {}
    low, step = 0, 16 * n + 64
    while len(found) < n:
        drawn = spark.range(low, low + step).select(F.pmod(F.hash("id"), F.lit(n)).alias("to"), "id").groupBy("to").agg(F.min("id"))
        for to, first in drawn.collect():
            found.setdefault(to, first)
        low += step
    return [found[k] for k in range(n)]


def with_first(rows: DataFrame, first: DataFrame) -> DataFrame:
    """Adds least and repeated. Payloads of many rows are few, and broadcast; only the others are joined by their digest."""
    many = first.count()
    if many <= BROADCAST_ROWS:
        return rows.join(F.broadcast(first.drop("n")), "digest", "left")
    total = first.agg(F.sum("n")).first()[0]
    hot = F.col("n") * (BROADCAST_ROWS // 4) >= total  # BROADCAST_ROWS / 4 at most
    rows = rows.join(F.broadcast(first.where(hot).select("digest", F.col("least").alias("_l"), F.col("repeated").alias("_r"))), "digest", "left")
    rows = rows.withColumn("_key", F.when(F.col("_r").isNull(), F.col("digest")).otherwise(F.concat(F.lit("-"), F.xxhash64("page_id", "url").cast("string"))))
    rows = rows.join(first.where(~hot).select(F.col("digest").alias("_key"), "least", "repeated"), "_key", "left")
    return rows.withColumn("least", F.coalesce("least", "_l")).withColumn("repeated", F.coalesce("repeated", "_r")).drop("_key", "_l", "_r")


def write_warc(pages: DataFrame, root: str, roll_bytes: int = ROLL_BYTES, range_bytes: int = RANGE_BYTES, floor: int = 0, level: int = LEVEL) -> DataFrame:
    """Write all rows of pages(page_id, url, html) under root; the committed manifest. Payloads of fewer than `floor` bytes are all responses."""
    spark = pages.sparkSession
    table = materialise(digests(pages))
    edges = boundaries(table, range_bytes)
    groups = table.where(F.col("payload_bytes") >= floor).groupBy("digest").agg(F.count(F.lit(1)).alias("n"), F.min("page_id").alias("least"))
    first = materialise(groups.where("n > 1").select("digest", "n", "least", F.lit(True).alias("repeated")))
    payload = F.coalesce(F.col("html"), F.lit(""))
    rows = pages.select("page_id", F.coalesce(F.col("url"), F.lit("")).alias("url"), payload.alias("html"), F.sha1(payload).alias("digest"))
    rows = with_first(rows, first).withColumn("part", range_of(edges).cast("int"))
    # One range a task. With a number given AQE may not merge them.
    lane = F.element_at(F.from_json(F.lit(json.dumps(lanes(spark, len(edges) + 1))), "array<bigint>"), F.col("part") + 1)
    rows = rows.repartition(len(edges) + 1, lane).sortWithinPartitions("part", F.col("page_id").asc_nulls_first(), "digest", "url")
    rows = rows.select("page_id", "url", "html", "digest", "least", "repeated", "part")

    def run(batches: Iterator[pa.RecordBatch]):
        roller, last = None, None
        done = []
        for batch in batches:
            for page, url, html, digest, least, repeated, number in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if roller is None or number != roller.part:
                    if roller is not None:
                        roller.close()
                        done += roller.rows
                    roller = Roller(root, number, roll_bytes)
                body = html.encode()
                revisit = bool(repeated) and (page != least or last == (page, digest))
                last = (page, digest)
                raw = record("revisit" if revisit else "response", re.sub(r"[\r\n]", "", url), body, b32(bytes.fromhex(digest)), page, least if revisit else None)
                roller.write(member(raw, level))
        if roller is not None:
            roller.close()
            done += roller.rows
        yield pa.RecordBatch.from_arrays([pa.array(list(x), t) for x, t in zip(zip(*done, strict=True) if done else [[]] * 4, (pa.string(), pa.int64(), pa.int64(), pa.string()), strict=True)], names=["page_file", "n_records", "compressed_bytes", "sha256"])

    pafs_root(root)
    manifest = mapped(rows, run, MANIFEST)
    where = f"{root}/_manifest"
    manifest.write.parquet(where)
    return spark.read.schema(MANIFEST).parquet(where)


def pafs_root(root: str) -> None:
    fs, path = pafs.FileSystem.from_uri(root)
    fs.create_dir(path, recursive=True)


def members(stream, size: int = 1 << 20) -> Iterator[bytes]:
    """The gzip members of a file, one at a time."""
    unpack, out = zlib.decompressobj(31), []
    while chunk := stream.read(size):
        while chunk:
            out.append(unpack.decompress(chunk))
            chunk = unpack.unused_data
            if unpack.eof:
                yield b"".join(out)
                unpack, out = zlib.decompressobj(31), []
    if any(out):
        raise ValueError("a file ends inside a record")


def parse(raw: bytes) -> tuple[dict[str, str], dict[str, str], bytes]:
    """Record headers, HTTP headers, body; checks the lengths and the block digest."""
    head, _, rest = raw.partition(b"\r\n\r\n")
    lines = head.decode().split("\r\n")
    if lines[0] != VERSION:
        raise ValueError("not a WARC record")
    fields = dict(x.split(": ", 1) for x in lines[1:] if ": " in x)
    block = rest[: int(fields["Content-Length"])]
    if rest[len(block) :] != b"\r\n\r\n" or fields["WARC-Block-Digest"] != f"sha1:{b32(hashlib.sha1(block).digest())}":
        raise ValueError("a record does not match its headers")
    http, _, body = block.partition(b"\r\n\r\n")
    return fields, dict(x.split(": ", 1) for x in http.decode().split("\r\n")[1:]), body


def read_warc(manifest: DataFrame, root: str, with_payload: bool = False) -> DataFrame:
    """page_id, url, payload_bytes, payload_digest, record_type, refers_to (and html) of each record of the listed files."""
    kinds = "page_id bigint, url string, payload_bytes bigint, payload_digest string, record_type string, refers_to bigint" + (", html string" if with_payload else "")
    names = [x.split()[0] for x in kinds.split(", ")]
    types = [pa.int64(), pa.string(), pa.int64(), pa.string(), pa.string(), pa.int64(), pa.string()]

    def run(batches: Iterator[pa.RecordBatch]):
        fs, path = pafs.FileSystem.from_uri(root)
        for batch in batches:
            for name in batch.column(0).to_pylist():
                rows = []
                with fs.open_input_stream(f"{path}/{name}", compression=None) as stream:
                    for raw in members(stream):
                        f, http, body = parse(raw)
                        digest, kind = f["WARC-Payload-Digest"].removeprefix("sha1:"), f["WARC-Type"]
                        if kind == "response" and (b32(hashlib.sha1(body).digest()) != digest or len(body) != int(http["Content-Length"])):
                            raise ValueError("a payload does not match its digest")
                        page, refers = f.get("WARC-Page-Number"), f.get("WARC-Refers-To-Page-Number")
                        row = (page and int(page), f.get("WARC-Target-URI", ""), int(http["Content-Length"]), digest, kind, refers and int(refers))
                        rows.append(row + ((body.decode() if kind == "response" else None,) if with_payload else ()))
                        if len(rows) == 1000:
                            yield pa.RecordBatch.from_arrays([pa.array(list(x), t) for x, t in zip(zip(*rows, strict=True), types, strict=False)], names=names)
                            rows = []
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(list(x), t) for x, t in zip(zip(*rows, strict=True), types, strict=False)], names=names)

    return mapped(manifest.select("page_file").coalesce(1).repartition(max(1, manifest.count())), run, kinds)


def round_trip(pages: DataFrame, root: str | None = None, **options) -> DataFrame:
    """Write all pages and read them back."""
    root = root or scratch_dir(pages.sparkSession)
    return read_warc(write_warc(pages, root, **options), root)
