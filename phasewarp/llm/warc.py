"""WARC archives, revisit records, and capture histories by an external index merge.

Payload digests decide the record types before anything is written: of equal payloads of at least
``least_bytes`` bytes the smallest ``page_id`` is the response and the others revisit it.  Each
task writes gzip-member archives into the shared folder (a finished file gets its name by one
rename, so a repeated task replaces it whole) and one index run per archive, sorted by URL key,
capture time and page.  The runs are merged range by range: a task holds the segments of its key
range from all runs and a loser tree of k leaves emits them in order.

Archives are read back record by record through the list of archives in the index.

Rows: null html counts as empty; a null url has the empty key; a null ``page_id`` is larger than
any other when the response is chosen; of repeated rows (same page and payload) one is the
response or all revisit another; an empty table gives an empty result.
"""

from __future__ import annotations

import base64
import gzip
import hashlib
import re
import uuid
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from phasewarp.llm.common import shared_folder, shuffle_width, stored

ARCHIVE_BYTES = 128 << 20
#: Fixed values of the format.
VERSION = "WARC/1.1"
REVISIT = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
INDEX = "run string, urlkey string, captured string, page_id long, record_type string, payload_digest string, at long, size long"
RECORD = "run string, at long, page_id long, payload_bytes long, payload_digest string, record_type string, refers_to long"
_BAD = re.compile(r"[\x00-\x20\x7f]")


def url_key(url: Column) -> Column:
    """Sort-friendly key: host labels reversed, then the path, lower case, without scheme and www."""
    bare = F.regexp_replace(F.lower(F.coalesce(url, F.lit(""))), r"^[a-z][a-z0-9+.-]*://(www\.)?", "")
    host, rest = F.regexp_extract(bare, r"^([^/?#]*)", 1), F.regexp_extract(bare, r"^[^/?#]*([^#]*)", 1)
    return F.when(bare == "", F.lit("")).otherwise(F.concat(F.array_join(F.reverse(F.split(host, r"\.")), ","), F.lit(")"), rest))


def _open(folder: str):
    from pyarrow import fs

    where, path = fs.FileSystem.from_uri(folder)
    return where, path


def _base32(data: bytes) -> str:
    return base64.b32encode(data).decode()


def _record(row: dict) -> bytes:
    payload = (row["html"] or "").encode("utf-8", "surrogatepass")
    url = _BAD.sub(lambda m: f"%{ord(m[0]):02X}", row["url"]) if row["url"] is not None else None
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    revisit = row["record_type"] == "revisit"
    block = http if revisit else http + payload
    head = [VERSION, f"WARC-Type: {row['record_type']}", f"WARC-Record-ID: <urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, repr((row['page_id'], row['copy'])))}>"]
    head += [f"WARC-Date: {row['captured']}"] + ([f"WARC-Target-URI: {url}"] if url is not None else [])
    head += [f"WARC-Payload-Digest: sha1:{_base32(row['digest'])}", "Content-Type: application/http; msgtype=response"]
    head += [f"X-Page: {row['page_id']}"] if row["page_id"] is not None else []
    if revisit:
        head += [f"WARC-Profile: {REVISIT}"] + ([f"X-Refers-To-Page: {row['refers_to']}"] if row["refers_to"] is not None else [])
    head += [f"Content-Length: {len(block)}"]
    return "\r\n".join(head).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


class _Archive:
    """One archive being written under a private name, and its index run."""

    def __init__(self, where, path: str, name: str):
        self.where, self.final, self.name = where, f"{path}/{name}", name
        self.private = f"{path}/.{name}-{uuid.uuid4().hex}"
        self.out, self.at, self.run = where.open_output_stream(self.private, compression=None), 0, []

    def add(self, row: dict) -> None:
        member = gzip.compress(_record(row), 1, mtime=0)
        self.out.write(member)
        self.run.append((self.name, row["urlkey"], row["captured"], row["page_id"], row["record_type"], _base32(row["digest"]), self.at, len(member)))
        self.at += len(member)

    def close(self) -> pa.RecordBatch:
        self.out.close()
        self.where.move(self.private, self.final)
        self.run.sort(key=lambda r: (r[1], r[2], r[3] is not None, r[3] or 0, r[6]))
        return _batch(self.run, INDEX)


def _batch(rows: list[tuple], schema: str) -> pa.RecordBatch:
    kinds = {"string": pa.string(), "long": pa.int64(), "int": pa.int32()}
    fields = [f.split() for f in schema.split(", ")]
    columns = list(zip(*rows)) if rows else [()] * len(fields)
    return pa.RecordBatch.from_arrays([pa.array(c, kinds[k]) for c, (_, k) in zip(columns, fields)], names=[n for n, _ in fields])


def _write_batches(folder: str, archive_bytes: int):
    def run(batches):
        from pyspark import TaskContext

        where, path = _open(folder)
        where.create_dir(path, recursive=True)
        part, k, archive, last, copy = TaskContext.get().partitionId(), 0, None, None, 0
        for b in batches:
            for row in b.to_pylist():
                same = (row["page_id"], row["digest"])
                copy = copy + 1 if same == last else 0
                last = same
                row["copy"] = copy
                first = row["first_page"] == row["page_id"] and row["long_enough"]
                if row["long_enough"] and not (first and copy == 0):
                    row |= {"record_type": "revisit", "refers_to": row["first_page"]}
                else:
                    row |= {"record_type": "response", "refers_to": None}
                if archive is None:
                    archive = _Archive(where, path, f"part-{part:06d}-{k:04d}.warc.gz")
                archive.add(row)
                if archive.at >= archive_bytes:
                    yield archive.close()
                    archive, k = None, k + 1
        if archive is not None:
            yield archive.close()

    return run


def write_archives(pages: DataFrame, folder: str, least_bytes: int = 0, archive_bytes: int = ARCHIVE_BYTES) -> DataFrame:
    """Write ``pages(page_id, url, html[, captured])`` as archives; returns the index runs
    (stored), one per archive, each sorted by ``urlkey, captured, page_id``."""
    body = F.coalesce(F.col("html").cast("string"), F.lit(""))
    when = "captured" if "captured" in pages.columns else None
    made = F.timestamp_seconds(F.lit(1704067200) + F.pmod(F.coalesce(F.col("page_id"), F.lit(0)), F.lit(1 << 31)))
    base = pages.select(
        F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), body.alias("html"),
        url_key(F.col("url").cast("string")).alias("urlkey"),
        F.date_format(F.to_utc_timestamp(F.col(when).cast("timestamp"), F.current_timezone()) if when else F.to_utc_timestamp(made, F.current_timezone()), "yyyy-MM-dd'T'HH:mm:ss'Z'").alias("captured"),
        F.unhex(F.sha1(body)).alias("digest"),
    )
    seen = stored(base.select("page_id", "digest", F.octet_length("html").alias("bytes")), folder, "digests")
    first = seen.groupBy("digest").agg(F.min("page_id").alias("first_page"))
    roles = (
        seen.groupBy("page_id", "digest").agg(F.max("bytes").alias("bytes"))
        .join(first, "digest")
        .select(F.coalesce("page_id", F.lit(-(2**63))).alias("key"), "digest", "first_page", (F.col("bytes") >= least_bytes).alias("long_enough"))
    )
    width = shuffle_width(pages.sparkSession)
    ready = (
        base.withColumn("key", F.coalesce("page_id", F.lit(-(2**63))))
        .join(roles, ["key", "digest"])
        .repartition(width, "key", "digest")
        .sortWithinPartitions("key", "digest")
        .drop("key")
    )
    return stored(ready.mapInArrow(_write_batches(f"{folder}/archives", archive_bytes), INDEX), folder, "runs")


class LoserTree:
    """Merge of sorted runs: each step replays one leaf's path to the root, log2(k) matches."""

    def __init__(self, runs: list[Iterator]):
        self.runs = runs
        self.size = 1
        while self.size < max(1, len(runs)):
            self.size *= 2
        self.head = [next(r, None) for r in runs] + [None] * (self.size - len(runs))
        self.losers = [0] * self.size
        winners = [0] * self.size + list(range(self.size))
        for node in range(self.size - 1, 0, -1):
            a, b = winners[2 * node], winners[2 * node + 1]
            winners[node], self.losers[node] = (a, b) if self._wins(a, b) else (b, a)
        self.top = winners[1] if self.size > 1 else 0

    def _wins(self, a: int, b: int) -> bool:
        x, y = self.head[a], self.head[b]
        return y is None or (x is not None and (x, a) <= (y, b))

    def __iter__(self):
        while (out := self.head[self.top]) is not None:
            yield out
            leaf = self.top
            self.head[leaf] = next(self.runs[leaf], None)
            node = (self.size + leaf) // 2
            while node:
                if not self._wins(leaf, self.losers[node]):
                    leaf, self.losers[node] = self.losers[node], leaf
                node //= 2
            self.top = leaf


def _merge_batches(batches):
    """Segments of the runs (rows arrive run by run, each sorted) merged into one sequence."""
    from pyspark import TaskContext

    part, segments = TaskContext.get().partitionId(), {}
    for b in batches:
        for r in b.to_pylist():
            segments.setdefault(r["run"], []).append((r["urlkey"], r["captured"], r["page_id"] is not None, r["page_id"] or 0, r["at"], r["run"]))
    out, pos = [], 0
    for key, captured, known, page, at, run in LoserTree([iter(s) for s in segments.values()]):
        out.append((run, at, key, captured, part, pos))
        pos += 1
        if len(out) == 20_000:
            yield _batch(out, "run string, at long, urlkey string, captured string, part int, pos long")
            out = []
    if out:
        yield _batch(out, "run string, at long, urlkey string, captured string, part int, pos long")


def histories(runs: DataFrame, parts: int | None = None) -> DataFrame:
    """Capture histories in global order: ``(part, pos)`` sorts all captures by
    ``urlkey, captured, page_id``.  A host or URL with many captures may span tasks, because the
    ranges are of the whole key."""
    order = ["urlkey", "captured", F.col("page_id").asc_nulls_first(), "run", "at"]
    return (
        runs.repartitionByRange(parts or shuffle_width(runs.sparkSession), *order)
        .sortWithinPartitions("run", *order[:3], "at")
        .select("run", "urlkey", "captured", "page_id", "at")
        .mapInArrow(_merge_batches, "run string, at long, urlkey string, captured string, part int, pos long")
    )


def _members(stream, chunk: int = 1 << 20):
    """(offset, bytes) of each gzip member of a stream."""
    at, data, box, got = 0, b"", zlib.decompressobj(31), []
    used = 0
    while True:
        if not data:
            data = stream.read(chunk)
            if not data:
                return
        got.append(box.decompress(data))
        left = box.unused_data
        used += len(data) - len(left)
        data = left
        if box.eof:
            yield at, b"".join(got)
            at, used, box, got = at + used, 0, zlib.decompressobj(31), []


def parse_record(record: bytes) -> tuple[dict[str, str], dict[str, str], bytes]:
    """(WARC headers, HTTP headers, payload) of one record."""
    head, _, rest = record.partition(b"\r\n\r\n")
    lines = head.decode("utf-8").split("\r\n")
    if lines[0] != VERSION:
        raise ValueError(f"not a {VERSION} record: {lines[0]!r}")
    warc = dict(x.split(": ", 1) for x in lines[1:])
    block = rest[: int(warc["Content-Length"])]
    http, _, payload = block.partition(b"\r\n\r\n")
    return warc, dict(x.split(": ", 1) for x in http.decode("utf-8").split("\r\n")[1:]), payload


def _read_batches(folder: str):
    def run(batches):
        where, path = _open(folder)
        for b in batches:
            for name in b.column("run").to_pylist():
                rows = []
                with where.open_input_stream(f"{path}/{name}", compression=None) as stream:
                    for at, record in _members(stream):
                        warc, http, payload = parse_record(record)
                        digest = warc["WARC-Payload-Digest"].removeprefix("sha1:")
                        kind = warc["WARC-Type"]
                        if kind == "response" and _base32(hashlib.sha1(payload).digest()) != digest:
                            raise ValueError(f"{name} at {at}: the payload does not match its digest")
                        size = len(payload) if kind == "response" else int(http["Content-Length"])
                        page, refers = warc.get("X-Page"), warc.get("X-Refers-To-Page")
                        rows.append((name, at, int(page) if page else None, size, digest, kind, int(refers) if refers else None))
                        if len(rows) == 5_000:
                            yield _batch(rows, RECORD)
                            rows = []
                if rows:
                    yield _batch(rows, RECORD)

    return run


def read_archives(runs: DataFrame, folder: str) -> DataFrame:
    """Every record of the archives that the index runs name."""
    names = runs.select("run").distinct()
    return names.repartition(shuffle_width(runs.sparkSession), "run").mapInArrow(_read_batches(f"{folder}/archives"), RECORD)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    folder = shared_folder(spark)
    runs = write_archives(spark.read.parquet(f"{sf_dir}/pages.parquet"), folder)
    return (
        read_archives(runs, folder)
        .join(histories(runs), ["run", "at"])
        .select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to", "urlkey", "captured", "part", "pos")
    )
