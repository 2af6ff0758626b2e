"""WARC archives as a Spark data source, for reading and writing.

Reading plans partitions of whole files (small files share one), takes equality, comparison, IN and null
filters on header columns from Spark, parses a record's headers first and, where the filters or the schema
do not want it, steps over the payload without unpacking it: files are gzip members, one pair for each record
(headers, then content), and each member names its packed length in an extra field of its header, so a reader that
knows nothing of this still sees ordinary gzip, and this one seeks. Plain .warc and foreign .warc.gz files are
read too, the latter by unpacking.

Writing gives each task its own files, rolled at FILE_BYTES; the commit lists them in _files.json, and only
listed files are read, so a task that runs twice does no harm. Options: path; payload (true: a payload column);
verify (true: unpack payloads and hold them against digest and length).

Defined results (op2): null html is empty; records under DEDUPE_BYTES are always responses; of equal longer
payloads the smallest page_id is the response; rows that repeat that page_id with that payload are responses
too; null page_ids revisit if any page with the payload has an id, else they are responses; a null url stays null; an empty table
gives an archive without records. Columns are taken by name; extra ones are not read.
"""

from __future__ import annotations

import hashlib
import json
import struct
import uuid
import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import (
    DataSource,
    DataSourceArrowWriter,
    DataSourceReader,
    EqualNullSafe,
    EqualTo,
    GreaterThan,
    GreaterThanOrEqual,
    In,
    InputPartition,
    IsNotNull,
    IsNull,
    LessThan,
    LessThanOrEqual,
    WriterCommitMessage,
)

from .common import materialize, scratch_dir, ship, table

FILE_BYTES, PARTITION_BYTES, DEDUPE_BYTES = 256 << 20, 64 << 20, 100
HEADER_COLUMNS = "page_id long, url string, record_type string, refers_to long, payload_bytes long, payload_digest string"
HTTP = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n\r\n"
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"


def record_id(page_id: int | None) -> str:
    return f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, f'page:{page_id}')}>"


def _packed(raw: bytes) -> bytes:
    """A gzip member whose extra field SL holds the member's whole length."""
    squeeze = zlib.compressobj(1, zlib.DEFLATED, -15)
    body = squeeze.compress(raw) + squeeze.flush()
    whole = 24 + len(body) + 8
    return struct.pack("<BBBBIBBH2sHQ", 31, 139, 8, 4, 0, 0, 255, 12, b"SL", 8, whole) + body + struct.pack("<II", zlib.crc32(raw), len(raw) & 0xFFFFFFFF)


def _member_length(head: bytes) -> int | None:
    if len(head) >= 24 and head[:2] == b"\x1f\x8b" and head[3] & 4 and head[12:14] == b"SL":
        return struct.unpack_from("<Q", head, 16)[0]
    return None


def _line_safe(text: str) -> str:
    """Header values hold no line ends; a backslash escapes itself and them."""
    return text.replace("\\", "\\\\").replace("\r", "\\r").replace("\n", "\\n")


def _line_read(text: str) -> str:
    out, it = [], iter(text)
    for c in it:
        out.append({"r": "\r", "n": "\n"}.get(d := next(it, ""), d) if c == "\\" else c)
    return "".join(out)


def record_parts(page_id: int | None, url: str | None, kind: str, refers_to: int | None, n_bytes: int, digest: str, payload: bytes) -> tuple[bytes, bytes]:
    content = HTTP + payload if kind == "response" else HTTP
    head = ["WARC/1.1", f"WARC-Type: {kind}", f"WARC-Record-ID: {record_id(page_id)}", "WARC-Date: 2000-01-01T00:00:00Z", "Content-Type: application/http; msgtype=response"]
    if url is not None:
        head.append(f"WARC-Target-URI: {_line_safe(url)}")
    if page_id is not None:
        head.append(f"X-Page-Id: {page_id}")
    if kind == "revisit":
        head += [f"WARC-Profile: {PROFILE}", f"WARC-Refers-To: {record_id(refers_to)}"]
        if refers_to is not None:
            head.append(f"X-Refers-To-Page-Id: {refers_to}")
    head += [f"WARC-Payload-Digest: sha256:{digest}", f"X-Payload-Length: {n_bytes}", f"Content-Length: {len(content)}"]
    return ("\r\n".join(head) + "\r\n\r\n").encode(), content + b"\r\n\r\n"


def parse_headers(raw: bytes) -> dict[str, str]:
    out = {}
    for line in raw.decode("utf-8", "replace").split("\r\n")[1:]:
        name, sep, value = line.partition(":")
        if sep:
            out[name.strip().lower()] = value.strip()
    return out


def header_row(h: dict[str, str]) -> dict:
    number = lambda k: int(h[k]) if k in h else None
    return {
        "page_id": number("x-page-id"),
        "url": _line_read(h["warc-target-uri"]) if "warc-target-uri" in h else None,
        "record_type": h.get("warc-type"),
        "refers_to": number("x-refers-to-page-id"),
        "payload_bytes": number("x-payload-length"),
        "payload_digest": h.get("warc-payload-digest", "").rpartition(":")[2] or None,
    }


class _Source:
    """Records of one file: headers, and a function that unpacks the content."""

    def __init__(self, file):
        self.file, self.size = file, file.size()

    def records(self) -> Iterator[tuple[dict[str, str], object]]:
        self.file.seek(0)
        head = self.file.read(24)
        if _member_length(head) is not None:
            yield from self._indexed()
        else:
            yield from self._streamed(head[:2] == b"\x1f\x8b")

    def _indexed(self):
        """Members with a length field; from the first one without on, the file is streamed."""
        at = 0
        while at < self.size:
            self.file.seek(at)
            head = self.file.read(4096)
            n = _member_length(head)
            if n is not None:
                if n > len(head):
                    head += self.file.read(n - len(head))
                self.file.seek(at + n)
                size = _member_length(self.file.read(24))
            if n is None or size is None:
                yield from self._streamed(head[:2] == b"\x1f\x8b", at)
                return
            headers = parse_headers(zlib.decompress(head[24:n], -15))
            yield headers, lambda at=at + n, n=size: self._content(at, n)
            at += n + size

    def _content(self, at: int, n: int) -> bytes:
        self.file.seek(at)
        raw = self.file.read(n)
        return zlib.decompress(raw, 31)[:-4]

    def _streamed(self, packed: bool, begin: int = 0):
        self.file.seek(begin)
        buffer, at, inflate = bytearray(), 0, zlib.decompressobj(31) if packed else None

        def more() -> bool:
            nonlocal at, inflate
            chunk = self.file.read(1 << 20)
            if not chunk:
                return False
            del buffer[:at]
            at = 0
            while chunk:
                if inflate is None:
                    buffer.extend(chunk)
                    return True
                buffer.extend(inflate.decompress(chunk))
                chunk = inflate.unused_data
                if inflate.eof:
                    inflate = zlib.decompressobj(31)
            return True

        while True:
            while (end := buffer.find(b"\r\n\r\n", at)) < 0 and more():
                pass
            if end < 0:
                end = len(buffer)
            if not buffer[at:end].strip():
                if end == len(buffer):
                    return
                at = end + 4
                continue
            headers = parse_headers(bytes(buffer[at:end]).lstrip())
            at = end + 4
            n = int(headers.get("content-length", 0))
            while len(buffer) - at < n + 4 and more():
                pass
            content = bytes(buffer[at : at + n])
            at = min(at + n + 4, len(buffer))
            yield headers, lambda content=content: content


TESTS = {
    EqualTo: lambda v, x: v is not None and v == x,
    EqualNullSafe: lambda v, x: v == x,
    GreaterThan: lambda v, x: v is not None and v > x,
    GreaterThanOrEqual: lambda v, x: v is not None and v >= x,
    LessThan: lambda v, x: v is not None and v < x,
    LessThanOrEqual: lambda v, x: v is not None and v <= x,
    In: lambda v, x: v is not None and v in x,
    IsNull: lambda v, x: v is None,
    IsNotNull: lambda v, x: v is not None,
}


@dataclass
class WarcFiles(InputPartition):
    uris: list[str]

    def __init__(self, uris: list[str]):
        super().__init__(uris)
        self.uris = uris


@dataclass
class Written(WriterCommitMessage):
    names: list[str]


class WarcReader(DataSourceReader):
    def __init__(self, folder: str, schema, payload: bool, verify: bool):
        self.folder, self.schema, self.payload, self.verify = folder, schema, payload, verify
        self.tests: list[tuple[str, str, object]] = []

    def pushFilters(self, filters):
        known = {c.split()[0] for c in HEADER_COLUMNS.split(", ")}
        for f in filters:
            if type(f) in TESTS and len(f.attribute) == 1 and f.attribute[0] in known:
                self.tests.append((f.attribute[0], type(f).__name__, getattr(f, "value", None)))
            else:
                yield f

    def partitions(self):
        from pyarrow import fs

        where, base = fs.FileSystem.from_uri(self.folder)
        listed = fs.FileSelector(base, recursive=True, allow_not_found=True)
        names = {x.path: x.size for x in where.get_file_info(listed) if x.is_file}
        manifest = f"{base}/_files.json"
        if manifest in names:
            with where.open_input_stream(manifest) as f:
                own = [f"{base}/{n}" for n in json.loads(f.read())]
        else:
            own = sorted(n for n in names if n.endswith((".warc", ".warc.gz")))
        out, group, size = [], [], 0
        for path in own:
            if group and size + names[path] > PARTITION_BYTES:
                out.append(WarcFiles(group))
                group, size = [], 0
            group = [*group, self.folder.rstrip("/") + path[len(base) :]]
            size += names[path]
        return [*out, WarcFiles(group)] if group or not out else out

    def read(self, partition):
        from pyarrow import fs

        by_name = {k.__name__: f for k, f in TESTS.items()}
        tests = [(c, by_name[k], set(x) if k == "In" else x) for c, k, x in self.tests]
        names = [f.name for f in self.schema.fields]
        rows: list[tuple] = []
        size = 0
        for uri in partition.uris:
            where, path = fs.FileSystem.from_uri(uri)
            with where.open_input_file(path) as file:
                for headers, content in _Source(file).records():
                    row = header_row(headers)
                    if not all(test(row[c], x) for c, test, x in tests):
                        continue
                    if row["record_type"] == "response" and (self.payload or self.verify):
                        body = content().partition(b"\r\n\r\n")[2]
                        if self.verify and (hashlib.sha256(body).hexdigest() != row["payload_digest"] or len(body) != row["payload_bytes"]):
                            raise ValueError(f"page {row['page_id']}: the payload differs from its digest")
                        row["payload"] = body if self.payload else None
                        size += len(body) * self.payload
                    rows.append(tuple(row.get(n) for n in names))
                    if len(rows) >= 4096 or size > 16 << 20:
                        yield self._batch(rows)
                        rows, size = [], 0
        if rows:
            yield self._batch(rows)

    def _batch(self, rows: list[tuple]) -> pa.RecordBatch:
        from pyspark.sql.pandas.types import to_arrow_schema

        schema = to_arrow_schema(self.schema)
        return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), schema, strict=True)], schema=schema)


class WarcWriter(DataSourceArrowWriter):
    def __init__(self, folder: str):
        self.folder = folder

    def write(self, iterator):
        from pyarrow import fs

        where, base = fs.FileSystem.from_uri(self.folder)
        context = TaskContext.get()
        stem = f"part-{context.partitionId():06d}-{context.taskAttemptId()}-{uuid.uuid4().hex[:8]}"
        names, out, size = [], None, 0
        for batch in iterator:
            for r in batch.to_pylist():
                if out is None:
                    where.create_dir(base, recursive=True)
                    names.append(f"{stem}-{len(names):04d}.warc.gz")
                    out, size = where.open_output_stream(f"{base}/{names[-1]}", compression=None), 0
                payload = r["payload"] or b""
                for part in record_parts(r["page_id"], r["url"], r["record_type"], r["refers_to"], r["payload_bytes"], r["payload_digest"], payload):
                    packed = _packed(part)
                    out.write(packed)
                    size += len(packed)
                if size >= FILE_BYTES:
                    out.close()
                    out = None
        if out is not None:
            out.close()
        return Written(names)

    def commit(self, messages):
        from pyarrow import fs

        where, base = fs.FileSystem.from_uri(self.folder)
        where.create_dir(base, recursive=True)
        names = sorted(n for m in messages if m for n in m.names)
        manifest = f"{base}/_files.json"
        if where.get_file_info(manifest).is_file:
            with where.open_input_stream(manifest) as f:
                names = sorted({*names, *json.loads(f.read())})
        with where.open_output_stream(manifest) as f:
            f.write(json.dumps(names).encode())

    def abort(self, messages):
        from pyarrow import fs

        where, base = fs.FileSystem.from_uri(self.folder)
        for n in (n for m in messages if m for n in m.names):
            where.delete_file(f"{base}/{n}")


class WarcDataSource(DataSource):
    @classmethod
    def name(cls):
        return "warc"

    def _on(self, option: str) -> bool:
        return self.options.get(option, "false").lower() == "true"

    def schema(self):
        return HEADER_COLUMNS + ", payload binary" * self._on("payload")

    def reader(self, schema):
        return WarcReader(self.options["path"], schema, self._on("payload"), self._on("verify"))

    def writer(self, schema, overwrite):
        if overwrite:
            raise ValueError("archives are append-only: use mode append")
        return WarcWriter(self.options["path"])


def register(spark: SparkSession) -> None:
    ship(spark)
    spark.dataSource.register(WarcDataSource)
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")


def archive_rows(pages: DataFrame) -> DataFrame:
    """Rows of the writer's schema; equal payloads become one response and its revisits.

    Digests of payloads that occur more than once are written to a table first, so the join with all
    pages has a plain exchange on both sides and Spark can split the partition of a payload that many pages share.
    """
    payload = F.coalesce(F.col("html"), F.lit("")).cast("binary")
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"), payload.alias("payload"))
    rows = rows.select("*", F.octet_length("payload").cast("long").alias("payload_bytes"), F.sha2("payload", 256).alias("payload_digest"))
    shared = rows.filter(F.col("payload_bytes") >= DEDUPE_BYTES).groupBy(F.col("payload_digest").alias("digest")).agg(F.min("page_id").alias("first_id"), F.count(F.lit(1)).alias("n"))
    shared = materialize(shared.filter("n > 1 and first_id is not null").drop("n"), "warc-shared")
    revisit = F.col("first_id").isNotNull() & ~F.col("page_id").eqNullSafe(F.col("first_id"))
    joined = rows.join(shared, F.col("payload_digest") == F.col("digest"), "left")
    return joined.select("page_id", "url", F.when(revisit, "revisit").otherwise("response").alias("record_type"), F.when(revisit, F.col("first_id")).alias("refers_to"), "payload_bytes", "payload_digest", F.when(~revisit, F.col("payload")).alias("payload"))


def write_archive(pages: DataFrame, folder: str) -> None:
    register(pages.sparkSession)
    archive_rows(pages).write.format("warc").mode("append").save(folder)


def read_archive(spark: SparkSession, folder: str, payload: bool = False, verify: bool = False) -> DataFrame:
    register(spark)
    return spark.read.format("warc").option("payload", str(payload).lower()).option("verify", str(verify).lower()).load(folder)


def op2_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    folder = scratch_dir(spark, "warc")
    write_archive(table(spark, sf_dir, "pages"), folder)
    return read_archive(spark, folder, verify=True).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


OP2_SQL = """
WITH p AS (SELECT page_id, encode(coalesce(html, '')) AS b FROM pages),
q AS (SELECT page_id, octet_length(b) AS payload_bytes, sha256(b) AS payload_digest FROM p),
f AS (SELECT payload_digest AS d, min(page_id) AS first_id FROM q WHERE payload_bytes >= 100 GROUP BY 1)
SELECT page_id, CAST(payload_bytes AS BIGINT) AS payload_bytes, payload_digest,
       CASE WHEN first_id IS NOT NULL AND page_id IS DISTINCT FROM first_id THEN 'revisit' ELSE 'response' END AS record_type,
       CASE WHEN first_id IS NOT NULL AND page_id IS DISTINCT FROM first_id THEN first_id END AS refers_to
FROM q LEFT JOIN f ON payload_digest = d
"""
