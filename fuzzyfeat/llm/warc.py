"""WARC archives: a writer with revisit records, and a Python data source that reads archives headers first.

Reading: a partition is a file, or with range_bytes a range of an uncompressed file, whose reader steps from record head to
record head until its range begins (no search for marks, which a payload may hold too). Predicates on the record type, and equality, IN or
prefix predicates on other header fields, are pushed into the source: it parses a record's head, tests it, and steps over
a payload that is unwanted (a seek in plain files; in gzip members the bytes are inflated but never decoded or kept).

Writing: archives of ARCHIVE_BYTES or little more, so that one of them is a bounded task for its reader. Each has a temporary
name until it is whole; a list of the archives of the tasks that succeeded is written last, and readers of the folder go by
it, so what a lost task left behind is never read. Every path goes through pyarrow's file systems, so the folder may be any shared store they know.
"""

from __future__ import annotations

import base64
import gzip
import hashlib
import io
import re
from collections.abc import Iterator
from urllib.parse import quote

import pyarrow as pa
from pyarrow import fs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, In, InputPartition, StringStartsWith

from fuzzyfeat.session import prepare

HTTP = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\n\r\n"
DATE = "2024-01-01T00:00:00Z"
ARCHIVE_BYTES, LIST = 1 << 28, "archives.txt"
SCHEMA = "record_type string, record_id string, target_uri string, payload_digest string, refers_to string, payload_bytes long, payload binary, headers map<string,string>"
#: Columns that a predicate can be pushed on, and the header field of each. Fixed names of the format.
FIELDS = {"record_type": "warc-type", "record_id": "warc-record-id", "target_uri": "warc-target-uri", "payload_digest": "warc-payload-digest", "refers_to": "warc-refers-to"}


def open_store(path: str) -> tuple[fs.FileSystem, str]:
    """The file system of a path or URI, and the path in it."""
    if re.match(r"file:/(?!/)", path):
        path = "file://" + path.removeprefix("file:")
    return fs.FileSystem.from_uri(path) if "://" in path else (fs.LocalFileSystem(), path)


def sha1_base32(payload: bytes) -> str:
    return base64.b32encode(hashlib.sha1(payload).digest()).decode()


def record(kind: str, number, url: str | None, payload: bytes, digest: str, refers_to=None) -> bytes:
    """The bytes of one record. A revisit carries the HTTP head only; its payload is that of the record it refers to."""
    block = HTTP + (payload if kind == "response" else b"")
    head = ["WARC/1.1", f"WARC-Type: {kind}", f"WARC-Record-ID: <urn:page:{'' if number is None else number}>", f"WARC-Date: {DATE}"]
    if url is not None:
        head.append("WARC-Target-URI: " + quote(url, safe=":/?#[]@!$&'()*+,;=%~"))
    head += [f"WARC-Payload-Digest: sha1:{digest}", f"WARC-Payload-Length: {len(payload)}"]
    if kind == "revisit":
        head += ["WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", f"WARC-Refers-To: <urn:page:{'' if refers_to is None else refers_to}>"]
    head += ["Content-Type: application/http; msgtype=response", f"Content-Length: {len(block)}"]
    return "\r\n".join(head).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


def mark_revisits(pages: DataFrame, least_bytes: int = 0) -> DataFrame:
    """page_id, url, payload, digest_hex, and refers_to: null for the records that keep their payload.

    Of equal payloads of at least `least_bytes` bytes, the row with the largest page_id keeps it. The payload's hash is the
    only key that is dealt out for the choice, pre-aggregated; the join with it can be split at a hot payload.
    """
    rows = pages.select("page_id", "url", F.coalesce(F.col("html"), F.lit("")).cast("binary").alias("payload")).withColumn("digest_hex", F.sha1("payload"))
    keepers = rows.filter(F.octet_length("payload") >= least_bytes).groupBy("digest_hex").agg(F.max("page_id").alias("keeper")).select(F.concat("digest_hex", F.lit("")).alias("digest_hex"), "keeper")
    met = rows.join(keepers, "digest_hex", "left")
    return met.withColumn("refers_to", F.when(F.col("keeper").isNotNull() & ~F.col("page_id").eqNullSafe(F.col("keeper")), F.col("keeper"))).drop("keeper")


def write_warc(pages: DataFrame, folder: str, compress: bool = True, least_bytes: int = 0, archive_bytes: int = ARCHIVE_BYTES) -> list[str]:
    """Write a record for each page (page_id, url, html; a null html is an empty payload) and return the archives' paths.

    Rows that share the largest page_id of a payload as a whole all keep their payload. An empty table gives no archive.
    """
    prepare(pages.sparkSession)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        store, root = open_store(folder)
        store.create_dir(root, recursive=True)
        task, attempt = TaskContext.get().partitionId(), TaskContext.get().taskAttemptId()
        number, count, size, out = 0, 0, 0, None

        def done() -> pa.RecordBatch:
            name = f"part-{task:06d}-{attempt}-{number:05d}.warc" + ".gz" * compress
            out.close()
            store.move(f"{root}/.{task}-{attempt}", f"{root}/{name}")
            return pa.RecordBatch.from_pydict({"name": [name], "records": [count]})

        for batch in batches:
            for page, url, payload, refers_to in zip(*(batch.column(c) for c in ("page_id", "url", "payload", "refers_to")), strict=True):
                out = out or store.open_output_stream(f"{root}/.{task}-{attempt}", compression=None)
                payload, refers_to = payload.as_py(), refers_to.as_py()
                raw = record("response" if refers_to is None else "revisit", page.as_py(), url.as_py(), payload, sha1_base32(payload), refers_to)
                raw = gzip.compress(raw, 1, mtime=0) if compress else raw
                out.write(raw)
                count, size = count + 1, size + len(raw)
                if size >= archive_bytes:
                    yield done()
                    number, count, size, out = number + 1, 0, 0, None
        if out:
            yield done()

    marked = mark_revisits(pages, least_bytes).select("page_id", "url", "payload", "refers_to")
    names = sorted(row["name"] for row in marked.mapInArrow(work, "name string, records long").collect())  # a row per archive
    store, root = open_store(folder)
    store.create_dir(root, recursive=True)
    with store.open_output_stream(f"{root}/{LIST}", compression=None) as out:
        out.write("\n".join(names).encode())
    return [f"{folder.rstrip('/')}/{name}" for name in names]


class Range(InputPartition):
    def __init__(self, path: str, start: int, end: int | None):
        self.path, self.start, self.end = path, start, end


class _Stream:
    """Sequential bytes of a plain or gzip archive with a cheap skip."""

    def __init__(self, raw, compressed: bool):
        self.compressed = compressed
        self.buffered = io.BufferedReader(gzip.GzipFile(fileobj=raw) if compressed else raw, 1 << 18)

    def head(self) -> bytes | None:
        """The next record's head without its blank line, or None at the end."""
        lines = []
        while True:
            line = self.buffered.readline()
            if not line:
                return None
            if line in (b"\r\n", b"\n"):
                if lines:
                    return b"".join(lines)
                continue
            lines.append(line)

    def read(self, n: int) -> bytes:
        """A record's block; the two line ends after it go too."""
        block = self.buffered.read(n)
        self.buffered.read(4)
        return block

    def skip(self, n: int) -> None:
        n += 4
        if not self.compressed:
            self.buffered.seek(n, 1)
            return
        while n:
            n -= len(self.buffered.read(min(n, 1 << 16))) or n


class WarcReader(DataSourceReader):
    def __init__(self, options: dict[str, str]):
        self.options = dict(options)
        self.tests: list[tuple[str, str, object]] = [("record_type", "in", (options["record_type"],))] if "record_type" in options else []
        self.payload = options.get("payload", "true").lower() == "true"

    def pushFilters(self, filters):
        for f in filters:
            if isinstance(f, EqualTo) and f.attribute[0] in FIELDS and len(f.attribute) == 1:
                self.tests.append((f.attribute[0], "in", (f.value,)))
            elif isinstance(f, In) and f.attribute[0] in FIELDS and len(f.attribute) == 1:
                self.tests.append((f.attribute[0], "in", tuple(f.value)))
            elif isinstance(f, StringStartsWith) and f.attribute[0] in FIELDS and len(f.attribute) == 1:
                self.tests.append((f.attribute[0], "prefix", f.value))
            else:
                yield f

    def partitions(self):
        named = [x for x in self.options.get("files", "").split("\n") if x]
        if not named:
            folder = self.options["path"]
            store, root = open_store(folder)
            root = root.rstrip("/")
            if store.get_file_info(f"{root}/{LIST}").is_file:
                with store.open_input_stream(f"{root}/{LIST}", compression=None) as listed:
                    named = [f"{folder.rstrip('/')}/{x}" for x in listed.read().decode().split("\n") if x]
            else:
                found = store.get_file_info(fs.FileSelector(root, recursive=True))
                named = sorted(f"{folder.rstrip('/')}/{x.path[len(root) + 1 :]}" for x in found if x.is_file and re.search(r"\.warc(\.gz)?$", x.path) and not x.base_name.startswith("."))
        out, step = [], int(self.options.get("range_bytes", 0))
        for path in named:
            if path.endswith(".gz") or not step:
                out.append(Range(path, 0, None))
            else:
                store, inner = open_store(path)
                size = store.get_file_info(inner).size
                out += [Range(path, a, min(size, a + step)) for a in range(0, size, step)]
        return out or [Range("", 0, 0)]

    def _wanted(self, row: dict[str, str | None]) -> bool:
        return all(row[c] is not None and (row[c] in v if how == "in" else row[c].startswith(v)) for c, how, v in self.tests)

    def read(self, partition: Range):
        if not partition.path:
            return
        store, inner = open_store(partition.path)
        compressed = partition.path.endswith(".gz")
        with store.open_input_stream(inner, compression=None) if compressed else store.open_input_file(inner) as raw:
            stream = _Stream(raw, compressed)
            while partition.end is None or stream.buffered.tell() < partition.end:
                before = not compressed and stream.buffered.tell() < partition.start
                head = stream.head()
                if head is None:
                    return
                fields = {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in head.decode("utf-8", "replace").splitlines()[1:])}
                size = int(fields["content-length"])
                if before:  # a range's reader steps from head to head until its own begins
                    stream.skip(size)
                    continue
                row = {c: fields.get(f) for c, f in FIELDS.items()}
                for c in ("record_id", "refers_to"):
                    row[c] = row[c] and row[c].strip("<>")
                given = row["payload_digest"]
                row["payload_digest"] = given and given.removeprefix("sha1:")  # predicates are tested on the column's value
                if not self._wanted(row):
                    stream.skip(size)
                    continue
                length = int(fields["warc-payload-length"]) if "warc-payload-length" in fields else None
                payload = None
                if self.payload and row["record_type"] == "response":
                    block = stream.read(size)
                    payload = block.partition(b"\r\n\r\n")[2] if fields.get("content-type", "").startswith("application/http") else block
                    if given and given != "sha1:" + sha1_base32(payload):
                        raise ValueError(f"{partition.path}: the payload of {row['record_id']} doesn't have its digest")
                    length = len(payload)
                else:
                    stream.skip(size)
                yield row["record_type"], row["record_id"], row["target_uri"], row["payload_digest"], row["refers_to"], length, payload, fields


class WarcSource(DataSource):
    """format("warc"): options path or files (one per line), record_type, payload (false: heads only), range_bytes."""

    @classmethod
    def name(cls) -> str:
        return "warc"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> DataSourceReader:
        return WarcReader(self.options)


def read_warc(spark: SparkSession, files: list[str] | None = None, path: str | None = None, **options) -> DataFrame:
    """Records of the archives; filters on the frame are pushed into the source."""
    prepare(spark)
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(WarcSource)
    reader = spark.read.format("warc").options(**{k: str(v) for k, v in options.items()})
    if files is not None:
        if not files:
            return spark.createDataFrame([], SCHEMA)
        reader = reader.option("files", "\n".join(files))
    return reader.load(path) if path else reader.load()
