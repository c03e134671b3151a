"""WARC archives: a distributed writer and a splittable reader.

Writer: one gzip member for each record, dealt to files by a hash of the record and written by tasks under
temporary names, then renamed, so a task that runs again replaces its own files; archives of an earlier run
in the folder are removed first.  A payload that an earlier record (least page id) holds is written as a
revisit that names the other's record.

Reader: files are cut into byte ranges; a task looks for gzip magic in its range, accepts a candidate
only if its member's start decompresses to a WARC version line and the headers parse, and owns the
records that start inside its range, reading past the end to finish the last one.

Defined cases: null payloads count as empty, null urls are written as an empty target; payloads below the
least size are all responses; rows with a null page id are written and read with a null id, as revisits if a
row with an id has their payload, else as responses; repeated rows, and rows of one id with equal payloads,
become records of their own, one of them the response and the others revisits that name their own id; rows
of one id with different payloads are judged each by its payload; an empty table makes no file and reads as
an empty result; further columns are ignored, whatever their names.
"""

from __future__ import annotations

import base64
import hashlib
import io
import zlib
from collections.abc import Iterator

import pyarrow as pa
import pyarrow.fs as pafs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.durable import Durable
from .text import blob, bound_batches, with_class

MAGIC = b"\x1f\x8b\x08"
#: Bytes of a range that a read task owns, and of one read.
SPLIT_BYTES, READ_BYTES = 4 << 20, 1 << 18
PAGES_PER_FILE = 4000
PROFILE = "http://netpreserve.org/warc/1.1/revisit/identical-payload-digest"
RECORDS = "page_id long, url string, payload_bytes long, payload_digest string, record_type string, refers_to long, payload binary"


def _open(uri: str) -> tuple[pafs.FileSystem, str]:
    return pafs.FileSystem.from_uri(uri) if "://" in uri or uri.startswith("file:") else (pafs.LocalFileSystem(), uri)


def sha1_base32(data: bytes) -> str:
    return base64.b32encode(hashlib.sha1(data).digest()).decode()


def record_bytes(page_id: int | None, url: str | None, payload: bytes, payload_digest: str, refers_to: int | None, revisit: bool) -> bytes:
    """One record as a gzip member."""
    key = "none" if page_id is None else str(page_id)
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: %d\r\n\r\n" % len(payload)
    block = http if revisit else http + payload
    head = ["WARC/1.1", f"WARC-Type: {'revisit' if revisit else 'response'}", f"WARC-Record-ID: <urn:page:{key}>", "WARC-Date: 1970-01-01T00:00:00Z"]
    head.append("WARC-Target-URI: " + " ".join((url or "").split()))
    head.append(f"WARC-Payload-Digest: sha1:{payload_digest}")
    if revisit:
        head += [f"WARC-Refers-To: <urn:page:{refers_to}>", f"WARC-Profile: {PROFILE}"]
    head += ["Content-Type: application/http; msgtype=response", f"Content-Length: {len(block)}"]
    raw = "\r\n".join(head).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"
    packer = zlib.compressobj(6, zlib.DEFLATED, 31)
    return packer.compress(raw) + packer.flush()


def parse_record(raw: bytes) -> tuple | None:
    """A decompressed record as a row of RECORDS, or None if it is none."""
    head, sep, rest = raw.partition(b"\r\n\r\n")
    lines = head.decode("utf-8", "replace").split("\r\n")
    if not sep or not lines[0].startswith("WARC/1."):
        return None
    fields = {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in lines[1:])}
    if not fields.get("content-length", "").isdigit() or "warc-type" not in fields:
        return None
    block = rest[: int(fields["content-length"])]
    payload_head, _, payload = block.partition(b"\r\n\r\n")
    number = lambda name: int(v) if (v := fields.get(name, "").removeprefix("<urn:page:").removesuffix(">")).lstrip("-").isdigit() else None
    revisit = fields["warc-type"] == "revisit"
    declared = next((int(x.split(b":")[1]) for x in payload_head.split(b"\r\n") if x.lower().startswith(b"content-length:")), 0)
    known = fields.get("warc-payload-digest", "").removeprefix("sha1:") if revisit else sha1_base32(payload)
    return number("warc-record-id"), fields.get("warc-target-uri"), declared if revisit else len(payload), known, fields["warc-type"], number("warc-refers-to"), None if revisit else payload


def classify(pages: DataFrame, least_bytes: int = 0, id_col: str = "page_id", html_col: str = "html", url_col: str = "url") -> DataFrame:
    """(page_id, url, payload, sha, refers_to, copies, first): equal rows are one with their number; `first` marks the
    response of the payload, or of a row of its own where refers_to is null.

    Classes of equal payloads are found over rows without payloads; the payloads move once, to meet their verdict.
    """
    store, data = Durable(pages.sparkSession, "warc-classes"), blob(F.col(html_col))
    rows = pages.select(F.col(id_col).cast("long").alias("page_id"), F.col(url_col).cast("string").alias("url"), data.alias("payload"), F.unhex(F.sha1(data)).alias("sha"), F.unhex(F.md5(data)).alias("md5"))
    named = F.concat_ws("|", F.coalesce(F.col("page_id").cast("string"), F.lit("none")), F.when(F.col("url").isNull(), "0").otherwise(F.concat(F.lit("1"), "url")))
    rows = rows.withColumn("key", F.concat("sha", "md5")).withColumn("rec", F.unhex(F.sha2(F.concat(F.col("key"), named.cast("binary")), 256)))
    narrow = rows.groupBy("rec", "key", "page_id").agg(F.count("*").alias("copies"), F.min(F.octet_length("payload")).alias("length"))
    narrow = store.save(narrow, "records")
    shared = narrow.filter((F.col("length") >= least_bytes) & F.col("page_id").isNotNull())
    classes = store.save(shared.groupBy("key").agg(F.min(F.struct("page_id", "rec")).alias("least"), F.count("*").alias("n")), "classes")
    met = with_class(narrow, classes, "key", "n", "rec")
    known = (F.col("length") >= least_bytes) & F.col("class").isNotNull()
    verdict = met.select("rec", "copies", F.when(known, F.col("class.least.page_id")).alias("refers_to"), F.when(known, F.col("class.least.rec") == F.col("rec")).otherwise(True).alias("first"))
    whole = rows.groupBy("rec").agg(*(F.first(c).alias(c) for c in ("page_id", "url", "payload", "sha")))
    return whole.join(verdict, "rec").select("page_id", "url", "payload", F.lower(F.hex("sha")).alias("sha"), "refers_to", "copies", "first")


def write_archives(records: DataFrame, folder: str, pages_per_file: int = PAGES_PER_FILE) -> int:
    """Write the records of classify() below folder, in place of the archives there; the number of records.

    Every task writes its own files, of at most pages_per_file records each.
    """
    spark = records.sparkSession
    _clear(spark, folder)

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        context = TaskContext.get()
        fs, root = _open(folder)
        temp, out, count, files = f"{root}/_{context.taskAttemptId()}.tmp", None, 0, 0

        def close() -> None:
            out.close()
            fs.move(temp, f"{root}/part-{context.partitionId():06d}-{files:04d}.warc.gz")

        for batch in batches:
            for page_id, url, payload, sha, refers_to, copies, first in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                digest = base64.b32encode(bytes.fromhex(sha)).decode()
                for copy in range(copies):
                    if out is not None and count % pages_per_file == 0:
                        close()
                        out, files = None, files + 1
                    if out is None:
                        fs.create_dir(root, recursive=True)
                        out = fs.open_output_stream(temp)
                    revisit = refers_to is not None and not (first and copy == 0)
                    out.write(record_bytes(page_id, url, payload, digest, refers_to if revisit else None, revisit))
                    count += 1
        if out is not None:
            close()
        yield pa.RecordBatch.from_pydict({"n": pa.array([count], pa.int64())})

    bound_batches(records)
    return records.mapInArrow(write, "n long").agg(F.sum("n").alias("n")).first().n or 0


def _clear(spark: SparkSession, folder: str) -> None:
    """Remove archives and unfinished files that an earlier run left in a folder."""
    at = spark._jvm.org.apache.hadoop.fs.Path(folder)
    fs = at.getFileSystem(spark._jsc.hadoopConfiguration())
    for status in fs.listStatus(at) if fs.exists(at) else ():
        name = status.getPath().getName()
        if name.endswith(".warc.gz") or (name.startswith("_") and name.endswith(".tmp")):
            fs.delete(status.getPath(), False)


def _list(spark: SparkSession, folder: str) -> list[tuple[str, int]]:
    """Archives of a folder with their lengths, by the cluster's own file system."""
    at = spark._jvm.org.apache.hadoop.fs.Path(folder)
    fs = at.getFileSystem(spark._jsc.hadoopConfiguration())
    if not fs.exists(at):
        return []
    return sorted((f"{folder}/{s.getPath().getName()}", s.getLen()) for s in fs.listStatus(at) if s.getPath().getName().endswith(".warc.gz"))


class _Window:
    """Buffered reads of a file at any position."""

    def __init__(self, file, size: int):
        self.file, self.size, self.start, self.data = file, size, 0, b""

    def at(self, position: int, n: int) -> bytes:
        if not (self.start <= position and position + n <= self.start + len(self.data)):
            self.file.seek(position)
            self.start, self.data = position, self.file.read(min(max(n, READ_BYTES), self.size - position))
        return self.data[position - self.start : position - self.start + n]


def read_range(file, size: int, start: int, end: int) -> Iterator[bytes]:
    """Decompressed records whose members start in [start, end)."""
    window, position = _Window(file, size), start
    while position < end:
        chunk = window.at(position, min(READ_BYTES, end - position + len(MAGIC) - 1, size - position))
        found = chunk.find(MAGIC)
        if found < 0:
            position += max(1, len(chunk) - len(MAGIC) + 1)
            continue
        position += found
        if position >= end:
            return
        member = _member(window, position, size)
        if member is None:  # magic bytes inside other data
            position += 1
            continue
        raw, length = member
        yield raw
        position += length


def _member(window: _Window, position: int, size: int) -> tuple[bytes, int] | None:
    unpack, out, used = zlib.decompressobj(31), io.BytesIO(), 0
    try:
        while not unpack.eof:
            if position + used >= size:
                return None
            chunk = window.at(position + used, min(1 << 14 if not used else READ_BYTES, size - position - used))
            out.write(unpack.decompress(chunk))
            used += len(chunk)
            if out.tell() >= 7 and not out.getbuffer()[:7].tobytes() == b"WARC/1.":
                return None
    except zlib.error:
        return None
    raw = out.getvalue()
    return (raw, used - len(unpack.unused_data)) if parse_record(raw) else None


def read_archives(spark: SparkSession, folder: str, split_bytes: int = SPLIT_BYTES) -> DataFrame:
    """All records below folder, as RECORDS."""
    files = _list(spark, folder)
    if not files:
        return spark.createDataFrame([], RECORDS)
    listed = spark.createDataFrame(files, "path string, size long")
    ranges = listed.select("path", "size", F.explode(F.sequence(F.lit(0).cast("long"), F.col("size") - 1, F.lit(split_bytes).cast("long"))).alias("start"))
    tasks = max(1, sum(-(-size // split_bytes) for _, size in files))
    from pyspark.sql.pandas.types import to_arrow_schema

    arrow = to_arrow_schema(spark.createDataFrame([], RECORDS).schema)

    def packed(rows: list[tuple]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(c, type=f.type) for c, f in zip(zip(*rows, strict=True), arrow, strict=True)], schema=arrow)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for path, size, start in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                fs, name = _open(path)
                rows, held = [], 0
                with fs.open_input_file(name) as file:
                    for raw in read_range(file, size, start, min(size, start + split_bytes)):
                        rows.append(parse_record(raw))
                        held += len(raw)
                        if held > 1 << 23:
                            yield packed(rows)
                            rows, held = [], 0
                if rows:
                    yield packed(rows)

    return ranges.repartition(min(tasks, 100_000), "path", "start").mapInArrow(run, RECORDS)


def round_trip(pages: DataFrame, folder: str, least_bytes: int = 0) -> DataFrame:
    """(page_id, payload_bytes, payload_digest, record_type, refers_to) as the archives written from pages give them."""
    write_archives(classify(pages, least_bytes), folder)
    return read_archives(pages.sparkSession, folder).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")

