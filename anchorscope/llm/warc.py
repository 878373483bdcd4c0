"""WARC archives: a writer with one gzip member a record, and a splittable reader.

Writer: equal payloads of at least `MIN_SHARED` bytes are stored once, as the response of the smallest page id; the
others become revisit records that name it. Every task writes archive files of its own under a temporary name and
renames them when whole, so a task that is run again replaces its files and never leaves half of one.

Reader: archive files are dealt out as byte ranges. A task looks for gzip magic in its range and takes a candidate only if the
member there decodes to a whole WARC header; it owns the records whose members begin inside its range and
reads the last of them beyond the end. From one member to the next it goes by the member's true end, so magic bytes
inside a member count only where a range begins inside that member, and there the header must decode.
(A range that begins inside an incompressible payload which is itself a WARC archive could be misled; `range_bytes` above the
largest such payload rules this out.)

Headers are as long as their urls; a header and its block must fit into a task's memory.

Paths are URIs of the shared folder, opened through pyarrow's file systems (local, HDFS, S3).

Null html is an empty payload; a null url leaves out the target; null ids are written as "null", read back as
null and count as larger than any id; pages with equal id and payload are responses both; empty tables give no
record; other columns are not archived.
"""

from __future__ import annotations

import hashlib
import uuid
import zlib
from collections.abc import Iterator
from urllib.parse import quote

import pyarrow as pa
import pyarrow.fs as pafs
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .spark import by_size, cut, shared_folder

MIN_SHARED = 100
RANGE_BYTES = 8 << 20
_MAGIC = b"\x1f\x8b\x08"
_READ = 1 << 18
_HTTP = "HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {}\r\n\r\n"
#: Pages of one payload beyond which its digest is met by broadcast or under salts.
HOT = 10_000
_PREFIX = "urn:page:"


def _open(uri: str) -> tuple[pafs.FileSystem, str]:
    return pafs.FileSystem.from_uri(uri if "://" in uri or uri.startswith("file:") else f"file://{uri}")


# ---------------------------------------------------------------- writing


def record(page_id: int | None, url: str | None, payload: bytes, sha256: str, refers_to: int | None) -> bytes:
    """One WARC record as a gzip member."""
    name = lambda i: f"<{_PREFIX}{'null' if i is None else i}>"
    lines = ["WARC/1.1", f"WARC-Type: {'response' if refers_to is None else 'revisit'}", f"WARC-Record-ID: {name(page_id)}", "WARC-Date: 2024-01-01T00:00:00Z"]
    if url is not None:
        lines.append(f"WARC-Target-URI: {quote(url, safe='%:/?#[]@!$&()*+,;=-._~' + chr(39))}")
    lines.append(f"WARC-Payload-Digest: sha256:{sha256}")
    if refers_to is not None:
        lines += ["WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", f"WARC-Refers-To: {name(refers_to)}"]
    block = _HTTP.format(len(payload)).encode() + (payload if refers_to is None else b"")  # of a revisit the headers of the page that it stands for
    lines += ["Content-Type: application/http; msgtype=response", f"Content-Length: {len(block)}"]
    pack = zlib.compressobj(6, zlib.DEFLATED, 31)
    return pack.compress("\r\n".join(lines).encode() + b"\r\n\r\n" + block + b"\r\n\r\n") + pack.flush()


def plan_records(pages: DataFrame, *, page_id: str = "page_id", url: str = "url", html: str = "html") -> DataFrame:
    """page_id, url, payload, sha256, refers_to: what each record is to hold."""
    rows = pages.select(F.col(f"`{page_id}`").cast("long").alias("page_id"), F.col(f"`{url}`").alias("url"), F.coalesce(F.col(f"`{html}`"), F.lit("")).cast("binary").alias("payload"))
    rows = rows.withColumn("sha256", F.sha2("payload", 256))
    shared = rows.filter(F.octet_length("payload") >= MIN_SHARED).groupBy("sha256").agg(F.min("page_id").alias("_least"), F.count("*").alias("_n")).filter("_n > 1")
    shared = cut(shared)
    # payloads of very many pages are few; their pages stay where they are, the others meet by digest
    hot = by_size(shared.filter(F.col("_n") > HOT).select("sha256", F.col("_least").alias("_hot")))
    rows = rows.join(hot, "sha256", "left")
    own = F.when(F.col("_hot").isNull(), F.col("sha256")).otherwise(F.concat_ws("#", "sha256", F.xxhash64("page_id", "url")))
    cold = shared.filter(F.col("_n") <= HOT).select(F.col("sha256").alias("_key"), F.col("_least").alias("_cold"))
    rows = rows.withColumn("_key", own).join(cold, "_key", "left").withColumn("_least", F.coalesce("_hot", "_cold"))
    refers = F.when(F.col("page_id").isNull() | (F.col("_least") < F.col("page_id")), F.col("_least"))
    return rows.select("page_id", "url", "payload", "sha256", refers.alias("refers_to"))


def write_archives(pages: DataFrame, folder: str, **columns) -> DataFrame:
    """Writes the archives under `folder` (a URI that all tasks reach); returns file, bytes, records (run once, when acted on)."""
    rows = plan_records(pages, **columns).sortWithinPartitions("page_id", "sha256")

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        context = TaskContext.get()
        fs, path = _open(folder)
        fs.create_dir(path, recursive=True)
        final, temporary = f"{path}/part-{context.partitionId():06d}.warc.gz", f"{path}/.try-{context.taskAttemptId()}-{uuid.uuid4().hex}"
        n = size = 0
        with fs.open_output_stream(temporary, compression=None) as out:
            for batch in batches:
                for row in batch.to_pylist():
                    data = record(row["page_id"], row["url"], row["payload"], row["sha256"], row["refers_to"])
                    out.write(data)
                    n, size = n + 1, size + len(data)
        if n:
            fs.move(temporary, final)
            yield pa.RecordBatch.from_pydict({"file": [final], "bytes": [size], "records": [n]})
        else:
            fs.delete_file(temporary)

    return rows.mapInArrow(write, "file string, bytes long, records long")


# ---------------------------------------------------------------- reading


class _Source:
    """A file read forward in blocks from any place."""

    def __init__(self, handle, size: int, at: int):
        self.handle, self.size, self.base, self.data = handle, size, at, bytearray()

    def fill(self, to: int) -> bool:
        """Holds bytes up to `to` if the file has them."""
        while self.base + len(self.data) < min(to, self.size):
            self.data += self.handle.read_at(min(_READ, self.size - self.base - len(self.data)), self.base + len(self.data))
        return self.base + len(self.data) >= to

    def drop(self, before: int) -> None:
        if before > self.base:
            del self.data[: before - self.base]
            self.base = before


def _member(source: _Source, at: int) -> tuple[dict[str, str], bytes, int] | None:
    """Header fields, block and end of the member at `at`; None unless it decodes to a WARC record."""
    unpack, out, place = zlib.decompressobj(31), bytearray(), at
    try:
        while not unpack.eof:
            if not source.fill(place + 1):
                return None  # the file ends inside
            some = source.data[place - source.base : place - source.base + _READ]
            out += unpack.decompress(some)
            place += len(some) - len(unpack.unused_data)
            if not b"WARC/1.".startswith(bytes(out[:7])):
                return None
    except zlib.error:
        return None
    head, gap, rest = bytes(out).partition(b"\r\n\r\n")
    lines = head.decode("utf-8", "replace").split("\r\n")
    fields = {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in lines[1:])}
    if not gap or not lines[0].startswith("WARC/1.") or not fields.get("content-length", "").isdigit() or len(rest) < (n := int(fields["content-length"])):
        return None
    return fields, rest[:n], place


def read_range(handle, size: int, start: int, end: int) -> Iterator[tuple[int, dict[str, str], bytes]]:
    """Place, header fields and block of every record whose member begins in [start, end)."""
    source, at = _Source(handle, size, start), start
    while at < end:
        source.drop(at)
        source.fill(at + _READ)
        found = source.data.find(_MAGIC, at - source.base)
        if found < 0:
            at = source.base + max(len(source.data) - len(_MAGIC) + 1, at - source.base + 1)
            if source.base + len(source.data) >= size:
                return
            continue
        at = source.base + found
        if at >= end:
            return
        if (got := _member(source, at)) is None:
            at += 1
            continue
        yield at, got[0], got[1]
        at = got[2]


def split_files(spark: SparkSession, folder: str, range_bytes: int = RANGE_BYTES) -> DataFrame:
    """file, size, start, end: byte ranges of all archives in a folder, as a table over the cluster."""
    jvm = spark.sparkContext._jvm
    root = jvm.org.apache.hadoop.fs.Path(folder)
    fs = root.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    files = [(str(s.getPath().toString()), int(s.getLen())) for s in fs.listStatus(root) if not s.getPath().getName().startswith((".", "_"))] if fs.exists(root) else []
    table = spark.createDataFrame(files, "file string, size long")
    starts = F.explode(F.expr(f"sequence(0L, greatest(size - 1, 0L), {int(range_bytes)}L)"))
    ranges = table.filter("size > 0").withColumn("start", starts).withColumn("end", F.least(F.col("size"), F.col("start") + range_bytes))
    return ranges.repartition(max(1, sum(-(-n // range_bytes) for _, n in files)), "file", "start")


def read_archives(spark: SparkSession, folder: str, range_bytes: int = RANGE_BYTES) -> DataFrame:
    """file, offset, record_type, page_id, url, refers_to, payload_digest, payload_bytes, payload for every record of the archives in `folder`.

    The digest of a response is taken of the payload read, and must be that of its header. A revisit has the digest and the size (null if its HTTP headers have none) of the
    payload that it stands for, so nothing has to be joined to it.
    """

    def length(headers: bytes) -> int | None:
        stated = [v.strip() for k, _, v in (line.partition(b":") for line in headers.split(b"\r\n")) if k.strip().lower() == b"content-length"]
        return int(stated[0]) if stated and stated[0].isdigit() else None

    def number(name: str | None) -> int | None:
        text = (name or "").strip("<>").removeprefix(_PREFIX)
        return int(text) if text.lstrip("-").isdigit() else None

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = ["file", "offset", "record_type", "page_id", "url", "refers_to", "payload_digest", "payload_bytes", "payload"]
        types = [pa.string(), pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64(), pa.binary()]
        for batch in batches:
            for split in batch.to_pylist():
                fs, path = _open(split["file"])
                rows, held = [], 0
                with fs.open_input_file(path) as handle:
                    for at, fields, block in read_range(handle, split["size"], split["start"], split["end"]):
                        kind, (headers, _, payload) = fields["warc-type"], block.partition(b"\r\n\r\n")
                        stored = fields.get("warc-payload-digest", "").removeprefix("sha256:")
                        if kind == "response" and hashlib.sha256(payload).hexdigest() != stored:
                            raise ValueError(f"payload of the record at {at} of {split['file']} doesn't match its digest")
                        rows.append((split["file"], at, kind, number(fields.get("warc-record-id")), fields.get("warc-target-uri"), number(fields.get("warc-refers-to")), stored, len(payload) if kind == "response" else length(headers), payload if kind == "response" else None))
                        held += len(payload)
                        if held > 4 << 20:
                            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), types, strict=True)], names=names)
                            rows, held = [], 0
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), types, strict=True)], names=names)

    schema = "file string, offset long, record_type string, page_id long, url string, refers_to long, payload_digest string, payload_bytes long, payload binary"
    return split_files(spark, folder, range_bytes).mapInArrow(read, schema)


def report(pages: DataFrame, folder: str | None = None) -> DataFrame:
    """Writes pages as archives, reads these back; raises if not all are read."""
    spark = pages.sparkSession
    folder = folder or f"{shared_folder(spark)}/warc-{uuid.uuid4().hex}"
    written = write_archives(pages, folder).agg(F.sum("records")).first()[0] or 0
    rows = cut(read_archives(spark, folder).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to"))
    if (read := rows.count()) != written:
        raise ValueError(f"{written} records written to {folder}, {read} read")
    return rows
