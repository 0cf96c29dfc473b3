"""WARC archives: a deduplicating writer and a splittable reader.

Writer: one gzip member for each record (`response`, or `revisit` for payloads that another record holds), archives in a
folder that all executors share. A task attempt writes files under names of its own and reports them; only what finished
tasks have reported is listed, so retries leave no double records.

Reader: the archives are cut into byte ranges. A task scans its range for the gzip magic, accepts a candidate member if it
decompresses to a WARC header, and owns the records that start inside its range, reading past its end where the last one
does; a member that fails to decode is skipped by scanning on. No index and no whole-file read is needed.

The writer's list says how many records it wrote; complete() fails if another number was read.

Duplicates: payloads of at least `least` bytes with equal SHA-1 and length; the largest page_id among them is the response.
Only groups of two or more rows are kept for that, and they are broadcast up to BROADCAST_GROUPS rows, joined beyond.

Defined edge results: null html is an empty payload; null urls are written as an empty target; pages with a null id are
written and read back as null, and are revisits if another row has their payload; rows with equal id and payload are all
responses; an empty table gives no archives and no records.
"""

from __future__ import annotations

import hashlib
import urllib.parse
import uuid
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyarrow import fs as pafs
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import as_bytes, shared_folder, small, written

LEAST = 1000
BROADCAST_GROUPS = 50_000
ARCHIVE_BYTES = 1 << 30
SPLIT_BYTES = 8 << 20
MAX_TASKS = 20_000
MAGIC = b"\x1f\x8b\x08"
#: Bytes of a candidate member that are decompressed at a time until its WARC header ends.
HEADER_STEP = 1 << 14
DATE = "2024-01-01T00:00:00Z"

RECORD_SCHEMA = ("page_id long, url string, record_type string, record_id string, refers_to long, payload_bytes long, "
                 "payload_digest string, payload binary, archive string, start long")


def duplicates(pages: DataFrame, least: int = LEAST) -> DataFrame:
    """page_id, url, html and `keeper`: the page that holds the payload if another row has to, else null."""
    html = F.coalesce(F.col("html"), F.lit(""))
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), "url", html.alias("html"),
                        F.sha1(html.cast("binary")).alias("digest"), F.octet_length(html).alias("size"))
    groups = written(rows.filter(F.col("size") >= least).groupBy("digest", "size")
                     .agg(F.max("page_id").alias("keeper"), F.count("*").alias("n")).filter("n > 1 and keeper is not null")
                     .select(F.col("digest").alias("d"), F.col("size").alias("s"), "keeper"), "equal-payloads")
    side = F.broadcast(groups) if groups.count() <= BROADCAST_GROUPS else groups
    joined = rows.join(side, (F.col("digest") == F.col("d")) & (F.col("size") == F.col("s")), "left")
    return joined.select("page_id", "url", "html", F.when(F.col("page_id").eqNullSafe(F.col("keeper")), None).otherwise(F.col("keeper")).alias("keeper"))


def record_id(page_id) -> str:
    return f"<urn:uuid:{uuid.uuid5(uuid.NAMESPACE_URL, f'page:{page_id}')}>"


def member(page_id, url: str | None, payload: bytes, keeper, level: int = 6) -> bytes:
    """One record as a gzip member."""
    digest = hashlib.sha1(payload).hexdigest()
    body = b"" if keeper is not None else payload
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=utf-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    target = urllib.parse.quote(url or "", safe="".join(chr(c) for c in range(33, 127)))
    lines = ["WARC/1.1", f"WARC-Type: {'response' if keeper is None else 'revisit'}", f"WARC-Record-ID: {record_id(page_id)}", f"WARC-Date: {DATE}",
             f"WARC-Target-URI: {target}", f"WARC-Payload-Digest: sha1:{digest}", f"X-Payload-Length: {len(payload)}"]
    if page_id is not None:
        lines.append(f"X-Page-Id: {page_id}")
    if keeper is not None:
        lines += ["WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", f"WARC-Refers-To: {record_id(keeper)}", f"X-Refers-To-Page-Id: {keeper}"]
    lines += ["Content-Type: application/http;msgtype=response", f"Content-Length: {len(http) + len(body)}"]
    z = zlib.compressobj(level, zlib.DEFLATED, 31)
    return z.compress("\r\n".join(lines).encode() + b"\r\n\r\n" + http + body + b"\r\n\r\n") + z.flush()


def write_archives(pages: DataFrame, folder: str | None = None, archive_bytes: int = ARCHIVE_BYTES) -> DataFrame:
    """Writes pages (page_id, url, html, keeper) and returns the written list: archive, bytes, records."""
    spark = pages.sparkSession
    folder = folder or shared_folder(spark, "warc")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        store, base = pafs.FileSystem.from_uri(folder)
        store.create_dir(base, recursive=True)
        done, out, name = [], None, ""
        size = records = 0
        for b in small(batches):
            for page, url, html, keeper in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), as_bytes(b.column(2)), b.column(3).to_pylist()):
                if out is None:
                    name = f"{base}/part-{TaskContext.get().partitionId():06d}-{uuid.uuid4().hex}.warc.gz"
                    out, size, records = store.open_output_stream(name, compression=None), 0, 0
                data = member(page, url, html, keeper)
                out.write(data)
                size += len(data)
                records += 1
                if size >= archive_bytes:
                    out.close()
                    done.append((name, size, records))
                    out = None
        if out is not None:
            out.close()
            done.append((name, size, records))
        cols = list(zip(*done)) or [(), (), ()]
        names = [f"{folder.rstrip('/')}/{n.rsplit('/', 1)[1]}" for n in cols[0]]
        yield pa.RecordBatch.from_arrays([pa.array(names, pa.string()), pa.array(cols[1], pa.int64()), pa.array(cols[2], pa.int64())], ["archive", "bytes", "records"])

    return written(pages.select("page_id", "url", "html", "keeper").mapInArrow(run, "archive string, bytes long, records long"), "warc-list")


class RangeReader:
    """Records of one archive that start in [start, end)."""

    STEP = 1 << 20

    def __init__(self, file, size: int):
        self.file, self.size = file, size
        self.base, self.data = 0, b""

    def _at(self, offset: int, n: int) -> bytes:
        """n bytes from offset, as far as there are; keeps one buffer."""
        if not (self.base <= offset and offset + n <= self.base + len(self.data)):
            self.base, self.data = offset, self.file.read_at(min(max(n, self.STEP), self.size - offset), offset) if offset < self.size else b""
        return self.data[offset - self.base:offset - self.base + n]

    def _header(self, offset: int) -> bool:
        """Whether a WARC record's header can be decoded from a gzip member at offset."""
        z, text, here = zlib.decompressobj(31), bytearray(), offset
        try:
            while not z.eof and b"\r\n\r\n" not in text[-HEADER_STEP - 3:]:
                piece = z.unconsumed_tail
                if not piece:
                    piece = self._at(here, HEADER_STEP)
                    here += len(piece)
                    if not piece:
                        return False
                text += z.decompress(piece, HEADER_STEP)
                if not text[:7] == b"WARC/1."[:len(text)]:
                    return False
        except zlib.error:
            return False
        head, end, _ = text.partition(b"\r\n\r\n")
        return head.startswith(b"WARC/1.") and bool(end) and b"\r\nWARC-Type:" in head

    def _find(self, offset: int, end: int) -> int | None:
        """The first valid member that starts in [offset, end)."""
        while offset < end:
            piece = self._at(offset, min(self.STEP, end - offset + len(MAGIC) - 1))
            at = piece.find(MAGIC)
            if at < 0:
                offset += max(1, len(piece) - len(MAGIC) + 1)
                continue
            if offset + at >= end:
                return None
            if self._header(offset + at):
                return offset + at
            offset += at + 1
        return None

    def _member(self, offset: int) -> tuple[bytes, int] | None:
        """Content and end of the member at offset; None if it is damaged."""
        z, parts, here = zlib.decompressobj(31), [], offset
        try:
            while not z.eof:
                piece = self._at(here, 1 << 16)
                if not piece:
                    return None
                parts.append(z.decompress(piece))
                here += len(piece)
        except zlib.error:
            return None
        return b"".join(parts), here - len(z.unused_data)

    def records(self, start: int, end: int) -> Iterator[tuple[int, dict[str, str], bytes]]:
        offset = self._find(start, end)
        while offset is not None:
            got = self._member(offset)
            if got is None:
                offset = self._find(offset + 1, end)
                continue
            content, after = got
            head, _, block = content.partition(b"\r\n\r\n")
            fields = dict(line.split(": ", 1) for line in head.decode("utf-8", "replace").split("\r\n")[1:] if ": " in line)
            yield offset, fields, block[:int(fields.get("Content-Length", "0"))]
            offset = after if after < end and self._header(after) else self._find(after, end)


def read_archives(spark: SparkSession, archives: DataFrame, split_bytes: int = SPLIT_BYTES, payloads: bool = True) -> DataFrame:
    """archives (archive, bytes) -> one row per record, RECORD_SCHEMA. Digest and length of a response are those of the
    payload that was read; a revisit carries them in its header."""
    ranges = archives.filter("bytes > 0").select("archive", "bytes", F.explode(F.sequence(F.lit(0).cast("long"), F.col("bytes") - 1, F.lit(split_bytes).cast("long"))).alias("start"))
    # the rows are tiny, so a shuffle by size would read everything in one task: a task for each range, as far as MAX_TASKS
    n = archives.agg(F.sum(F.ceil(F.col("bytes") / split_bytes))).first()[0] or 1
    ranges = ranges.withColumn("end", F.least(F.col("start") + split_bytes, F.col("bytes"))).repartition(min(int(n), MAX_TASKS))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kinds = [pa.int64(), pa.string(), pa.string(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.binary(), pa.string(), pa.int64()]
        names = [x.split()[0] for x in RECORD_SCHEMA.split(", ")]
        number = lambda x: None if x is None else int(x)

        def batch(rows):
            cols = list(zip(*rows)) or [()] * len(names)
            return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds)], names)

        for b in batches:
            for archive, size, start, end in zip(*(b.column(k).to_pylist() for k in range(4))):
                store, path = pafs.FileSystem.from_uri(archive)
                rows, held = [], 0
                with store.open_input_file(path) as file:
                    for at, fields, block in RangeReader(file, size).records(start, end):
                        payload = block.partition(b"\r\n\r\n")[2]
                        kind = fields["WARC-Type"]
                        if kind == "response":
                            length, digest = len(payload), hashlib.sha1(payload).hexdigest()
                        else:
                            length, digest = number(fields.get("X-Payload-Length")), fields.get("WARC-Payload-Digest", "").removeprefix("sha1:")
                        rows.append((number(fields.get("X-Page-Id")), fields.get("WARC-Target-URI"), kind, fields.get("WARC-Record-ID"),
                                     number(fields.get("X-Refers-To-Page-Id")), length, digest, payload if payloads else None, archive, at))
                        held += len(payload) if payloads else 0
                        if held > 16 << 20 or len(rows) >= 10_000:
                            yield batch(rows)
                            rows, held = [], 0
                yield batch(rows)

    return ranges.mapInArrow(run, RECORD_SCHEMA)


def complete(records: DataFrame, archives: DataFrame) -> DataFrame:
    """The records read from the archives, written; fails if they are not as many as the archives' list says."""
    records = written(records, "warc-records")
    read, wrote = records.count(), archives.agg(F.sum("records")).first()[0] or 0
    if read != wrote:
        raise RuntimeError(f"{read} records were read of {wrote} written")
    return records
