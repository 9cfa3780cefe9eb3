"""WARC archives: a writer with one gzip member for each record, and a splittable reader.

Writer: of records with equal payloads of at least MIN_BYTES, that with the largest page_id is a response, the others are
revisits that refer to it and carry its digest and length, not its payload. A task writes one archive under a temporary
name and renames it, so a task that runs twice leaves one whole file. Reader: a task gets a byte range, looks for gzip
magic, takes a candidate for a member only if it decodes and begins with a WARC header, and owns the records that start
inside its range, of which the last may end beyond it.

Null html is an empty payload. A null page_id is written as `none` and read as null; equal payloads whose ids are all null
are responses. Rows that share the largest id are all responses. Empty tables give an empty archive. Payloads of any
length are whole, one at a time in memory. Columns other than page_id, url and html are not stored."""

from __future__ import annotations

import base64
import hashlib
import uuid
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import materialise, shared_dir

MIN_BYTES = 1000
SPLIT_BYTES = 8 << 20
MAGIC = b"\x1f\x8b\x08"
LEVEL = 3
CHUNK = 1 << 20


def file_system(uri: str):
    """(file system, path) of a folder that driver and executors see."""
    from pyarrow import fs

    return fs.FileSystem.from_uri(uri) if "://" in uri or uri.startswith("file:") else (fs.LocalFileSystem(), uri)


def marked(pages: DataFrame, min_bytes: int = MIN_BYTES) -> DataFrame:
    """pages (page_id, url, payload) plus refers_to, not null for revisits. Only digests and ids are grouped; payloads move
    once, by page_id."""
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), "url", F.coalesce(F.encode("html", "UTF-8"), F.lit(b"")).alias("payload"))
    named = rows.where(F.octet_length("payload") >= min_bytes).select("page_id", F.sha1("payload").alias("digest"))
    last = named.groupBy("digest").agg(F.max("page_id").alias("refers_to"), F.count("*").alias("n")).where("n > 1 and refers_to is not null").drop("n")
    again = named.join(last, "digest").where("page_id <> refers_to").select("page_id", F.col("digest").alias("of"), "refers_to").distinct()
    out = rows.join(again, "page_id", "left")
    # Rows that share an id but not the payload keep their own.
    other = F.col("of").isNotNull() & (F.sha1("payload") != F.col("of"))
    return out.select("page_id", "url", "payload", F.when(~other, F.col("refers_to")).alias("refers_to"))



def record(page_id: int | None, url: str | None, payload: bytes, refers_to: int | None) -> bytes:
    """One record: headers, block, two line ends."""
    name = lambda k: f"<urn:page:{'none' if k is None else k}>"
    digest = base64.b32encode(hashlib.sha1(payload).digest()).decode()
    http = f"HTTP/1.1 200 OK\r\nContent-Type: text/html; charset=UTF-8\r\nContent-Length: {len(payload)}\r\n\r\n".encode()
    revisit = refers_to is not None
    block = http if revisit else http + payload
    head = [
        "WARC/1.1",
        f"WARC-Type: {'revisit' if revisit else 'response'}",
        f"WARC-Record-ID: {name(page_id)}",
        "WARC-Date: 1970-01-01T00:00:00Z",
        f"WARC-Target-URI: {(url or 'urn:none').replace(chr(13), '%0D').replace(chr(10), '%0A')}",
        f"WARC-Payload-Digest: sha1:{digest}",
        "Content-Type: application/http; msgtype=response",
        f"Content-Length: {len(block)}",
    ]
    if revisit:
        head += ["WARC-Profile: http://netpreserve.org/warc/1.1/revisit/identical-payload-digest", f"WARC-Refers-To: {name(refers_to)}"]
    return "\r\n".join(head).encode() + b"\r\n\r\n" + block + b"\r\n\r\n"


def member(data: bytes) -> bytes:
    pack = zlib.compressobj(LEVEL, zlib.DEFLATED, 31)
    return pack.compress(data) + pack.flush()


def write(rows: DataFrame, folder: str) -> DataFrame:
    """Writes the rows of marked() to archives in the folder; (file, bytes, records) of each, already on disk."""

    def run(batches):
        from pyspark import TaskContext

        fs, path = file_system(folder)
        fs.create_dir(path, recursive=True)
        part = TaskContext.get().partitionId()
        name, temporary = f"part-{part:06d}.warc.gz", f".{part:06d}-{uuid.uuid4().hex}"
        size = records = 0
        with fs.open_output_stream(f"{path}/{temporary}", compression=None) as out:
            for batch in batches:
                for i in range(batch.num_rows):
                    page_id, url, payload, refers_to = (batch.column(c)[i].as_py() for c in range(4))
                    data = member(record(page_id, url, payload, refers_to))
                    out.write(data)
                    size += len(data)
                    records += 1
        if records:
            fs.move(f"{path}/{temporary}", f"{path}/{name}")
            yield pa.RecordBatch.from_pydict({"file": [name], "bytes": pa.array([size], pa.int64()), "records": pa.array([records], pa.int64())})
        else:
            fs.delete_file(f"{path}/{temporary}")

    return materialise(rows.mapInArrow(run, "file string, bytes long, records long"), "archives")


class Range:
    """Bytes of a file from an offset on, read in chunks as they are asked for."""

    def __init__(self, file, low: int, size: int):
        self.file, self.base, self.size = file, low, size
        self.held = bytearray()

    def have(self, end: int) -> bool:
        """Reads on until the bytes before `end` (a file offset) are held, or the file ends."""
        while self.base + len(self.held) < end and self.base + len(self.held) < self.size:
            self.file.seek(self.base + len(self.held))
            self.held += self.file.read(max(CHUNK, end - self.base - len(self.held)))
        return self.base + len(self.held) >= end

    def drop(self, before: int) -> None:
        del self.held[: before - self.base]
        self.base = before


def inflate(view: Range, at: int) -> tuple[bytes, int] | None:
    """(content, end) of the gzip member at the offset, if it is one of a WARC record; headers are decoded first."""
    unpack = zlib.decompressobj(31)
    out, pos, checked = [], at, False
    try:
        while not unpack.eof:
            step = 512 if not checked else CHUNK
            if not view.have(pos + 1):
                return None
            view.have(pos + step)
            piece = bytes(view.held[pos - view.base : pos - view.base + step])
            out.append(unpack.decompress(piece))
            pos += len(piece) - len(unpack.unused_data)
            if not checked and (head := b"".join(out)[:7]):
                if not b"WARC/1.".startswith(head):
                    return None
                checked = len(head) == 7
    except zlib.error:
        return None
    data = b"".join(out)
    return (data, pos) if data.startswith(b"WARC/1.") and b"\r\n\r\n" in data else None


def records(file, start: int, end: int, size: int) -> Iterator[bytes]:
    """The records whose members start in [start, end)."""
    view, at = Range(file, start, size), start
    while at < end:
        view.drop(at)
        view.have(min(end + 2, at + CHUNK))
        k = view.held.find(MAGIC)
        if k < 0 or at + k >= end:
            if view.base + len(view.held) >= min(end + 2, size):
                return
            at = max(at + 1, view.base + len(view.held) - 2)
            continue
        at += k
        if found := inflate(view, at):
            yield found[0]
            at = found[1]
        else:
            at += 1


PARSED = "page_id long, url string, payload binary, payload_bytes long, payload_digest string, record_type string, refers_to long"


def parse(data: bytes) -> tuple:
    head, _, rest = data.partition(b"\r\n\r\n")
    fields = {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in head.decode().split("\r\n")[1:])}
    block = rest[: int(fields["content-length"])]
    http, _, payload = block.partition(b"\r\n\r\n")
    length = next(int(x.split(b":")[1]) for x in http.split(b"\r\n") if x.lower().startswith(b"content-length:"))
    number = lambda v: None if v is None or v == "<urn:page:none>" else int(v.removeprefix("<urn:page:").removesuffix(">"))
    response = fields["warc-type"] == "response"
    digest = base64.b32decode(fields["warc-payload-digest"].removeprefix("sha1:")).hex()
    if response and (len(payload) != length or hashlib.sha1(payload).hexdigest() != digest):
        raise ValueError(f"record {fields['warc-record-id']} does not match its digest")
    return number(fields["warc-record-id"]), fields["warc-target-uri"], payload if response else None, length, digest, fields["warc-type"], number(fields.get("warc-refers-to"))


def read(spark: SparkSession, folder: str, *, split_bytes: int = SPLIT_BYTES, columns: list[str] | None = None) -> DataFrame:
    """All records of the archives in the folder (PARSED, or some of its columns), by byte ranges of split_bytes."""
    from pyarrow import fs as pfs

    fs, path = file_system(folder)
    files = [f for f in fs.get_file_info(pfs.FileSelector(path, allow_not_found=True)) if f.is_file and f.base_name.endswith(".warc.gz")]
    fields = dict(x.split() for x in PARSED.split(", "))
    columns = columns or list(fields)
    schema = ", ".join(f"{c} {fields[c]}" for c in columns)
    # One row for each file comes from the driver; the ranges are made by the executors.
    listed = spark.createDataFrame([(f.base_name, f.size) for f in files], "file string, size long")
    ranges = listed.select("file", "size", F.explode(F.sequence(F.lit(0).cast("long"), F.greatest(F.col("size") - 1, F.lit(0)), F.lit(split_bytes).cast("long"))).alias("start"))
    count = sum(-(-f.size // split_bytes) for f in files)
    pick = [list(fields).index(c) for c in columns]
    kinds = {"long": pa.int64(), "string": pa.string(), "binary": pa.binary()}

    def run(batches):
        fs, path = file_system(folder)
        for batch in batches:
            for x in batch.to_pylist():
                with fs.open_input_file(f"{path}/{x['file']}") as f:
                    rows: list[tuple] = []
                    held = 0
                    for data in records(f, x["start"], min(x["start"] + split_bytes, x["size"]), x["size"]):
                        rows.append(parse(data))
                        held += len(data)
                        if len(rows) >= 1000 or held >= CHUNK:
                            yield pa.RecordBatch.from_arrays([pa.array([r[p] for r in rows], kinds[fields[c]]) for c, p in zip(columns, pick, strict=True)], names=columns)
                            rows, held = [], 0
                    if rows:
                        yield pa.RecordBatch.from_arrays([pa.array([r[p] for r in rows], kinds[fields[c]]) for c, p in zip(columns, pick, strict=True)], names=columns)

    return ranges.repartition(max(1, count), "file", "start").mapInArrow(run, schema)


def archive(pages: DataFrame, folder: str | None = None, *, min_bytes: int = MIN_BYTES) -> tuple[str, DataFrame]:
    """Writes pages (page_id, url, html) to archives; the folder and the list of files."""
    folder = folder or f"{shared_dir(pages.sparkSession)}/warc-{uuid.uuid4().hex[:12]}"
    return folder, write(marked(pages, min_bytes), folder)
