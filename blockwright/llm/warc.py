"""WARC files: from one gzip stream per file to one gzip member per record, with an index.

A monolithic file (all records in one gzip stream) can only be read from its start. The
normaliser inflates each such file once, as a stream, rewrites every record as a gzip
member of its own and writes a sidecar index (a line of JSON per record: number, offset,
length, type, uri, record id, payload bytes). Afterwards any record is read by one seek.

Files are the unit of work: a task streams a file with bounded memory (a record at a
time). Names are fixed by the input and files appear under them only when complete
(written under a name of the attempt, then moved), so a task that is lost or run twice does no harm.
Paths are URIs of any file system that Arrow knows and all executors share.

Defined results: an input that already has one member a record, or several streams, gives
the same output; a stream that breaks off keeps its complete records and is reported as
"truncated"; one with something else than a record as "malformed" from there on; an empty
file gives an empty file and index. In `write_monolithic` null urls and ids leave their
headers out; a null page is a record without payload marked `WARC-Truncated: unspecified`
and is read back as null, an empty one as empty; repeated rows are records of their own;
other columns are ignored; an empty table writes no file.
"""

from __future__ import annotations

import hashlib
import json
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.scratch import cut, scratch_path

READ = 1 << 20
INDEX_SCHEMA = "path string, number bigint, offset bigint, length bigint, type string, uri string, record_id string, payload_bytes bigint, status string"
#: Records (or a file, where it has none) carry how their file ended.
COMPLETE, TRUNCATED, MALFORMED = "complete", "truncated", "malformed"


def _fs(uri: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(uri if "://" in uri or uri.startswith("file:") else "file://" + uri)


def _publish(fs, temporary: str, final: str) -> None:
    fs.move(temporary, final)


def inflated(stream, status: list[str]) -> Iterator[bytes]:
    """Pieces of the text of one or more gzip streams; status[0] is set to how it ended."""
    z, fresh = zlib.decompressobj(31), True
    while True:
        raw = stream.read(READ)
        if not raw:
            break
        out = b""
        # a full piece may have left text inside the decompressor though all input is taken
        while raw or len(out) == READ:
            try:
                out = z.decompress(raw, READ)
            except zlib.error:
                status[0] = TRUNCATED
                return
            fresh = False
            if out:
                yield out
            raw = z.unconsumed_tail
            if z.eof:
                raw, out = z.unused_data, b""
                z, fresh = zlib.decompressobj(31), True
    if not fresh:
        status[0] = TRUNCATED


def records(pieces: Iterator[bytes], status: list[str]) -> Iterator[tuple[bytes, bytes]]:
    """(header block, payload) of each complete record."""
    buf = bytearray()
    live = True

    def more() -> bool:
        nonlocal live
        got = next(pieces, None) if live else None
        if got is None:
            live = False
            return False
        buf.extend(got)
        return True

    while True:
        while len(buf) < 5 and more():
            pass
        lead = len(buf) - len(buf.lstrip(b"\r\n"))
        if lead:
            del buf[:lead]
            continue
        if not buf:
            return
        if not bytes(buf[:5]).startswith(b"WARC/"[: len(buf)]):
            status[0] = MALFORMED
            return
        seen = 0
        while (end := buf.find(b"\r\n\r\n", seen)) < 0:
            seen = max(0, len(buf) - 3)
            if not more():
                status[0] = TRUNCATED
                return
        head = bytes(buf[: end + 4])
        try:
            size = int(header(head).get("content-length", "x"))
        except ValueError:
            status[0] = MALFORMED
            return
        total = end + 4 + size
        while len(buf) < total and more():
            pass
        if len(buf) < total:
            status[0] = TRUNCATED
            return
        yield head, bytes(buf[end + 4 : total])
        del buf[:total]


def header(head: bytes) -> dict[str, str]:
    """Header fields of a record, by lower-case name."""
    lines = head.decode("utf-8", "replace").split("\r\n")[1:]
    return {k.strip().lower(): v.strip() for k, _, v in (x.partition(":") for x in lines) if v or k}


def member(head: bytes, payload: bytes, level: int = 6) -> bytes:
    """One record as one gzip member, the same bytes every time."""
    z = zlib.compressobj(level, zlib.DEFLATED, 31)
    return z.compress(head + payload + b"\r\n\r\n") + z.flush()


def normalise_file(source: str, target: str, attempt: str = "0") -> list[tuple]:
    """Rewrite one file; rows of the index."""
    fs_in, p_in = _fs(source)
    fs_out, p_out = _fs(target)
    status, rows, at = [COMPLETE], [], 0
    tmp, tmp_index = f"{p_out}.{attempt}.part", f"{p_out}.idx.{attempt}.part"
    with fs_in.open_input_stream(p_in, compression=None) as src, fs_out.open_output_stream(tmp, compression=None) as out, fs_out.open_output_stream(tmp_index, compression=None) as index:
        for number, (head, payload) in enumerate(records(inflated(src, status), status)):
            data = member(head, payload)
            out.write(data)
            h = header(head)
            row = (target, number, at, len(data), h.get("warc-type"), h.get("warc-target-uri"), h.get("warc-record-id"), len(payload))
            index.write((json.dumps(dict(zip(("number", "offset", "length", "type", "uri", "record_id", "payload_bytes"), row[1:]))) + "\n").encode())
            rows.append(row)
            at += len(data)
    _publish(fs_out, tmp, p_out)
    _publish(fs_out, tmp_index, p_out + ".idx")
    return [(*r, status[0]) for r in rows] or [(target, None, None, None, None, None, None, None, status[0])]


def normalise(paths: DataFrame, folder: str) -> DataFrame:
    """Index rows of all files of `paths` (column path), rewritten into `folder` under the name of their own path's digest."""

    def run(batches):
        attempt = str(TaskContext.get().taskAttemptId())
        fs, base = _fs(folder)
        fs.create_dir(base, recursive=True)
        for batch in batches:
            for p in batch.column(0).to_pylist():
                if p is None:
                    continue
                name = hashlib.md5(p.encode()).hexdigest()
                rows = normalise_file(p, f"{folder}/{name}.warc.gz", attempt)
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), (pa.string(), pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.string(), pa.int64(), pa.string()))], INDEX_NAMES)

    return paths.select("path").mapInArrow(run, INDEX_SCHEMA)


INDEX_NAMES = [c.split()[0] for c in INDEX_SCHEMA.split(", ")]


def read_index(spark: SparkSession, folder: str) -> DataFrame:
    """The index of the normalised files of `folder`, from their sidecars alone; the status of a file is in none, so it is null."""
    fields = [c for c in INDEX_SCHEMA.split(", ") if c.split()[0] not in ("path", "status")]
    rows = spark.read.schema(", ".join(fields)).option("pathGlobFilter", "*.idx").json(folder)
    return rows.select(F.regexp_replace("_metadata.file_path", r"\.idx$", "").alias("path"), *[c.split()[0] for c in fields], F.lit(None).cast("string").alias("status"))


def read_records(index: DataFrame) -> DataFrame:
    """(path, number, uri, record_id, payload, alone) of every record of an index, each read by its offset; alone: those bytes are exactly one gzip member."""

    def run(batches):
        for batch in batches:
            rows = [r for r in batch.to_pylist() if r["number"] is not None]
            out, size, open_path, f = [], 0, None, None
            for r in rows:
                if r["path"] != open_path:
                    fs, p = _fs(r["path"])
                    f, open_path = fs.open_input_file(p), r["path"]
                raw = f.read_at(r["length"], r["offset"])
                z = zlib.decompressobj(31)
                text = z.decompress(raw)
                end = text.index(b"\r\n\r\n") + 4
                none = "warc-truncated" in header(text[:end])
                out.append((r["path"], r["number"], r["uri"], r["record_id"], None if none else text[end : end + r["payload_bytes"]], z.eof and not z.unused_data))
                size += len(text)
                if size > 8 << 20:
                    yield _records_batch(out)
                    out, size = [], 0
            if out:
                yield _records_batch(out)

    return index.select(INDEX_NAMES).mapInArrow(run, "path string, number bigint, uri string, record_id string, payload binary, alone boolean")


def _records_batch(rows: list[tuple]) -> pa.RecordBatch:
    types = (pa.string(), pa.int64(), pa.string(), pa.string(), pa.binary(), pa.bool_())
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), types)], ["path", "number", "uri", "record_id", "payload", "alone"])


def write_monolithic(pages: DataFrame, folder: str) -> DataFrame:
    """Rows (page_id, url, html) as WARC files of one gzip stream, one per partition; their paths."""

    def run(batches):
        part, attempt = TaskContext.get().partitionId(), TaskContext.get().taskAttemptId()
        fs, base = _fs(folder)
        fs.create_dir(base, recursive=True)
        name = f"pages-{part:06d}.warc.gz"
        out, z = None, zlib.compressobj(1, zlib.DEFLATED, 31)
        for batch in batches:
            ids, urls, htmls = (batch.column(i).to_pylist() for i in range(3))
            for i, u, h in zip(ids, urls, htmls):
                if out is None:
                    out = fs.open_output_stream(f"{base}/{name}.{attempt}.part", compression=None)
                body = (h or "").encode("utf-8", "replace")
                fields = ["WARC/1.1", "WARC-Type: resource", f"Content-Length: {len(body)}"]
                fields += [f"WARC-Target-URI: {u}"] if u is not None else []
                fields += [f"WARC-Record-ID: <urn:page:{i}>"] if i is not None else []
                fields += ["WARC-Truncated: unspecified"] if h is None else []
                out.write(z.compress("\r\n".join(fields).encode() + b"\r\n\r\n" + body + b"\r\n\r\n"))
        if out is not None:
            out.write(z.flush())
            out.close()
            _publish(fs, f"{base}/{name}.{attempt}.part", f"{base}/{name}")
            yield pa.RecordBatch.from_arrays([pa.array([f"{folder}/{name}"])], ["path"])

    return pages.select(F.col("page_id").cast("string"), "url", "html").mapInArrow(run, "path string")


def op5_warc_normaliser(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every page, written into monolithic files, normalised, and read back record by record through the sidecars."""
    pages = spark.read.parquet(f"{sf_dir}/pages.parquet")
    folder = scratch_path(spark, "warc")
    paths = cut(write_monolithic(pages, f"{folder}/monolithic"), "paths")
    # a file is a task's work
    n = paths.count()
    index = cut(normalise(paths.repartition(max(1, n), "path"), f"{folder}/members"), "index")
    if n:
        index = read_index(spark, f"{folder}/members")
    back = read_records(index.repartition(max(1, n), "path").sortWithinPartitions("path", "number"))
    return back.select(F.regexp_extract("record_id", "([0-9]+)>$", 1).cast("bigint").alias("page_id"), F.col("uri").alias("url"), F.octet_length("payload").cast("bigint").alias("payload_bytes"), F.md5("payload").alias("payload_md5"), F.col("alone").alias("own_member"))


OP5_SQL = """
SELECT page_id, url, CAST(octet_length(encode(html)) AS BIGINT) AS payload_bytes, md5(html) AS payload_md5, true AS own_member FROM pages
"""
