"""Line deduplication with two Bloom filters.

A line is kept at its first occurrence, in order of (doc_id, text fingerprint, line
number), and dropped everywhere else, within and across documents.

1. Every task sets the filter bits of its own lines and ships them as compact, delta-coded
   positions, split by filter segment; the reducer of a segment holds its part of both
   filters: the bits set at least once, and the bits set at least twice. Only the
   twice-seen part, a bit map, goes on.
2. A line all of whose bits are in the twice-seen filter is suspected to repeat; no repeat
   is ever missed. Only suspects shuffle, as whole lines: grouping by the line itself
   confirms repeats exactly and picks the first occurrence.
3. The line numbers to drop are joined back to the documents.

The filter has `BITS_PER_LINE` bits a line, at most `MAX_FILTER_BITS` (it is broadcast to
the executors). Beyond that it lets more suspects through; where it would be more than
half full it is left out, and all lines are confirmed by the exact shuffle. The result is the same
in each case.

Defined results: blank lines (white space only) are never dropped; null texts stay null
and lose nothing; a document all of whose lines go keeps its row with the empty text; a
null doc_id orders before all others; rows with equal doc_id and equal text are one
document read twice and keep the same lines; `n_chars`, where present, is set to the new
length; other columns, whatever their names, are kept as they are, but a column called
`n_lines_removed` is replaced.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.scratch import cut
from . import _grams as G

BITS_PER_LINE = 16
MAX_FILTER_BITS = 1 << 30
SEGMENT_BITS = 1 << 20
HASHES = 2


def _lines(buf: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Of the lines with a visible character: (row, line number, start, end, hash)."""
    n = len(buf)
    if not n:
        none = np.zeros(0, np.int64)
        return none, none, none, none, np.zeros(0, np.uint64)
    nl = np.zeros(n + 1, bool)
    nl[1:] = buf == 10
    rows = np.flatnonzero(np.diff(off) > 0)
    nl[off[rows]] = True
    start = np.flatnonzero(nl[:n])
    row = np.searchsorted(off, start, "right") - 1
    # a newline at a row's very end opens one more, empty line, which is never looked at
    first = np.searchsorted(start, off[row])
    number = np.arange(len(start)) - first
    end = np.append(start[1:], n)
    closed = buf[end - 1] == 10
    end = np.where(closed, end - 1, end)
    solid = np.concatenate([[0], np.cumsum(buf > 32)])
    seen = solid[end] > solid[start]
    row, number, start, end = row[seen], number[seen], start[seen], end[seen]
    r, inv = G._pow(n)
    total = np.zeros(n + 1, np.uint64)
    np.cumsum((buf.astype(np.uint64) + np.uint64(1)) * r[:n], out=total[1:])
    return row, number, start, end, G.mix((total[end] - total[start]) * inv[start])


def _positions(h: np.ndarray, bits: int) -> list[np.ndarray]:
    """Filter positions of each hash, one array per hash function."""
    step = G.mix(h ^ np.uint64(0xA5A5A5A5A5A5A5A5)) | np.uint64(1)
    return [(h + np.uint64(k) * step) >> np.uint64(64 - (bits.bit_length() - 1)) for k in range(HASHES)]


def _coded(p: np.ndarray) -> bytes:
    """Sorted positions as 16-bit steps; a step of 65535 adds that much and goes on."""
    d = np.diff(p, prepend=0)
    big = d // 65535
    if not big.any():
        return d.astype(np.uint16).tobytes()
    out = np.full(len(d) + int(big.sum()), 65535, np.uint16)
    out[np.cumsum(big + 1) - 1] = d - big * 65535
    return out.tobytes()


def _decoded(b: bytes) -> np.ndarray:
    s = np.frombuffer(b, np.uint16)
    return np.cumsum(s, dtype=np.int64)[s != 65535]


def twice_seen(texts: DataFrame, bits: int) -> np.ndarray:
    """Bit map (packed) of the filter positions that lines hit at least twice."""
    segment = min(SEGMENT_BITS, bits)

    def collect(batches):
        # positions of a task, held until they fill a buffer: fewer, denser pieces
        held, n = [], 0

        def pieces():
            p = np.sort(np.concatenate(held)).astype(np.int64)
            edges = np.searchsorted(p, np.arange(0, bits + 1, segment))
            s = [(i, _coded(p[a:b] - i * segment)) for i, (a, b) in enumerate(zip(edges[:-1], edges[1:])) if b > a]
            return pa.RecordBatch.from_arrays([pa.array([x[0] for x in s], pa.int32()), pa.array([x[1] for x in s], pa.binary())], ["segment", "steps"])

        for batch in batches:
            for part in G.chunks(batch, "text"):
                h = _lines(*G.view(part.column(0)))[4]
                for p in _positions(h, bits):
                    held.append(p)
                n += len(h)
                if n > 1 << 20:
                    yield pieces()
                    held, n = [], 0
        if held:
            yield pieces()

    def merge(batches):
        count: dict[int, np.ndarray] = {}
        for batch in batches:
            for i, steps in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                p = _decoded(steps)
                once, twice = count.setdefault(i, (np.zeros(segment, bool), np.zeros(segment, bool)))
                hit, c = np.unique(p, return_counts=True)
                twice[hit[(c > 1) | once[hit]]] = True
                once[hit] = True
        for i, (_, twice) in count.items():
            yield pa.RecordBatch.from_arrays([pa.array([i], pa.int32()), pa.array([np.packbits(twice, bitorder="little").tobytes()], pa.binary())], ["segment", "map"])

    got = texts.mapInArrow(collect, "segment int, steps binary").repartition("segment").mapInArrow(merge, "segment int, map binary").collect()
    out = np.zeros(bits // 8, np.uint8)
    for r in got:
        m = np.frombuffer(r["map"], np.uint8)
        out[r["segment"] * segment // 8 :][: len(m)] = m
    return out


def suspects(keyed: DataFrame, twice: np.ndarray | None) -> DataFrame:
    """(doc_id, fp, number, line) of the lines that may repeat; all lines where there is no filter."""
    kind = keyed.schema["doc_id"].dataType.simpleString()
    held = keyed.sparkSession.sparkContext.broadcast(twice)

    def run(batches):
        m = held.value
        for batch in batches:
            for part in G.chunks(batch, "text"):
                buf, off = G.view(part.column(2))
                row, number, start, end, h = _lines(buf, off)
                keep = np.ones(len(h), bool)
                if m is not None:
                    for p in _positions(h, len(m) * 8):
                        keep &= (m[p >> np.uint64(3)] >> (p & np.uint64(7)).astype(np.uint8)) & 1 > 0
                k = np.flatnonzero(keep)
                data = buf.tobytes()
                lines = pa.array([data[a:b] for a, b in zip(start[k], end[k])], pa.binary())
                at = pa.array(row[k])
                yield pa.RecordBatch.from_arrays([part.column(0).take(at), part.column(1).take(at), pa.array(number[k], pa.int32()), lines], ["doc_id", "fp", "number", "line"])

    return keyed.mapInArrow(run, f"doc_id {kind}, fp bigint, number int, line binary")


def filter_bits(lines: int, max_bits: int = MAX_FILTER_BITS) -> int | None:
    """Filter size for so many lines, a power of two; None where the largest would be over half full."""
    bits = 1 << max(10, (max(lines, 1) * BITS_PER_LINE - 1).bit_length())
    if bits > max_bits:
        bits = 1 << (max_bits.bit_length() - 1)
    return None if lines * HASHES > bits // 2 else bits


def dedup_lines(docs: DataFrame, max_bits: int = MAX_FILTER_BITS) -> DataFrame:
    """`docs` without repeated lines, plus `n_lines_removed`."""
    text = F.col("text")
    fp = F.xxhash64(text)
    lines = docs.select(F.sum(F.length(text) - F.length(F.translate(text, "\n", "")) + 1).alias("n")).first()["n"] or 0
    bits = filter_bits(lines, max_bits)
    twice = twice_seen(docs.where(text.isNotNull()).select("text"), bits) if bits else None
    sus = cut(suspects(docs.where(text.isNotNull()).select("doc_id", fp.alias("fp"), "text"), twice), "suspects")
    place = F.struct("doc_id", "fp", "number")
    first = sus.groupBy("line").agg(F.min(place).alias("first"), F.count("*").alias("n")).where("n > 1").select("line", "first")
    gone = sus.join(first, "line").where(~place.eqNullSafe(F.col("first")))
    drops = gone.groupBy("doc_id", "fp").agg(F.collect_set("number").alias("__drop")).withColumnsRenamed({"doc_id": "__id", "fp": "__fp"})
    left = docs.withColumn("__f", fp)
    out = left.join(drops, left["doc_id"].eqNullSafe(drops["__id"]) & (left["__f"] == drops["__fp"]), "left")
    # a column of its own, so that a text is split once and not again for each line
    out = out.withColumn("__parts", F.when(F.col("__drop").isNotNull(), F.split("text", "\n", -1)))
    parts = F.col("__parts")
    stay = F.array_except(F.sequence(F.lit(0), F.size(parts) - 1), F.col("__drop"))
    out = out.withColumn("n_lines_removed", F.when(text.isNull() | F.col("__drop").isNull(), 0).otherwise(F.size("__drop")))
    out = out.withColumn("text", F.when(F.col("n_lines_removed") == 0, text).otherwise(F.array_join(F.transform(stay, lambda i: F.get(parts, i)), "\n")))
    if "n_chars" in docs.columns:
        out = out.withColumn("n_chars", F.when(F.col("n_lines_removed") == 0, F.col("n_chars")).otherwise(F.length("text").cast(docs.schema["n_chars"].dataType)))
    return out.select(*[F.col(f"`{c}`") for c in docs.columns if c != "n_lines_removed"], "n_lines_removed")


def op3_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return dedup_lines(spark.read.parquet(f"{sf_dir}/documents.parquet"))


OP3_SQL = r"""
WITH l AS (
  SELECT doc_id, unnest(string_split(text, chr(10))) AS line, generate_subscripts(string_split(text, chr(10)), 1) AS pos FROM documents
), r AS (
  SELECT doc_id, line, pos, regexp_matches(line, '[^\x00-\x20]') AND row_number() OVER (PARTITION BY line ORDER BY doc_id, pos) > 1 AS dup FROM l
), k AS (
  SELECT doc_id, coalesce(string_agg(line, chr(10) ORDER BY pos) FILTER (WHERE NOT dup), '') AS text, CAST(count(*) FILTER (WHERE dup) AS INTEGER) AS n_lines_removed FROM r GROUP BY doc_id
)
SELECT d.doc_id, k.text, d.lang, d.source, CASE WHEN n_lines_removed = 0 THEN d.n_chars ELSE CAST(length(k.text) AS BIGINT) END AS n_chars, n_lines_removed
FROM documents d JOIN k ON d.doc_id = k.doc_id
"""
