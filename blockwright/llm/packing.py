"""Bulk-synchronous best-fit packing of documents into bins of `capacity` tokens.

A document is cut into whole bins of `capacity` tokens and a rest; the rests are packed.
As many bins are opened as their tokens need at least. Then, round by round:

1. documents and gaps are range-sorted together by size, a document before a gap of the
   same size;
2. every partition sweeps its range once: a gap takes the largest document before it that
   is still free, which is matching parentheses, done on whole arrays. What remains of a partition
   are gaps, then documents;
3. the remaining counts of the partitions (a few numbers each) settle, on the driver, which
   rank of which partition's documents goes to which rank of which partition's gaps; ranks
   make every match unique, and one join on them carries it out;
4. gaps shrink, full bins leave, and the next round begins. When no document fits any gap,
   new bins are opened for what is left.

Items are numbered in order of (doc_id, piece, tokens), and the matching depends only on the
order of (size, kind, id), so the result never depends on the partitioning. A gap gets at
most one document a round. State is narrow (an id and a size a row), written to
the shared folder after every round.

Tokens are white-space separated words, or those of the byte-level vocabulary at
`tokenizer` (a file of ranks). Defined results: null texts and texts without a token give
no piece; repeated rows and ties are packed like any other documents, each once; texts of
any length are cut, never truncated; an empty table gives an empty result; columns beyond
`doc_id` and `text` are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.scratch import cut
from .mixing import n_tokens

CAPACITY = 2048


def _count_bpe(docs: DataFrame, ranks_file: str) -> DataFrame:
    """(doc_id, n) by a byte-level BPE vocabulary; the file must be readable on every executor."""
    kind = docs.schema["doc_id"].dataType.simpleString()

    def run(batches):
        import base64

        import tiktoken

        with open(ranks_file, "rb") as f:
            ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
        enc = tiktoken.Encoding("given", pat_str=r"'(?:[sdmt]|ll|ve|re)| ?\p{L}++| ?\p{N}++| ?[^\s\p{L}\p{N}]++|\s++$|\s+(?!\S)|\s", mergeable_ranks=ranks, special_tokens={})
        for b in batches:
            n = [len(enc.encode_ordinary(t)) if t else 0 for t in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(n, pa.int64())], ["doc_id", "n"])

    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {kind}, n bigint")


def pieces(docs: DataFrame, capacity: int, tokenizer: str | None = None) -> DataFrame:
    """(item, doc_id, piece, first_token, n_tokens): whole bins and a rest of each document, numbered from 0 in order of (doc_id, piece, n_tokens).

    Rows are range-sorted and numbered within their partition; the partitions' numbers of rows
    then say where each begins, so the numbers don't depend on the partitioning.
    """
    counted = _count_bpe(docs, tokenizer) if tokenizer else docs.select("doc_id", n_tokens(F.col("text")).alias("n"))
    counted = cut(counted.where("n > 0"), "tokens")
    # the outer form, as for the inner one Spark would infer a filter that counts all tokens once more
    p = counted.select("doc_id", "n", F.posexplode_outer(F.sequence(F.lit(0).cast("bigint"), F.col("n") - 1, F.lit(capacity).cast("bigint"))).alias("piece", "first_token"))
    p = p.select("doc_id", "piece", "first_token", F.least(F.lit(capacity).cast("bigint"), F.col("n") - F.col("first_token")).cast("int").alias("n_tokens"))
    order = ["doc_id", "piece", "n_tokens"]
    p = p.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("at", F.monotonically_increasing_id())
    p = cut(p.withColumn("part", F.shiftright("at", 33).cast("int")).withColumn("at", F.col("at").bitwiseAND(F.lit((1 << 33) - 1))), "numbered")
    begins, rows = 0, []
    for r in p.groupBy("part").count().orderBy("part").collect():
        rows.append((r["part"], begins))
        begins += r["count"]
    starts = docs.sparkSession.createDataFrame(rows, "part int, begins bigint")
    return p.join(F.broadcast(starts), "part").select((F.col("begins") + F.col("at")).alias("item"), *["doc_id", "piece", "first_token", "n_tokens"])


def match_runs(kind: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Index pairs (document, gap) of one swept range; kind: 0 document, 1 gap, in order. A gap takes the last free document before it."""
    depth = np.cumsum(1 - 2 * kind.astype(np.int64))
    level = depth + kind
    order = np.lexsort((np.arange(len(kind)), level))
    a, b = order[:-1], order[1:]
    pair = (level[a] == level[b]) & (kind[a] == 0) & (kind[b] == 1)
    return a[pair], b[pair]


def _sweep(state: DataFrame) -> DataFrame:
    """(what, part, rank, id, size, other, other_size): matches ("m": document id and size, gap id and size) and remainders ("d", "g")."""

    def run(batches):
        held = [b for b in batches if b.num_rows]
        if not held:
            return
        size, kind, ident = (np.concatenate([b.column(i).to_numpy() for b in held]) for i in range(3))
        part = TaskContext.get().partitionId()
        d, g = match_runs(kind)
        free = np.ones(len(kind), bool)
        free[d] = free[g] = False
        out = [("m", np.arange(len(d)), ident[d], size[d], ident[g], size[g])]
        for what, k in (("d", 0), ("g", 1)):
            at = np.flatnonzero(free & (kind == k))
            out.append((what, np.arange(len(at)), ident[at], size[at], np.zeros(len(at), np.int64), np.zeros(len(at), np.int32)))
        for what, rank, a, b, c, e in out:
            if len(rank):
                yield pa.RecordBatch.from_arrays([pa.array([what] * len(rank)), pa.array(np.full(len(rank), part), pa.int32()), pa.array(rank), pa.array(a), pa.array(b), pa.array(c), pa.array(e)], ["what", "part", "rank", "id", "size", "other", "other_size"])

    return state.repartitionByRange("size", "kind", "id").sortWithinPartitions("size", "kind", "id").mapInArrow(run, "what string, part int, rank bigint, id bigint, size int, other bigint, other_size int")


def carry(counts: list[tuple[int, int, int]]) -> list[tuple[int, int, int, int, int]]:
    """Segments (document part, its highest rank, gap part, its lowest rank, length) that match what sweeps left over; counts: (part, documents, gaps) in order of range."""
    stack: list[list[int]] = []
    out = []
    for part, docs, gaps in sorted(counts):
        at = 0
        while at < gaps and stack:
            p, left = stack[-1]
            n = min(left, gaps - at)
            out.append((p, left - 1, part, at, n))
            at += n
            if left == n:
                stack.pop()
            else:
                stack[-1][1] = left - n
        if docs:
            stack.append([part, docs])
    return out


def pack_items(items: DataFrame, capacity: int, max_rounds: int = 10_000) -> DataFrame:
    """(item, bin) of every item (item, size), each size being under `capacity`."""
    spark = items.sparkSession
    head = items.agg(F.count("*"), F.sum("size")).first()
    todo, tokens = head[0], head[1] or 0
    docs = items.select(F.col("size").cast("int"), F.lit(0).alias("kind"), F.col("item").alias("id"))
    gaps = None
    placed, opened = [], 0
    for _ in range(max_rounds):
        if not todo:
            break
        if gaps is None:
            n = max(1, -(-tokens // capacity))
            fresh = spark.range(opened, opened + n).select(F.lit(capacity).alias("size"), F.lit(1).alias("kind"), "id")
            opened += n
        else:
            fresh = None
        state = docs if gaps is None else docs.unionByName(gaps)
        state = state if fresh is None else state.unionByName(fresh)
        swept = cut(_sweep(state), "sweep")
        counts = swept.groupBy("part").agg(F.count(F.when(F.col("what") == "d", 1)), F.count(F.when(F.col("what") == "g", 1)), F.count(F.when(F.col("what") == "m", 1)), F.sum(F.when(F.col("what") == "m", F.col("size")))).collect()
        segments = carry([(r[0], r[1], r[2]) for r in counts])
        matched = swept.where("what = 'm'").select("id", "size", "other", "other_size")
        left_d, left_g = swept.where("what = 'd'"), swept.where("what = 'g'")
        crossed = sum(s[4] for s in segments)
        if segments:
            seg = F.broadcast(spark.createDataFrame([(i, *s) for i, s in enumerate(segments)], "seg int, dp int, dr bigint, gp int, gr bigint, n bigint"))
            d_in = (F.col("part") == F.col("dp")) & (F.col("rank") <= F.col("dr")) & (F.col("rank") > F.col("dr") - F.col("n"))
            g_in = (F.col("part") == F.col("gp")) & (F.col("rank") >= F.col("gr")) & (F.col("rank") < F.col("gr") + F.col("n"))
            dk = left_d.join(seg, d_in, "left").select("id", "size", "seg", (F.col("dr") - F.col("rank")).alias("at"))
            gk = left_g.join(seg, g_in, "left").select(F.col("id").alias("other"), F.col("size").alias("other_size"), "seg", (F.col("rank") - F.col("gr")).alias("at"))
            both = cut(dk.where("seg is not null").join(gk.where("seg is not null"), ["seg", "at"]).select("id", "size", "other", "other_size"), "carried")
            matched = matched.unionByName(both)
            left_d, left_g = dk.where("seg is null"), gk.where("seg is null").select(F.col("other").alias("id"), F.col("other_size").alias("size"))
        n_match = sum(r[3] for r in counts) + crossed
        placed.append(matched.select(F.col("id").alias("item"), F.col("other").alias("bin")))
        docs = left_d.select("size", F.lit(0).alias("kind"), "id")
        gaps = left_g.select("size", F.lit(1).alias("kind"), "id").unionByName(matched.where("other_size > size").select((F.col("other_size") - F.col("size")).alias("size"), F.lit(1).alias("kind"), F.col("other").alias("id")))
        todo -= n_match
        if todo and not n_match:
            # nothing fits any gap: those bins stay as they are, and the rest begins anew
            tokens = docs.agg(F.sum("size")).first()[0]
            gaps = None
    if todo:
        raise RuntimeError("packing did not end")
    if not placed:
        return items.select("item", F.lit(0).cast("bigint").alias("bin")).limit(0)
    out = placed[0]
    for p in placed[1:]:
        out = out.unionByName(p)
    return out


def pack(docs: DataFrame, capacity: int = CAPACITY, tokenizer: str | None = None) -> DataFrame:
    """(bin_id, bin_offset, doc_id, piece, first_token, n_tokens) of every piece; bins that one piece fills have negative numbers."""
    p = cut(pieces(docs, capacity, tokenizer), "pieces")
    rest = p.where(F.col("n_tokens") < capacity)
    bins = pack_items(rest.select("item", F.col("n_tokens").alias("size")), capacity)
    order = Window.partitionBy("bin_id").orderBy(F.desc("n_tokens"), "item").rowsBetween(Window.unboundedPreceding, -1)
    packed = rest.join(bins, "item").withColumn("bin_id", F.col("bin")).withColumn("bin_offset", F.coalesce(F.sum("n_tokens").over(order), F.lit(0)).cast("int"))
    whole = p.where(F.col("n_tokens") == capacity).withColumn("bin_id", -1 - F.col("item")).withColumn("bin_offset", F.lit(0))
    cols = ["bin_id", "bin_offset", "doc_id", "piece", "first_token", "n_tokens"]
    return packed.select(cols).unionByName(whole.select(cols))


def op6_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(spark.read.parquet(f"{sf_dir}/documents.parquet"))
