"""Near-duplicate groups from SetSketch registers.

A document is the set of its runs of `SHINGLE` lower-cased words. Each of `M` registers
holds the smallest of the exponentially distributed hash values of the set, truncated to
a power of `BASE`: sketches merge by their maximum, and two sets agree in a register with
about the probability of their Jaccard similarity.

1. One pass over the texts gives fingerprint, number of shingles and registers of every
   document. Documents with the same shingle set become one node.
2. Registers are banded; nodes that agree in a whole band share a bucket. Buckets of the
   same members are taken once. Only nodes that share a bucket go on.
3. Within a bucket, members are linked to a leader, those the leader misses to the members
   it caught, and so on, until every member is linked to all it should be: a pair is linked
   where the joint likelihood of the counts of larger, smaller and equal registers, given
   the set sizes, is highest at a similarity of at least `THRESHOLD - SLACK`. A bucket of n
   copies costs n comparisons, not n squared, and none is capped.
4. Linked nodes form components; in each, the same linking with the exact Jaccard
   similarity of the shingle sets, `THRESHOLD` or more, gives the final groups.

One document of a group stays: the one of lowest (doc_id, text fingerprint).

Defined results: null texts and texts without a word have no shingles, group with nothing
and all stay; shorter texts than `SHINGLE` words are one shingle; repeated rows (equal
doc_id and text) are copies, of which exactly one row stays; a null doc_id orders first;
columns beyond `doc_id` and `text` are kept. Nodes are 64-bit fingerprints of sets.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.scratch import cut
from ..operators.components import connected_components
from . import _grams as G

SHINGLE = 3
BANDS, ROWS = 40, 4
M = BANDS * ROWS
BASE = 1.001
TOP = 65534
THRESHOLD = 0.5
SLACK = 0.1
_LOG_BASE = float(np.log(BASE))
_rng = np.random.default_rng(20240501)
_MUL = _rng.integers(1, 1 << 63, M, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_ADD = _rng.integers(0, 1 << 63, M, dtype=np.uint64)


def shingle_sets(col: pa.Array, k: int = SHINGLE) -> tuple[np.ndarray, np.ndarray]:
    """(distinct shingle hashes, sorted within each row; offsets)."""
    h, off = G.shingles(*G.words(*G.view(G.lowered(col))), k)
    row = np.repeat(np.arange(len(off) - 1), np.diff(off))
    order = np.lexsort((h, row))
    h, row = h[order], row[order]
    new = np.ones(len(h), bool)
    new[1:] = (h[1:] != h[:-1]) | (row[1:] != row[:-1])
    return h[new], np.searchsorted(row[new], np.arange(len(off)))


def registers(h: np.ndarray, off: np.ndarray) -> np.ndarray:
    """Registers (rows by M) of sets given as hashes and offsets; an empty set has zeros."""
    out = np.zeros((len(off) - 1, M), np.uint16)
    full = np.flatnonzero(np.diff(off) > 0)
    if not len(full):
        return out
    at = off[full]
    low = np.empty((len(full), M))
    for i in range(M):
        v = h * _MUL[i]
        v += _ADD[i]
        low[:, i] = np.minimum.reduceat(v, at)
    # the least of n uniform values, made exponential; its power of BASE, counted downwards
    e = -np.log1p(-(low + 1) / 2.0**64 * (1 - 1e-16))
    k = np.floor(1 - np.log(np.maximum(e, 1e-300)) / _LOG_BASE) + 10000
    out[full] = np.clip(k, 1, TOP).astype(np.uint16)
    return out


def likeliest(larger: np.ndarray, smaller: np.ndarray, na: np.ndarray, nb: np.ndarray, steps: int = 24) -> np.ndarray:
    """Jaccard similarity of highest likelihood, given how many registers of a are larger and smaller than b's, and both set sizes."""
    u = na / (na + nb)
    v = 1 - u
    top = np.minimum(u / v, v / u)
    c = (BASE - 1) / BASE

    def slope(j):
        """Derivative of the log-likelihood in j."""
        x, y = np.maximum(u - v * j, 1e-12), np.maximum(v - u * j, 1e-12)
        p, q = -np.log1p(-c * x) / _LOG_BASE, -np.log1p(-c * y) / _LOG_BASE
        dp, dq = -v * c / (1 - c * x) / _LOG_BASE, -u * c / (1 - c * y) / _LOG_BASE
        return larger * dp / p + smaller * dq / q - (M - larger - smaller) * (dp + dq) / np.maximum(1 - p - q, 1e-12)

    lo, hi = np.zeros(len(u)), top.copy()
    for _ in range(steps):
        mid = (lo + hi) / 2
        up = slope(mid) > 0
        lo, hi = np.where(up, mid, lo), np.where(up, hi, mid)
    return np.where((larger == 0) & (smaller == 0), top, (lo + hi) / 2)


def link(n: int, near) -> np.ndarray:
    """Parent of each of n members: near(i, others) says which others are close enough to i. A member that is its own parent begins a group."""
    parent = np.arange(n)
    open_ = np.arange(n)
    while len(open_):
        queue, open_ = [open_[0]], open_[1:]
        root = queue[0]
        while queue and len(open_):
            hit = near(queue.pop(0), open_)
            parent[open_[hit]] = root
            queue += open_[hit].tolist()
            open_ = open_[~hit]
    return parent


def _grouped(batches, key: int):
    """Record batches, of input sorted by column `key`, cut so that no group is split."""
    held = []
    for b in batches:
        if not b.num_rows:
            continue
        n = b.num_rows
        vals = b.column(key).to_numpy(zero_copy_only=False)
        cut_at = int(np.searchsorted(vals, vals[-1], "left")) if vals[0] != vals[-1] else 0
        if held and held[0].column(key)[0].as_py() != vals[0]:
            yield pa.Table.from_batches(held).combine_chunks().to_batches()[0]
            held = []
        if cut_at:
            head = b.slice(0, cut_at)
            yield pa.Table.from_batches([*held, head]).combine_chunks().to_batches()[0] if held else head
            held = []
        held.append(b.slice(cut_at, n - cut_at))
    if held:
        yield pa.Table.from_batches(held).combine_chunks().to_batches()[0]


def sketches(docs: DataFrame) -> DataFrame:
    """(doc_id, fp, node, n, regs): node is null where a text has no shingle."""
    kind = docs.schema["doc_id"].dataType.simpleString()

    def run(batches):
        for batch in batches:
            for part in G.chunks(batch, "text"):
                h, off = shingle_sets(part.column(2))
                n = np.diff(off)
                r = registers(h, off)
                total = np.zeros(len(h) + 1, np.uint64)
                np.cumsum(G.mix(h), out=total[1:])
                node = G.mix(total[off[1:]] - total[off[:-1]] + n.astype(np.uint64)).view(np.int64)
                regs = pa.FixedSizeBinaryArray.from_buffers(pa.binary(2 * M), len(n), [None, pa.py_buffer(r.tobytes())]).cast(pa.binary())
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), pa.array(node, mask=n == 0), pa.array(n, pa.int32()), regs], ["doc_id", "fp", "node", "n", "regs"])

    return docs.select("doc_id", F.xxhash64("text").alias("fp"), "text").mapInArrow(run, f"doc_id {kind}, fp bigint, node bigint, n int, regs binary")


def _bands(nodes: DataFrame) -> DataFrame:
    """(band, node): one 64-bit hash of each band's registers."""

    def run(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            r = np.frombuffer(b"".join(batch.column(1).to_pylist()), np.uint64).reshape(batch.num_rows, BANDS, ROWS // 4)
            b = G.mix(r[:, :, 0] * np.uint64(BANDS) + np.arange(BANDS, dtype=np.uint64)[None])
            for k in range(1, r.shape[2]):
                b = G.mix(b ^ r[:, :, k])
            node = np.repeat(batch.column(0).to_numpy(), BANDS)
            yield pa.RecordBatch.from_arrays([pa.array(b.reshape(-1).view(np.int64)), pa.array(node)], ["band", "node"])

    return nodes.select("node", "regs").mapInArrow(run, "band bigint, node bigint")


def _links(members: DataFrame, threshold: float) -> DataFrame:
    """(src, dst) tree edges of each bucket; members: (bucket, node, n, regs)."""

    def run(batches):
        for b in _grouped(batches, 0):
            bucket, node, n = (b.column(i).to_numpy() for i in range(3))
            r = np.frombuffer(b"".join(b.column(3).to_pylist()), np.uint16).reshape(len(node), M)
            start = np.flatnonzero(np.append(True, bucket[1:] != bucket[:-1]))
            size = np.diff(np.append(start, len(node)))

            def near(i, others):
                a, o = r[i], r[others]
                return likeliest((a > o).sum(1), (a < o).sum(1), n[i].astype(float), n[others].astype(float)) >= threshold

            lead = np.repeat(start, size)
            rest = np.flatnonzero(lead != np.arange(len(node)))
            close = np.zeros(len(node), bool)
            for at in range(0, len(rest), 4096):
                x = rest[at : at + 4096]
                close[x] = near(lead[x], x)
            src, dst = [node[lead[close]]], [node[close]]
            # buckets whose leader missed someone: the missed ones against all others
            missed = np.add.reduceat((~close).astype(np.int64), start) - 1
            for g in np.flatnonzero((missed > 0) & (size > 2)):
                at = np.arange(start[g], start[g] + size[g])
                p = link(len(at), lambda i, o: near(np.full(len(o), at[i]), at[o]))
                k = p != np.arange(len(at))
                src.append(node[at[p[k]]])
                dst.append(node[at[k]])
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(src)), pa.array(np.concatenate(dst))], ["src", "dst"])

    return members.repartition("bucket").sortWithinPartitions("bucket").mapInArrow(run, "src bigint, dst bigint")


def _confirmed(texts: DataFrame, threshold: float) -> DataFrame:
    """(node, group): within each component, linked by exact similarity; texts: (label, node, text)."""

    def run(batches):
        for b in _grouped(batches, 0):
            label, node = b.column(0).to_numpy(), b.column(1).to_numpy()
            start = np.flatnonzero(np.append(True, label[1:] != label[:-1]))
            ends = np.append(start[1:], len(node))
            out = node.copy()
            for s, e in zip(start, ends):
                h, off = shingle_sets(b.column(2).slice(s, e - s))
                n = np.diff(off)

                def near(i, others):
                    mine = h[off[i] : off[i + 1]]
                    at = np.concatenate([np.arange(off[o], off[o + 1]) for o in others])
                    x = np.searchsorted(mine, h[at])
                    hit = mine[np.minimum(x, len(mine) - 1)] == h[at]
                    both = np.add.reduceat(hit.astype(np.int64), np.concatenate([[0], np.cumsum(n[others])[:-1]]))
                    return both >= threshold * (n[i] + n[others] - both)

                out[s:e] = node[s:e][link(e - s, near)]
            yield pa.RecordBatch.from_arrays([pa.array(node), pa.array(out)], ["node", "group"])

    return texts.repartition("label").sortWithinPartitions("label", "node").mapInArrow(run, "node bigint, group bigint")


def node_groups(docs: DataFrame, table: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """(node, group) of the nodes that share a group with another node; table: `sketches(docs)`, written."""
    nodes = table.where("node is not null").groupBy("node").agg(F.min_by(F.struct("doc_id", "fp", "n", "regs"), F.struct("doc_id", "fp")).alias("r")).select("node", "r.*")
    nodes = cut(nodes, "nodes")
    # a bucket is known by the number of its members and two sums of their hashes; windows spill, so no bucket is ever one row
    band = Window.partitionBy("band")
    held = _bands(nodes).select("band", "node", F.count("*").over(band).alias("n"), *[F.bit_xor(F.xxhash64("node", F.lit(i))).over(band).alias(f"s{i}") for i in (0, 1)]).where("n > 1")
    bucket = F.xxhash64("n", "s0", "s1")
    members = held.select(bucket.alias("bucket"), "band", "node").withColumn("first", F.min("band").over(Window.partitionBy("bucket"))).where("band = first").select("bucket", "node")
    edges = _links(members.join(nodes.select("node", "n", "regs"), "node").select("bucket", "node", "n", "regs"), threshold - SLACK)
    parts = connected_components(edges)
    inside = parts.join(nodes.select("node", "doc_id", "fp"), "node").select("label", "node", F.col("doc_id").alias("__id"), F.col("fp").alias("__fp"))
    keyed = docs.select("doc_id", F.xxhash64("text").alias("fp"), "text")
    # rows that are equal in both give the same text, so one of them will do
    texts = inside.join(keyed, F.col("__id").eqNullSafe(keyed["doc_id"]) & (F.col("__fp") == keyed["fp"])).select("label", "node", "text").dropDuplicates(["label", "node"])
    return _confirmed(texts, threshold)


def grouped(docs: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """(doc_id, fp, group, kept) of each row of `docs`; group is null where a text has no shingle."""
    table = cut(sketches(docs), "sketches")
    groups = cut(node_groups(docs, table, threshold), "groups").select(F.col("node").alias("__n"), F.col("group").alias("__g"))
    rows = table.select("doc_id", "fp", "node").join(groups, F.col("node") == F.col("__n"), "left").select("doc_id", "fp", F.coalesce("__g", "node").alias("group"))
    w = Window.partitionBy("group").orderBy("doc_id", "fp")
    return rows.withColumn("kept", F.col("group").isNull() | (F.row_number().over(w) == 1))


def keep_one(docs: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """`docs` with one row of each group of near duplicates, all columns."""
    kept = grouped(docs, threshold).where("kept").groupBy("doc_id", "fp", F.col("group").isNull().alias("__free")).count().select(F.col("doc_id").alias("__id"), F.col("fp").alias("__fp"), "__free")
    left = docs.withColumn("__f", F.xxhash64("text"))
    out = left.join(kept, left["doc_id"].eqNullSafe(kept["__id"]) & (left["__f"] == kept["__fp"]))
    # of repeated rows one stays, unless their text has no shingle
    w = Window.partitionBy("__id", "__fp").orderBy("__f")
    return out.withColumn("__k", F.row_number().over(w)).where("__free or __k = 1").select(*[F.col(f"`{c}`") for c in docs.columns])


def op9_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(doc_id, group_id, kept): group_id is the lowest doc_id of the group."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    g = grouped(docs)
    lowest = F.min("doc_id").over(Window.partitionBy("group"))
    return g.select("doc_id", F.when(F.col("group").isNull(), F.col("doc_id")).otherwise(lowest).alias("group_id"), "kept")
