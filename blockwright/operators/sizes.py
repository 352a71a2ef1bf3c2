"""Block sizes without a scan per tree: heavy values and the signature table.

A conjunction of hash values can exceed the cap only if each of its values alone does. So
the learner needs, of every record, only which of its values are heavy. Three passes over
the records give it all: counts of hashed value buckets (a bucket not over the cap holds
no heavy value), exact counts of the values in the buckets left, and counts of the
distinct combinations of heavy values, the signatures. The last table stands for the
records in every tree, chain or round, for every scorer and fold, and for every larger cap.
"""

from __future__ import annotations

import hashlib
import tempfile
from dataclasses import dataclass, field, replace

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import hashes
from ..functions.scratch import cut
from ..model import BlockingSpec, HashFn

#: Hashed value buckets of the first pass, for each function.
BUCKETS = 1 << 16
#: Rows of driver state: above it the cap is too small for this number of records, and the functions with most heavy values have to go first.
MAX_SIGNATURES = 4_000_000
#: Signatures of a node from which its sizes are kept, and numbers kept in all.
MEMO_ROWS, MEMO_CELLS = 128, 8_000_000
#: Signatures of a node from which functions are counted one after the other, as all at once would take some copies of the node's codes.
WIDE_ROWS = 4096
#: Pairs that come to the driver at once.
PAIRS_AT_ONCE = 500_000
#: Kinds of pairs that are counted, and pairs that are looked at, at once.
PIECE = 1 << 16


def mixer(id_col: Column, seed: int) -> Column:
    """A number from 0 to 2^32-1 of an id, the same in DuckDB: the first 8 digits of an md5."""
    return F.conv(F.substring(F.md5(F.concat(id_col.cast("string"), F.lit(f"|{seed}"))), 1, 8), 16, 10).cast("bigint")


def mixer_sql(id_col: str, seed: int) -> str:
    return f"CAST(('0x' || substr(md5(CAST({id_col} AS VARCHAR) || '|{seed}'), 1, 8)) AS BIGINT)"


def project(df: DataFrame, spec: BlockingSpec, library: list[HashFn]) -> DataFrame:
    """id and one column h0, h1, ... for each function."""
    return hashes.columns(df, library, spec, F.col(spec.id_col).alias("id"))


def _long(hashed: DataFrame, n: int) -> DataFrame:
    """(hash, value), a row for each record and function."""
    return hashed.select(F.posexplode_outer(F.array(*[F.col(f"h{i}") for i in range(n)])).alias("hash", "value"))


def heavy_values(hashed: DataFrame, n: int, cap: int, buckets: int = BUCKETS) -> DataFrame:
    """(hash, value, n) of the values that more than `cap` records have."""
    long = _long(hashed, n)
    bucket = F.pmod(F.xxhash64("value"), F.lit(buckets)).cast("int")
    full = long.groupBy("hash", bucket.alias("bucket")).agg(F.count("*").alias("n")).where(F.col("n") > cap).select("hash", "bucket")
    # at most one row for each `cap` records and function
    left = long.withColumn("bucket", bucket).join(full, ["hash", "bucket"], "left_semi")
    return left.groupBy("hash", "value").agg(F.count("*").alias("n")).where(F.col("n") > cap)


class Kinds:
    """Rows of a small table by number, of which many are equal: `table[kind]` without writing it out."""

    def __init__(self, table: np.ndarray, kind: np.ndarray):
        self.table, self.kind = table, kind

    def __len__(self) -> int:
        return len(self.kind)

    @property
    def shape(self) -> tuple[int, int]:
        return len(self.kind), self.table.shape[1]

    def __getitem__(self, at):
        """[rows, h] is an array; [rows] and [:, functions] are tables by number again."""
        rows, h = at if isinstance(at, tuple) else (at, slice(None))
        table = self.table[:, h]
        return table[self.kind[rows]] if table.ndim == 1 else Kinds(table, self.kind[rows])

    def counts(self, rows=slice(None)) -> np.ndarray:
        """How many of the rows are of each kind."""
        return np.bincount(self.kind[rows], minlength=len(self.table))

    def sum(self, axis: int = 0) -> np.ndarray:
        n = self.counts()
        at = np.flatnonzero(n)
        return n[at] @ self.table[at].astype(np.int64)

    def all(self, axis: int = 1) -> np.ndarray:
        return self.table.all(1)[self.kind]


class Held:
    """Rows of a table by number: picking some keeps their numbers, and what is asked for is read."""

    def __init__(self, table, rows: np.ndarray):
        self.table, self.rows = table, rows

    def __len__(self) -> int:
        return len(self.rows)

    @property
    def shape(self) -> tuple[int, ...]:
        return len(self.rows), *self.table.shape[1:]

    def __getitem__(self, at):
        rows, *more = at if isinstance(at, tuple) else (at,)
        return self.table[(self.rows[rows], *more)]

    def __iter__(self):
        return (self[i] for i in range(len(self)))


def _on_disk(n: int, columns: int, dtype) -> np.ndarray:
    """An array in a file of the driver without a name, which goes with the array."""
    if not n:
        return np.zeros((0, columns), dtype)
    with tempfile.TemporaryFile() as file:
        return np.memmap(file, dtype, "w+", shape=(n, columns))


def pieces(n: int, size: int = PIECE):
    return (slice(i, min(n, i + size)) for i in range(0, n, size))


def _kinds(x):
    return Kinds(x, np.arange(len(x))) if isinstance(x, np.ndarray) else x


@dataclass
class Features:
    """What learners see: signatures of the records, and of each labelled pair which functions keep it.

    codes[s, h] is 0 where signature s has a light value of function h, else the number of
    the heavy value from 1; count[s] its records. same[p, h] says whether both records of
    pair p agree; pair_code[p, h] is the shared heavy value's number, or 0. Both are held once
    for each kind of pair. Light values of pairs stay in `lookup`, where they are asked for by
    trees learnt on other records alone.
    """

    library: list[HashFn]
    cap: int
    n: float
    codes: np.ndarray
    count: np.ndarray
    values: list[list[str]]
    pair_ids: np.ndarray
    same: Kinds
    pair_code: Kinds
    pair_values: Kinds | None
    mix: np.ndarray
    missing: int = 0
    #: Sizes of large nodes, which every fold, scorer and round asks for again; shared by all picks of the same records and functions.
    memo: dict = field(default_factory=dict, repr=False, compare=False)
    #: (l_id, r_id, lv, rv) of the pairs, hashed values by function of `hashed`; read only where it has to be.
    lookup: DataFrame | None = field(default=None, repr=False, compare=False)
    hashed: list[str] = field(default_factory=list, repr=False, compare=False)
    #: Where a row stands for all pairs of a kind, their number.
    weight: np.ndarray | None = field(default=None, repr=False, compare=False)

    def __post_init__(self):
        self.same, self.pair_code, self.pair_values = _kinds(self.same), _kinds(self.pair_code), _kinds(self.pair_values)

    def same_light(self, rows: np.ndarray, h: int, v: str) -> np.ndarray:
        """Whether pairs share value v of function h, which is light here."""
        if self.lookup is None:
            return self.pair_values[rows, h] == v
        x, i = F.xxhash64(F.lit(v)), self.hashed.index(self.library[h].name)
        got = self.lookup.where((F.get("lv", F.lit(i)) == x) & (F.get("rv", F.lit(i)) == x)).select("l_id", "r_id").toArrow()
        held = pd.MultiIndex.from_arrays([got["l_id"].to_numpy(), got["r_id"].to_numpy()])
        return pd.MultiIndex.from_arrays(self.pair_ids[rows].T).isin(held) if len(held) else np.zeros(len(rows), bool)

    # What learners ask of a node's records; `sig` is the node's rows of signatures.

    def root(self):
        return np.arange(len(self.count))

    def sizes(self, sig, flat) -> np.ndarray:
        """Records of the node by value, in the common numbering of all functions' values."""
        key = hashlib.blake2b(sig, digest_size=16).digest() if len(sig) >= MEMO_ROWS else None
        if key in self.memo:
            return self.memo[key]
        if len(sig) < WIDE_ROWS:
            out = np.bincount((self.codes[sig] + flat.start).ravel(), np.repeat(self.count[sig], len(self.library)), flat.n)
        else:
            out = np.concatenate([self.sizes_of(sig, h) for h in range(len(self.library))])
        if key is not None:
            if len(self.memo) * flat.n > MEMO_CELLS:
                self.memo.clear()
            self.memo[key] = out
        return out

    def sizes_of(self, sig, h: int) -> np.ndarray:
        return np.bincount(self.codes[sig, h], self.count[sig], len(self.values[h]) + 1)

    def total(self, sig) -> float:
        return self.count[sig].sum()

    def child(self, sig, h: int, code: int):
        return sig[self.codes[sig, h] == code]

    # What they ask of its pairs; all pairs of a kind meet the same fate, so rows may stand for kinds.

    def n_pairs(self, prs) -> int:
        return len(prs) if self.weight is None else int(self.weight[prs].sum())

    def pair_counts(self, prs) -> np.ndarray:
        """How many of the pairs are of each kind."""
        return self.same.counts(prs) if self.weight is None else np.bincount(self.same.kind[prs], self.weight[prs], len(self.same.table)).astype(np.int64)

    def kept(self, prs) -> np.ndarray:
        """How many of the pairs each function keeps."""
        n = self.pair_counts(prs)
        at, out = np.flatnonzero(n), np.zeros(len(self.library), np.int64)
        for x in pieces(len(at)):
            out += n[at[x]] @ self.same.table[at[x]].astype(np.int64)
        return out

    def by_kind(self) -> "Features":
        """The same records with a row for each kind of pair that there is, and no numbers of single pairs."""
        if self.weight is not None:
            return self
        n = self.same.counts()
        at = np.flatnonzero(n)
        none = np.zeros((0, 2), np.int64)
        out = replace(self, pair_ids=none, mix=none, same=Kinds(self.same.table, at), pair_code=Kinds(self.pair_code.table, at), pair_values=None, weight=n[at])
        if hasattr(self, "_flat"):
            out._flat = self._flat
        return out

    def pick(self, rows: np.ndarray) -> "Features":
        """The same records with a part of the pairs."""
        rows = np.asarray(rows, np.int32)
        held = rows
        if isinstance(self.mix, Held):
            held = self.mix.rows[rows]
        ids, mix = (Held(x.table if isinstance(x, Held) else x, held) for x in (self.pair_ids, self.mix))
        kind = self.same.kind[rows]
        out = replace(self, pair_ids=ids, same=Kinds(self.same.table, kind), pair_code=Kinds(self.pair_code.table, kind), pair_values=None if self.pair_values is None else self.pair_values[rows], mix=mix)
        if hasattr(self, "_flat"):
            out._flat = self._flat
        return out

    def restrict(self, keep: list[int]) -> "Features":
        """The same records and pairs with a part of the functions."""
        return replace(self, memo={}, library=[self.library[i] for i in keep], codes=self.codes[:, keep], values=[self.values[i] for i in keep], same=self.same[:, keep], pair_code=self.pair_code[:, keep], pair_values=None if self.pair_values is None else self.pair_values[:, keep])


@dataclass
class EstimatedFeatures(Features):
    """Sizes from a histogram of each function alone, as if functions were independent: a node is known by its estimated records.

    share[h][v] is the part of all records with heavy value v of function h, at 0 the part of all light ones.
    """

    share: list[np.ndarray] = field(default_factory=list)

    def root(self):
        return self.n

    def sizes(self, sig, flat) -> np.ndarray:
        return sig * np.concatenate(self.share)

    def sizes_of(self, sig, h: int) -> np.ndarray:
        return sig * self.share[h]

    def total(self, sig) -> float:
        return sig

    def child(self, sig, h: int, code: int):
        return sig * self.share[h][code]

    def restrict(self, keep: list[int]) -> "EstimatedFeatures":
        return replace(super().restrict(keep), share=[self.share[i] for i in keep])

def canonical_pairs(pairs: DataFrame) -> DataFrame:
    """Pairs with l_id < r_id, each once; self-pairs and nulls left out."""
    return pairs.where("l_id is not null and r_id is not null and l_id <> r_id").select(F.least("l_id", "r_id").alias("l_id"), F.greatest("l_id", "r_id").alias("r_id")).distinct()


def pair_table(df: DataFrame, spec: BlockingSpec, pairs: DataFrame, library: list[HashFn], seed: int) -> DataFrame:
    """(l_id, r_id, lv, rv, lm, rm): 64-bit hashes of the values and mixers of both records. Only records of a pair are hashed."""
    pairs = canonical_pairs(pairs)
    ids = pairs.select(F.explode_outer(F.array("l_id", "r_id")).alias("__pid")).distinct()
    part = df.join(ids, F.col(spec.id_col) == F.col("__pid"), "left_semi")
    h = project(part, spec, library).select("id", F.array(*[F.xxhash64(f"h{i}") for i in range(len(library))]).alias("v"), mixer(F.col("id"), seed).alias("m"))
    # a record's values are many times what Spark takes from the size of its file, and would be broadcast
    left, right = (h.select(F.col("id").alias(f"{s}_id"), F.col("v").alias(f"{s}v"), F.col("m").alias(f"{s}m")).hint("merge") for s in "lr")
    return pairs.join(left, "l_id").join(right, "r_id")


def _sorted_heavy(heavy: list[list[int]]) -> list:
    """For each function the sorted hashes of its heavy values with their numbers from 1, or None."""
    return [(np.array(x, np.int64)[(o := np.argsort(np.array(x, np.int64)))], o.astype(np.int32) + 1) if x else None for x in heavy]


def _numbers(t, v: np.ndarray) -> np.ndarray:
    at = np.minimum(np.searchsorted(t[0], v), len(t[0]) - 1)
    return np.where(t[0][at] == v, t[1][at], 0)


def _small(heavy: list[list]) -> type:
    """The narrower type of the numbers of heavy values."""
    return np.int16 if max(map(len, heavy)) < 1 << 15 else np.int32


def _codes(sig: pa.ChunkedArray, n: int, small: type) -> np.ndarray:
    """Rows of n codes out of their bytes."""
    out, at = np.zeros((len(sig), n), small), 0
    for x in sig.chunks:
        if len(x):
            skip = x.offset * n
            out[at : at + len(x)] = np.frombuffer(x.buffers()[2], small)[skip : skip + len(x) * n].reshape(len(x), n)
            at += len(x)
    return out


def pair_kinds(table: DataFrame, n: int, heavy: list[list[int]]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(ids, mixers, table of kinds, kind of each pair), in order of ids. A kind has for each function -1 where the pair differs, else the number of the heavy value they share, or 0.

    Kinds come to the driver once each. Pairs are sorted and come a partition at a time, as
    batches of bytes; the driver keeps their kinds in memory, ids and mixers in a file.
    """
    spark = table.sparkSession
    held, small = spark.sparkContext.broadcast(_sorted_heavy(heavy)), _small(heavy)

    def run(batches):
        for b in batches:
            l, r = (b.column(k).flatten().to_numpy(zero_copy_only=False).reshape(b.num_rows, n) for k in (4, 5))
            sig = np.zeros((b.num_rows, n), small)
            for k, t in enumerate(held.value):
                if t is not None and b.num_rows:
                    sig[:, k] = _numbers(t, l[:, k])
            sig[l != r] = -1
            yield pa.RecordBatch.from_arrays([*(b.column(k) for k in range(4)), pa.array([k.tobytes() for k in sig], pa.binary())], ["l_id", "r_id", "lm", "rm", "sig"])

    made = cut(table.select("l_id", "r_id", "lm", "rm", "lv", "rv").mapInArrow(run, "l_id bigint, r_id bigint, lm bigint, rm bigint, sig binary"), "kinds")
    of = F.xxhash64("sig").alias("k")
    kinds = made.select("sig").distinct().select(of, "sig").toArrow()
    name = kinds["k"].to_numpy()
    by = np.argsort(name)
    names = spark.sparkContext.broadcast(name[by])
    total = made.count()
    ids, mix, kind = _on_disk(total, 2, np.int64), _on_disk(total, 2, np.uint32), np.zeros(total, np.int32)

    def packed(batches):
        for b in batches:
            c = [x.to_numpy() for x in b.columns]
            parts = np.stack(c[:2], axis=1), np.stack(c[2:4], axis=1).astype(np.uint32), np.searchsorted(names.value, c[4]).astype(np.int32)
            yield pa.RecordBatch.from_arrays([pa.array([b.num_rows]), *(pa.array([x.tobytes()], pa.binary()) for x in parts)], ["n", "ids", "mix", "kind"])

    at = 0
    ranged = made.repartitionByRange(total // PAIRS_AT_ONCE + 1, "l_id", "r_id").sortWithinPartitions("l_id", "r_id")
    for b in ranged.select("l_id", "r_id", "lm", "rm", of).mapInArrow(packed, "n bigint, ids binary, mix binary, kind binary").toLocalIterator():
        rows = slice(at, at + b["n"])
        ids[rows], mix[rows] = (np.frombuffer(b[k], x.dtype).reshape(-1, 2) for k, x in (("ids", ids), ("mix", mix)))
        kind[rows] = np.frombuffer(b["kind"], np.int32)
        at += b["n"]
    return ids, mix, _codes(kinds["sig"], n, small)[by], kind


def signatures(hashed: DataFrame, keep: list[int], heavy: list[list[int]]) -> tuple[np.ndarray, np.ndarray]:
    """(codes, records) of the distinct combinations of heavy values, in one order; codes are numbers, one for each function of `keep`.

    Values travel as 64-bit hashes; a batch is looked up by sorted search, a column at a
    time, and counted before it leaves the task.
    """
    held, small = hashed.sparkSession.sparkContext.broadcast(_sorted_heavy(heavy)), _small(heavy)

    def run(batches):
        for b in batches:
            sig = np.zeros((b.num_rows, len(keep)), small)
            for k, t in enumerate(held.value):
                if t is not None and b.num_rows:
                    sig[:, k] = _numbers(t, b.column(k).to_numpy())
            if len(sig):
                kinds, n = np.unique(sig, axis=0, return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array([k.tobytes() for k in kinds], pa.binary()), pa.array(n)], ["sig", "n"])

    counted = hashed.select(*[F.xxhash64(f"h{i}").alias(f"x{i}") for i in keep]).mapInArrow(run, "sig binary, n bigint").groupBy("sig").agg(F.sum("n").alias("n"))
    got = counted.limit(MAX_SIGNATURES + 1).toArrow()
    if got.num_rows > MAX_SIGNATURES:
        raise ValueError("too many combinations of heavy values: raise the cap or lower max_heavy")
    codes, n = _codes(got["sig"], len(keep), small), got["n"].to_numpy()
    del got
    order = np.lexsort(codes.T[::-1])
    return codes[order], n[order]


def sketched_values(hashed: DataFrame, n: int, cap: int, records: int, tracked: int = 100_000) -> list[tuple[int, str, int]]:
    """(hash, value, estimated records) of the frequent values of every function over `cap`, from one pass with one sketch a function."""
    k = int(min(tracked // 2, max(1, records // max(cap, 1))))
    row = hashed.agg(*[F.expr(f"approx_top_k(h{i}, {k}, {tracked})").alias(f"s{i}") for i in range(n)]).first()
    return [(i, x["item"], x["count"]) for i in range(n) for x in (row[f"s{i}"] or []) if x["count"] > cap]


def _hashed(spark, values: list[list[str]]) -> list[list[int]]:
    """The values' 64-bit hashes."""
    rows = [(i, j, v) for i, vs in enumerate(values) for j, v in enumerate(vs)]
    got = {(r["i"], r["j"]): r["x"] for r in spark.createDataFrame(rows, "i int, j int, v string").select("i", "j", F.xxhash64("v").alias("x")).collect()} if rows else {}
    return [[got[i, j] for j in range(len(vs))] for i, vs in enumerate(values)]


#: Where the sizes of conjunctions come from: exact counts; a histogram of each function's heavy values; a sketch of them.
ORACLES = ("exact", "histogram", "sketch")


def features(df: DataFrame, spec: BlockingSpec, pairs: DataFrame, library: list[HashFn], cap: int, seed: int = 42, sample: float | None = None, max_heavy: int = 10_000, oracle: str = "exact") -> Features:
    """Features for every cap of at least `cap`. Three scans of the records, one join of the pairs with them.

    With `sample`, sizes are estimated from that share of the records (by a hash of the id)
    and scaled up; pairs are always taken whole. Functions with more than `max_heavy` heavy
    values are left out, as they would create that many children of one node.
    oracle: "exact" counts signatures; "histogram" takes two scans and "sketch" one, and both
    estimate a conjunction by its functions' own shares, as if they were independent.
    """
    if oracle not in ORACLES:
        raise ValueError(f"unknown size oracle {oracle}")
    base, scale = df, 1.0
    if sample:
        base = df.where(mixer(F.col(spec.id_col), seed + 1) < int(sample * 2**32))
        scale = 1 / sample
    small_cap = max(1, int(cap / scale))
    hashed = project(base, spec, library)
    if oracle == "sketch":
        records = base.count()
        rows = sketched_values(hashed, len(library), small_cap, records)
        per = {i: sum(r[0] == i for r in rows) for i in {r[0] for r in rows}}
    else:
        # written once: its size is looked at before its rows are taken
        found = cut(heavy_values(hashed, len(library), small_cap), "heavy")
        # bounded: no more than max_heavy + 1 rows of a function come to the driver
        per = {r["hash"]: r["n"] for r in found.groupBy("hash").agg(F.count("*").alias("n")).collect()}
    keep = [i for i in range(len(library)) if per.get(i, 0) <= max_heavy]
    if not keep:
        raise ValueError("every function creates too many heavy blocks for this cap")
    if oracle != "sketch":
        rows = [(r["hash"], r["value"], r["n"], r["x"]) for r in found.where(F.col("hash").isin(keep)).select("hash", "value", "n", F.xxhash64("value").alias("x")).collect()] if per else []
    heavy = [sorted(r[1:] for r in rows if r[0] == i) for i in keep]
    values = [[v[0] for v in vs] for vs in heavy]
    lib = [library[i] for i in keep]
    share = None
    if oracle == "exact":
        codes, count = signatures(hashed, keep, [[v[2] for v in vs] for vs in heavy])
        count = count.astype(float) * scale
    else:
        records = records if oracle == "sketch" else base.count()
        codes, count = np.zeros((1, len(keep)), np.int32), np.array([records * scale], float)
        own = [np.array([v[1] for v in vs], float) / max(records, 1) for vs in heavy]
        share = [np.concatenate([[max(0.0, 1 - x.sum())], x]) for x in own]
    n_pairs = cut(canonical_pairs(pairs), "pairs")
    both = pair_table(df, spec, n_pairs, lib, seed)
    total = n_pairs.count()
    # a sketch brings no hashes of its values
    hashes_ = [[v[2] for v in vs] for vs in heavy] if oracle != "sketch" else _hashed(df.sparkSession, values)
    ids, mix, kinds, kind = pair_kinds(both, len(lib), hashes_)
    same, code = kinds >= 0, np.maximum(kinds, 0)
    f = Features(lib, cap, float(count.sum()), codes, count, values, ids, Kinds(same, kind), Kinds(code, kind), None, mix, total - len(ids), lookup=both.select("l_id", "r_id", "lv", "rv"), hashed=[x.name for x in lib])
    return f if share is None else EstimatedFeatures(**vars(f), share=share)


def block_sizes(assigned: DataFrame) -> DataFrame:
    """(block_key, n) of an assignment."""
    return assigned.groupBy("block_key").agg(F.count("*").alias("n"))
