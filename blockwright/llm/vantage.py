"""Nearest neighbours by vantage-point trees, one to a shard.

Vectors are sharded in two levels: by their nearest of a few cell pivots, then by the nearest
pivot within the cell (a seeded sample, one for about `SHARD_ROWS` vectors in all), and every
shard grows a vantage-point tree: a node splits its
vectors at the median distance to its vantage point and keeps the range of distances of
either half. By the triangle inequality a half can hold nothing nearer than the gap
between the query's own distance and that range; it is pruned where that bound times
`factor` exceeds the distance of the k-th best found so far. Factor 1 prunes nothing that
could matter, so the search is exact; larger factors prune more and may miss.

Queries are the vectors whose id is divisible by `every` (1: all of them; op8 takes 50), and
each is held against all vectors. It first searches its own shard, then only the shards that
its k-th best distance (by the same rule, from the pivots' distances, radii and bisecting
planes) leaves open: first the cells, then the shards of those. The queries of a shard are
streamed past its one tree and walk it together: distances at a node or leaf are one matrix
product. At a leaf that product is in single precision and only sorts out: what may be among
the k best by the bound of its rounding errors is measured again in double precision, so
nothing is lost. The driver and a broadcast hold the cell pivots alone, about the root of the
number of shards; a task holds one shard, or the pivots of one cell.

Defined results: rows without an id, and rows whose vector is null, empty, of another
length than most, or has a null or non-finite entry, take no part; rows of equal id are one
vector, the smallest; a vector is not its own neighbour; equal distances (to 9 digits of
the square) rank by id; with fewer than k others all are returned; other columns are
ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, FloatType

from ..functions.scratch import cut, drop

K = 10
FACTOR = 1.0
LEAF = 256
SHARD_ROWS = 16_384
SENT_ROWS = 65_536
#: op8 asks for the neighbours of every so many-th id.
EVERY = 50
#: Pairs measured at a time.
MEASURED = 65_536


def squares(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Squared distances of rows of a and b, rounded to 9 digits so that equal vectors tie at 0."""
    return np.round(np.maximum((a * a).sum(1)[:, None] + (b * b).sum(1)[None] - 2 * (a @ b.T), 0), 9)


class Tree:
    def __init__(self, ids: np.ndarray, x: np.ndarray, leaf: int = LEAF):
        self.ids, self.x, self.leaf = ids, x, leaf
        with np.errstate(over="ignore"):
            self.norms = (x * x).sum(1)
            self.single = np.column_stack([x, self.norms]).astype(np.float32)
        self.root = self._grow(np.arange(len(ids)))

    def _grow(self, rows: np.ndarray):
        if len(rows) <= self.leaf:
            return rows
        d = np.sqrt(squares(self.x[rows[:1]], self.x[rows])[0])
        order = np.argsort(d, kind="stable")
        half = len(rows) // 2
        near, far = order[:half], order[half:]
        return rows[0], (d[near[0]], d[near[-1]]), self._grow(rows[near]), (d[far[0]], d[far[-1]]), self._grow(rows[far])

    def search(self, q_ids: np.ndarray, q: np.ndarray, k: int, factor: float, bound: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
        """(squared distances, ids), n by k, of each query's best; missing ones are inf and -1. bound: squared distances known already."""
        self.q_ids, self.q, self.k, self.factor = q_ids, q, k, factor
        self.best = np.full((len(q), k), np.inf)
        self.who = np.full((len(q), k), np.iinfo(np.int64).max)
        self.bound = np.full(len(q), np.inf) if bound is None else bound.copy()
        self.visited = 0
        with np.errstate(over="ignore"):
            self.q_norms = (q * q).sum(1)
            self.q_single = np.column_stack([-2 * q, np.ones(len(q))]).astype(np.float32)
        if bound is None:
            self._home(self.root, np.arange(len(q)))
            self.bound = self.best[:, -1].copy()
            self.best[:] = np.inf
            self.who[:] = np.iinfo(np.int64).max
        self._walk(self.root, np.arange(len(q)))
        return self.best, np.where(np.isinf(self.best), -1, self.who)

    def _home(self, node, at: np.ndarray) -> None:
        """Every query down to one leaf, for a first bound."""
        if not len(at):
            return
        if not isinstance(node, tuple):
            self._scan(node, at)
            return
        v, near, a, far, b = node
        d = np.sqrt(squares(self.q[at], self.x[v : v + 1])[:, 0])
        inner = d < (near[1] + far[0]) / 2
        self._home(a, at[inner])
        self._home(b, at[~inner])

    def _walk(self, node, at: np.ndarray) -> None:
        if not len(at):
            return
        if not isinstance(node, tuple):
            self._scan(node, at)
            return
        v, near, a, far, b = node
        d = np.sqrt(squares(self.q[at], self.x[v : v + 1])[:, 0])
        for (lo, hi), half in ((near, a), (far, b)):
            gap = np.maximum(np.maximum(d - hi, lo - d), 0) * self.factor
            reach = np.sqrt(np.minimum(self.bound[at], self.best[at, -1]))
            self._walk(half, at[gap <= reach + 1e-6])

    def _scan(self, rows: np.ndarray, at: np.ndarray) -> None:
        self.visited += len(rows) * len(at)
        ids, single, longest = self.ids[rows], self.single[rows].T, self.norms[rows].max()
        for i in range(0, len(at), 1024):
            a = at[i : i + 1024]
            most = self.q_norms[a] + longest
            # what rounding to single precision, and the square to 9 digits, can shift a square by; unknown near overflow
            slack = np.where(most < 1e37, 4 * (self.x.shape[1] + 4) * np.finfo(np.float32).eps * most + 1e-8, np.inf)
            with np.errstate(over="ignore", invalid="ignore"):
                # squares less the query's own norm
                rough = self.q_single[a] @ single
                limit = np.where(np.isinf(slack), np.inf, np.minimum(self.bound[a], self.best[a, -1]) + slack - self.q_norms[a])
                flat = np.flatnonzero(~(rough > limit.astype(np.float32)[:, None]))
                of, to = np.divmod(flat, len(rows))
                crowded = np.flatnonzero(np.bincount(of, minlength=len(a)) > 4 * self.k)
                if len(crowded):
                    # the k + 1 least by rough squares (one may be the query itself) bound the k-th best
                    kth = np.full(len(a), np.inf)
                    kth[crowded] = np.partition(rough[crowded], self.k, axis=1)[:, self.k] + 2 * slack[crowded]
                    near = ~(rough[of, to] > kth.astype(np.float32)[of])
                    of, to = of[near], to[near]
            other = self.q_ids[a[of]] != ids[to]
            of, to = of[other], to[other]
            if len(of):
                self._keep(a, of, ids[to], self._measured(a[of], rows[to]))

    def _measured(self, of: np.ndarray, to: np.ndarray) -> np.ndarray:
        """Squared distances of pairs of a query and a row, rounded as in `squares`."""
        d = np.empty(len(of))
        for i in range(0, len(of), MEASURED):
            apart = self.q[of[i : i + MEASURED]] - self.x[to[i : i + MEASURED]]
            d[i : i + MEASURED] = np.einsum("ij,ij->i", apart, apart)
        return np.round(d, 9)

    def _keep(self, a: np.ndarray, of: np.ndarray, who: np.ndarray, d: np.ndarray) -> None:
        """The k best of what queries `a` have and of new pairs (of: places in a, in order)."""
        new = np.unique(of)
        has = np.isfinite(self.best[a[new]])
        of = np.concatenate([np.repeat(new, has.sum(1)), of])
        who = np.concatenate([self.who[a[new]][has], who])
        d = np.concatenate([self.best[a[new]][has], d])
        order = np.lexsort((who, d, of))
        of, who, d = of[order], who[order], d[order]
        rank = np.arange(len(of)) - np.searchsorted(of, of)
        top = rank < self.k
        self.best[a[of[top]], rank[top]] = d[top]
        self.who[a[of[top]], rank[top]] = who[top]


def _matrix(col) -> np.ndarray:
    """Rows of an Arrow column of lists of equal length."""
    return col.flatten().to_numpy().reshape(len(col), -1).astype(np.float64, copy=False) if len(col) else np.zeros((0, 1))


def _columns(part) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(ids, vectors, a, b, home) of a record batch (key, kind, id, v, a, b, home)."""
    return part.column(2).to_numpy(), _matrix(part.column(3)), *(part.column(i).to_numpy() for i in (4, 5, 6))


def _lists(x: np.ndarray, number: str) -> pa.Array:
    """Rows as lists of `number`, float or double: vectors are written and sent as wide as they came."""
    return pa.ListArray.from_arrays(pa.array(np.arange(0, x.size + 1, x.shape[1]), pa.int32()), pa.array(x.reshape(-1).astype(np.float32 if number == "float" else np.float64, copy=False)))


def _row(key, a=None, b=None, home=None, id_="id") -> list:
    """The columns of one side of `_meet`; what it doesn't use is zero."""
    zero = F.lit(0.0)
    return [F.col(key).alias("key"), F.col(id_).alias("id"), "v", (F.col(a) if a else zero).alias("a"), (F.col(b) if b else zero).alias("b"), (F.col(home) if home else F.lit(0).cast("bigint")).alias("home")]


def _meet(held: DataFrame, asked: DataFrame, build, ask, schema: str) -> DataFrame:
    """Rows of `asked` streamed past the rows of `held` of the same key, both as `_row` makes them.

    The held rows of a key come first in its partition: `build(ids, vectors, a, b, home)` makes
    a state of them, once, and `ask(state, key, ids, vectors, a, b, home)` answers each batch of
    asked rows with record batches. No more than one key's held rows are in memory.
    """
    both = held.withColumn("kind", F.lit(0)).unionByName(asked.withColumn("kind", F.lit(1))).select("key", "kind", "id", "v", "a", "b", "home")

    def run(batches):
        key, first, state = None, [], None
        for batch in batches:
            if not batch.num_rows:
                continue
            k, kind = batch.column(0).to_numpy(), batch.column(1).to_numpy()
            edges = (np.flatnonzero((np.diff(k) != 0) | (np.diff(kind) != 0)) + 1).tolist()
            for lo, hi in zip([0, *edges], [*edges, len(k)]):
                part = batch.slice(lo, hi - lo)
                if key is None or k[lo] != key:
                    key, first, state = k[lo], [], None
                if kind[lo] == 0:
                    first.append(part)
                elif first:
                    if state is None:
                        state = build(*(np.concatenate(x) for x in zip(*map(_columns, first))))
                    yield from ask(state, key, *_columns(part))

    return both.repartition("key").sortWithinPartitions("key", "kind", "id").mapInArrow(run, schema)


def _gaps(d2: np.ndarray, pivots: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
    """Least possible distance of queries (rows of squared distances to pivots) to anything that belongs to each pivot.

    A group lies between two spheres around its pivot, and beyond the plane that halves the
    way from its pivot to the one nearest to the query, as its own pivot is nearest to it.
    """
    d = np.sqrt(d2)
    near = d2.argmin(1)
    between = np.sqrt(squares(pivots, pivots))[near]
    # equal pivots share no plane
    plane = np.where(between > 1e-9, (d2 - d2[np.arange(len(d2)), near][:, None]) / np.maximum(2 * between, 1e-9), 0)
    return np.maximum(np.maximum(np.maximum(d - hi[None], lo[None] - d), plane), 0)


def _sent(go: np.ndarray, keys: np.ndarray, ids: np.ndarray, x: np.ndarray, bound: np.ndarray, home: np.ndarray, number: str):
    """Record batches (key, id, v, a, home) of the queries and the keys they go to, `SENT_ROWS` at a time."""
    at, to = np.nonzero(go)
    for i in range(0, len(at), SENT_ROWS):
        q, k = at[i : i + SENT_ROWS], to[i : i + SENT_ROWS]
        yield pa.RecordBatch.from_arrays([pa.array(keys[k]), pa.array(ids[q]), _lists(x[q], number), pa.array(bound[q]), pa.array(home[q])], ["key", "id", "v", "a", "home"])


def _found(q_ids: np.ndarray, best: np.ndarray, who: np.ndarray) -> pa.RecordBatch:
    at, rank = np.nonzero(who >= 0)
    return pa.RecordBatch.from_arrays([pa.array(q_ids[at]), pa.array(who[at, rank]), pa.array(best[at, rank])], ["id", "neighbour", "square"])


def neighbours(vectors: DataFrame, k: int = K, factor: float = FACTOR, id_col: str = "vec_id", vec_col: str = "embedding", shard_rows: int = SHARD_ROWS, seed: int = 3, leaf: int = LEAF, every: int = 1) -> DataFrame:
    """(id, neighbour, rank, distance) of the k best of all vectors for each whose id is divisible by `every`; the distance is rounded to 6 digits."""
    spark = vectors.sparkSession
    given = vectors.select(vec_col).schema[0].dataType
    number = "float" if isinstance(given, ArrayType) and isinstance(given.elementType, FloatType) else "double"
    v = F.col(vec_col).cast(f"array<{number}>")
    sound = vectors.select(F.col(id_col).cast("bigint").alias("id"), v.alias("v")).where("id is not null and size(v) > 0").where(~F.exists("v", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf"))))
    lengths = sound.groupBy(F.size("v").alias("dims")).count().orderBy(F.desc("count"), "dims").first()
    if lengths is None:
        return spark.createDataFrame([], "id bigint, neighbour bigint, rank int, distance double")
    base = cut(sound.where(F.size("v") == lengths["dims"]).groupBy("id").agg(F.min("v").alias("v")), "vectors")
    n = base.count()
    shards = max(1, -(-n // shard_rows))
    order = F.xxhash64("id", F.lit(seed))
    # the root of the number of shards: all that the driver and a broadcast ever hold
    first = base.orderBy(order, "id").limit(max(1, int(np.ceil(np.sqrt(shards))))).collect()
    top = spark.sparkContext.broadcast(np.array([r["v"] for r in first]))
    place = f"id bigint, v array<{number}>, cell bigint, d double"

    def to_cell(batches):
        for b in batches:
            x = _matrix(b.column(1))
            if len(x):
                d = squares(x, top.value)
                home = d.argmin(1)
                yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(home.astype(np.int64)), pa.array(np.sqrt(d[np.arange(len(d)), home]))], ["id", "v", "cell", "d"])

    celled = cut(base.mapInArrow(to_cell, place), "cells")
    around = {r["cell"]: (r["lo"], r["hi"]) for r in celled.groupBy("cell").agg(F.min("d").alias("lo"), F.max("d").alias("hi")).collect()}
    ring = spark.sparkContext.broadcast(tuple(np.array([around.get(i, (np.inf, -np.inf))[j] for i in range(len(first))]) for j in (0, 1)))
    # pivots of shards: each vector by a seeded hash with the chance shards / n, and those of the cells, so that no cell is without
    share = F.pmod(order, F.lit(1 << 30)) < int((1 << 30) * min(1.0, shards / max(n, 1)))
    pivots = celled.where(share | F.col("id").isin([r["id"] for r in first])) if shards > 1 else celled.where(F.col("id") == first[0]["id"])

    def nearest(state, key, ids, x, *_):
        p_ids, p = state
        d = squares(x, p)
        home = d.argmin(1)
        yield pa.RecordBatch.from_arrays([pa.array(ids), _lists(x, number), pa.array(np.full(len(ids), key)), pa.array(p_ids[home]), pa.array(np.sqrt(d[np.arange(len(d)), home]))], ["id", "v", "cell", "shard", "d"])

    placed = cut(_meet(pivots.select(*_row("cell")), celled.select(*_row("cell")), lambda ids, x, *_: (ids, x), nearest, f"id bigint, v array<{number}>, cell bigint, shard bigint, d double"), "shards")
    # `placed` has their rows
    drop(base)
    drop(celled)

    def own(tree, key, ids, x, *_):
        yield _found(ids, *tree.search(ids, x, k, factor))

    out = "id bigint, neighbour bigint, square double"
    asked = placed.where(F.col("id") % every == 0)
    home = _meet(placed.select(*_row("shard")), asked.select(*_row("shard")), lambda ids, x, *_: Tree(ids, x, leaf), own, out)
    if shards > 1:
        home = cut(home, "home")
        kth = home.groupBy("id").agg(F.when(F.count("*") >= k, F.max("square")).otherwise(float("inf")).alias("bound"))
        questions = asked.join(kth, "id", "left").select("id", "v", F.coalesce("bound", F.lit(float("inf"))).alias("bound"), "shard")
        shape = f"key bigint, id bigint, v array<{number}>, a double, home bigint"

        def open_cells(batches):
            lo, hi = ring.value
            for b in batches:
                x = _matrix(b.column(1))
                if len(x):
                    gap = _gaps(squares(x, top.value), top.value, lo, hi) * factor
                    ids, bound, own_shard = (b.column(i).to_numpy() for i in (0, 2, 3))
                    yield from _sent(gap <= np.sqrt(bound)[:, None] + 1e-6, np.arange(len(first)), ids, x, bound, own_shard, number)

        to_cells = questions.mapInArrow(open_cells, shape).select(*_row("key", a="a", home="home"))
        rings = placed.groupBy("cell", "shard").agg(F.min("d").alias("a"), F.max("d").alias("b"))
        signs = rings.join(placed.select(F.col("id").alias("shard"), "v"), "shard").select(*_row("cell", a="a", b="b", id_="shard"))

        def open_shards(state, key, ids, x, bound, _, home):
            p_ids, p, lo, hi = state
            go = (_gaps(squares(x, p), p, lo, hi) * factor <= np.sqrt(bound)[:, None] + 1e-6) & (p_ids[None] != home[:, None])
            yield from _sent(go, p_ids, ids, x, bound, home, number)

        to_shards = _meet(signs, to_cells, lambda ids, x, a, b, _: (ids, x, a, b), open_shards, shape).select(*_row("key", a="a"))

        def others(tree, key, ids, x, bound, *_):
            best, who = tree.search(ids, x, k, factor, bound)
            yield _found(ids, best, np.where(best <= bound[:, None], who, -1))

        home = home.unionByName(_meet(placed.select(*_row("shard")), to_shards, lambda ids, x, *_: Tree(ids, x, leaf), others, out))
    rank = F.row_number().over(Window.partitionBy("id").orderBy("square", "neighbour"))
    return home.withColumn("rank", rank).where(F.col("rank") <= k).select("id", "neighbour", "rank", F.round(F.sqrt("square"), 6).alias("distance"))


def op8_vantage_points(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The 10 nearest of all vectors for every vector whose id is divisible by 50."""
    return neighbours(spark.read.parquet(f"{sf_dir}/embeddings.parquet"), every=EVERY).withColumnsRenamed({"id": "vec_id", "neighbour": "neighbour_id"})


OP8_SQL = """
WITH p AS (
  SELECT a.vec_id, b.vec_id AS neighbour_id, round(greatest(list_sum(list_transform(list_zip(a.embedding, b.embedding), lambda z: (z[1]::DOUBLE - z[2]::DOUBLE) * (z[1]::DOUBLE - z[2]::DOUBLE))), 0), 9) AS sq
  FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id AND a.vec_id % 50 = 0
), r AS (SELECT *, row_number() OVER (PARTITION BY vec_id ORDER BY sq, neighbour_id) AS rank FROM p)
SELECT vec_id, neighbour_id, CAST(rank AS INTEGER) AS rank, round(sqrt(sq), 6) AS distance FROM r WHERE rank <= 10
"""
