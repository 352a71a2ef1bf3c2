"""Costs and accuracy of block sets, and assignment of blocks to machines."""

from __future__ import annotations

import heapq
import time
from itertools import product

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.scratch import cut
from .sizes import canonical_pairs

_BIG = "decimal(38,0)"


def cost_summary(sizes: DataFrame) -> DataFrame:
    """One row: blocks, records, largest block, comparisons as squares and as pairs, squares of the largest. sizes: (block_key, n)."""
    n = F.col("n").cast(_BIG)
    return sizes.agg(
        F.count("*").alias("n_blocks"),
        F.coalesce(F.sum("n"), F.lit(0)).cast("bigint").alias("n_records"),
        F.coalesce(F.max("n"), F.lit(0)).cast("bigint").alias("max_block"),
        F.coalesce(F.sum(n * n), F.lit(0)).cast(_BIG).alias("sum_sq"),
        F.coalesce(F.sum((n * (n - 1)).cast(_BIG)), F.lit(0)).cast(_BIG).alias("twice_pairs"),
        F.coalesce(F.max(n * n), F.lit(0)).cast(_BIG).alias("max_sq"),
    )


def makespan_bounds(sizes: DataFrame, machines: int) -> DataFrame:
    """Lower bound X = max(largest square, all squares / m), its double, and the bound (1 + k/m) largest square."""
    s = cost_summary(sizes)
    mx, sm = F.col("max_sq").cast("double"), F.col("sum_sq").cast("double")
    x = F.greatest(mx, sm / machines)
    return s.select(F.lit(machines).alias("machines"), F.round(x, 6).alias("lower"), F.round(2 * x, 6).alias("upper"), F.round((1 + F.col("n_blocks") / machines) * mx, 6).alias("upper_by_count"))


def overlap_cost(assigned: DataFrame) -> DataFrame:
    """Cost of overlapping blocks: squares of the largest plus all memberships. assigned: (id, round, block_key)."""
    s = assigned.groupBy("round", "block_key").agg(F.count("*").alias("n")).agg(F.coalesce(F.max("n"), F.lit(0)).cast("bigint").alias("max_block"), F.coalesce(F.sum("n"), F.lit(0)).cast("bigint").alias("memberships"))
    return s.withColumn("overlap_cost", (F.col("max_block") * F.col("max_block") + F.col("memberships")).cast("bigint"))


def pair_blocks_cost(records: DataFrame) -> DataFrame:
    """`overlap_cost` of a block for every pair of records, of which there are as many as their number says, without making one."""
    n = records.agg(F.count("*").alias("n")).select((F.col("n") * (F.col("n") - 1)).alias("m"))
    return n.select(F.lit(2).cast("bigint").alias("max_block"), F.col("m").alias("memberships"), (F.col("m") + 4).alias("overlap_cost"))


def custom_cost(assigned: DataFrame, measure: Column, combine: str = "max") -> DataFrame:
    """Any monotone cost: an aggregate `measure` for each block, combined by max or sum."""
    return assigned.groupBy("block_key").agg(measure.alias("cost")).agg(getattr(F, combine)("cost").alias("cost"))


def together(assigned: DataFrame, pairs: DataFrame) -> DataFrame:
    """(l_id, r_id, kept) of a disjoint assignment (id, block_key). Pairs with a record that isn't there are dropped."""
    assigned = cut(assigned.select("id", "block_key"), "assigned")
    l, r = (assigned.select(F.col("id").alias(f"{p}_id"), F.col("block_key").alias(f"{p}k")) for p in "lr")
    return canonical_pairs(pairs).join(l, "l_id").join(r, "r_id").select("l_id", "r_id", (F.col("lk") == F.col("rk")).alias("kept"))


def recall(assigned: DataFrame, pairs: DataFrame) -> DataFrame:
    """One row: pairs, kept ones, split ones, recall."""
    t = together(assigned, pairs)
    kept = F.coalesce(F.sum(F.col("kept").cast("bigint")), F.lit(0))
    return t.agg(F.count("*").alias("n_pairs"), kept.alias("kept"), (F.count("*") - kept).alias("split"), F.round(kept / F.count("*"), 6).alias("recall"))


def recall_by_round(assigned: DataFrame, pairs: DataFrame, rounds: int) -> DataFrame:
    """(round, covered, recall): pairs first covered by each round, cumulative recall. assigned: (id, round, block_key)."""
    from pyspark.sql import Window

    l, r = (assigned.select(F.col("id").alias(f"{p}_id"), "round", F.col("block_key").alias(f"{p}k")) for p in "lr")
    p = canonical_pairs(pairs)
    first = p.join(l, "l_id").join(r, ["r_id", "round"]).where("lk = rk").groupBy("l_id", "r_id").agg(F.min("round").alias("round"))
    n = p.count()
    grid = assigned.sparkSession.range(rounds).select(F.col("id").cast("int").alias("round"))
    by = grid.join(first.groupBy("round").agg(F.count("*").alias("covered")), "round", "left").fillna(0)
    return by.select("round", "covered", F.round(F.sum("covered").over(Window.orderBy("round").rowsBetween(Window.unboundedPreceding, 0)) / F.lit(max(n, 1)), 6).alias("recall"))


def reduction_ratio(sizes: DataFrame) -> DataFrame:
    """Share of all record pairs that need no comparison."""
    s = cost_summary(sizes)
    n = F.col("n_records").cast("double")
    return s.select(F.round(1 - F.col("twice_pairs").cast("double") / (n * (n - 1)), 6).alias("reduction_ratio"))


def quality_of_pairs(predicted: DataFrame, truth: DataFrame) -> DataFrame:
    """Precision, recall and F1 of predicted pairs against true ones."""
    p, t = canonical_pairs(predicted), canonical_pairs(truth)
    hit = p.join(t, ["l_id", "r_id"]).agg(F.count("*").alias("hits"))
    np_, nt = p.agg(F.count("*").alias("predicted")), t.agg(F.count("*").alias("true_pairs"))
    x = hit.crossJoin(F.broadcast(np_)).crossJoin(F.broadcast(nt))
    prec, rec = F.col("hits") / F.col("predicted"), F.col("hits") / F.col("true_pairs")
    return x.select("hits", "predicted", "true_pairs", F.round(prec, 6).alias("precision"), F.round(rec, 6).alias("recall"), F.round(2 * F.col("hits") / (F.col("predicted") + F.col("true_pairs")), 6).alias("f1"))


# machines -------------------------------------------------------------------------


def schedule(squares: list[int], machines: int, method: str = "lpt") -> tuple[int, list[int]]:
    """(makespan, machine of each block): "lpt" largest first, "list" in order, "round_robin", or "exact" for at most 12."""
    n = len(squares)
    if method == "exact":
        if n > 12:
            raise ValueError("exact scheduling is for at most 12 blocks")
        best = None
        for a in product(range(machines), repeat=n):
            if n and a[0] != 0:
                break
            load = [0] * machines
            for s, m in zip(squares, a):
                load[m] += s
            if best is None or max(load) < best[0]:
                best = (max(load), list(a))
        return best or (0, [])
    if method == "round_robin":
        at = [i % machines for i in range(n)]
    else:
        order = sorted(range(n), key=lambda i: (-squares[i], i)) if method == "lpt" else range(n)
        heap, at = [(0, m) for m in range(machines)], [0] * n
        for i in order:
            load, m = heapq.heappop(heap)
            at[i] = m
            heapq.heappush(heap, (load + squares[i], m))
    load = [0] * machines
    for s, m in zip(squares, at):
        load[m] += s
    return max(load, default=0), at


def lpt_makespan(sizes: DataFrame, machines: int) -> int:
    """Makespan of largest-first scheduling from the histogram of block sizes, which has no more rows than the largest block."""
    rows = sizes.groupBy("n").agg(F.count("*").alias("k")).orderBy(F.desc("n")).collect()
    heap = [(0, m) for m in range(machines)]
    heapq.heapify(heap)
    for r in rows:
        sq, k = r["n"] ** 2, r["k"]
        # whole rounds put one block on every machine and change no order
        low = heap[0][0]
        if k > 4 * machines and max(x for x, _ in heap) - low <= sq:
            each, k = divmod(k, machines)
            heap = [(x + each * sq, m) for x, m in heap]
            heapq.heapify(heap)
        for _ in range(k):
            x, m = heapq.heappop(heap)
            heapq.heappush(heap, (x + sq, m))
    return max(x for x, _ in heap)


def makespan(sizes: DataFrame, assignment: DataFrame) -> DataFrame:
    """Makespan of a given assignment (block_key, machine)."""
    n = F.col("n").cast(_BIG)
    return sizes.join(assignment, "block_key").groupBy("machine").agg(F.sum(n * n).alias("load")).agg(F.max("load").cast(_BIG).alias("makespan"))


def lpt_partitions(assigned: DataFrame, sizes: DataFrame) -> DataFrame:
    """Records range-partitioned so that blocks of most comparisons come first: the scheduler, which takes tasks in order, then works largest-first."""
    return assigned.join(sizes, "block_key").repartitionByRange(F.desc("n"), "block_key")


def time_per_record(df: DataFrame, blocked: DataFrame, reps: int = 5) -> dict:
    """Microseconds a record to block, over the scan alone, averaged over repetitions into the noop sink.

    Wall time over all cores; scans and blockings take turns, so that a slower spell hits both.
    A difference below the noise may come out negative and is reported as it is.
    """

    def run(x: DataFrame) -> float:
        t = time.perf_counter()
        x.write.format("noop").mode("overwrite").save()
        return time.perf_counter() - t

    n = df.count()
    run(df), run(blocked)
    turns = [(run(df), run(blocked)) for _ in range(reps)]
    scan, full = (sum(x) / reps / max(n, 1) * 1e6 for x in zip(*turns))
    return {"records": n, "scan_us": scan, "block_us": full - scan}
