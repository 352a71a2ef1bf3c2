"""Cross-validated experiments: recall by algorithm, cap, scorer and round."""

from __future__ import annotations

from dataclasses import replace

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..model import BlockingConfig
from . import learn
from .sizes import Features, canonical_pairs, pieces

RESULT = "workload string, algorithm string, scorer string, cap bigint, fold int, recall double, height double, rounds int"
ALGORITHMS = ("random", "single", "chain", "level_tree", "block_tree")


def _order(l, r, seed: int):
    return F.md5(F.concat_ws("|", F.lit(str(seed)), l.cast("string"), r.cast("string")))


def cross_validation_folds(pairs: DataFrame, k: int = 5, seed: int = 42) -> DataFrame:
    """(l_id, r_id, fold): equal folds in the order of an md5. The pair table is small; its window has one partition."""
    p = canonical_pairs(pairs)
    return p.withColumn("fold", F.ntile(k).over(Window.orderBy(_order(F.col("l_id"), F.col("r_id"), seed), "l_id", "r_id")) - 1)


def folds(f: Features, k: int = 5, seed: int = 42, by: str = "pair") -> np.ndarray:
    """Fold of each pair: at random by pair, or by cluster, so that copies of one record don't stand in training and test."""
    import hashlib

    n = len(f.pair_ids)
    if by == "cluster":
        parent: dict = {}

        def root(x):
            while parent.setdefault(x, x) != x:
                parent[x] = parent[parent[x]]
                x = parent[x]
            return x

        of: dict = {}
        for x in pieces(n):
            for a, b in f.pair_ids[x].tolist():
                parent[root(a)] = root(b)
        out = np.zeros(n, np.int16)
        for x in pieces(n):
            top = [root(a) for a in f.pair_ids[x, 0].tolist()]
            for t in set(top).difference(of):
                of[t] = int(hashlib.md5(f"{seed}|{t}".encode()).hexdigest()[:8], 16) % k
            out[x] = [of[t] for t in top]
        return out

    def keys(ids) -> np.ndarray:
        return np.frombuffer(b"".join(hashlib.md5(f"{seed}|{a}|{b}".encode()).digest() for a, b in ids.tolist()), ">u8").reshape(-1, 2)

    # folds are runs of the order of md5: the first half of it tells on which side of a run's end a pair is, and the whole of it for the few where it is the end
    first = np.empty(n, np.uint64)
    for x in pieces(n):
        first[x] = keys(f.pair_ids[x])[:, 0]
    ends = np.cumsum([n // k + (i < n % k) for i in range(k)])[:-1]
    out = np.zeros(n, np.int16)
    ordered = np.sort(first)
    for end in ends[ends < n]:
        at = ordered[end]
        rows = np.flatnonzero(first == at)
        ids = np.asarray(f.pair_ids[rows])
        rows = rows[np.lexsort((ids[:, 1], ids[:, 0], keys(ids)[:, 1]))]
        out += first > at
        out[rows[end - np.searchsorted(ordered, at) :]] += 1
    return out


def _parts(f: Features, k: int, seed: int, by: str):
    of = folds(f, k, seed, by)
    for fold in range(k):
        yield fold, f.pick(np.flatnonzero(of != fold)), f.pick(np.flatnonzero(of == fold))


def cross_validate(f: Features, workload: str, caps: list[int], algorithms=ALGORITHMS, scorers=("optimistic",), k: int = 5, seed: int = 42, rounds: bool = False, by: str = "pair", config: BlockingConfig | None = None, only_fold: int | None = None) -> list[tuple]:
    """Rows of RESULT: test recall, height and rounds of every algorithm, scorer, cap and fold, without another scan."""
    out = []
    base = config or BlockingConfig(1)
    for fold, train, test in _parts(f, k, seed, by):
        if only_fold is not None and fold != only_fold:
            continue
        for cap in caps:
            for algorithm in algorithms:
                if algorithm == "random":
                    blocks = max(1, int(np.ceil(f.n / cap)))
                    hit = sum(int(np.equal(*(test.mix[x] % blocks).T).sum()) for x in pieces(len(test.same))) / len(test.same) if len(test.same) else 1.0
                    out.append((workload, "random", "", cap, fold, float(hit), 0.0, 1))
                    continue
                for scorer in scorers:
                    c = replace(base, max_block_size=cap, scorer=scorer, seed=seed)
                    if rounds:
                        plan = learn.learn_rounds(train, c, algorithm)
                        hit = learn.covered_by_any(test, plan)
                        h = float(np.mean([t.height for t in plan.rounds])) if plan.rounds else 0.0
                        out.append((workload, algorithm + "_rounds", scorer, cap, fold, float(hit.mean()) if len(hit) else 1.0, h, len(plan.rounds)))
                    else:
                        t = learn.LEARNERS[algorithm](train, c)
                        out.append((workload, algorithm, scorer, cap, fold, learn.recall(test, t), float(t.height), 1))
    return out


def result_table(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    return spark.createDataFrame(rows, RESULT)


def means(result: DataFrame) -> DataFrame:
    """Mean over folds."""
    return result.groupBy("workload", "algorithm", "scorer", "cap").agg(F.round(F.avg("recall"), 6).alias("recall"), F.round(F.avg("height"), 6).alias("height"), F.round(F.avg("rounds"), 6).alias("rounds"), F.count("*").alias("folds"))


def pivoted(result: DataFrame, caps: list[int]) -> DataFrame:
    """Algorithms by caps, the form of a results table."""
    return result.groupBy("algorithm").pivot("cap", caps).agg(F.round(F.avg("recall"), 4)).orderBy("algorithm")


def grouping_report(result: DataFrame) -> DataFrame:
    """Mean recall by (algorithm, cap), by algorithm, by cap and in all; `level` tells which."""
    return result.cube("algorithm", "cap").agg(F.round(F.avg("recall"), 6).alias("recall"), F.count("*").alias("n"), F.grouping_id().cast("bigint").alias("level")).fillna("(all)", ["algorithm"]).fillna(-1, ["cap"])


def per_round(f: Features, caps: int, learner: str, k: int = 5, seed: int = 42, fold: int = 0, config: BlockingConfig | None = None) -> list[tuple]:
    """(algorithm, round, recall): cumulative test recall of each round on one fold."""
    out = []
    for i, train, test in _parts(f, k, seed, "pair"):
        if i != fold:
            continue
        plan = learn.learn_rounds(train, replace(config or BlockingConfig(caps), max_block_size=caps, seed=seed), learner)
        hits = learn.covered_by_round(test, plan)
        seen = np.zeros(len(test.same), bool)
        for r in range(hits.shape[1]):
            seen |= hits[:, r]
            out.append((learner, r, float(seen.mean()) if len(seen) else 1.0))
    return out


def diff_plans(a: DataFrame, b: DataFrame, pairs: DataFrame) -> DataFrame:
    """Pairs kept by both of two assignments, by one alone, by none."""
    from .cost import together

    x, y = together(a, pairs).withColumnRenamed("kept", "in_a"), together(b, pairs).withColumnRenamed("kept", "in_b")
    return x.join(y, ["l_id", "r_id"], "full").groupBy(F.coalesce("in_a", F.lit(False)).alias("in_a"), F.coalesce("in_b", F.lit(False)).alias("in_b")).agg(F.count("*").alias("n_pairs"))


def check_rollup(before: DataFrame, merged: DataFrame, cap: int) -> DataFrame:
    """One row: does every merged block fit the cap, and is every old block in one new block?"""
    sizes = before.groupBy("block_key").agg(F.count("*").alias("n"))
    new = sizes.join(merged, "block_key", "left").withColumn("merged_key", F.coalesce("merged_key", "block_key"))
    by = new.groupBy("merged_key").agg(F.sum("n").alias("n"), F.count("*").alias("old"))
    return by.agg(F.max(F.when(F.col("old") > 1, F.col("n"))).alias("largest_merged"), F.coalesce(F.every((F.col("old") == 1) | (F.col("n") <= cap)), F.lit(True)).alias("fits"), F.sum("old").alias("old_blocks"), F.count("*").alias("new_blocks"))
