"""Scores of hash functions at a node as a DataFrame, for pair sets too large for the driver and for reports."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..model import BlockingSpec, HashFn
from .sizes import _long, canonical_pairs, project


def _names(df: DataFrame, library: list[HashFn]) -> DataFrame:
    return df.withColumn("hash", F.element_at(F.array(*[F.lit(h.name) for h in library]), F.col("hash") + 1))


def long_sizes(df: DataFrame, spec: BlockingSpec, library: list[HashFn]) -> DataFrame:
    """(hash, value, n) of every value of every function: one pass, a partial aggregate and one shuffle of blocks."""
    return _names(_long(project(df, spec, library), len(library)).groupBy("hash", "value").agg(F.count("*").alias("n")), library)


def long_pairs(df: DataFrame, spec: BlockingSpec, pairs: DataFrame, library: list[HashFn]) -> DataFrame:
    """(hash, l_id, r_id, lv, rv): values of both records of every pair."""
    p = canonical_pairs(pairs)
    ids = p.select(F.explode_outer(F.array("l_id", "r_id")).alias("__pid")).distinct()
    h = project(df.join(ids, F.col(spec.id_col) == F.col("__pid"), "left_semi"), spec, library).select("id", F.array(*[F.col(f"h{i}") for i in range(len(library))]).alias("v"))
    # a record's values are many times what Spark takes from the size of its file, and would be broadcast
    l, r = (h.select(F.col("id").alias(f"{s}_id"), F.col("v").alias(f"{s}v")).hint("merge") for s in "lr")
    both = p.join(l, "l_id").join(r, "r_id")
    z = both.select("l_id", "r_id", F.posexplode_outer(F.arrays_zip("lv", "rv")).alias("hash", "z"))
    return _names(z.select("hash", "l_id", "r_id", F.col("z.lv").alias("lv"), F.col("z.rv").alias("rv")), library)


def profile(df: DataFrame, spec: BlockingSpec, pairs: DataFrame, library: list[HashFn]) -> DataFrame:
    """(hash, n_blocks, max_block, sum_sq, pairs_kept, recall) of every function alone."""
    n = F.col("n").cast("decimal(38,0)")
    s = long_sizes(df, spec, library).groupBy("hash").agg(F.count("*").alias("n_blocks"), F.max("n").alias("max_block"), F.sum(n * n).cast("bigint").alias("sum_sq"))
    kept = long_pairs(df, spec, pairs, library).groupBy("hash").agg(F.sum((F.col("lv") == F.col("rv")).cast("bigint")).alias("pairs_kept"), F.count("*").alias("p"))
    return s.join(kept, "hash").select("hash", "n_blocks", "max_block", "sum_sq", "pairs_kept", F.round(F.col("pairs_kept") / F.col("p"), 6).alias("recall"))


def score_root(df: DataFrame, spec: BlockingSpec, pairs: DataFrame, library: list[HashFn], cap: int) -> DataFrame:
    """(hash, broken, n_heavy, max_child, optimistic, pessimistic, expected) at the root."""
    size = long_sizes(df, spec, library)
    p = long_pairs(df, spec, pairs, library)
    broken = p.groupBy("hash").agg(F.sum((F.col("lv") != F.col("rv")).cast("bigint")).alias("broken"))
    inside = p.where("lv = rv").groupBy("hash", F.col("lv").alias("value")).agg(F.count("*").alias("pairs"))
    heavy = size.where(F.col("n") > cap).join(inside, ["hash", "value"], "left").fillna(0, ["pairs"])
    parts = F.ceil(F.col("n") / cap)
    h = heavy.groupBy("hash").agg(F.count("*").alias("n_heavy"), F.sum("pairs").alias("at_risk"), F.sum(F.col("pairs") * (parts - 1) / parts).alias("expected_loss"))
    top = size.groupBy("hash").agg(F.max("n").alias("max_child"))
    x = broken.join(top, "hash").join(h, "hash", "left").fillna(0, ["n_heavy", "at_risk"]).fillna(0.0, ["expected_loss"])
    return x.select("hash", "broken", F.col("n_heavy").cast("bigint").alias("n_heavy"), "max_child", F.col("broken").cast("double").alias("optimistic"), (F.col("broken") + F.col("at_risk")).cast("double").alias("pessimistic"), F.round(F.col("broken") + F.col("expected_loss"), 6).alias("expected"))


def first_split(scores: DataFrame, scorer: str, n: int) -> DataFrame:
    """The function that the greedy learner takes first: least score, then fewer heavy children, smaller largest child, name."""
    w = Window.orderBy(scorer, "n_heavy", "max_child", "hash")
    return scores.where(F.col("max_child") < n).withColumn("rank", F.row_number().over(w)).where("rank = 1").select("hash", F.col(scorer).alias("score"), "n_heavy", "max_child")


def score_root_sql(spec: BlockingSpec, library: list[HashFn], source: str, pairs: str, cap: int) -> str:
    """The same table in DuckDB; source and pairs are SELECTs."""
    from ..functions.hashes import duck_sql

    vals = " UNION ALL ".join(f"SELECT {spec.id_col} AS id, '{h.name}' AS hash, {duck_sql(h, spec)} AS value FROM src" for h in library)
    return f"""
WITH src AS ({source}), pr AS ({pairs}), v AS ({vals}),
size AS (SELECT hash, value, count(*) AS n FROM v GROUP BY ALL),
p AS (SELECT l.hash, l.value AS lv, r.value AS rv FROM pr JOIN v l ON l.id = pr.l_id JOIN v r ON r.id = pr.r_id AND r.hash = l.hash),
b AS (SELECT hash, CAST(count(*) FILTER (WHERE lv <> rv) AS BIGINT) AS broken FROM p GROUP BY hash),
i AS (SELECT hash, lv AS value, count(*) AS pairs FROM p WHERE lv = rv GROUP BY ALL),
h AS (SELECT hash, count(*) AS n_heavy, sum(coalesce(pairs, 0)) AS at_risk, sum(coalesce(pairs, 0) * (ceil(n / {cap}.0) - 1) / ceil(n / {cap}.0)) AS expected_loss
  FROM size LEFT JOIN i USING (hash, value) WHERE n > {cap} GROUP BY hash),
t AS (SELECT hash, max(n) AS max_child FROM size GROUP BY hash),
scores AS (SELECT hash, broken, CAST(coalesce(n_heavy, 0) AS BIGINT) AS n_heavy, max_child, CAST(broken AS DOUBLE) AS optimistic,
  CAST(broken + coalesce(at_risk, 0) AS DOUBLE) AS pessimistic, round(CAST(broken + coalesce(expected_loss, 0) AS DOUBLE), 6) AS expected
  FROM b JOIN t USING (hash) LEFT JOIN h USING (hash))"""


def profile_sql(spec: BlockingSpec, library: list[HashFn], source: str, pairs: str) -> str:
    from ..functions.hashes import duck_sql

    vals = " UNION ALL ".join(f"SELECT {spec.id_col} AS id, '{h.name}' AS hash, {duck_sql(h, spec)} AS value FROM src" for h in library)
    return f"""
WITH src AS ({source}), pr AS ({pairs}), v AS ({vals}),
size AS (SELECT hash, value, count(*) AS n FROM v GROUP BY ALL),
s AS (SELECT hash, count(*) AS n_blocks, max(n) AS max_block, CAST(sum(n * n) AS BIGINT) AS sum_sq FROM size GROUP BY hash),
p AS (SELECT l.hash, l.value = r.value AS kept FROM pr JOIN v l ON l.id = pr.l_id JOIN v r ON r.id = pr.r_id AND r.hash = l.hash),
k AS (SELECT hash, CAST(count(*) FILTER (WHERE kept) AS BIGINT) AS pairs_kept, count(*) AS n FROM p GROUP BY hash)
SELECT hash, n_blocks, max_block, sum_sq, pairs_kept, round(pairs_kept / n, 6) AS recall FROM s JOIN k USING (hash)"""
