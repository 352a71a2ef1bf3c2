"""Driver queries: one for each method, variant, baseline, measure and workload, with SQL where SQL can say it."""

from __future__ import annotations

import json
from functools import cache
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import workloads as w
from .functions import hashes as h
from .functions.hashes import default_library, duck_sql
from .functions.scratch import cut
from .model import BlockingConfig, BlockTree, Interval, Node, RoundPlan
from .operators import assign, cost, dedup, drilldown, evaluate, learn, rollup, score, sizes
from .plans.sqltext import assign_sql, split_sql, tree_sql
from .streaming import blocks as events_

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return add


@cache
def _frozen() -> dict[str, str]:
    return json.loads((Path(__file__).parent / "plans" / "frozen.json").read_text())


def frozen(name: str) -> BlockTree:
    return BlockTree.from_json(_frozen()[name])


#: Caps of the frozen trees; random splits of oversized blocks are made by real sizes.
CAP, SMALL_CAP = 50, 10


def frozen_rounds() -> RoundPlan:
    return RoundPlan([assign.without_parts(t) for t in RoundPlan.from_json(_frozen()["rounds"]).rounds])


def docs_of(spark: SparkSession, sf_dir: str) -> DataFrame:
    return w.table(spark, sf_dir, "documents")


D, P, C = w.DOC_SPEC, w.PART_SPEC, w.CUSTOMER_SPEC
PARTS = f"SELECT * FROM ({w.PART_FEEDS_SQL})"
PART_PAIRS = f"SELECT a.rec_id AS l_id, b.rec_id AS r_id FROM ({w.PART_FEEDS_SQL}) a JOIN ({w.PART_FEEDS_SQL}) b ON a.ent = b.ent AND a.rec_id < b.rec_id"
DOC_PAIRS = f"SELECT l_id, r_id FROM ({w.DOC_PAIRS_SQL})"
#: All functions, and all but the longest token, which alone keeps nearly all pairs of this data in small blocks.
D_LIBRARY = default_library(D)
D_CUT = default_library(D, without=("longest_token",))
P_LIBRARY = default_library(P)
C_LIBRARY = default_library(C)


def _column_name(f) -> str:
    return f"{f.attribute}_{f.family}" if f.family == "no_stopwords" else f.name.replace(".", "_")


#: Partitions of part sizes, and of names ordered by a token.
INTERVALS = [Interval(None, 7, False), Interval(7, 20, True, True), Interval(20, 35, False), Interval(35, None, True)]
NAME_INTERVALS = [Interval(None, "c", False), Interval("c", "mid", True), Interval("mid", "s", True, True), Interval("s", None, False)]


def _hash_query(spec, library, source, sql_source):
    def run(spark, sf_dir):
        return source(spark, sf_dir).select(F.col(spec.id_col).alias("id"), *[h.column(x, spec).alias(_column_name(x)) for x in library])

    sql = f"SELECT {spec.id_col} AS id, " + ", ".join(f"{duck_sql(x, spec)} AS {_column_name(x)}" for x in library) + f" FROM ({sql_source})"
    return run, sql


for _name, _args in {
    "hash_library_documents": (D, [x for x in default_library(D) if x.family in ("identity", "prefix", "suffix") and x.attribute != "text"] + [h.prefix("text", 5), h.suffix("text", 5)], docs_of, "FROM documents"),
    "hash_top_chars": (P, [h.top_chars(a, k) for a in ("name", "brand") for k in (1, 3, 5)], w.part_feeds, w.PART_FEEDS_SQL),
    "hash_top_chars_documents": (D, [h.top_chars(a, k) for a in ("line1", "text") for k in (1, 3, 5)], docs_of, "FROM documents"),
    "hash_intervals": (P, [h.interval_hash("size", INTERVALS), h.interval_hash("name", NAME_INTERVALS, "last_token"), h.interval_hash("name", NAME_INTERVALS, "first_token")], w.part_feeds, w.PART_FEEDS_SQL),
    "hash_longest_token": (D, [h.longest_token("text"), h.longest_token("line1")], docs_of, "FROM documents"),
    "hash_name_tokens": (C, [h.first_token("name"), h.last_token("name"), h.token("name", 2), h.no_stopwords("name"), h.normalised("name"), h.digit_prefix("name", 8)], w.customer_feeds, w.CUSTOMER_FEEDS_SQL),
    "hash_bucket_int": (C, [h.bucket_int("zip", k) for k in (2, 5, 10, 100, 1000)], w.customer_feeds, w.CUSTOMER_FEEDS_SQL),
    "hash_dates": (w.ORDER_SPEC, [h.date_bucket("day", u) for u in ("week", "month", "year")], lambda s, d: w.table(s, d, "orders"), "FROM orders"),
}.items():
    QUERIES[_name], ORACLES[_name] = _hash_query(*_args)


@query()
def hash_extensions(spark, sf_dir):
    """Phonetic, min-hash and hyperplane functions, which DuckDB lacks."""
    emb = w.BlockingSpec("vec_id", (w.Attribute("embedding", "text", "embedding"),))
    d = docs_of(spark, sf_dir).select("doc_id", h.column(h.soundex("line1"), D).alias("a"), h.column(h.minhash("line1", 0), D).alias("b"))
    v = w.table(spark, sf_dir, "embeddings").select("vec_id", h.column(h.sign_bits("embedding", 8), emb).alias("bits"))
    return d.groupBy("a").agg(F.count("*").alias("n"), F.count_distinct("b").alias("n_minhash")).unionByName(v.groupBy(F.col("bits").alias("a")).agg(F.count("*").alias("n"), F.lit(0).cast("bigint").alias("n_minhash")))


# sizes, profiles, scores -----------------------------------------------------------


@query(f"SELECT value AS block_key, count(*) AS n FROM (SELECT {duck_sql(h.prefix('text', 3), D)} AS value FROM documents) GROUP BY 1")
def block_sizes_prefix(spark, sf_dir):
    return docs_of(spark, sf_dir).select(h.column(h.prefix("text", 3), D).alias("block_key")).groupBy("block_key").agg(F.count("*").alias("n"))


@query(score.profile_sql(D, D_LIBRARY, "FROM documents", DOC_PAIRS))
def single_hash_profile(spark, sf_dir):
    d = docs_of(spark, sf_dir)
    return score.profile(d, D, w.doc_pairs(d), D_LIBRARY)


@query(score.profile_sql(P, P_LIBRARY, PARTS, PART_PAIRS))
def single_hash_profile_parts(spark, sf_dir):
    p = w.part_feeds(spark, sf_dir)
    return score.profile(p, P, w.ent_pairs(p), P_LIBRARY)


@query(f"WITH v AS (SELECT {duck_sql(h.prefix('name', 1), P)} AS v FROM ({w.PART_FEEDS_SQL})) SELECT v AS value, count(*) AS n FROM v GROUP BY 1 HAVING count(*) > 250")
def heavy_values(spark, sf_dir):
    """Two-pass search of the values over the cap."""
    return sizes.heavy_values(sizes.project(w.part_feeds(spark, sf_dir), P, [h.prefix("name", 1)]), 1, 250).select("value", "n")


@query(
    f"WITH v AS (SELECT {duck_sql(h.identity('name'), P)} AS v FROM ({w.PART_FEEDS_SQL})), s AS (SELECT v AS block_key, count(*) AS n FROM v GROUP BY 1) "
    "SELECT block_key, n, round(cume_dist() OVER (ORDER BY n), 6) AS cume, round(percent_rank() OVER (ORDER BY n), 6) AS pct, CAST(first_value(n) OVER (ORDER BY n DESC, block_key) AS BIGINT) AS largest FROM s"
)
def size_profile(spark, sf_dir):
    """Where each block stands among the sizes; the windows run over the distinct sizes, of which there are few, and not over blocks."""
    s = cut(w.part_feeds(spark, sf_dir).select(h.column(h.identity("name"), P).alias("block_key")).groupBy("block_key").agg(F.count("*").alias("n")), "sizes")
    every, up = Window.orderBy(F.lit(1)).rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing), Window.orderBy("n").rowsBetween(Window.unboundedPreceding, 0)
    d = s.groupBy("n").agg(F.count("*").alias("k")).select("n", "k", F.sum("k").over(up).alias("upto"), F.sum("k").over(every).alias("total"), F.max("n").over(every).alias("largest"))
    rank = F.when(F.col("total") > 1, (F.col("upto") - F.col("k")) / (F.col("total") - 1)).otherwise(0.0)
    d = d.select("n", F.round(F.col("upto") / F.col("total"), 6).alias("cume"), F.round(rank, 6).alias("pct"), "largest")
    return s.join(d, "n").select("block_key", "n", "cume", "pct", "largest")


_PART_SCORES = score.score_root_sql(P, P_LIBRARY, PARTS, PART_PAIRS, 60)


def _scores(scorer):
    def run(spark, sf_dir):
        p = w.part_feeds(spark, sf_dir)
        return score.score_root(p, P, w.ent_pairs(p), P_LIBRARY, 60).select("hash", "broken", "n_heavy", "max_child", F.col(scorer).alias("score"))

    return run, f"{_PART_SCORES} SELECT hash, broken, n_heavy, max_child, {scorer} AS score FROM scores"


for _s in learn.SCORERS:
    QUERIES[f"score_root_{_s}"], ORACLES[f"score_root_{_s}"] = _scores(_s)


@query(f"{_PART_SCORES}, n AS (SELECT count(*) AS n FROM src) SELECT hash, pessimistic AS score, n_heavy, max_child FROM scores, n WHERE max_child < n QUALIFY row_number() OVER (ORDER BY pessimistic, n_heavy, max_child, hash) = 1")
def tree_learned_first_split(spark, sf_dir):
    """The root function of the learnt tree, by the learner itself."""
    p = w.part_feeds(spark, sf_dir)
    f = sizes.features(p, P, w.ent_pairs(p), P_LIBRARY, cap=60).by_kind()
    import numpy as np

    s = learn.best_split(f, np.arange(len(f.count)), np.arange(len(f.same)), 60, BlockingConfig(60, scorer="pessimistic"))
    top = score.long_sizes(p, P, [f.library[s.h]]).agg(F.max("n").alias("max_child"))
    return top.select(F.lit(f.library[s.h].name).alias("hash"), F.lit(float(s.score)).alias("score"), F.lit(len(s.codes)).cast("bigint").alias("n_heavy"), "max_child")


# labelled pairs ---------------------------------------------------------------------


@query(w.DOC_PAIRS_SQL)
def labelled_pairs_documents(spark, sf_dir):
    return w.doc_pairs(docs_of(spark, sf_dir))


@query(PART_PAIRS)
def labelled_pairs_parts(spark, sf_dir):
    return w.ent_pairs(w.part_feeds(spark, sf_dir))


@query(f"SELECT a.rec_id AS l_id, b.rec_id AS r_id FROM ({w.CUSTOMER_FEEDS_SQL}) a JOIN ({w.CUSTOMER_FEEDS_SQL}) b ON a.ent = b.ent AND a.rec_id < b.rec_id")
def labelled_pairs_customers(spark, sf_dir):
    return w.ent_pairs(w.customer_feeds(spark, sf_dir))


@query(w.ORDER_PAIRS_SQL)
def labelled_pairs_orders(spark, sf_dir):
    return w.order_pairs(w.table(spark, sf_dir, "orders"))


@query(w.PAGE_RECORDS_SQL)
def page_records(spark, sf_dir):
    return w.page_records(w.table(spark, sf_dir, "pages"))


_PAGE_PAIRS_SQL = w.DOC_PAIRS_SQL.replace("FROM documents", f"FROM (SELECT page_id AS doc_id, body_text AS text FROM ({w.PAGE_RECORDS_SQL}))")


@query(_PAGE_PAIRS_SQL)
def labelled_pairs_pages(spark, sf_dir):
    return w.doc_pairs(w.page_records(w.table(spark, sf_dir, "pages")).select(F.col("page_id").alias("doc_id"), F.col("body_text").alias("text")))


# trees -------------------------------------------------------------------------------

#: The worked example: names first; the null name goes on to the size, the frequent one to the brand.
EXAMPLE = BlockTree("block_tree", Node(0, 3000, 1000, h.identity("name"), {"n": Node(1, 200, 0, h.identity("size")), "vred plate": Node(2, 64, 0, h.identity("brand"))}))


@query(assign_sql(EXAMPLE, P, f"({w.PART_FEEDS_SQL})"))
def tree_assign_parts(spark, sf_dir):
    return assign.assign_blocks(w.part_feeds(spark, sf_dir), EXAMPLE, P)


@query(f"SELECT block_key, count(*) AS n FROM ({assign_sql(EXAMPLE, P, f'({w.PART_FEEDS_SQL})')}) GROUP BY 1")
def tree_leaf_sizes_parts(spark, sf_dir):
    return sizes.block_sizes(tree_assign_parts(spark, sf_dir))


def _cap(name: str) -> int:
    return SMALL_CAP if name.endswith("_small") else CAP


def assigned(spark, sf_dir, name: str) -> DataFrame:
    """Documents by a frozen tree, with the blocks that are over its cap on this table split at random."""
    d = docs_of(spark, sf_dir)
    return assign.split_oversize(assign.assign_blocks(d, assign.without_parts(frozen(name)), D), _cap(name))


def assigned_sql(name: str) -> str:
    return split_sql(assign_sql(assign.without_parts(frozen(name)), D, "documents"), _cap(name))


def _assigned(name):
    return (lambda spark, sf_dir: assigned(spark, sf_dir, name)), assigned_sql(name)


for _k in ("single", "chain", "level_tree", "block_tree"):
    QUERIES[f"{_k}_assign"], ORACLES[f"{_k}_assign"] = _assigned(_k)
    QUERIES[f"{_k}_assign_small_cap"], ORACLES[f"{_k}_assign_small_cap"] = _assigned(f"{_k}_small")


@query(f"WITH a AS ({split_sql(assign_sql(BlockTree('single', Node(0, 0, 0, h.identity('lang'))), D, 'documents'), CAP)}) SELECT block_key, count(*) AS n FROM a GROUP BY 1")
def oversize_split(spark, sf_dir):
    """Languages are far over the cap; sizes of the random parts they are split into."""
    a = assign.assign_blocks(docs_of(spark, sf_dir), BlockTree("single", Node(0, 0, 0, h.identity("lang"))), D)
    return sizes.block_sizes(assign.split_oversize(a, CAP))


def _random_sql(cap: int) -> str:
    return f"SELECT doc_id AS id, CAST({sizes.mixer_sql('doc_id', 42)} % greatest(1, CAST(ceil((SELECT count(*) FROM documents) / {cap}.0) AS BIGINT)) AS VARCHAR) AS block_key FROM documents"


@query(_random_sql(50))
def random_assign(spark, sf_dir):
    d = docs_of(spark, sf_dir)
    return assign.random_blocks(d, "doc_id", d.count(), 50)


@query(f"SELECT id, block_key || '+' || CAST((row_number() OVER (PARTITION BY block_key ORDER BY {sizes.mixer_sql('id', 42)}, id) - 1) // 50 AS VARCHAR) AS block_key FROM ({_random_sql(50)})")
def random_assign_strict(spark, sf_dir):
    d = docs_of(spark, sf_dir)
    return assign.random_blocks(d, "doc_id", d.count(), 50, strict=True)


_ALGORITHMS = {k: assigned_sql(k) for k in ("single", "chain", "level_tree", "block_tree")} | {"random": _random_sql(CAP)}
_RECALL = " UNION ALL ".join(
    f"SELECT '{k}' AS algorithm, count(*) AS n_pairs, CAST(count(*) FILTER (WHERE l.block_key = r.block_key) AS BIGINT) AS kept FROM pr JOIN a_{k} l ON l.id = l_id JOIN a_{k} r ON r.id = r_id" for k in _ALGORITHMS
)


@query(f"WITH pr AS ({DOC_PAIRS}), " + ", ".join(f"a_{k} AS ({s})" for k, s in _ALGORITHMS.items()) + f" SELECT *, n_pairs - kept AS split, round(kept / n_pairs, 6) AS recall FROM ({_RECALL})")
def recall_by_algorithm(spark, sf_dir):
    """Pairs kept and split by each algorithm's blocks, all within the same cap."""
    d = docs_of(spark, sf_dir)
    pairs = cut(sizes.canonical_pairs(w.doc_pairs(d)), "pairs")
    every = None
    for k in _ALGORITHMS:
        a = assign.random_blocks(d, "doc_id", d.count(), CAP) if k == "random" else assigned(spark, sf_dir, k)
        a = a.select(F.lit(k).alias("algorithm"), "id", "block_key")
        every = a if every is None else every.unionByName(a)
    every = cut(every, "assigned")
    l, r = (every.select("algorithm", F.col("id").alias(f"{p}_id"), F.col("block_key").alias(f"{p}k")) for p in "lr")
    t = pairs.join(l, "l_id").join(r, ["r_id", "algorithm"]).groupBy("algorithm").agg(F.count("*").alias("n_pairs"), F.sum((F.col("lk") == F.col("rk")).cast("bigint")).alias("kept"))
    return t.select("algorithm", "n_pairs", "kept", (F.col("n_pairs") - F.col("kept")).alias("split"), F.round(F.col("kept") / F.col("n_pairs"), 6).alias("recall"))


def _frontier_sql(name: str, cap: int) -> str:
    """DuckDB text of a tree cut at its shallowest nodes of at most `cap` records by real sizes: the number of records under each node decides, branch by branch."""
    tree = assign.without_parts(frozen(name))
    path = {tree.root.id: [tree.root.id]}
    for n in tree.root.walk():
        for c in n.heavy.values():
            path[c.id] = [*path[n.id], c.id]
    deepest = "CAST(regexp_extract(block_key, '^([0-9]+)', 1) AS INTEGER)"
    above = ", ".join(f"({i}, {j}, {k})" for i, p in path.items() for k, j in enumerate(p))
    return f"""WITH a AS (SELECT id, block_key, {deepest} AS node FROM ({assign_sql(tree, D, "documents")})),
p AS (SELECT * FROM (VALUES {above}) t(node, above, depth)),
s AS (SELECT above, count(*) AS n FROM a JOIN p USING (node) GROUP BY above),
f AS (SELECT node, min(depth) FILTER (WHERE n <= {cap}) AS depth FROM p JOIN s USING (above) GROUP BY node),
c AS (SELECT f.node, p.above AS stop FROM f JOIN p ON p.node = f.node AND p.depth = f.depth)
SELECT id, CASE WHEN stop IS NOT NULL THEN stop || '#0' WHEN regexp_matches(block_key, '^[0-9]+#0$') AND n > {cap} THEN node || '#' || CAST({sizes.mixer_sql("id", 42)} % CAST(ceil(n / {cap}.0) AS BIGINT) AS VARCHAR) ELSE block_key END AS block_key
FROM a LEFT JOIN c USING (node) LEFT JOIN s ON s.above = a.node"""


@query(_frontier_sql("fine", 60))
def adaptive_cut(spark, sf_dir):
    """A tree learnt for blocks of 10, cut at run time for blocks of 60 by real sizes."""
    d = docs_of(spark, sf_dir)
    return assign.assign_blocks(d, assign.refine_to(d, assign.without_parts(frozen("fine")), D, 60), D)


@query()
def tree_learned_summary(spark, sf_dir):
    """Learnt trees of all languages: height, nodes, largest block, recall by a full assignment."""
    d = docs_of(spark, sf_dir)
    pairs = w.doc_pairs(d)
    n = d.count()
    cap = max(5, n // 50)
    f = sizes.features(d, D, pairs, D_LIBRARY, cap=cap)
    out = None
    for name, learner in learn.LEARNERS.items():
        t = learner(f, BlockingConfig(cap, scorer="best"))
        a = assign.assign_blocks(d, t, D)
        one = cost.cost_summary(sizes.block_sizes(a)).select("n_blocks", "max_block").crossJoin(cost.recall(a, pairs).select("n_pairs", "recall"))
        one = one.select(F.lit(name).alias("algorithm"), F.lit(t.height).alias("height"), F.lit(t.n_nodes).alias("nodes"), "*")
        out = one if out is None else out.unionByName(one)
    return out


# experiments ---------------------------------------------------------------------------

#: Caps as shares of the records: those of the second data set, and a tenth.
_SHARES = (0.0025, 0.005, 0.0125, 0.025, 0.1)


def even(df: DataFrame) -> DataFrame:
    """`df` written in as many files as there are cores, where it comes in fewer: a small table in one file would be scanned by one of them, several times."""
    cores = df.sparkSession.sparkContext.defaultParallelism
    return df if len(df.inputFiles()) >= cores else cut(df.repartition(cores), "even")


def doc_features(spark, sf_dir, shares=_SHARES, library=None):
    """Features of the documents for the smallest of the caps, and the caps."""
    d = even(docs_of(spark, sf_dir))
    n = d.count()
    caps = sorted({max(10, int(n * s)) for s in shares})
    return sizes.features(d, D, cut(w.doc_pairs(d), "labels"), library or D_CUT, cap=caps[0]), caps


@query()
def recall_by_size_grid(spark, sf_dir):
    """Disjoint recall by cap, five algorithms, five folds; with the full library and without the longest token."""
    f, caps = doc_features(spark, sf_dir, library=D_LIBRARY)
    names = [x.name for x in D_CUT]
    rest = f.restrict([i for i, x in enumerate(f.library) if x.name in names])
    rows = [r for x, label in ((f, "documents"), (rest, "documents without longest token")) for r in evaluate.cross_validate(x, label, caps, scorers=("best",))]
    return evaluate.means(evaluate.result_table(spark, rows))


def part_features(spark, sf_dir):
    p = w.part_feeds(spark, sf_dir)
    n = p.count()
    caps = sorted({max(5, int(n * s)) for s in _SHARES})
    return sizes.features(p, P, w.ent_pairs(p), P_LIBRARY, cap=caps[0]), caps


@query()
def recall_by_size_grid_parts(spark, sf_dir):
    f, caps = part_features(spark, sf_dir)
    return evaluate.means(evaluate.result_table(spark, evaluate.cross_validate(f, "parts", caps, scorers=("best",))))


@query()
def scorer_ablation(spark, sf_dir):
    """Three ways to score a function, at one cap."""
    f, caps = doc_features(spark, sf_dir, (0.01,))
    return evaluate.means(evaluate.result_table(spark, evaluate.cross_validate(f, "documents", caps, algorithms=tuple(learn.LEARNERS), scorers=learn.SCORERS)))


@query()
def nondisjoint_recall(spark, sf_dir):
    """Recall of overlapping blocking by cap, on documents and on part feeds."""
    rows = []
    for label, (f, caps) in (("documents", doc_features(spark, sf_dir)), ("parts", part_features(spark, sf_dir))):
        rows += evaluate.cross_validate(f, label, caps, algorithms=(*learn.LEARNERS, "best_per_round"), scorers=("best",), rounds=True)
    return evaluate.means(evaluate.result_table(spark, rows))


@query()
def rounds_gain(spark, sf_dir):
    """What rounds add to the disjoint tree, by cap, and the change from one cap to the next."""
    f, caps = doc_features(spark, sf_dir)
    rows = [r for rounds in (False, True) for r in evaluate.cross_validate(f, "documents", caps, algorithms=("block_tree",), scorers=("best",), rounds=rounds)]
    m = evaluate.means(evaluate.result_table(spark, rows)).groupBy("cap").pivot("algorithm", ["block_tree", "block_tree_rounds"]).agg(F.first("recall"))
    g = m.withColumn("gain", F.round(F.col("block_tree_rounds") - F.col("block_tree"), 6))
    return g.withColumn("change", F.round(F.col("gain") - F.lag("gain").over(Window.orderBy("cap")), 6))


@query()
def recall_by_round(spark, sf_dir):
    f, caps = doc_features(spark, sf_dir, (0.005,))
    rows = [x for a in learn.LEARNERS for x in evaluate.per_round(f, caps[0], a, config=BlockingConfig(caps[0], scorer="best"))]
    t = spark.createDataFrame(rows, "algorithm string, round int, recall double")
    return t.withColumn("gain", F.round(F.col("recall") - F.coalesce(F.lag("recall").over(Window.partitionBy("algorithm").orderBy("round")), F.lit(0.0)), 6))


def customer_features(spark, sf_dir, caps):
    c = even(w.customer_feeds(spark, sf_dir))
    return sizes.features(c, C, w.ent_pairs(c), C_LIBRARY, cap=min(caps))


def customer_caps(n: int) -> list[int]:
    """The caps of the second data set: 0.22, 0.44, 1.1 and 2.2 percent of the records (100 to 1000 of 45,000)."""
    return [max(4, n * c // 45_000) for c in (100, 200, 500, 1000)]


@query()
def customer_summary(spark, sf_dir):
    """Chain against tree, disjoint and in rounds, four caps: algorithms by caps."""
    caps = customer_caps(w.customer_feeds(spark, sf_dir).count())
    f = customer_features(spark, sf_dir, caps)
    rows = [r for rounds in (False, True) for r in evaluate.cross_validate(f, "customers", caps, algorithms=("chain", "block_tree"), scorers=("best",), rounds=rounds)]
    t = evaluate.means(evaluate.result_table(spark, rows)).groupBy("algorithm").pivot("cap", caps).agg(F.first("recall"))
    return t.select("algorithm", *[F.col(f"`{c}`").alias(f"s{i + 1}") for i, c in enumerate(caps)])


@query()
def tree_heights(spark, sf_dir):
    """Height of each kind of tree over folds, as learnt and where a function has to halve its node."""
    f, caps = doc_features(spark, sf_dir, (0.0125, 0.1))
    out = None
    for shrink in (1.0, 0.5):
        m = evaluate.means(evaluate.result_table(spark, evaluate.cross_validate(f, "documents", caps, algorithms=tuple(learn.LEARNERS), config=BlockingConfig(1, min_shrink=shrink))))
        m = m.select("algorithm", "cap", F.lit(shrink).alias("min_shrink"), "height", "recall")
        out = m if out is None else out.unionByName(m)
    return out


@query()
def library_ablation(spark, sf_dir):
    """Hand-made functions, learnt intervals, and both."""
    p = w.part_feeds(spark, sf_dir)
    pairs = w.ent_pairs(p)
    cap = max(5, p.count() // 50)
    auto = drilldown.auto_library(p, P, pairs, cap)
    manual = [x for x in P_LIBRARY if x.attribute in ("size", "price")]
    f = sizes.features(p, P, pairs, manual + auto, cap=cap)
    names = [x.name for x in f.library]
    rows = []
    for kind, keep in (("manual", [i for i, x in enumerate(f.library) if x.family != "interval"]), ("auto", [i for i, x in enumerate(f.library) if x.family == "interval"]), ("both", list(range(len(names))))):
        rows += [(kind, *r[1:]) for r in evaluate.cross_validate(f.restrict(keep), kind, [cap], algorithms=("single", "block_tree"), scorers=("expected",))]
    return evaluate.means(evaluate.result_table(spark, rows))


@query()
def sampled_sizes(spark, sf_dir):
    """A tree learnt with sizes from a sample, and the same cut by real sizes: largest block and recall of both."""
    d = docs_of(spark, sf_dir)
    pairs = w.doc_pairs(d)
    cap = max(10, d.count() // 20)
    f = sizes.features(d, D, pairs, D_LIBRARY, cap=cap, sample=0.3)
    t = learn.learn_block_tree(f, BlockingConfig(cap, scorer="best", slack=0.5))
    out = None
    for name, tree in (("estimated", t), ("adapted", assign.refine_to(d, t, D, cap))):
        a = assign.assign_blocks(d, tree, D)
        one = cost.cost_summary(sizes.block_sizes(a)).select("max_block").crossJoin(cost.recall(a, pairs).select("recall")).select(F.lit(name).alias("tree"), F.lit(cap).alias("cap"), "*")
        out = one if out is None else out.unionByName(one)
    return out


@query()
def cluster_folds(spark, sf_dir):
    """Recall when copies of one record stay in one fold."""
    f, caps = doc_features(spark, sf_dir, (0.02,))
    rows = [("pair" if by == "pair" else "cluster", *r[1:]) for by in ("pair", "cluster") for r in evaluate.cross_validate(f, by, caps, algorithms=("chain", "block_tree"), by=by)]
    return evaluate.means(evaluate.result_table(spark, rows))


@query()
def classifier_features(spark, sf_dir):
    """Few functions for a classifier: a tree learnt on pairs of documents of one quality class, and the functions it uses."""
    lab = w.table(spark, sf_dir, "labels").where("quality is not null").select("doc_id", "quality")
    d = docs_of(spark, sf_dir)
    # each document with the next of its class in order of md5: as many pairs as documents
    nxt = lab.withColumn("r_id", F.lead("doc_id").over(Window.partitionBy("quality").orderBy(F.md5(F.col("doc_id").cast("string")), "doc_id")))
    pairs = nxt.where("r_id is not null").select(F.col("doc_id").alias("l_id"), "r_id")
    part = d.join(lab.select("doc_id"), "doc_id", "left_semi")
    f = sizes.features(part, D, pairs, D_LIBRARY, cap=max(5, part.count() // 4))
    t = learn.learn_block_tree(f, BlockingConfig(f.cap, scorer="pessimistic"))
    return spark.createDataFrame([(n.id, n.hash.name if n.hash else "", n.size, n.pairs) for n in t.root.walk()], "node int, function string, records bigint, pairs bigint")


@query()
def disjunction_baseline(spark, sf_dir):
    """The learner with negatives: conjunctions chosen, with the positives and negatives each keeps."""
    d = docs_of(spark, sf_dir)
    near = w.doc_pairs(d, threshold=0.05)
    pos, neg = near.where("jaccard >= 0.5"), near.where("jaccard < 0.4")
    f = sizes.features(d, D, pos, D_LIBRARY, cap=max(10, d.count() // 10))
    g = sizes.features(d, D, neg, D_LIBRARY, cap=max(10, d.count() // 10))
    common = [i for i, x in enumerate(f.library) if x.name in {y.name for y in g.library}]
    f = f.restrict(common)
    g = g.restrict([next(j for j, y in enumerate(g.library) if y.name == x.name) for x in f.library])
    terms = dedup.learn_disjunction(f, g.same, max_terms=2)
    rows = [(i, "&".join(f.library[x].name for x in c), int(f.same[:, list(c)].all(1).sum()), int(g.same[:, list(c)].all(1).sum())) for i, c in enumerate(terms)]
    return spark.createDataFrame(rows, "disjunct int, conjunction string, positives bigint, negatives bigint")


@query(
    "WITH r AS (SELECT algorithm, cap, kept FROM (VALUES ('chain', 10, 0.5), ('chain', 20, 0.75), ('tree', 10, 0.875), ('tree', 20, 1.0)) t(algorithm, cap, kept)) "
    "SELECT coalesce(algorithm, '(all)') AS algorithm, CAST(coalesce(cap, -1) AS BIGINT) AS cap, round(avg(kept), 6) AS recall, count(*) AS n, CAST(grouping(algorithm, cap) AS BIGINT) AS level FROM r GROUP BY CUBE (algorithm, cap)"
)
def grouping_sets_report(spark, sf_dir):
    rows = [("x", a, "", c, 0, float(k), 1.0, 1) for a, c, k in (("chain", 10, 0.5), ("chain", 20, 0.75), ("tree", 10, 0.875), ("tree", 20, 1.0))]
    return evaluate.grouping_report(evaluate.result_table(spark, rows))


# costs ----------------------------------------------------------------------------------

_SIZES = f"SELECT block_key, count(*) AS n FROM ({assigned_sql('block_tree')}) GROUP BY 1"


def _sizes(spark, sf_dir):
    return sizes.block_sizes(assigned(spark, sf_dir, "block_tree"))


@query(f"SELECT count(*) AS n_blocks, CAST(sum(n) AS BIGINT) AS n_records, max(n) AS max_block, CAST(sum(n * n) AS BIGINT) AS sum_sq, CAST(sum(n * (n - 1)) AS BIGINT) AS twice_pairs, max(n) * max(n) AS max_sq FROM ({_SIZES})")
def cost_summary(spark, sf_dir):
    x = cost.cost_summary(_sizes(spark, sf_dir))
    return x.select("n_blocks", "n_records", "max_block", *[F.col(c).cast("bigint").alias(c) for c in ("sum_sq", "twice_pairs", "max_sq")])


@query(
    " UNION ALL ".join(
        f"SELECT {m} AS machines, round(greatest(max(n * n), sum(n * n) / {m}.0)::DOUBLE, 6) AS lower, round(2 * greatest(max(n * n), sum(n * n) / {m}.0)::DOUBLE, 6) AS upper, round(((1 + count(*) / {m}.0) * max(n * n))::DOUBLE, 6) AS upper_by_count FROM ({_SIZES})"
        for m in (2, 4, 8, 16)
    )
)
def makespan_bounds(spark, sf_dir):
    s = _sizes(spark, sf_dir)
    out = None
    for m in (2, 4, 8, 16):
        one = cost.makespan_bounds(s, m)
        out = one if out is None else out.unionByName(one)
    return out


@query()
def lpt_makespan(spark, sf_dir):
    """Largest-first makespan beside its bounds."""
    s = _sizes(spark, sf_dir)
    out = None
    for m in (2, 4, 8, 16):
        one = cost.makespan_bounds(s, m).withColumn("lpt", F.lit(cost.lpt_makespan(s, m)))
        out = one if out is None else out.unionByName(one)
    return out.withColumn("within", (F.col("lower") <= F.col("lpt")) & (F.col("lpt") <= F.col("upper")))


def _rounds_sql() -> str:
    """(id, round, block_key) of the frozen rounds, each with the cap of its trees by real sizes."""
    every = " UNION ALL ".join(f"SELECT id, {i} AS round, block_key FROM ({assign_sql(t, D, 'documents')})" for i, t in enumerate(frozen_rounds().rounds))
    return split_sql(every, SMALL_CAP)


def rounds(spark, sf_dir, mode: str = "union") -> DataFrame:
    return assign.split_oversize(assign.assign_rounds(docs_of(spark, sf_dir), frozen_rounds(), D, mode), SMALL_CAP)


@query(f"WITH s AS (SELECT round, block_key, count(*) AS n FROM ({_rounds_sql()}) GROUP BY ALL) SELECT max(n) AS max_block, CAST(sum(n) AS BIGINT) AS memberships, CAST(max(n) * max(n) + sum(n) AS BIGINT) AS overlap_cost FROM s")
def overlap_cost(spark, sf_dir):
    return cost.overlap_cost(rounds(spark, sf_dir))


@query(f"SELECT id, CAST(round AS INTEGER) AS round, block_key FROM ({_rounds_sql()})")
def rounds_assign_union(spark, sf_dir):
    return rounds(spark, sf_dir)


@query(f"SELECT id, CAST(round AS INTEGER) AS round, block_key FROM ({_rounds_sql()})")
def rounds_assign_rounds(spark, sf_dir):
    return rounds(spark, sf_dir, "rounds")


@query(f"WITH s AS ({_SIZES}) SELECT round(1 - sum(n * (n - 1)) / (sum(n) * (sum(n) - 1)), 6) AS reduction_ratio FROM s")
def reduction_ratio(spark, sf_dir):
    return cost.reduction_ratio(_sizes(spark, sf_dir))


@query(f"WITH p AS ({DOC_PAIRS}), o AS (SELECT *, md5('42|' || l_id || '|' || r_id) AS m FROM p) SELECT l_id, r_id, CAST(ntile(5) OVER (ORDER BY m, l_id, r_id) - 1 AS INTEGER) AS fold FROM o")
def cross_validation_folds(spark, sf_dir):
    return evaluate.cross_validation_folds(w.doc_pairs(docs_of(spark, sf_dir)))


def _spread(spark, df: DataFrame, copies: int) -> DataFrame:
    """`copies` times the records in as many files as there are cores, so that a run is long enough to time."""
    n = spark.sparkContext.defaultParallelism
    return cut(df.crossJoin(F.broadcast(spark.range(copies).select(F.lit(None).cast("void").alias("__copy")))).drop("__copy").repartition(2 * n), "spread")


@query()
def apply_time(spark, sf_dir):
    """Microseconds a record to block documents, customer feeds and lineitem, by trees learnt on the table itself (lineitem: given ones), for a cap of a tenth of the records."""
    rows = []
    for label, df, spec, library, pairs, copies in (
        # the attributes timed elsewhere are short; counting the characters of whole texts takes half a millisecond by itself
        ("documents", docs_of(spark, sf_dir), D, [x for x in D_CUT if (x.attribute, x.family) != ("text", "top_chars")], w.doc_pairs(docs_of(spark, sf_dir)), 4),
        ("customers", w.customer_feeds(spark, sf_dir), C, C_LIBRARY, w.ent_pairs(w.customer_feeds(spark, sf_dir)), 8),
    ):
        df = even(df)
        cap = max(10, df.count() // 10)
        f = sizes.features(df, spec, cut(pairs, "labels"), library, cap=cap)
        many = _spread(spark, df, copies)
        for name in ("single", "level_tree", "block_tree"):
            t = learn.LEARNERS[name](f, BlockingConfig(cap, scorer="expected" if name == "single" else "optimistic", min_shrink=0.5))
            r = cost.time_per_record(many, assign.assign_blocks(many, t, spec), reps=5)
            rows.append((label, name, r["records"], t.height, r["scan_us"], r["block_us"], learn.recall(f, t)))
    li = w.table(spark, sf_dir, "lineitem")
    spec = w.BlockingSpec("l_orderkey", (w.Attribute("flag", "code", "l_returnflag"), w.Attribute("mode", "code", "l_linestatus"), w.Attribute("part", "int", "l_partkey"), w.Attribute("qty", "float", "l_quantity")))
    a, b, c = h.identity("flag"), h.bucket_int("qty", 10), h.bucket_int("part", 100)
    trees = {
        "single": BlockTree("single", Node(0, 0, 0, c)),
        "level_tree": BlockTree("level_tree", Node(0, 0, 0, a, {f"v{x}": Node(1 + i, 0, 0, b, {f"v{q}": Node(10 + 10 * i + j, 0, 0, c) for j, q in enumerate((0, 10, 20, 30, 40))}) for i, x in enumerate("ANR")})),
        "block_tree": BlockTree("block_tree", Node(0, 0, 0, c, {"v0": Node(1, 0, 0, b), "v100": Node(2, 0, 0, a)})),
    }
    many = _spread(spark, li.select("l_orderkey", "l_returnflag", "l_linestatus", "l_partkey", "l_quantity"), 5)
    for name, t in trees.items():
        r = cost.time_per_record(many, assign.assign_blocks(many, t, spec), reps=5)
        rows.append(("lineitem, given trees", name, r["records"], t.height, r["scan_us"], r["block_us"], None))
    return spark.createDataFrame(rows, "workload string, tree string, records bigint, height int, scan_us double, block_us double, training_recall double")


# roll-up ----------------------------------------------------------------------------------

_PART_BLOCKS = assign_sql(EXAMPLE, P, f"({w.PART_FEEDS_SQL})")
_CROSS = f"""WITH a AS ({_PART_BLOCKS}), pr AS ({PART_PAIRS}),
e AS (SELECT least(l.block_key, r.block_key) AS a, greatest(l.block_key, r.block_key) AS b, count(*) AS benefit FROM pr JOIN a l ON l.id = l_id JOIN a r ON r.id = r_id WHERE l.block_key <> r.block_key GROUP BY 1, 2)"""


def _part_blocks(spark, sf_dir):
    p = w.part_feeds(spark, sf_dir)
    return assign.assign_blocks(p, EXAMPLE, P), w.ent_pairs(p)


@query(f"{_CROSS} SELECT * FROM e")
def rollup_edges(spark, sf_dir):
    return rollup.edges(*_part_blocks(spark, sf_dir))


@query(
    f"""{_CROSS}, s AS (SELECT block_key, count(*) AS n FROM a GROUP BY 1), f AS (SELECT e.*, x.n AS na, y.n AS nb FROM e JOIN s x ON x.block_key = a JOIN s y ON y.block_key = b WHERE x.n + y.n <= 60)
SELECT a, b, benefit FROM f ORDER BY benefit / least(na, nb) DESC, a, b LIMIT 1"""
)
def rollup_first_merge(spark, sf_dir):
    """The merge that the greedy roll-up makes first."""
    a, pairs = _part_blocks(spark, sf_dir)
    e = rollup.edges(a, pairs)
    s = sizes.block_sizes(a)
    x, y = (s.select(F.col("block_key").alias(k), F.col("n").alias(f"n{k}")) for k in "ab")
    fit = e.join(x, "a").join(y, "b").where(F.col("na") + F.col("nb") <= 60)
    return fit.orderBy(F.desc(F.col("benefit") / F.least("na", "nb")), "a", "b").limit(1).select("a", "b", "benefit")


#: Every merge of the greedy roll-up, in turn: the state is one row that holds each touched block with its group and size.
_GREEDY = f"""WITH RECURSIVE {_CROSS[5:]}, s AS (SELECT block_key, count(*) AS n FROM a GROUP BY 1),
t AS (SELECT block_key, n FROM s WHERE block_key IN (SELECT a FROM e UNION SELECT b FROM e)),
state AS (SELECT 0 AS step, (SELECT list({{'b': block_key, 'g': block_key, 'n': n}}) FROM t) AS m
  UNION ALL
  SELECT step + 1, list_transform(m, lambda x: {{'b': x.b, 'g': CASE WHEN x.g = best.hi THEN best.lo ELSE x.g END, 'n': x.n}})
  FROM state, LATERAL (
    WITH u AS (SELECT unnest(m) AS x), z AS (SELECT x.g AS g, sum(x.n) AS n FROM u GROUP BY 1),
    p AS (SELECT least(y.x.g, w.x.g) AS lo, greatest(y.x.g, w.x.g) AS hi, sum(benefit) AS gain FROM e JOIN u y ON y.x.b = e.a JOIN u w ON w.x.b = e.b WHERE y.x.g <> w.x.g GROUP BY 1, 2)
    SELECT lo, hi FROM p JOIN z zl ON zl.g = lo JOIN z zh ON zh.g = hi WHERE zl.n + zh.n <= 60 ORDER BY gain / least(zl.n, zh.n) DESC, lo, hi LIMIT 1) best),
last AS (SELECT unnest(m) AS x FROM state ORDER BY step DESC LIMIT (SELECT count(*) FROM t)),
o AS (SELECT x.b AS block_key, x.g AS merged_key, count(*) OVER (PARTITION BY x.g) AS k FROM last),
plan AS (SELECT block_key, merged_key FROM o WHERE k > 1)"""


@query(f"{_GREEDY} SELECT * FROM plan")
def rollup_plan_parts(spark, sf_dir):
    """The whole greedy roll-up: which block goes where."""
    return rollup.rollup(*_part_blocks(spark, sf_dir), 60, safeguard=False)


@query(f"{_GREEDY} SELECT id, coalesce(merged_key, block_key) AS block_key FROM a LEFT JOIN plan USING (block_key)")
def rollup_assign_parts(spark, sf_dir):
    """Part feeds by the example tree with the roll-up on top of it."""
    p = w.part_feeds(spark, sf_dir)
    plan = rollup.rollup(*_part_blocks(spark, sf_dir), 60, safeguard=False)
    return assign.assign_blocks(p, EXAMPLE, P, rollup=plan)


@query(
    f"""{_GREEDY}, r AS (SELECT id, coalesce(merged_key, block_key) AS block_key FROM a LEFT JOIN plan USING (block_key)),
x AS (SELECT count(*) FILTER (WHERE l.block_key <> r.block_key) AS before FROM pr JOIN a l ON l.id = l_id JOIN a r ON r.id = r_id),
y AS (SELECT count(*) FILTER (WHERE l.block_key <> q.block_key) AS after FROM pr JOIN r l ON l.id = l_id JOIN r q ON q.id = r_id)
SELECT CAST(before AS BIGINT) AS split_before, CAST(after AS BIGINT) AS split_after, (SELECT count(DISTINCT block_key) FROM a) AS blocks_before, (SELECT count(DISTINCT block_key) FROM r) AS blocks_after FROM x, y"""
)
def rollup_result_parts(spark, sf_dir):
    """Split pairs and blocks before and after the roll-up."""
    a, pairs = _part_blocks(spark, sf_dir)
    a, pairs = cut(a, "assigned"), cut(pairs, "pairs")
    after = cut(rollup.merged(a, rollup.rollup(a, pairs, 60, safeguard=False)), "merged")
    one = cost.recall(a, pairs).select(F.col("split").alias("split_before")).crossJoin(cost.recall(after, pairs).select(F.col("split").alias("split_after")))
    return one.crossJoin(a.agg(F.count_distinct("block_key").alias("blocks_before"))).crossJoin(after.agg(F.count_distinct("block_key").alias("blocks_after")))


@query()
def rollup_matching_parts(spark, sf_dir):
    """The distributed roll-up: do merged blocks fit, and how many pairs it wins back."""
    a, pairs = _part_blocks(spark, sf_dir)
    a, pairs = cut(a, "assigned"), cut(pairs, "pairs")
    m = cut(rollup.rollup(a, pairs, 60, strategy="matching"), "plan")
    before = cost.recall(a, pairs).select(F.col("split").alias("split_before"))
    return evaluate.check_rollup(a, m, 60).crossJoin(before).crossJoin(cost.recall(rollup.merged(a, m), pairs).select(F.col("split").alias("split_after")))


@query(f"SELECT CAST(ceil(count(*) / 60.0) AS BIGINT) AS least_blocks, true AS all_fit, count(*) AS records, true AS enough FROM ({PARTS})")
def rollup_zero_benefit_parts(spark, sf_dir):
    """Blocks packed on without common pairs: all fit, no record is lost, and the blocks are no more than 1.7 times those that a cap needs at least, plus one.

    The example tree doesn't know the table at hand, so its blocks over the cap are numbered off first.
    """
    a, pairs = _part_blocks(spark, sf_dir)
    a = assign.sliced(a, 60)
    after = rollup.merged(a, rollup.rollup(a, pairs, 60, merge_zero_benefit=True))
    x = sizes.block_sizes(after).agg(F.count("*").alias("blocks"), F.max("n").alias("n"), F.sum("n").alias("records"))
    least = F.ceil(F.col("records") / 60).cast("bigint")
    return x.select(least.alias("least_blocks"), (F.col("n") <= 60).alias("all_fit"), "records", (F.col("blocks") <= 1.7 * least + 1).alias("enough"))


@query()
def rollup_gain(spark, sf_dir):
    """Recall of every algorithm before and after roll-up, on documents and blocks of at most `SMALL_CAP`."""
    d = docs_of(spark, sf_dir)
    pairs = cut(w.doc_pairs(d), "labels")
    out = None
    for k in ("random", "single", "chain", "level_tree", "block_tree"):
        a = assign.random_blocks(d, "doc_id", d.count(), SMALL_CAP, strict=True) if k == "random" else assigned(spark, sf_dir, f"{k}_small")
        a = cut(a, "assigned")
        m = cut(rollup.rollup(a, pairs, SMALL_CAP), "plan")
        after = rollup.merged(a, m)
        one = cost.recall(a, pairs).select(F.lit(k).alias("algorithm"), F.col("recall").alias("before")).crossJoin(cost.recall(after, pairs).select(F.col("recall").alias("after"))).crossJoin(evaluate.check_rollup(a, m, SMALL_CAP).select("fits"))
        out = one if out is None else out.unionByName(one)
    return out


@query()
def rounds_rolled_up(spark, sf_dir):
    """Rounds of block trees with a roll-up in each, beside the same rounds without: recall by round, of all labelled pairs."""
    p = w.part_feeds(spark, sf_dir)
    pairs = cut(w.ent_pairs(p), "labels")
    cap = max(5, p.count() // 50)
    f = sizes.features(p, P, pairs, P_LIBRARY, cap=cap)
    rows = []
    for rolled in (False, True):
        done, plans = rollup.rolled_rounds(p, P, f, BlockingConfig(cap, scorer="expected", max_rounds=4), pairs, rolled)
        rows += [("rolled up" if rolled else "plain", i, n, n / len(f.same)) for i, n in enumerate(done)]
    return spark.createDataFrame(rows, "kind string, round int, covered bigint, recall double")


# drill-down ----------------------------------------------------------------------------------


def _least_violations_sql(keyed: str, pairs: str, share: float | None, width: int | None = None) -> str:
    """Least violations over all partitions: recursion over the cut that ends the last interval, over every value of the domain.

    A run of values fits by its records (a share of all) or by the difference of its ends.
    """
    fits = f"z.up - x.up + x.n <= (SELECT CAST(floor((SELECT count(*) FROM k) * {share}) AS BIGINT))" if width is None else f"z.k - x.k <= {width}"
    return f"""
WITH RECURSIVE k AS ({keyed}), pr AS ({pairs}), d AS (SELECT k, count(*) AS n, row_number() OVER (ORDER BY k) AS i, sum(count(*)) OVER (ORDER BY k) AS up FROM k WHERE k IS NOT NULL GROUP BY k), m AS (SELECT max(i) AS m FROM d),
p AS (SELECT least(x.i, y.i) AS a, greatest(x.i, y.i) AS b FROM pr JOIN k l ON l.id = l_id JOIN k r ON r.id = r_id JOIN d x ON x.k = l.k JOIN d y ON y.k = r.k),
fit AS (SELECT x.i AS i, z.i AS j FROM d x JOIN d z ON z.i >= x.i WHERE x.i = z.i OR {fits}),
out_ AS (SELECT f.i, f.j, count(*) AS lost FROM fit f JOIN p ON p.a BETWEEN f.i AND f.j AND p.b > f.j GROUP BY 1, 2),
runs AS (SELECT f.i, f.j, coalesce(lost, 0) AS lost FROM fit f LEFT JOIN out_ o USING (i, j)),
walk AS (SELECT CAST(0 AS BIGINT) AS j, CAST(0 AS BIGINT) AS lost UNION SELECT r.j, w.lost + r.lost FROM walk w JOIN runs r ON r.i = w.j + 1)
SELECT min(lost) AS violations, (SELECT count(*) FROM p) AS n_pairs FROM walk WHERE j = (SELECT m FROM m)"""


def _violations(spark, df, id_col, key, pairs, share, width=None, solver="endpoints"):
    pv = drilldown.counted_values(df, id_col, key, pairs)
    if width is None:
        part = drilldown.drilldown(df, key, pv, int(df.count() * share), solver=solver)
    else:
        part = drilldown.drilldown(df, key, pv, width, cost="width")
    return spark.createDataFrame([(drilldown.broken(part, pv), sum(pv.values()))], "violations bigint, n_pairs bigint")


@query(_least_violations_sql("SELECT o_orderkey AS id, month(o_orderdate) AS k FROM orders", w.ORDER_PAIRS_SQL, 0.3))
def drilldown_month(spark, sf_dir):
    o = w.table(spark, sf_dir, "orders")
    return _violations(spark, o, "o_orderkey", F.month("o_orderdate"), w.order_pairs(o), 0.3)


_WEEKS = "SELECT o_orderkey AS id, CAST(floor(date_diff('day', DATE '1990-01-01', CAST(o_orderdate AS DATE)) / 7) AS BIGINT) AS k FROM orders"


@query(_least_violations_sql(_WEEKS, w.ORDER_PAIRS_SQL, 0.03))
def drilldown_week(spark, sf_dir):
    """Every week of the order dates."""
    o = w.table(spark, sf_dir, "orders")
    return _violations(spark, o, "o_orderkey", F.floor(F.datediff(F.to_date("o_orderdate"), F.lit("1990-01-01")) / 7), w.order_pairs(o), 0.03)


@query(_least_violations_sql(_WEEKS, w.ORDER_PAIRS_SQL, 0.03))
def drilldown_week_full(spark, sf_dir):
    """The recurrence over the whole domain, for the same weeks."""
    o = w.table(spark, sf_dir, "orders")
    return _violations(spark, o, "o_orderkey", F.floor(F.datediff(F.to_date("o_orderdate"), F.lit("1990-01-01")) / 7), w.order_pairs(o), 0.03, solver="full")


@query(_least_violations_sql(_WEEKS, w.ORDER_PAIRS_SQL, None, 8))
def drilldown_week_width(spark, sf_dir):
    """Intervals bounded by their width, nine weeks."""
    o = w.table(spark, sf_dir, "orders")
    return _violations(spark, o, "o_orderkey", F.floor(F.datediff(F.to_date("o_orderdate"), F.lit("1990-01-01")) / 7), w.order_pairs(o), None, width=8)


@query(_least_violations_sql("SELECT doc_id AS id, n_chars AS k FROM documents", DOC_PAIRS, 0.05))
def drilldown_nchars(spark, sf_dir):
    """Every length of a document."""
    d = docs_of(spark, sf_dir)
    return _violations(spark, d, "doc_id", F.col("n_chars"), w.doc_pairs(d), 0.05)


@query(_least_violations_sql(f"SELECT rec_id AS id, p_size AS k FROM ({w.PART_FEEDS_SQL})", PART_PAIRS, 0.25))
def drilldown_size(spark, sf_dir):
    p = w.part_feeds(spark, sf_dir)
    return _violations(spark, p, "rec_id", F.col("p_size"), w.ent_pairs(p), 0.25)


@query(
    f"WITH RECURSIVE k AS ({_WEEKS}), pr AS ({w.ORDER_PAIRS_SQL}), p AS (SELECT DISTINCT least(l.k, r.k) AS low, greatest(l.k, r.k) AS high FROM pr JOIN k l ON l.id = l_id JOIN k r ON r.id = r_id) "
    "SELECT low, high, count(*) AS n FROM p JOIN k ON k.k BETWEEN low AND high GROUP BY 1, 2 HAVING count(*) <= (SELECT CAST(floor(count(*) * 0.005) AS BIGINT) FROM k)"
)
def drilldown_overlapping_weeks(spark, sf_dir):
    """Without disjointness: the intervals of pairs that hold no more than a two-hundredth of the orders."""
    o = w.table(spark, sf_dir, "orders")
    key = F.floor(F.datediff(F.to_date("o_orderdate"), F.lit("1990-01-01")) / 7)
    rows = drilldown.overlapping_by_count(o, key, drilldown.pair_values(o, "o_orderkey", key, w.order_pairs(o)), int(o.count() * 0.005))
    return spark.createDataFrame(rows, "low bigint, high bigint, n bigint")


@query(
    f"WITH RECURSIVE k AS ({_WEEKS}), d AS (SELECT k, count(*) AS n, row_number() OVER (ORDER BY k) AS i FROM k GROUP BY k), c AS (SELECT CAST(floor(count(*) * 0.05) AS BIGINT) AS s FROM k), "
    "f AS (SELECT i, k AS start, CAST(n AS BIGINT) AS n FROM d WHERE i = 1 UNION ALL SELECT d.i, CASE WHEN f.n + d.n <= s THEN f.start ELSE d.k END, CAST(CASE WHEN f.n + d.n <= s THEN f.n + d.n ELSE d.n END AS BIGINT) FROM f JOIN d ON d.i = f.i + 1, c) "
    "SELECT CAST(row_number() OVER (ORDER BY start) - 1 AS INTEGER) AS slot, max(n) AS n FROM f GROUP BY start"
)
def equi_depth_weeks(spark, sf_dir):
    """Weeks filled up to a twentieth of the orders from the left."""
    o = w.table(spark, sf_dir, "orders")
    key = F.floor(F.datediff(F.to_date("o_orderdate"), F.lit("1990-01-01")) / 7)
    counts = [(r[0], r[1]) for r in o.groupBy(key.alias("k")).agg(F.count("*")).orderBy("k").collect()]
    part = drilldown.equi_depth(counts, int(sum(n for _, n in counts) * 0.05))
    return spark.createDataFrame([(i, x.n) for i, x in enumerate(part)], "slot int, n bigint")


@query()
def drilldown_vs_equiwidth(spark, sf_dir):
    """Broken pairs of learnt intervals, equal widths and equal depths of order dates, at four caps."""
    o = w.table(spark, sf_dir, "orders")
    key = F.to_date("o_orderdate")
    pv = drilldown.pair_values(o, "o_orderkey", key, w.order_pairs(o))
    counts = [(r[0], r[1]) for r in o.groupBy(key.alias("k")).agg(F.count("*")).orderBy("k").collect()]
    n = sum(c for _, c in counts)
    rows = []
    for share in (0.02, 0.05, 0.1, 0.3):
        cap = int(n * share)
        best = drilldown.drilldown(o, key, pv, cap)
        days, width = [v for v, _ in counts], 1
        # the widest equal intervals that keep the cap
        lo = days[0]

        def largest(k):
            by: dict = {}
            for v, c in counts:
                by[(v - lo).days // k] = by.get((v - lo).days // k, 0) + c
            return max(by.values())

        while width < 3000 and largest(width + 1) <= cap:
            width += 1
        equal = drilldown.equi_width(lo, days[-1], width)
        depth = drilldown.equi_depth(counts, cap)
        rows.append((cap, len(pv), *[drilldown.broken(x, pv) for x in (best, equal, depth)], len(best), drilldown.is_dcc(best), max(x.n for x in best)))
    return spark.createDataFrame(rows, "cap bigint, n_pairs bigint, learnt bigint, equal_width bigint, equal_depth bigint, intervals int, covers boolean, largest bigint")


@query()
def drilldown_text_order(spark, sf_dir):
    """Another order: documents by their last token, then their first."""
    d = docs_of(spark, sf_dir)
    key = F.concat_ws("|", h.column(h.last_token("text"), D), h.column(h.first_token("text"), D))
    pv = drilldown.counted_values(d, "doc_id", key, w.doc_pairs(d))
    cap = max(5, d.count() // 20)
    part = drilldown.drilldown(d, key, pv, cap)
    return spark.createDataFrame([(i, x.lo, x.hi, x.n, x.infeasible) for i, x in enumerate(part)], "slot int, lo string, hi string, n bigint, infeasible boolean")


# pairs, clusters, linkage ------------------------------------------------------------------------


@query(f"WITH a AS ({assigned_sql('block_tree_small')}) SELECT l.id AS l_id, r.id AS r_id FROM a l JOIN a r ON l.block_key = r.block_key AND l.id < r.id")
def candidate_pairs_disjoint(spark, sf_dir):
    return dedup.candidate_pairs(assigned(spark, sf_dir, "block_tree_small"))


@query(f"WITH a AS ({_rounds_sql()}) SELECT l.id AS l_id, r.id AS r_id, CAST(min(l.round) AS INTEGER) AS round FROM a l JOIN a r ON l.round = r.round AND l.block_key = r.block_key AND l.id < r.id GROUP BY 1, 2")
def candidate_pairs_rounds(spark, sf_dir):
    return dedup.candidate_pairs_rounds(assign.keys_by_round(rounds(spark, sf_dir)))


@query(
    f"WITH a AS ({_rounds_sql()}), pr AS ({DOC_PAIRS}), f AS (SELECT l_id, r_id, min(l.round) AS round FROM pr JOIN a l ON l.id = l_id JOIN a r ON r.id = r_id AND r.round = l.round AND r.block_key = l.block_key GROUP BY 1, 2), "
    f"g AS (SELECT unnest(range({len(frozen_rounds().rounds)})) AS round), c AS (SELECT g.round, count(f.l_id) AS covered FROM g LEFT JOIN f ON f.round = g.round GROUP BY 1) "
    "SELECT CAST(round AS INTEGER) AS round, covered, round(sum(covered) OVER (ORDER BY round) / (SELECT count(*) FROM pr), 6) AS recall FROM c"
)
def recall_of_rounds(spark, sf_dir):
    """Pairs that each round covers first, and the recall so far."""
    return cost.recall_by_round(rounds(spark, sf_dir), w.doc_pairs(docs_of(spark, sf_dir)), len(frozen_rounds().rounds))


@query(
    f"WITH c AS (SELECT l.id AS l_id, r.id AS r_id FROM ({assigned_sql('block_tree_small')}) l JOIN ({assigned_sql('block_tree_small')}) r ON l.block_key = r.block_key AND l.id < r.id), pr AS ({DOC_PAIRS}), "
    "h AS (SELECT count(*) AS hits FROM c JOIN pr USING (l_id, r_id)), x AS (SELECT (SELECT hits FROM h) AS hits, (SELECT count(*) FROM c) AS predicted, (SELECT count(*) FROM pr) AS true_pairs) "
    "SELECT *, round(hits / predicted, 6) AS precision, round(hits / true_pairs, 6) AS recall, round(2 * hits / (predicted + true_pairs), 6) AS f1 FROM x"
)
def pair_quality(spark, sf_dir):
    """Precision, recall and F1 of candidate pairs, were all of them called duplicates."""
    return cost.quality_of_pairs(candidate_pairs_disjoint(spark, sf_dir), w.doc_pairs(docs_of(spark, sf_dir)))


@query(f"WITH a AS ({assigned_sql('block_tree')}) SELECT CAST(max(c) AS BIGINT) AS cost FROM (SELECT sum(length(text)) AS c FROM a JOIN documents ON id = doc_id GROUP BY block_key)")
def custom_cost_characters(spark, sf_dir):
    """Another monotone cost of a block: the characters of its texts."""
    d = docs_of(spark, sf_dir).select(F.col("doc_id").alias("id"), F.length("text").alias("n_text"))
    return cost.custom_cost(assigned(spark, sf_dir, "block_tree").join(d, "id"), F.sum("n_text"))


@query(f"WITH s AS ({_SIZES}), m AS (SELECT CAST(('0x' || substr(md5(block_key || '|42'), 1, 8)) AS BIGINT) % 8 AS machine, n FROM s) SELECT CAST(max(l) AS BIGINT) AS makespan FROM (SELECT sum(n * n) AS l FROM m GROUP BY machine)")
def makespan_hashed(spark, sf_dir):
    """Makespan of blocks dealt to eight machines by a hash of their key."""
    s = cut(_sizes(spark, sf_dir), "sizes")
    dealt = s.select("block_key", (sizes.mixer(F.col("block_key"), 42) % 8).alias("machine"))
    return cost.makespan(s, dealt).select(F.col("makespan").cast("bigint"))


@query("SELECT a.s_suppkey AS l_id, b.s_suppkey AS r_id FROM supplier a JOIN supplier b ON a.s_suppkey < b.s_suppkey")
def all_pairs_suppliers(spark, sf_dir):
    """No blocking at all, for a small table."""
    return dedup.all_pairs(w.table(spark, sf_dir, "supplier"), "s_suppkey", limit=None)


@query("WITH n AS (SELECT count(*) AS n FROM supplier) SELECT CAST(2 AS BIGINT) AS max_block, CAST(n * (n - 1) AS BIGINT) AS memberships, CAST(4 + n * (n - 1) AS BIGINT) AS overlap_cost FROM n")
def pair_blocks_cost(spark, sf_dir):
    """The degenerate solution: a block for every pair keeps all pairs at a cost in memberships."""
    return cost.pair_blocks_cost(w.table(spark, sf_dir, "supplier"))


_MATCHED = f"""
s AS (SELECT doc_id, CASE WHEN len(w) < 5 THEN [array_to_string(w, ' ')] ELSE list_distinct(list_transform(range(1, len(w) - 3), lambda i: array_to_string(list_slice(w, i, i + 4), ' '))) END AS s
  FROM (SELECT doc_id, string_split(lower(trim(regexp_replace(text, '\\s+', ' ', 'g'))), ' ') AS w FROM documents)),
a AS ({assigned_sql('block_tree_small')}),
c AS (SELECT l.id AS l_id, r.id AS r_id FROM a l JOIN a r ON l.block_key = r.block_key AND l.id < r.id),
m AS (SELECT l_id, r_id FROM c JOIN s l ON l.doc_id = l_id JOIN s r ON r.doc_id = r_id WHERE len(list_intersect(l.s, r.s)) / (len(l.s) + len(r.s) - len(list_intersect(l.s, r.s))) >= 0.5)"""


@query(
    f"WITH RECURSIVE {_MATCHED}, e AS (SELECT l_id AS x, r_id AS y FROM m UNION SELECT r_id, l_id FROM m), "
    "t AS (SELECT doc_id AS id, doc_id AS r FROM documents UNION SELECT t.id, e.y FROM t JOIN e ON e.x = t.r) SELECT id, min(r) AS cluster FROM t GROUP BY id"
)
def dedup_clusters_documents(spark, sf_dir):
    """End to end: block, compare within blocks, cluster."""
    d = docs_of(spark, sf_dir)
    pairs = dedup.candidate_pairs(assigned(spark, sf_dir, "block_tree_small"))
    records = dedup.shingles(d.select("doc_id", "text"), "text").select("doc_id", "shingles")
    found = dedup.match(pairs, records, "doc_id", dedup.jaccard(F.col("l.shingles"), F.col("r.shingles")), 0.5)
    return dedup.clusters(d, "doc_id", found)


@query(w.BENCHMARK_LINKS_SQL)
def linkage_benchmark_documents(spark, sf_dir):
    return w.benchmark_links(w.table(spark, sf_dir, "benchmark"), docs_of(spark, sf_dir))


@query(f"WITH a AS ({_PART_BLOCKS}), f AS ({PARTS}) SELECT l.id AS a_id, r.id AS b_id FROM a l JOIN a r USING (block_key) JOIN f x ON x.rec_id = l.id AND x.feed = 'A' JOIN f y ON y.rec_id = r.id AND y.feed = 'B' WHERE x.p_size IS NOT DISTINCT FROM y.p_size AND x.p_type IS NOT DISTINCT FROM y.p_type")
def linkage_part_feeds(spark, sf_dir):
    """Two feeds: pairs across them within blocks that agree, nulls included, in size and type."""
    p = w.part_feeds(spark, sf_dir)
    keyed = assign.with_block_key(p, EXAMPLE, P)
    a, b = (keyed.where(F.col("feed") == x).select(F.col("rec_id").alias(f"{x.lower()}_id"), "block_key", F.col("p_size").alias(f"{x}s"), F.col("p_type").alias(f"{x}t")) for x in "AB")
    return a.join(b, (a["block_key"] == b["block_key"]) & a["As"].eqNullSafe(b["Bs"]) & a["At"].eqNullSafe(b["Bt"])).select("a_id", "b_id")


@query("SELECT o_orderpriority, count(*) AS n, round(sum(l_extendedprice), 2) AS total FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1")
def join_bounded_orders_lineitem(spark, sf_dir):
    """A join whose key groups are bounded gives the plain join's rows."""
    li = w.table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("k"), "l_linenumber", F.col("l_extendedprice").cast("decimal(18,4)").alias("l_extendedprice"))
    o = w.table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("k"), "o_orderpriority")
    j = dedup.bounded_join(li, o, "k", 3)
    return j.groupBy("o_orderpriority").agg(F.count("*").alias("n"), F.round(F.sum("l_extendedprice").cast("double"), 2).alias("total"))


@query(f"WITH x AS ({assigned_sql('single_small')}), y AS ({assigned_sql('block_tree_small')}), pr AS ({DOC_PAIRS}) SELECT a.block_key = b.block_key AS in_a, c.block_key = d.block_key AS in_b, count(*) AS n_pairs FROM pr JOIN x a ON a.id = l_id JOIN x b ON b.id = r_id JOIN y c ON c.id = l_id JOIN y d ON d.id = r_id GROUP BY ALL")
def diff_plans(spark, sf_dir):
    d = docs_of(spark, sf_dir)
    return evaluate.diff_plans(assigned(spark, sf_dir, "single_small"), assigned(spark, sf_dir, "block_tree_small"), cut(w.doc_pairs(d), "labels"))


# events ----------------------------------------------------------------------------------------------

EVENT_TREE = BlockTree("block_tree", Node(0, 0, 0, h.identity("type"), {"vpurchase": Node(1, 0, 0, h.bucket_int("user", 10)), "vview": Node(2, 0, 0, h.identity("k"))}))
_EVENTS = f"SELECT *, {tree_sql(EVENT_TREE, events_.EVENT_SPEC)} AS block_key FROM events"


@query(f"SELECT block_key, date_trunc('hour', ts) AS start, count(*) AS n FROM ({_EVENTS}) GROUP BY 1, 2")
def events_block_windows(spark, sf_dir):
    e = events_.assign(w.table(spark, sf_dir, "events"), EVENT_TREE, events_.EVENT_SPEC)
    return events_.block_counts(e).withColumn("start", F.col("start").cast("timestamp_ntz"))


@query(
    f"""WITH e AS ({_EVENTS}), g AS (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY block_key ORDER BY ts) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS new FROM e),
s AS (SELECT *, sum(new) OVER (PARTITION BY block_key ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS s FROM g) SELECT block_key, min(ts) AS start, count(*) AS n FROM s GROUP BY block_key, s"""
)
def events_session_blocks(spark, sf_dir):
    e = events_.assign(w.table(spark, sf_dir, "events"), EVENT_TREE, events_.EVENT_SPEC)
    return events_.session_blocks(e).withColumn("start", F.col("start").cast("timestamp_ntz"))
