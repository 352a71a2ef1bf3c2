"""The block tree learnt level by level with aggregates, where signatures are too many for the driver.

Each level is one pass over the records that are still in an oversized node: they are routed
by the tree so far, and the heavy values of every function are counted by node. Labelled
pairs are a written table that carries each pair's node. Scores, eligibility and the choice
of a function are DataFrame aggregates and one window over (node, function); the driver sees
the chosen functions and their heavy children, at most a row for each cap of records. The
tree is the one that `learn_block_tree` learns from exact features.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import hashes
from ..functions.scratch import cut
from ..model import BlockingConfig, BlockingSpec, BlockTree, HashFn, Node
from .assign import _route
from .learn import by_chance
from .sizes import canonical_pairs, heavy_values, project


def _hashed_pairs(df: DataFrame, spec: BlockingSpec, pairs: DataFrame, n: int, library: list[HashFn]) -> DataFrame:
    """(node, lx, rx): the hashed values of both records of each pair, all at the root."""
    p = cut(canonical_pairs(pairs), "pairs")
    ids = p.select(F.explode_outer(F.array("l_id", "r_id")).alias("__pid")).distinct()
    part = df.join(ids, F.col(spec.id_col) == F.col("__pid"), "left_semi")
    h = project(part, spec, library).select("id", F.array(*[F.xxhash64(f"h{i}") for i in range(n)]).alias("x"))
    l, r = (h.select(F.col("id").alias(f"{s}_id"), F.col("x").alias(f"{s}x")) for s in "lr")
    return cut(p.join(l, "l_id").join(r, "r_id").select(F.lit(0).alias("node"), "lx", "rx"), "pairs")


def score_level(sizes: DataFrame, pairs: DataFrame, nodes: DataFrame, ranks: DataFrame, config: BlockingConfig) -> DataFrame:
    """(node, hash, score) chosen for each node that has an eligible function.

    sizes: (node, hash, x, n) of the heavy values; pairs: (node, lx, rx); nodes: (node, total);
    ranks: (hash, rank) of the functions in order of name.
    """
    cap = config.cap
    each = pairs.select("node", F.posexplode_outer(F.arrays_zip("lx", "rx")).alias("hash", "z")).select("node", "hash", F.col("z.lx").alias("x"), (F.col("z.lx") == F.col("z.rx")).alias("same"))
    broken = each.groupBy("node", "hash").agg(F.sum((~F.col("same")).cast("bigint")).alias("broken"))
    inside = each.where("same").groupBy("node", "hash", "x").agg(F.count("*").alias("pairs"))
    held = sizes.join(inside, ["node", "hash", "x"], "left").fillna(0, ["pairs"])
    parts = F.ceil(F.col("n") / cap)
    risk = {"optimistic": F.lit(0.0), "pessimistic": F.col("pairs").cast("double"), "expected": F.col("pairs") * (parts - 1) / parts}[config.scorer]
    heavy = held.groupBy("node", "hash").agg(F.count("*").alias("n_heavy"), F.max("n").alias("largest"), F.sum(risk).alias("risk"))
    every = nodes.crossJoin(F.broadcast(ranks)).join(broken, ["node", "hash"], "left").join(heavy, ["node", "hash"], "left").fillna(0)
    score = F.round(F.col("broken") + F.col("risk"), 9)
    allowed = every.where((F.col("largest") < F.col("total")) & (F.col("largest") <= config.min_shrink * F.col("total")) & (F.col("n_heavy") <= config.max_heavy_children))
    best = Window.partitionBy("node").orderBy(score, "n_heavy", "largest", "rank")
    return allowed.withColumn("place", F.row_number().over(best)).where("place = 1").select("node", "hash", score.alias("score"))


def learn_block_tree_wide(df: DataFrame, spec: BlockingSpec, pairs: DataFrame, library: list[HashFn], config: BlockingConfig) -> BlockTree:
    """Block tree of `df` for the cap of `config`, with a scan for each level and two before the first."""
    spark, cap = df.sparkSession, config.cap
    root = Node(0, df.count())
    tree = BlockTree("block_tree", root, config.seed)
    hashed_pairs = _hashed_pairs(df, spec, pairs, len(library), library)
    root.pairs = hashed_pairs.count()
    if root.size <= cap:
        return tree
    # a value that is light in all records is light in every node
    heavy = cut(heavy_values(project(df, spec, library), len(library), cap).select("hash", "value", F.xxhash64("value").alias("x")), "heavy")
    ranks = spark.createDataFrame([(i, r) for r, i in enumerate(sorted(range(len(library)), key=lambda i: library[i].name))], "hash int, rank int")
    level, n, first = [root], 1, 0
    for _ in range(config.max_depth):
        if not level:
            break
        routed, _ = _route(df, tree, spec, "__route_")
        # a filter stops at a column that an explode made, and is not pushed below the routing with all of it written out
        inside = routed.select("*", F.explode_outer(F.array("__route_node")).alias("__at")).where(F.col("__at") >= first)
        inside = hashes.columns(inside, library, spec, F.col("__at").alias("node"))
        long = inside.select("node", F.posexplode_outer(F.array(*[F.xxhash64(f"h{i}") for i in range(len(library))])).alias("hash", "x"))
        sizes = long.join(heavy.select("hash", "x"), ["hash", "x"], "left_semi").groupBy("node", "hash", "x").agg(F.count("*").alias("n")).where(F.col("n") > cap)
        sizes = cut(sizes, "sizes")
        nodes = spark.createDataFrame([(c.id, c.size) for c in level], "node int, total bigint")
        chosen = cut(score_level(sizes, hashed_pairs, nodes, ranks, config), "chosen")
        kids = chosen.select("node", "hash", "score").join(sizes, ["node", "hash"], "left").join(heavy, ["hash", "x"], "left").select("node", "hash", "score", "value", "x", "n").collect()
        of: dict[int, list] = {}
        for r in kids:
            of.setdefault(r["node"], []).append(r)
        nxt, rows = [], []
        for node in level:
            if node.id not in of or config.random_function and by_chance(node, cap) < of[node.id][0]["score"]:
                continue
            node.hash = library[of[node.id][0]["hash"]]
            for r in sorted((r for r in of[node.id] if r["n"] is not None), key=lambda r: r["value"]):
                child = Node(n, int(r["n"]))
                node.heavy[r["value"]] = child
                rows.append((node.id, r["hash"], r["x"], n))
                nxt.append(child)
                n += 1
        for node in level:
            if node.hash is None:
                node.parts = math.ceil(node.size / cap)
        down = spark.createDataFrame(rows, "node int, hash int, x bigint, child int")
        held = hashed_pairs.join(chosen, "node").withColumn("x", F.get("lx", F.col("hash"))).where(F.col("x") == F.get("rx", F.col("hash")))
        hashed_pairs = cut(held.join(down, ["node", "hash", "x"]).select(F.col("child").alias("node"), "lx", "rx"), "pairs")
        counted = {r["node"]: r["count"] for r in hashed_pairs.groupBy("node").count().collect()}
        for c in nxt:
            c.pairs = counted.get(c.id, 0)
        first = nxt[0].id if nxt else n
        level = nxt
    for node in level:
        node.parts = math.ceil(node.size / cap)
    return tree
