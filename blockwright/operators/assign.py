"""Learnt functions as columns: routing a record is a few projections, without UDF or shuffle."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import hashes
from ..functions.scratch import cut
from ..model import BlockingSpec, BlockTree, Node, RoundPlan
from .sizes import mixer

#: Heavy children of a level up to which routing is a CASE; beyond it, a broadcast join of (node, value).
CASE_LIMIT = 100
#: Levels of a tree from which its key is hidden from Spark's tracing of join keys.
TRACED = 3


def _levels(tree: BlockTree) -> list[list[Node]]:
    out, level = [], [tree.root]
    while level:
        out.append(level)
        level = [c for n in level for c in n.heavy.values()]
    return out


def _route(df: DataFrame, tree: BlockTree, spec: BlockingSpec, p: str, helpers=()) -> tuple[DataFrame, Column]:
    """`df` with helper columns, and the block key in terms of them.

    Two flat projections a level: the value under the node's own function, then the child.
    A key is 'node|value' or, for a leaf that is split, 'node#part'.
    """
    node, value = f"{p}node", f"{p}value"
    df = df.withColumns({node: F.lit(0), value: F.lit(None).cast("string")})
    part = mixer(F.col(spec.id_col), tree.seed)
    for level in _levels(tree):
        split = [n for n in level if n.hash is not None]
        if not split:
            break
        by_hash: dict[str, list[Node]] = {}
        for n in split:
            by_hash.setdefault(n.hash.name, []).append(n)
        case = None
        for group in by_hash.values():
            test = F.col(node).isin([n.id for n in group])
            col = hashes.column(group[0].hash, spec, helpers)
            case = F.when(test, col) if case is None else case.when(test, col)
        df = df.withColumn(value, case.otherwise(F.col(value)))
        kids = [(n.id, v, c.id) for n in split for v, c in n.heavy.items()]
        if not kids:
            continue
        if len(kids) <= CASE_LIMIT:
            case = None
            for parent, v, child in kids:
                test = (F.col(node) == parent) & (F.col(value) == v)
                case = F.when(test, child) if case is None else case.when(test, child)
            down = case.otherwise(F.col(node))
            df = df.withColumn(f"{p}down", down)
        else:
            table = df.sparkSession.createDataFrame(kids, f"{p}from int, {p}v string, {p}to int")
            df = df.join(F.broadcast(table), (F.col(node) == F.col(f"{p}from")) & (F.col(value) == F.col(f"{p}v")), "left")
            df = df.withColumn(f"{p}down", F.coalesce(f"{p}to", node)).drop(f"{p}from", f"{p}v", f"{p}to")
        # a record that went down has no value yet at its new node
        df = df.withColumn(value, F.when(F.col(f"{p}down") == F.col(node), F.col(value))).withColumn(node, F.col(f"{p}down")).drop(f"{p}down")
    leaves = [n for n in tree.root.walk() if n.hash is None]
    case = None
    for n in leaves:
        key = F.concat(F.lit(f"{n.id}#"), (part % n.parts).cast("string")) if n.parts > 1 else F.lit(f"{n.id}#0")
        test = F.col(node) == n.id
        case = F.when(test, key) if case is None else case.when(test, key)
    inner = F.concat(F.col(node).cast("string"), F.lit("|"), F.col(value))
    return df, inner if case is None else case.otherwise(inner)


def _chain_key(tree: BlockTree, spec: BlockingSpec, helpers=()) -> Column:
    joined = F.concat_ws("\x1f", *[hashes.column(h, spec, helpers) for h in tree.chain])
    if not tree.chain_parts:
        return joined
    part = mixer(F.col(spec.id_col), tree.seed)
    case = None
    for k, p in sorted(tree.chain_parts.items()):
        key = F.concat(joined, F.lit("\x1e"), (part % p).cast("string"))
        case = F.when(joined == k, key) if case is None else case.when(joined == k, key)
    return case.otherwise(joined)


def with_block_key(df: DataFrame, tree: BlockTree, spec: BlockingSpec, name: str = "block_key", helpers=()) -> DataFrame:
    """All columns of `df` and the block key. An existing column of that name is replaced. helpers: names of columns of `hashes.shared` that are there."""
    if tree.chain:
        # every function of a chain is computed for every record
        own = {} if helpers else hashes.shared(list(tree.chain), spec)
        return df.withColumns(own).withColumn(name, _chain_key(tree, spec, helpers or own)).drop(*own)
    helper = "__route_"
    keep = [c for c in df.columns if c != name]
    routed, key = _route(df, tree, spec, helper, helpers)
    # Never null, and known not to be: else a join on it would push a filter with the whole routing below the projections.
    # A join also looks for partitions to prune and traces its keys down to the scan, writing out each projection's
    # expressions in the next, which doubles them level by level; it stops at a column that an explode made.
    key = F.coalesce(key, F.lit(""))
    made = F.explode_outer(F.array(key)).alias(name) if tree.height >= TRACED else key.alias(name)
    return routed.select(*[F.col(f"`{c}`") for c in keep], made)


def assign_blocks(df: DataFrame, tree: BlockTree, spec: BlockingSpec, rollup: DataFrame | None = None) -> DataFrame:
    """(id, block_key): each record once. `rollup`: (block_key, merged_key) of blocks that were merged."""
    out = with_block_key(df, tree, spec).select(F.col(spec.id_col).alias("id"), "block_key")
    if rollup is not None:
        # a row for each merged block; Spark broadcasts it where it is small
        out = out.join(rollup, "block_key", "left").select("id", F.coalesce("merged_key", "block_key").alias("block_key"))
    return out


def assign_rounds(df: DataFrame, plan: RoundPlan, spec: BlockingSpec, mode: str = "union") -> DataFrame:
    """(id, round, block_key) of every round.

    "union": one projection computes all keys and an explode emits them, so that pairing
    shuffles once; "rounds": a union of one assignment a round, each a pass of its own.
    """
    if not plan.rounds:
        return df.select(F.col(spec.id_col).alias("id"), F.lit(0).alias("round"), F.lit("").alias("block_key")).limit(0)
    if mode == "rounds":
        out = None
        for i, t in enumerate(plan.rounds):
            one = assign_blocks(df, t, spec).select("id", F.lit(i).alias("round"), "block_key")
            out = one if out is None else out.unionByName(one)
        return out
    # the outer form: for the inner one Spark would infer a filter on the array and push the whole routing below itself once more
    return round_keys(df, plan, spec).select("id", F.posexplode_outer("keys").alias("round", "block_key"))


def round_keys(df: DataFrame, plan: RoundPlan, spec: BlockingSpec) -> DataFrame:
    """(id, keys): the block keys of all rounds of each record. What functions of several rounds share is computed once."""
    every = {h.name: h for t in plan.rounds for h in t.functions()}
    helpers = hashes.shared(list(every.values()), spec, least=1)
    out = df.withColumns(helpers)
    for i, t in enumerate(plan.rounds):
        out = with_block_key(out, t, spec, f"__key{i}", helpers)
    return out.select(F.col(spec.id_col).alias("id"), F.array(*[F.col(f"__key{i}") for i in range(len(plan.rounds))]).alias("keys"))


def split_oversize(assigned: DataFrame, cap: int, seed: int = 42) -> DataFrame:
    """An assignment (id, block_key) or (id, round, block_key) with every block of n > cap records split at random into ceil(n / cap) parts, by real sizes.

    Sizes are one aggregate; only blocks over the cap, no more than records / cap, are joined
    back. Works on any blocking, so a tree learnt on other data keeps its cap.
    """
    assigned = cut(assigned, "assigned")
    by = [c for c in assigned.columns if c != "id"]
    big = assigned.groupBy(by).agg(F.count("*").alias("n")).where(F.col("n") > cap).select(*by, F.ceil(F.col("n") / cap).cast("bigint").alias("parts"))
    key = F.when(F.col("parts").isNull(), F.col("block_key")).otherwise(F.concat("block_key", F.lit("/"), (mixer(F.col("id"), seed) % F.col("parts")).cast("string")))
    return assigned.join(big, by, "left").select(*[key.alias(c) if c == "block_key" else F.col(c) for c in assigned.columns])


def sliced(assigned: DataFrame, cap: int) -> DataFrame:
    """An assignment (id, block_key) with every block of n > cap records numbered off into ceil(n / cap) blocks, none of which is over the cap; written, as numbers follow the files."""
    from .dedup import bounded_parts

    key = F.when(F.col("__part") > 0, F.concat("block_key", F.lit("\x1e"), F.col("__part").cast("string"))).otherwise(F.col("block_key"))
    return cut(bounded_parts(assigned.select("id", "block_key"), "block_key", cap).select("id", key.alias("block_key")), "sliced")


def keys_by_round(assigned: DataFrame) -> DataFrame:
    """(id, keys) of (id, round, block_key): a record's keys in order of rounds."""
    return assigned.groupBy("id").agg(F.array_sort(F.collect_list(F.struct("round", "block_key"))).alias("k")).select("id", F.col("k.block_key").alias("keys"))


def random_blocks(df: DataFrame, id_col: str, n: int, cap: int, seed: int = 42, strict: bool = False) -> DataFrame:
    """(id, block_key): records at random in ceil(n / cap) blocks.

    The cap holds on average; with `strict`, what a block has too much is numbered on into
    further blocks of at most `cap`.
    """
    blocks = max(1, -(-n // cap))
    m = mixer(F.col(id_col), seed)
    out = df.select(F.col(id_col).alias("id"), (m % blocks).alias("b"), m.alias("m"))
    if not strict:
        return out.select("id", F.col("b").cast("string").alias("block_key"))
    from pyspark.sql import Window

    at = F.row_number().over(Window.partitionBy("b").orderBy("m", "id")) - 1
    return out.select("id", F.concat_ws("+", F.col("b").cast("string"), F.floor(at / cap).cast("string")).alias("block_key"))


def without_parts(tree: BlockTree) -> BlockTree:
    """The tree without random splits, which `split_oversize` makes by real sizes instead."""

    def bare(n: Node) -> Node:
        return Node(n.id, n.size, n.pairs, n.hash, {v: bare(c) for v, c in n.heavy.items()})

    return BlockTree(tree.kind, bare(tree.root), tree.seed, tree.chain)


def frontier(sizes: dict[int, int], tree: BlockTree, cap: int) -> BlockTree:
    """The tree cut at its shallowest nodes of at most `cap` records by real `sizes` (node -> records); leaves over the cap are split."""

    def kept(n: Node) -> Node:
        size = sizes.get(n.id, 0)
        out = Node(n.id, size, n.pairs)
        if size <= cap:
            return out
        if n.hash is None:
            out.parts = -(-size // cap)
            return out
        out.hash = n.hash
        out.heavy = {v: kept(c) for v, c in n.heavy.items()}
        return out

    return BlockTree(tree.kind, kept(tree.root), tree.seed)


def node_sizes(df: DataFrame, tree: BlockTree, spec: BlockingSpec) -> dict[int, int]:
    """Records at or below each node of a tree: one aggregate over its deepest nodes, summed up on the driver."""
    routed, _ = _route(df, tree, spec, "__route_")
    own = {r[0]: r[1] for r in routed.groupBy("__route_node").count().collect()}
    out: dict[int, int] = {}

    def total(n: Node) -> int:
        out[n.id] = own.get(n.id, 0) + sum(total(c) for c in n.heavy.values())
        return out[n.id]

    total(tree.root)
    return out


def refine_to(df: DataFrame, tree: BlockTree, spec: BlockingSpec, cap: int) -> BlockTree:
    """Run-time adaptation: deeper where real sizes demand it, shallower where they don't."""
    return frontier(node_sizes(df, tree, spec), tree, cap)
