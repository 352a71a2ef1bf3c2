"""Roll-up: merge small blocks, within the cap, to win back pairs that they split.

Only blocks that a split pair touches can gain, so the driver sees one number per such
block and one per pair of blocks with a split pair between them, never the records.
"""

from __future__ import annotations

import heapq

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.scratch import cut
from .components import connected_components

#: Cross edges up to which the greedy merge runs on the driver; beyond it, in a task for each connected component.
DRIVER_EDGES = 100_000


def edges(assigned: DataFrame, pairs: DataFrame) -> DataFrame:
    """(a, b, benefit): split pairs between two blocks, a < b. assigned: (id, block_key); pairs: (l_id, r_id)."""
    from .sizes import canonical_pairs

    l, r = (assigned.select(F.col("id").alias(f"{p}_id"), F.col("block_key").alias(f"{p}k")) for p in "lr")
    split = canonical_pairs(pairs).join(l, "l_id").join(r, "r_id").where("lk <> rk")
    return split.groupBy(F.least("lk", "rk").alias("a"), F.greatest("lk", "rk").alias("b")).agg(F.count("*").alias("benefit"))


def touched_sizes(assigned: DataFrame, cross: DataFrame) -> DataFrame:
    """(block_key, n) of the blocks that an edge touches."""
    keys = cross.select(F.explode_outer(F.array("a", "b")).alias("block_key")).distinct()
    return assigned.join(keys, "block_key", "left_semi").groupBy("block_key").agg(F.count("*").alias("n"))


def greedy(sizes: dict[str, int], cross: dict[tuple[str, str], int], cap: int, by_density: bool = True) -> list[set[str]]:
    """Groups of blocks to merge, each within the cap.

    The pair of groups with most benefit for the smaller of the two merges first (or, with
    `by_density` off, simply of most benefit); ties go to the smaller keys. Benefits of a
    merged group add up; outdated heap entries are dropped when they come up.
    """
    group = {k: {k} for k in sizes}
    size = dict(sizes)
    near: dict[str, dict[str, int]] = {k: {} for k in sizes}
    for (a, b), n in cross.items():
        near[a][b] = near[b][a] = near[a].get(b, 0) + n
    heap: list[tuple] = []

    def push(a: str, b: str) -> None:
        if size[a] + size[b] <= cap:
            a, b = min(a, b), max(a, b)
            gain = near[a][b]
            heapq.heappush(heap, (-gain / min(size[a], size[b]) if by_density else -gain, a, b, gain, size[a], size[b]))

    for a, b in cross:
        if a in size and b in size:
            push(a, b)
    while heap:
        _, a, b, gain, sa, sb = heapq.heappop(heap)
        if a not in group or b not in group or near[a].get(b) != gain or (size[a], size[b]) != (sa, sb):
            continue
        group[a] |= group.pop(b)
        size[a] += size.pop(b)
        for c, n in near.pop(b).items():
            near[c].pop(b, None)
            if c != a:
                near[a][c] = near[c][a] = near[a].get(c, 0) + n
        for c in near[a]:
            push(a, c)
    return list(group.values())


def first_fit(sizes: list[tuple[str, int]], cap: int, target: int = 0) -> list[list[str]]:
    """Blocks packed by falling size (ties: the smaller key), each into the first group with room, until `target` groups are left.

    The room of the groups is held in a tree of maxima, so that a block finds its group in O(log n).
    """
    order = sorted(sizes, key=lambda x: (-x[1], x[0]))
    width = 1 << max(0, (len(order) - 1).bit_length())
    room = [-1] * (2 * width)

    def put(i: int, value: int) -> None:
        p = i + width
        room[p] = value
        while p > 1:
            p >>= 1
            room[p] = max(room[2 * p], room[2 * p + 1])

    groups: list[list[str]] = []
    left = len(order)
    for k, n in order:
        if room[1] < n or left <= target:
            put(len(groups), cap - n)
            groups.append([k])
            continue
        p = 1
        while p < width:
            p = 2 * p if room[2 * p] >= n else 2 * p + 1
        groups[p - width].append(k)
        put(p - width, room[p] - n)
        left -= 1
    return groups


#: Blocks that one task packs; more are dealt by a hash of their key to as many tasks as that needs.
PACKED_BLOCKS = 200_000


def merge_small(sizes: DataFrame, cap: int, target_blocks: int | None = None, at_once: int = PACKED_BLOCKS) -> DataFrame:
    """(block_key, merged_key): blocks without common pairs packed together within the cap, to leave fewer blocks. sizes: (block_key, n).

    Merging stops once `target_blocks` are left, or goes on as far as blocks fit. Packing runs
    in tasks: no size comes to the driver. Blocks of over `cap` records are left alone.
    """
    n = sizes.count()
    parts = max(1, -(-n // at_once))
    # of the blocks to leave, each part its share
    target = 0 if target_blocks is None else max(1, -(-target_blocks // parts))
    part = F.pmod(F.xxhash64("block_key"), F.lit(parts)).cast("int")

    def pack(pdf):
        small = [(k, int(x)) for k, x in zip(pdf["block_key"], pdf["n"])]
        return pd.DataFrame([(k, min(g)) for g in first_fit(small, cap, target) if len(g) > 1 for k in g], columns=["block_key", "merged_key"])

    return sizes.where(F.col("n") <= cap).withColumn("part", part).groupBy("part").applyInPandas(pack, "block_key string, merged_key string")


def recovered(groups: list[set[str]], cross: dict[tuple[str, str], int]) -> int:
    """Split pairs that the groups bring together."""
    of = {k: i for i, g in enumerate(groups) for k in g}
    return sum(n for (a, b), n in cross.items() if a in of and of.get(a) == of.get(b))


def best_greedy(sizes, cross, cap) -> list[set[str]]:
    """Density greedy, or greedy by benefit alone where that recovers more (density can spend room on a small gain)."""
    plans = [greedy(sizes, cross, cap, by_density=d) for d in (True, False)]
    return max(plans, key=lambda g: recovered(g, cross))


def fitting(assigned: DataFrame, cross: DataFrame, cap: int) -> DataFrame:
    """(a, b, benefit, na, nb): the cross edges whose two blocks fit the cap together."""
    sizes = cut(touched_sizes(assigned, cross), "sizes")
    x, y = (sizes.select(F.col("block_key").alias(k), F.col("n").alias(f"n{k}")) for k in "ab")
    return cut(cross.join(x, "a").join(y, "b").where(F.col("na") + F.col("nb") <= cap).select("a", "b", "benefit", "na", "nb"), "fit")


def _of(fit: pd.DataFrame) -> tuple[dict[str, int], dict[tuple[str, str], int]]:
    """Sizes and benefits of rows of `fitting`."""
    sizes = dict(zip(fit["a"], map(int, fit["na"]))) | dict(zip(fit["b"], map(int, fit["nb"])))
    return sizes, {(a, b): int(n) for a, b, n in zip(fit["a"], fit["b"], fit["benefit"])}


def greedy_by_component(fit: DataFrame, cap: int, safeguard: bool = True) -> DataFrame:
    """(block_key, merged_key) of the greedy merge over (a, b, benefit, na, nb), a task for each connected component.

    Merges of one component change nothing in another, so the groups are those of one merge over
    all. With `safeguard` both plans are made, and the one that recovers more in all is taken.
    """
    label = connected_components(fit.select("a", "b"), "a", "b").select(F.col("node").alias("a"), F.col("label").alias("component"))

    def run(pdf):
        sizes, cross = _of(pdf)
        rows = []
        for plan, d in enumerate((True, False) if safeguard else (True,)):
            groups = [g for g in greedy(sizes, cross, cap, by_density=d) if len(g) > 1]
            rows += [(plan, k, min(g), 0) for g in groups for k in g] + [(plan, None, None, recovered(groups, cross))]
        return pd.DataFrame(rows, columns=["plan", "block_key", "merged_key", "won"])

    made = cut(fit.join(label, "a").groupBy("component").applyInPandas(run, "plan int, block_key string, merged_key string, won bigint"), "plans")
    won = {r["plan"]: r["won"] for r in made.groupBy("plan").agg(F.sum("won").alias("won")).collect()}
    return made.where((F.col("plan") == max(sorted(won), key=won.get, default=0)) & F.col("block_key").isNotNull()).select("block_key", "merged_key")


def exact_rollup(sizes: dict[str, int], cross: dict[tuple[str, str], int], cap: int) -> list[set[str]]:
    """Best grouping of at most 12 blocks, by trying all."""
    if len(sizes) > 12:
        raise ValueError("exact roll-up is for at most 12 blocks")
    keys = sorted(sizes)
    best: tuple[int, list[set[str]]] = (-1, [])

    def put(i: int, groups: list[set[str]], room: list[int]) -> None:
        nonlocal best
        if i == len(keys):
            got = recovered(groups, cross)
            if got > best[0]:
                best = (got, [set(g) for g in groups])
            return
        k = keys[i]
        for j in range(len(groups)):
            if room[j] >= sizes[k]:
                groups[j].add(k)
                room[j] -= sizes[k]
                put(i + 1, groups, room)
                groups[j].discard(k)
                room[j] += sizes[k]
        groups.append({k})
        room.append(cap - sizes[k])
        put(i + 1, groups, room)
        groups.pop()
        room.pop()

    put(0, [], [])
    return best[1]


def to_map(spark: SparkSession, groups: list[set[str]]) -> DataFrame:
    """(block_key, merged_key) of merged blocks; the smallest key names the group."""
    rows = [(k, min(g)) for g in groups if len(g) > 1 for k in sorted(g)]
    return spark.createDataFrame(rows, "block_key string, merged_key string")


def rollup(assigned: DataFrame, pairs: DataFrame, cap: int, strategy: str = "density", safeguard: bool = True, merge_zero_benefit: bool = False, target_blocks: int | None = None) -> DataFrame:
    """(block_key, merged_key) for the blocks of any disjoint assignment that are merged.

    "density" works on the cross edges whose two blocks fit the cap together, as no others can
    ever be in one group: few of them on the driver, more in tasks by connected component, with
    the same result. "matching" goes by rounds of mutually best merges. With `merge_zero_benefit` what is
    left is packed further by `merge_small`, without looking at pairs.
    """
    spark = assigned.sparkSession
    assigned = cut(assigned.select("id", "block_key"), "assigned")
    cross = cut(edges(assigned, pairs), "cross")
    if strategy == "matching":
        merged = matching_rollup(assigned, cross, cap)
    else:
        fit = fitting(assigned, cross, cap)
        if fit.count() > DRIVER_EDGES:
            merged = greedy_by_component(fit, cap, safeguard)
        else:
            sizes, got = _of(fit.toPandas())
            merged = to_map(spark, best_greedy(sizes, got, cap) if safeguard else greedy(sizes, got, cap))
    if not merge_zero_benefit:
        return merged
    every = assigned.groupBy("block_key").agg(F.count("*").alias("n"))
    label = cut(every.join(merged, "block_key", "left").select("block_key", "n", F.coalesce("merged_key", "block_key").alias("merged_key")), "label")
    packed = merge_small(label.groupBy(F.col("merged_key").alias("block_key")).agg(F.sum("n").alias("n")), cap, target_blocks).select(F.col("block_key").alias("merged_key"), F.col("merged_key").alias("packed_key"))
    label = label.join(packed, "merged_key", "left").select("block_key", F.coalesce("packed_key", "merged_key").alias("merged_key"))
    shared = label.groupBy("merged_key").agg(F.count("*").alias("old")).where("old > 1").select("merged_key")
    return label.join(shared, "merged_key", "left_semi").select("block_key", "merged_key")


def merged(assigned: DataFrame, plan: DataFrame) -> DataFrame:
    """(id, block_key) of an assignment after a roll-up (block_key, merged_key)."""
    return assigned.join(plan, "block_key", "left").select("id", F.coalesce("merged_key", "block_key").alias("block_key"))


def rolled_rounds(df: DataFrame, spec, features, config, pairs: DataFrame, roll: bool = True, learner: str = "block_tree") -> tuple[list[int], list[tuple]]:
    """(pairs covered after each round, (tree, roll-up plan) of each round): rounds of disjoint blocking with a roll-up inside each.

    What a round's merged blocks win back is covered too, so the next round learns on the pairs
    that are still open. Ends like `learn_rounds`.
    """
    import numpy as np

    from . import learn
    from .assign import assign_blocks
    from .cost import together

    open_, out, plans, seen = np.arange(len(features.same)), [], [], 0
    spark = df.sparkSession
    while len(open_) and len(plans) < config.max_rounds:
        tree = learn.LEARNERS[learner](features.pick(open_), config)
        left = cut(spark.createDataFrame(pa.table({"l_id": features.pair_ids[open_, 0], "r_id": features.pair_ids[open_, 1], "i": open_})), "open")
        blocks = cut(assign_blocks(df, tree, spec), "blocks")
        plan = cut(rollup(blocks, left, config.max_block_size), "plan") if roll else None
        kept = together(merged(blocks, plan) if roll else blocks, left).where("kept").join(left, ["l_id", "r_id"]).select("i").toArrow()["i"].to_numpy()
        if not len(kept):
            break
        plans.append((tree, plan))
        seen += len(kept)
        out.append(seen)
        open_ = np.setdiff1d(open_, kept)
    return out, plans


def matching_rollup(assigned: DataFrame, cross: DataFrame, cap: int, max_rounds: int = 20) -> DataFrame:
    """Roll-up by rounds of mutually best merges: every group names its best partner, pairs that name each other merge.

    A round is two windows over the cross edges and never looks at the records again.
    """
    sizes = cut(touched_sizes(assigned, cross), "sizes").select(F.col("block_key").alias("k"), "n")
    label = sizes.select(F.col("k").alias("block_key"), F.col("k").alias("merged_key"))
    e = cross
    for _ in range(max_rounds):
        sa, sb = (sizes.select(F.col("k").alias(x), F.col("n").alias(f"n{x}")) for x in "ab")
        fit = e.join(sa, "a").join(sb, "b").where(F.col("na") + F.col("nb") <= cap).withColumn("ratio", F.col("benefit") / F.least("na", "nb"))
        both = fit.select(F.col("a").alias("x"), F.col("b").alias("y"), "ratio").unionByName(fit.select(F.col("b").alias("x"), F.col("a").alias("y"), "ratio"))
        edge = F.struct((-F.col("ratio")).alias("r"), F.least("x", "y").alias("lo"), F.greatest("x", "y").alias("hi"))
        best = both.withColumn("rank", F.row_number().over(Window.partitionBy("x").orderBy(edge))).where("rank = 1").select("x", "y")
        back = best.select(F.col("x").alias("y"), F.col("y").alias("x2"))
        mutual = cut(best.join(back, "y").where("x = x2 and x < y").select("x", "y"), "mutual")
        if mutual.isEmpty():
            break
        to = mutual.select(F.col("y").alias("old"), F.col("x").alias("new"))

        def renamed(df: DataFrame, c: str) -> DataFrame:
            return df.join(to, df[c] == F.col("old"), "left").withColumn(c, F.coalesce("new", c)).drop("old", "new")

        label = cut(renamed(label, "merged_key"), "label")
        sizes = cut(renamed(sizes, "k").groupBy("k").agg(F.sum("n").alias("n")), "sizes")
        e = renamed(renamed(e, "a"), "b").where("a <> b")
        e = cut(e.groupBy(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).agg(F.sum("benefit").alias("benefit")), "cross")
    moved = label.where("block_key <> merged_key").select("merged_key").distinct()
    return label.join(moved, "merged_key", "left_semi").select("block_key", "merged_key")
