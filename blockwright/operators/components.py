"""Connected components of an undirected edge list, by alternating star contractions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.scratch import cut, drop


def connected_components(edges: DataFrame, src: str = "src", dst: str = "dst", max_rounds: int = 60) -> DataFrame:
    """(node, label) of every node of `edges`; the label is the smallest node of its component.

    Every round hangs each node's larger neighbours on its smallest neighbour and then each
    node's smaller neighbours on the smallest of them; the edge list shrinks to one star per
    component in a number of rounds that grows with the logarithm of the longest path. Minima
    are partial aggregates and the joins are plain equi-joins, so a hub of any degree is split
    by adaptive execution instead of being collected in one row. Each round is written to the
    shared folder: lineage stays short and a lost executor costs nothing finished.

    Self-loops give a component of one node; repeated and reversed edges count once; edges
    with a null end are ignored; an empty list gives an empty result.
    """
    a, b = F.col(src), F.col(dst)
    e = edges.where(a.isNotNull() & b.isNotNull()).select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).distinct()
    # written before its two uses, as the edges may be costly to make
    e = cut(e, "edges")
    nodes = e.select(F.explode_outer(F.array("u", "v")).alias("node")).distinct()
    e = e.where("u <> v")
    last = None
    for _ in range(max_rounds):
        both = e.unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = both.join(low, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(low.select("u", F.col("m").alias("v"))).distinct()
        before, e = e, cut(small.where("u <> v"), "edges")
        if last is not None:
            # the nodes still read the first table, but nothing reads a round's edges once the next are written
            drop(before)
        now = e.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if tuple(now) == last:
            break
        last = tuple(now)
    return nodes.join(e.select(F.col("u").alias("node"), F.col("v").alias("label")), "node", "left").select("node", F.coalesce("label", "node").alias("label"))
