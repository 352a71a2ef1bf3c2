"""Learnt trees as SQL text, for other engines and for SQL users."""

from __future__ import annotations

from pyspark.sql import SparkSession

from ..functions.hashes import duck_sql
from ..model import BlockingSpec, BlockTree, Node
from ..operators.sizes import mixer_sql


def _q(v: str) -> str:
    return "'" + v.replace("'", "''") + "'"


def tree_sql(tree: BlockTree, spec: BlockingSpec) -> str:
    """A DuckDB expression of the block key, equal to `assign_blocks`."""
    mix = mixer_sql(spec.id_col, tree.seed)
    if tree.chain:
        joined = "concat_ws(chr(31), " + ", ".join(duck_sql(h, spec) for h in tree.chain) + ")"
        if not tree.chain_parts:
            return joined
        cases = " ".join(f"WHEN {joined} = concat_ws(chr(31), {', '.join(_q(v) for v in k.split(chr(31)))}) THEN {joined} || chr(30) || CAST({mix} % {p} AS VARCHAR)" for k, p in sorted(tree.chain_parts.items()))
        return f"CASE {cases} ELSE {joined} END"

    def of(n: Node) -> str:
        if n.hash is None:
            return f"'{n.id}#' || CAST({mix} % {n.parts} AS VARCHAR)" if n.parts > 1 else f"'{n.id}#0'"
        value = duck_sql(n.hash, spec)
        cases = " ".join(f"WHEN {value} = {_q(v)} THEN {of(c)}" for v, c in n.heavy.items())
        rest = f"'{n.id}|' || {value}"
        return f"CASE {cases} ELSE {rest} END" if cases else rest

    return of(tree.root)


def assign_sql(tree: BlockTree, spec: BlockingSpec, source: str) -> str:
    return f"SELECT {spec.id_col} AS id, {tree_sql(tree, spec)} AS block_key FROM {source}"


def split_sql(assigned: str, cap: int, seed: int = 42) -> str:
    """DuckDB text of `split_oversize` over a SELECT of (id, block_key), or of (id, round, block_key) with its sizes by both."""
    by = "round, block_key" if "AS round" in assigned else "block_key"
    rest = ", round" if "AS round" in assigned else ""
    return f"SELECT id{rest}, CASE WHEN n > {cap} THEN block_key || '/' || CAST({mixer_sql('id', seed)} % CAST(ceil(n / {cap}.0) AS BIGINT) AS VARCHAR) ELSE block_key END AS block_key FROM (SELECT *, count(*) OVER (PARTITION BY {by}) AS n FROM ({assigned}))"


def register_udtf(spark: SparkSession, name: str = "split_rounds") -> None:
    """A table function (keys array<string>) -> (round, block_key), for LATERAL joins in SQL over `round_keys`."""
    from pyspark.sql.functions import udtf

    class SplitRounds:
        def eval(self, keys: list):
            for i, k in enumerate(keys or []):
                yield i, k

    spark.udtf.register(name, udtf(SplitRounds, returnType="round int, block_key string"))
