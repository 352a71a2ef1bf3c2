"""Mixing sources to target weights over a domain - language - source tree.

A token budget is split from the root down. A node gives each child its share by weight,
but no child more than its subtree can supply (its tokens times `max_epochs`); what a
child can't take goes to its siblings by their weights. As a node's own budget never
exceeds what its subtree supplies, a shortage is made good among siblings first and
reaches an ancestor's siblings only where the whole subtree is exhausted.

A leaf's budget is spent in epochs: whole passes first, then the longest prefix, in the
seeded order of the next epoch, whose tokens don't exceed what is left. The order is that
of md5(seed, epoch, doc_id), so a prefix is described by one cut-off key; it is found by
summing tokens in 4096 ranges of the key and running sums inside the one range where the budget
ends. The texts themselves are only filtered against the cut-offs, which are a row for each
leaf and epoch: they don't shuffle.

Tokens are white-space separated words. Defined results: null languages and sources are
leaves named "(none)"; null and blank texts have 0 tokens and are taken as long as their
place in the order is within the prefix; rows of equal doc_id have one place and are taken
together or not at all; an empty table gives an empty result; a column called `epoch` or
`domain` is replaced, other columns are kept as they are; weights of 0 give nothing.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.scratch import cut

NONE = "(none)"


@dataclass(frozen=True)
class Weights:
    """Relative weights of the children at each level; a name without one has `other`."""

    domain: dict[str, float] = field(default_factory=dict)
    language: dict[str, float] = field(default_factory=dict)
    source: dict[str, float] = field(default_factory=dict)
    other: float = 1.0


DEFAULT = Weights(domain={"crawl": 5, "reference": 3, "forum": 2}, language={"en": 5, "de": 2, "fr": 2, "es": 1})
BUDGET_SHARE = 0.6
MAX_EPOCHS = 2
SEED = 17


def default_domain() -> Column:
    """Domain of a source by its number: under 5 crawl, under 12 reference, else forum; sources without a number are crawl."""
    n = F.regexp_extract(F.coalesce("source", F.lit("")), "([0-9]+)$", 1).try_cast("int")
    return F.when(n.isNull() | (n < 5), "crawl").when(n < 12, "reference").otherwise("forum")


def n_tokens(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(r"\S+")), F.lit(0)).cast("bigint")


def _split(budget: float, children: list[tuple[str, float, float]]) -> dict[str, float]:
    """Budget of each (name, weight, capacity): by weight, none above its capacity, the rest to the others."""
    order = sorted((c for c in children if c[1] > 0), key=lambda c: (c[2] / c[1], c[0]))
    out = {c[0]: 0.0 for c in children}
    taken, weight = 0.0, sum(c[1] for c in order)
    for i, (name, w, cap) in enumerate(order):
        if cap * weight <= (budget - taken) * w:
            out[name] = cap
            taken += cap
            weight -= w
        else:
            rest = (budget - taken) / weight
            out |= {c[0]: rest * c[1] for c in order[i:]}
            break
    return out


def allocate(leaves: list[tuple[str, str, str, int]], budget: float, weights: Weights, max_epochs: int) -> dict[tuple[str, str, str], int]:
    """Token budget of each leaf (domain, language, source, tokens)."""
    cap: dict[tuple, float] = {}
    for d, g, s, t in leaves:
        for k in ((d,), (d, g), (d, g, s)):
            cap[k] = cap.get(k, 0) + t * max_epochs
    out = {}
    tables = (weights.domain, weights.language, weights.source)

    def down(node: tuple, amount: float) -> None:
        if len(node) == 3:
            out[node] = math.floor(amount + 1e-6)
            return
        kids = sorted({k for k in cap if len(k) == len(node) + 1 and k[: len(node)] == node})
        w = tables[len(node)]
        shares = _split(amount, [(k[-1], w.get(k[-1], weights.other), cap[k]) for k in kids])
        for k in kids:
            down(k, shares[k[-1]])

    total = sum(v for k, v in cap.items() if len(k) == 1)
    down((), min(budget, total))
    return out


def _key(epoch: Column, seed: int) -> Column:
    return F.md5(F.concat_ws("|", F.lit(str(seed)), epoch.cast("string"), F.coalesce(F.col("doc_id").cast("string"), F.lit("")))) 


def mix(docs: DataFrame, weights: Weights = DEFAULT, budget_share: float | None = BUDGET_SHARE, budget: int | None = None, max_epochs: int = MAX_EPOCHS, seed: int = SEED, domain: Column | None = None) -> DataFrame:
    """The selected rows of `docs`, once for each epoch they are in, with `domain`, `epoch` and `n_tokens`.

    The budget is `budget` tokens or the share `budget_share` of all tokens there are.
    """
    spark = docs.sparkSession
    leaf = [(domain if domain is not None else default_domain()).alias("__d"), F.coalesce("lang", F.lit(NONE)).alias("__g"), F.coalesce("source", F.lit(NONE)).alias("__s")]
    narrow = cut(docs.select("doc_id", *leaf, n_tokens(F.col("text")).alias("__t")), "tokens")
    totals = [tuple(r) for r in narrow.groupBy("__d", "__g", "__s").agg(F.sum("__t")).collect()]
    amount = budget if budget is not None else budget_share * sum(t[3] for t in totals)
    plan = []
    for (d, g, s), b in allocate(totals, amount, weights, max_epochs).items():
        have = next(t[3] for t in totals if t[:3] == (d, g, s))
        for e in range(max_epochs):
            r = min(have, b - e * have)
            if r > 0 or (e == 0 and b >= 0 and have == 0 and b == have):
                plan.append((d, g, s, e, r, r == have))
    quota = spark.createDataFrame(plan, "d string, g string, s string, epoch int, quota bigint, whole boolean")
    same = (F.col("__d") == F.col("d")) & (F.col("__g") == F.col("g")) & (F.col("__s") == F.col("s"))
    part = narrow.join(F.broadcast(quota.where("not whole")), same).select("d", "g", "s", "epoch", "quota", "__t", _key(F.col("epoch"), seed).alias("key")).withColumn("range", F.substring("key", 1, 3))
    leaf_epoch = ("d", "g", "s", "epoch", "quota")
    upto = Window.partitionBy(*leaf_epoch).orderBy("range")
    ranges = part.groupBy(*leaf_epoch, "range").agg(F.sum("__t").alias("t")).withColumn("sum", F.sum("t").over(upto))
    # the range in which the budget ends, with the tokens before it
    ends = ranges.where("sum > quota").groupBy(*leaf_epoch).agg(F.min_by(F.struct("range", (F.col("sum") - F.col("t")).alias("before")), "range").alias("x")).select("d", "g", "s", "epoch", "x.*")
    inner = part.join(F.broadcast(ends), ["d", "g", "s", "epoch", "range"])
    run = F.sum("__t").over(Window.partitionBy("d", "g", "s", "epoch").orderBy("key").rangeBetween(Window.unboundedPreceding, Window.currentRow)) + F.col("before")
    last = inner.withColumn("run", run).where("run <= quota").groupBy("d", "g", "s", "epoch").agg(F.max("key").alias("cutoff"))
    cutoffs = quota.where("not whole").join(ends.select("d", "g", "s", "epoch", F.col("range").alias("end")), ["d", "g", "s", "epoch"]).join(last, ["d", "g", "s", "epoch"], "left").select("d", "g", "s", "epoch", F.coalesce("cutoff", "end").alias("cutoff")).unionByName(quota.where("whole").select("d", "g", "s", "epoch", F.lit("g").alias("cutoff")))
    rows = [tuple(r) for r in cutoffs.collect()]
    bounds = spark.createDataFrame(rows, "__bd string, __bg string, __bs string, __be int, __bc string")
    keyed = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("__row"), "doc_id", *leaf)
    hit = keyed.join(F.broadcast(bounds), (F.col("__d") == F.col("__bd")) & (F.col("__g") == F.col("__bg")) & (F.col("__s") == F.col("__bs"))).where(_key(F.col("__be"), seed) <= F.col("__bc"))
    kept = [c for c in docs.columns if c not in ("domain", "epoch", "n_tokens")]
    return hit.select(*[F.col("__row").getField(c).alias(c) for c in kept], F.col("__d").alias("domain"), F.col("__be").alias("epoch"), n_tokens(F.col("__row").getField("text")).alias("n_tokens"))


def op1_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix(spark.read.parquet(f"{sf_dir}/documents.parquet")).select("doc_id", "epoch", "domain", "lang", "source", "n_tokens")


def _level(name: str, parent: str, keys: str, own: str, weight: str) -> str:
    """SQL of one level's split: `parent` has the budgets b of `keys`; `own` is the child's name."""
    up = f"PARTITION BY {keys}" if keys else ""
    using = f"JOIN {parent} USING ({keys})" if keys else f"CROSS JOIN {parent}"
    group = ", ".join(x for x in (keys, own) if x)
    return f"""
{name}_c AS (SELECT {group}, sum(t) * 2.0 AS cap, {weight} AS w FROM leaf GROUP BY {group}),
{name}_o AS (SELECT {name}_c.*, b,
    sum(cap) OVER ({up} ORDER BY cap / w, {own}) - cap AS before,
    sum(w) OVER ({up}) - sum(w) OVER ({up} ORDER BY cap / w, {own}) + w AS rest
  FROM {name}_c {using}),
{name}_s AS (SELECT *, cap * rest <= (b - before) * w AS full_ FROM {name}_o),
{name} AS (SELECT {group}, CASE WHEN full_ THEN cap ELSE
    (b - coalesce(sum(cap) FILTER (WHERE full_) OVER ({up}), 0)) / (sum(w) FILTER (WHERE NOT full_) OVER ({up})) * w END AS b FROM {name}_s)"""


OP1_SQL = rf"""
WITH t AS (
  SELECT doc_id, lang, source, coalesce(len(regexp_extract_all(text, '\S+')), 0) AS n,
    CASE WHEN k IS NULL OR k < 5 THEN 'crawl' WHEN k < 12 THEN 'reference' ELSE 'forum' END AS d, coalesce(lang, '(none)') AS g, coalesce(source, '(none)') AS s
  FROM (SELECT *, try_cast(nullif(regexp_extract(source, '([0-9]+)$', 1), '') AS INTEGER) AS k FROM documents)
), leaf AS (SELECT d, g, s, sum(n) AS t FROM t GROUP BY d, g, s),
root AS (SELECT 0.6::DOUBLE * sum(t)::DOUBLE AS b FROM leaf),
{_level("l1", "root", "", "d", "CASE d WHEN 'crawl' THEN 5.0 WHEN 'reference' THEN 3.0 WHEN 'forum' THEN 2.0 ELSE 1.0 END::DOUBLE")},
{_level("l2", "l1", "d", "g", "CASE g WHEN 'en' THEN 5.0 WHEN 'de' THEN 2.0 WHEN 'fr' THEN 2.0 WHEN 'es' THEN 1.0 ELSE 1.0 END::DOUBLE")},
{_level("l3", "l2", "d, g", "s", "1.0::DOUBLE")},
q AS (
  SELECT d, g, s, e, least(t, floor(b + 1e-6) - e * t) AS quota FROM l3 JOIN leaf USING (d, g, s) CROSS JOIN (SELECT unnest([0, 1]) AS e)
), r AS (
  SELECT t.*, q.e, q.quota, sum(n) OVER (PARTITION BY t.d, t.g, t.s, q.e ORDER BY md5('17|' || q.e || '|' || t.doc_id)) AS run
  FROM t JOIN q ON t.d = q.d AND t.g = q.g AND t.s = q.s AND q.quota > 0
)
SELECT doc_id, CAST(e AS INTEGER) AS epoch, d AS domain, lang, source, CAST(n AS BIGINT) AS n_tokens FROM r WHERE run <= quota
"""
