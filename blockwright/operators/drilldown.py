"""Drill-down: the contiguous partition of an ordered attribute that breaks fewest pairs.

Only ends of labelled pairs matter. If the gap between two neighbouring ends is cut at all,
it may as well be cut at both its sides, as every cut inside breaks the same pairs; so one
decides which gaps to cut, and a run of ends left uncut must fit the cost bound. With
V(i) = least over j of (pairs leaving the run i..j) + V(j+1), from right to left and with a
segment tree over j, that takes O((n + pairs) log n), however many values the attribute has.
Gaps that hold too many records are then sliced freely, and neighbours that fit together joined.

Sizes come from one aggregate: records by end and by gap. A null is no value of the order
and is left to `interval_hash`, which gives it a block of its own.
"""

from __future__ import annotations

import bisect
import datetime as dt
from itertools import combinations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashes import interval_hash, order_key
from ..functions.scratch import cut
from ..model import BlockingSpec, HashFn, Interval
from .sizes import canonical_pairs


#: Values and places are held in one whole number, value first, so that the least one is that of least value and, among equals, of last place.
_STEP = 1 << 32
_NONE = 1 << 100


class _Least:
    """Segment tree over whole numbers: add to a range, least value of a range with its last place; all in O(log n), bottom up."""

    def __init__(self, n: int):
        self.n = 1 << max(1, (n - 1).bit_length())
        self.low = [_NONE] * (2 * self.n)
        self.wait = [0] * self.n

    def _apply(self, p: int, v: int) -> None:
        self.low[p] += v
        if p < self.n:
            self.wait[p] += v

    def _push(self, p: int) -> None:
        """What waits above leaf p goes down to it."""
        for h in range(p.bit_length() - 1, 0, -1):
            i = p >> h
            if v := self.wait[i]:
                self._apply(2 * i, v)
                self._apply(2 * i + 1, v)
                self.wait[i] = 0

    def _pull(self, p: int) -> None:
        low, wait = self.low, self.wait
        while p > 1:
            p >>= 1
            a, b = low[2 * p], low[2 * p + 1]
            low[p] = (a if a < b else b) + wait[p]

    def set(self, i: int, value: int) -> None:
        p = i + self.n
        self._push(p)
        self.low[p] = value * _STEP - i
        self._pull(p)

    def add(self, lo: int, hi: int, value: int) -> None:
        """Add to the places from lo to before hi."""
        if lo >= hi:
            return
        a, b, v = lo + self.n, hi + self.n, value * _STEP
        first, last = a, b - 1
        while a < b:
            if a & 1:
                self._apply(a, v)
                a += 1
            if b & 1:
                b -= 1
                self._apply(b, v)
            a >>= 1
            b >>= 1
        self._pull(first)
        self._pull(last)

    def least(self, lo: int, hi: int) -> tuple[int, int]:
        """(value, place) over [lo, hi)."""
        a, b = lo + self.n, hi + self.n
        self._push(a)
        self._push(b - 1)
        best = _NONE
        while a < b:
            if a & 1:
                best = min(best, self.low[a])
                a += 1
            if b & 1:
                b -= 1
                best = min(best, self.low[b])
            a >>= 1
            b >>= 1
        value = -(-best // _STEP)
        return value, value * _STEP - best


def _times(pairs: list[tuple] | dict[tuple, int]):
    """((low, high), times) of pairs that are listed, or counted by their values."""
    return pairs.items() if isinstance(pairs, dict) else ((p, 1) for p in pairs)


def solve(ends: list, pairs: list[tuple] | dict[tuple, int], reach: list[int]) -> tuple[int, list[tuple[int, int]]]:
    """(violations, runs): the best runs (i, j) of sorted `ends`; reach[i] is the furthest end that fits with i (at least i).

    pairs are (low, high) values among the ends, with low < high, or how many pairs have them.
    """
    k = len(ends)
    if not k:
        return 0, []
    at = {e: i for i, e in enumerate(ends)}
    starting: list[list[tuple[int, int]]] = [[] for _ in range(k)]
    for (a, b), n in _times(pairs):
        if a != b:
            starting[at[a]].append((at[b], n))
    tree = _Least(k)
    value = [0] * (k + 1)
    choice = [0] * k
    for i in range(k - 1, -1, -1):
        # a run that ends at j leaves V(j+1), plus the pairs that begin inside and end beyond j
        tree.set(i, value[i + 1])
        for r, n in starting[i]:
            tree.add(i, r, n)
        value[i], choice[i] = tree.least(i, reach[i] + 1)
    runs, i = [], 0
    while i < k:
        runs.append((i, choice[i]))
        i = choice[i] + 1
    return value[0], runs


def solve_full(counts: list[tuple], pairs: list[tuple], cap: float) -> tuple[int, list[int]]:
    """(violations, first place of each interval), by the recurrence over all values of the domain.

    The least loss from a value on is the least, over the cuts worth trying, of the pairs that
    begin in the interval and end beyond it, plus the least loss from the cut on. Only values
    that some chain of cuts reaches are solved, and what no pair touches costs nothing. counts:
    sorted (value, records). For comparison: `solve` gives the same from the ends alone.
    """
    values = [v for v, _ in counts]
    m = len(values)
    pairs = [p for p in pairs if p[0] != p[1]]
    reach = reach_of([n for _, n in counts], [0] * max(0, m - 1), cap)
    at = {v: i for i, v in enumerate(values)}
    spans = sorted((at[a], at[b]) for a, b in pairs)
    cuts = sorted({c for a, b in spans for c in (a, a + 1, b, b + 1)})
    found, todo = set(), [0]
    nexts: dict[int, list[int]] = {}
    while todo:
        i = todo.pop()
        if i in found or i >= m:
            continue
        found.add(i)
        top = reach[i] + 1
        nexts[i] = cuts[bisect.bisect_right(cuts, i) : bisect.bisect_right(cuts, top)]
        if not nexts[i] or nexts[i][-1] != top:
            nexts[i] = [*nexts[i], top]
        todo += nexts[i]
    value, choice = {m: 0}, {}
    lows = [a for a, _ in spans]
    for i in sorted(found, reverse=True):
        for c in nexts[i]:
            lost = sum(b >= c for _, b in spans[bisect.bisect_left(lows, i) : bisect.bisect_left(lows, c)])
            if i not in value or lost + value[c] < value[i]:
                value[i], choice[i] = lost + value[c], c
    starts, i = [], 0
    while i < m:
        starts.append(i)
        i = choice[i]
    return value[0], starts


def reach_of(at_end: list[float], in_gap: list[float], cap: float) -> list[int]:
    """Furthest end that fits with each end; at_end[i] records at end i, in_gap[i] strictly between i and i+1."""
    k = len(at_end)
    out, j, total = [], -1, 0.0
    for i in range(k):
        if j < i:
            j, total = i, at_end[i]
        while j + 1 < k and total + in_gap[j] + at_end[j + 1] <= cap:
            total += in_gap[j] + at_end[j + 1]
            j += 1
        out.append(j)
        total -= at_end[i] + (in_gap[i] if i < j else 0)
    return out


def order_values(rows: list) -> list:
    return sorted({r for r in rows if r is not None})


def slot_counts(df: DataFrame, key: Column, ends: list) -> tuple[list[int], list[int], list]:
    """(records at each end, records in each gap incl. before the first and after the last, least value of each gap): one tiny shuffle.

    Ends are at most twice the pairs; the literal array is searched by binary search in a
    vectorised function only where it is long, else by a flat CASE.
    """
    spark = df.sparkSession
    counted = df.select(key.alias("k"))
    if len(ends) <= 64:
        case = F.when(F.col("k").isNull(), -1)
        for i, e in enumerate(ends):
            case = case.when(F.col("k") < F.lit(e), 2 * i).when(F.col("k") == F.lit(e), 2 * i + 1)
        rows = counted.select(case.otherwise(2 * len(ends)).alias("slot"), "k").groupBy("slot").agg(F.count("*"), F.min("k")).collect()
    else:
        # distinct values first: a partial aggregate, then the search of the few that are left
        held = spark.sparkContext.broadcast(ends)

        rows = counted.groupBy("k").agg(F.count("*").alias("n")).select(_slot(held)("k").alias("slot"), "n", "k").groupBy("slot").agg(F.sum("n"), F.min("k")).collect()
    got = {r[0]: r[1] for r in rows}
    first = {r[0]: r[2] for r in rows}
    k = len(ends)
    return [got.get(2 * i + 1, 0) for i in range(k)], [got.get(2 * i, 0) for i in range(k + 1)], [first.get(2 * i) for i in range(k + 1)]


def _slot(held):
    """Vectorised search of sorted ends: 2i + 1 at end i, 2i in the gap before it, -1 for a null."""

    @F.pandas_udf("long")
    def slot(k: pd.Series) -> pd.Series:
        e, there = held.value, k.notna().to_numpy()
        kind = "datetime64[us]" if isinstance(e[0], (dt.date, dt.datetime)) else None if isinstance(e[0], (int, float)) else object
        e = np.array(e, kind)
        x = np.array(k[there].tolist(), e.dtype)
        i = np.searchsorted(e, x)
        out = np.full(len(k), -1, np.int64)
        out[there] = 2 * i + ((i < len(e)) & (e[np.minimum(i, len(e) - 1)] == x))
        return pd.Series(out)

    return slot


def _slices(df: DataFrame, key: Column, ends: list, gaps: list[int], cap: int) -> dict[int, list[tuple]]:
    """For each gap of more than `cap` records, (value, records) runs that each start at their value and hold at most `cap` records, if no value alone has more.

    All such gaps at once: their distinct values are counted, range-sorted and summed up along
    the order; a value belongs to the half cap its sum begins in, and a value of over half a
    cap stands alone. So a run has no more than two halves, and the driver sees a few rows for
    each cap of records, whatever the number of values.
    """
    big = {i: n for i, n in enumerate(gaps) if n > cap}
    if not big:
        return {}
    spark = df.sparkSession
    counted = df.select(key.alias("k")).where(F.col("k").isNotNull()).groupBy("k").agg(F.count("*").alias("n"))
    slotted = counted.withColumn("slot", _slot(spark.sparkContext.broadcast(ends))("k")) if ends else counted.withColumn("slot", F.lit(0).cast("bigint"))
    # the records of the gaps before each, in the order of values
    before, base = 0, []
    for i, n in big.items():
        base.append((2 * i, before))
        before += n
    inside = slotted.join(F.broadcast(spark.createDataFrame(base, "slot bigint, base bigint")), "slot")
    half = max(1, cap // 2)
    ranged = inside.repartitionByRange("k").sortWithinPartitions("k").select("slot", "base", "k", "n", (F.col("n") > half).cast("int").alias("alone"), F.spark_partition_id().alias("part"))
    ranged = cut(ranged, "ranged")
    done, alone, offsets = 0, 0, []
    for r in ranged.groupBy("part").agg(F.sum("n").alias("n"), F.sum("alone").alias("alone")).orderBy("part").collect():
        offsets.append((r["part"], done, alone))
        done, alone = done + r["n"], alone + r["alone"]
    up = Window.partitionBy("part").orderBy("k").rowsBetween(Window.unboundedPreceding, -1)
    placed = ranged.join(F.broadcast(spark.createDataFrame(offsets, "part int, done bigint, heavy bigint")), "part")
    start = F.col("done") + F.coalesce(F.sum("n").over(up), F.lit(0)) - F.col("base")
    heavy = F.col("heavy") + F.coalesce(F.sum("alone").over(up), F.lit(0))
    runs = placed.select("slot", "k", "n", "alone", F.floor(start / half).alias("s"), heavy.alias("h")).groupBy("slot", "s", "h", "alone").agg(F.min("k").alias("k"), F.sum("n").alias("n")).orderBy("k").collect()
    out: dict[int, list[tuple]] = {}
    for r in runs:
        out.setdefault(r["slot"] // 2, []).append((r["k"], r["n"]))
    return {i: _joined(x, cap) for i, x in out.items()}


def _joined(starts: list[tuple], cap: float) -> list[tuple]:
    """Neighbouring (start, records) joined as far as they fit."""
    out: list[list] = []
    for s, n in starts:
        if out and out[-1][1] + n <= cap:
            out[-1][1] += n
        else:
            out.append([s, n])
    return [tuple(x) for x in out]


def tile(starts: list[tuple], cap: float) -> list[Interval]:
    """Half-open intervals that cover the whole order, from (first value, records)."""
    out = []
    for i, (s, n) in enumerate(starts):
        hi = starts[i + 1][0] if i + 1 < len(starts) else None
        out.append(Interval(None if i == 0 else s, hi, i > 0, False, int(n), n > cap))
    return out or [Interval(None, None, False, False, 0)]


#: Distinct values up to which `solver="full"` may bring a domain to the driver.
FULL_VALUES = 1_000_000


def drilldown(df: DataFrame, key: Column, pairs: list[tuple] | dict[tuple, int], cap: int, cost="count", solver: str = "endpoints") -> list[Interval]:
    """Optimal intervals of the ordered column `key` under a bound on each.

    pairs: values (low, high) of labelled pairs, in any order, or how many pairs have them; nulls are ignored.
    cost: "count", records in an interval; "width", the difference of its ends (numbers and
    dates); or a function of (low, high) that does not fall when the interval grows.
    solver: "endpoints" needs only the ends of pairs; "full" runs the recurrence over all values
    of the domain (cost "count" alone, at most `FULL_VALUES` of them), for comparison.
    """
    counted: dict[tuple, int] = {}
    for x, n in _times(pairs):
        if None not in x:
            x = min(x), max(x)
            counted[x] = counted.get(x, 0) + n
    pairs = counted
    if solver == "full":
        if cost != "count":
            raise ValueError("the full solver counts records")
        pairs = [x for x, n in pairs.items() for _ in range(n)]
        rows = df.select(key.alias("k")).where("k is not null").groupBy("k").agg(F.count("*").alias("n")).orderBy("k").limit(FULL_VALUES + 1).collect()
        if len(rows) > FULL_VALUES:
            raise ValueError('too many values for the driver: use solver="endpoints"')
        counts = [(r["k"], r["n"]) for r in rows]
        _, starts = solve_full(counts, pairs, cap)
        return tile([(counts[a][0], sum(n for _, n in counts[a:b])) for a, b in zip(starts, [*starts[1:], len(counts)])], cap)
    ends = order_values([x for p in pairs for x in p])
    if cost != "count":
        width = (lambda a, b: (b - a).days if isinstance(a, (dt.date, dt.datetime)) else b - a) if cost == "width" else cost
        reach = []
        for i in range(len(ends)):
            lo, hi = i, len(ends) - 1
            while lo < hi:
                m = (lo + hi + 1) // 2
                lo, hi = (m, hi) if width(ends[i], ends[m]) <= cap else (lo, m - 1)
            reach.append(lo)
        _, runs = solve(ends, pairs, reach)
        return tile([(ends[i], 0) for i, _ in runs], float("inf"))
    at_end, gaps, first = slot_counts(df, key, ends)
    _, runs = solve(ends, pairs, reach_of(at_end, gaps[1:-1], cap) if ends else [])
    starts: list[tuple] = []
    sliced = _slices(df, key, ends, gaps, cap)

    def gap(i: int) -> None:
        """Records before end i (after the last one for i = len(ends)), sliced."""
        if 0 < gaps[i] <= cap:
            starts.append((first[i], gaps[i]))
        elif gaps[i]:
            starts.extend(sliced[i])

    gap(0)
    for i, j in runs:
        starts.append((ends[i], sum(at_end[i : j + 1]) + sum(gaps[i + 1 : j + 1])))
        gap(j + 1)
    return tile(_joined(starts, cap), cap)


def broken(partition: list[Interval], pairs: list[tuple] | dict[tuple, int]) -> int:
    """Pairs (with values on both sides) that the partition splits."""
    ups = [x.hi for x in partition if x.hi is not None]
    at = lambda v: bisect.bisect_right(ups, v)
    return sum(n for (a, b), n in _times(pairs) if a is not None and b is not None and at(a) != at(b))


def is_dcc(partition: list[Interval]) -> bool:
    """Whether intervals are disjoint, contiguous and cover everything."""
    if not partition or partition[0].lo is not None or partition[-1].hi is not None:
        return False
    return all(a.hi == b.lo and a.hi_incl != b.lo_incl for a, b in zip(partition, partition[1:]))


def equi_width(lo, hi, width) -> list[Interval]:
    """Intervals of one width, counted from `lo`: numbers, or dates with a width in days."""
    step = dt.timedelta(days=width) if isinstance(lo, (dt.date, dt.datetime)) else width
    cuts, x = [], lo + step
    while x <= hi:
        cuts.append(x)
        x += step
    return tile([(None, 0)] + [(c, 0) for c in cuts], float("inf"))


def equi_depth(counts: list[tuple], cap: int) -> list[Interval]:
    """Intervals filled up to `cap` records from the left; counts: sorted (value, records)."""
    return tile(_joined(list(counts), cap), cap)


def exhaustive_drilldown(counts: list[tuple], pairs: list[tuple], cap: int) -> int:
    """Least number of broken pairs over all partitions of at most 12 values, by trying every set of cuts."""
    values = [v for v, _ in counts]
    if len(values) > 12:
        raise ValueError("exhaustive drill-down is for at most 12 values")
    best = None
    for r in range(len(values)):
        for cuts in combinations(range(1, len(values)), r):
            edges_ = [0, *cuts, len(values)]
            if all(sum(n for _, n in counts[a:b]) <= cap or b - a == 1 for a, b in zip(edges_, edges_[1:])):
                of = {v: i for i, (a, b) in enumerate(zip(edges_, edges_[1:])) for v in values[a:b]}
                lost = sum(of[a] != of[b] for a, b in pairs)
                best = lost if best is None else min(best, lost)
    return best


def overlapping(pairs: list[tuple], cost, cap) -> list[tuple]:
    """Without disjointness: one interval for each pair whose own cost fits."""
    return sorted({(min(p), max(p)) for p in pairs if None not in p and cost(min(p), max(p)) <= cap})


def overlapping_by_count(df: DataFrame, key: Column, pairs: list[tuple], cap: int) -> list[tuple]:
    """(low, high, records) of the pairs' own intervals that hold at most `cap` records: prefix sums over ends and gaps, one pass."""
    pairs = [p for p in pairs if None not in p]
    ends = order_values([x for p in pairs for x in p])
    if not ends:
        return []
    at_end, gaps, _ = slot_counts(df, key, ends)
    # records below each end, and up to and with it
    up = np.cumsum([n for g, e in zip(gaps, at_end) for n in (g, e)])
    place = {e: i for i, e in enumerate(ends)}

    def count(a, b):
        return int(up[2 * place[b] + 1] - up[2 * place[a]])

    return [(a, b, count(a, b)) for a, b in overlapping(pairs, count, cap)]


def _valued(df: DataFrame, id_col: str, key: Column, pairs: DataFrame) -> DataFrame:
    p = canonical_pairs(pairs)
    ids = p.select(F.explode_outer(F.array("l_id", "r_id")).alias("__pid")).distinct()
    v = df.join(ids, F.col(id_col) == F.col("__pid"), "left_semi").select(F.col(id_col).alias("id"), key.alias("k"))
    l, r = (v.select(F.col("id").alias(f"{s}_id"), F.col("k").alias(f"{s}k")) for s in "lr")
    return p.join(l, "l_id").join(r, "r_id")


def pair_values(df: DataFrame, id_col: str, key: Column, pairs: DataFrame) -> list[tuple]:
    """Values of both records of each labelled pair."""
    return [(x["lk"], x["rk"]) for x in _valued(df, id_col, key, pairs).orderBy("l_id", "r_id").select("lk", "rk").collect()]


def counted_values(df: DataFrame, id_col: str, key: Column, pairs: DataFrame) -> dict[tuple, int]:
    """How many labelled pairs have each two (low, high) values: pairs are counted before they reach the driver, and equal copies are one row. Pairs with a null are left out."""
    v = _valued(df, id_col, key, pairs).where("lk is not null and rk is not null").groupBy(F.least("lk", "rk").alias("low"), F.greatest("lk", "rk").alias("high")).agg(F.count("*").alias("n"))
    v = cut(v, "values")
    return {(x["low"], x["high"]): x["n"] for x in v.coalesce(v.count() // VALUES_AT_ONCE + 1).toLocalIterator()}


#: Counted values of pairs that come to the driver at once.
VALUES_AT_ONCE = 200_000
#: Orders of text attributes besides that of the value itself: by the first and by the last token.
TEXT_ORDERS = ("identity", "first_token", "last_token")


def auto_library(df: DataFrame, spec: BlockingSpec, pairs: DataFrame, cap: int, kinds: tuple[str, ...] = ("int", "float", "date", "text", "token_text"), orders: tuple[str, ...] = TEXT_ORDERS) -> list[HashFn]:
    """An interval function, learnt for this cap, for every ordered attribute; text attributes get one for each order."""
    out = []
    for a in spec.attributes:
        if a.kind not in kinds:
            continue
        for order in orders if a.kind in ("text", "token_text") else (None,):
            key = order_key(a, order)
            out.append(interval_hash(a.name, drilldown(df, key, counted_values(df, spec.id_col, key, pairs), cap), order))
    return out
