"""What failed on tables larger than those of the other tests."""

import dataclasses
import hashlib

import numpy as np
import pytest
from pyspark.sql import functions as F

import blockwright.queries as q
from blockwright import workloads as w
from blockwright.model import BlockingConfig
from blockwright.operators import assign, cost, dedup, drilldown, evaluate, learn, rollup, sizes

SF = "/root/testdata/sf0.001"


def test_packed_blocks_fit_on_a_table_the_example_tree_does_not_know(spark):
    r = q.rollup_zero_benefit_parts(spark, "/root/testdata/sf0.1").first()
    assert r.asDict() == {"least_blocks": 500, "all_fit": True, "records": 30_000, "enough": True}
    a = spark.range(1000).select("id", F.when(F.col("id") < 905, "big").when(F.col("id") < 910, F.lit(None).cast("string")).otherwise("small").alias("block_key"))
    s = assign.sliced(a, 100)
    assert sorted(x["n"] for x in sizes.block_sizes(s).collect()) == [5, 5, 90] + [100] * 9
    assert {x["id"] for x in s.collect()} == set(range(1000)) and {x["block_key"] for x in s.where("id >= 910").collect()} == {"small"}


@pytest.fixture(scope="module")
def suppliers(spark, tmp_path_factory):
    at = str(tmp_path_factory.mktemp("suppliers"))
    spark.range(20_001).select(F.col("id").alias("s_suppkey")).write.parquet(f"{at}/supplier.parquet")
    return at


def test_all_pairs_of_many_suppliers(spark, suppliers):
    p = q.all_pairs_suppliers(spark, suppliers)
    assert p.where("l_id = 0").count() == 20_000 and p.where("r_id = 20000").agg(F.count_distinct("l_id")).first()[0] == 20_000
    few = spark.range(300).unionByName(spark.createDataFrame([(None,)], "id bigint"))
    got = dedup.all_pairs(few, "id", limit=None).collect()
    assert len(got) == 300 * 299 // 2 and {tuple(r) for r in got} == {(a, b) for a in range(300) for b in range(a + 1, 300)}
    with pytest.raises(ValueError):
        dedup.all_pairs(few, "id", limit=300)


def test_cost_of_a_block_for_every_pair(spark, suppliers):
    assert tuple(q.pair_blocks_cost(spark, suppliers).first()) == (2, 20_001 * 20_000, 20_001 * 20_000 + 4)
    few = spark.range(30)
    assert cost.pair_blocks_cost(few).collect() == cost.overlap_cost(dedup.pair_blocks(few, "id")).collect()


@pytest.mark.parametrize("safeguard", [True, False])
def test_rollup_in_tasks_merges_like_the_driver(spark, monkeypatch, safeguard):
    p = w.part_feeds(spark, SF)
    a, pairs = assign.random_blocks(p, "rec_id", p.count(), 5, strict=True), w.ent_pairs(p)
    # pairs of neighbours besides, so that components have several blocks
    pairs = pairs.unionByName(p.select(F.col("rec_id").alias("l_id"), (F.col("rec_id") + 14).alias("r_id")).where("l_id % 3 = 0"))
    want = sorted(map(tuple, rollup.rollup(a, pairs, 12, safeguard=safeguard).collect()))
    monkeypatch.setattr(rollup, "DRIVER_EDGES", 0)
    assert want and sorted(map(tuple, rollup.rollup(a, pairs, 12, safeguard=safeguard).collect())) == want


def test_pairs_reach_the_driver_by_kind(spark):
    p = w.part_feeds(spark, SF)
    f = sizes.features(p, w.PART_SPEC, w.ent_pairs(p), q.P_LIBRARY, cap=8)
    assert f.pair_values is None and len(f.same.table) <= len(f.same) == 100
    kept = f.same.table[f.same.kind].sum(0)
    assert (f.same.sum(0) == kept).all() and (f.same[:, [0, 1]].all(1) == f.same.table[f.same.kind][:, :2].all(1)).all()
    # a value that is light here is looked up among the pairs
    h = next(i for i, x in enumerate(f.library) if x.name == "size.identity")
    light = p.where("p_size IS NOT NULL").groupBy("p_size").count().where("count between 2 and 8").orderBy("p_size").first()["p_size"]
    own = {r["rec_id"] for r in p.where(F.col("p_size") == light).collect()}
    got = f.same_light(list(range(100)), h, f"v{light}")
    assert list(got) == [a in own and b in own for a, b in f.pair_ids]


def test_pairs_of_equal_values_reach_the_driver_once(spark):
    df = spark.range(600).select("id", F.when(F.col("id") < 590, F.concat(F.lit("v"), F.col("id") % 3)).alias("k"))
    pairs = df.alias("a").crossJoin(df.alias("b")).where("a.id < b.id and a.id % 7 = b.id % 7").select(F.col("a.id").alias("l_id"), F.col("b.id").alias("r_id"))
    listed, counted = (f(df, "id", F.col("k"), pairs) for f in (drilldown.pair_values, drilldown.counted_values))
    listed = [p for p in listed if None not in p]
    assert sum(counted.values()) == len(listed) > 20_000 and len(counted) == 6
    for cap in (150, 250, 450):
        a, b = (drilldown.drilldown(df, F.col("k"), p, cap) for p in (listed, counted))
        assert a == b and drilldown.broken(a, listed) == drilldown.broken(a, counted)


def test_pairs_stay_in_a_file_and_trees_are_learnt_by_kind(spark, monkeypatch):
    p = w.part_feeds(spark, SF)
    # pairs of neighbours besides, which random splits and lookups separate
    pairs = w.ent_pairs(p).unionByName(p.select(F.col("rec_id").alias("l_id"), (F.col("rec_id") + 4).alias("r_id")).join(p.select(F.col("rec_id").alias("r_id")), "r_id").select("l_id", "r_id"))
    for x in (sizes, evaluate):
        monkeypatch.setattr(x, "pieces", lambda n, size=0: (slice(i, min(n, i + 7)) for i in range(0, n, 7)))
    monkeypatch.setattr(sizes, "PAIRS_AT_ONCE", 40)
    f = sizes.features(p, w.PART_SPEC, pairs, q.P_LIBRARY, cap=8)
    n = len(f.pair_ids)
    assert isinstance(f.pair_ids, np.memmap) and isinstance(f.mix, np.memmap) and n > 150
    assert [tuple(x) for x in f.pair_ids] == sorted(map(tuple, sizes.canonical_pairs(pairs).collect()))
    # folds in the order of md5, as its definition says
    order = sorted(range(n), key=lambda i: (hashlib.md5(f"42|{f.pair_ids[i, 0]}|{f.pair_ids[i, 1]}".encode()).digest(), *f.pair_ids[i]))
    of = evaluate.folds(f)
    assert [of[i] for i in order] == [k for k in range(5) for _ in range(n // 5 + (k < n % 5))]
    part = f.pick(np.arange(0, n, 2)).pick(np.arange(1, n // 2))
    assert (part.pair_ids[:] == f.pair_ids[np.arange(2, n - 1, 2)][: len(part.mix)]).all() and len(part.mix) == len(part.same)
    for learner in learn.LEARNERS.values():
        t = learner(f, BlockingConfig(8, scorer="optimistic"))
        a = assign.assign_blocks(p, t, w.PART_SPEC)
        kept = {(r["l_id"], r["r_id"]): r["kept"] for r in cost.together(a, pairs).collect()}
        assert [bool(x) for x in learn.covered(f, t)] == [bool(kept.get(tuple(x))) for x in f.pair_ids] and learn.hits(f, t) == sum(map(bool, kept.values()))
        # as many rows as pairs give the same tree
        single = dataclasses.replace(f, same=f.same.table[f.same.kind], pair_code=f.pair_code.table[f.pair_code.kind], memo={})
        assert learner(single, BlockingConfig(8, scorer="optimistic")).to_json() == t.to_json()
