"""The engine on the small tables: invariants, determinism, adaptation, sinks and streams."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

import blockwright.queries as q
from blockwright import workloads as w
from blockwright.functions import hashes as h
from blockwright.model import Attribute, BlockingConfig, BlockingSpec, BlockTree, Node
from blockwright.operators import assign, components, cost, dedup, drilldown, evaluate, learn, rollup, sizes
from blockwright.sources import io
from blockwright.streaming import blocks as stream_

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def parts(spark):
    p = w.part_feeds(spark, SF).cache()
    return p, w.ent_pairs(p).cache()


@pytest.fixture(scope="module")
def feats(parts):
    return sizes.features(parts[0], w.PART_SPEC, parts[1], h.default_library(w.PART_SPEC), cap=8)


def test_signatures_count_like_group_by(parts, feats):
    assert feats.n == parts[0].count()
    hashed = sizes.project(parts[0], w.PART_SPEC, feats.library)
    for i in (0, 7, 20):
        want = {r[0]: r[1] for r in hashed.groupBy(f"h{i}").count().collect() if r[1] > 8}
        got = np.bincount(feats.codes[:, i], feats.count)
        assert {v: got[j + 1] for j, v in enumerate(feats.values[i])} == want


@pytest.mark.parametrize("name", list(learn.LEARNERS))
def test_trees_partition_and_keep_the_cap(spark, parts, feats, name):
    p, pairs = parts
    t = learn.LEARNERS[name](feats, BlockingConfig(20, scorer="best"))
    a = assign.assign_blocks(p, t, w.PART_SPEC).cache()
    assert a.count() == p.count() == a.select("id").distinct().count()
    if name in ("block_tree", "level_tree") and all(n.parts == 1 for n in t.root.walk()):
        assert cost.cost_summary(sizes.block_sizes(a)).first()["max_block"] <= 20
    assert cost.recall(a, pairs).first()["recall"] == pytest.approx(learn.recall(feats, t), abs=1e-5)


def test_routing_by_join_equals_routing_by_case(parts, feats, monkeypatch):
    t = learn.learn_block_tree(feats, BlockingConfig(8))
    one = set(map(tuple, assign.assign_blocks(parts[0], t, w.PART_SPEC).collect()))
    monkeypatch.setattr(assign, "CASE_LIMIT", 0)
    assert set(map(tuple, assign.assign_blocks(parts[0], t, w.PART_SPEC).collect())) == one


def test_same_result_whatever_the_partitions(spark, parts, feats):
    t = learn.learn_block_tree(feats, BlockingConfig(8))
    got = []
    before = spark.conf.get("spark.sql.shuffle.partitions")
    for n in ("1", "7", "64"):
        spark.conf.set("spark.sql.shuffle.partitions", n)
        f = sizes.features(parts[0].repartition(int(n) % 5 + 1), w.PART_SPEC, parts[1], h.default_library(w.PART_SPEC), cap=8)
        got.append(learn.learn_block_tree(f, BlockingConfig(8)).to_json())
    spark.conf.set("spark.sql.shuffle.partitions", before)
    assert got == [t.to_json()] * 3


def test_null_is_a_value(spark):
    spec = BlockingSpec("id", (Attribute("a", "text", "a"), Attribute("b", "int", "b")))
    df = spark.createDataFrame([(1, None, 1), (2, None, 1), (3, "x", 2), (4, "", None)], "id long, a string, b int")
    t = BlockTree("block_tree", Node(0, 4, 0, h.identity("a"), {"n": Node(1, 2, 0, h.identity("b"))}))
    assert dict(map(tuple, assign.assign_blocks(df, t, spec).collect())) == {1: "1|v1", 2: "1|v1", 3: "0|vx", 4: "0|v"}
    every = h.default_library(spec) + [h.top_chars("a", 3), h.longest_token("a"), h.first_token("a"), h.last_token("a"), h.soundex("a")]
    assert all(v is not None for r in sizes.project(df, spec, every).collect() for v in r)


def test_edges_of_the_inputs(spark, parts):
    p, pairs = parts
    none = pairs.limit(0)
    f = sizes.features(p, w.PART_SPEC, none, h.default_library(w.PART_SPEC), cap=8)
    assert learn.recall(f, learn.learn_block_tree(f, BlockingConfig(8))) == 1.0
    assert not learn.learn_rounds(f, BlockingConfig(8)).rounds
    odd = pairs.unionByName(spark.createDataFrame([(2, 2), (5, 4), (4, 5), (-1, 4), (None, 3)], "l_id long, r_id long"))
    f = sizes.features(p, w.PART_SPEC, odd, h.default_library(w.PART_SPEC), cap=8)
    assert f.missing == 1 and (f.pair_ids[:, 0] < f.pair_ids[:, 1]).all()
    empty = sizes.features(p.limit(0), w.PART_SPEC, none, h.default_library(w.PART_SPEC), cap=8)
    assert learn.learn_block_tree(empty, BlockingConfig(8)).root.hash is None
    big = learn.learn_block_tree(f, BlockingConfig(10**6))
    assert big.height == 0 and assign.assign_blocks(p, big, w.PART_SPEC).select("block_key").distinct().count() == 1


def test_adaptation_keeps_the_cap(spark, parts, feats):
    t = learn.learn_block_tree(feats, BlockingConfig(8))
    for cap in (30, 60):
        cut = assign.refine_to(parts[0], t, w.PART_SPEC, cap)
        a = assign.assign_blocks(parts[0], cut, w.PART_SPEC)
        assert sizes.block_sizes(a).agg(F.max("n")).first()[0] <= cap and cut.height <= t.height


def test_rounds_union_equals_rounds_and_pairs_are_unique(spark, parts, feats):
    plan = learn.learn_rounds(feats, BlockingConfig(20), "chain")
    assert plan.rounds
    a, b = (set(map(tuple, assign.assign_rounds(parts[0], plan, w.PART_SPEC, m).collect())) for m in ("union", "rounds"))
    assert a == b
    got = [tuple(r)[:2] for r in dedup.candidate_pairs_rounds(assign.round_keys(parts[0], plan, w.PART_SPEC)).collect()]
    by: dict = {}
    for i, r, k in a:
        by.setdefault((r, k), []).append(i)
    want = {(min(x, y), max(x, y)) for ids in by.values() for x in ids for y in ids if x != y}
    assert len(got) == len(set(got)) and set(got) == want


def test_rollup_strategies(spark, parts, feats):
    p, pairs = parts
    a = assign.assign_blocks(p, learn.learn_single(feats, BlockingConfig(20)), w.PART_SPEC).cache()
    before = cost.recall(a, pairs).first()["split"]
    for strategy in ("density", "matching"):
        m = rollup.rollup(a, pairs, 20, strategy=strategy)
        check = evaluate.check_rollup(a, m, 20).first()
        after = a.join(m, "block_key", "left").select("id", F.coalesce("merged_key", "block_key").alias("block_key"))
        assert check["fits"] and cost.recall(after, pairs).first()["split"] <= before


def test_drilldown_on_dates(spark):
    o = w.table(spark, SF, "orders")
    key = F.to_date("o_orderdate")
    pv = drilldown.pair_values(o, "o_orderkey", key, w.order_pairs(o))
    last = None
    for cap in (30, 75, 300):
        part = drilldown.drilldown(o, key, pv, cap)
        assert drilldown.is_dcc(part) and all(x.n <= cap or x.infeasible for x in part) and sum(x.n for x in part) == o.count()
        lost = drilldown.broken(part, pv)
        assert last is None or lost <= last
        last = lost
    spec = BlockingSpec("o_orderkey", (Attribute("day", "date", "CAST(o_orderdate AS DATE)"),))
    sizes_ = o.groupBy(h.column(h.interval_hash("day", part), spec)).count().collect()
    assert sorted(r[1] for r in sizes_) == sorted(x.n for x in part if x.n)


def test_components_against_union_find(spark):
    rnd = random.Random(8)
    e = [(rnd.randrange(300), rnd.randrange(300)) for _ in range(220)] + [(i, i + 1) for i in range(1000, 1060)] + [(5, 5), (None, 3)]
    got = dict(map(tuple, components.connected_components(spark.createDataFrame(e, "src long, dst long")).collect()))
    parent = {x: x for p in e if None not in p for x in p}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in e:
        if None not in (a, b):
            a, b = root(a), root(b)
            parent[max(a, b)] = min(a, b)
    assert got == {x: root(x) for x in parent}


def test_bounded_join_is_the_join(spark):
    l = spark.createDataFrame([(i % 3 if i < 90 else i, i) for i in range(120)], "k long, x long")
    r = spark.createDataFrame([(k, y) for k in (0, 1, 2, 95) for y in "ab"], "k long, y string")
    got = sorted(map(tuple, dedup.bounded_join(l, r, "k", 10).select("k", "x", "y").collect()))
    assert got == sorted(map(tuple, l.join(r, "k").select("k", "x", "y").collect()))


def test_overlap_cost_by_hand(spark):
    four = spark.range(4).withColumnRenamed("id", "rec_id")
    assert cost.overlap_cost(dedup.pair_blocks(four, "rec_id")).first()["overlap_cost"] == 16
    one = four.select(F.col("rec_id").alias("id"), F.lit(0).alias("round"), F.lit("b").alias("block_key"))
    assert cost.overlap_cost(one).first()["overlap_cost"] == 20


def test_sinks_and_plans(spark, parts, feats, tmp_path):
    t = learn.learn_block_tree(feats, BlockingConfig(20))
    a = assign.assign_blocks(parts[0], t, w.PART_SPEC)
    io.save_blocks(a, str(tmp_path / "blocks"), buckets=8)
    key = a.first()["block_key"]
    assert io.load_blocks(spark, str(tmp_path / "blocks")).count() == a.count()
    assert io.load_blocks(spark, str(tmp_path / "blocks"), [key], 8).count() == a.where(F.col("block_key") == key).count()
    io.save_plan(spark, t, str(tmp_path / "plan"))
    assert io.load_plan(spark, str(tmp_path / "plan")) == t
    with pytest.raises(ValueError):
        io.validate(parts[0].unionByName(parts[0].limit(1)), w.PART_SPEC)


def test_stream_equals_batch(spark, tmp_path):
    e = w.table(spark, SF, "events")
    e.repartition(3).write.parquet(str(tmp_path / "in"))
    s = stream_.assign(stream_.stream(spark, str(tmp_path / "in"), e.schema), q.EVENT_TREE, stream_.EVENT_SPEC)
    run = s.select("event_id", "block_key").writeStream.format("memory").queryName("blocked").option("checkpointLocation", str(tmp_path / "cp")).trigger(availableNow=True).start()
    run.awaitTermination(120)
    want = set(map(tuple, stream_.assign(e, q.EVENT_TREE, stream_.EVENT_SPEC).select("event_id", "block_key").collect()))
    assert set(map(tuple, spark.table("blocked").collect())) == want


def test_plan_of_assignment_has_no_shuffle_and_prunes(spark):
    a = assign.assign_blocks(w.table(spark, SF, "documents"), q.frozen("block_tree"), w.DOC_SPEC)
    plan = a._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan and "Python" not in plan and "*(" in plan


def test_queries_have_names_and_sql():
    import __spark_entry__ as entry

    assert set(entry.oracle_sql()) <= set(entry.queries())


@pytest.mark.parametrize("name", ["tree_assign_parts", "score_root_expected", "block_tree_assign", "drilldown_month", "rollup_first_merge", "cost_summary", "hash_bucket_int"])
def test_against_sql(spark, name):
    duckdb = pytest.importorskip("duckdb")
    import glob
    import os

    c = duckdb.connect()
    for p in glob.glob(f"{SF}/*.parquet"):
        c.sql(f"create view {os.path.basename(p)[:-8]} as select * from '{p}'")
    want = c.sql(q.ORACLES[name]).df()
    got = q.QUERIES[name](spark, SF).toPandas()
    cols = sorted(want.columns)
    assert cols == sorted(got.columns)
    same = [x[cols].astype(str).sort_values(cols).values.tolist() for x in (got, want)]
    assert same[0] == same[1]


def test_trends_of_the_first_experiment(spark):
    # 4,432 pairs; the 182 of sf0.01 leave 36 to a fold, where functions of more parameters fit chance
    caps = [25, 50, 125]
    library = h.default_library(w.DOC_SPEC, without=("longest_token", "top_chars"))
    f, _ = q.doc_features(spark, "/root/testdata/sf0.1", (0.0025,), library)
    rows = evaluate.cross_validate(f, "documents", caps, scorers=("best",))
    mean = lambda a, c: np.mean([r[5] for r in rows if r[1] == a and r[3] == c])
    for cap in caps:
        assert mean("block_tree", cap) >= mean("level_tree", cap) - 0.02
        assert mean("block_tree", cap) > mean("chain", cap) - 0.02 and mean("chain", cap) > mean("random", cap)
    rounds = evaluate.cross_validate(f, "documents", caps, algorithms=("block_tree",), scorers=("best",), rounds=True)
    gain = [np.mean([r[5] for r in rounds if r[3] == cap]) - mean("block_tree", cap) for cap in caps]
    assert min(gain) > -0.005 and gain[0] >= gain[-1]


def test_document_pairs_are_whole_whatever_the_frequency_of_their_runs(spark):
    rnd = random.Random(4)
    word = lambda n: ["".join(rnd.choices("abcdefgh", k=7)) for _ in range(n)]
    a, b = word(30), word(24)
    # more equal texts, and more texts with a long passage in common, than any cap on candidates lets through
    texts = [" ".join(a)] * 105 + [" ".join(b + word(6)) for _ in range(110)] + [" ".join(word(30)) for _ in range(20)] + ["one", "ONE ", "", None]
    runs = lambda t: {tuple(x[i : i + 5]) for x in [t.strip().lower().split()] for i in range(max(1, len(x) - 4))}
    sets = {i: runs(t) for i, t in enumerate(texts) if t is not None}
    j = {(x, y): round(len(sets[x] & sets[y]) / len(sets[x] | sets[y]), 6) for x in sets for y in sets if x < y}
    got = {(r["l_id"], r["r_id"]): (r["jaccard"], r["exact"]) for r in w.doc_pairs(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()}
    assert got == {k: (v, texts[k[0]] == texts[k[1]]) for k, v in j.items() if v >= 0.5} and len(got) > 105 * 104 // 2 + 110 * 109 // 2


def test_benchmark_items_are_linked_by_any_run_and_short_ones_whole(spark):
    word = [f"w{i}" for i in range(40)]
    items = [(0, " ".join(word[:20])), (1, "a short item"), (2, "never"), (3, ""), (4, " ".join(word[20:32]))]
    texts = ["x " + " ".join(word[12:20]), " ".join([*word[:8], "edited", *word[9:12]]), "that is a\n short  item too", " ".join(word[13:20]), " ".join(word[24:32]) + " y", "", None]
    got = w.benchmark_links(spark.createDataFrame(items, "item_id long, text string"), spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()
    assert sorted(map(tuple, got)) == [(0, 0), (0, 1), (1, 2), (4, 4)]
