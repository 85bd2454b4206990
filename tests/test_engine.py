"""Worked examples and invariants of the index."""

from __future__ import annotations

from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import functions as F

from ivfspark.config import DELTA_ID, IndexConfig
from ivfspark.functions import vectors as V
from ivfspark.operators import clustering, hybrid, measures, search, updates
from ivfspark.catalog.common import private_index
from ivfspark.functions import vectors
from ivfspark.plans import planner, statistics
from ivfspark.plans.predicates import Leaf, match_all, match_any
from ivfspark.plans.scratch import scratch_path
from ivfspark.plans.sharing import share
from ivfspark.sources import collections, snapshots
from ivfspark.sources.index import Index, build, open_index, write_centroids, write_vectors
from ivfspark.sources.snapshots import Store

CFG = IndexConfig(target_size=50)


@pytest.fixture(scope="module")
def index(spark, sf):
    from ivfspark.plans.shipping import ship

    ship(spark)
    return build(spark, scratch_path(spark, "t"), collections.v1(spark, sf), CFG, two_level=4)


@pytest.fixture(scope="module")
def queries(spark, sf):
    return collections.v1(spark, sf).where("vec_id < 12").select(F.col("vec_id").alias("qid"), F.col("embedding").alias("qvec"))


def rows(df):
    return [tuple(r) for r in df.collect()]


# the worked figure: three centres on a plane, two of them probed, an attribute filter


@pytest.fixture
def figure(spark):
    store = Store(spark, scratch_path(spark, "figure"))
    vectors = [(0, 1, [0.2, 1.5]), (0, 2, [0.1, 1.7]), (2, 3, [0.3, 2.8]), (2, 4, [0.5, 4.5]), (1, 5, [10.0, 1.0])]
    df = spark.createDataFrame([(p, i, i, e, 0) for p, i, e in vectors], "part_id long, asset_id long, vec_id long, embedding array<float>, seq long")
    centres = clustering.Centroids(np.array([[0.0, 0], [10, 0], [0, 4]]), np.zeros(3, np.int64), "l2", np.array([2, 1, 2]))
    manifest = {
        "main": [write_vectors(store, df, 5, "main")],
        "centroids": [write_centroids(store, centres, None)],
        "delta": [],
        "tombstones": [],
        "supers": [],
        "parent": None,
        "config": CFG.as_dict(),
        "dim": 2,
        "k": 3,
        "n_main": 5,
        "n_delta": 0,
        "avg_at_build": 5 / 3,
        "last_seq": 0,
        "ledger": {},
    }
    attributes = spark.createDataFrame([(1, "foo"), (2, "bar"), (3, "foo"), (4, "bar"), (5, "foo"), (6, "foo")], "asset_id long, attribute string")
    return Index(store, snapshots.commit(store, manifest)), attributes


def test_worked_figure(spark, figure):
    index, attributes = figure
    q, foo = [0.0, 1.8], Leaf("attribute", "=", "foo")
    assert search.probe(index.centroids(), q, 2) == [0, 2]
    fused = rows(hybrid.postfilter(index, attributes, q, 2, 2, foo))
    assert [r[1] for r in fused] == [1, 3]
    assert fused[0][2] == pytest.approx(0.360555, abs=1e-6) and fused[1][2] == pytest.approx(1.044031, abs=1e-6)
    assert [r[1] for r in rows(hybrid.postfilter(index, attributes, q, 2, 2, foo, fused=False))] == [1]
    assert [r[1] for r in rows(hybrid.prefilter(index, attributes, q, 2, foo))] == [1, 3]
    new = spark.createDataFrame([(6, 6, q)], "asset_id long, vec_id long, embedding array<float>")
    grown = updates.upsert(index, new)
    assert [r[1] for r in rows(hybrid.postfilter(grown, attributes, q, 2, 2, foo))] == [6, 1]
    gone = updates.delete(grown, spark.createDataFrame([(6,)], "asset_id long"))
    assert [r[1] for r in rows(hybrid.postfilter(gone, attributes, q, 2, 2, foo))] == [1, 3]
    assert [r[1] for r in rows(hybrid.postfilter(grown, attributes, q, 2, 2, foo))] == [6, 1]  # its version is unchanged


def test_worked_clustering():
    """One dimension, centres 0 and 10, batches 1 3 9 (without penalty) and 4 8 5."""

    def run(lam, scope):
        c, v = np.array([[0.0], [10.0]]), np.zeros(2, np.int64)
        for batch, cfg in (([1, 3, 9], IndexConfig(lam=0.0)), ([4, 8, 5], IndexConfig(lam=lam, scope=scope))):
            x = np.array(batch, float)[:, None]
            labels = clustering.assign_balanced(x, c, v, cfg)
            c, v = clustering.update_centroids(c, v, *clustering._sums(x, labels, 2))
        return c.ravel().round(6).tolist(), v.tolist()

    assert run(0.0, "frozen") == ([3.25, 8.5], [4, 2])
    assert run(1.0, "frozen") == ([2.666667, 7.333333], [3, 3])
    assert run(1.0, "sequential") == ([3.25, 8.5], [4, 2])


def test_worked_growth(spark):
    from ivfspark.catalog.update_queries import growth_table

    acts = [r.action for r in growth_table(spark, 150_000, 12, 100).orderBy("epoch").collect()]
    assert acts.index("rebuild") == 8
    growth = {r.epoch: r.growth for r in growth_table(spark, 150_000, 12, 100).collect()}
    assert growth[8] == pytest.approx(0.48) and growth[9] == pytest.approx(0.54)


# clustering


def test_closed_form_equals_single_steps():
    rng = np.random.default_rng(1)
    x, c, v = rng.normal(size=(50, 6)), rng.normal(size=(4, 6)), np.array([3, 0, 7, 1])
    labels = rng.integers(0, 4, 50)
    a, na = clustering.update_centroids(c, v, *clustering._sums(x, labels, 4))
    b, nb = clustering.update_sequential(c, v, x, labels)
    assert np.allclose(a, b, atol=1e-8) and (na == nb).all()


def test_training_counts_and_seed(spark, sf):
    v = collections.v1(spark, sf)
    first = clustering.train(v, CFG)
    assert first.counts.sum() == CFG.batch * CFG.iters
    again = clustering.train(v.repartition(7), CFG)
    assert (first.centers == again.centers).all()
    other = clustering.train(v, replace(CFG, seed=7))
    assert not np.allclose(first.centers, other.centers)


def test_penalty_evens_counts(spark, sf):
    for source in (collections.v1, collections.v4):
        v = source(spark, sf)
        cfg = replace(CFG, target_size=v.count() // 10, iters=30)
        plain, even = clustering.train(v, replace(cfg, lam=0.0)), clustering.train(v, cfg)
        assert even.counts.std() <= plain.counts.std()


def test_assignment_is_nearest(index):
    got = index.main().select("part_id", "embedding").collect()
    dist = V.pairwise(np.array([r.embedding for r in got]), index.centroids().centers)
    assert [r.part_id for r in got] == dist.argmin(axis=1).tolist()
    assert index.main().count() == 500


def test_kernels_agree():
    rng = np.random.default_rng(0)
    a, b = rng.normal(size=(20, 9)), rng.normal(size=(20, 9))
    b[3] = 0
    for metric in V.METRICS:
        full = V.pairwise(a, b, metric)
        assert np.allclose(full, V.pairwise_fast(a, b, metric))
        assert (np.diag(full) == V.paired(a, b, metric)).all()
    assert V.pairwise(a, b, "cosine")[0, 3] == 1.0
    assert (V.unpack([V.pack(x) for x in a], 9) == a.astype("<f4")).all()


# search


def test_all_probes_is_exact(spark, index, queries):
    exact = rows(search.knn_exact_batch(index.live(), queries, 10))
    assert sorted(rows(search.ann_batch(index, queries, 10, index.centroids().k))) == sorted(exact)


def test_recall_grows_with_probes(index, queries):
    curve = [r.recall for r in search.recall_curve(index, queries, 10).orderBy("n").collect()]
    assert curve == sorted(curve) and curve[-1] == 1.0
    n = search.calibrate_probes(index, queries, 10, 0.9)
    assert curve[n - 1] >= 0.9 and (n == 1 or curve[n - 2] < 0.9)


def test_batches_equal_singles(index, queries):
    batch = sorted(rows(search.ann_batch(index, queries, 5, 3)))
    assert batch == sorted(rows(search.ann_batch(index, queries, 5, 3, "sql")))
    assert batch == sorted(rows(search.ann_sequential(index, queries, 5, 3)))


def test_exact_batches_of_any_size(spark, sf, queries, monkeypatch):
    v = collections.v1(spark, sf)
    whole = sorted(rows(search.knn_exact_batch(v, queries, 4)))
    monkeypatch.setattr(search, "QUERY_BLOCK", 8)
    assert sorted(rows(search.knn_exact_batch(v, queries, 4))) == whole


def test_extremes(spark, index, sf):
    q = collections.v1(spark, sf).first().embedding
    assert search.ann(index, q, 10_000, 10_000).count() == 500
    assert search.ann(index, [0.0] * 64, 5, 2).count() == 5
    one = build(spark, scratch_path(spark, "one"), collections.v1(spark, sf).where("vec_id = 0"), CFG)
    assert [r[1] for r in rows(search.ann(one, q, 3, 3))] == [0]
    same = collections.v1(spark, sf).where("vec_id = 0").crossJoin(spark.range(6)).select(F.col("id").alias("vec_id"), "embedding")
    equal = build(spark, scratch_path(spark, "equal"), same, replace(CFG, target_size=2))
    assert [r[1] for r in rows(search.ann(equal, q, 3, 3))] == [0, 1, 2]


def test_pruned_scan(index, spark, sf):
    q = collections.v1(spark, sf).first().embedding
    plan = search.ann(index, q, 5, 2)._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [In(part_id" in plan and "TakeOrderedAndProject" in plan


def test_wrong_vectors_are_refused(spark, index):
    bad = spark.createDataFrame([(1, 1, [1.0])], "asset_id long, vec_id long, embedding array<float>")
    with pytest.raises(ValueError):
        updates.upsert(index, bad)


# updates


@pytest.fixture
def fresh(spark, sf):
    return build(spark, scratch_path(spark, "u"), collections.v1(spark, sf), CFG)


def _asset(spark, sf, asset, source):
    return collections.v1(spark, sf).where(F.col("vec_id") == source).select(F.lit(asset).cast("long").alias("asset_id"), F.lit(10_000 + asset).cast("long").alias("vec_id"), "embedding")


def test_upsert_delete_flush_rebuild(spark, sf, fresh):
    q = collections.v1(spark, sf).where("vec_id = 3").first().embedding
    v1 = updates.upsert(fresh, _asset(spark, sf, 900, 3))
    assert [r[1] for r in rows(search.ann(v1, q, 2, 1))] == [3, 10_900]  # before any flush, equal distance by id
    v2 = updates.upsert(v1, _asset(spark, sf, 900, 4))
    assert v2.live().where("asset_id = 900").count() == 1
    v3 = updates.delete(v2, spark.createDataFrame([(3,), (123_456,)], "asset_id long"))
    assert 3 not in [r[1] for r in rows(search.ann(v3, q, 10, 100))]
    v4 = updates.upsert(v3, _asset(spark, sf, 3, 3))
    assert v4.live().where("asset_id = 3").count() == 1
    before = sorted(rows(v4.live().select("asset_id", "vec_id", "seq")))
    flushed = updates.flush(v4)
    assert flushed.manifest["delta"] == [] and sorted(rows(flushed.live().select("asset_id", "vec_id", "seq"))) == before
    assert flushed.live().where(F.col("part_id") == DELTA_ID).count() == 0
    rebuilt = updates.rebuild(flushed)
    assert sorted(rows(rebuilt.live().select("asset_id", "vec_id", "seq"))) == before
    assert rebuilt.manifest["tombstones"] == [] and rebuilt.main().count() == len(before)
    assert open_index(spark, fresh.store.path, 0).live().count() == 500  # time travel
    with pytest.raises(snapshots.ConcurrentWriter):
        updates.upsert(v1, _asset(spark, sf, 901, 5))  # a writer on an old version
    store = fresh.store
    store.create("t-orphan", "x")
    assert "t-orphan" in snapshots.vacuum(store, keep=1)
    assert len(snapshots.versions(store)) == 1 and open_index(spark, store.path).live().count() == len(before)


def test_replayed_batch_changes_nothing(spark, sf, fresh):
    change = _asset(spark, sf, 901, 5).select("asset_id", F.lit(7).cast("long").alias("seq"), F.lit("upsert").alias("op"), "vec_id", "embedding")
    once = updates.apply_changes(fresh, change, ("s", 0))
    assert updates.apply_changes(once, change, ("s", 0)).version == once.version
    older = change.withColumn("seq", F.lit(3).cast("long")).withColumn("vec_id", F.lit(5).cast("long"))
    late = updates.apply_changes(once, older, ("s", 1))
    assert rows(late.live().where("asset_id = 901").select("vec_id", "seq")) == [(10_901, 7)]


def test_monitor_boundary():
    health = lambda g: updates.Health(1.0, g, 0.1)
    assert updates.action(health(0.49)) == "flush" and updates.action(health(0.5)) == "flush" and updates.action(health(0.51)) == "rebuild"
    assert updates.action(health(9.0), policy="never") == "none" and updates.action(health(0.0), policy="rebuild_always") == "rebuild"
    assert search.rescale_probes(8, 100, 150) == 5 and search.rescale_probes(1, 1, 100) == 1


# predicates and plans


def test_estimates(spark):
    data = [(i, "a" if i % 4 else "b", float(i), None if i % 5 == 0 else i % 3, ["x"] if i % 2 else ["x", "y"]) for i in range(100)]
    a = spark.createDataFrame(data, "asset_id long, s string, f double, q long, tokens array<string>")
    stats = statistics.analyze(a, ["s", "f", "q"], ["tokens"], bins=4)
    est = lambda p, **o: statistics.estimate(p, stats, **o)
    assert est(Leaf("s", "=", "b")) == 25 and est(Leaf("s", "!=", "b")) == 75 and est(Leaf("s", "=", "zz")) == 0
    assert est(Leaf("q", "is null")) == 20 and est(Leaf("tokens", "match", "y")) == 50 and est(Leaf("tokens", "match", "no")) == 0
    assert est(Leaf("f", "<", 50.0)) == pytest.approx(50, abs=2) and est(Leaf("f", ">=", 0.0)) == 100
    b, y = Leaf("s", "=", "b"), Leaf("tokens", "match", "y")
    assert est(b & y) == 25 and est(b | y) == 75 and est(b | y | Leaf("q", "is not null")) == 100
    assert est(b & y, rule="independence") == pytest.approx(12.5)
    assert est(match_any("tokens", ["x", "y"])) == 100 and est(match_all("tokens", ["x", "y"])) == 50
    assert planner.choose(b, stats, 1, 25).kind == "post"  # equal shares
    assert planner.choose(b, stats, 1, 26).kind == "pre"
    assert planner.choose(b, stats, 1, 1, threshold=0.9).kind == "pre"
    assert a.where((~(b & y)).to_column()).count() == 75
    assert a.where(Leaf("q", "!=", 1).to_column()).count() == a.where("q <> 1").count()
    assert statistics.q_error(10, 5) == 2 and statistics.true_selectivity(a, b) == 0.25
    assert len(statistics.histogram_sketch(a, "f", 4)) == 5


def test_missing_attributes_do_not_qualify(spark, small):
    from ivfspark.catalog.common import attributes

    index = build(spark, scratch_path(spark, "m"), collections.v1(spark, small), CFG)
    q = collections.v1(spark, small).first().embedding
    attrs = attributes(spark, small)
    assert attrs.count() == 200
    everything = Leaf("n_chars", ">=", 0)
    assert hybrid.prefilter(index, attrs, q, 1000, everything).count() == 200
    nothing = Leaf("lang", "=", "xx")
    assert hybrid.prefilter(index, attrs, q, 5, nothing).count() == 0 and hybrid.postfilter(index, attrs, q, 5, 2, nothing).count() == 0


def test_recall_measure(spark):
    t = spark.createDataFrame([(1, 1), (1, 2), (2, 5)], "qid long, vec_id long")
    a = spark.createDataFrame([(1, 2), (1, 9)], "qid long, vec_id long")
    assert sorted(rows(measures.recall_at_k(a, t, 10))) == [(1, 0.5), (2, 0.0)]
    m = measures.memory_model(150_000, 512, replace(CFG, batch=60), 1500)
    assert m["full_kmeans_bytes"] / m["train_bytes"] > 4


def test_servers_answer_alike(spark, sf, index):
    from ivfspark.catalog.update_queries import changed_index
    from ivfspark.operators import serving

    q = collections.v1(spark, sf).where("vec_id = 1").first().embedding
    for one in (index, changed_index(spark, sf)):
        want = [(r.vec_id, r.dist) for r in search.ann(one, q, 10, 3).collect()]
        assert serving.DiskServer(one).search(q, 10, 3) == want
        assert serving.MemoryServer(one).search(q, 10, 3) == want
    assert serving.cold(index, q, 10, 3) == [(r.vec_id, r.dist) for r in search.ann(index, q, 10, 3).collect()]


def test_replacing_vectors_is_no_growth(spark, sf):
    """Fifty of 500 vectors are replaced six times: as many are live throughout, and nothing is rebuilt."""
    index = private_index(spark, sf, CFG)
    v = collections.v1(spark, sf).where("vec_id < 50").withColumn("asset_id", F.col("vec_id"))
    for _ in range(6):
        index, act = updates.maintain(updates.upsert(index, v), 0.5)
        assert act == "flush" and index.manifest["n_main"] == 500 and updates.monitor(index).growth == pytest.approx(0)
    assert index.live().count() == 500 and index.centroids().members.sum() == 500


def test_probes_by_second_level(spark, sf, index, queries, monkeypatch):
    """Through super centres the same results at a large share, and most neighbours at a smaller one."""
    two = build(spark, scratch_path(spark, "two"), collections.v1(spark, sf), CFG, two_level=3)
    whole = sorted(rows(search.ann_batch(two, queries, 5, 4)))
    monkeypatch.setattr(search, "TWO_LEVEL_CENTRES", 1)
    monkeypatch.setattr(search, "SUPER_SHARE", 1.0)
    assert sorted(rows(search.ann_batch(two, queries, 5, 4))) == whole
    x, centers = np.random.default_rng(0).normal(size=(300, 8)), np.random.default_rng(1).normal(size=(64, 8))
    tops, labels = clustering.train_super(clustering.Centroids(centers, np.zeros(64, np.int64)), 8)
    below = clustering.members_below(labels, len(tops))
    near = clustering.nearest_below(x, centers, tops, below, "l2")
    assert (near == clustering.nearest(x, centers, "l2")).mean() > 0.9


def test_batches_of_any_size(spark, index, queries, monkeypatch):
    whole = sorted(rows(search.ann_batch(index, queries, 5, 3)))
    monkeypatch.setattr(search, "QUERY_BLOCK", 3)
    assert sorted(rows(search.ann_batch(index, queries, 5, 3))) == whole


def test_broadcasts_are_checked(spark):
    with pytest.raises(ValueError, match="too many to broadcast"):
        share(spark, (np.zeros(100), {1: np.zeros(50)}), "centres", 1000)


def test_attributes_follow_their_vectors(spark, sf):
    """Attributes stored by partition give the same filtered results before and after flushes and rebuilds, from fewer rows."""
    attrs = collections.table(spark, sf, "documents").where("doc_id < 700").select(F.col("doc_id").alias("asset_id"), "lang", "n_chars")
    index = statistics.attach(private_index(spark, sf, CFG), attrs, ["lang"])
    assert statistics.stored_statistics(index).columns["lang"].n == attrs.count()
    q, p = [0.1] * 64, Leaf("lang", "=", "en")
    moved = collections.v1(spark, sf).where("vec_id < 30").select((F.col("vec_id") + 600).alias("asset_id"), (F.col("vec_id") + 5000).alias("vec_id"), "embedding")
    grown = updates.upsert(index, moved)
    flushed = updates.flush(grown)
    for one in (index, grown, flushed, updates.rebuild(flushed)):
        own = one.attributes()
        assert own.dropDuplicates(["asset_id"]).count() == attrs.count()
        asked = spark.createDataFrame([(1, q)], "qid long, qvec array<double>")
        for n in (2, 100):
            want = rows(hybrid.postfilter(one, attrs, q, 7, n, p))
            assert rows(hybrid.postfilter(one, own, q, 7, n, p)) == want
            assert [r[1:] for r in rows(hybrid.hybrid_batch(one, own, asked, 7, n, {1: p}))] == want
    parts = search.probe(index.centroids(), q, 2)
    plan = index.attributes(parts)._jdf.queryExecution().executedPlan().toString()
    assert "part_id" in plan.split("PushedFilters")[1] and index.attributes(parts).count() < attrs.count()


def test_range_join_finds_all_pairs(spark, sf):
    base = collections.v1(spark, sf).where("vec_id < 200")
    near = base.where("vec_id < 40").select((F.col("vec_id") + 1000).alias("vec_id"), F.transform("embedding", lambda x: (x * 1.05 + 0.004).cast("float")).alias("embedding"))
    every = base.unionByName(near)
    for metric, radius in (("l2", 0.9), ("cosine", 0.3)):
        one = build(spark, scratch_path(spark, "near"), every, replace(CFG, metric=metric))
        a, b = every.select(F.col("vec_id").alias("a"), F.col("embedding").alias("x")), every.select(F.col("vec_id").alias("b"), F.col("embedding").alias("y"))
        want = {(r.a, r.b) for r in a.crossJoin(b).where("a < b").where(vectors.distance(F.col("x"), F.col("y"), metric) <= radius).select("a", "b").collect()}
        assert {(r.a, r.b) for r in search.range_join(one, radius).collect()} == want and len(want) > 30
