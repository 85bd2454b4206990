"""One test for each defect that a reviewer found."""

from __future__ import annotations

from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import functions as F

from ivfspark.catalog import common
from ivfspark.config import IndexConfig
from ivfspark.functions import vectors
from ivfspark.operators import clustering, hybrid, search, updates
from ivfspark.plans.predicates import Leaf
from ivfspark.plans.scratch import scratch_path
from ivfspark.sources import collections
from ivfspark.sources.index import build

CFG = IndexConfig(target_size=50)


def rows(df):
    return [tuple(r) for r in df.collect()]


@pytest.mark.parametrize("metric", ["l2", "cosine", "ip"])
def test_widened_search_is_exact(spark, sf, metric):
    """k rows of the first partitions are not the k nearest."""
    index = build(spark, scratch_path(spark, "wide"), collections.v2(spark, sf), replace(CFG, metric=metric))
    attributes = collections.v2(spark, sf).select(F.col("vec_id").alias("asset_id"), (F.col("vec_id") % 3).alias("n_chars"))
    for vec_id in (0, 7, 33):
        q = common.query_vector(spark, sf, vec_id, "v2")
        for p in (Leaf("n_chars", "<", 2), Leaf("n_chars", "<", 0)):
            assert rows(hybrid.postfilter(index, attributes, q, 10, 1, p, widen=True)) == rows(hybrid.prefilter(index, attributes, q, 10, p))


def _by_expressions(rows, key, terms, dim):
    """Vectors of hashed terms as expressions define them."""
    number = F.conv(F.substring(F.md5(F.col("term").cast("binary")), 1, 8), 16, 10).cast("long") % dim
    counts = rows.select(key, F.explode(terms).alias("term")).groupBy(key, number.alias("b")).agg(F.count("*").alias("n"))
    out = {}
    for r in counts.collect():
        out.setdefault(r[0], np.zeros(dim))[r.b] = r.n
    return {i: (x / np.sqrt((x * x).sum())).astype(np.float32).tolist() for i, x in out.items()}


ODD = ["", None, "ab", "abc", "Été été ÉTÉ × ÷ ß Ÿ", "\U0001f600\U0001f601 x y\nz_z İI", "a-b " * 3000, "\r\n\t"]


def test_hashed_vectors_equal_expressions(spark):
    df = spark.createDataFrame(list(enumerate(ODD)), "id long, text string")
    text = F.coalesce("text", F.lit(""))
    grams = F.when(F.length(text) >= 3, F.transform(F.sequence(F.lit(1), F.length(text) - 2), lambda i: F.substring(text, i, F.lit(3))))
    for count, terms, dim in ((collections.count_tokens, collections.tokens(F.col("text")), 256), (collections.count_trigrams, grams, 960)):
        got = {r.vec_id: r.embedding for r in collections.hashed(df, "id", "text", count, dim).collect()}
        assert got == _by_expressions(df, "id", terms, dim)


def test_hashed_vectors_move_no_rows(spark, sf):
    for make in (collections.v3, collections.v6, collections.v7):
        assert "Exchange" not in make(spark, sf)._jdf.queryExecution().executedPlan().toString()


@pytest.mark.parametrize("metric,radius", [("l2", 0.9), ("cosine", 0.3)])
def test_range_join_holds_no_pairs(spark, sf, metric, radius, monkeypatch):
    """Runs and pieces of partitions give the same links as one run, and no join deals out pairs of vectors."""
    base = collections.v1(spark, sf)
    near = base.where("vec_id < 60").select((F.col("vec_id") + 1000).alias("vec_id"), F.transform("embedding", lambda x: (x * 1.05 + 0.004).cast("float")).alias("embedding"))
    index = build(spark, scratch_path(spark, "runs"), base.unionByName(near), replace(CFG, metric=metric))
    monkeypatch.setattr(search, "JOIN_BYTES", 1 << 24, raising=False)
    want = sorted(rows(search.range_join(index, radius)))
    for most in (1 << 15, 1 << 13):
        monkeypatch.setattr(search, "JOIN_BYTES", most)
        found = search.range_join(index, radius)
        assert sorted(rows(found)) == want and len(want) > 30 and all(a < b for a, b in want)
        assert "Join" not in found._jdf.queryExecution().executedPlan().toString()


@pytest.mark.parametrize("metric", ["l2", "cosine"])
def test_nearest_by_groups(metric):
    """The same centre as among all, with copies of centres and far from them all, and few comparisons."""
    rng = np.random.default_rng(1)
    centers = rng.normal(size=(40, 6))[rng.integers(0, 40, 3000)] + rng.normal(size=(3000, 6)) / 20
    centers[1000:1500] = centers[:500]
    x = np.concatenate([centers[::7], rng.normal(size=(300, 6)), centers[:50] * 30])
    groups = clustering.grouped(centers, metric)
    assert groups and len(groups[0]) <= 2500
    assert (clustering.nearest_grouped(x, centers, groups, metric) == clustering.nearest(x, centers, metric)).all()


def test_frozen_choice_by_products():
    rng = np.random.default_rng(2)
    centers, x = rng.normal(size=(300, 8)), rng.normal(size=(500, 8))
    centers[200:] = centers[:100]
    for counts in (np.zeros(300, np.int64), rng.integers(0, 9, 300)):
        for penalty in ("none", "multiplicative"):
            cfg = replace(CFG, penalty=penalty)
            want = clustering.penalised(vectors.pairwise(x, centers), counts.astype(float), cfg).argmin(axis=1)
            assert (clustering.assign_balanced(x, centers, counts, cfg) == want).all()


@pytest.mark.parametrize("metric", ["l2", "cosine"])
def test_exact_through_index_and_ranks(spark, sf, metric, monkeypatch):
    """Exact neighbours through balls of partitions, and their probe ranks without a row a query and centre."""
    index = build(spark, scratch_path(spark, "exact"), collections.v2(spark, sf), replace(CFG, metric=metric))
    asked = common.query_batch(spark, sf, "v2")
    truth = search.knn_exact_indexed(index, asked, 7)
    assert sorted(rows(truth)) == sorted(rows(search.knn_exact_batch(index.live(), asked, 7, metric)))
    plain = truth.join(index.live().select("vec_id", "part_id"), "vec_id").join(search.probes_of(asked, index.centroids(), 10_000), ["qid", "part_id"])
    monkeypatch.setattr(search, "probes_of", None)
    ranks = search.neighbour_probe_ranks(index, asked, 7, truth)
    assert sorted(rows(ranks)) == sorted(rows(plain.select("qid", "vec_id", "probe_rank")))


def test_written_batches_hold_one_block(spark, sf, monkeypatch):
    """Answers of many blocks come from files, not from one plan with a block of queries in each branch."""
    monkeypatch.setattr(search, "QUERY_BLOCK", 16)
    index = build(spark, scratch_path(spark, "written"), collections.v1(spark, sf), CFG)
    asked = common.query_batch(spark, sf).unionByName(collections.v1(spark, sf).where("vec_id % 5 = 1").select(F.col("vec_id").alias("qid"), F.col("embedding").alias("qvec")))
    found = search.ann_batch_written(index, asked, 2, 3)
    assert "Union" not in found._jdf.queryExecution().executedPlan().toString()
    assert sorted(rows(found)) == sorted(rows(search.ann_batch(index, asked, 2, 3)))


def test_rescaling_reads_orders(spark, small):
    from ivfspark.catalog import search_queries

    found = search_queries.rescaled_probes(spark, small).orderBy("year").collect()
    assert found[-1].n_rows == collections.table(spark, small, "orders").count() and found[0].n == 8


def test_sequential_jobs_share_their_code(spark, sf, monkeypatch):
    """One at a time and as exact as before, also with a delta, without an expression that holds the query."""
    index = build(spark, scratch_path(spark, "alone"), collections.v1(spark, sf), CFG)
    index = updates.upsert(index, collections.v1(spark, sf).where("vec_id < 9").withColumn("asset_id", F.col("vec_id") + 5).withColumn("vec_id", F.col("vec_id") + 5000))
    asked = common.query_batch(spark, sf).where("qid < 150")
    want = [(r.qid, x["rank"], x.vec_id, x.dist) for r in asked.collect() for x in search.ann(index, r.qvec, 5, 3).collect()]
    monkeypatch.setattr(search, "literal", None)
    assert sorted(rows(search.ann_sequential(index, asked, 5, 3))) == sorted(want)


def test_results_do_not_depend_on_the_number_of_centres(spark, sf, monkeypatch):
    """Beyond any number of centres a vector goes to its nearest one, and a query to its nearest ones."""
    from ivfspark.sources import index as index_module

    cfg, v = replace(CFG, target_size=5), collections.v2(spark, sf)
    extra = v.where("vec_id < 90").withColumn("asset_id", F.col("vec_id") + 5000)
    placed = lambda i: sorted(rows(i.live().select("asset_id", "part_id")))
    whole = build(spark, scratch_path(spark, "whole"), v, cfg, two_level=4)
    want, flushed = placed(whole), placed(updates.flush(updates.upsert(whole, extra)))
    monkeypatch.setattr(index_module, "ASSIGN_CENTRES", 1, raising=False)
    monkeypatch.setattr(clustering, "ASSIGN_SUPERS", 1)
    monkeypatch.setattr(search, "TWO_LEVEL_CENTRES", 1)
    index = build(spark, scratch_path(spark, "large"), v, cfg, two_level=4)
    assert placed(index) == want
    assert placed(updates.flush(updates.upsert(index, extra))) == flushed
    x = np.array([r.qvec for r in common.query_batch(spark, sf, "v2").collect()], np.float64)
    for metric in ("l2", "cosine", "ip"):
        for n in (1, 7, 60, 1000):
            own = index.centroids().centers
            assert (search.probe_matrix(x, own, metric, n, index.super_centroids()) == search.probe_matrix(x, own, metric, n)).all()


def test_growth_runs_every_policy_to_the_last_row(spark, small, monkeypatch):
    """All epochs of all policies, single searches of the whole query batch, and recall against exact neighbours."""
    from ivfspark.catalog import update_queries as u

    whole, asked, timed, latency = u.grown, [], [], u._latency
    monkeypatch.setattr(u, "_latency", lambda index, found, n: timed.append(len(found)) or latency(index, found, n))
    one = whole(spark, small, "never", 1, True).first()
    assert timed == [u.GROWTH_QUERIES] * 2 and one.n_delta == 45 and 0.85 < one.recall <= 1
    monkeypatch.setattr(u, "grown", lambda spark, sf_dir, policy, epochs, measured=False: asked.append((policy, epochs)) or whole(spark, small, "never", 1, True))
    u.growth_recall(spark, small)
    assert asked == [(policy, 17) for policy in ("auto", "rebuild_always", "never")]


def test_growth_truth_is_exact(spark, sf):
    from ivfspark.catalog import update_queries as u

    v = collections.v1(spark, sf).withColumn("place", F.col("vec_id"))
    bounds, asked = [200, 290, 290, 400], common.query_batch(spark, sf)
    found = sorted(rows(u.growth_truth(v, asked, bounds, 7)))
    want = [(e, r.qid, r.vec_id) for e, hi in enumerate(bounds) if e for r in search.knn_exact_batch(v.where(F.col("place") < hi), asked, 7).collect()]
    assert found == sorted(want)


def test_changes_do_not_keep_all_shuffle_partitions(spark, sf):
    """An upsert and a flush of few rows run few tasks, however many partitions a shuffle has."""

    def tasks():
        core = spark.sparkContext._jsc.sc()
        core.listenerBus().waitUntilEmpty()
        stages, n = core.statusStore().stageList(None, False, False, spark.sparkContext._gateway.new_array(spark.sparkContext._jvm.double, 0), None).iterator(), 0
        while stages.hasNext():
            n += stages.next().numCompleteTasks()
        return n

    v = collections.v1(spark, sf)
    index = build(spark, scratch_path(spark, "few"), v, CFG)
    held = spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.shuffle.partitions", "150")
    try:
        before = tasks()
        index = updates.flush(updates.upsert(index, v.where("vec_id < 90").withColumn("asset_id", F.col("vec_id") + 5000)))
        assert tasks() - before < 150 and index.manifest["n_main"] == 590
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", held)


def test_training_holds_a_tile_of_distances(spark, sf, monkeypatch):
    """Samples on the driver meet the centres in tiles, with the same centres as at once, in either scope."""
    v, sizes, fast, slow = collections.v1(spark, sf), [], clustering.pairwise_fast, clustering.pairwise
    for name, kernel in (("pairwise_fast", fast), ("pairwise", slow)):
        monkeypatch.setattr(clustering, name, lambda a, b, metric="l2", kernel=kernel: sizes.append(len(a) * len(b)) or kernel(a, b, metric))
    for scope, penalty in (("frozen", "multiplicative"), ("sequential", "multiplicative"), ("sequential", "cap")):
        cfg = replace(CFG, batch=300, iters=3, target_size=5, scope=scope, penalty=penalty)
        whole = clustering.train(v, cfg, exec_mode="local")
        sizes.clear()
        monkeypatch.setattr(clustering, "TILE", 2000)
        tiled = clustering.train(v, cfg, exec_mode="local")
        monkeypatch.setattr(clustering, "TILE", 1 << 22)
        assert sizes and max(sizes) <= 2000
        assert (tiled.centers == whole.centers).all() and (tiled.counts == whole.counts).all()


def test_large_batches_train_on_executors(spark, sf, monkeypatch):
    """A batch of many distances leaves the driver, with the same centres."""
    steps, step, v, cfg = [], clustering._distributed_step, collections.v1(spark, sf), replace(CFG, batch=300, iters=2, target_size=5)
    monkeypatch.setattr(clustering, "_distributed_step", lambda *a: steps.append(a) or step(*a))
    want = clustering.train(v, cfg)
    assert not steps
    monkeypatch.setattr(clustering, "LOCAL_PAIRS", 1000, raising=False)
    found = clustering.train(v, cfg)
    assert len(steps) == 2 and (found.centers == want.centers).all() and (found.counts == want.counts).all()


def test_a_task_gives_its_own_k_nearest():
    """Whatever number of record batches a task reads, k rows of it reach the driver; ties go to the smaller id."""
    import pyarrow as pa

    x = np.array([[1.0, 0.0], [0.0, 1.0], [3.0, 0.0], [0.5, 0.0], [2.0, 0.0], [0.0, 2.0]], np.float32)
    whole = pa.RecordBatch.from_arrays([pa.array([0] * 6), pa.array([5, 4, 3, 2, 1, 0]), pa.array(x.tolist(), pa.list_(pa.float32()))], ["part_id", "vec_id", "embedding"])
    found = [r for b in search._alone([0.0, 0.0], 3, "l2")(iter([whole.slice(0, 2), whole.slice(2, 0), whole.slice(2, 4)])) for r in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True)]
    assert found == [(2, 0.5), (4, 1.0), (5, 1.0)]
    assert sum(b.num_rows for b in search._alone([0.0, 0.0], 3, "l2")(iter([]))) == 0
