"""Building and searching: vector functions, clustering, exact and approximate search, batches."""

from __future__ import annotations

from dataclasses import replace

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ivfspark import oracles as O
from ivfspark.catalog.common import CONFIG, EVERY, K, PROBES, Q0, SUPER_SIZE, calibrated, query_batch, query_vector, rounded, standard_index
from ivfspark.functions import vectors as V
from ivfspark.operators import clustering, measures, search
from ivfspark.operators.clustering import Centroids
from ivfspark.sources import collections
from ivfspark.sources.collections import table

QUERIES_BY_KEY: dict = {}
SQL: dict[str, str] = {}


def query(fn):
    QUERIES_BY_KEY[fn.__name__] = fn
    return fn


def _centroid_rows(spark: SparkSession, c: Centroids, values: bool = True) -> DataFrame:
    rows = [(i, j + 1, float(x), int(n)) for i, (row, n) in enumerate(zip(c.centers, c.counts, strict=True)) for j, x in enumerate(row)]
    return rounded(spark.createDataFrame(rows, "part_id long, dim int, value double, received long"), "value")


def _centroid_sql(cte: str, source: str, count: str = "v") -> str:
    return f"{cte} SELECT part_id, dim::INT AS dim, round(c[dim], 6) AS value, {count}::BIGINT AS received FROM (SELECT *, unnest(range(1, len(c) + 1)) AS dim FROM {source})"


def _pairs(spark, sf_dir, metric):
    """The stated queries against all vectors, by expressions."""
    a = collections.v1(spark, sf_dir)
    b = query_batch(spark, sf_dir).select(F.col("qid").alias("b_id"), F.col("qvec").alias("eb"))
    dist = V.distance(F.col("embedding"), F.col("eb"), metric)
    return rounded(a.crossJoin(b).select(F.col("vec_id").alias("a_id"), "b_id", dist.alias("dist")), "dist")


@query
def pairwise_l2(spark, sf_dir):
    return _pairs(spark, sf_dir, "l2")


@query
def pairwise_cosine(spark, sf_dir):
    return _pairs(spark, sf_dir, "cosine")


for _m in ("l2", "cosine"):
    SQL[f"pairwise_{_m}"] = f"WITH x AS ({O.V1}) SELECT a.vec_id AS a_id, b.vec_id AS b_id, round({O.distance('a.e', 'b.e', _m)}, 6) AS dist FROM x a, x b WHERE b.vec_id % {EVERY} = 0"


@query
def vector_functions(spark, sf_dir):
    q = V.literal(query_vector(spark, sf_dir))
    e = F.col("embedding")
    d = V.doubles(e)
    total = F.aggregate(d, F.lit(0.0), lambda s, x: s + x)
    rows = collections.v1(spark, sf_dir).select(
        "vec_id",
        V.norm(e).alias("norm"),
        V.dot(e, q).alias("dot0"),
        V.l2(e, q).alias("l2_0"),
        V.cosine(e, q).alias("cos_0"),
        (total / F.size(e)).alias("mean_elem"),
        F.array_max(d).alias("max_elem"),
        V.norm(V.add(e, V.scale(e, 2.0))).alias("norm3"),
        V.norm(V.normalise(V.scale(e, 5.0))).alias("norm_unit"),
    )
    return rounded(rows, *rows.columns[1:])


SQL["vector_functions"] = f"""WITH x AS ({O.V1}), q AS (SELECT e AS q FROM x WHERE vec_id = 0)
SELECT vec_id, round(sqrt({O.dot('e', 'e')}), 6) AS norm, round({O.dot('e', 'q')}, 6) AS dot0, round({O.l2('e', 'q')}, 6) AS l2_0,
  round({O.cosine('e', 'q')}, 6) AS cos_0, round(list_sum(e) / len(e), 6) AS mean_elem, round(list_max(e), 6) AS max_elem,
  round(3 * sqrt({O.dot('e', 'e')}), 6) AS norm3, CASE WHEN {O.dot('e', 'e')} = 0 THEN 0.0 ELSE 1.0 END AS norm_unit FROM x, q"""


def _exact(spark, sf_dir, source, metric):
    q = query_vector(spark, sf_dir, 0, source)
    return rounded(search.knn_exact(collections.COLLECTIONS[source](spark, sf_dir), q, K, metric), "dist")


@query
def knn_exact_l2(spark, sf_dir):
    return _exact(spark, sf_dir, "v2", "l2")


@query
def knn_exact_cosine(spark, sf_dir):
    return _exact(spark, sf_dir, "v1", "cosine")


@query
def knn_exact_ip(spark, sf_dir):
    return _exact(spark, sf_dir, "v2", "ip")


def _exact_sql(source: str, metric: str, offset: int = 0) -> str:
    return f"""WITH x AS ({source}), t AS (SELECT vec_id, {O.distance('e', Q0, metric)} AS d FROM x)
SELECT (row_number() OVER (ORDER BY d, vec_id) - {offset})::INT AS rank, vec_id, round(d, 6) AS dist FROM t QUALIFY rank BETWEEN 1 AND {K}"""


SQL |= {"knn_exact_l2": _exact_sql(O.V2, "l2"), "knn_exact_cosine": _exact_sql(O.V1, "cosine"), "knn_exact_ip": _exact_sql(O.V2, "ip")}


@query
def knn_exact_batch(spark, sf_dir):
    return rounded(search.knn_exact_batch(collections.v1(spark, sf_dir), query_batch(spark, sf_dir), K), "dist")


SQL["knn_exact_batch"] = f"""WITH x AS ({O.V1}) SELECT q.vec_id AS qid, row_number() OVER (PARTITION BY q.vec_id ORDER BY {O.l2('x.e', 'q.e')}, x.vec_id)::INT AS rank,
  x.vec_id, round({O.l2('x.e', 'q.e')}, 6) AS dist FROM x, x q WHERE q.vec_id % {EVERY} = 0 QUALIFY rank <= {K}"""


@query
def topk_merge_two_phase(spark, sf_dir):
    """Heaps of single tasks, merged: the k nearest of every range of ids, then of all."""
    q = V.literal(query_vector(spark, sf_dir))
    rows = collections.v1(spark, sf_dir).select((F.col("vec_id") % 8).alias("qid"), "vec_id", V.l2(F.col("embedding"), q).alias("dist"))
    partial = search.top_k_per_query(rows, K)
    return rounded(search._ranked(partial, K), "dist")


SQL["topk_merge_two_phase"] = _exact_sql(O.V1, "l2")


@query
def topk_page2(spark, sf_dir):
    q = V.literal(query_vector(spark, sf_dir))
    rows = collections.v1(spark, sf_dir).select("vec_id", V.l2(F.col("embedding"), q).alias("dist"))
    page = rows.orderBy("dist", "vec_id").offset(K).limit(K)
    return rounded(search._ranked(page, K), "dist")


SQL["topk_page2"] = _exact_sql(O.V1, "l2", K)


@query
def range_search(spark, sf_dir):
    return rounded(search.range_search(collections.v1(spark, sf_dir), query_batch(spark, sf_dir), 1.2), "dist")


SQL["range_search"] = f"WITH x AS ({O.V1}) SELECT q.vec_id AS qid, x.vec_id, round({O.l2('x.e', 'q.e')}, 6) AS dist FROM x, x q WHERE q.vec_id % {EVERY} = 0 AND {O.l2('x.e', 'q.e')} <= 1.2"


@query
def index_meta(spark, sf_dir):
    m = standard_index(spark, sf_dir).manifest
    return spark.createDataFrame([(m["n_main"], m["k"], m["dim"], m["config"]["target_size"])], "n long, k long, dim int, target_size int")


SQL["index_meta"] = "SELECT count(*) AS n, greatest(1, count(*) // 50) AS k, max(len(embedding))::INT AS dim, 50 AS target_size FROM embeddings"


@query
def kmeans_seed(spark, sf_dir):
    v = collections.v1(spark, sf_dir)
    return clustering.seeds(v, clustering.partition_count(v.count(), 50), 42).select("part_id", "vec_id")


SQL["kmeans_seed"] = "SELECT row_number() OVER (ORDER BY md5('42:seed:' || vec_id), vec_id) - 1 AS part_id, vec_id FROM embeddings QUALIFY part_id < (SELECT greatest(1, count(*) // 50) FROM embeddings)"


@query
def minibatch_sample(spark, sf_dir):
    return clustering.minibatches(collections.v1(spark, sf_dir), 64, 6, 42).select("iter", "vec_id")


SQL["minibatch_sample"] = """SELECT iter::INT AS iter, vec_id FROM (SELECT vec_id, unnest(range(1, 7)) AS iter FROM embeddings)
QUALIFY row_number() OVER (PARTITION BY iter ORDER BY md5('42:batch:' || iter || ':' || vec_id), vec_id) <= 64"""


@query
def minibatch_one_pass(spark, sf_dir):
    return clustering.minibatches(collections.v1(spark, sf_dir), 64, 6, 42, "one_pass").select("iter", "vec_id")


SQL["minibatch_one_pass"] = """SELECT iter::INT AS iter, vec_id FROM (SELECT vec_id, unnest(range(1, 7)) AS iter FROM embeddings)
WHERE ('0x' || substr(md5('42:batch:' || iter || ':' || vec_id), 1, 8))::BIGINT < floor(64 / (SELECT count(*) FROM embeddings) * 4294967296)"""


def _second_batch(spark, sf_dir, cfg):
    """Centres and counts after one iteration, and the second batch's rows."""
    v = collections.v1(spark, sf_dir)
    state = clustering.train(v, replace(cfg, iters=1))
    rows = clustering.minibatches(v, cfg.batch, 2, cfg.seed).where("iter = 2").orderBy("_key", "vec_id").collect()
    return state, [r.vec_id for r in rows], np.array([r.embedding for r in rows], np.float64)


@query
def balanced_assign_frozen(spark, sf_dir):
    state, ids, x = _second_batch(spark, sf_dir, CONFIG)
    labels = clustering.assign_balanced(x, state.centers, state.counts, CONFIG)
    return spark.createDataFrame(list(zip(ids, labels.tolist(), strict=True)), "vec_id long, part_id long")


SQL["balanced_assign_frozen"] = O.index() + " SELECT vec_id, part_id FROM a2"


@query
def balanced_assign_variants(spark, sf_dir):
    """The second batch under every penalty."""
    state, ids, x = _second_batch(spark, sf_dir, CONFIG)
    rows = []
    for penalty in ("none", "multiplicative", "additive", "cap"):
        labels = clustering.assign_balanced(x, state.centers, state.counts, replace(CONFIG, penalty=penalty, cap=1.2))
        rows += [(penalty, i, p) for i, p in zip(ids, labels.tolist(), strict=True)]
    return spark.createDataFrame(rows, "penalty string, vec_id long, part_id long")


_L2C = O.l2("b2.e", "c")
SQL["balanced_assign_variants"] = (
    O.index()
    + f""", dd AS (SELECT b2.vec_id, part_id, v, {_L2C} AS d, (SELECT sum(v) / count(*) FROM c1) AS m FROM b2, c1),
near AS (SELECT avg(s) AS s FROM (SELECT min(d) AS s FROM dd GROUP BY vec_id)),
sc AS (SELECT vec_id, part_id, [d, d * (1.0 + 0.5 * (v / m)), d + 0.5 * s * (v / m), CASE WHEN v >= 1.2 * m THEN 'inf'::DOUBLE ELSE d END] AS s FROM dd, near),
names AS (SELECT unnest(range(1, 5)) AS i)
SELECT ['none', 'multiplicative', 'additive', 'cap'][i] AS penalty, vec_id, arg_min(part_id, (s[i], part_id)) AS part_id FROM sc, names GROUP BY i, vec_id"""
)


@query
def balanced_assign_seq(spark, sf_dir):
    """The first batch in sequence: counts grow with every row."""
    cfg = replace(CONFIG, scope="sequential", lam=1.0)
    v = collections.v1(spark, sf_dir)
    k = clustering.partition_count(v.count(), cfg.target_size)
    centers = np.array([r.embedding for r in clustering.seeds(v, k, cfg.seed).orderBy("part_id").collect()], np.float64)
    rows = clustering.minibatches(v, cfg.batch, 1, cfg.seed).orderBy("_key", "vec_id").collect()
    labels = clustering.assign_balanced(np.array([r.embedding for r in rows], np.float64), centers, np.zeros(k, np.int64), cfg)
    return spark.createDataFrame([(r.vec_id, int(p)) for r, p in zip(rows, labels, strict=True)], "vec_id long, part_id long")


SQL["balanced_assign_seq"] = (
    "WITH RECURSIVE "
    + O.training()
    + f""", o AS MATERIALIZED (SELECT row_number() OVER (ORDER BY md5('42:batch:1:' || b1.vec_id), b1.vec_id) AS i, b1.vec_id, b1.e FROM b1),
ds AS MATERIALIZED (SELECT i, vec_id, list(d ORDER BY part_id) AS d FROM (SELECT i, vec_id, part_id, {O.l2('o.e', 'c')} AS d FROM o, c0) GROUP BY i, vec_id),
r AS (
  SELECT 0::BIGINT AS i, 0::BIGINT AS vec_id, list_transform(range((SELECT k FROM kk)), lambda z: 0.0::DOUBLE) AS v, 0::BIGINT AS p
  UNION ALL
  SELECT i, vec_id, list_transform(range(len(v)), lambda z: v[z + 1] + CASE WHEN z = p THEN 1.0 ELSE 0.0 END) AS v, p FROM (
    SELECT i, vec_id, v, (list_position(s, list_min(s)) - 1)::BIGINT AS p FROM (
      SELECT ds.i, ds.vec_id, r.v, CASE WHEN list_sum(r.v) = 0 THEN ds.d ELSE
        list_transform(range(len(ds.d)), lambda z: ds.d[z + 1] * (1.0 + 1.0 * (r.v[z + 1] / (list_sum(r.v) / len(r.v))))) END AS s
      FROM r JOIN ds ON ds.i = r.i + 1)))
SELECT vec_id, p AS part_id FROM r WHERE i > 0"""
)


@query
def minibatch_step(spark, sf_dir):
    return _centroid_rows(spark, clustering.train(collections.v1(spark, sf_dir), replace(CONFIG, iters=1)))


@query
def kmeans_centroids(spark, sf_dir):
    return _centroid_rows(spark, clustering.train(collections.v1(spark, sf_dir), CONFIG))


@query
def kmeans_centroids_distributed(spark, sf_dir):
    return _centroid_rows(spark, clustering.train(collections.v1(spark, sf_dir), CONFIG, exec_mode="distributed"))


@query
def kmeans_unbalanced(spark, sf_dir):
    """Baseline: no size penalty."""
    return _centroid_rows(spark, clustering.train(collections.v1(spark, sf_dir), replace(CONFIG, penalty="none")))


@query
def kmeans_cosine(spark, sf_dir):
    return _centroid_rows(spark, clustering.train(collections.v2(spark, sf_dir), replace(CONFIG, metric="cosine")))


@query
def kmeans_full(spark, sf_dir):
    """Baseline: all vectors in every iteration."""
    return _centroid_rows(spark, clustering.train_full_kmeans(collections.v1(spark, sf_dir), replace(CONFIG, iters=3)))


SQL["minibatch_step"] = _centroid_sql(O.index(), "c1")
SQL["kmeans_centroids"] = SQL["kmeans_centroids_distributed"] = _centroid_sql(O.index(), "cen")
SQL["kmeans_unbalanced"] = _centroid_sql(O.index(lam=0.0), "cen")
SQL["kmeans_cosine"] = _centroid_sql(O.index(source=O.V2, metric="cosine"), "cen")
SQL["kmeans_full"] = _centroid_sql("WITH " + O.lloyd(O.V1, "(SELECT greatest(1, count(*) // 50) FROM embeddings)", 3), "fc3", "m")


@query
def train_spread(spark, sf_dir):
    """Spread of the samples that centres receive, without and with the size penalty."""
    v = collections.v1(spark, sf_dir)
    rows = []
    for lam in (0.0, 0.5, 2.0):
        counts = clustering.train(v, replace(CONFIG, lam=lam)).counts
        rows.append((lam, float(counts.std()), int(counts.max())))
    return rounded(spark.createDataFrame(rows, "lam double, std_count double, max_count long"), "std_count")


SQL["train_spread"] = " UNION ALL ".join(
    f"SELECT * FROM (WITH {O.training(lam=lam)} SELECT {lam}::DOUBLE AS lam, round(stddev_pop(v), 6) AS std_count, max(v)::BIGINT AS max_count FROM cen)" for lam in (0.0, 0.5, 2.0)
)


def _stored(spark, sf_dir, metric="l2"):
    return standard_index(spark, sf_dir, metric).main().select("vec_id", "part_id")


@query
def assign_all(spark, sf_dir):
    v = collections.v1(spark, sf_dir)
    return clustering.assign_all(v, clustering.train(v, CONFIG)).select("vec_id", "part_id")


@query
def index_build(spark, sf_dir):
    return _stored(spark, sf_dir)


SQL["assign_all"] = SQL["index_build"] = O.index() + " SELECT vec_id, part_id FROM p"


@query
def index_build_orders(spark, sf_dir):
    """The order vectors, clustered into parts of about 100 rows each; 64 samples an iteration."""
    cfg = replace(CONFIG, target_size=500)
    return standard_index(spark, sf_dir, source="v4", cfg=cfg).main().groupBy("part_id").agg(F.count("*").alias("size"), F.sum("vec_id").alias("id_sum"))


SQL["index_build_orders"] = O.index(source=O.V4, target=500) + " SELECT part_id, count(*) AS size, sum(vec_id)::BIGINT AS id_sum FROM p GROUP BY part_id"


@query
def partition_sizes(spark, sf_dir):
    return measures.partition_sizes(standard_index(spark, sf_dir))


SQL["partition_sizes"] = O.index() + " SELECT part_id, count(*) AS size FROM p GROUP BY part_id"


@query
def partition_balance(spark, sf_dir):
    return rounded(measures.balance(measures.partition_sizes(standard_index(spark, sf_dir))), "avg_size", "std_size", "imbalance")


SQL["partition_balance"] = (
    O.index()
    + """, s AS (SELECT count(*) AS size FROM p GROUP BY part_id)
SELECT min(size) AS min_size, max(size) AS max_size, round(avg(size), 6) AS avg_size, round(stddev_pop(size), 6) AS std_size, round(max(size) / avg(size), 6) AS imbalance FROM s"""
)


@query
def two_level_probe(spark, sf_dir):
    index = standard_index(spark, sf_dir)
    parts = search.probe_two_level(index, query_vector(spark, sf_dir), PROBES, 2)
    labels = index.super_centroids()[1]
    return spark.createDataFrame([(i + 1, p, int(labels[p])) for i, p in enumerate(parts)], "rank int, part_id long, super_id long")


SQL["two_level_probe"] = (
    O.index()
    + ", "
    + O.lloyd("SELECT part_id AS vec_id, c AS e FROM cen", f"(SELECT greatest(1, count(*) // {SUPER_SIZE}) FROM cen)", 3, "super")
    + f""", lab AS (SELECT cen.part_id, cen.c, arg_min(f.part_id, ({O.l2('cen.c', 'f.c')}, f.part_id)) AS super_id FROM cen, fc3 f GROUP BY cen.part_id, cen.c),
top AS (SELECT part_id FROM fc3 ORDER BY {O.l2('c', Q0)}, part_id LIMIT 2)
SELECT row_number() OVER (ORDER BY {O.l2('c', Q0)}, part_id)::INT AS rank, part_id, super_id FROM lab WHERE super_id IN (SELECT part_id FROM top) QUALIFY rank <= {PROBES}"""
)


@query
def probe_partitions(spark, sf_dir):
    index, q = standard_index(spark, sf_dir), query_vector(spark, sf_dir)
    near = index.centroid_rows().select(F.col("part_id").alias("vec_id"), V.l2(F.col("centroid"), V.literal(q)).alias("dist"))
    return rounded(search._ranked(near, PROBES), "dist").withColumnRenamed("vec_id", "part_id")


SQL["probe_partitions"] = O.index() + f" SELECT row_number() OVER (ORDER BY {O.l2('c', Q0)}, part_id)::INT AS rank, part_id, round({O.l2('c', Q0)}, 6) AS dist FROM cen QUALIFY rank <= {PROBES}"


@query
def ann_search(spark, sf_dir):
    """Flagship: the ten nearest vectors through as many of the nearest partitions as a recall of 0.9 takes."""
    return rounded(search.ann(standard_index(spark, sf_dir), query_vector(spark, sf_dir), K, calibrated(spark, sf_dir)), "dist")


@query
def ann_search_cosine(spark, sf_dir):
    return rounded(search.ann(standard_index(spark, sf_dir, "cosine"), query_vector(spark, sf_dir), K, calibrated(spark, sf_dir, "cosine")), "dist")


@query
def ann_single_plan(spark, sf_dir):
    return rounded(search.ann_single_plan(standard_index(spark, sf_dir), query_vector(spark, sf_dir), K, calibrated(spark, sf_dir)), "dist")


def ann_sql(metric: str = "l2", where: str = "true") -> str:
    d = O.distance("e", Q0, metric)
    return (
        O.index(metric=metric)
        + f" SELECT row_number() OVER (ORDER BY {d}, vec_id)::INT AS rank, vec_id, round({d}, 6) AS dist FROM p WHERE part_id IN {O.probes(Q0, metric=metric)} AND {where} QUALIFY rank <= {K}"
    )


SQL |= {"ann_search": ann_sql(), "ann_search_cosine": ann_sql("cosine"), "ann_single_plan": ann_sql()}

#: Neighbours, probe ranks and truths of the query batch.
BATCH = f""", q AS (SELECT vec_id AS qid, e AS qe FROM x WHERE vec_id % {EVERY} = 0),
pr AS MATERIALIZED (SELECT qid, part_id, row_number() OVER (PARTITION BY qid ORDER BY {O.l2('c', 'qe')}, part_id) AS pr FROM q, cen),
dq AS MATERIALIZED (SELECT qid, vec_id, part_id, {O.l2('e', 'qe')} AS d FROM q, p),
tr AS MATERIALIZED (SELECT qid, vec_id, part_id FROM dq QUALIFY row_number() OVER (PARTITION BY qid ORDER BY d, vec_id) <= {K}),
ap AS MATERIALIZED (SELECT qid, vec_id, d, row_number() OVER (PARTITION BY qid ORDER BY d, vec_id) AS rank FROM dq JOIN pr USING (qid, part_id) WHERE pr <= {O.N} QUALIFY rank <= {K})"""


@query
def recall_vs_probes(spark, sf_dir):
    return rounded(search.recall_curve(standard_index(spark, sf_dir), query_batch(spark, sf_dir), K), "recall")


_CURVE = ", cu AS (SELECT n, (SELECT count(*) FROM tr JOIN pr USING (qid, part_id) WHERE pr <= n) / (SELECT count(*) FROM tr) AS recall FROM (SELECT unnest(range(1, (SELECT count(*) + 1 FROM cen))) AS n))"
SQL["recall_vs_probes"] = O.index() + BATCH + _CURVE + " SELECT n, round(recall, 6) AS recall FROM cu"


@query
def calibrate_probes(spark, sf_dir):
    return spark.createDataFrame([(calibrated(spark, sf_dir),)], "n long")


SQL["calibrate_probes"] = O.index() + BATCH + _CURVE + " SELECT min(n) AS n FROM cu WHERE recall >= 0.9"


#: Probes that the rescaling starts from.
BUILT_PROBES = 8


@query
def rescaled_probes(spark, sf_dir):
    """Probes by year of an index that was built over the orders of the first year and takes in the later ones."""
    years = table(spark, sf_dir, "orders").where("o_orderdate IS NOT NULL").groupBy(F.year("o_orderdate").alias("year")).agg(F.count("*").alias("n"))
    rows, total = [], 0
    for r in years.orderBy("year").collect():  # a row a year
        total += r.n
        first = rows[0][1] if rows else total
        k = clustering.partition_count(first)
        rows.append((r.year, total, total / first - 1, search.rescale_probes(BUILT_PROBES, first / k, total / k)))
    return rounded(spark.createDataFrame(rows, "year int, n_rows long, growth double, n long"), "growth")


SQL["rescaled_probes"] = f"""WITH y AS (SELECT year(o_orderdate)::INT AS year, count(*) AS c FROM orders WHERE o_orderdate IS NOT NULL GROUP BY 1),
r AS (SELECT year, sum(c) OVER (ORDER BY year)::BIGINT AS t, first_value(c) OVER (ORDER BY year) AS b FROM y), k AS (SELECT *, greatest(1, b // 100) AS k FROM r)
SELECT year, t AS n_rows, round(t / b - 1, 6) AS growth, greatest(1, floor({BUILT_PROBES} * (b / k) / (t / k) + 0.5))::BIGINT AS n FROM k"""


def _batch_results(spark, sf_dir):
    index, q = standard_index(spark, sf_dir), query_batch(spark, sf_dir)
    return index, q, search.ann_batch(index, q, K, calibrated(spark, sf_dir)), search.knn_exact_batch(index.live(), q, K)


@query
def recall_ann(spark, sf_dir):
    _, _, found, truth = _batch_results(spark, sf_dir)
    return rounded(measures.recall_at_k(found, truth, K), "recall")


SQL["recall_ann"] = O.index() + BATCH + f" SELECT qid, round(count(*) FILTER (vec_id IN (SELECT vec_id FROM ap WHERE ap.qid = tr.qid)) / {K}, 6) AS recall FROM tr GROUP BY qid"


@query
def recall_intersect(spark, sf_dir):
    _, _, found, truth = _batch_results(spark, sf_dir)
    both = found.select("qid", "vec_id").intersect(truth.select("qid", "vec_id"))
    return both.groupBy("qid").agg(F.count("*").alias("hits"))


SQL["recall_intersect"] = O.index() + BATCH + " SELECT qid, count(*) AS hits FROM (SELECT qid, vec_id FROM ap INTERSECT SELECT qid, vec_id FROM tr) GROUP BY qid"


@query
def missed_neighbours(spark, sf_dir):
    _, _, found, truth = _batch_results(spark, sf_dir)
    return truth.select("qid", "vec_id").exceptAll(found.select("qid", "vec_id"))


SQL["missed_neighbours"] = O.index() + BATCH + " SELECT qid, vec_id FROM tr EXCEPT SELECT qid, vec_id FROM ap"


@query
def batch_probe_groups(spark, sf_dir):
    index = standard_index(spark, sf_dir)
    groups = search.probe_groups(query_batch(spark, sf_dir), index.centroids(), calibrated(spark, sf_dir))
    return groups.select("part_id", F.size("qids").cast("long").alias("n_queries"), F.array_join("qids", ",").alias("qids"))


SQL["batch_probe_groups"] = O.index() + BATCH + f" SELECT part_id, count(*) AS n_queries, string_agg(qid, ',' ORDER BY qid) AS qids FROM pr WHERE pr <= {O.N} GROUP BY part_id"


@query
def ann_batch(spark, sf_dir):
    return rounded(search.ann_batch(standard_index(spark, sf_dir), query_batch(spark, sf_dir), K, calibrated(spark, sf_dir)), "dist")


@query
def ann_batch_sql(spark, sf_dir):
    return rounded(search.ann_batch(standard_index(spark, sf_dir), query_batch(spark, sf_dir), K, calibrated(spark, sf_dir), "sql"), "dist")


@query
def ann_sequential(spark, sf_dir):
    """Baseline: queries one at a time."""
    return rounded(search.ann_sequential(standard_index(spark, sf_dir), query_batch(spark, sf_dir), K, calibrated(spark, sf_dir)), "dist")


_AP = " SELECT qid, rank::INT AS rank, vec_id, round(d, 6) AS dist FROM ap"
SQL |= {"ann_batch": O.index() + BATCH + _AP, "ann_batch_sql": O.index() + BATCH + _AP, "ann_sequential": O.index() + BATCH + _AP}


@query
def scan_cost(spark, sf_dir):
    index = standard_index(spark, sf_dir)
    return measures.scan_cost(index, search.probes_of(query_batch(spark, sf_dir), index.centroids(), calibrated(spark, sf_dir)))


SQL["scan_cost"] = O.index() + BATCH + f" SELECT qid, count(*) AS rows_scanned FROM pr JOIN p USING (part_id) WHERE pr <= {O.N} GROUP BY qid"


@query
def distinct_probes(spark, sf_dir):
    index = standard_index(spark, sf_dir)
    return search.probes_of(query_batch(spark, sf_dir), index.centroids(), calibrated(spark, sf_dir)).agg(F.count_distinct("part_id").alias("n"))


SQL["distinct_probes"] = O.index() + BATCH + f" SELECT count(DISTINCT part_id) AS n FROM pr WHERE pr <= {O.N}"


@query
def batch_sharing_factor(spark, sf_dir):
    """Partition reads saved, by size of the batch: ids are taken in order and over again."""
    index = standard_index(spark, sf_dir)
    v = collections.v1(spark, sf_dir)
    n = v.count()
    copied = v.withColumn("copy", F.explode(F.sequence(F.lit(0), F.lit(-(-1024 // n) - 1))))
    all_queries = copied.select((F.col("copy") * n + F.col("vec_id")).alias("qid"), F.col("embedding").alias("qvec")).where("qid < 1024")
    probes = search.probes_of(all_queries, index.centroids(), PROBES)
    sizes = spark.createDataFrame([(s,) for s in (1, 8, 64, 256, 512, 1024)], "batch_size long")
    joined = probes.join(F.broadcast(sizes), F.col("qid") < F.col("batch_size"))  # six rows
    grouped = joined.groupBy("batch_size").agg(F.count("*").alias("probes"), F.count_distinct("part_id").alias("parts"))
    return rounded(grouped.withColumn("factor", F.col("probes") / F.col("parts")), "factor")


SQL["batch_sharing_factor"] = (
    O.index()
    + f""", n AS (SELECT count(*) AS n FROM x), aq AS (SELECT cp * n + vec_id AS qid, e AS qe FROM x, n, (SELECT unnest(range(1024)) AS cp) WHERE cp * n + vec_id < 1024),
prb AS MATERIALIZED (SELECT vec_id, part_id FROM x, cen QUALIFY row_number() OVER (PARTITION BY vec_id ORDER BY {O.l2('c', 'e')}, part_id) <= {PROBES}),
ap AS (SELECT qid, part_id FROM aq, n, prb WHERE prb.vec_id = qid % n)
SELECT s AS batch_size, count(*) AS probes, count(DISTINCT part_id) AS parts, round(count(*) / count(DISTINCT part_id), 6) AS factor
FROM ap, (SELECT unnest([1, 8, 64, 256, 512, 1024])::BIGINT AS s) WHERE qid < s GROUP BY s"""
)


@query
def ds_profile(spark, sf_dir):
    """The derived collections: rows, dimensions, metric."""
    rows = None
    for name, make in collections.COLLECTIONS.items():
        one = make(spark, sf_dir).agg(F.lit(name).alias("set_name"), F.count("*").alias("n"), F.max(F.size("embedding")).alias("d"), F.lit(collections.METRIC[name]).alias("metric"))
        rows = one if rows is None else rows.unionByName(one)
    return rows


SQL["ds_profile"] = r"""WITH tok AS (SELECT len(list_filter(regexp_split_to_array(coalesce(text, ''), '[^A-Za-z0-9À-ÿ]+'), lambda t: t <> '')) AS k FROM documents),
cv AS (SELECT len(list_filter(regexp_split_to_array(coalesce(text, ''), '[^A-Za-z0-9À-ÿ]+'), lambda t: t <> '')) AS k FROM conversations)
SELECT 'v1' AS set_name, count(*) AS n, 64 AS d, 'cosine' AS metric FROM embeddings UNION ALL SELECT 'v2', count(*), 64, 'l2' FROM embeddings
UNION ALL SELECT 'v3', count(*), 256, 'cosine' FROM tok WHERE k > 0 UNION ALL SELECT 'v4', count(*), 10, 'l2' FROM orders
UNION ALL SELECT 'v5', count(*), 10, 'l2' FROM lineitem UNION ALL SELECT 'v6', count(*), 960, 'l2' FROM pages WHERE length(html) >= 3
UNION ALL SELECT 'v7', count(*), 200, 'l2' FROM cv WHERE k > 0"""


@query
def build_memory_model(spark, sf_dir):
    n = collections.v4(spark, sf_dir).count()
    rows = []
    for share in (0.0004, 0.01, 0.1, 1.0):
        batch = max(1, int(np.floor(n * share + 0.5)))
        m = measures.memory_model(n, 10, replace(CONFIG, batch=batch), max(1, n // 100))
        rows.append((share, batch, m["train_bytes"], m["full_kmeans_bytes"], m["query_bytes"], m["in_memory_bytes"]))
    return spark.createDataFrame(rows, "batch_share double, batch long, train_bytes long, full_kmeans_bytes long, query_bytes long, in_memory_bytes long")


SQL["build_memory_model"] = """WITH n AS (SELECT count(*) AS n, greatest(1, count(*) // 100) AS k FROM orders), s AS (SELECT unnest([0.0004, 0.01, 0.1, 1.0])::DOUBLE AS s),
b AS (SELECT *, greatest(1, floor(n * s + 0.5))::BIGINT AS b FROM n, s)
SELECT s AS batch_share, b AS batch, b * 40 + k * 80 AS train_bytes, n * 40 + k * 80 AS full_kmeans_bytes, k * 80 + 12800 AS query_bytes, n * 40 + k * 80 AS in_memory_bytes FROM b"""


@query
def pack_roundtrip(spark, sf_dir):
    """Vectors to kernel blobs and back: rows whose bits changed (none)."""
    from pyspark.sql.functions import pandas_udf

    @pandas_udf("binary")
    def packed(e):
        return e.map(V.pack)

    @pandas_udf("array<float>")
    def unpacked(b):
        import pandas as pd

        return pd.Series(list(V.unpack(b, 64))) if len(b) else pd.Series([], dtype=object)

    rows = collections.v1(spark, sf_dir)
    back = rows.withColumn("back", unpacked(packed("embedding")))
    return back.agg(F.count("*").alias("n"), F.sum((F.col("back") == F.col("embedding")).cast("long")).alias("same"))


SQL["pack_roundtrip"] = "SELECT count(*) AS n, count(*) AS same FROM embeddings"
