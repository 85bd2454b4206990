"""Relational operators around the index: joins, aggregates, functions, SQL surface, sources and sinks."""

from __future__ import annotations

import time
from dataclasses import replace

from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ivfspark import oracles as O
from ivfspark.catalog.common import ATTRIBUTES, CONFIG, EVERY, K, Q0, attributes, calibrated, query_batch, query_vector, rounded, standard_index
from ivfspark.functions import tables
from ivfspark.functions import vectors as V
from ivfspark.operators import measures, search
from ivfspark.operators.graph import connected_components
from ivfspark.plans.scratch import materialize, scratch_path
from ivfspark.sources import collections
from ivfspark.sources.collections import table
from ivfspark.sources.index import build

QUERIES_BY_KEY: dict = {}
SQL: dict[str, str] = {}


def query(fn):
    QUERIES_BY_KEY[fn.__name__] = fn
    return fn


# joins


def _with_attributes(spark, sf_dir, hint: str | None = None):
    rows = standard_index(spark, sf_dir).live().select("asset_id", "vec_id", "part_id")
    other = attributes(spark, sf_dir).select("asset_id", "lang", "n_chars", "quality")
    return rows.join(other.hint(hint) if hint else other, "asset_id")


@query
def join_vectors_attrs(spark, sf_dir):
    return _with_attributes(spark, sf_dir).select("vec_id", "part_id", "lang", "n_chars")


SQL["join_vectors_attrs"] = O.index() + f", {ATTRIBUTES} SELECT vec_id, part_id, lang, n_chars FROM p JOIN att ON asset_id = vec_id"


@query
def join_strategies_agree(spark, sf_dir):
    """Row count and id sum of the same join under every physical strategy."""
    out = None
    for hint in ("broadcast", "merge", "shuffle_hash", "shuffle_replicate_nl"):
        one = _with_attributes(spark, sf_dir, hint).agg(F.lit(hint).alias("strategy"), F.count("*").alias("n"), F.sum("vec_id").alias("id_sum"))
        out = one if out is None else out.unionByName(one)
    return out


SQL["join_strategies_agree"] = "SELECT s AS strategy, count(*) AS n, sum(vec_id)::BIGINT AS id_sum FROM embeddings JOIN documents ON doc_id = vec_id, (SELECT unnest(['broadcast', 'merge', 'shuffle_hash', 'shuffle_replicate_nl']) AS s) GROUP BY s"


@query
def attrs_with_labels(spark, sf_dir):
    return attributes(spark, sf_dir).select("asset_id", "lang", "source", "n_chars", "quality", "toxic")


SQL["attrs_with_labels"] = f"WITH {ATTRIBUTES} SELECT asset_id, lang, source, n_chars, quality, toxic FROM att"

BAND = 2000


@query
def range_join_bands(spark, sf_dir):
    """Pairs of vectors whose documents' lengths differ by at most ten: an equi-join on bands of lengths,
    each row also in the next band, and the exact test."""
    a = attributes(spark, sf_dir).select("asset_id", "n_chars")
    band = F.floor(F.col("n_chars") / BAND)
    left = a.select(F.col("asset_id").alias("a_id"), F.col("n_chars").alias("a_chars"), band.alias("band"))
    near = F.array_distinct(F.array(F.floor((F.col("n_chars") - 10) / BAND), band, F.floor((F.col("n_chars") + 10) / BAND)))
    right = a.select(F.col("asset_id").alias("b_id"), F.col("n_chars").alias("b_chars"), F.explode(near).alias("band"))
    return left.join(right, "band").where((F.col("a_id") < F.col("b_id")) & (F.abs(F.col("a_chars") - F.col("b_chars")) <= 10)).select("a_id", "b_id")


SQL["range_join_bands"] = f"WITH {ATTRIBUTES} SELECT a.asset_id AS a_id, b.asset_id AS b_id FROM att a JOIN att b ON a.asset_id < b.asset_id AND abs(a.n_chars - b.n_chars) <= 10"


# graph of neighbours


@query
def knn_graph(spark, sf_dir):
    """Five nearest other vectors of every vector, as batches of index searches in which each partition is read once for a
    block of queries. All partitions are probed, so that the result is exact; ``knn_graph_ann`` probes fewer."""
    index = standard_index(spark, sf_dir)
    return _neighbours(index, index.manifest["k"])


def _neighbours(index, n):
    asked = index.live().select(F.col("vec_id").alias("qid"), F.col("embedding").alias("qvec"))
    others = search.ann_batch(index, asked, 6, n).where(F.col("qid") != F.col("vec_id"))
    named = others.select(F.col("qid").alias("vec_id"), F.col("vec_id").alias("nbr"), "dist")
    place = F.row_number().over(W.partitionBy("vec_id").orderBy("dist", "nbr"))
    return rounded(named.withColumn("rank", place).where("rank <= 5").select("vec_id", "nbr", "rank", "dist"), "dist")


_GRAPH = f"WITH RECURSIVE x AS ({O.V1}), g AS MATERIALIZED (SELECT a.vec_id, b.vec_id AS nbr, {O.l2('a.e', 'b.e')} AS d, row_number() OVER (PARTITION BY a.vec_id ORDER BY {O.l2('a.e', 'b.e')}, b.vec_id) AS rank FROM x a, x b WHERE a.vec_id <> b.vec_id QUALIFY rank <= 5)"
SQL["knn_graph"] = _GRAPH + " SELECT vec_id, nbr, rank::INT AS rank, round(d, 6) AS dist FROM g"


@query
def knn_graph_ann(spark, sf_dir):
    """The same through the calibrated number of partitions only."""
    return _neighbours(standard_index(spark, sf_dir), calibrated(spark, sf_dir))


SQL["knn_graph_ann"] = (
    O.index()
    + f""", gp AS MATERIALIZED (SELECT vec_id AS src, e AS qe, part_id FROM x, cen QUALIFY row_number() OVER (PARTITION BY vec_id ORDER BY {O.l2('c', 'e')}, part_id) <= {O.N}),
six AS (SELECT src, vec_id, {O.l2('e', 'qe')} AS d, row_number() OVER (PARTITION BY src ORDER BY {O.l2('e', 'qe')}, vec_id) AS r FROM gp JOIN p USING (part_id) QUALIFY r <= 6)
SELECT src AS vec_id, vec_id AS nbr, row_number() OVER (PARTITION BY src ORDER BY d, vec_id)::INT AS rank, round(d, 6) AS dist FROM six WHERE src <> vec_id QUALIFY rank <= 5"""
)

#: Cosine distance up to which two documents are near copies.
NEAR = 0.02


def near_copy_groups(spark, vectors, metric, radius):
    """``(vec_id, group_id)`` of vectors within ``radius`` of each other, directly or through others. Equal vectors collapse
    to their least id first; the others are found by an index over the distinct ones, whose every partition within reach of
    a query is read, so that no link is lost: a partition's reach is bounded by its radius."""
    bits = F.xxhash64("embedding")
    keyed = materialize(vectors.withColumn("bits", bits), "keyed")
    distinct = keyed.groupBy("bits", "embedding").agg(F.min("vec_id").alias("vec_id"))
    cfg = replace(CONFIG, metric=metric)
    index = build(spark, scratch_path(spark, "near"), distinct.select("vec_id", "embedding"), cfg)
    links = materialize(search.range_join(index, radius).where("a <> b"), "near")
    groups = connected_components(links)
    named = distinct.select("bits", "vec_id").join(groups, F.col("vec_id") == F.col("node"), "left")
    named = named.select("bits", F.col("vec_id").alias("rep"), F.coalesce("component", "vec_id").alias("group_id"))
    return keyed.select("vec_id", "bits").join(named, "bits").select("vec_id", "group_id")


@query
def related_groups(spark, sf_dir):
    """Groups of documents that are near copies by their token vectors; every document has its group."""
    return near_copy_groups(spark, collections.v3(spark, sf_dir), "cosine", NEAR)


_V3 = O.V3
SQL["related_groups"] = f"""WITH RECURSIVE x AS MATERIALIZED ({_V3}), u AS MATERIALIZED (SELECT e, min(vec_id) AS rep FROM x GROUP BY e),
m AS MATERIALIZED (SELECT a.rep AS a, b.rep AS b FROM u a, u b WHERE a.rep <> b.rep AND {O.cosine('a.e', 'b.e')} <= {NEAR}),
c AS (SELECT a AS node, a AS root FROM m UNION SELECT m.b, c.root FROM c JOIN m ON m.a = c.node),
l AS (SELECT node, min(root) AS root FROM c GROUP BY node)
SELECT x.vec_id, coalesce(root, rep) AS group_id FROM x JOIN u USING (e) LEFT JOIN l ON node = rep"""


# aggregates


def _recalls(spark, sf_dir):
    index, q = standard_index(spark, sf_dir), query_batch(spark, sf_dir)
    recall = measures.recall_at_k(search.ann_batch(index, q, K, calibrated(spark, sf_dir)), search.knn_exact_batch(index.live(), q, K), K)
    return recall.join(attributes(spark, sf_dir).select(F.col("asset_id").alias("qid"), "lang", "source"), "qid")


_RECALLS = (
    O.index()
    + f""", {ATTRIBUTES}, q AS (SELECT vec_id AS qid, e AS qe FROM x WHERE vec_id % {EVERY} = 0),
pr AS MATERIALIZED (SELECT qid, part_id FROM q, cen QUALIFY row_number() OVER (PARTITION BY qid ORDER BY {O.l2('c', 'qe')}, part_id) <= {O.N}),
dq AS MATERIALIZED (SELECT qid, vec_id, part_id, {O.l2('e', 'qe')} AS d FROM q, p),
tr AS (SELECT qid, vec_id FROM dq QUALIFY row_number() OVER (PARTITION BY qid ORDER BY d, vec_id) <= {K}),
ap AS (SELECT qid, vec_id FROM dq JOIN pr USING (qid, part_id) QUALIFY row_number() OVER (PARTITION BY qid ORDER BY d, vec_id) <= {K}),
rq AS (SELECT qid, count(ap.vec_id) / {K} AS recall FROM tr LEFT JOIN ap USING (qid, vec_id) GROUP BY qid),
rl AS MATERIALIZED (SELECT recall, lang, source FROM rq JOIN att ON asset_id = qid)"""
)


def _grouped(df):
    return rounded(df.agg(F.count("*").alias("n"), F.avg("recall").alias("avg_recall")), "avg_recall")


@query
def recall_rollup(spark, sf_dir):
    return _grouped(_recalls(spark, sf_dir).rollup("lang", "source"))


@query
def recall_cube(spark, sf_dir):
    return _grouped(_recalls(spark, sf_dir).cube("lang", "source"))


@query
def sets_grouping(spark, sf_dir):
    return _grouped(_recalls(spark, sf_dir).groupingSets([["lang"], ["source"], []], "lang", "source"))


for _name, _by in {"recall_rollup": "ROLLUP (lang, source)", "recall_cube": "CUBE (lang, source)", "sets_grouping": "GROUPING SETS ((lang), (source), ())"}.items():
    SQL[_name] = _RECALLS + f" SELECT lang, source, count(*) AS n, round(avg(recall), 6) AS avg_recall FROM rl GROUP BY {_by}"


@query
def agg_centroid_sums(spark, sf_dir):
    """Means of partitions by dimension, from fixed-point partial sums."""
    rows = standard_index(spark, sf_dir).live().select("part_id", F.posexplode("embedding").alias("dim", "x"))
    total = F.sum(F.floor(F.col("x").cast("double") * (1 << 30) + 0.5))
    grouped = rows.groupBy("part_id", "dim").agg((total / float(1 << 30) / F.count("*")).alias("mean"))
    return rounded(grouped.withColumn("dim", F.col("dim") + 1), "mean")


SQL["agg_centroid_sums"] = O.index() + " SELECT part_id, dim::INT AS dim, round(sum(floor(e[dim] * 1073741824 + 0.5)::BIGINT)::DOUBLE / 1073741824 / count(*), 6) AS mean FROM (SELECT part_id, e, unnest(range(1, len(e) + 1)) AS dim FROM p) GROUP BY part_id, dim"


@query
def distance_percentiles(spark, sf_dir):
    q = V.literal(query_vector(spark, sf_dir))
    rows = standard_index(spark, sf_dir).live().select("part_id", V.l2(F.col("embedding"), q).alias("d"))
    return rounded(rows.groupBy("part_id").agg(F.min("d").alias("d_min"), F.percentile("d", 0.5).alias("d_mid"), F.max("d").alias("d_max")), "d_min", "d_mid", "d_max")


SQL["distance_percentiles"] = O.index() + f", d AS (SELECT part_id, {O.l2('e', Q0)} AS d FROM p) SELECT part_id, round(min(d), 6) AS d_min, round(quantile_cont(d, 0.5), 6) AS d_mid, round(max(d), 6) AS d_max FROM d GROUP BY part_id"


# scalar functions


@query
def tokenise_docs(spark, sf_dir):
    rows = table(spark, sf_dir, "documents").select("doc_id", collections.tokens(F.col("text")).alias("t"))
    return rows.select("doc_id", F.size("t").cast("long").alias("n_tokens"), F.size(F.array_distinct("t")).cast("long").alias("n_distinct"), F.get("t", 0).alias("first_token"))


SQL["tokenise_docs"] = """WITH t AS (SELECT doc_id, list_filter(list_transform(regexp_split_to_array(coalesce(text, ''), '[^A-Za-z0-9À-ÿ]+'), lambda t: lower(t)), lambda t: t <> '') AS t FROM documents)
SELECT doc_id, len(t) AS n_tokens, len(list_distinct(t)) AS n_distinct, t[1] AS first_token FROM t"""


@query
def json_props(spark, sf_dir):
    rows = table(spark, sf_dir, "events").select("event_type", F.from_json("props", "k int").alias("p"))
    return rows.groupBy("event_type").agg(F.count("*").alias("n"), F.sum("p.k").alias("k_sum"), F.count_distinct("p.k").alias("k_distinct"))


SQL["json_props"] = "SELECT event_type, count(*) AS n, sum((props->>'k')::INT)::BIGINT AS k_sum, count(DISTINCT (props->>'k')::INT) AS k_distinct FROM events GROUP BY event_type"


@query
def date_attr_filter(spark, sf_dir):
    """Orders of a date range by month, as a date predicate on attributes."""
    o = table(spark, sf_dir, "orders").where((F.col("o_orderdate") >= F.lit("1996-01-01").cast("timestamp_ntz")) & (F.col("o_orderdate") < F.lit("1997-01-01").cast("timestamp_ntz")))
    return o.groupBy(F.month("o_orderdate").alias("month")).agg(F.count("*").alias("n"), F.sum("o_orderkey").alias("key_sum"))


SQL["date_attr_filter"] = "SELECT month(o_orderdate)::INT AS month, count(*) AS n, sum(o_orderkey)::BIGINT AS key_sum FROM orders WHERE o_orderdate >= TIMESTAMP '1996-01-01' AND o_orderdate < TIMESTAMP '1997-01-01' GROUP BY 1"


@query
def attr_map(spark, sf_dir):
    """Attributes as a map, and one looked up."""
    a = attributes(spark, sf_dir)
    pairs = F.create_map(F.lit("lang"), F.col("lang"), F.lit("source"), F.col("source"), F.lit("chars"), F.col("n_chars").cast("string"))
    m = a.select("asset_id", pairs.alias("m"))
    return m.select("asset_id", F.size("m").alias("n_keys"), F.try_element_at("m", F.lit("source")).alias("source"), F.try_element_at("m", F.lit("none")).alias("missing"))


SQL["attr_map"] = f"WITH {ATTRIBUTES} SELECT asset_id, 3 AS n_keys, source, NULL::VARCHAR AS missing FROM att"


@query
def vector_slices(spark, sf_dir):
    """Slices, sorts and zips of vectors."""
    d = V.doubles("embedding")
    rows = collections.v1(spark, sf_dir).select(
        "vec_id",
        F.size(F.slice(d, 1, 8)).alias("head_size"),
        F.element_at(F.array_sort(d), 1).alias("least"),
        V.dot(F.slice(d, 1, 32), F.slice(d, 33, 32)).alias("half_dot"),
    )
    return rounded(rows, "least", "half_dot")


SQL["vector_slices"] = f"WITH x AS ({O.V1}) SELECT vec_id, len(e[1:8])::INT AS head_size, round(list_min(e), 6) AS least, round({O.dot('e[1:32]', 'e[33:64]')}, 6) AS half_dot FROM x"


# user functions and SQL surface


@query
def udf_distance(spark, sf_dir):
    fn = tables.distance_udf("l2")
    q = V.literal(query_vector(spark, sf_dir))
    return rounded(collections.v1(spark, sf_dir).select("vec_id", fn(V.doubles("embedding"), q).alias("dist")), "dist")


SQL["udf_distance"] = f"WITH x AS ({O.V1}) SELECT vec_id, round({O.l2('e', Q0)}, 6) AS dist FROM x"


@query
def udaf_centroid(spark, sf_dir):
    fn = tables.centroid_udaf()
    rows = standard_index(spark, sf_dir).live().groupBy("part_id").agg(fn("embedding").alias("c"))
    return rounded(rows.select("part_id", F.posexplode("c").alias("dim", "mean")).withColumn("dim", F.col("dim") + 1), "mean")


SQL["udaf_centroid"] = SQL["agg_centroid_sums"]


@query
def udtf_ann(spark, sf_dir):
    """The probe as a table function in SQL, joined to the vectors' view."""
    index = standard_index(spark, sf_dir)
    tables.register_ann(spark, index, "ivf")
    V.register_sql_functions(spark)
    q = ", ".join(f"{x!r}D" for x in query_vector(spark, sf_dir))
    rows = spark.sql(
        f"""SELECT vec_id, vec_l2(CAST(embedding AS ARRAY<DOUBLE>), array({q})) AS dist
        FROM ivf_vectors JOIN ivf_probe(array({q}), {calibrated(spark, sf_dir)}) USING (part_id) ORDER BY dist, vec_id LIMIT {K}"""
    )
    return rounded(search._ranked(rows, K), "dist")


@query
def sql_ann(spark, sf_dir):
    """The whole search in SQL: probes are a subquery over the centroid view."""
    index = standard_index(spark, sf_dir)
    tables.register_ann(spark, index, "ivf")
    V.register_sql_functions(spark)
    q = ", ".join(f"{x!r}D" for x in query_vector(spark, sf_dir))
    rows = spark.sql(
        f"""WITH centres AS (SELECT part_id, vec_l2(centroid, array({q})) AS d FROM ivf_centroids),
        near AS (SELECT part_id FROM centres ORDER BY d, part_id LIMIT {calibrated(spark, sf_dir)})
        SELECT vec_id, vec_l2(CAST(embedding AS ARRAY<DOUBLE>), array({q})) AS dist FROM ivf_vectors
        WHERE part_id IN (SELECT part_id FROM near) ORDER BY dist, vec_id LIMIT {K}"""
    )
    return rounded(search._ranked(rows, K), "dist")


_ANN = O.index() + f" SELECT row_number() OVER (ORDER BY {O.l2('e', Q0)}, vec_id)::INT AS rank, vec_id, round({O.l2('e', Q0)}, 6) AS dist FROM p WHERE part_id IN {O.probes(Q0)} QUALIFY rank <= {K}"
SQL["udtf_ann"] = SQL["sql_ann"] = _ANN


# sources and sinks


@query
def scan_partition_pruned(spark, sf_dir):
    """Rows of the probed partitions, through the index data source."""
    from ivfspark.sources.datasource import IvfSource

    index = standard_index(spark, sf_dir)
    spark.dataSource.register(IvfSource)
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    parts = search.probe(index.centroids(), query_vector(spark, sf_dir), calibrated(spark, sf_dir))
    rows = spark.read.format("ivf").option("path", index.store.path).load()
    return rows.where(F.col("part_id").isin(parts)).select("vec_id", "part_id")


SQL["scan_partition_pruned"] = O.index() + f" SELECT vec_id, part_id FROM p WHERE part_id IN {O.probes(Q0)}"


@query
def roundtrip_formats(spark, sf_dir):
    """Results written and read again as parquet, ORC, JSON and CSV."""
    found = rounded(search.knn_exact(collections.v1(spark, sf_dir), query_vector(spark, sf_dir), K), "dist")
    out = None
    for kind in ("parquet", "orc", "json", "csv"):
        path = scratch_path(spark, kind)
        found.write.format(kind).save(path)
        one = spark.read.schema(found.schema).format(kind).load(path).select(F.lit(kind).alias("format"), *found.columns)
        out = one if out is None else out.unionByName(one)
    return out


SQL["roundtrip_formats"] = f"""WITH x AS ({O.V1}), t AS (SELECT vec_id, {O.l2('e', Q0)} AS d FROM x), r AS (SELECT row_number() OVER (ORDER BY d, vec_id)::INT AS rank, vec_id, round(d, 6) AS dist FROM t QUALIFY rank <= {K})
SELECT f AS format, rank, vec_id, dist FROM r, (SELECT unnest(['parquet', 'orc', 'json', 'csv']) AS f)"""


# star schema around the order vectors


def _near_orders(spark, sf_dir):
    q = V.literal(query_vector(spark, sf_dir, 1, "v4"))
    return search._ranked(collections.v4(spark, sf_dir).select("vec_id", V.l2(F.col("embedding"), q).alias("dist")), 200)


@query
def knn_orders_by_region(spark, sf_dir):
    """The 200 orders nearest to order 1, by region of the customer."""
    t = lambda name: table(spark, sf_dir, name)
    rows = _near_orders(spark, sf_dir).join(t("orders"), F.col("vec_id") == F.col("o_orderkey")).join(t("customer"), F.col("o_custkey") == F.col("c_custkey"))
    rows = rows.join(t("nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(t("region"), F.col("n_regionkey") == F.col("r_regionkey"))
    return rounded(rows.groupBy("r_name").agg(F.count("*").alias("n"), F.avg("dist").alias("avg_dist")), "avg_dist")


_ORDERS = f"WITH x AS ({O.V4}), nr AS MATERIALIZED (SELECT vec_id, {O.l2('e', '(SELECT e FROM x WHERE vec_id = 1)')} AS d FROM x ORDER BY d, vec_id LIMIT 200)"
SQL["knn_orders_by_region"] = _ORDERS + """ SELECT r_name, count(*) AS n, round(avg(d), 6) AS avg_dist FROM nr JOIN orders ON o_orderkey = vec_id JOIN customer ON c_custkey = o_custkey
JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey GROUP BY r_name"""


@query
def neighbour_revenue(spark, sf_dir):
    """Revenue of the 200 nearest orders by part brand; sums in cents."""
    t = lambda name: table(spark, sf_dir, name)
    lines = t("lineitem").select("l_orderkey", "l_partkey", F.floor(F.col("l_extendedprice") * 100 + 0.5).alias("cents"))
    rows = lines.join(_near_orders(spark, sf_dir), F.col("l_orderkey") == F.col("vec_id")).join(t("part"), F.col("l_partkey") == F.col("p_partkey"))
    return rows.groupBy("p_brand").agg(F.count("*").alias("n"), F.sum("cents").alias("cents"))


SQL["neighbour_revenue"] = _ORDERS + " SELECT p_brand, count(*) AS n, sum(floor(l_extendedprice * 100 + 0.5)::BIGINT)::BIGINT AS cents FROM nr JOIN lineitem ON l_orderkey = vec_id JOIN part ON p_partkey = l_partkey GROUP BY p_brand"


MINIBATCH_SHARES = (0.0004, 0.01, 0.1, 1.0)


@query
def recall_vs_minibatch(spark, sf_dir):
    """Training batch from 0.04 % to all of the order vectors against recall of the 100 nearest, with the probes that 90 %
    takes at the smallest batch; seconds of training are measured."""
    v = materialize(collections.v4(spark, sf_dir), "orders")
    n, asked, rows, probes, truth = v.count(), v.where(F.col("vec_id") % EVERY == 0).select(F.col("vec_id").alias("qid"), F.col("embedding").alias("qvec")), [], None, None
    for share in MINIBATCH_SHARES:
        cfg = replace(CONFIG, target_size=100, batch=max(1, int(n * share + 0.5)))
        began = time.perf_counter()
        index = build(spark, scratch_path(spark, "minibatch"), v, cfg)
        seconds = time.perf_counter() - began
        truth = truth or search.knn_exact_indexed(index, asked, 100)  # the same rows under every index
        curve = search.recall_curve(index, asked, 100, truth)
        found = curve.where(F.col("n") == probes).first() if probes else curve.where(F.col("recall") >= 0.9).orderBy("n").first()
        probes, recall = found.n, found.recall
        rows.append((share, cfg.batch, measures.memory_model(n, 10, cfg, index.manifest["k"])["train_bytes"], probes, recall, seconds))
    return rounded(spark.createDataFrame(rows, "batch_share double, batch long, train_bytes long, n_probe long, recall double, build_s double"), "recall")
