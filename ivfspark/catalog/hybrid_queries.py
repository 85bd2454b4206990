"""Predicates, statistics, estimates, plans, and hybrid searches."""

from __future__ import annotations

from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ivfspark import oracles as O
from ivfspark.catalog.common import ATTRIBUTES, EVERY, K, PROBES, Q0, attributed_index, attributes, calibrated, query_batch, query_vector, rounded, standard_index
from ivfspark.functions.vectors import distance
from ivfspark.operators import hybrid, measures, search
from ivfspark.plans import planner, statistics
from ivfspark.plans.predicates import Leaf, match_all
from ivfspark.plans.scratch import materialize

QUERIES_BY_KEY: dict = {}
SQL: dict[str, str] = {}
BINS = 8


def query(fn):
    QUERIES_BY_KEY[fn.__name__] = fn
    return fn


EN, NOT_EN = Leaf("lang", "=", "en"), Leaf("lang", "!=", "en")
SRC3, SHORT = Leaf("source", "=", "src3"), Leaf("n_chars", "<", 200)
LONG, MIDDLE = Leaf("n_chars", ">", 3000), Leaf("n_chars", "between", (1000, 3000))
GOOD, UNLABELLED = Leaf("quality", "=", 1), Leaf("quality", "is null")
FR, ES = Leaf("lang", "=", "fr"), Leaf("lang", "=", "es")
WORD = Leaf("tokens", "match", "token")

#: Predicates by name, in the order of their definition.
LADDER = {
    "en": EN,
    "not_en": NOT_EN,
    "src3": SRC3,
    "short": SHORT,
    "long": LONG,
    "middle": MIDDLE,
    "good": GOOD,
    "unlabelled": UNLABELLED,
    "in_langs": Leaf("lang", "in", ("fr", "es")),
    "word": WORD,
    "fr_and_long": FR & LONG,
    "fr_or_es": FR | ES,
    "src3_or_short": SRC3 | SHORT,
    "nested": (FR | ES) & MIDDLE & NOT_EN,
    "wide_or": EN | NOT_EN | MIDDLE,
}


def _ops(name, predicate):
    def run(spark, sf_dir):
        return attributes(spark, sf_dir).where(predicate.to_column()).select(F.col("asset_id").alias("vec_id"))

    QUERIES_BY_KEY[f"hybrid_ops_{name}"] = run
    SQL[f"hybrid_ops_{name}"] = f"WITH {ATTRIBUTES} SELECT asset_id AS vec_id FROM att WHERE {predicate.to_sql()}"


for _name, _p in {
    "eq": EN,
    "ne": NOT_EN,
    "lt": SHORT,
    "gt": LONG,
    "between": MIDDLE,
    "in": LADDER["in_langs"],
    "null": UNLABELLED,
    "and": FR & LONG,
    "or": SRC3 | SHORT,
    "not": ~(FR & LONG),
    "match": WORD,
}.items():
    _ops(_name, _p)


@query
def stats_histogram(spark, sf_dir):
    return statistics.histogram(attributes(spark, sf_dir), "n_chars", BINS)


HIST = f"""hv AS (SELECT n_chars::DOUBLE AS v, count(*) AS c FROM att WHERE n_chars IS NOT NULL GROUP BY 1),
hp AS (SELECT v, c, coalesce(sum(c) OVER (ORDER BY v ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)::BIGINT AS b, (SELECT sum(c) FROM hv)::BIGINT AS t FROM hv),
hist AS (SELECT (b * {{bins}} // t)::INT AS bin, min(v) AS lo, max(v) AS hi, sum(c)::BIGINT AS cnt FROM hp GROUP BY 1)"""
SQL["stats_histogram"] = f"WITH {ATTRIBUTES}, {HIST.format(bins=BINS)} SELECT bin, lo, hi, cnt FROM hist"


@query
def stats_mcv(spark, sf_dir):
    a = attributes(spark, sf_dir)
    columns = [statistics.common_values(a, c, 8).select(F.lit(c).alias("col"), "value", "cnt") for c in ("lang", "source", "quality")]
    return columns[0].unionByName(columns[1]).unionByName(columns[2])


SQL["stats_mcv"] = f"WITH {ATTRIBUTES} " + " UNION ALL ".join(
    f"(SELECT '{c}' AS col, {c}::VARCHAR AS value, count(*) AS cnt FROM att WHERE {c} IS NOT NULL GROUP BY 2 ORDER BY cnt DESC, value LIMIT 8)" for c in ("lang", "source", "quality")
)


@query
def stats_token_df(spark, sf_dir):
    return statistics.token_frequencies(attributes(spark, sf_dir))


SQL["stats_token_df"] = f"WITH {ATTRIBUTES} SELECT token, count(*) AS df FROM (SELECT unnest(tokens) AS token FROM att) GROUP BY token"


def _statistics(spark, sf_dir):
    """As stored with the index."""
    return statistics.stored_statistics(attributed_index(spark, sf_dir))


def _sql_estimates() -> str:
    """Estimates of the ladder, from exact counts, the histogram and document frequencies."""
    leaf = lambda where: f"(SELECT count(*) FROM att WHERE {where})::DOUBLE"
    below = lambda a, inc: (
        f"(SELECT coalesce(sum(CASE WHEN hi {'<=' if inc else '<'} {a} THEN cnt WHEN lo < {a} AND hi > lo THEN cnt * ({a} - lo) / (hi - lo) ELSE 0 END), 0)::DOUBLE FROM hist)"
    )
    filled = leaf("n_chars IS NOT NULL")
    single = {
        "en": leaf("lang = 'en'"),
        "not_en": leaf("lang <> 'en'"),
        "src3": leaf("source = 'src3'"),
        "short": below(200, False),
        "long": f"({filled} - {below(3000, True)})",
        "middle": f"({below(3000, True)} - {below(1000, False)})",
        "good": leaf("quality = 1"),
        "unlabelled": leaf("quality IS NULL"),
        "in_langs": leaf("lang IN ('fr', 'es')"),
        "word": leaf("list_contains(tokens, 'token')"),
    }
    fr, es, n = leaf("lang = 'fr'"), leaf("lang = 'es'"), leaf("true")
    combined = {
        "fr_and_long": f"least({fr}, {single['long']})",
        "fr_or_es": f"least({fr} + {es}, {n})",
        "src3_or_short": f"least({single['src3']} + {single['short']}, {n})",
        "nested": f"least(least(least({fr} + {es}, {n}), {single['middle']}), {single['not_en']})",
        "wide_or": f"least(least({single['en']} + {single['not_en']}, {n}) + {single['middle']}, {n})",
    }
    rows = [f"SELECT '{name}' AS pred, {est} AS est, (SELECT count(*) FROM att WHERE {LADDER[name].to_sql()}) AS true_rows, {name in single} AS single" for name, est in (single | combined).items()]
    return f"WITH {ATTRIBUTES}, {HIST.format(bins=32)}, es AS MATERIALIZED ({' UNION ALL '.join(rows)}), nn AS (SELECT count(*) AS n FROM att)"


def _estimated(spark, sf_dir):
    stats = _statistics(spark, sf_dir)
    flags = attributes(spark, sf_dir).agg(*[F.sum(p.to_column().cast("long")).alias(name) for name, p in LADDER.items()]).first()
    rows = [(name, float(statistics.estimate(p, stats)), int(flags[name] or 0), isinstance(p, Leaf)) for name, p in LADDER.items()]
    return stats, rows


@query
def est_single_predicates(spark, sf_dir):
    rows = [(n, e, t) for n, e, t, single in _estimated(spark, sf_dir)[1] if single]
    return rounded(spark.createDataFrame(rows, "pred string, est double, true_rows long"), "est")


@query
def est_combined(spark, sf_dir):
    rows = [(n, e, t) for n, e, t, single in _estimated(spark, sf_dir)[1] if not single]
    return rounded(spark.createDataFrame(rows, "pred string, est double, true_rows long"), "est")


SQL["est_single_predicates"] = _sql_estimates() + " SELECT pred, round(est, 6) AS est, true_rows FROM es WHERE single"
SQL["est_combined"] = _sql_estimates() + " SELECT pred, round(est, 6) AS est, true_rows FROM es WHERE NOT single"


@query
def selectivity_qerror(spark, sf_dir):
    rows = [(n, float(statistics.q_error(e, t))) for n, e, t, _ in _estimated(spark, sf_dir)[1]]
    return rounded(spark.createDataFrame(rows, "pred string, qerr double"), "qerr")


SQL["selectivity_qerror"] = _sql_estimates() + " SELECT pred, round(greatest(greatest(est, 1) / greatest(true_rows, 1), greatest(true_rows, 1) / greatest(est, 1)), 6) AS qerr FROM es"


@query
def true_selectivity(spark, sf_dir):
    flags = [F.avg(p.to_column().cast("int")).alias(name) for name, p in LADDER.items()]
    wide = attributes(spark, sf_dir).agg(*flags)
    return rounded(wide.unpivot([], list(LADDER), "pred", "f"), "f")


SQL["true_selectivity"] = _sql_estimates() + " SELECT pred, round(true_rows / n, 6) AS f FROM es, nn"


@query
def ivf_selectivity(spark, sf_dir):
    n = standard_index(spark, sf_dir).manifest["n_main"]
    return rounded(spark.createDataFrame([(p, planner.ivf_selectivity(p, 50, n)) for p in (1, 2, 3, 5, 8)], "n long, f_ivf double"), "f_ivf")


SQL["ivf_selectivity"] = "SELECT p::BIGINT AS n, round(p * 50 / (SELECT count(*) FROM embeddings), 6) AS f_ivf FROM (SELECT unnest([1, 2, 3, 5, 8]) AS p)"


@query
def plan_choice(spark, sf_dir):
    stats = _statistics(spark, sf_dir)
    rows = []
    for name, p in LADDER.items():
        plan = planner.choose(p, stats, PROBES, 50)
        rows.append((name, PROBES, plan.f_filters, plan.f_ivf, plan.kind))
    return rounded(spark.createDataFrame(rows, "pred string, n long, f_filters double, f_ivf double, plan string"), "f_filters", "f_ivf")


@query
def plan_vs_probes(spark, sf_dir):
    stats = _statistics(spark, sf_dir)
    rows = [(name, n, planner.choose(LADDER[name], stats, n, 50).kind) for name in ("src3", "in_langs", "good", "en") for n in (1, 2, 4, 8)]
    return spark.createDataFrame(rows, "pred string, n long, plan string")


_PLAN = "CASE WHEN least(est, n) / n < p * 50 / n THEN 'pre' ELSE 'post' END"
SQL["plan_choice"] = _sql_estimates() + f" SELECT pred, p AS n, round(least(est, n) / n, 6) AS f_filters, round(p * 50 / n, 6) AS f_ivf, {_PLAN} AS plan FROM es, nn, (SELECT {PROBES}::BIGINT AS p)"
SQL["plan_vs_probes"] = _sql_estimates() + f" SELECT pred, p AS n, {_PLAN} AS plan FROM es, nn, (SELECT unnest([1, 2, 4, 8])::BIGINT AS p) WHERE pred IN ('src3', 'in_langs', 'good', 'en')"


@query
def prefilter_ids(spark, sf_dir):
    return hybrid.qualifying(attributes(spark, sf_dir), FR | ES)


SQL["prefilter_ids"] = f"WITH {ATTRIBUTES} SELECT asset_id FROM att WHERE lang = 'fr' OR lang = 'es'"


def _ranked_sql(where: str, naive: bool = False) -> str:
    d = O.l2("e", Q0)
    probed = f"part_id IN {O.probes(Q0)}"
    if naive:
        return (
            O.index()
            + f", {ATTRIBUTES}, f AS (SELECT vec_id, {d} AS d FROM p WHERE {probed} ORDER BY d, vec_id LIMIT {K}) "
            + f"SELECT row_number() OVER (ORDER BY d, vec_id)::INT AS rank, vec_id, round(d, 6) AS dist FROM f WHERE vec_id IN (SELECT asset_id FROM att WHERE {where})"
        )
    return O.index() + f", {ATTRIBUTES} SELECT row_number() OVER (ORDER BY {d}, vec_id)::INT AS rank, vec_id, round({d}, 6) AS dist FROM p WHERE {{probed}} vec_id IN (SELECT asset_id FROM att WHERE {where}) QUALIFY rank <= {K}"


def pre_sql(where: str) -> str:
    return _ranked_sql(where).replace("{probed}", "")


def post_sql(where: str) -> str:
    return _ranked_sql(where).replace("{probed}", f"part_id IN {O.probes(Q0)} AND")


def _setup(spark, sf_dir):
    index = attributed_index(spark, sf_dir)
    return index, index.attributes(), query_vector(spark, sf_dir)


@query
def hybrid_prefilter(spark, sf_dir):
    index, attrs, q = _setup(spark, sf_dir)
    return rounded(hybrid.prefilter(index, attrs, q, K, FR | ES), "dist")


@query
def hybrid_postfilter(spark, sf_dir):
    index, attrs, q = _setup(spark, sf_dir)
    return rounded(hybrid.postfilter(index, attrs, q, K, calibrated(spark, sf_dir), FR | ES), "dist")


@query
def hybrid_postfilter_naive(spark, sf_dir):
    index, attrs, q = _setup(spark, sf_dir)
    return rounded(hybrid.postfilter(index, attrs, q, K, calibrated(spark, sf_dir), FR | ES, fused=False), "dist")


@query
def hybrid_postfilter_wide(spark, sf_dir):
    """Probes are doubled until ten rows qualify; under a rare predicate that reads everything."""
    index, attrs, q = _setup(spark, sf_dir)
    return rounded(hybrid.postfilter(index, attrs, q, K, 1, Leaf("n_chars", "<", 50), widen=True), "dist")


@query
def hybrid_auto(spark, sf_dir):
    """A rare predicate (filtered first) and a common one (filtered in the scan)."""
    index, attrs, q = _setup(spark, sf_dir)
    stats, probes = statistics.stored_statistics(index), calibrated(spark, sf_dir)
    out = None
    for name, p in (("src3", SRC3), ("en", EN)):
        found, plan = hybrid.hybrid(index, attrs, stats, q, K, probes, p)
        one = found.select(F.lit(name).alias("pred"), F.lit(plan.kind).alias("plan"), "rank", "vec_id", "dist")
        out = one if out is None else out.unionByName(one)
    return rounded(out, "dist")


@query
def hybrid_match(spark, sf_dir):
    index, attrs, q = _setup(spark, sf_dir)
    return rounded(hybrid.prefilter(index, attrs, q, K, match_all("tokens", ["the", "of"])), "dist")


_FR_ES = "lang = 'fr' OR lang = 'es'"
SQL |= {"hybrid_prefilter": pre_sql(_FR_ES), "hybrid_postfilter": post_sql(_FR_ES), "hybrid_postfilter_naive": _ranked_sql(_FR_ES, True)}
SQL["hybrid_postfilter_wide"] = pre_sql("n_chars < 50")
SQL["hybrid_match"] = pre_sql("list_contains(tokens, 'the') AND list_contains(tokens, 'of')")
_CHOSEN = "(SELECT CASE WHEN count(*) FILTER ({where}) < {n} * (SELECT count(*) FROM x) / (SELECT count(*) FROM cen) THEN 'pre' ELSE 'post' END FROM documents JOIN embeddings ON vec_id = doc_id)"
SQL["hybrid_auto"] = " UNION ALL ".join(
    f"SELECT '{name}' AS pred, '{kind}' AS plan, rank, vec_id, dist FROM ({make(p.to_sql()).replace(' QUALIFY rank', f' AND {_CHOSEN.format(where=p.to_sql(), n=O.N)} = {kind!r} QUALIFY rank')})"
    for name, p in (("src3", SRC3), ("en", EN))
    for kind, make in (("pre", pre_sql), ("post", post_sql))
)


@query
def hybrid_batch(spark, sf_dir):
    """A batch in which even queries ask for English and odd ones for middle-sized documents."""
    index, attrs, _ = _setup(spark, sf_dir)
    asked = query_batch(spark, sf_dir)
    predicates = {r.qid: EN if r.qid // EVERY % 2 == 0 else MIDDLE for r in asked.select("qid").collect()}
    return rounded(hybrid.hybrid_batch(index, attrs, asked, K, calibrated(spark, sf_dir), predicates), "dist")


SQL["hybrid_batch"] = (
    O.index()
    + f""", {ATTRIBUTES}, q AS (SELECT vec_id AS qid, e AS qe FROM x WHERE vec_id % {EVERY} = 0),
pr AS MATERIALIZED (SELECT qid, part_id FROM q, cen QUALIFY row_number() OVER (PARTITION BY qid ORDER BY {O.l2('c', 'qe')}, part_id) <= {O.N})
SELECT qid, row_number() OVER (PARTITION BY qid ORDER BY {O.l2('e', 'qe')}, vec_id)::INT AS rank, vec_id, round({O.l2('e', 'qe')}, 6) AS dist
FROM q JOIN pr USING (qid) JOIN p USING (part_id) JOIN att ON asset_id = vec_id
WHERE CASE WHEN qid // {EVERY} % 2 = 0 THEN lang = 'en' ELSE n_chars BETWEEN 1000 AND 3000 END QUALIFY rank <= {K}"""
)


@query
def postings_intersection(spark, sf_dir):
    return hybrid.assets_with_all(hybrid.postings(attributes(spark, sf_dir)), ["the", "of", "is"])


SQL["postings_intersection"] = f"WITH {ATTRIBUTES} SELECT asset_id FROM att WHERE list_contains(tokens, 'the') AND list_contains(tokens, 'of') AND list_contains(tokens, 'is')"

#: Queries a bin, probes (the share of rows that these read is what matters) and neighbours of the experiment on selectivity.
PER_BIN, BIN_PROBES, BIN_K = 10, 1, 100

_binned: dict[tuple, str] = {}


def bin_queries(spark, sf_dir):
    """``(qid, token, mate, qvec, df, bin)``: for every decade of a token's share, ten vectors with a token of their own
    document, picked by md5; ``mate`` is the document's most frequent token, and a query asks for both."""
    attrs = attributes(spark, sf_dir)
    n = attrs.count()
    posts = hybrid.postings(attrs)
    df = posts.groupBy("token").agg(F.count("*").alias("df"))
    decade = F.when(F.col("df") * 10 >= n, -1).when(F.col("df") * 100 >= n, -2).when(F.col("df") * 1000 >= n, -3).otherwise(-4)
    keyed = posts.join(df, "token").withColumn("bin", decade).withColumn("_key", F.md5(F.concat_ws(":", "asset_id", "token").cast("binary")))
    place = F.row_number().over(W.partitionBy("bin").orderBy("_key"))
    chosen = keyed.withColumn("_place", place).where(F.col("_place") <= PER_BIN)
    mates = keyed.join(F.broadcast(chosen.select("asset_id").distinct()), "asset_id", "left_semi").groupBy("asset_id").agg(F.max_by("token", F.struct("df", "token")).alias("mate"))
    vectors = standard_index(spark, sf_dir).live().select(F.col("vec_id").alias("asset_id"), F.col("embedding").alias("qvec"))
    numbered = chosen.join(mates, "asset_id").join(vectors, "asset_id")
    return numbered.select(((F.col("bin") + 4) * 100 + F.col("_place")).cast("long").alias("qid"), "token", "mate", "qvec", "df", "bin"), posts


def bin_results(spark, sf_dir):
    """Per query of the bins: recall of the three ways to run it, each run as a batch, and the plan chosen for it from the
    stored statistics. The truth comes from postings, not from an index."""
    key = (spark.sparkContext.applicationId, sf_dir)
    if key not in _binned:
        index = attributed_index(spark, sf_dir)
        attrs, stats = index.attributes(), statistics.stored_statistics(index)
        found, posts = bin_queries(spark, sf_dir)
        queries = materialize(found, "bins")
        predicates = {r.qid: match_all("tokens", [r.token, r.mate]) for r in queries.select("qid", "token", "mate").collect()}
        stats.frequencies("tokens", {x.value for p in predicates.values() for x in statistics.leaves(p)})
        both = queries.join(posts, "token").join(posts.withColumnRenamed("token", "mate"), ["mate", "asset_id"])
        vectors = index.live().select("asset_id", "vec_id", "embedding")
        scored = both.join(vectors, "asset_id").select("qid", "vec_id", distance(F.col("embedding"), F.col("qvec"), index.metric).alias("dist"))
        truth = materialize(search.top_k_per_query(scored, BIN_K), "truth")
        auto, plans = hybrid.hybrid_each(index, attrs, stats, queries, BIN_K, BIN_PROBES, predicates)
        ways = {
            "pre": hybrid.prefilter_batch(index, attrs, queries, BIN_K, predicates),
            "post": hybrid.hybrid_batch(index, attrs, queries, BIN_K, BIN_PROBES, predicates),
            "auto": auto,
        }
        out = queries.select("qid", "bin", "df")
        for way, rows in ways.items():
            out = out.join(measures.recall_at_k(rows, truth, BIN_K).withColumnRenamed("recall", f"recall_{way}"), "qid")
        chosen = spark.createDataFrame([(q, p.kind, float(p.f_filters)) for q, p in plans.items()], "qid long, plan string, f_filters double")
        kept = materialize(out.join(F.broadcast(chosen), "qid"), "bins")  # as many rows as queries
        _binned[key] = kept.inputFiles()[0].rsplit("/", 1)[0]
    return spark.read.parquet(_binned[key])


@query
def hybrid_bins(spark, sf_dir):
    return bin_queries(spark, sf_dir)[0].select("qid", "token", "mate", "df", "bin")


@query
def recall_hybrid(spark, sf_dir):
    rows = bin_results(spark, sf_dir).select("qid", "bin", "df", "plan", "f_filters", "recall_pre", "recall_post", "recall_auto")
    return rounded(rows, "f_filters", "recall_pre", "recall_post", "recall_auto")


@query
def hybrid_recall_by_bin(spark, sf_dir):
    g = bin_results(spark, sf_dir).groupBy("bin").agg(F.count("*").alias("queries"), *[F.avg(c).alias(c) for c in ("recall_pre", "recall_post", "recall_auto")])
    return rounded(g, "recall_pre", "recall_post", "recall_auto")


@query
def hybrid_plan_by_bin(spark, sf_dir):
    return bin_results(spark, sf_dir).groupBy("bin", "plan").agg(F.count("*").alias("queries"))


_BINS = (
    O.index()
    + f""", {ATTRIBUTES}, nn AS (SELECT count(*) AS n, (SELECT count(*) FROM x) / (SELECT count(*) FROM cen) AS size FROM att), po AS MATERIALIZED (SELECT asset_id, unnest(tokens) AS token FROM att),
df AS MATERIALIZED (SELECT token, count(*) AS df FROM po GROUP BY token),
mt AS MATERIALIZED (SELECT asset_id, arg_max(token, (df, token)) AS mate FROM po JOIN df USING (token) GROUP BY asset_id),
bk AS (SELECT asset_id, token, df, CASE WHEN df * 10 >= n THEN -1 WHEN df * 100 >= n THEN -2 WHEN df * 1000 >= n THEN -3 ELSE -4 END AS bin FROM po JOIN df USING (token), nn),
bq AS MATERIALIZED (SELECT asset_id, token, df, bin, row_number() OVER (PARTITION BY bin ORDER BY md5(asset_id || ':' || token)) AS pl FROM bk QUALIFY pl <= {PER_BIN}),
q AS MATERIALIZED (SELECT ((bin + 4) * 100 + pl)::BIGINT AS qid, token, mate, e AS qe, df, bin::INT AS bin FROM bq JOIN mt USING (asset_id) JOIN p ON vec_id = asset_id),
pr AS MATERIALIZED (SELECT qid, part_id FROM q, cen QUALIFY row_number() OVER (PARTITION BY qid ORDER BY {O.l2('c', 'qe')}, part_id) <= {BIN_PROBES}),
sd AS MATERIALIZED (SELECT qid, part_id, vec_id, {O.l2('e', 'qe')} AS d FROM q JOIN po USING (token) JOIN po pm ON pm.token = q.mate AND pm.asset_id = po.asset_id JOIN p ON p.vec_id = po.asset_id),
tr AS MATERIALIZED (SELECT qid, vec_id FROM sd QUALIFY row_number() OVER (PARTITION BY qid ORDER BY d, vec_id) <= {BIN_K}),
fo AS MATERIALIZED (SELECT qid, vec_id FROM sd JOIN pr USING (qid, part_id) QUALIFY row_number() OVER (PARTITION BY qid ORDER BY d, vec_id) <= {BIN_K}),
sz AS (SELECT qid, count(*) AS size, count(*) FILTER ((qid, vec_id) IN (SELECT (qid, vec_id) FROM fo)) AS hits FROM tr GROUP BY qid),
fe AS (SELECT q.qid, least(q.df, d.df) / n AS f FROM q JOIN df d ON d.token = q.mate, nn),
rs AS MATERIALIZED (SELECT qid, bin, df, f, CASE WHEN f < {BIN_PROBES} * avg_size / n THEN 'pre' ELSE 'post' END AS plan, hits / sz.size AS post FROM q JOIN sz USING (qid) JOIN fe USING (qid), (SELECT n, size AS avg_size FROM nn) nx),
ra AS (SELECT qid, bin, df, f AS f_filters, plan, 1.0::DOUBLE AS recall_pre, post AS recall_post, CASE WHEN plan = 'pre' THEN 1.0 ELSE post END AS recall_auto FROM rs)"""
)
SQL["hybrid_bins"] = _BINS + " SELECT qid, token, mate, df, bin FROM q"
SQL["recall_hybrid"] = _BINS + " SELECT qid, bin, df, plan, round(f_filters, 6) AS f_filters, recall_pre, round(recall_post, 6) AS recall_post, round(recall_auto, 6) AS recall_auto FROM ra"
SQL["hybrid_recall_by_bin"] = _BINS + " SELECT bin, count(*) AS queries, round(avg(recall_pre), 6) AS recall_pre, round(avg(recall_post), 6) AS recall_post, round(avg(recall_auto), 6) AS recall_auto FROM ra GROUP BY bin"
SQL["hybrid_plan_by_bin"] = _BINS + " SELECT bin, plan, count(*) AS queries FROM ra GROUP BY bin, plan"
