"""Upserts, deletes, flush, rebuild, monitoring, snapshots and streams."""

from __future__ import annotations

import time
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ivfspark import oracles as O
from ivfspark.catalog.common import CONFIG, K, Q0, calibrated, private_index, query_vector, rounded
from ivfspark.operators import measures, search, serving, updates
from ivfspark.operators.prefix import running_total
from ivfspark.plans.scratch import copied, materialize, scratch_path
from ivfspark.sources import collections
from ivfspark.sources.collections import table
from ivfspark.sources.index import Index, open_index
from ivfspark.streaming import ingest

QUERIES_BY_KEY: dict = {}
SQL: dict[str, str] = {}

_changed: dict[tuple, str] = {}
_flushed: dict[tuple, str] = {}


def query(fn):
    QUERIES_BY_KEY[fn.__name__] = fn
    return fn


def changes_of(spark: SparkSession, sf_dir: str) -> DataFrame:
    v = collections.v1(spark, sf_dir)
    return ingest.event_changes(table(spark, sf_dir, "events"), v, v.count())


def changed_index(spark: SparkSession, sf_dir: str) -> Index:
    """The base index (version 0) after the first and second half of the events (versions 1 and 2)."""
    key = (spark.sparkContext.applicationId, sf_dir)
    if key not in _changed:
        index = private_index(spark, sf_dir)
        half = table(spark, sf_dir, "events").count() // 2
        changes = changes_of(spark, sf_dir)
        index = updates.apply_changes(index, changes.where(F.col("seq") <= half))
        updates.apply_changes(index, changes.where(F.col("seq") > half))
        _changed[key] = index.store.path
    return open_index(spark, _changed[key], 2)


def flushed_index(spark: SparkSession, sf_dir: str) -> Index:
    key = (spark.sparkContext.applicationId, sf_dir)
    if key not in _flushed:
        index = private_index(spark, sf_dir)
        updates.flush(updates.apply_changes(index, changes_of(spark, sf_dir)))
        _flushed[key] = index.store.path
    return open_index(spark, _flushed[key])


def state_sql(limit: str = "9000000000", x: str = "") -> str:
    """SQL of the state after events up to a sequence number: ``st`` (last changes) and ``lv`` (live rows)."""
    return f"""{x}ev AS (SELECT user_id AS asset_id, event_id + 1 AS seq, event_type, 1000000000 + event_id AS vec_id, event_id % (SELECT count(*) FROM x) AS src
  FROM events WHERE event_type <> 'click' AND event_id + 1 <= {limit}),
{x}st AS MATERIALIZED (SELECT ev.*, x.e FROM {x}ev ev JOIN x ON x.vec_id = src QUALIFY row_number() OVER (PARTITION BY asset_id ORDER BY seq DESC) = 1),
{x}lv AS MATERIALIZED (SELECT asset_id, seq, vec_id, e FROM {x}st WHERE event_type <> 'error'
  UNION ALL SELECT vec_id, 0, vec_id, e FROM x WHERE vec_id NOT IN (SELECT asset_id FROM {x}st))"""


_STATE = f"WITH x AS ({O.V1}), {state_sql()}"
_INDEXED = O.index() + ", " + state_sql()
_PLACED = ", pl AS MATERIALIZED (SELECT lv.*, CASE WHEN seq > 0 THEN -1 ELSE p.part_id END AS part_id FROM lv LEFT JOIN p ON p.vec_id = lv.vec_id)"
_VISIBLE = f"(part_id = -1 OR part_id IN {O.probes(Q0)})"
_FLUSHED = f""", fl AS MATERIALIZED (SELECT asset_id, vec_id, e, arg_min(part_id, (d, part_id)) AS part_id FROM (
  SELECT asset_id, vec_id, e, part_id, {O.l2('e', 'c')} AS d FROM lv, cen WHERE seq > 0) GROUP BY asset_id, vec_id, e),
af AS MATERIALIZED (SELECT asset_id, vec_id, e, part_id FROM fl UNION ALL SELECT lv.asset_id, lv.vec_id, lv.e, p.part_id FROM lv JOIN p ON p.vec_id = lv.vec_id WHERE seq = 0)"""
_D = O.l2("e", Q0)


def _search_sql(source: str, where: str) -> str:
    return f" SELECT row_number() OVER (ORDER BY {_D}, vec_id)::INT AS rank, vec_id, round({_D}, 6) AS dist FROM {source} WHERE {where} QUALIFY rank <= {K}"


@query
def upsert_state(spark, sf_dir):
    """Live assets after all events, and which vector each has."""
    return changed_index(spark, sf_dir).live().select("asset_id", "vec_id", "seq")


@query
def delete_state(spark, sf_dir):
    """Assets whose last change was a delete."""
    index = changed_index(spark, sf_dir)
    gone = index.tombstones().groupBy("asset_id").agg(F.max("seq").alias("seq"))
    return gone.join(index.live().select("asset_id"), "asset_id", "left_anti")


@query
def delta_share(spark, sf_dir):
    index = changed_index(spark, sf_dir)
    delta, live = index.live_delta().count(), index.live().count()
    return rounded(spark.createDataFrame([(delta, live, delta / live)], "n_delta long, n_live long, share double"), "share")


@query
def union_delta(spark, sf_dir):
    """Rows that a search reads, by where they are."""
    index = changed_index(spark, sf_dir)
    parts = search.probe(index.centroids(), query_vector(spark, sf_dir), calibrated(spark, sf_dir))
    return index.live(parts).groupBy("part_id").agg(F.count("*").alias("n"))


@query
def ann_with_delta(spark, sf_dir):
    """Search while the changes are in the delta."""
    return rounded(search.ann(changed_index(spark, sf_dir), query_vector(spark, sf_dir), K, calibrated(spark, sf_dir)), "dist")


@query
def ann_after_delete(spark, sf_dir):
    """The three nearest assets are deleted; none of them comes back."""
    index, n = private_index(spark, sf_dir), calibrated(spark, sf_dir)
    q = query_vector(spark, sf_dir)
    gone = search.ann(index, q, 3, n).select(F.col("vec_id").alias("asset_id"))
    return rounded(search.ann(updates.delete(index, gone), q, K, n), "dist")


@query
def flush_assign(spark, sf_dir):
    """Partitions of all live assets after the delta was flushed."""
    return flushed_index(spark, sf_dir).live().select("asset_id", "vec_id", "part_id")


@query
def flush_centroids(spark, sf_dir):
    """Centres after their drift to the flushed vectors."""
    rows = flushed_index(spark, sf_dir).centroid_rows().select("part_id", "n_members", F.posexplode("centroid").alias("dim", "value"))
    return rounded(rows.withColumn("dim", F.col("dim") + 1), "value")


@query
def ann_after_flush(spark, sf_dir):
    return rounded(search.ann(flushed_index(spark, sf_dir), query_vector(spark, sf_dir), K, 100_000), "dist")


@query
def rebuild_sizes(spark, sf_dir):
    """Partition sizes after a rebuild over the live rows."""
    index = private_index(spark, sf_dir)
    rebuilt = updates.rebuild(updates.apply_changes(index, changes_of(spark, sf_dir)))
    return rebuilt.main().groupBy("part_id").agg(F.count("*").alias("size"))


SQL |= {
    "upsert_state": _STATE + " SELECT asset_id, vec_id, seq FROM lv",
    "delete_state": _STATE + " SELECT asset_id, seq FROM st WHERE event_type = 'error'",
    "delta_share": _STATE + " SELECT count(*) FILTER (seq > 0) AS n_delta, count(*) AS n_live, round(count(*) FILTER (seq > 0) / count(*), 6) AS share FROM lv",
    "union_delta": _INDEXED + _PLACED + f" SELECT part_id, count(*) AS n FROM pl WHERE {_VISIBLE} GROUP BY part_id",
    "ann_with_delta": _INDEXED + _PLACED + _search_sql("pl", _VISIBLE),
    "ann_after_delete": O.index()
    + f", f AS (SELECT vec_id, {_D} AS d, row_number() OVER (ORDER BY {_D}, vec_id) AS r FROM p WHERE part_id IN {O.probes(Q0)}) SELECT (r - 3)::INT AS rank, vec_id, round(d, 6) AS dist FROM f WHERE r BETWEEN 4 AND {K + 3}",
    "flush_assign": _INDEXED + _FLUSHED + " SELECT asset_id, vec_id, part_id FROM af",
    "flush_centroids": _INDEXED
    + _FLUSHED
    + """, mem AS (SELECT part_id, count(*) FILTER (vec_id NOT IN (SELECT asset_id FROM st)) AS n FROM p GROUP BY part_id),
fs AS (SELECT part_id, dim, sum(floor(e[dim] * 1073741824 + 0.5)::BIGINT)::BIGINT AS s, count(*) AS m FROM (SELECT part_id, e, unnest(range(1, len(e) + 1)) AS dim FROM fl) GROUP BY part_id, dim),
cd AS (SELECT part_id, unnest(range(1, len(c) + 1)) AS dim, c FROM cen)
SELECT cd.part_id, n + coalesce(m, 0) AS n_members, cd.dim::INT AS dim, round(CASE WHEN m IS NULL THEN c[cd.dim] ELSE (n * c[cd.dim] + s::DOUBLE / 1073741824) / (n + m) END, 6) AS value
FROM cd JOIN mem USING (part_id) LEFT JOIN fs ON fs.part_id = cd.part_id AND fs.dim = cd.dim""",
    "ann_after_flush": _STATE + _search_sql("lv", "true"),
    "rebuild_sizes": f"WITH x AS ({O.V1}), {state_sql()}, " + O.training("SELECT vec_id, e FROM lv", prefix="r_") + " SELECT part_id, count(*) AS size FROM r_p GROUP BY part_id",
}


@query
def monitor_growth(spark, sf_dir):
    """Health and the monitor's choice before and after the flush."""
    rows = []
    for step, index in (("delta", changed_index(spark, sf_dir)), ("flushed", flushed_index(spark, sf_dir))):
        h = updates.monitor(index)
        rows.append((step, h.average, h.growth, updates.action(h, 0.2)))
    return rounded(spark.createDataFrame(rows, "step string, average double, growth double, action string"), "average", "growth")


SQL["monitor_growth"] = (
    _STATE
    + """, b AS (SELECT count(*) AS n, greatest(1, count(*) // 50) AS k FROM x), f AS (SELECT count(*) AS f FROM lv)
SELECT 'delta' AS step, round(n / k, 6) AS average, 0.0::DOUBLE AS growth, 'flush' AS action FROM b
UNION ALL SELECT 'flushed', round(f / k, 6), round(f / n - 1, 6), CASE WHEN f / n - 1 > 0.2 THEN 'rebuild' ELSE 'none' END FROM b, f"""
)


def _flush_and_rebuild(spark, sf_dir):
    """What the jobs of a flush and of a rebuild of the same changes read and wrote, by their task metrics."""
    out = []
    for name, step in (("flush", updates.flush), ("rebuild", updates.rebuild)):
        io = updates.IoCounter()
        step(updates.apply_changes(private_index(spark, sf_dir), changes_of(spark, sf_dir)), io)
        out.append((name, io))
    return out


@query
def io_incremental_vs_full(spark, sf_dir):
    """Rows written by a flush and by a rebuild, counted by their tasks."""
    rows = [(name, io.rows_written) for name, io in _flush_and_rebuild(spark, sf_dir)]
    return spark.createDataFrame(rows, "policy string, rows_written long")


@query
def io_measured(spark, sf_dir):
    """Rows, bytes and seconds of a flush and of a rebuild, as measured."""
    rows = [(name, io.rows_read, io.rows_written, io.bytes_read, io.bytes_written, io.seconds) for name, io in _flush_and_rebuild(spark, sf_dir)]
    return spark.createDataFrame(rows, "policy string, rows_read long, rows_written long, bytes_read long, bytes_written long, seconds double")


SQL["io_incremental_vs_full"] = (
    _INDEXED
    + _FLUSHED
    + """, k AS (SELECT count(*) AS k FROM cen), f AS (SELECT count(*) AS f FROM fl), l AS (SELECT count(*) AS n FROM lv)
SELECT 'flush' AS policy, 2 * f + k AS rows_written FROM f, k
UNION ALL SELECT 'rebuild', n + greatest(1, n // 50) FROM l"""
)

#: The growth experiment: share of all rows that an epoch adds to the first half, growth limit, epochs that reach all rows, queries, neighbours.
GROWTH_SHARE, GROWTH_LIMIT, GROWTH_EPOCHS, GROWTH_QUERIES, GROWTH_K = 0.03, 0.5, 17, 128, 100
GROWTH_CONFIG = replace(CONFIG, target_size=100)
#: Epochs of the queries that run one of the policies compared with.
OTHER_EPOCHS = 12

_grown: dict[tuple, str] = {}
_started: dict[tuple, tuple] = {}
_asked: dict[tuple, tuple] = {}


def _start(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, int, str]:
    """What every policy starts from: the orders by place, their number, and the index of the first half."""
    key = (spark.sparkContext.applicationId, sf_dir)
    if key not in _started:
        v = collections.v4(spark, sf_dir)
        ranked = materialize(running_total(v, F.floor(F.col("vec_id") / 4096), [F.col("vec_id")], F.lit(1).cast("long"), "place"), "orders")
        n = ranked.count()
        _started[key] = ranked, n, private_index(spark, sf_dir, GROWTH_CONFIG, ranked.where(F.col("place") < n // 2).drop("place")).store.path
    return _started[key]


def _bounds(n: int) -> list[int]:
    """Visible rows at the start and after every epoch."""
    return [min(n, n // 2 + epoch * int(n * GROWTH_SHARE)) for epoch in range(GROWTH_EPOCHS + 1)]


def growth_truth(ranked: DataFrame, queries: DataFrame, bounds: list[int], k: int) -> DataFrame:
    """``(epoch, qid, vec_id)``: exact neighbours among the rows that are visible after each epoch. Rows only come in, so
    each is compared once: the nearest of every epoch's own rows, merged with those of the epochs before it."""
    own = None
    for epoch, (lo, hi) in enumerate(zip([0, *bounds], bounds, strict=False)):
        rows = ranked.where((F.col("place") >= lo) & (F.col("place") < hi)).drop("place")
        one = search.knn_exact_batch(rows, queries, k, GROWTH_CONFIG.metric).withColumn("since", F.lit(epoch).cast("long"))
        own = one if own is None else own.unionByName(one)
    own, epochs = materialize(own.drop("rank"), "nearest"), ranked.sparkSession.range(1, len(bounds)).withColumnRenamed("id", "epoch")
    place = F.row_number().over(W.partitionBy("epoch", "qid").orderBy("dist", "vec_id"))
    merged = own.join(F.broadcast(epochs), F.col("since") <= F.col("epoch")).withColumn("rank", place)
    return materialize(merged.where(F.col("rank") <= k).select("epoch", "qid", "vec_id"), "truth")


def _questions(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, list, int, DataFrame]:
    """The query batch, its vectors, the probes that it takes at the start, and its true neighbours after each epoch."""
    key = (spark.sparkContext.applicationId, sf_dir)
    if key not in _asked:
        ranked, n, path = _start(spark, sf_dir)
        first = F.md5(F.col("vec_id").cast("string").cast("binary"))
        chosen = ranked.where(F.col("place") < n // 2).orderBy(first).limit(GROWTH_QUERIES)
        queries = materialize(chosen.select(F.col("vec_id").alias("qid"), F.col("embedding").alias("qvec")), "queries")
        probes = search.calibrate_probes(open_index(spark, path), queries, GROWTH_K, 0.9)
        _asked[key] = queries, [r.qvec for r in queries.collect()], probes, growth_truth(ranked, queries, _bounds(n), GROWTH_K)
    return _asked[key]


def _latency(index: Index, vectors: list, n: int) -> float:
    server = serving.DiskServer(index)
    began = time.perf_counter()
    for q in vectors:
        server.search(q, GROWTH_K, n)
    return 1000 * (time.perf_counter() - began) / max(1, len(vectors))


def grown(spark: SparkSession, sf_dir: str, policy: str, epochs: int, measured: bool = False) -> DataFrame:
    """The growth experiment on real versions of an index of the order vectors: half of the rows, then 3 % of all an epoch.

    Probes follow the average partition. Recall is over the visible rows; rows and bytes are those that the jobs
    of an epoch's maintenance wrote and read; latencies are of single searches of the whole batch before and after it.
    Probes, recall and latencies are taken where ``measured``, else null.
    """
    key = (spark.sparkContext.applicationId, sf_dir, policy, epochs, measured)
    if key not in _grown:
        ranked, n, start = _start(spark, sf_dir)
        index, bounds = open_index(spark, copied(spark, start, "grown")), _bounds(n)
        queries, timed, probes, truth = _questions(spark, sf_dir) if measured else (None, [], None, None)
        rows, built, answers = [], index.manifest["avg_at_build"], scratch_path(spark, "answers")
        for epoch in range(1, epochs + 1):
            new = (F.col("place") >= bounds[epoch - 1]) & (F.col("place") < bounds[epoch])
            index = updates.upsert(index, ranked.where(new).drop("place").withColumn("asset_id", F.col("vec_id")))
            own = lambda: search.rescale_probes(probes, built, updates.monitor(index).average)  # noqa: B023, E731
            before, io = _latency(index, timed, own()) if measured else None, updates.IoCounter()
            flushed, act = updates.maintain(index, GROWTH_LIMIT, policy=policy, io=io)
            health = updates.Health(flushed.average, (flushed.manifest["n_main"] / index.manifest["k"]) / index.manifest["avg_at_build"] - 1, 0.0)
            index = flushed
            after = _latency(index, timed, own()) if measured else None
            if measured:
                search.ann_batch(index, queries, GROWTH_K, own()).select(F.lit(epoch).cast("long").alias("epoch"), "qid", "vec_id").write.mode("append").parquet(answers)
            m = index.manifest
            rows.append((epoch, m["n_main"], m["n_delta"], health.average, health.growth, act, io.rows_written, io.rows_read, io.bytes_read + io.bytes_written, own() if measured else None, before, after))
        schema = "epoch long, n long, n_delta long, average double, growth double, action string, rows_written long, rows_read long, bytes long, n_probe long, before_ms double, after_ms double"
        grew, path = spark.createDataFrame(rows, schema), scratch_path(spark, f"growth-{policy}")
        if measured:
            asked = F.struct("epoch", "qid").alias("qid")  # one query in one epoch
            found = spark.read.schema("epoch long, qid long, vec_id long").parquet(answers)
            each = measures.recall_at_k(found.select(asked, "vec_id"), truth.where(F.col("epoch") <= epochs).select(asked, "vec_id"), GROWTH_K)
            grew = grew.join(each.groupBy(F.col("qid.epoch").alias("epoch")).agg(F.avg("recall").alias("recall")), "epoch", "left")
        else:
            grew = grew.withColumn("recall", F.lit(None).cast("double"))
        grew.coalesce(1).write.parquet(path)
        _grown[key] = path
    return spark.read.parquet(_grown[key])


def growth_table(spark: SparkSession, n: int, epochs: int, target: int, share: float = 0.03, limit: float = 0.5, policy: str = "auto") -> DataFrame:
    """Bootstrap with half of ``n``, then ``share`` of all rows an epoch, under the monitor's own rules.

    A forecast from row counts only; ``grown`` runs the real thing.
    """
    rows, main = [], n // 2
    k = max(1, main // target)
    built = main / k
    step = int(n * share)
    for epoch in range(1, epochs + 1):
        main += step
        average = main / k
        growth = average / built - 1
        act, written = "flush", step
        if policy == "rebuild_always" or updates.action(updates.Health(average, growth, 0.0), limit, 1.0) == "rebuild":
            act, k = "rebuild", max(1, main // target)
            built, written = main / k, main + k
        rows.append((epoch, main, main / k, growth, act, written))
    return spark.createDataFrame(rows, "epoch long, n long, average double, growth double, action string, rows_written long")


_GROWTH = ("epoch", "n", "average", "growth", "action", "rows_written")


@query
def growth_epochs(spark, sf_dir):
    """State after each epoch, and rows written by its maintenance, under the monitor's own rules."""
    return rounded(grown(spark, sf_dir, "auto", GROWTH_EPOCHS).select(*_GROWTH), "average", "growth")


@query
def growth_epochs_rebuild_always(spark, sf_dir):
    """Baseline: a rebuild after every epoch."""
    return rounded(grown(spark, sf_dir, "rebuild_always", OTHER_EPOCHS).select(*_GROWTH), "average", "growth")


@query
def growth_never_flush(spark, sf_dir):
    """Baseline: the delta only grows, and every search reads all of it."""
    return grown(spark, sf_dir, "never", OTHER_EPOCHS).select("epoch", "n", "n_delta", "action", "rows_written")


def _growth_sql(always: bool, epochs: int) -> str:
    rebuild = "true" if always else f"m / r.k / r.built - 1 > {GROWTH_LIMIT}"
    written = "m + greatest(1, m // 100)" if always else f"2 * (m - r.n) + r.k + CASE WHEN {rebuild} THEN m + greatest(1, m // 100) ELSE 0 END"
    return f"""WITH RECURSIVE c AS (SELECT count(*) AS n, floor(count(*) * {GROWTH_SHARE})::BIGINT AS st FROM orders),
r AS (SELECT 0::BIGINT AS epoch, n // 2 AS n, greatest(1, (n // 2) // 100) AS k, (n // 2) / greatest(1, (n // 2) // 100) AS built, 0.0::DOUBLE AS growth, '' AS action, 0::BIGINT AS written FROM c
UNION ALL SELECT epoch + 1, m, CASE WHEN {rebuild} THEN greatest(1, m // 100) ELSE r.k END,
  CASE WHEN {rebuild} THEN m / greatest(1, m // 100) ELSE built END, m / r.k / built - 1,
  CASE WHEN {rebuild} THEN 'rebuild' ELSE 'flush' END, {written} FROM (SELECT r.*, least(c.n, r.n + st) AS m FROM r, c) r WHERE epoch < {epochs})
SELECT epoch, n, round(n / k, 6) AS average, round(growth, 6) AS growth, action, written AS rows_written FROM r WHERE epoch > 0"""


SQL["growth_epochs"], SQL["growth_epochs_rebuild_always"] = _growth_sql(False, GROWTH_EPOCHS), _growth_sql(True, OTHER_EPOCHS)
SQL["growth_never_flush"] = f"SELECT i::BIGINT AS epoch, n // 2 AS n, i * floor(n * {GROWTH_SHARE})::BIGINT AS n_delta, 'none' AS action, 0::BIGINT AS rows_written FROM (SELECT count(*) AS n FROM orders), (SELECT unnest(range(1, {OTHER_EPOCHS + 1})) AS i)"


@query
def growth_recall(spark, sf_dir):
    """Recall, probes, I/O and latencies by epoch, for the monitor's policy and the two it is compared with."""
    out = None
    for policy in ("auto", "rebuild_always", "never"):
        one = grown(spark, sf_dir, policy, GROWTH_EPOCHS, True).select(F.lit(policy).alias("policy"), "epoch", "action", "n_probe", "recall", "rows_read", "rows_written", "bytes", "before_ms", "after_ms")
        out = one if out is None else out.unionByName(one)
    return rounded(out, "recall")


@query
def snapshot_time_travel(spark, sf_dir):
    """Every version's live assets that differ from the base, read after all commits."""
    path = changed_index(spark, sf_dir).store.path
    out = None
    for version in (0, 1, 2):
        one = open_index(spark, path, version).live().where("seq > 0").select(F.lit(version).alias("version"), "asset_id", "seq")
        out = one if out is None else out.unionByName(one)
    return out


SQL["snapshot_time_travel"] = (
    f"WITH x AS ({O.V1}), {state_sql('(SELECT count(*) // 2 FROM events)', 'h_')}, {state_sql()}"
    + " SELECT 1 AS version, asset_id, seq FROM h_lv WHERE seq > 0 UNION ALL SELECT 2, asset_id, seq FROM lv WHERE seq > 0"
)


@query
def asof_vector_version(spark, sf_dir):
    """The change of the same user that was current at each click: one sort a user, no range join."""
    events = table(spark, sf_dir, "events")
    seen = W.partitionBy("user_id").orderBy("event_id").rowsBetween(W.unboundedPreceding, -1)
    change = F.when(F.col("event_type") != "click", F.col("event_id"))
    joined = events.select("event_id", "user_id", "event_type", F.last(change, ignorenulls=True).over(seen).alias("version"))
    return joined.where("event_type = 'click'").select("event_id", "user_id", "version")


SQL["asof_vector_version"] = """SELECT a.event_id, a.user_id, b.event_id AS version FROM (SELECT * FROM events WHERE event_type = 'click') a
ASOF LEFT JOIN (SELECT * FROM events WHERE event_type <> 'click') b ON a.user_id = b.user_id AND a.event_id > b.event_id"""


def _stream(spark, sf_dir, files: int = 4):
    return ingest.read_events(spark, ingest.replayed(spark, sf_dir, scratch_path(spark, "events"), files))


def run_to_table(stream: DataFrame, mode: str) -> DataFrame:
    """Run a stream over all available files; the result is the last batch (complete) or all (append)."""
    spark = stream.sparkSession
    target = scratch_path(spark, "stream")
    batches: list[int] = []

    def write(df: DataFrame, number: int) -> None:
        df.write.mode("overwrite").parquet(f"{target}/batch={number}")
        batches.append(number)

    stream.writeStream.foreachBatch(write).outputMode(mode).option("checkpointLocation", scratch_path(spark, "offsets")).trigger(availableNow=True).start().awaitTermination()
    chosen = batches[-1:] if mode == "complete" else batches
    return spark.read.schema(stream.schema).parquet(*[f"{target}/batch={b}" for b in chosen])


def _times(df: DataFrame) -> DataFrame:
    return df.withColumns({c: F.col(c).cast("timestamp_ntz") for c in ("w_start", "w_end")})


@query
def stream_tumbling(spark, sf_dir):
    return _times(run_to_table(ingest.tumbling(ingest.with_time(_stream(spark, sf_dir))), "complete"))


@query
def stream_sliding(spark, sf_dir):
    return _times(run_to_table(ingest.sliding(ingest.with_time(_stream(spark, sf_dir))), "complete"))


@query
def stream_session(spark, sf_dir):
    return _times(run_to_table(ingest.sessions(ingest.with_time(_stream(spark, sf_dir))), "complete"))


SQL["stream_tumbling"] = "SELECT time_bucket(INTERVAL 1 DAY, ts) AS w_start, time_bucket(INTERVAL 1 DAY, ts) + INTERVAL 1 DAY AS w_end, event_type, count(*) AS n FROM events GROUP BY 1, 2, 3"
SQL["stream_sliding"] = (
    "SELECT w AS w_start, w + INTERVAL 2 DAY AS w_end, count(*) AS n FROM (SELECT unnest([date_trunc('day', ts)::TIMESTAMP, date_trunc('day', ts)::TIMESTAMP - INTERVAL 1 DAY]) AS w FROM events) GROUP BY w"
)
SQL["stream_session"] = """WITH g AS (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS b FROM events),
s AS (SELECT *, sum(b) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS sid FROM g)
SELECT min(ts) AS w_start, max(ts) + INTERVAL 6 HOUR AS w_end, user_id, count(*) AS n FROM s GROUP BY user_id, sid"""


@query
def stream_latest(spark, sf_dir):
    """Stateful latest change a user, as updates; the last update of each is the state."""
    found = run_to_table(ingest.latest_state(_stream(spark, sf_dir)), "update")
    return found.groupBy("asset_id").agg(F.max("seq").alias("seq"), F.max_by("event_type", "seq").alias("event_type"))


SQL["stream_latest"] = "SELECT user_id AS asset_id, max(event_id) AS seq, arg_max(event_type, event_id) AS event_type FROM events WHERE event_type <> 'click' GROUP BY user_id"


@query
def stream_dedup(spark, sf_dir):
    """Events of a replay in which all come twice, each kept once within the watermark."""
    events = ingest.with_time(_stream(spark, sf_dir), "40 days")
    once = events.unionByName(events).dropDuplicatesWithinWatermark(["event_id"])
    return run_to_table(once.select("event_id", "user_id"), "append")


SQL["stream_dedup"] = "SELECT event_id, user_id FROM events"


@query
def stream_final_state(spark, sf_dir):
    """Live assets after the update stream was applied batch by batch, with maintenance in between."""
    index = private_index(spark, sf_dir)
    v = materialize(collections.v1(spark, sf_dir), "vectors")
    source = ingest.event_changes(_stream(spark, sf_dir, 3), v, v.count())
    ingest.stream_updates(source, spark, index.store.path, scratch_path(spark, "offsets"), every=2, growth_limit=10.0).awaitTermination()
    return index.refreshed().live().select("asset_id", "vec_id", "seq")


SQL["stream_final_state"] = SQL["upsert_state"]


@query
def stream_queries(spark, sf_dir):
    """Click events as queries: each arriving batch searches the index; two nearest vectors a click."""
    index = private_index(spark, sf_dir)
    v = materialize(collections.v1(spark, sf_dir), "vectors")
    n = v.count()
    clicks = _stream(spark, sf_dir, 2).where("event_type = 'click'").select(F.col("event_id").alias("qid"), (F.col("event_id") % n).alias("copied"))
    named = v.select(F.col("vec_id").alias("copied"), F.col("embedding").alias("qvec"))
    target, probes = scratch_path(spark, "answers"), calibrated(spark, sf_dir)

    def answer(df: DataFrame, number: int) -> None:
        """Clicks of one vector ask one question: each is searched once, and its answer goes to all its clicks."""
        kept = df.select("qid", "copied").persist()
        asked = materialize(kept.select("copied").distinct().join(named, "copied").withColumnRenamed("copied", "qid"), "asked")
        found = search.ann_batch_written(index, asked, 2, probes).withColumnRenamed("qid", "copied")
        kept.join(found, "copied").select("qid", "rank", "vec_id", "dist").write.mode("append").parquet(target)
        kept.unpersist()

    clicks.writeStream.foreachBatch(answer).option("checkpointLocation", scratch_path(spark, "offsets")).trigger(availableNow=True).start().awaitTermination()
    return rounded(spark.read.schema("qid long, rank int, vec_id long, dist double").parquet(target), "dist")


SQL["stream_queries"] = (
    O.index()
    + f""", n AS (SELECT count(*) AS n FROM x),
pr AS MATERIALIZED (SELECT vec_id AS src, e AS qe, part_id FROM x, cen QUALIFY row_number() OVER (PARTITION BY vec_id ORDER BY {O.l2('c', 'e')}, part_id) <= {O.N}),
nb AS MATERIALIZED (SELECT src, vec_id, {O.l2('e', 'qe')} AS d, row_number() OVER (PARTITION BY src ORDER BY {O.l2('e', 'qe')}, vec_id) AS rank FROM pr JOIN p USING (part_id) QUALIFY rank <= 2)
SELECT event_id AS qid, rank::INT AS rank, vec_id, round(d, 6) AS dist FROM events, n JOIN nb ON src = event_id % n WHERE event_type = 'click'"""
)
