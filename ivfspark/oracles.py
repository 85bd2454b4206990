"""DuckDB SQL builders: the index as one chain of common table expressions, written independently of the
engine (set algebra over the given tables, no engine output)."""

from __future__ import annotations

D = "list_transform(list_zip({a}, {b}), lambda p: p[1]::DOUBLE * p[2]::DOUBLE)"


def dot(a: str, b: str) -> str:
    return f"list_sum(list_transform(list_zip({a}, {b}), lambda p: p[1]::DOUBLE * p[2]::DOUBLE))"


def l2(a: str, b: str) -> str:
    return f"sqrt(list_sum(list_transform(list_zip({a}, {b}), lambda p: (p[1]::DOUBLE - p[2]::DOUBLE) * (p[1]::DOUBLE - p[2]::DOUBLE))))"


def cosine(a: str, b: str) -> str:
    size = f"(sqrt({dot(a, a)}) * sqrt({dot(b, b)}))"
    return f"(CASE WHEN {size} = 0 THEN 1.0 ELSE 1.0 - {dot(a, b)} / {size} END)"


def distance(a: str, b: str, metric: str = "l2") -> str:
    return {"l2": l2, "cosine": cosine}[metric](a, b) if metric != "ip" else f"(-{dot(a, b)})"


V1 = "SELECT vec_id, embedding::DOUBLE[] AS e FROM embeddings"
V2 = "SELECT vec_id, list_transform(embedding, lambda x: (x * (1 + vec_id % 7)::FLOAT)::FLOAT)::DOUBLE[] AS e FROM embeddings"
V3 = (
    "SELECT vec_id, list_transform(list_transform(range(256), lambda i: coalesce(c[i], 0)), lambda y: (y / sqrt(nn))::FLOAT)::DOUBLE[] AS e FROM ("
    "SELECT vec_id, map(list(b), list(n)) AS c, sum(n * n)::DOUBLE AS nn FROM (SELECT doc_id AS vec_id, ('0x' || substr(md5(t), 1, 8))::BIGINT % 256 AS b, count(*)::DOUBLE AS n FROM ("
    "SELECT doc_id, unnest(list_filter(list_transform(regexp_split_to_array(coalesce(text, ''), '[^A-Za-z0-9À-ÿ]+'), lambda t: lower(t)), lambda t: t <> '')) AS t FROM documents) "
    "GROUP BY ALL) GROUP BY vec_id)"
)
DAYS = "datediff('day', DATE '1995-01-01', {c}::DATE)::DOUBLE"
V4 = (
    "SELECT o_orderkey AS vec_id, [(o_totalprice / 500000)::FLOAT, ("
    + DAYS.format(c="o_orderdate")
    + " / 2404)::FLOAT, "
    + ", ".join(f"(CASE WHEN o_orderstatus = '{v}' THEN 1 ELSE 0 END)::FLOAT" for v in "FOP")
    + ", "
    + ", ".join(f"(CASE WHEN o_orderpriority = '{v}' THEN 1 ELSE 0 END)::FLOAT" for v in ("1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED", "5-LOW"))
    + "]::DOUBLE[] AS e FROM orders"
)


def training(
    source: str = V1, target: int = 50, batch: int = 64, iters: int = 6, lam: float = 0.5, seed: int = 42, metric: str = "l2", prefix: str = ""
) -> str:
    """CTEs ``x`` (vectors), ``kk`` (k), ``c0`` .. ``c<iters>`` (part_id, c, v), ``cen``, ``p`` (vec_id, part_id, e)."""
    x = prefix
    ctes = [
        f"{x}x AS MATERIALIZED ({source})",
        f"{x}kk AS (SELECT greatest(1, count(*) // {target}) AS k FROM {x}x)",
        f"""{x}c0 AS MATERIALIZED (SELECT row_number() OVER (ORDER BY md5('{seed}:seed:' || vec_id), vec_id) - 1 AS part_id, e AS c, 0::BIGINT AS v
  FROM {x}x QUALIFY part_id < (SELECT k FROM {x}kk))""",
    ]
    for i in range(1, iters + 1):
        ctes.append(step(i, batch, lam, seed, metric, x))
    ctes.append(f"{x}cen AS MATERIALIZED (SELECT part_id, c, v FROM {x}c{iters})")
    ctes.append(
        f"{x}p AS MATERIALIZED (SELECT vec_id, e, arg_min(part_id, (d, part_id)) AS part_id FROM "
        f"(SELECT {x}x.vec_id, {x}x.e, part_id, {distance(f'{x}x.e', 'c', metric)} AS d FROM {x}x, {x}cen) GROUP BY vec_id, e)"
    )
    if not x:
        ctes.append(calibration(metric))
    return ",\n".join(ctes)


def calibration(metric: str = "l2", k: int = 10, target: float = 0.9) -> str:
    """CTE ``np`` (n): the least number of partitions with the target recall, over the queries of id divisible by 50."""
    return f"""cq AS (SELECT vec_id AS qid, e AS qe FROM x WHERE vec_id % 50 = 0),
cr AS MATERIALIZED (SELECT qid, part_id, row_number() OVER (PARTITION BY qid ORDER BY {distance('c', 'qe', metric)}, part_id) AS pr FROM cq, cen),
ct AS MATERIALIZED (SELECT qid, vec_id, part_id FROM cq, p QUALIFY row_number() OVER (PARTITION BY qid ORDER BY {distance('e', 'qe', metric)}, vec_id) <= {k}),
np AS MATERIALIZED (SELECT min(n) AS n FROM (SELECT n, (SELECT count(*) FROM ct JOIN cr USING (qid, part_id) WHERE pr <= n) / (SELECT count(*) FROM ct) AS recall
  FROM (SELECT unnest(range(1, (SELECT count(*) + 1 FROM cen))) AS n)) WHERE recall >= {target})"""


def step(i: int, batch: int, lam: float, seed: int, metric: str = "l2", x: str = "") -> str:
    """One iteration: batch, penalised choice with frozen counts, running means in closed form."""
    return f"""{x}b{i} AS (SELECT vec_id, e FROM {x}x ORDER BY md5('{seed}:batch:{i}:' || vec_id), vec_id LIMIT {batch}),
{x}a{i} AS MATERIALIZED (SELECT vec_id, e, arg_min(part_id, (s, part_id)) AS part_id FROM (
  SELECT {x}b{i}.vec_id, {x}b{i}.e, part_id, {distance(f'{x}b{i}.e', 'c', metric)} *
    (CASE WHEN t.m = 0 THEN 1.0 ELSE 1.0 + {lam} * (v / t.m) END) AS s
  FROM {x}b{i}, {x}c{i - 1}, (SELECT sum(v) / count(*) AS m FROM {x}c{i - 1}) t) GROUP BY vec_id, e),
{x}s{i} AS (SELECT part_id, dim, sum(floor(e[dim] * 1073741824 + 0.5)::BIGINT)::BIGINT AS s, count(*) AS m
  FROM (SELECT part_id, e, unnest(range(1, len(e) + 1)) AS dim FROM {x}a{i}) GROUP BY part_id, dim),
{x}u{i} AS (SELECT part_id, list(s ORDER BY dim) AS s, any_value(m) AS m FROM {x}s{i} GROUP BY part_id),
{x}c{i} AS MATERIALIZED (SELECT o.part_id, CASE WHEN u.m IS NULL THEN o.c ELSE
    list_transform(list_zip(o.c, u.s), lambda q: (o.v * q[1] + q[2]::DOUBLE / 1073741824) / (o.v + u.m)) END AS c,
  o.v + coalesce(u.m, 0) AS v FROM {x}c{i - 1} o LEFT JOIN {x}u{i} u USING (part_id))"""


def index(metric: str = "l2", **options) -> str:
    return "WITH " + training(metric=metric, **options)


#: The calibrated number of probes.
N = "(SELECT n FROM np)"


def probes(query: str, n: int | str = N, metric: str = "l2", x: str = "") -> str:
    """Partition ids of the n nearest centres to a query expression (a subquery of a list)."""
    return f"(SELECT part_id FROM {x}cen QUALIFY row_number() OVER (ORDER BY {distance('c', query, metric)}, part_id) <= {n})"


def lloyd(source: str, k: str, iters: int, tag: str = "seed", seed: int = 42, metric: str = "l2", x: str = "f") -> str:
    """CTEs of plain k-means over ``source(vec_id, e)``: ``<x>c<iters>`` (part_id, c, m)."""
    ctes = [
        f"{x}x AS MATERIALIZED ({source})",
        f"""{x}c0 AS MATERIALIZED (SELECT row_number() OVER (ORDER BY md5('{seed}:{tag}:' || vec_id), vec_id) - 1 AS part_id, e AS c, 0 AS m
  FROM {x}x QUALIFY part_id < {k})""",
    ]
    for i in range(1, iters + 1):
        ctes.append(
            f"""{x}a{i} AS MATERIALIZED (SELECT vec_id, e, arg_min(part_id, (d, part_id)) AS part_id FROM (
  SELECT vec_id, e, part_id, {distance('e', 'c', metric)} AS d FROM {x}x, {x}c{i - 1}) GROUP BY vec_id, e),
{x}s{i} AS (SELECT part_id, dim, sum(floor(e[dim] * 1073741824 + 0.5)::BIGINT)::BIGINT AS s, count(*) AS m
  FROM (SELECT part_id, e, unnest(range(1, len(e) + 1)) AS dim FROM {x}a{i}) GROUP BY part_id, dim),
{x}u{i} AS (SELECT part_id, list(s ORDER BY dim) AS s, any_value(m) AS m FROM {x}s{i} GROUP BY part_id),
{x}c{i} AS MATERIALIZED (SELECT o.part_id, CASE WHEN u.m IS NULL THEN o.c ELSE
    list_transform(u.s, lambda q: q::DOUBLE / 1073741824 / u.m) END AS c, coalesce(u.m, 0) AS m
  FROM {x}c{i - 1} o LEFT JOIN {x}u{i} u USING (part_id))"""
        )
    return ",\n".join(ctes)
