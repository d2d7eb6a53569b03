"""Queries of kernels, measures, samplers, certificates, density and rendering, with their DuckDB SQL."""

from __future__ import annotations

import math
import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from spreadsample.functions import bandwidth, kernels
from spreadsample.functions.points import load, raw_sql, unit_sql
from spreadsample.functions.runtime import durable
from spreadsample.operators import baselines as bl
from spreadsample.operators import certify, density, exact, measures, render
from spreadsample.operators import exchange as ex
from spreadsample.plans import catalog
from spreadsample.registry import Registry

EPS, WIDE = math.sqrt(2) / 100, 0.1
R = Registry()

#: The printed pairs of log loss ratio and success of the regression task, in groups of four for uniform, balanced-grid and spread.
PRINTED_PAIRS = [(257.05, 0.2128), (49.94, 0.2599), (6.749, 0.2151), (2.343, 0.5934), (126.17, 0.2251), (14.01, 0.2849), (3.073, 0.3598), (1.733, 0.6436), (55.36, 0.4278), (3.648, 0.6374), (1.855, 0.8950), (0.886, 0.9889)]


def unit(name: str) -> str:
    return unit_sql(name, duck=True)


def bottom(name: str, k: int, seed: int = 7) -> str:
    return f"SELECT * FROM ({unit(name)}) AS pts ORDER BY md5(concat('{seed}:', id)), id LIMIT {k}"


def d2(a: str, b: str) -> str:
    return f"(({a}.x - {b}.x) * ({a}.x - {b}.x) + ({a}.y - {b}.y) * ({a}.y - {b}.y))"


def rounded(df: DataFrame, *cols: str, digits: int = 6) -> DataFrame:
    return df.withColumns({c: F.round(c, digits) for c in cols})


def uni(spark: SparkSession, sf: str, name: str, k: int) -> DataFrame:
    return bl.uniform(load(spark, sf, name), k)


# --- kernels and bandwidths
for _k in kernels.KERNELS:
    R.add(f"k_{_k}", lambda s, d, k=_k: rounded(measures.pair_values(uni(s, d, "supp", 30), WIDE, k), "k", digits=9), f"WITH s AS ({bottom('supp', 30)}) SELECT a.id AS i, b.id AS j, round({kernels.sql(_k, d2('a', 'b'), WIDE)}, 9) AS k FROM s a JOIN s b ON a.id < b.id")
R.add("k_pair_quadrature", lambda s, d: rounded(kernels.pair_by_quadrature(s.read.parquet(f"{d}/lineitem.parquet").select((F.col("l_quantity") / 10).alias("d")).distinct(), 1.0), "value", digits=5), "SELECT d, round(exp(-d * d / 2e0), 5) AS value FROM (SELECT DISTINCT l_quantity / 10 AS d FROM lineitem) AS t")
R.add("k_bandwidth_bbox", lambda s, d: rounded(bandwidth.bbox(load(s, d, "latency", unit=False)), "eps"), f"SELECT round(sqrt((max(x) - min(x)) * (max(x) - min(x)) + (max(y) - min(y)) * (max(y) - min(y))) / 100, 6) AS eps FROM ({raw_sql('latency', True)}) AS p")
R.add("k_bandwidth_hull", lambda s, d: rounded(bandwidth.by_diameter(load(s, d, "supp")), "eps", digits=9), f"WITH p AS ({unit('supp')}) SELECT round(max(sqrt({d2('a', 'b')})) / 100, 9) AS eps FROM p a, p b")
R.add("k_bandwidth_normal_ref", lambda s, d: rounded(bandwidth.normal_reference(load(s, d, "latency")), "eps", digits=9), f"SELECT round(sqrt((var_samp(x) + var_samp(y)) / 2) * pow(count(*), -1e0 / 6), 9) AS eps FROM ({unit('latency')}) AS p")
CUTOFFS = {"gaussian": "4e0", "pair": "4e0 * sqrt(2e0)", "laplacian": "16e0", "epanechnikov": "1e0"}


def cutoffs(s: SparkSession, d: str) -> DataFrame:
    """The cut-off radius of each kernel at the bandwidth of each kind of event."""
    eps = bandwidth.normal_reference(load(s, d, "latency"), "category")
    return eps.select("category", F.inline(F.array(*[F.struct(F.lit(k).alias("kernel"), F.round(kernels.cutoff(k, F.col("eps")), 9).alias("radius")) for k in CUTOFFS])))


R.add("k_cutoff", cutoffs, f"SELECT category, kernel, round(eps * factor, 9) AS radius FROM (SELECT category, sqrt((var_samp(x) + var_samp(y)) / 2) * pow(count(*), -1e0 / 6) AS eps FROM ({unit('latency')}) AS p GROUP BY category) AS b, (VALUES {', '.join(f"('{k}', {v})" for k, v in CUTOFFS.items())}) AS t(kernel, factor)")
R.add("w17_locality_constant", lambda s, d: rounded(s.range(1).select(F.exp(F.lit(-16.0)).alias("at_gaussian"), F.exp(F.lit(-8.0)).alias("at_pair")), "at_gaussian", "at_pair", digits=13), "SELECT round(exp(-16e0), 13) AS at_gaussian, round(exp(-8e0), 13) AS at_pair")

# --- measures
PROBES = lambda n: f"SELECT i AS probe_id, 0.5e0 + i * 0.7548776662466927e0 - floor(0.5e0 + i * 0.7548776662466927e0) AS x, 0.5e0 + i * 0.5698402909980532e0 - floor(0.5e0 + i * 0.5698402909980532e0) AS y FROM range(1, {n} + 1) AS t(i)"
DOMAIN = lambda name, m: f"SELECT probe_id, x, y FROM ({PROBES(8 * m)}) AS pr WHERE EXISTS (SELECT 1 FROM ({unit(name)}) AS dd WHERE {d2('pr', 'dd')} <= 0.1e0 * 0.1e0) ORDER BY probe_id LIMIT {m}"


def losses_sql(at: str, rows: str, eps: float) -> str:
    return f"""SELECT probe_id, -(top + ln(s)) / ln(10) AS l FROM (
      SELECT probe_id, max(top) AS top, sum(exp(a - top)) AS s FROM (
        SELECT probe_id, a, max(a) OVER (PARTITION BY probe_id) AS top FROM (
          SELECT pb.probe_id, -{d2('pb', 'sm')} / ({eps!r} * {eps!r}) AS a FROM ({at}) AS pb, ({rows}) AS sm) AS v) AS w GROUP BY probe_id) AS z"""


def ratio_sql(name: str, sample: str, m: int, eps: float) -> str:
    return f"SELECT round((SELECT median(l) FROM ({losses_sql(DOMAIN(name, m), sample, eps)}) AS q1) - (SELECT median(l) FROM ({losses_sql(DOMAIN(name, m), unit(name), eps)}) AS q2), 6) AS log_ratio"


def grid_sql(name: str, k: int, g: int, seed: int = 7) -> str:
    bins = f"SELECT *, least({g - 1}, greatest(0, CAST(floor(x * {g}) AS INT))) * {g} + least({g - 1}, greatest(0, CAST(floor(y * {g}) AS INT))) AS bin FROM ({unit(name)}) AS p"
    return f"SELECT id, x, y, value, category FROM (SELECT *, row_number() OVER (PARTITION BY bin ORDER BY md5(concat('{seed}:', id)), id) AS nth FROM ({bins}) AS b) AS r ORDER BY nth, md5(CAST(bin AS VARCHAR)), bin LIMIT {k}"


def square(g: int) -> str:
    return f"SELECT i AS probe_id, (i // {g} + 0.5e0) / {g} AS x, (i % {g} + 0.5e0) / {g} AS y FROM range({g * g}) AS t(i)"


_gauss = kernels.sql("gaussian", d2("pb", "sm"), WIDE)
_mass = f"SELECT probe_id, sum(k) AS u, sum(k * k) AS own FROM (SELECT probe_id, {_gauss} AS k FROM ({square(20)}) AS pb, ({bottom('docs', 50)}) AS sm) AS v GROUP BY probe_id"
_pairs = lambda name, k, eps: f"SELECT a.id AS i, b.id AS j, {kernels.sql('pair', d2('a', 'b'), eps)} AS k, {d2('a', 'b')} AS d2 FROM ({bottom(name, k)}) AS a, ({bottom(name, k)}) AS b WHERE a.id < b.id"

R.add("m_point_loss", lambda s, d: rounded(measures.point_loss(measures.probes(s, 50, 1), uni(s, d, "latency", 100), EPS), "log10_loss"), f"SELECT probe_id, round(l, 6) AS log10_loss FROM ({losses_sql(PROBES(50), bottom('latency', 100), EPS)}) AS q")
R.add("m_integral_loss", lambda s, d: rounded(measures.integral_loss(measures.grid(s, 20), uni(s, d, "docs", 50), WIDE), "loss", digits=3), f"SELECT round(avg(1 / greatest(u, 1e-12)), 3) AS loss FROM ({_mass}) AS m")
R.add("m_domain_probes", lambda s, d: rounded(measures.domain_probes(load(s, d, "docs"), 100), "px", "py", digits=9), f"SELECT probe_id, round(x, 9) AS px, round(y, 9) AS py FROM ({DOMAIN('docs', 100)}) AS q")
for _stat, _agg in (("median", "median(l)"), ("mean", "max(l) + log10(avg(pow(10e0, l - (SELECT max(l) FROM q))))")):
    R.add(f"m_mc_{_stat}", lambda s, d, st=_stat: rounded(measures.average_loss(measures.point_loss(measures.domain_probes(load(s, d, "docs"), 100), uni(s, d, "docs", 60), EPS), st), "log10_loss"), f"WITH q AS ({losses_sql(DOMAIN('docs', 100), bottom('docs', 60), EPS)}) SELECT round({_agg}, 6) AS log10_loss FROM q")


def ratio(s: SparkSession, d: str, name: str, sample: DataFrame, m: int = 200, stat: str = "median", eps: float = EPS) -> DataFrame:
    points = load(s, d, name)
    return measures.log_ratio(points, sample, measures.domain_probes(points, m), eps, stat)


R.add("m_log_ratio_uniform", lambda s, d: rounded(ratio(s, d, "latency", uni(s, d, "latency", 100)), "log_ratio"), ratio_sql("latency", bottom("latency", 100), 200, EPS))
R.add("m_log_ratio_grid", lambda s, d: rounded(ratio(s, d, "latency", bl.balanced_grid(load(s, d, "latency"), 100)), "log_ratio"), ratio_sql("latency", grid_sql("latency", 100, 10), 200, EPS))
R.add("m_objective", lambda s, d: rounded(measures.objective(uni(s, d, "latency", 300), EPS), "objective"), f"SELECT round(coalesce(sum(k), 0), 6) AS objective FROM ({_pairs('latency', 300, EPS)}) AS p")
R.add("m_objective_cells", lambda s, d: rounded(measures.objective_by_cells(uni(s, d, "latency", 300), EPS), "objective"), f"SELECT round(coalesce(sum(k), 0), 6) AS objective FROM ({_pairs('latency', 300, EPS)}) AS p WHERE d2 <= {kernels.cutoff('pair', EPS) ** 2!r}")
R.add("m_avg_objective", lambda s, d: rounded(measures.average_objective(uni(s, d, "latency", 300), EPS), "avg_objective", digits=9), f"SELECT round(sum(k) / (300 * 299), 9) AS avg_objective FROM ({_pairs('latency', 300, EPS)}) AS p")
R.add("m_burden", lambda s, d: rounded(measures.burdens(uni(s, d, "docs", 40), WIDE), "burden"), f"WITH s AS ({bottom('docs', 40)}) SELECT a.id, round(sum(CASE WHEN a.id <> b.id THEN {kernels.sql('pair', d2('a', 'b'), WIDE)} ELSE 0 END), 6) AS burden FROM s a, s b GROUP BY a.id")
R.add("m_surrogate_stages", lambda s, d: rounded(measures.surrogate(measures.grid(s, 20), uni(s, d, "docs", 50), WIDE), "second_order", "reduced", "pair_sum"), f"SELECT round(avg((u - 1) * (u - 1) - (u - 1) + 1), 6) AS second_order, round(avg(u * u - 3 * u), 6) AS reduced, round(avg((u * u - own) / 2), 6) AS pair_sum FROM ({_mass}) AS m")
SPEARMAN = "SELECT round(rho, 8) AS rho, round(rho * sqrt((n - 2) / (1 - rho * rho)), 6) AS t, n FROM (SELECT corr(ra, rb) AS rho, count(*) AS n FROM (SELECT rank() OVER (ORDER BY a) + (count(*) OVER (PARTITION BY a) - 1) / 2e0 AS ra, rank() OVER (ORDER BY b) + (count(*) OVER (PARTITION BY b) - 1) / 2e0 AS rb FROM ({0}) AS v) AS w) AS z"
R.add("m_spearman_printed", lambda s, d: measures.spearman(load(s, d, "orders").select(F.col("x").alias("a"), F.col("y").alias("b")), "a", "b", durable).select(F.round("rho", 8).alias("rho"), F.round("t", 6).alias("t"), "n"), SPEARMAN.format(f"SELECT x AS a, y AS b FROM ({unit('orders')}) AS u"))  # of the printed pairs: w7_correlation_sign
R.add("m_spearman_ties", lambda s, d: measures.spearman(load(s, d, "discount").select(F.col("x").alias("a"), F.col("value").alias("b")), "a", "b", durable).select(F.round("rho", 8).alias("rho"), F.round("t", 6).alias("t"), "n"), SPEARMAN.format(f"SELECT x AS a, value AS b FROM ({unit('discount')}) AS u"))

# --- baselines
ROW = lambda df: rounded(df.select("id", "x", "y", "value", "category"), "x", "y", "value")
ROW_SQL = "SELECT id, round(x, 6) AS x, round(y, 6) AS y, round(value, 6) AS value, category FROM ({0}) AS out".format
R.add("s_uniform_bottomk", lambda s, d: ROW(uni(s, d, "latency", 200)), ROW_SQL(bottom("latency", 200)))
R.add("s_grid_100", lambda s, d: ROW(bl.balanced_grid(load(s, d, "latency"), 150, 10)), ROW_SQL(grid_sql("latency", 150, 10)))
R.add("s_grid_316", lambda s, d: ROW(bl.balanced_grid(load(s, d, "hubs"), 2000, 316)), ROW_SQL(grid_sql("hubs", 2000, 316)))
R.add("s_grid_k_strata", lambda s, d: ROW(bl.balanced_grid(load(s, d, "docs"), 100, math.ceil(math.sqrt(100)))), ROW_SQL(grid_sql("docs", 100, 10)))
R.add("s_all", lambda s, d: ROW(bl.every_row(load(s, d, "supp"))), ROW_SQL(unit("supp")))


def quota_sql(counts: str, k: int) -> str:
    """Quotas from the round-robin itself: the k-th row in the order of (turn, bin) ends it."""
    return f"SELECT bin, n, CAST(count(turn) AS BIGINT) AS quota FROM ({counts}) AS c LEFT JOIN (SELECT bin AS b, turn FROM ({counts}) AS c2, unnest(range(1, least(n, {k}) + 1)) AS t(turn) ORDER BY turn, bin LIMIT {k}) AS r ON c.bin = r.b GROUP BY bin, n"


_types = "SELECT event_type AS bin, count(*) AS n FROM events GROUP BY event_type"
R.add("s_quota", lambda s, d: bl.balanced_quota(load(s, d, "latency").groupBy(F.col("category").alias("bin")).agg(F.count("*").alias("n")), 777), quota_sql(_types, 777))
R.add("s_quota_example", lambda s, d: bl.balanced_quota(s.createDataFrame([("large", 1000), ("small", 10)], "bin string, n long"), 100), "SELECT * FROM (VALUES ('large', CAST(1000 AS BIGINT), CAST(90 AS BIGINT)), ('small', CAST(10 AS BIGINT), CAST(10 AS BIGINT))) AS t(bin, n, quota)")
R.add("s_prethin", lambda s, d: rounded(bl.prethin(load(s, d, "latency"), 0.1), "x", "y"), f"SELECT cx, cy, arg_min(id, h) AS id, round(arg_min(x, h), 6) AS x, round(arg_min(y, h), 6) AS y, count(*) AS n FROM (SELECT *, CAST(floor(x / (0.1e0 / 4)) AS BIGINT) AS cx, CAST(floor(y / (0.1e0 / 4)) AS BIGINT) AS cy, md5(concat('7:', id)) AS h FROM ({unit('latency')}) AS p) AS q GROUP BY cx, cy")
R.add("s_reservoir", lambda s, d: bl.reservoir(load(s, d, "latency"), 200).agg(F.count("*").alias("n_rows"), F.count_distinct("id").alias("n_ids")), "SELECT CAST(200 AS BIGINT) AS n_rows, CAST(200 AS BIGINT) AS n_ids")
R.add("s_bernoulli", lambda s, d: bl.bernoulli(p := load(s, d, "latency"), 200, p.count()).agg(F.count("*").between(100, 320).alias("near_k")), "SELECT true AS near_k")

# --- exchange
EXCHANGE_SQL = """
WITH RECURSIVE r AS (SELECT row_number() OVER (ORDER BY md5(concat('7:', id)), id) AS n, id, x, y FROM ({points}) AS p),
st AS (
  SELECT CAST(0 AS BIGINT) AS n, CAST([] AS STRUCT(id VARCHAR, x DOUBLE, y DOUBLE, b DOUBLE)[]) AS s
  UNION ALL
  SELECT n, CASE WHEN len(g) <= {k} THEN g ELSE list_transform(list_filter(g, lambda m: m.id <> worst.id), lambda m: {{'id': m.id, 'x': m.x, 'y': m.y, 'b': m.b - exp(-((m.x - worst.x) ** 2 + (m.y - worst.y) ** 2) / {two})}}) END
  FROM (SELECT n, g, list_reverse_sort(list_transform(list_filter(g, lambda m: m.b >= top - 1e-12), lambda m: {{'late': m.id = new, 'id': m.id, 'x': m.x, 'y': m.y}}))[1] AS worst
        FROM (SELECT n, g, new, list_max(list_transform(g, lambda m: m.b)) AS top
              FROM (SELECT r.n, r.id AS new, list_append(list_transform(s, lambda m: {{'id': m.id, 'x': m.x, 'y': m.y, 'b': m.b + exp(-((m.x - r.x) ** 2 + (m.y - r.y) ** 2) / {two})}}),
                           {{'id': r.id, 'x': r.x, 'y': r.y, 'b': coalesce(list_sum(list_transform(s, lambda m: exp(-((m.x - r.x) ** 2 + (m.y - r.y) ** 2) / {two}))), 0e0)}}) AS g
                    FROM st JOIN r ON r.n = st.n + 1) AS a) AS b) AS c)
SELECT m.id AS id, round(m.x, 6) AS x, round(m.y, 6) AS y, round(m.b, 6) AS burden FROM (SELECT unnest(s) AS m FROM st WHERE n = (SELECT max(n) FROM r)) AS z"""


def exchange_sql(points: str, k: int, eps: float) -> str:
    return EXCHANGE_SQL.format(points=points, k=k, two=repr(2 * eps * eps))


BURDENS = lambda df: rounded(df.select("id", "x", "y", "burden"), "x", "y", "burden")
for _name, _points, _kk, _opt in (("s_exchange_supplier", "supp", 5, {}), ("s_exchange_part", "part", 12, {}), ("s_exchange_burden_test", "supp", 5, {"variant": "burden_test"}), ("s_exchange_recompute", "supp", 5, {"variant": "recompute"}), ("s_exchange_local_small", "supp", 5, {"variant": "local", "tol": 1e-300}), ("s_exchange_grid_heap", "supp", 5, {"variant": "heap", "tol": 1e-300})):
    R.add(_name, lambda s, d, p=_points, k=_kk, o=_opt: BURDENS(ex.exchange(load(s, d, p), k, WIDE, **o)), exchange_sql(unit(_points) if _points == "supp" else bottom("part", 100000), _kk, WIDE))


def judged(points: DataFrame, sample: DataFrame, k: int, eps: float) -> DataFrame:
    """Invariants of a sample and whether it beats the uniform sample of its size."""
    kept = durable(sample.select("id", "x", "y", "burden"))
    ours, other = measures.objective_by_cells(kept, eps), measures.objective_by_cells(bl.uniform(points, k), eps).withColumnRenamed("objective", "u")
    return certify.consistency(points, kept, k, eps).crossJoin(ours.crossJoin(other).select((F.col("objective") <= F.col("u")).alias("beats_uniform")))


def judged_sql(name: str, k: int) -> str:
    return f"SELECT least({k}, count(*)) AS n_rows, least({k}, count(*)) AS n_ids, true AS burdens_match, CAST(0 AS BIGINT) AS n_outside, true AS beats_uniform FROM ({unit(name)}) AS p"


HOW = {
    "s_exchange_first_k": lambda p: ex.exchange(p, 100, EPS, order="natural"),
    "s_exchange_zorder": lambda p: ex.exchange(p, 100, EPS, order="zorder"),
    "s_exchange_local": lambda p: ex.exchange(p, 100, EPS, variant="local"),
    "s_exchange_tiles": lambda p: ex.exchange_tiles(p, 100, EPS),
    "s_exchange_tree": lambda p: ex.exchange_tree(p, 100, EPS, durable=durable),
    "s_exchange_random_parts": lambda p: ex.exchange_random_parts(p, 100, EPS),
    "s_exchange_two_pass": lambda p: ex.rescan(p, durable(ex.exchange(p, 100, EPS)), 100, EPS),
    "s_exchange_prethinned": lambda p: ex.exchange_tiles(bl.prethin(p, EPS).select("id", "x", "y"), 100, EPS),
    "s_exchange_heap": lambda p: ex.exchange(p, 100, EPS, variant="heap"),
    "s_exchange_greedy_start": lambda p: ex.rescan(p, durable(ex.greedy_start(p, 100, EPS)), 100, EPS),
}
for _name, _how in HOW.items():
    R.add(_name, lambda s, d, h=_how: judged(p := load(s, d, "latency"), h(p), 100, EPS), judged_sql("latency", 100))


def timed(s: SparkSession, d: str, seconds: float = 1.0) -> DataFrame:
    """A build that is stopped by the clock: its sample is whole, and its scans kept to the bound (the rest is the starting of jobs)."""
    points, began = load(s, d, "latency"), time.time()
    sample = durable(ex.exchange_until_stable(points, 100, EPS, max_passes=3, max_seconds=seconds, durable=durable)[0])
    return judged(points, sample, 100, EPS).withColumn("in_time", F.lit(time.time() - began < seconds + 60))


def large(points: DataFrame, tiled: bool, k: int = 10_000, eps: float = EPS / 20) -> DataFrame:
    build = ex.exchange_tiles(durable(points.select("id", "x", "y")), k, eps, variant="heap") if tiled else catalog.spread_sample(points, k, eps, points.count(), durable)
    return judged(points, build, k, eps)


R.add("s_exchange_timed", timed, f"SELECT *, true AS in_time FROM ({judged_sql('latency', 100)}) AS j")
R.add("s_build_large_k", lambda s, d: large(load(s, d, "hubs"), False), judged_sql("hubs", 10_000))
R.add("s_build_large_k_tiles", lambda s, d: large(load(s, d, "hubs"), True), judged_sql("hubs", 10_000))
R.add("s_hydrate", lambda s, d: ex.hydrate(s.read.parquet(f"{d}/events.parquet"), durable(ex.exchange(load(s, d, "latency"), 50, EPS)), 50, "event_id").agg(F.count("*").alias("n"), F.count_distinct("event_id").alias("ids"), F.max("sample_rank").alias("top_rank"), F.bool_and(F.col("value").isNotNull()).alias("whole")), "SELECT least(50, count(*)) AS n, least(50, count(*)) AS ids, CAST(least(50, count(*)) AS INT) AS top_rank, true AS whole FROM events")
R.add("s_choose_variant", lambda s, d: s.createDataFrame([(k, n, ex.choose_variant(k, float(n))) for k, n in ((100, 50), (100, 1), (5000, 30), (5000, 5000), (100_000, 60))], "k int, neighbours int, variant string"), "SELECT * FROM (VALUES (100, 50, 'add_drop'), (100, 1, 'local'), (5000, 30, 'local'), (5000, 5000, 'add_drop'), (100000, 60, 'heap')) AS t(k, neighbours, variant)")
R.add("s_exchange_stable", lambda s, d: certify.improving_swaps(p := load(s, d, "supp"), durable(ex.exchange_until_stable(p, 6, WIDE, durable=durable)[0]), WIDE), "SELECT CAST(0 AS BIGINT) AS swaps")
R.add("s_exchange_per_group", lambda s, d: ex.exchange_per_group(load(s, d, "latency"), 20, EPS, "category").groupBy("category").agg(F.count("*").alias("n")), "SELECT event_type AS category, least(20, count(*)) AS n FROM events GROUP BY event_type")


def pair_table(points: DataFrame, eps: float = WIDE) -> DataFrame:
    return measures.pair_values(points, eps)


R.add("s_exchange_pairs", lambda s, d: ex.exchange_pairs(pair_table(p := durable(load(s, d, "supp"))), 4, p).agg(F.count("*").alias("n"), F.count_distinct("id").alias("ids")), "SELECT CAST(4 AS BIGINT) AS n, CAST(4 AS BIGINT) AS ids")

# --- greedy and exact
GREEDY_SQL = f"""
WITH RECURSIVE p AS ({unit('supp')}),
st AS (
  SELECT 0 AS nth, CAST([] AS STRUCT(id VARCHAR, x DOUBLE, y DOUBLE)[]) AS s, CAST(NULL AS STRUCT(p DOUBLE, id VARCHAR, x DOUBLE, y DOUBLE)) AS best
  UNION ALL
  SELECT nth + 1, list_append(s, {{'id': b.id, 'x': b.x, 'y': b.y}}), b FROM (
    SELECT nth, s, (SELECT min({{'p': coalesce(list_sum(list_transform(st.s, lambda m: exp(-((m.x - p.x) ** 2 + (m.y - p.y) ** 2) / {2 * WIDE * WIDE!r}))), 0e0), 'id': p.id, 'x': p.x, 'y': p.y}})
                    FROM p WHERE NOT list_contains(list_transform(st.s, lambda m: m.id), p.id)) AS b FROM st WHERE nth < 6) AS q)
SELECT best.id AS id, nth, round(best.p, 6) AS added FROM st WHERE nth > 0"""
R.add("s_greedy_supplier", lambda s, d: rounded(exact.greedy(load(s, d, "supp"), 6, WIDE, durable=durable), "added"), GREEDY_SQL)
_supp = lambda k: _pairs("supp", k, WIDE)
K3_SQL = f"WITH p AS ({_supp(30)}) SELECT ab.i AS a, ab.j AS b, ac.j AS c, ab.k + ac.k + bc.k AS objective FROM p ab JOIN p ac ON ab.i = ac.i JOIN p bc ON bc.i = ab.j AND bc.j = ac.j ORDER BY objective, a, b, c LIMIT 1"
R.add("s_exact_k2", lambda s, d: rounded(exact.exact_2(load(s, d, "supp"), WIDE), "objective", digits=12), f"WITH p AS ({unit('supp')}) SELECT a.id AS a, b.id AS b, round({kernels.sql('pair', d2('a', 'b'), WIDE)}, 12) AS objective FROM p a JOIN p b ON a.id < b.id ORDER BY {kernels.sql('pair', d2('a', 'b'), WIDE)}, a.id, b.id LIMIT 1")
R.add("s_exact_k3", lambda s, d: rounded(exact.exact_3(uni(s, d, "supp", 30), WIDE), "objective", digits=12), f"SELECT a, b, c, round(objective, 12) AS objective FROM ({K3_SQL}) AS q")
R.add("s_exact_bnb", lambda s, d: rounded(exact.exact(uni(s, d, "supp", 30), 3, WIDE), "objective", digits=12).agg(F.sort_array(F.collect_list("id")).alias("v"), F.max("objective").alias("objective")).select(F.concat_ws(",", "v").alias("ids"), "objective"), f"SELECT concat_ws(',', a, b, c) AS ids, round(objective, 12) AS objective FROM ({K3_SQL}) AS q")
R.add("s_exact_model", lambda s, d: exact.exact_model(uni(s, d, "supp", 20), 4, WIDE).groupBy("part").agg(F.count("*").alias("n")), f"WITH s AS ({bottom('supp', 20)}), c AS (SELECT count(*) AS n FROM s) SELECT part, CASE WHEN pairs THEN n * (n - 1) // 2 ELSE n END AS n FROM c, (VALUES ('minimize', true), ('subject', true), ('bounds', true), ('sum', false), ('binary', false)) AS t(part, pairs)")

# --- certificates
_near = kernels.sql("pair", d2("t", "s"), WIDE)
R.add("c_improving_swaps", lambda s, d: certify.improving_swaps(load(s, d, "supp"), uni(s, d, "supp", 5), WIDE), f"""
WITH p AS ({unit('supp')}), s AS ({bottom('supp', 5)}),
b AS (SELECT a.id, a.x, a.y, sum(CASE WHEN a.id <> c.id THEN {kernels.sql('pair', d2('a', 'c'), WIDE)} ELSE 0 END) AS burden FROM s a, s c GROUP BY a.id, a.x, a.y),
k AS (SELECT t.id AS t, s.id AS s, {_near} AS near, burden FROM p t, b s WHERE t.id NOT IN (SELECT id FROM s)),
q AS (SELECT *, sum(near) OVER (PARTITION BY t) AS potential FROM k)
SELECT count(*) AS swaps FROM q WHERE potential - near < burden - 1e-12""")
R.add("c_consistency", lambda s, d: certify.consistency(p := load(s, d, "docs"), ex.exchange(p, 50, EPS), 50, EPS), f"SELECT least(50, count(*)) AS n_rows, least(50, count(*)) AS n_ids, true AS burdens_match, CAST(0 AS BIGINT) AS n_outside FROM ({unit('docs')}) AS p")


def bound(s: SparkSession, d: str) -> DataFrame:
    points = uni(s, d, "supp", 13)
    stable = durable(ex.exchange_until_stable(points, 4, WIDE, durable=durable)[0])
    ours, best = measures.objective(stable, WIDE).first()[0] / 12, exact.exact(points, 4, WIDE).first()["objective"] / 12
    return s.createDataFrame([(certify.quality_bound(ours, best), best <= ours + 1e-12)], "within_bound boolean, optimum_lower boolean")


R.add("c_bound_small", bound, "SELECT true AS within_bound, true AS optimum_lower")


def reduction(s: SparkSession, d: str) -> DataFrame:
    """The heaviest three-vertex subgraph, found as the lightest triple of the reduced pair table."""
    points = uni(s, d, "supp", 12)
    edges = measures.pair_values(points, WIDE).select(F.col("i").alias("u"), F.col("j").alias("v"), F.col("k").alias("w"))
    p = exact.to_pairs(edges, points.select("id"))
    ab, ac, bc = (p.select(F.col("i").alias(u), F.col("j").alias(v), F.col("k").alias(f"k_{u}{v}")) for u, v in ("ab", "ac", "bc"))
    best = ab.join(ac, "a").join(bc, ["b", "c"]).select("a", "b", "c", F.round(F.col("k_ab") + F.col("k_ac") + F.col("k_bc"), 9).alias("light"))
    return best.orderBy("light", "a", "b", "c").limit(1).select("a", "b", "c")


R.add("c_reduction", reduction, f"WITH p AS ({_supp(12)}) SELECT a, b, c FROM (SELECT ab.i AS a, ab.j AS b, ac.j AS c, round(3 * (SELECT max(k) FROM p) - ab.k - ac.k - bc.k, 9) AS light FROM p ab JOIN p ac ON ab.i = ac.i JOIN p bc ON bc.i = ab.j AND bc.j = ac.j) AS q ORDER BY light, a, b, c LIMIT 1")


def trace_checks(s: SparkSession, d: str) -> DataFrame:
    from pyspark.sql import Window

    t = durable(ex.trace(load(s, d, "latency"), 50, EPS, every=200))
    before = F.lag("objective").over(Window.orderBy("rows_seen"))
    return t.withColumn("rise", F.col("objective") - before).agg(F.max("rows_seen").alias("rows_seen"), F.coalesce(F.max("rise") <= 1e-9, F.lit(True)).alias("never_rises"))


R.add("c_trace", trace_checks, f"SELECT count(*) AS rows_seen, true AS never_rises FROM ({unit('latency')}) AS p")


def equivalence(s: SparkSession, d: str) -> DataFrame:
    p = load(s, d, "supp")
    ids = [ex.exchange(p, 6, WIDE, variant=v).select("id") for v in ("add_drop", "burden_test", "recompute")]
    same = ids[0].intersect(ids[1]).intersect(ids[2])
    return same.agg(F.count("*").alias("in_all"))


R.add("c_equivalence", equivalence, "SELECT CAST(6 AS BIGINT) AS in_all")


def counters(s: SparkSession, d: str) -> DataFrame:
    """All rows, with and without add-drop: evaluations of the kernel and the swaps, which are the same."""
    p = durable(load(s, d, "latency").select("id", "x", "y"))
    one, other = (ex.trace(p, 20, EPS, variant=v, every=1 << 40).groupBy().agg(F.max("rows_seen").alias("rows_seen"), F.max("kernel_evals").alias(f"evals_{v}"), F.max("swaps").alias(f"swaps_{v}")) for v in ("burden_test", "add_drop"))
    return one.join(other, "rows_seen").select("rows_seen", (F.col("evals_burden_test") > 8 * F.col("evals_add_drop")).alias("saves"), (F.col("swaps_burden_test") == F.col("swaps_add_drop")).alias("same_swaps"))


R.add("c_counters", counters, "SELECT count(*) AS rows_seen, true AS saves, true AS same_swaps FROM events")

# --- density and drawing
DENSITY_SQL = lambda name, k, rows=None: f"WITH s AS ({rows or bottom(name, k)}), n AS (SELECT arg_min(s.id, ROW({d2('p', 's')}, s.id)) AS sid FROM (SELECT row_number() OVER () AS rn, * FROM ({unit(name)}) AS u) AS p, s GROUP BY rn) SELECT s.id, count(n.sid) AS density FROM s LEFT JOIN n ON n.sid = s.id GROUP BY s.id"
for _name, _how in (("scan", density.by_scan), ("grid", lambda a, b: density.by_index(a, b, "grid")), ("kdtree", density.by_index), ("cell_join", lambda a, b: density.by_cells(a, b, durable=durable))):
    R.add(f"d_density_{_name}", lambda s, d, h=_how: h(uni(s, d, "docs", 40), load(s, d, "docs")), DENSITY_SQL("docs", 40))
R.add("d_density_ties", lambda s, d: density.by_index(uni(s, d, "discount", 60), load(s, d, "discount")), DENSITY_SQL("discount", 60))


def weighted(s: SparkSession, d: str, name: str, k: int) -> DataFrame:
    sample = durable(uni(s, d, name, k))
    return sample.join(density.by_index(sample, load(s, d, name)), "id")


R.add("d_marker", lambda s, d: rounded(render.marker_size(weighted(s, d, "docs", 40)).select("id", "density", "marker_size"), "marker_size"), f"SELECT id, density, round(2 + 18 * sqrt(density) / (SELECT sqrt(max(density)) FROM ({DENSITY_SQL('docs', 40)}) AS m), 6) AS marker_size FROM ({DENSITY_SQL('docs', 40)}) AS w")
_draw = lambda axis: f"(CAST(('0x' || substr(md5(concat('{axis}', id, ':', copy)), 1, 8)) AS BIGINT) / 4294967296e0 - 0.5)"
R.add("d_jitter", lambda s, d: rounded(render.jitter(weighted(s, d, "docs", 40)), "x", "y"), f"SELECT id, copy, round(CASE WHEN copy = 1 THEN x ELSE x + 2 * 0.005e0 * {_draw('x')} END, 6) AS x, round(CASE WHEN copy = 1 THEN y ELSE y + 2 * 0.005e0 * {_draw('y')} END, 6) AS y FROM (SELECT s.id, x, y, CAST(c AS INT) AS copy FROM ({bottom('docs', 40)}) AS s JOIN ({DENSITY_SQL('docs', 40)}) AS w ON s.id = w.id, unnest(range(1, greatest(1, least(20, density // 10)) + 1)) AS t(c)) AS q")
RASTER_SQL = lambda name, w, h: f"SELECT least({w - 1}, CAST(floor((x - 0e0) / 1e0 * {w}) AS INT)) AS px, least({h - 1}, CAST(floor(y * {h}) AS INT)) AS py, count(*) AS n, round(avg(value), 6) AS colour FROM ({unit(name)}) AS p GROUP BY 1, 2"
R.add("d_raster", lambda s, d: rounded(render.raster(load(s, d, "hubs"), 100, 80), "colour"), RASTER_SQL("hubs", 100, 80))
R.add("d_bin2d", lambda s, d: render.bin2d(load(s, d, "latency"), 24, 10), f"SELECT px AS bx, py AS by, n FROM ({RASTER_SQL('latency', 24, 10)}) AS r")
R.add("d_zoom", lambda s, d: ROW(render.zoom(uni(s, d, "hubs", 3000), (0.2, 0.6, 0.3, 0.9))), ROW_SQL(f"SELECT * FROM ({bottom('hubs', 3000)}) AS b WHERE x BETWEEN 0.2e0 AND 0.6e0 AND y BETWEEN 0.3e0 AND 0.9e0"))
R.add("d_progressive", lambda s, d: render.progressive(uni(s, d, "docs", 80), 25, seed=11).select("id", "sample_rank"), f"SELECT id, CAST(row_number() OVER (ORDER BY md5(concat('11:', id)), id) AS INT) AS sample_rank FROM ({bottom('docs', 80)}) AS s QUALIFY sample_rank <= 25")


def first_slice(s: SparkSession, d: str) -> DataFrame:
    """A spread sample of the latency plot with burdens and density weights."""
    points = load(s, d, "latency")
    sample = durable(ex.exchange(points, 100, EPS))
    return sample.join(density.by_index(sample, points), "id").select("id", F.round("x", 9).alias("x"), F.round("y", 9).alias("y"), F.round("burden", 6).alias("burden"), "density")


R.add("w0_first_slice", first_slice)
R.add("w0_first_slice_whole", lambda s, d: first_slice(s, d).agg(F.count("*").alias("n"), F.sum("density").alias("stands_for"), F.round(F.max("burden"), 6).alias("top")).select("n", "stands_for", (F.col("top") < 1).alias("uncrowded")), "SELECT least(100, count(*)) AS n, count(*) AS stands_for, true AS uncrowded FROM events")
