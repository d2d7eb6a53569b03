"""The experiments, re-expressed on the given tables: one tidy row per configuration and measure."""

from __future__ import annotations

import time
from functools import partial, reduce, wraps

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from spreadsample.functions import points
from spreadsample.functions.points import load
from spreadsample.functions.runtime import bounded, durable, new_path, parked, together
from spreadsample.operators import baselines as bl
from spreadsample.operators import density, exact, measures, render, tasks
from spreadsample.operators import exchange as ex
from spreadsample.operators.queries import DENSITY_SQL, EPS, PRINTED_PAIRS, WIDE, bottom, grid_sql, quota_sql, rounded, uni, unit
from spreadsample.plans import budget, catalog
from spreadsample.registry import Registry
from spreadsample.streaming import refresh

R = Registry()
#: Sizes of the task and loss experiments, and the probes of a loss.
SIZES, PROBE_COUNT = (100, 316, 1000, 10_000), 1000


def spread(p: DataFrame, k: int, eps: float = EPS) -> DataFrame:
    sample = catalog.spread_sample(p, k, eps, p.count())
    return p.join(bounded(sample.select("id"), k), "id", "left_semi")


METHODS = {"uniform": lambda p, k: bl.uniform(p, k), "grid": lambda p, k: bl.balanced_grid(p, k, 100), "spread": spread}


_kept: dict[tuple, DataFrame] = {}


def key_of(make: str, spark: SparkSession, sf: str, *args, **options) -> tuple:
    return make, sf, spark.sparkContext.applicationId, args, tuple(sorted(options.items()))


def remembered(make, keep=durable):
    """Results of an experiment stay in the shared folder for the session: tables and claims read the same ones, and tasks and losses
    the same samples."""

    @wraps(make)
    def run(spark: SparkSession, sf: str, *args, **options) -> DataFrame:
        key = key_of(make.__name__, spark, sf, *args, **options)
        if key not in _kept:
            _kept[key] = keep(make(spark, sf, *args, **options))
        return _kept[key]

    return run


@partial(remembered, keep=parked)
def point_set(spark: SparkSession, sf: str, name: str) -> DataFrame:
    return load(spark, sf, name)


@remembered
def sample_of(spark: SparkSession, sf: str, name: str, method: str, k: int, widest: int) -> DataFrame:
    """A sample of k rows. Uniform and grid samples are nested (the first k rows of one order), so that of the widest size holds the others."""
    nested = method != "spread" and k < widest
    return METHODS[method](sample_of(spark, sf, name, method, widest, widest) if nested else point_set(spark, sf, name), k)


def spreads(spark: SparkSession, sf: str, name: str, ks: tuple[int, ...]) -> None:
    """Builds the spread samples that are not there yet together, if rows go through tiles for two of them or more."""
    p, key = point_set(spark, sf, name), lambda k: key_of("sample_of", spark, sf, name, "spread", k, max(ks))
    n, todo = p.count(), [k for k in ks if key(k) not in _kept]
    if sum(not catalog.in_block(k, n) for k in todo) > 1:
        made = durable(catalog.spread_samples(p, todo, EPS, n, durable))
        _kept.update({key(k): made.where(F.col("size") == k).drop("size") for k in todo})


@remembered
def weights_of(spark: SparkSession, sf: str, name: str, ks: tuple[int, ...]) -> DataFrame:
    """(size, and the columns of a sample, density): the spread samples of all sizes with what their rows stand for, from one scan."""
    drawn = [sample_of(spark, sf, name, "spread", k, max(ks)) for k in ks]
    weights = density.by_indexes(drawn, point_set(spark, sf, name), durable=durable)
    return reduce(DataFrame.union, [s.join(w, "id").withColumn("size", F.lit(k)) for k, s, w in zip(ks, drawn, weights)])


def samples(spark: SparkSession, sf: str, name: str, ks: tuple[int, ...]) -> list[tuple[int, str, DataFrame]]:
    """(k, method, sample) of all sizes and methods. Builds run side by side, the largest first; the nested ones follow those that hold them."""
    point_set(spark, sf, name)
    largest, first = sorted(ks, reverse=True), [(k, m) for k in sorted(ks, reverse=True) for m in METHODS if m == "spread" or k == max(ks)]
    spreads(spark, sf, name, ks)
    for some in (first, [(k, m) for k in largest[1:] for m in METHODS if m != "spread"]):
        together(*[partial(sample_of, spark, sf, name, m, k, max(ks)) for k, m in some])
    return [(k, m, sample_of(spark, sf, name, m, k, max(ks))) for k in ks for m in METHODS]


def measured(spark: SparkSession, rows: list[tuple]) -> DataFrame:
    return spark.createDataFrame(rows, "dataset string, method string, k int, measure string, v double")


def w1_zoom_coverage(spark: SparkSession, sf: str) -> DataFrame:
    """Pixels kept in the overview and in three zooms, balanced over a fine grid against spread."""
    boxes = {"overview": (0, 1, 0, 1), "zoom1": (0.2, 0.5, 0.2, 0.5), "zoom2": (0.5, 0.8, 0.1, 0.4), "zoom3": (0.4, 0.6, 0.6, 0.8)}
    sets = {name: point_set(spark, sf, name) for name in ("hubs", "latency", "docs")}
    ks = {name: max(100, p.count() // 100) for name, p in sets.items()}
    makers = {"grid": lambda p, k: durable(bl.balanced_grid(p, k, 316)), "spread": lambda p, k: durable(spread(p, k))}
    keys = [(name, m) for name in sets for m in makers]
    kept = dict(zip(keys, together(*[partial(makers[m], sets[name], ks[name]) for name, m in keys])))
    looks = [(name, m, label) for name, m in keys for label in boxes]
    seen = together(*[lambda n=name, m=m, b=label: tasks.overview(sets[n], kept[n, m], boxes[b]).first() for name, m, label in looks])
    return measured(spark, [(name, m, ks[name], label, r["kept"] / max(1, r["total"])) for (name, m, label), r in zip(looks, seen)])


def drawing_times(spark: SparkSession, sf: str, names: tuple[str, ...], shares: tuple[int, ...]) -> DataFrame:
    """(series, n, seconds): drawing a raster of growing shares (by hash) of each set, by two ways: pixels aggregated where rows are
    read, and every row's mark brought to the driver, as plotting libraries do."""
    rows = []
    for name in names:
        p = durable(load(spark, sf, name))
        for share in shares:
            part = p.where(F.pmod(F.xxhash64("id"), F.lit(100)) < share)
            n, began = part.count(), time.time()
            render.raster(part).agg(F.sum("n")).collect()
            rows.append((f"{name}_raster", float(n), time.time() - began))
            began = time.time()
            for batch in part.select("x", "y").toLocalIterator():  # a mark at a time
                batch["x"]
            rows.append((f"{name}_marks", float(n), time.time() - began))
    return spark.createDataFrame(rows, "series string, n double, seconds double")


def w2_plot_latency(spark: SparkSession, sf: str) -> DataFrame:
    """Seconds to draw growing shares of one set by two plotters, and the linear fit."""
    return budget.fit_latency(drawing_times(spark, sf, ("price",), (25, 50, 75, 100)))


def w3_plot_latency_sets(spark: SparkSession, sf: str) -> DataFrame:
    """The same for both sets."""
    return budget.fit_latency(drawing_times(spark, sf, ("hubs", "gauss5"), (20, 50, 100)))


@remembered
def answers_regression(spark: SparkSession, sf: str, ks=SIZES, names=("hubs", "price"), questions: int = 72) -> DataFrame:
    out = None
    for name in names:
        p = point_set(spark, sf, name)
        at = durable(tasks.places(p, questions))
        truth = durable(tasks.regression_truth(p, at))
        for k, m, s in samples(spark, sf, name, ks):
            a = tasks.regression(p, s, at, truth=truth).select(F.lit(name).alias("dataset"), F.lit(m).alias("method"), F.lit(k).alias("k"), "question", "correct")
            out = a if out is None else out.union(a)
    return out


def regression_answers(spark: SparkSession, sf: str, names=("hubs", "price")) -> DataFrame:
    return reduce(DataFrame.union, [answers_regression(spark, sf, names=(n,)) for n in names])


def with_weights(spark: SparkSession, sf: str, name: str, ks: tuple[int, ...]) -> list[tuple[int, str, DataFrame, str | None]]:
    """(k, method, sample, its column of weights): the samples of all sizes and methods, and the spread ones with density weights."""
    drawn = samples(spark, sf, name, ks)
    weighed = weights_of(spark, sf, name, ks)
    return [(k, m, s, None) for k, m, s in drawn] + [(k, "spread_density", weighed.where(F.col("size") == k), "density") for k in ks]


@remembered
def answers_density(spark: SparkSession, sf: str, ks=SIZES, names=("hubs", "latency"), questions: int = 80) -> DataFrame:
    def asked(name: str) -> list:
        p = point_set(spark, sf, name)
        at = tasks.marks(spark, p, questions)
        truth = durable(tasks.crowds(p, at))
        answers = lambda rows, w: tasks.density(p, rows, at, w, truth=truth)
        return [answers(rows, w).select(F.lit(name).alias("dataset"), F.lit(label).alias("method"), F.lit(k).alias("k"), "question", "correct") for k, label, rows, w in with_weights(spark, sf, name, ks)]

    found = [a for some in together(*[partial(asked, n) for n in names]) for a in some]
    return reduce(DataFrame.union, together(*[partial(durable, a) for a in found]))


@remembered
def answers_clustering(spark: SparkSession, sf: str, ks=SIZES, names=("mix1a", "mix1b", "mix2a", "mix2b")) -> DataFrame:
    def asked(q: int, name: str) -> list[tuple]:
        truth = int(point_set(spark, sf, name).first()["value"])
        return [(name, label, k, q, tasks.clusters(s, weight=w).first()["n"] == truth) for k, label, s, w in with_weights(spark, sf, name, ks)]

    rows = [r for some in together(*[partial(asked, q, name) for q, name in enumerate(names)]) for r in some]
    return spark.createDataFrame(rows, "dataset string, method string, k int, question int, correct boolean")


@remembered
def losses(spark: SparkSession, sf: str, name: str = "hubs", ks=(100, 316, 1000, 3162, 10_000), m: int = PROBE_COUNT) -> DataFrame:
    """(dataset, method, k, measure, v): log loss ratio of every method and size; the loss of all rows is taken once."""
    p = point_set(spark, sf, name)
    at = durable(measures.domain_probes(p, m))
    base = measures.average_loss(measures.point_loss(at, p, EPS)).first()[0]
    drawn = samples(spark, sf, name, ks)
    found = together(*[lambda s=s: measures.average_loss(measures.point_loss(at, s, EPS)).first()[0] for _, _, s in drawn])
    return measured(spark, [(name, method, k, "log_loss_ratio", v - base) for (k, method, _), v in zip(drawn, found)])


def w7_loss_success_correlation(spark: SparkSession, sf: str) -> DataFrame:
    """Rank correlation of log loss ratio and regression success over (method, k), twelve points: ours, and that of the printed pairs."""
    ks = SIZES
    success = {(r["method"], r["k"]): r["s"] for r in regression_answers(spark, sf, ("hubs",)).groupBy("method", "k").agg(F.avg(F.col("correct").cast("double")).alias("s")).collect()}
    ours = [(r["v"], success[r["method"], r["k"]]) for r in losses(spark, sf).where(F.col("k").isin(*ks)).collect()]
    rho = lambda rows: measures.spearman(spark.createDataFrame(rows, "a double, b double"), "a", "b", durable).first()
    a, b = rho(ours), rho(PRINTED_PAIRS)
    return spark.createDataFrame([("ours", a["n"], a["rho"], measures.t_tail(a["t"], a["n"] - 2)), ("printed", b["n"], b["rho"], measures.t_tail(b["t"], b["n"] - 2))], "pairs string, points long, rho double, p double")


def w8_error_time(spark: SparkSession, sf: str, names=("hubs", "docs")) -> DataFrame:
    """Log loss ratio over size; seconds from a line fitted to drawing times measured here, mark by mark, and from the printed slope
    of 8.83 s a million rows."""
    out = None
    for name in names:
        fit = budget.fit_latency(drawing_times(spark, sf, (name,), (25, 50, 100)).where("series LIKE '%marks'")).first()
        one = losses(spark, sf, name=name).withColumns({"seconds": F.greatest(F.lit(0.0), F.lit(fit["intercept"]) + F.lit(fit["slope"]) * F.col("k")), "printed_seconds": F.col("k") * 8.83e-6})
        out = one if out is None else out.union(one)
    return out


@remembered
def w10_exact_heuristic(spark: SparkSession, sf: str, sizes=(50, 60, 70, 80), k: int = 10) -> DataFrame:
    """Objective, seconds and log loss of the optimum, the exchange and a random choice."""
    out = []
    for n in sizes:
        p = durable(bl.uniform(load(spark, sf, "cust"), n))
        at = measures.probes(spark, 100, 1)
        makers = {"exact": lambda p=p: exact.exact(p, k, WIDE).select("id"), "exchange": lambda p=p: ex.exchange_until_stable(p, k, WIDE, durable=durable)[0].select("id"), "random": lambda p=p: bl.uniform(p, k, seed=5).select("id")}
        for method, make in makers.items():
            began = time.time()
            s = durable(p.join(F.broadcast(make()), "id", "left_semi"))  # k ids
            took = time.time() - began
            loss = measures.average_loss(measures.point_loss(at, s, WIDE), "mean").first()[0]
            out += [("cust", method, n, m, float(v)) for m, v in (("seconds", took), ("objective", measures.objective(s, WIDE).first()[0]), ("log_loss", loss))]
    return measured(spark, out)


@remembered
def w11_convergence(spark: SparkSession, sf: str, k: int = 1000) -> DataFrame:
    """Objective relative to its first and best value along one scan."""
    t = ex.trace(load(spark, sf, "hubs"), k, EPS, every=max(1000, k), variant=ex.choose_variant(k, k * 100 * EPS * EPS))
    w = Window.partitionBy("variant")
    return t.withColumn("scaled", (F.col("objective") - F.min("objective").over(w)) / F.nullif(F.max("objective").over(w) - F.min("objective").over(w), F.lit(0.0)))


@remembered
def w12_ablation(spark: SparkSession, sf: str, small: int = 100, large: int = 5000) -> DataFrame:
    """Seconds and kernel evaluations of no add-drop, add-drop, locality and locality with a heap, each over all rows; whole_seconds and whole_evals are
    those of all rows, so the same. Evaluations are those that a variant's rule takes; the one without add-drop remembers what no swap
    changed, so its seconds are fewer than its evaluations would take. Scans of one task run side by side, the longest first."""
    p = durable(load(spark, sf, "price").select("id", "x", "y"))

    def scanned(k: int, v: str) -> DataFrame:
        t = durable(ex.trace(p, k, EPS, every=1 << 40, variant=v))
        return t.groupBy("variant").agg(F.max("rows_seen").alias("rows_seen"), F.max("kernel_evals").alias("kernel_evals"), F.max("seconds").alias("seconds"), F.min_by("objective", -F.col("rows_seen")).alias("objective")).withColumn("k", F.lit(k))

    asked = [(k, v) for k in (large, small) for v in ("burden_test", "add_drop", "local", "heap")]
    last = reduce(DataFrame.union, together(*[partial(scanned, *a) for a in asked]))
    return last.withColumns({"whole_seconds": F.col("seconds"), "whole_evals": F.col("kernel_evals").cast("double")})


@remembered
def w13_build(spark: SparkSession, sf: str, ks=(100, 500, 1000, 10_000)) -> DataFrame:
    """Stored samples of several sizes of two sets: the manifest, and the seconds of the whole build."""
    path, began = new_path(spark, "catalog"), time.time()
    m = catalog.build(spark, {n: point_set(spark, sf, n) for n in ("latency", "hubs")}, list(ks), path, EPS, durable)
    return m.withColumn("seconds", F.lit(time.time() - began))


@remembered
def w14_runtime_scaling(spark: SparkSession, sf: str) -> DataFrame:
    """Seconds of the builders over K on all rows, and over N at one K. Greedy takes the row of least value among all rows each time. Builds of
    one task run side by side, the largest first, each on a core of its own while there are AT_ONCE cores."""
    p = durable(load(spark, sf, "mix2a").select("id", "x", "y"))
    cut = {share: p if share == 100 else durable(p.where(F.pmod(F.xxhash64("id"), F.lit(100)) < share)) for share in (100, 10, 1)}
    builders = {"random": lambda q, k: bl.uniform(q, k), "exchange": lambda q, k: ex.exchange(q, k, EPS), "exchange_local": lambda q, k: ex.exchange(q, k, EPS, variant="local"), "greedy": lambda q, k: ex.greedy_start(q, k, EPS)}

    def timed(method: str, share: int, k: int) -> tuple:
        began = time.time()
        builders[method](cut[share], k).count()
        return f"share{share}", method, k, "seconds", time.time() - began

    asked = [(m, share, k) for m in builders for share, k in ((100, 10), (100, 100), (100, 1000), (100, 10_000), (1, 100), (10, 100))]
    made = sorted(asked, key=lambda a: (a[0] == "random", -a[1] * a[2]))
    took = dict(zip(made, together(*[partial(timed, *a) for a in made])))
    return measured(spark, [took[a] for a in asked])


def query_log(spark: SparkSession, n: int = 2000) -> DataFrame:
    """A generated log: 40 column pairs, visited by a steep power law."""
    u = F.conv(F.substring(F.md5(F.concat(F.lit("log:"), F.col("id").cast("string"))), 1, 8), 16, 10).cast("double") / 4294967296.0
    rank = F.floor(F.lit(40.0) * F.pow(u, F.lit(12.0))).cast("int")
    return spark.range(n).select(F.col("id").alias("qid"), F.concat(F.lit("x"), rank.cast("string")).alias("xcol"), F.concat(F.lit("y"), (rank % 7).cast("string")).alias("ycol"))


LOG_SQL = "SELECT concat('x', r) AS xcol, concat('y', r % 7) AS ycol FROM (SELECT CAST(floor(40e0 * pow(CAST('0x' || substr(md5(concat('log:', i)), 1, 8) AS BIGINT) / 4294967296e0, 12e0)) AS INT) AS r FROM range(2000) AS t(i)) AS q"
ADVISE_SQL = f"SELECT xcol, ycol, n, round(sum(n) OVER (ORDER BY n DESC, xcol, ycol ROWS UNBOUNDED PRECEDING) / sum(n) OVER (), 9) AS share FROM (SELECT xcol, ycol, count(*) AS n FROM ({LOG_SQL}) AS l GROUP BY xcol, ycol) AS c"


def w18_stream_refresh(spark: SparkSession, sf: str, k: int = 60) -> DataFrame:
    """Events as a stream of files into a sample of k rows, against a batch build."""
    p = durable(load(spark, sf, "latency").select("id", "x", "y"))
    src, out = new_path(spark, "stream"), new_path(spark, "sample")
    p.withColumn("part", F.pmod(F.xxhash64("id"), F.lit(4))).repartition(4, "part").drop("part").write.parquet(src)
    rows = spark.readStream.schema(p.schema).option("maxFilesPerTrigger", 1).parquet(src)
    refresh.stream(rows, k, EPS, out, new_path(spark, "offsets")).awaitTermination()
    now = refresh.current(spark, out)
    j = lambda s: measures.objective_by_cells(s, EPS).first()[0]
    streamed, uniform = j(now), j(bl.uniform(p, k))
    return spark.createDataFrame([(now.count(), now.join(p.select("id"), "id", "left_anti").count(), streamed <= uniform)], "n_rows long, n_outside long, beats_uniform boolean")


for _f in (w1_zoom_coverage, w2_plot_latency, w3_plot_latency_sets, w7_loss_success_correlation, w8_error_time, w10_exact_heuristic, w11_convergence, w12_ablation, w13_build, w14_runtime_scaling):
    R.add(_f.__name__, _f)


def claims(*names: str):
    """Registers a function of booleans under its name, with the SQL that says that all are true."""
    return lambda f: R.add(f.__name__, f, "SELECT " + ", ".join(f"true AS {n}" for n in names)) or f


def by_method(answers: DataFrame) -> dict[str, float]:
    return {r["method"]: r["s"] for r in answers.groupBy("method").agg(F.avg(F.col("correct").cast("double")).alias("s")).collect()}


def said(spark: SparkSession, **facts: bool) -> DataFrame:
    return spark.createDataFrame([tuple(bool(v) for v in facts.values())], ", ".join(f"{c} boolean" for c in facts))


@claims("spread_beats_uniform", "spread_beats_grid")
def w4_regression_order(spark: SparkSession, sf: str) -> DataFrame:
    s = by_method(regression_answers(spark, sf))
    return said(spark, spread_beats_uniform=s["spread"] > s["uniform"], spread_beats_grid=s["spread"] > s["grid"])


@claims("weights_beat_plain_spread", "weights_beat_grid")
def w5_density_order(spark: SparkSession, sf: str) -> DataFrame:
    s = by_method(answers_density(spark, sf))
    return said(spark, weights_beat_plain_spread=s["spread_density"] > s["spread"], weights_beat_grid=s["spread_density"] > s["grid"])


@claims("weights_no_worse_than_plain")
def w6_clustering_order(spark: SparkSession, sf: str) -> DataFrame:
    s = by_method(answers_clustering(spark, sf))
    return said(spark, weights_no_worse_than_plain=s["spread_density"] >= s["spread"])


@claims("twelve_points", "more_loss_less_success", "printed_rho")
def w7_correlation_sign(spark: SparkSession, sf: str) -> DataFrame:
    r = {x["pairs"]: x for x in w7_loss_success_correlation(spark, sf).collect()}
    return said(spark, twelve_points=r["ours"]["points"] == 12, more_loss_less_success=r["ours"]["rho"] < -0.5, printed_rho=abs(r["printed"]["rho"] + 0.84615) < 1e-5)


@claims("spread_is_lowest", "loss_falls_with_size", "spread_loses_nothing_at_last")
def w8_loss_order(spark: SparkSession, sf: str) -> DataFrame:
    v = {(r["method"], r["k"]): r["v"] for r in losses(spark, sf).collect()}
    ks = sorted({k for _, k in v})
    return said(spark, spread_is_lowest=all(v["spread", k] <= min(v["uniform", k], v["grid", k]) for k in ks), loss_falls_with_size=all(v[m, ks[-1]] < v[m, ks[0]] for m in METHODS), spread_loses_nothing_at_last=v["spread", ks[-1]] < 0.2)


@claims("exact_lowest", "exchange_below_random", "every_measure")
def w10_order(spark: SparkSession, sf: str) -> DataFrame:
    v = {(r["method"], r["k"], r["measure"]): r["v"] for r in w10_exact_heuristic(spark, sf).collect()}
    j = lambda m, n: v[m, n, "objective"]
    ns = sorted({n for _, n, _ in v})
    return said(spark, exact_lowest=all(j("exact", n) <= j("exchange", n) + 1e-12 for n in ns), exchange_below_random=all(j("exchange", n) < j("random", n) for n in ns), every_measure=len(v) == 9 * len(ns))


@claims("never_rises", "ends_at_best")
def w11_descent(spark: SparkSession, sf: str) -> DataFrame:
    t = [r["scaled"] for r in w11_convergence(spark, sf).orderBy("rows_seen").collect()]
    return said(spark, never_rises=all(b <= a + 1e-9 for a, b in zip(t, t[1:])), ends_at_best=t[-1] <= 1e-9)


@claims("add_drop_saves", "locality_saves_at_large_k", "heap_same_evals")
def w12_evals(spark: SparkSession, sf: str) -> DataFrame:
    v = {(r["k"], r["variant"]): r["whole_evals"] for r in w12_ablation(spark, sf).collect()}
    return said(spark, add_drop_saves=all(v[k, "add_drop"] < v[k, "burden_test"] for k in (100, 5000)), locality_saves_at_large_k=v[5000, "local"] < v[5000, "add_drop"], heap_same_evals=v[5000, "heap"] == v[5000, "local"])


@claims("every_size", "spread_is_lowest", "all_rows_seen")
def w13_manifest(spark: SparkSession, sf: str) -> DataFrame:
    m = [r.asDict() for r in w13_build(spark, sf).collect()]
    j = {(r["dataset"], r["k"], r["method"]): r["objective"] for r in m}
    lowest = all(j[d, k, "spread"] <= v * (1 + 1e-9) + 1e-9 for (d, k, _), v in j.items())  # equal where k takes all rows
    return said(spark, every_size=len(m) == 2 * 4 * 3, spread_is_lowest=lowest, all_rows_seen=all(r["rows_seen"] > 0 for r in m))


@claims("every_run", "positive")
def w14_runs(spark: SparkSession, sf: str) -> DataFrame:
    v = w14_runtime_scaling(spark, sf).collect()
    return said(spark, every_run=len(v) == 24, positive=all(r["v"] > 0 for r in v))


R.add("w4_regression", lambda s, d: tasks.success_table(regression_answers(s, d)))
R.add("w5_density", lambda s, d: tasks.success_table(answers_density(s, d)))
R.add("w6_clustering", lambda s, d: tasks.success_table(answers_clustering(s, d)))
R.add("w9_error_time_gauss", lambda s, d: w8_error_time(s, d, names=("gauss5",)))
R.add("w15_pair_shares", lambda s, d: budget.advise_by_frequency(query_log(s)).withColumn("share", F.round("share", 9)), ADVISE_SQL)
R.add("w16_quota", lambda s, d: bl.balanced_quota(s.createDataFrame([("a", 500), ("b", 10)], "bin string, n long"), 100), "SELECT * FROM (VALUES ('a', CAST(500 AS BIGINT), CAST(90 AS BIGINT)), ('b', CAST(10 AS BIGINT), CAST(10 AS BIGINT))) AS t(bin, n, quota)")
R.add("w18_stream_refresh", w18_stream_refresh, "SELECT CAST(60 AS BIGINT) AS n_rows, CAST(0 AS BIGINT) AS n_outside, true AS beats_uniform")

# --- tasks on samples that SQL can draw
MARKS = f"SELECT mx, my, mq FROM (SELECT x AS mx, y AS my, row_number() OVER (ORDER BY md5(concat('mark:', id)), id) - 1 AS mq FROM ({unit('docs')}) AS p) AS z WHERE z.mq < 40"


def near_sql(rows: str) -> str:
    return f"SELECT m.mq AS mq, arg_min(value, ROW((x - mx) * (x - mx) + (y - my) * (y - my), id)) AS v FROM ({rows}) AS r, ({MARKS}) AS m WHERE (x - mx) * (x - mx) + (y - my) * (y - my) <= 0.03e0 * 0.03e0 GROUP BY m.mq"


R.add("u_regression_uniform", lambda s, d: tasks.regression(p := load(s, d, "docs"), bl.uniform(p, 60), tasks.marks(s, p, 40)), f"SELECT CAST(m.mq AS INT) AS question, coalesce(abs(r.v - t.v) < (SELECT max(value) - min(value) FROM ({unit('docs')}) AS a) / 20, false) AS correct FROM ({MARKS}) AS m JOIN ({near_sql(unit('docs'))}) AS t ON t.mq = m.mq LEFT JOIN ({near_sql(bottom('docs', 60))}) AS r ON r.mq = m.mq")
R.add("u_regression_grid", lambda s, d: tasks.regression(p := load(s, d, "docs"), bl.balanced_grid(p, 60), tasks.marks(s, p, 40)), f"SELECT CAST(m.mq AS INT) AS question, coalesce(abs(r.v - t.v) < (SELECT max(value) - min(value) FROM ({unit('docs')}) AS a) / 20, false) AS correct FROM ({MARKS}) AS m JOIN ({near_sql(unit('docs'))}) AS t ON t.mq = m.mq LEFT JOIN ({near_sql(grid_sql('docs', 60, 10))}) AS r ON r.mq = m.mq")


def seen_sql(rows: str, weight: str) -> str:
    """Per question of four marks: the fullest and the emptiest, and whether each is alone."""
    counts = f"SELECT m.mq AS mq, CAST(m.mq // 4 AS INT) AS q, coalesce(sum({weight}) FILTER (WHERE (x - mx) * (x - mx) + (y - my) * (y - my) <= 0.03e0 * 0.03e0), 0) AS n FROM ({MARKS}) AS m LEFT JOIN ({rows}) AS r ON abs(x - mx) <= 0.03e0 AND abs(y - my) <= 0.03e0 GROUP BY m.mq"
    return f"SELECT q, arg_max(mq, n) AS most, arg_min(mq, n) AS least, count(*) FILTER (WHERE n = hi) = 1 AS top, count(*) FILTER (WHERE n = lo) = 1 AS low FROM (SELECT *, max(n) OVER (PARTITION BY q) AS hi, min(n) OVER (PARTITION BY q) AS lo FROM ({counts}) AS c) AS e GROUP BY q"


def density_sql(rows: str, weight: str) -> str:
    return f"SELECT a.q AS question, CASE WHEN a.top AND a.low AND b.top AND b.low THEN a.most = b.most AND a.least = b.least ELSE a.most = b.most AND a.least = b.least AND b.top AND b.low END AS correct FROM ({seen_sql(unit('docs'), '1')}) AS a JOIN ({seen_sql(rows, weight)}) AS b ON a.q = b.q"


R.add("u_density_uniform", lambda s, d: tasks.density(p := load(s, d, "docs"), bl.uniform(p, 300), tasks.marks(s, p, 40)), density_sql(bottom("docs", 300), "1"))
R.add("u_density_weighted_grid", lambda s, d: tasks.density(p := load(s, d, "docs"), (g := durable(bl.balanced_grid(p, 100))).join(density.by_index(g, p), "id"), tasks.marks(s, p, 40), "density"), density_sql(f"SELECT g.*, w.density FROM ({grid_sql('docs', 100, 10)}) AS g JOIN ({DENSITY_SQL('docs', 100, grid_sql('docs', 100, 10))}) AS w ON g.id = w.id", "density"))
CLUSTERS_SQL = f"""
WITH RECURSIVE px AS (SELECT least(15, CAST(floor(x * 16) AS INT)) AS px, least(15, CAST(floor(y * 16) AS INT)) AS py, CAST(count(*) AS DOUBLE) AS n FROM ({bottom('mix2a', 2000)}) AS s GROUP BY 1, 2),
o AS (SELECT a.range - 1 AS dx, b.range - 1 AS dy FROM range(3) AS a, range(3) AS b),
sm AS (SELECT px + dx AS px, py + dy AS py, sum(n / (1 + abs(dx) + abs(dy))) AS n FROM px, o GROUP BY 1, 2),
full_ AS (SELECT px, py, (px + 8) * 100 + py + 8 AS id FROM sm WHERE n >= 0.35e0 * (SELECT max(n) FROM sm)),
reach AS (SELECT id, id AS root FROM full_ UNION SELECT b.id, r.root FROM reach AS r JOIN full_ AS a ON a.id = r.id JOIN full_ AS b ON abs(a.px - b.px) <= 1 AND abs(a.py - b.py) <= 1)
SELECT CAST(count(*) AS INT) AS n FROM (SELECT root, count(*) AS size FROM (SELECT id, min(root) AS root FROM reach GROUP BY id) AS l GROUP BY root HAVING count(*) >= 3) AS z"""
R.add("u_clusters_raster", lambda s, d: tasks.clusters(uni(s, d, "mix2a", 2000)), CLUSTERS_SQL)
R.add("u_regression_spread", lambda s, d: tasks.success_table(answers_regression(s, d, ks=(200,), names=("price",))))
R.add("u_density_spread", lambda s, d: tasks.success_table(answers_density(s, d, ks=(200,), names=("hubs",)).where("method = 'spread'")))
R.add("u_density_spread_weighted", lambda s, d: tasks.success_table(answers_density(s, d, ks=(200,), names=("hubs",))))
R.add("u_clustering_spread", lambda s, d: tasks.success_table(answers_clustering(s, d, ks=(300,), names=("mix1a", "mix2a"))))
R.add("u_loss_correlation", lambda s, d: w7_loss_success_correlation(s, d).where("pairs = 'ours'"))
R.add("u_success_table", lambda s, d: tasks.success_table(s.createDataFrame([(100, "uniform", True), (100, "spread", True), (100, "spread", False), (1000, "uniform", False), (1000, "spread", True)], "k int, method string, correct boolean")), "SELECT * FROM (VALUES (100, 1e0, 0.5e0), (1000, 0e0, 1e0), (NULL, 0.5e0, 0.6666666666666666e0)) AS t(k, uniform, spread)")

# --- query time
#: Printed seconds of the plotting library for both datasets, and the printed error/time curves used for speed-ups.
LATENCIES = [("gps", 1, 9), ("gps", 5, 44), ("gps", 10, 87), ("gps", 24, 212), ("gauss", 1, 9), ("gauss", 5, 45), ("gauss", 10, 89), ("gauss", 50, 450)]
CURVES = [("spread", 0.1, 7.739), ("spread", 0.2, 1.099), ("spread", 1, 0.3141), ("spread", 9, 0.0780), ("grid", 1, 54.747), ("grid", 9, 15.550), ("grid", 18, 12.566), ("grid", 27, 12.192), ("grid", 36, 12.084), ("grid", 45, 0.598), ("grid", 54, 0.325), ("grid", 63, 0.0780), ("grid", 90, 0.0376), ("grid", 135, 0.0131), ("uniform", 9, 56.217), ("uniform", 18, 49.436), ("uniform", 27, 25.727), ("uniform", 36, 23.241), ("uniform", 45, 6.322), ("uniform", 54, 3.745), ("uniform", 63, 3.483), ("uniform", 90, 3.369), ("uniform", 135, 0.607), ("uniform", 171, 2.850), ("uniform", 180, 0.0890), ("uniform", 216, 0.0)]
values_sql = lambda rows, cols: "SELECT * FROM (VALUES " + ", ".join("(" + ", ".join(f"'{v}'" if isinstance(v, str) else f"{float(v)!r}e0" for v in r) + ")" for r in rows) + f") AS t({cols})"
curves = lambda s: s.createDataFrame([(m, float(t), float(e)) for m, t, e in CURVES], "method string, seconds double, error double")
CURVES_SQL = values_sql(CURVES, "method, seconds, error")
LINE_COLUMNS = ["l_quantity", "l_extendedprice", "l_discount", "l_tax"]
R.add("q_fit_latency", lambda s, d: budget.fit_latency(s.createDataFrame([(a, float(b), float(c)) for a, b, c in LATENCIES], "series string, n double, seconds double")).select("series", *[F.round(c, 6).alias(c) for c in ("slope", "intercept", "r2")]), f"SELECT series, round(regr_slope(seconds, n), 6) AS slope, round(regr_intercept(seconds, n), 6) AS intercept, round(regr_r2(seconds, n), 6) AS r2 FROM ({values_sql(LATENCIES, 'series, n, seconds')}) AS v GROUP BY series")
R.add("q_pick_size", lambda s, d: budget.pick(s.createDataFrame([(100,), (1000,), (10_000,), (100_000,)], "k int"), 0.5, 8.83e-6), "SELECT 10000 AS k, true AS fits")
R.add("q_error_vs_time", lambda s, d: budget.best_error_by_time(curves(s)), f"SELECT *, min(error) OVER (PARTITION BY method ORDER BY seconds ROWS UNBOUNDED PRECEDING) AS best FROM ({CURVES_SQL}) AS c")
R.add("q_time_for_error", lambda s, d: budget.time_for_error(curves(s), 1.0), f"SELECT method, min(seconds) AS seconds FROM ({CURVES_SQL}) AS c WHERE error <= 1 GROUP BY method")
R.add("q_speedup_printed", lambda s, d: budget.speedup(curves(s), "spread").withColumn("factor", F.round("factor", 6)), "SELECT * FROM (VALUES (0.1e0, 'uniform', 450e0), (0.2e0, 'uniform', 675e0), (1e0, 'uniform', 180e0), (9e0, 'uniform', 24e0), (0.1e0, 'grid', 450e0), (0.2e0, 'grid', 225e0), (1e0, 'grid', 63e0), (9e0, 'grid', 7e0)) AS t(ours_seconds, method, factor)")
R.add("q_advise_frequency", lambda s, d: budget.advise_by_frequency(query_log(s)).where("n > 20").withColumn("share", F.round("share", 9)), f"SELECT * FROM ({ADVISE_SQL}) AS a WHERE n > 20")
R.add("q_coverage_share", lambda s, d: budget.advise_by_frequency(query_log(s)).limit(4).agg((F.max("share") >= 0.8).alias("tenth_covers_most")), "SELECT true AS tenth_covers_most")
_shape = lambda c: f"(SELECT abs(skewness({c})) * (count({c}) - 2) / sqrt(CAST(count({c}) AS DOUBLE) * (count({c}) - 1)) FROM lineitem)"
_tails = lambda c: f"(SELECT abs(kurtosis_pop({c})) FROM lineitem)"
R.add("q_advise_stats", lambda s, d: (points.tables(s, d, "lineitem"), rounded(budget.advise_by_stats(s.table("lineitem"), LINE_COLUMNS).drop("distinct"), "score", "skew", "tails", digits=5))[1], " UNION ALL ".join(f"SELECT '{a}' AS xcol, '{b}' AS ycol, (SELECT round(1 - abs(corr({a}, {b})), 5) FROM lineitem) AS score, round({_shape(a)} + {_shape(b)}, 5) AS skew, round({_tails(a)} + {_tails(b)}, 5) AS tails" for i, a in enumerate(LINE_COLUMNS) for b in LINE_COLUMNS[i + 1 :]))
R.add("q_advise_manual", lambda s, d: budget.advise_manually(s.read.parquet(f"{d}/lineitem.parquet"), [("l_quantity", "l_extendedprice"), ("l_discount", "l_tax")]), "SELECT * FROM (VALUES ('l_quantity', 'l_extendedprice'), ('l_discount', 'l_tax')) AS t(xcol, ycol)")


def weighted_avg(s: SparkSession, d: str) -> DataFrame:
    p = load(s, d, "docs")
    sample = durable(bl.uniform(p, 60))
    return budget.weighted_average(sample.join(density.by_index(sample, p), "id"), "category").withColumn("estimate", F.round("estimate", 6))


R.add("q_weighted_avg", weighted_avg, f"SELECT category, round(sum(density * value) / sum(density), 6) AS estimate, CAST(sum(density) AS BIGINT) AS rows FROM ({bottom('docs', 60)}) AS s JOIN ({DENSITY_SQL('docs', 60)}) AS w ON s.id = w.id GROUP BY category")


def stored(s: SparkSession, d: str) -> str:
    path = new_path(s, "catalog")
    catalog.build(s, {"latency": durable(load(s, d, "latency"))}, [50, 200], path, EPS, durable, ("spread",))
    return path


R.add("q_routed_sql", lambda s, d: catalog.routed(s, "SELECT count(*) AS n, CAST(sum(density) AS BIGINT) AS stands_for FROM latency_sample", "latency_sample", stored(s, d), "latency", 0.001, 8.83e-6), "SELECT CAST(50 AS BIGINT) AS n, count(*) AS stands_for FROM events")


def through_source(s: SparkSession, d: str) -> DataFrame:
    from spreadsample.sources.sample_source import register

    register(s)
    files = s.read.parquet(stored(s, d)).where("k = 200").inputFiles()
    return s.read.format("spread_sample").option("files", "\n".join(f.removeprefix("file://") for f in files if "k=200" in f)).load().agg(F.count("*").alias("n"), F.sum("density").alias("stands_for"))


R.add("q_datasource", through_source, "SELECT CAST(200 AS BIGINT) AS n, count(*) AS stands_for FROM events")


def through_udtf(s: SparkSession, d: str) -> DataFrame:
    from spreadsample.sources.sample_source import register

    register(s)
    load(s, d, "latency").select("id", "x", "y", "category").createOrReplaceTempView("latency_points")
    return s.sql("SELECT count(*) AS n, count(DISTINCT id) AS ids FROM spread_sample(TABLE(latency_points) PARTITION BY (category), 10, 0.0141)")


R.add("q_udtf", through_udtf, "SELECT CAST(10 * count(DISTINCT event_type) AS BIGINT) AS n, CAST(10 * count(DISTINCT event_type) AS BIGINT) AS ids FROM events")


def small_build(s: SparkSession, d: str) -> DataFrame:
    return catalog.build(s, {"latency": durable(load(s, d, "latency"))}, [100, 500], new_path(s, "catalog"), EPS, durable)


R.add("q_catalog_build", lambda s, d: small_build(s, d).groupBy("dataset", "k").agg(F.count("*").alias("methods"), (F.min_by("method", "objective") == "spread").alias("spread_is_lowest")), "SELECT 'latency' AS dataset, k, CAST(3 AS BIGINT) AS methods, true AS spread_is_lowest FROM (VALUES (100), (500)) AS t(k)")
