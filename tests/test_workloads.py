"""Samples that experiments share, and what they ask of all rows once."""

import tracemalloc

import numpy as np
import pytest
from pyspark.sql import functions as F

from spreadsample.functions import points
from spreadsample.functions.runtime import durable, together
from spreadsample.operators import baselines as bl
from spreadsample.operators import exchange as ex
from spreadsample.operators import density, measures, tasks, workloads
from spreadsample.plans import catalog

SF = "/root/testdata/sf0.001"


def test_nested_samples(spark):
    p = workloads.point_set(spark, SF, "hubs")
    drawn = {(k, m): {r["id"] for r in s.select("id").collect()} for k, m, s in workloads.samples(spark, SF, "hubs", (50, 300))}
    assert set(drawn) == {(k, m) for k in (50, 300) for m in workloads.METHODS} and all(len(v) == k for (k, _), v in drawn.items())
    for k in (50, 300):
        assert drawn[k, "uniform"] == {r["id"] for r in bl.uniform(p, k).collect()}
        assert drawn[k, "grid"] == {r["id"] for r in bl.balanced_grid(p, k, 100).collect()}


def test_truth_is_taken_once(spark):
    p = workloads.point_set(spark, SF, "hubs")
    s, at, marks = bl.uniform(p, 200), tasks.places(p, 20), tasks.marks(spark, p, 20)
    assert sorted(tasks.regression(p, s, at).collect()) == sorted(tasks.regression(None, s, at, truth=tasks.regression_truth(p, at)).collect())
    assert sorted(tasks.density(p, s, marks).collect()) == sorted(tasks.density(None, s, marks, truth=tasks.crowds(p, marks)).collect())


def test_together(spark):
    assert together(*[lambda n=n: spark.range(n).count() for n in range(6)]) == list(range(6))
    with pytest.raises(ZeroDivisionError):
        together(lambda: 1, lambda: 1 / 0)


def test_spread_of_many_rows_goes_through_tiles(spark, monkeypatch):
    """Above the rows of a block, samples of the experiments are built in parallel, and are near the one-block build."""
    p = workloads.point_set(spark, SF, "hubs")
    one = measures.objective_by_cells(workloads.spread(p, 200), workloads.EPS).first()[0]
    uniform = measures.objective_by_cells(bl.uniform(p, 200), workloads.EPS).first()[0]
    seen = []
    tiled = ex.exchange_tiles
    monkeypatch.setattr(catalog, "BLOCK_ROWS", 1000)
    monkeypatch.setattr(ex, "exchange_tiles", lambda *a, **o: seen.append(o) or tiled(*a, **o))
    s = workloads.spread(p, 200)
    assert s.count() == 200 and s.join(p, "id", "left_anti").isEmpty() and seen and seen[0]["tile_variant"] == "add_drop"
    assert measures.objective_by_cells(s, workloads.EPS).first()[0] < one + 0.1 * (uniform - one)


def test_derived_sets_are_compiled(spark):
    """The filter on places stays above the struct, and rows are those of the SQL."""
    for name in ("hubs", "mix2b"):
        made = points.load(spark, SF, name)
        assert "Join Inner, ((abs(" not in (plan := made._jdf.queryExecution().optimizedPlan().toString()) and "inline(" in plan
        assert sorted(made.collect()) == sorted(spark.sql(points.unit_sql(name)).collect())
        assert sorted(points.load(spark, SF, name, False).collect()) == sorted(spark.sql(points.raw_sql(name)).collect())


def test_zoom_coverage_builds_side_by_side(spark, monkeypatch):
    seen = []
    run = workloads.together
    monkeypatch.setattr(workloads, "together", lambda *a: seen.append(len(a)) or run(*a))
    rows = workloads.w1_zoom_coverage(spark, SF).collect()
    assert seen == [6, 24] and len({(r["dataset"], r["method"], r["measure"]) for r in rows}) == 24
    p = points.load(spark, SF, "latency")
    r = tasks.overview(p, workloads.spread(p, max(100, p.count() // 100)), (0.2, 0.5, 0.2, 0.5)).first()
    assert [x["v"] for x in rows if (x["dataset"], x["method"], x["measure"]) == ("latency", "spread", "zoom1")] == [r["kept"] / max(1, r["total"])]


def test_spreads_of_many_rows_share_one_dealing(spark, monkeypatch):
    """Sizes that go through tiles are built from one dealing of all rows; each has k rows of the set, near the one-block build."""
    p = workloads.point_set(spark, SF, "mix1a")
    monkeypatch.setattr(catalog, "BLOCK_ROWS", 1000)
    seen = []
    pools = ex.tile_pools
    monkeypatch.setattr(ex, "tile_pools", lambda q, of, *a, **o: seen.append(of) or pools(q, of, *a, **o))
    drawn = {k: s for k, m, s in workloads.samples(spark, SF, "mix1a", (60, 200, 1100)) if m == "spread"}
    assert seen == [{k: catalog.tiles_for(k, p.count()) for k in (60, 200, 1100)}]
    for k, s in drawn.items():
        assert s.columns == p.columns and s.count() == k and s.join(p, p.columns, "left_anti").isEmpty()
        j = lambda d: measures.objective_by_cells(d, workloads.EPS).first()[0]
        one, uniform = j(ex.exchange(p, k, workloads.EPS)), j(bl.uniform(p, k))
        assert j(s) < one + 0.1 * (uniform - one)


def test_wide_builds_go_through_tiles():
    """600,000 rows at K = 10,000 are no block of one task."""
    assert not catalog.in_block(10_000, 600_000) and catalog.in_block(10_000, 60_000) and catalog.in_block(1000, 600_000)


def test_quadtree_is_exact():
    g = np.random.default_rng(3)
    for _ in range(100):
        k = int(g.integers(1, 80))
        mx, my = g.integers(0, 6, k) / 5, g.integers(0, 6, k) / 5  # ties, and members at one place
        x, y = g.integers(-10, 30, 200) / 10, g.integers(-10, 30, 200) / 10
        d2 = (x[:, None] - mx) ** 2 + (y[:, None] - my) ** 2
        assert (density.QuadIndex(mx, my).nearest(x, y) == d2.argmin(axis=1)).all()
    one = density.QuadIndex(np.zeros(5000), np.zeros(5000))
    assert len(one.who) == 1 and one.nearest(np.ones(3), np.ones(3)).tolist() == [0, 0, 0]


def test_quadtree_stays_small(monkeypatch):
    """Ten thousand members with a long thin tail: every task builds the index, so it may not take hundreds of MB. Cells that are not
    quartered are still exact."""
    g = np.random.default_rng(4)
    mx, my = g.integers(0, 86_400, 10_000) / 86_400, g.exponential(0.07, 10_000)
    tracemalloc.start()
    index = density.QuadIndex(mx, my)
    peak = tracemalloc.get_traced_memory()[1] >> 20
    tracemalloc.stop()
    assert peak < 100
    x, y = g.random(300), g.exponential(0.1, 300)
    best = ((x[:, None] - mx) ** 2 + (y[:, None] - my) ** 2).argmin(axis=1)
    assert (index.nearest(x, y) == best).all()
    monkeypatch.setattr(density, "LEVEL_MEMBERS", 1 << 14)
    monkeypatch.setattr(density, "QUARTERED", 1 << 10)
    assert (density.QuadIndex(mx, my).nearest(x, y) == best).all()


def test_weights_of_several_samples(spark):
    p = workloads.point_set(spark, SF, "hubs")
    drawn = [bl.uniform(p, k) for k in (5, 300)]
    for s, w in zip(drawn, density.by_indexes(drawn, p)):
        assert sorted(w.collect()) == sorted(density.by_scan(s, p).collect())


def test_catalog_deals_rows_once_for_all_sizes(spark, monkeypatch, tmp_path):
    monkeypatch.setattr(catalog, "BLOCK_ROWS", 1000)
    seen = []
    pools = ex.tile_pools
    monkeypatch.setattr(ex, "tile_pools", lambda q, of, *a, **o: seen.append(sorted(of)) or pools(q, of, *a, **o))
    p = workloads.point_set(spark, SF, "hubs")
    m = catalog.build(spark, {"hubs": p}, [50, 300], str(tmp_path / "c"), workloads.EPS, durable, ("spread",))
    assert seen == [[50, 300]] and m.count() == 2
    stored = {r["k"]: (r["n"], r["d"]) for r in spark.read.parquet(str(tmp_path / "c")).groupBy("k").agg(F.count("*").alias("n"), F.sum("density").alias("d")).collect()}
    assert stored == {50: (50, p.count()), 300: (300, p.count())}


def test_catalog_reads_rows_once_for_all_weights(spark, monkeypatch, tmp_path):
    """Samples of all methods and sizes of a set share the scan of their weights, and are those that each makes alone."""
    seen = []
    count = density.by_indexes
    monkeypatch.setattr(density, "by_indexes", lambda samples, *a, **o: seen.append(len(samples)) or count(samples, *a, **o))
    p = workloads.point_set(spark, SF, "hubs")
    m = catalog.build(spark, {"hubs": p}, [50, 300], str(tmp_path / "c"), workloads.EPS, durable)
    assert seen == [6] and m.count() == 6
    for method, make in (("uniform", bl.uniform), ("grid", bl.balanced_grid), ("spread", lambda q, k: workloads.spread(q, k))):
        for k in (50, 300):
            alone = make(p, k)
            stored = spark.read.parquet(str(tmp_path / "c")).where((F.col("method") == method) & (F.col("k") == k))
            assert sorted(stored.select("id", "density").collect()) == sorted(density.by_scan(alone, p).collect())


def test_wide_tiles_keep_more_rows(spark):
    """Most rows in a corner, the others all over: the tiles' survivors must cover the wide part, or the sample is worse than a grid's."""
    g = np.random.default_rng(5)
    x, y = (np.concatenate((g.random(16_000) * 0.1, g.random(4_000))) for _ in range(2))
    p = durable(spark.createDataFrame([(f"{i:05d}", float(a), float(b), 0.0, "a") for i, (a, b) in enumerate(zip(x, y))], "id string, x double, y double, value double, category string"))
    pools = {r["k"]: r["n"] for r in ex.tile_pools(p, {1500: 64}, workloads.EPS, variant="add_drop").where("x > 0.1 or y > 0.1").groupBy("k").agg(F.count("*").alias("n")).collect()}
    assert pools[1500] > 1200
    j = lambda s: measures.objective_by_cells(s, workloads.EPS).first()[0]
    assert j(ex.exchange_tiles(p, 1500, workloads.EPS, n_tiles=64)) < j(bl.balanced_grid(p, 1500))


def test_quotas_reach_what_is_wanted():
    g = np.random.default_rng(6)
    for _ in range(200):
        groups = {(i, 0): (int(g.integers(1, 50)), 0.0, float(g.random() ** 4), 0.0, float(g.integers(0, 2))) for i in range(int(g.integers(1, 20)))}
        want = int(g.integers(1, 600))
        got = ex.shares(groups, want)
        assert all(1 <= got[k] <= n[0] for k, n in groups.items()) and sum(got.values()) >= min(want, sum(n[0] for n in groups.values()))
    assert ex.shares({"crowd": (1000, 0.0, 0.1, 0.0, 0.1), "wide": (1000, 0.0, 1.0, 0.0, 1.0)}, 400)["wide"] > 250


def test_ablation_scans_all_rows(spark):
    """No variant stops early, and none is extrapolated: evaluations without add-drop are those of all rows."""
    n = points.load(spark, SF, "price").count()
    rows = {(r["k"], r["variant"]): r for r in workloads.w12_ablation(spark, SF, small=20, large=300).collect()}
    assert len(rows) == 8 and {r["rows_seen"] for r in rows.values()} == {n}
    for k in (20, 300):
        tested = rows[k, "burden_test"]
        assert tested["kernel_evals"] == tested["whole_evals"] >= (n - k) * k * k > rows[k, "add_drop"]["whole_evals"]
        assert tested["objective"] == pytest.approx(rows[k, "add_drop"]["objective"], rel=1e-6, abs=1e-12)


def test_burden_test_decides_by_the_rule():
    """With remembered proximities the same rows come in as when all are taken anew for each newcomer."""
    g = np.random.default_rng(7)
    x, y, ids, k = g.random(500) ** 2, g.random(500), np.array([f"{i:03d}" for i in range(500)], object), 40
    work = ex.WorkingSet(k, 0.05, variant="burden_test")
    work.offer(ids, x, y)
    near = lambda a, b: np.exp(-((x[a][:, None] - x[b]) ** 2 + (y[a][:, None] - y[b]) ** 2) / (2 * 0.05**2))
    held, swaps = np.arange(k), 0
    for i in range(k, 500):
        pairs, new = near(held, held), near(np.array([i]), held)[0]
        gains = pairs.sum(axis=1) - 1 - (new.sum() - new)
        if gains.max() > ex.SLACK:
            held[gains.argmax()] = i
            swaps += 1
    assert sorted(work.id.tolist()) == sorted(ids[held].tolist()) and work.swaps == swaps
    assert work.evals == k * (k - 1) // 2 + (500 - k) * k * k + swaps * k
    assert np.allclose(work.b, work.exact_burdens(), rtol=1e-12, atol=1e-14)


def test_burden_test_passes_over_rows_that_stay_out():
    """Beyond CALM members batches in single precision decide alike: the swaps and the set of add-drop, and evaluations for every row."""
    g = np.random.default_rng(8)
    x, y, ids, k = g.random(30_000), g.random(30_000) ** 2, np.arange(30_000).astype(str).astype(object), 600
    tested, dropped = (ex.WorkingSet(k, 0.02, variant=v) for v in ("burden_test", "add_drop"))
    for work in (tested, dropped):
        work.offer(ids, x, y)
    assert tested.swaps == dropped.swaps and sorted(tested.id) == sorted(dropped.id) and tested.calm > 1
    assert tested.evals == k * (k - 1) // 2 + (30_000 - k) * k * k + tested.swaps * k


def test_scaling_makes_every_run(spark):
    """No builder is left out at any size: plain exchange runs at K = 10,000 too."""
    rows = workloads.w14_runtime_scaling(spark, SF).collect()
    assert len(rows) == 24 and ("share100", "exchange", 10_000) in {(r["dataset"], r["method"], r["k"]) for r in rows}
