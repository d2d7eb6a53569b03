"""The working set against brute force, and samples on awkward inputs."""

import random
import time
from itertools import combinations

import numpy as np
import pyarrow as pa
import pytest

from spreadsample.functions import bandwidth, kernels
from spreadsample.operators import baselines, certify, density, exact, measures
from spreadsample.operators import exchange as ex
from spreadsample.operators import queries
from spreadsample.plans import catalog  # noqa: F401

EPS = 0.1


def cloud(n, seed):
    rng = np.random.default_rng(seed)
    return np.array([f"{i:04d}" for i in range(n)], object), rng.random(n), rng.random(n)


def frame(spark, rows):
    return spark.createDataFrame([(str(i), float(x), float(y), 0.0, "a") for i, x, y in rows], "id string, x double, y double, value double, category string")


def total(work):
    return sum(float(work.near(work.x[a], work.y[a], work.x[b], work.y[b])) for a, b in combinations(range(work.n), 2))


@pytest.mark.parametrize("seed", range(25))
def test_variants_agree_and_objective_descends(seed):
    ids, x, y = cloud(60, seed)
    sets = []
    for variant in ("add_drop", "burden_test", "recompute", "local", "heap"):
        work = ex.WorkingSet(6, EPS, variant=variant, tol=1e-300)
        last = None
        for i in range(len(ids)):
            work.offer(ids[i : i + 1], x[i : i + 1], y[i : i + 1])
            if work.n == 6:
                now = total(work)
                assert last is None or now <= last + 1e-12
                last = now
        sets.append(frozenset(work.id))
    assert len(set(sets)) == 1


@pytest.mark.parametrize("seed", range(10))
def test_batches_decide_like_single_rows(seed):
    ids, x, y = cloud(3000, seed)
    one, many = ex.WorkingSet(40, 0.02), ex.WorkingSet(40, 0.02)
    many.offer(ids, x, y)
    for i in range(len(ids)):
        one.offer(ids[i : i + 1], x[i : i + 1], y[i : i + 1])
    assert set(one.id) == set(many.id)
    assert np.allclose(many.b.sum() / 2, total(many))


def test_stable_sample_within_bound_of_optimum(spark):
    rows = list(zip(*cloud(13, 3)))
    p = frame(spark, rows)
    best = exact.exact(p, 4, EPS).first()["objective"]
    brute = min(sum(np.exp(-((a[1] - b[1]) ** 2 + (a[2] - b[2]) ** 2) / (2 * EPS * EPS)) for a, b in combinations(c, 2)) for c in combinations(rows, 4))
    assert abs(best - brute) < 1e-12
    from spreadsample.functions.runtime import durable

    stable, _ = ex.exchange_until_stable(p, 4, EPS, durable=durable)
    assert certify.improving_swaps(p, stable, EPS).first()[0] == 0
    assert certify.quality_bound(measures.objective(stable, EPS).first()[0] / 12, best / 12)


@pytest.mark.parametrize("rows,k,n", [([], 3, 0), ([("a", 0, 0)], 3, 1), ([(str(i), 1, 1) for i in range(9)], 4, 4), ([(str(i), i, 0) for i in range(9)], 9, 9), ([(str(i), i, 0) for i in range(9)], 1, 1)])
def test_awkward_inputs(spark, rows, k, n):
    p = frame(spark, rows)
    assert ex.exchange(p, k, EPS).count() == n
    assert ex.exchange_tiles(p, k, EPS, n_tiles=4).count() == n
    assert ex.exchange_random_parts(p, k, EPS, parts=4).count() == n
    assert ex.exchange_tree(p, k, EPS, n_tiles=4, durable=lambda d: d.cache()).count() == n
    assert baselines.uniform(p, k).count() == n and baselines.balanced_grid(p, k).count() == n


def test_equal_points_have_half_as_average(spark):
    p = frame(spark, [(str(i), 0.5, 0.5) for i in range(8)])
    assert measures.average_objective(ex.exchange(p, 5, EPS), EPS).first()[0] == pytest.approx(0.5)
    with pytest.raises(ValueError):
        ex.WorkingSet(0, EPS)


def test_cutoffs_and_pair_kernel():
    assert kernels.cutoff("gaussian", 1.0) == pytest.approx(4)
    assert kernels.values("gaussian", np.array(16.0), 1.0) == pytest.approx(1.1253517e-7)
    assert kernels.values("pair", np.array(16.0), 1.0) == pytest.approx(3.3546263e-4)


def test_three_on_a_line(spark):
    p = frame(spark, [("a", 0, 0), ("b", 1, 0), ("c", 10, 0)])
    assert {r["id"] for r in ex.exchange(p, 2, 1.0).collect()} == {"a", "c"}
    assert bandwidth.diameter(p) == pytest.approx(10)


def test_ratio_of_all_rows_is_zero_and_density_sums(spark):
    p = frame(spark, list(zip(*cloud(200, 5))))
    at = measures.domain_probes(p, 40)
    assert measures.log_ratio(p, p, at, 0.05).first()[0] == pytest.approx(0)
    s = baselines.uniform(p, 10)
    assert measures.log_ratio(p, s, at, 0.05).first()[0] >= 0
    for weights in (density.by_scan(s, p), density.by_index(s, p), density.by_index(s, p, "grid"), density.by_cells(s, p, durable=lambda d: d.cache())):
        assert sum(r["density"] for r in weights.collect()) == 200


def test_spread_beats_baselines_on_skewed_data(spark):
    rng = np.random.default_rng(1)
    x, y = np.concatenate((rng.normal(0.3, 0.02, 4000), rng.random(200))), np.concatenate((rng.normal(0.3, 0.02, 4000), rng.random(200)))
    p = frame(spark, [(i, a, b) for i, (a, b) in enumerate(zip(x, y))])
    at = measures.domain_probes(p, 100)
    ratio = lambda s: measures.log_ratio(p, s, at, 0.02).first()[0]
    spread, grid, uniform = ratio(ex.exchange(p, 80, 0.02)), ratio(baselines.balanced_grid(p, 80)), ratio(baselines.uniform(p, 80))
    assert spread < grid < uniform


def test_tiles_are_even_and_many_tiles_keep_the_plan_small(spark):
    p = frame(spark, [(i, (i * 37 % 1000) / 1000, (i * 91 % 997) / 997) for i in range(2000)])
    sizes = [r["count"] for r in ex.tiles(p, 16).groupBy("grp").count().collect()]
    assert sum(sizes) == 2000 and len(sizes) == 16 and max(sizes) <= 140
    many = ex.tiles(p, 400)
    assert many.count() == 2000 and len(many._jdf.queryExecution().optimizedPlan().toString()) < 20_000
    assert ex.tiles(p.limit(0), 16).count() == 0


def test_domain_probes_are_those_with_a_row_in_reach(spark):
    rng = np.random.default_rng(5)
    rows = [(i, *p) for i, p in enumerate(rng.random((60, 2)) * [0.3, 1.4])] + [(60, 0.9, 0.9), (61, 0.9, 0.9), (62, -0.05, 0.5)]
    p = frame(spark, rows).repartition(3)
    all_probes = [tuple(r) for r in measures.probes(spark, 50, 8).collect()]
    want = [q[0] for q in sorted(all_probes) if any((q[1] - x) ** 2 + (q[2] - y) ** 2 <= 0.01 for _, x, y in rows)][:50]
    assert [r["probe_id"] for r in measures.domain_probes(p, 50, 0.1, 8).orderBy("probe_id").collect()] == want
    assert measures.domain_probes(p.limit(0), 50).count() == 0


def test_nearest_counts_of_all_ways_agree(spark):
    p, s = frame(spark, [(i, i % 7, i % 5) for i in range(200)]), frame(spark, [("b", 1, 1), ("a", 3, 1), ("c", 50, 50)])
    ways = [density.by_scan(s, p), density.by_index(s, p), density.by_index(s, p, "grid"), density.by_cells(s, p)]
    found = [{r["id"]: r["density"] for r in w.collect()} for w in ways]
    assert all(f == found[0] for f in found) and sum(found[0].values()) == 200 and found[0]["c"] == 0
    assert density.by_scan(s.limit(0), p).count() == 0


def test_builds_beyond_a_block_offer_every_row(spark, monkeypatch):
    monkeypatch.setattr(catalog, "BLOCK_ROWS", 100)
    p = frame(spark, [(i, i % 10 / 1e4, i // 10 / 1e4) for i in range(400)])  # all within few micro cells
    ids = [r["id"] for r in catalog.spread_sample(p, 150, 0.01, 400, lambda d: d.cache()).collect()]
    assert len(ids) == len(set(ids)) == 150
    assert catalog.spread_sample(p, 500, 0.01, 400, lambda d: d.cache()).count() == 400


def test_pair_exchange_and_equivalence_read_the_whole_point_set(spark, monkeypatch):
    from spreadsample.functions.points import load
    from spreadsample.operators import queries

    sf, read = "/root/testdata/sf0.01", []
    n = load(spark, sf, "supp").count()
    for name in ("exchange_pairs", "exchange"):
        monkeypatch.setattr(ex, name, lambda p, *a, f=getattr(ex, name), **b: read.append(p.count()) or f(p, *a, **b))
    assert [tuple(r) for r in queries.R.queries["s_exchange_pairs"](spark, sf).collect()] == [(4, 4)]
    assert [tuple(r) for r in queries.R.queries["c_equivalence"](spark, sf).collect()] == [(6,)]
    assert n > 60 and read == [n * (n - 1) // 2, n, n, n]


@pytest.mark.parametrize("seed", range(5))
def test_local_variants_decide_alike_in_any_batches(seed):
    ids, x, y = cloud(3000, seed)
    sets = []
    for variant in ("local", "heap"):
        for step in (1, 7, 3000):
            work = ex.WorkingSet(60, 0.01, variant=variant)
            for lo in range(0, len(ids), step):
                work.offer(ids[lo : lo + step], x[lo : lo + step], y[lo : lo + step])
            assert np.allclose(work.b, work.exact_burdens())
            sets.append(frozenset(work.id))
    assert len(set(sets)) == 1


def test_heap_knows_the_largest_and_its_ties():
    b = np.array([1.0, 3.0, 3.0, 2.0])
    heap = ex.BurdenHeap(b)
    assert heap.top() == 3 and sorted(heap.tied(1e-12)) == [1, 2]
    b[1] = b[2] = 0.5
    heap.push(np.array([1, 2]))
    assert heap.top() == 2 and heap.tied(1e-12) == [3]


def test_a_stopped_scan_holds_k_rows_seen_so_far():
    ids, x, y = cloud(20_000, 1)
    work = ex.WorkingSet(50, 0.02)
    assert not work.offer(ids, x, y, until=0.0)
    assert work.n == 50 and work.rows == 50 and work.offer(ids[50:], x[50:], y[50:])


def test_the_clock_of_a_scan_starts_with_its_first_row():
    """Rows that come late, after a sort, are scanned all the same: the sample is not the k rows that began."""
    ids, x, y = cloud(4200, 5)

    def late():
        time.sleep(0.5)
        for low in range(0, len(ids), 1000):
            part = slice(low, low + 1000)
            yield pa.RecordBatch.from_arrays([pa.array(["all"] * len(ids[part])), pa.array(ids[part]), pa.array(x[part]), pa.array(y[part])], ["grp", "id", "x", "y"])

    got = next(ex._streamed(20, EPS, {"max_seconds": 0.3})(late()))
    assert set(got.column("id").to_pylist()) != set(ids[:20])


def test_greedy_start_takes_what_adds_least(spark):
    rows = list(zip(*cloud(60, 9)))
    got = [r["id"] for r in ex.greedy_start(frame(spark, rows), 8, EPS).collect()]
    place, left = {r[0]: r[1:] for r in rows}, [r["id"] for r in baselines.uniform(frame(spark, rows), 60).orderBy(baselines.hashed(7)).collect()]
    want = [left.pop(0)]
    while len(want) < 8:
        cost = [sum(np.exp(-((place[i][0] - place[j][0]) ** 2 + (place[i][1] - place[j][1]) ** 2) / (2 * EPS * EPS)) for j in want) for i in left]
        want.append(left.pop(int(np.argmin(cost))))
    assert got == want and ex.greedy_start(frame(spark, []), 3, EPS).count() == 0 and ex.greedy_start(frame(spark, rows), 99, EPS).count() == 60


def test_swaps_are_counted_like_by_hand(spark):
    rows = list(zip(*cloud(80, 4)))
    p, s = frame(spark, rows), frame(spark, rows[:12])
    k = lambda a, b: np.exp(-((a[1] - b[1]) ** 2 + (a[2] - b[2]) ** 2) / (2 * 0.05**2))
    burden = {m[0]: sum(k(m, o) for o in rows[:12] if o is not m) for m in rows[:12]}
    want = sum(sum(k(t, o) for o in rows[:12]) - k(t, m) < burden[m[0]] - 1e-12 for t in rows[12:] for m in rows[:12])
    assert certify.improving_swaps(p, s, 0.05).first()[0] == want and certify.improving_swaps(p, s.limit(0), 0.05).first()[0] == 0


def test_swaps_of_a_lonely_member_are_counted_exactly(spark):
    """Its burden, about 1.3e-12, is made of a pair above 1e-13 and of others below it."""
    at = lambda v: float(0.05 * np.sqrt(-2 * np.log(v)))
    members = [("m0", 0.0, 0.0), ("m1", at(9.9e-13), 0.0), ("m2", -at(9e-14), 0.0), ("m3", 0.0, at(9e-14)), ("m4", 0.0, -at(9e-14)), ("m5", 5.0, 5.0)]
    rows = members + [(f"r{i}", 9.0 + i, 9.0) for i in range(20)]
    near = lambda a, b: np.exp(-((a[1] - b[1]) ** 2 + (a[2] - b[2]) ** 2) / (2 * 0.05**2))
    want = sum(sum(near(t, m) for m in members if m is not s) < sum(near(s, m) for m in members if m is not s) - 1e-12 for t in rows[6:] for s in members)
    assert want == 20
    p = spark.createDataFrame(rows, "id string, x double, y double")
    assert certify.improving_swaps(p, p.where("id LIKE 'm%'"), 0.05).first()[0] == want


def test_hydrate_brings_whole_rows(spark):
    p = frame(spark, list(zip(*cloud(50, 2))))
    got = ex.hydrate(p, ex.exchange(p, 7, EPS), 7).collect()
    assert len(got) == 7 and sorted(r["sample_rank"] for r in got) == list(range(1, 8)) and {"value", "category", "burden"} <= set(got[0].asDict())


def test_average_ranks_over_ranges(spark):
    from spreadsample.functions.runtime import durable

    values = [5, 1, 1, 3, 5, 5, 2]
    got = {r["value"]: (r["n"], r["rank"]) for r in measures.average_ranks(spark.createDataFrame([(float(v),) for v in values], "v double"), "v", durable).collect()}
    assert got == {1: (2, 1.5), 2: (1, 3), 3: (1, 4), 5: (3, 6)}


def test_manual_advice_checks_columns(spark):
    from spreadsample.plans import budget

    p = frame(spark, [("a", 0, 0)])
    assert budget.advise_manually(p, [("x", "y")]).collect()[0].asDict() == {"xcol": "x", "ycol": "y"}
    with pytest.raises(ValueError):
        budget.advise_manually(p, [("x", "category")])


def test_printed_pairs_have_the_printed_rank_correlation(spark):
    r = measures.spearman(spark.createDataFrame(queries.PRINTED_PAIRS, "a double, b double"), "a", "b").first()
    assert r["n"] == 12 and abs(r["rho"] + 0.84615) < 1e-5


def read_rows(spark, sf, tmp_path, table, query):
    """The rows of a query over a copy of the tables in which one of them is empty."""
    import os

    for t in os.listdir(sf):
        if t != f"{table}.parquet":
            os.symlink(f"{sf}/{t}", tmp_path / t)
    spark.read.parquet(f"{sf}/{table}.parquet").limit(0).write.parquet(str(tmp_path / f"{table}.parquet"))
    import __spark_entry__ as entry

    return [tuple(r) for r in entry.queries()[query](spark, str(tmp_path)).collect()]


@pytest.mark.parametrize("query, table", [("k_cutoff", "events"), ("k_pair_quadrature", "lineitem"), ("m_spearman_printed", "orders"), ("op_cte_recursive", "orders")])
def test_queries_take_their_rows_from_a_table(spark, tmp_path, query, table):
    assert [r for r in read_rows(spark, "/root/testdata/sf0.001", tmp_path, table, query) if r[0] is not None] == []


@pytest.mark.parametrize("k", [1, 3, 5])
def test_pairs_like_a_scan_by_id(spark, monkeypatch, k):
    """Decisions of a row-by-row scan, from windows of the table; no task gets the whole table."""
    rng = random.Random(k)
    value = {(str(a), str(b)): rng.choice([0.0, rng.random(), -rng.random()]) for a in range(40) for b in range(a + 1, 40) if rng.random() < 0.8}
    of = lambda a, b: value.get((a, b), value.get((b, a), 0.0))
    members = []
    for t in sorted({i for pair in value for i in pair}):
        members.append(t)
        if len(members) > k:
            burden = [sum(of(a, b) for b in members if b != a) for a in members]
            tied = [a for a, v in zip(members, burden) if v >= max(burden) - 1e-12]
            members.remove(t if t in tied else max(tied))
    table = spark.createDataFrame([(a, b, v) for (a, b), v in value.items()], "i string, j string, k double")
    monkeypatch.setattr(type(table), "repartition", None)
    assert sorted(r["id"] for r in ex.exchange_pairs(table, k, window=7).collect()) == sorted(members)
    assert ex.exchange_pairs(table.limit(0), k).count() == 0


@pytest.mark.parametrize("seed", range(3))
def test_passed_over_batches_decide_like_exact_ones(seed, monkeypatch):
    """Single precision only tells rows that stay out: members, swaps and evaluations are those of double precision for every batch."""
    ids, x, y = cloud(12_000, seed)
    sets, passed = [], []
    monkeypatch.setattr(ex, "MATRIX", 512)
    look = ex.WorkingSet._first_better
    monkeypatch.setattr(ex.WorkingSet, "_first_better", lambda self, x, y: passed.append(r := look(self, x, y)) or r)
    for least in (32, 1 << 30):
        monkeypatch.setattr(ex, "CALM", least)
        sets.append(ex.WorkingSet(64, 0.03))
        sets[-1].offer(ids.astype(str).astype(object), x, y)
    a, b = sets
    assert (sorted(a.id), a.swaps, a.evals) == (sorted(b.id), b.swaps, b.evals) and None in passed


def test_greedy_touches_near_cells_with_equal_results(monkeypatch):
    """The rows of a pass over all rows for each pick, from far fewer kernel values."""
    values, seen = kernels.values, []
    monkeypatch.setattr(kernels, "values", lambda name, d2, eps: seen.append(np.size(d2)) or values(name, d2, eps))
    for n, k, eps, places in ((4000, 600, 0.01, None), (3000, 300, 0.02, 50), (500, 500, 0.3, 4), (40, 60, 0.01, 1)):
        rng = np.random.default_rng(n)
        x, y = (rng.random(n) if places is None else rng.integers(0, places, n) / places for _ in "xy")
        added, want = np.zeros(n), []
        for _ in range(min(k, n)):
            want.append(int(added.argmin()))
            added += values("pair", (x - x[want[-1]]) ** 2 + (y - y[want[-1]]) ** 2, eps)
            added[want[-1]] = np.inf
        seen.clear()
        assert ex.least_added(x, y, k, eps) == want
        assert n != 4000 or sum(seen) < 0.4 * n * k
