"""Baselines, demonstrations and joins on points; plans of the joins."""

import numpy as np
import pytest

from cutlearn import experiments as ex
from cutlearn.config import EmptyInput, GridTooCoarse
from cutlearn.operators import joins, measures, search
from cutlearn.plans import baselines, demo
from cutlearn.plans.cost import MeasuredCost, ModelledCost
from cutlearn.plans.grid import GridSpec, cell_histogram, dense, fit_grid
from cutlearn.plans.layout import Layout, Rect, assign
from cutlearn.sources.points import points

SF01 = "/root/testdata/sf0.01"

#: The snapped layouts of FIXTURES.md.
REFERENCE = {
    "geo_hot": [(0, 15, 0, 16), (0, 15, 16, 18), (15, 30, 0, 8), (15, 30, 8, 18), (0, 15, 18, 23), (0, 15, 23, 30), (15, 30, 18, 24), (15, 30, 24, 30)],
    "events_xy": [(0, 28, 0, 7), (0, 28, 7, 15), (28, 30, 0, 7), (28, 30, 7, 15), (0, 28, 15, 22), (0, 28, 22, 30), (28, 30, 15, 23), (28, 30, 23, 30)],
    "embed_xy": [(0, 14, 0, 12), (0, 14, 12, 15), (14, 30, 0, 11), (14, 30, 11, 15), (0, 14, 15, 19), (0, 14, 19, 30), (14, 30, 15, 19), (14, 30, 19, 30)],
}


def make(spark, rows):
    return spark.createDataFrame(rows, "pid long, x long, y long")


def brute(rows, d):
    return sorted((a, b, (x - u) ** 2 + (y - v) ** 2) for a, x, y in rows for b, u, v in rows if a < b and (x - u) ** 2 + (y - v) ** 2 <= d * d)


@pytest.mark.parametrize("name", sorted(REFERENCE))
def test_snapped_layouts(spark, name):
    p = points(spark, SF01, name)
    assert sorted(baselines.snapped_kdb(p, fit_grid(p), 8).rects) == sorted(Rect(*r) for r in REFERENCE[name])


def test_kdb_is_even_and_uniform_is_not(spark):
    p = points(spark, SF01, "geo_hot")
    spec = fit_grid(p)
    by = lambda df, m=8: measures.balance(measures.region_counts(df, m)).first().max_over_mean
    assert by(baselines.kdb_parts(p, spec, 8)) <= 1.05
    assert by(assign(p, spec, baselines.snapped_kdb(p, spec, 8))) <= 1.25
    assert by(assign(p, spec, baselines.uniform(spec, 8))) > 1.8


def test_quad_counts_and_errors():
    hist = np.zeros((8, 8), np.int64)
    hist[0, 0] = 10
    assert len(baselines.quad(hist, 8).rects) == 7 and len(baselines.quad(hist, 8, "at_least").rects) == 10
    assert len(baselines.quad(hist, 0, capacity=3).validate().rects) == 10
    with pytest.raises(GridTooCoarse):
        baselines.uniform(GridSpec(0, 0, 9, 9, 2), 8, 8, 1)
    with pytest.raises(GridTooCoarse):
        baselines.random_cuts(2, 5, 0)
    hist[7, 7] = 5
    for m in (5, 7, 9):
        assert len(demo.with_regions(baselines.quad(hist, 8), hist, m).validate().rects) == m


def test_grid_of_nothing(spark):
    with pytest.raises(EmptyInput):
        fit_grid(make(spark, []))


CASES = {
    "one": [(1, 5, 5)],
    "equal": [(k, 7, 7) for k in range(6)],
    "border": [(1, 0, 0), (2, 100, 0), (3, 49, 0), (4, 50, 0), (5, 0, 100), (6, 100, 100), (7, 51, 49)],
    "negative": [(k, -50 + 13 * k, 40 - 17 * k) for k in range(12)],
    "lines": [(k, (k % 5) * 25, (k // 5) * 25) for k in range(25)],
}


@pytest.mark.parametrize("case", sorted(CASES))
@pytest.mark.parametrize("d", [1, 50, 500])
def test_joins_equal_brute_force(spark, case, d):
    rows = CASES[case]
    p = make(spark, rows)
    spec = fit_grid(p, 4)
    layout = baselines.hist_kdb(dense(cell_histogram(p, spec), 4), 3)
    want = brute(rows, d)
    for df in (joins.distance_join(p, None, d, layout, spec, True), joins.distance_join(p, None, d, layout, spec, False), joins.half_join(p, d, spec), joins.refpoint_join(p, d, layout, spec), joins.distance_join(p, None, d, layout, spec, salt=3, strategy="merge")):
        assert sorted(map(tuple, df.collect())) == want


def test_zero_distance_and_single_region(spark):
    rows = CASES["equal"]
    p = make(spark, rows)
    spec = fit_grid(p, 4)
    assert sorted(map(tuple, joins.distance_join(p, None, 0, Layout.whole(4), spec).collect())) == brute(rows, 0)
    assert joins.distance_join(p, None, 0, Layout.whole(4), spec, pairs="with_self").count() == 36


def test_join_plan_has_no_nested_loop_and_two_exchanges(spark):
    p = points(spark, "/root/testdata/sf0.001", "geo_hot")
    spec, _, _, d = ex.setting(spark, "/root/testdata/sf0.001", "geo_hot")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        plan = joins.distance_join(p.select("pid", "x", "y"), None, 1000, d.layout, spec)._jdf.queryExecution().executedPlan().toString()
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
    assert "NestedLoop" not in plan and "Cartesian" not in plan and "ShuffledHashJoin" in plan
    assert plan.count("REPARTITION_BY_NUM") + plan.count("REPARTITION_BY_ID") + plan.count("ShufflePartitionIdPassThrough") >= 2


def test_knn_and_range(spark):
    rows = [(k, (k * 37) % 101, (k * 53) % 97) for k in range(60)]
    p = make(spark, rows)
    spec = fit_grid(p, 6)
    hist = dense(cell_histogram(p, spec), 6)
    for x, y in ((50, 50), (-30, 200)):
        want = sorted(((u - x) ** 2 + (v - y) ** 2, k) for k, u, v in rows)[:7]
        assert [(r.d2, r.pid) for r in search.knn_query(p, x, y, 7, spec, hist).collect()] == want
    got = {(r.pid_a, r["rank"]): (r.d2, r.pid_b) for r in search.knn_join(p, p, 4, spec, hist).collect()}
    for a, x, y in rows:
        for k, w in enumerate(sorted(((u - x) ** 2 + (v - y) ** 2, b) for b, u, v in rows)[:4], 1):
            assert got[a, k] == w
    with pytest.raises(ValueError):
        joins.brute_force(p, 5, max_rows=10)


def test_measured_cost_stops_and_leaves_no_job(spark):
    from cutlearn.config import DistanceJoin, Environment, TrainConfig, Workload

    p = points(spark, "/root/testdata/sf0.01", "geo_hot")
    spec, _, _, d = ex.setting(spark, "/root/testdata/sf0.01", "geo_hot")
    cost = MeasuredCost(p, spec, Environment(8, False), repeats=1)
    w = Workload((DistanceJoin(5000, 1.0),))
    first = cost.evaluate(d.layout, w)
    assert first.times[0] > 0 and not first.stopped
    hopeless = cost.evaluate(Layout.whole(30), w, (1e-4,), TrainConfig())
    assert hopeless.stopped and not spark.sparkContext.statusTracker().getActiveJobsIds()


def test_modelled_cost_orders_like_exact_counts(spark):
    spec, fine, _, d = ex.setting(spark, SF01, "geo_hot")
    p = points(spark, SF01, "geo_hot")
    model = ModelledCost(fine, spec)
    exact = {n: measures.exact_cost(p, spec, l, (5000,), True).first().cost_64 / 64 for n, l in (("demo", d.layout), ("uniform", baselines.uniform(spec, 8)))}
    assert (model.query(d.layout, 5000) < model.query(baselines.uniform(spec, 8), 5000)) == (exact["demo"] < exact["uniform"])


def test_learned_beats_the_rest_on_most_cases(spark):
    rows = measures.reductions(ex.runtime_table(spark, SF01, datasets=("geo_hot",)), "learned", "uniform").collect()
    assert len(rows) == 4 and sum(r.win for r in rows) >= 3 and all(r.vs_best_other >= -1e-6 for r in rows)


def test_salted_and_indexed_joins_spread_over_tasks(spark):
    """More tasks than regions hold pairs, and none has over twice its share of those of a hot region."""
    from pyspark.sql import functions as F

    from cutlearn import catalog

    before = spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.shuffle.partitions", "64")
    spark.conf.set("spark.sql.adaptive.coalescePartitions.enabled", "false")
    try:
        for name in ("djoin_salted", "djoin_bucket_dealt"):
            pairs = catalog.QUERIES[name](spark, "/root/testdata/sf0.01").withColumn("task", F.spark_partition_id())
            per = [r["count"] for r in pairs.groupBy("task").count().collect()]
            assert len(per) > 4 * catalog.M and max(per) < sum(per) / catalog.M, (name, per)
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", before)
        spark.conf.unset("spark.sql.adaptive.coalescePartitions.enabled")


def shuffled_rows(spark, df):
    """Rows that the stages of a run write for a shuffle."""
    store, sc = spark.sparkContext._jsc.sc().statusStore(), spark.sparkContext
    sc.setJobGroup("shuffled", "shuffled")
    before = set(sc.statusTracker().getJobIdsForGroup("shuffled"))
    df.write.format("noop").mode("overwrite").save()
    jobs = set(sc.statusTracker().getJobIdsForGroup("shuffled")) - before
    stages = {k for j in jobs for k in sc.statusTracker().getJobInfo(j).stageIds}
    sc._jsc.sc().listenerBus().waitUntilEmpty()
    rows = 0
    for k in stages:
        s = store.lastStageAttempt(k)
        rows += s.shuffleWriteRecords() if str(s.status()) == "COMPLETE" else 0
    return rows


@pytest.mark.parametrize("name, most", [("djoin_salted", 8), ("djoin_bucket_dealt", 5)])
def test_dealt_joins_shuffle_few_copies(spark, name, most):
    """A left row travels once to each task it has probes in, not once for each of its five probes."""
    from cutlearn import catalog

    before = spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.shuffle.partitions", "64")
    try:
        df = catalog.QUERIES[name](spark, SF01)
        assert 2 * 15_000 < shuffled_rows(spark, df) < most * 15_000
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", before)


@pytest.mark.parametrize("case", sorted(CASES))
def test_dealt_joins_in_every_mode(spark, case):
    rows = CASES[case]
    p = make(spark, rows)
    spec = fit_grid(p, 4)
    layout = baselines.hist_kdb(dense(cell_histogram(p, spec), 4), 3)
    far = {"l2": lambda u, v: u * u + v * v, "l1": lambda u, v: abs(u) + abs(v), "linf": lambda u, v: max(abs(u), abs(v))}
    keep = {"unordered": lambda i, j: i < j, "ordered": lambda i, j: i != j, "with_self": lambda i, j: True}
    for d, mode, metric, salt in ((50, "unordered", "l2", 3), (25, "ordered", "l1", 2), (25, "with_self", "linf", 1), (500, "unordered", "l1", 1)):
        limit = d * d if metric == "l2" else d
        want = sorted((i, j, far[metric](x - u, y - v)) for i, x, y in rows for j, u, v in rows if keep[mode](i, j) and far[metric](x - u, y - v) <= limit)
        got = joins.distance_join(p, None, d, layout, spec, pairs=mode, metric=metric, salt=salt, deal="bucket")
        assert sorted(map(tuple, got.collect())) == want
        both = joins.distance_join(p, p, d, layout, spec, metric=metric, salt=salt, deal="bucket")
        assert both.count() == sum(far[metric](x - u, y - v) <= limit for _, x, y in rows for _, u, v in rows)


def test_brute_force_takes_any_number_of_points(spark):
    rows = [(k, (k * 7919) % 200_003 - 100_000, (k * 104_729) % 211 - 100) for k in range(10_500)]
    x, y = np.array(rows).T[1:]
    want = [(i, j) for i in range(len(rows)) for j in i + 1 + np.flatnonzero((x[i + 1 :] - x[i]) ** 2 + (y[i + 1 :] - y[i]) ** 2 <= 400)]
    assert sorted((r.pid_a, r.pid_b) for r in joins.brute_force(make(spark, rows), 20).collect()) == want and len(want) > 100
    few = make(spark, CASES["lines"])
    for metric, pairs, n in (("l1", "ordered", 80), ("linf", "with_self", 169), ("l2", "unordered", 40)):
        assert joins.brute_force(few, 25, pairs, metric).count() == n


@pytest.mark.parametrize("case", sorted(CASES))
@pytest.mark.parametrize("d", [1, 50, 500])
def test_sweeps_equal_brute_force(spark, case, d):
    rows = CASES[case]
    p = make(spark, rows)
    spec = fit_grid(p, 4)
    layout = baselines.hist_kdb(dense(cell_histogram(p, spec), 4), 3)
    want = brute(rows, d)
    assert sorted(map(tuple, joins.sweep_join(p, d, layout, spec).collect())) == want
    bands = {r.band: r.n for r in joins.pair_bands(p, d, max(1, d // 5), layout, spec).collect()}
    assert bands == {k: n for k in range(7) if (n := sum(int(q**0.5) // max(1, d // 5) == k for *_, q in want))}
    for pairs, metric in (("ordered", "l2"), ("with_self", "l1"), ("unordered", "linf")):
        a, b = (joins.distance_join(p, None, d, layout, spec, index, pairs, metric) for index in (True, False))
        assert sorted(map(tuple, a.collect())) == sorted(map(tuple, b.collect()))
    a, b = (joins.distance_join(p, p.where("pid % 2 = 0"), d, layout, spec, index) for index in (True, False))
    assert sorted(map(tuple, a.collect())) == sorted(map(tuple, b.collect()))


def test_a_sweep_tests_few_pairs_at_once(monkeypatch):
    """Small batches and blocks find the same pairs, and no block is larger than twice the bound."""
    import pyarrow as pa

    rng, most = np.random.default_rng(3), []
    x, y = np.sort(rng.integers(0, 300, 400)), rng.integers(0, 40, 400)
    flags = pa.array(np.ones(400, bool))
    whole = pa.RecordBatch.from_arrays([pa.array(np.arange(400) // 200), pa.array(x), pa.array(y), pa.array(np.arange(400)), flags, flags, flags], ["k0", "x", "y", "pid", "l", "r", "home"])
    want = sorted((i, j) for i in range(400) for j in range(i + 1, 400) if i // 200 == j // 200 and (x[i] - x[j]) ** 2 + (y[i] - y[j]) ** 2 <= 400)
    real = np.nonzero
    monkeypatch.setattr(joins, "BLOCK", 64)
    monkeypatch.setattr(np, "nonzero", lambda v: most.append(v.size) or real(v))
    got = [(int(a), int(b)) for p, q, _ in joins._runs([whole.slice(k, 7) for k in range(0, 400, 7)], 1, 20, "l2", "unordered") for a, b in zip(p, q)]
    assert sorted(got) == want and max(most) <= 128


def test_a_swept_region_spreads_over_tasks(spark):
    from pyspark.sql import functions as F

    before = spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.shuffle.partitions", "32")
    spark.conf.set("spark.sql.adaptive.coalescePartitions.enabled", "false")
    try:
        spec, _, _, d = ex.setting(spark, SF01, "geo_hot")
        per = joins.sweep_join(points(spark, SF01, "geo_hot"), 5000, d.layout, spec).groupBy(F.spark_partition_id()).count().count()
        assert per > 2 * len(d.layout.rects)
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", before)
        spark.conf.unset("spark.sql.adaptive.coalescePartitions.enabled")


@pytest.mark.parametrize("case", sorted(CASES))
def test_pairs_of_two_layouts_come_once_and_are_not_shuffled(spark, case):
    rows = CASES[case]
    p = make(spark, rows)
    spec = fit_grid(p, 4)
    both = [baselines.hist_kdb(dense(cell_histogram(p, spec), 4), 3), baselines.uniform(spec, 4)]
    for d in (1, 50, 500):
        got = joins.union_of_layouts(p, d, both, spec)
        assert sorted(map(tuple, got.collect())) == brute(rows, d)
    from cutlearn import catalog

    plan = catalog.QUERIES["union_layout_pairs"](spark, SF01)._jdf.queryExecution().executedPlan().toString()
    assert "keys=[pid_a" not in plan and plan.count("Exchange hashpartitioning(kx") == 2


def test_a_fit_asks_for_short_code(spark, monkeypatch):
    """Each point's node and bin are one short expression, and the points are derived once for all levels."""
    frame, plans = type(spark.range(1)), []
    collect = frame.collect
    monkeypatch.setattr(frame, "collect", lambda df: plans.append(df._jdf.queryExecution().optimizedPlan().toString()) or collect(df))
    ex.forget_settings()
    ex.setting(spark, SF01, "geo_hot")
    steps = [t for t in plans if "Aggregate [" in t]
    assert len(steps) > 6 and all("InMemoryRelation" in t for t in steps)
    assert max(t.split("InMemoryRelation")[0].count("CASE") for t in steps) < 100
    assert not spark.sparkContext._jsc.getPersistentRDDs()


def test_measured_joins_count_the_pairs_of_every_layout(spark):
    from cutlearn.config import DistanceJoin, Environment, Workload

    rows = CASES["lines"]
    p = make(spark, rows)
    spec = fit_grid(p, 4)
    cost, w = MeasuredCost(p, spec, Environment(4), repeats=1), Workload((DistanceJoin(25, 1.0),))
    for layout in (Layout.whole(4), baselines.uniform(spec, 4)):
        cost.evaluate(layout, w)
    assert cost.found[25][0] == len(brute(rows, 25))
    cost.found[25] = (cost.found[25][0] - 1, cost.found[25][1])
    with pytest.raises(RuntimeError):
        cost.evaluate(baselines.uniform(spec, 2), w)


@pytest.mark.parametrize("options", [{}, {"deal": "bucket"}, {"salt": 2, "strategy": "merge"}])
def test_indexed_pairs_leave_tile_by_tile(spark, options):
    """All pairs of two tiles leave in a row (by salt of the left one), not scattered over the left rows, so a file packs them well."""
    rng = np.random.default_rng(5)
    rows = [(k, int(x), int(y)) for k, (x, y) in enumerate(rng.integers(0, 1_600, (1_500, 2)))]
    p = make(spark, rows)
    spec = fit_grid(p, 4)
    got = list(map(tuple, joins.distance_join(p, None, 400, Layout.whole(4), spec, **options).collect()))
    assert sorted(got) == brute(rows, 400) and len(got) > 100_000
    tile = [((x - spec.x0) // 100, (y - spec.y0) // 100) for _, x, y in rows]
    met = [frozenset((tile[i], tile[j])) for i, j, _ in got]
    assert 1 + sum(u != v for u, v in zip(met, met[1:])) <= 2 * options.get("salt", 1) * len(set(met))


def test_measured_joins_are_described_once_and_run_anew(spark, monkeypatch):
    """One description of a join for all its runs, each of which runs every stage; a layout's cells go to the JVM in one call."""
    from itertools import count
    from types import SimpleNamespace

    from pyspark.sql import functions as F

    from cutlearn.config import DistanceJoin, Environment, Workload
    from cutlearn.plans import cost as costs

    p = make(spark, CASES["lines"])
    spec, calls, lits, real, lit, runs = fit_grid(p, 4), [], [], joins.distance_join, F.lit, count()
    monkeypatch.setattr(joins, "distance_join", lambda *a, **k: calls.append(a[2]) or real(*a, **k))
    monkeypatch.setattr(costs.uuid, "uuid4", lambda: SimpleNamespace(hex=f"run-{next(runs)}"))
    cost = MeasuredCost(p, spec, Environment(4), repeats=3, warm=True)
    cost.evaluate(baselines.uniform(spec, 4), Workload((DistanceJoin(25, 0.5), DistanceJoin(10, 0.5))))
    assert sorted(calls) == [10, 25]
    tracker = spark.sparkContext.statusTracker()
    jobs = [len(tracker.getJobIdsForGroup(f"cutlearn-run-{k}")) for k in range(6)]
    assert min(jobs) > 1 and len(set(jobs)) == 1
    monkeypatch.setattr(F, "lit", lambda v: lits.append(v) or lit(v))
    Layout.whole(30).part(F.col("r"), F.col("c"))
    assert len(lits) < 10


@pytest.mark.parametrize("mode", ["unordered", "ordered", "with_self"])
def test_joins_by_place_find_a_pair_in_one_task_for_all_layouts(spark, mode):
    rng = np.random.default_rng(6)
    rows = [(k, int(x), int(y)) for k, (x, y) in enumerate(rng.integers(0, 3_000, (600, 2)))]
    p = make(spark, rows)
    spec = fit_grid(p, 6)
    layouts = [Layout.whole(6), baselines.uniform(spec, 4), baselines.uniform(spec, 6)]
    got = joins.distance_join(p, None, 90, layouts, spec, deal="place", tasks=12, pairs=mode).collect()
    want = brute(rows, 90)
    want += [(b, a, n) for a, b, n in want] * (mode != "unordered") + [(k, k, 0) for k, _, _ in rows] * (mode == "with_self")
    for nth in range(3):
        assert sorted((r.pid_a, r.pid_b, r.d2) for r in got if r.nth == nth) == sorted(want)
    assert len({r.unit for r in got}) > 6 and len({(r.pid_a, r.pid_b, r.unit) for r in got}) == len(want)
    with pytest.raises(ValueError):
        joins.distance_join(p, None, 90, layouts, spec)


def test_pairs_of_two_layouts_are_compared_where_they_are_found(spark):
    from cutlearn import catalog

    df = catalog.QUERIES["except_layouts"](spark, "/root/testdata/sf0.001")
    exchanges = [x for x in df._jdf.queryExecution().executedPlan().toString().split("\n") if "Exchange " in x and "Broadcast" not in x]
    assert sorted("REPARTITION_BY_NUM" in x for x in exchanges) == [False, True, True] and any("SinglePartition" in x for x in exchanges)
    assert df.first().n == 0
