"""The evaluation's experiments on the given tables, and the searches around them."""

from __future__ import annotations

import statistics
from dataclasses import replace

import numpy as np
from pyspark.sql import DataFrame, SparkSession

from cutlearn.config import ARMS, SKEWS, THRESHOLDS, Environment, TrainConfig, Workload
from cutlearn.learning.learner import Learner, TrainResult
from cutlearn.plans import baselines
from cutlearn.plans.cost import MeasuredCost, ModelledCost, workload_time
from cutlearn.plans.demo import Demo, make_demo, with_regions
from cutlearn.plans.grid import GridSpec, cell_histogram, dense, fit_grid
from cutlearn.plans.layout import Layout
from cutlearn.sources.points import hash_sample, points

DATASETS = ("geo_hot", "events_xy", "embed_xy")
FINE = 4  # fine cells per cell and axis of the modelled cost

#: Training small enough for tests; TrainConfig() itself has the published sizes.
SMALL = TrainConfig(g=12, hidden=(128, 64), episodes=400, pretrain_iters=1500, target_every=50, mass_scale="unit")

#: Few episodes, each of which runs the workload's joins: for trials. The query trains by the published settings.
MEASURED = replace(SMALL, episodes=4, repeats=1)


_KEPT: dict[tuple, object] = {}  # what was learned, by the counts it was learned from
_SETTINGS: dict[tuple, object] = {}  # of the query at hand, by application, folder and settings


def forget_settings() -> None:
    """The next query reads its tables again."""
    _SETTINGS.clear()


def setting(spark: SparkSession, sf_dir: str, dataset: str, g: int = 30, m: int = 8) -> tuple[GridSpec, np.ndarray, np.ndarray, Demo]:
    """(grid, fine histogram, histogram, snapped KDB demonstration) of a dataset. A few bounded aggregates over points
    that are derived once: inside the conditions of a tree their expressions would be repeated beyond what Spark compiles."""
    key = (spark.sparkContext.applicationId, sf_dir, dataset, g, m)
    if key not in _SETTINGS:
        kept = points(spark, sf_dir, dataset).persist()
        p = kept.coalesce(4 * spark.sparkContext.defaultParallelism)  # a few groups from each of many small tasks cost more than the points
        try:
            spec = fit_grid(p, g)
            fine = dense(cell_histogram(p, spec.finer(FINE)), g * FINE)
            hist = fine.reshape(g, FINE, g, FINE).sum(axis=(1, 3))
            _SETTINGS[key] = spec, fine, hist, make_demo(p, spec, hist, m)
        finally:
            kept.unpersist()
    return _SETTINGS[key]


def trained(spark: SparkSession, sf_dir: str, dataset: str, skew: str = "small", local_index: bool = True, m: int = 8, cfg: TrainConfig = SMALL) -> TrainResult:
    """Learns against the modelled cost."""
    spec, fine, hist, demo = setting(spark, sf_dir, dataset, cfg.g, m)
    key = (fine.tobytes(), spec, tuple(demo.actions), demo.layout.key, dataset, skew, local_index, m, cfg)
    if key not in _KEPT:
        cost = ModelledCost(fine, spec, Environment(m, local_index))
        _KEPT[key] = Learner(hist, m, cfg).train(demo, Workload.of(dataset, skew), cost)
    return _KEPT[key]


def layouts(spark: SparkSession, sf_dir: str, dataset: str, skew: str, local_index: bool, cfg: TrainConfig = SMALL, m: int = 8) -> dict[str, Layout]:
    spec, _, hist, demo = setting(spark, sf_dir, dataset, cfg.g, m)
    return {
        "uniform": baselines.uniform(spec, m), "quad": baselines.quad(hist, m), "kdb_hist": with_regions(baselines.hist_kdb(hist, m), hist, m),
        "demo": demo.layout, "learned": trained(spark, sf_dir, dataset, skew, local_index, m, cfg).best,
    }


def runtime_table(spark: SparkSession, sf_dir: str, measured: bool = False, cfg: TrainConfig = SMALL, datasets: tuple[str, ...] = DATASETS, per_mille: int = 1000) -> DataFrame:
    """case, dataset, local_index, skew, method, seconds: the workload's weighted time of five methods on three
    datasets, two index settings and two skews. By default modelled units; measured runs every join."""
    rows = []
    for dataset in datasets:
        for index in (False, True):
            for skew in SKEWS:
                spec, fine, _, _ = setting(spark, sf_dir, dataset, cfg.g)
                if measured:
                    p = points(spark, sf_dir, dataset)
                    cost = MeasuredCost((hash_sample(p, per_mille) if per_mille < 1000 else p).persist(), spec, Environment(8, index), cfg.repeats)
                else:
                    cost = ModelledCost(fine, spec, Environment(8, index))
                w = Workload.of(dataset, skew)
                for method, layout in layouts(spark, sf_dir, dataset, skew, index, cfg).items():
                    rows.append((f"{dataset}/{'index' if index else 'none'}/{skew}", dataset, index, skew, method, float(workload_time(cost.evaluate(layout, w).times, w.freqs))))
                if measured:
                    cost.points.unpersist()
    return spark.createDataFrame(rows, "case string, dataset string, local_index boolean, skew string, method string, seconds double")


def layout_table(spark: SparkSession, sf_dir: str, cfg: TrainConfig = SMALL) -> DataFrame:
    """dataset, method, part_id, r0, r1, c0, c1, n: what the pictures of the layouts show."""
    rows = []
    for dataset in DATASETS:
        _, _, hist, _ = setting(spark, sf_dir, dataset, cfg.g)
        for method, layout in layouts(spark, sf_dir, dataset, "small", True, cfg).items():
            rows += [(dataset, method, k, *map(int, r), int(n)) for k, (r, n) in enumerate(zip(layout.rects, layout.counts(hist), strict=True))]
    return spark.createDataFrame(rows, "dataset string, method string, part_id int, r0 int, r1 int, c0 int, c1 int, n long")


def ablation(spark: SparkSession, sf_dir: str, dataset: str = "geo_hot", skew: str = "small", local_index: bool = True, cfg: TrainConfig = SMALL, arms: dict | None = None) -> tuple[DataFrame, DataFrame]:
    """(summary by arm, history by arm and episode). spent is the cost paid for workload runs: a stopped one pays
    until stop_factor times the best."""
    summary, history = [], []
    for arm, change in (arms or ARMS).items():
        r = trained(spark, sf_dir, dataset, skew, local_index, 8, replace(cfg, **change))
        demo = workload_time(r.demo_times, Workload.of(dataset, skew).freqs)
        spent = sum(min(e.cost, cfg.stop_factor * e.best_cost) if e.stopped else e.cost for e in r.history)
        best = workload_time(r.best_times, Workload.of(dataset, skew).freqs)
        first = next((e.episode for e in r.history if e.best_cost <= demo * 1.0001), -1)
        summary.append((arm, r.episodes, float(r.wall), float(spent), sum(e.stopped for e in r.history) / max(r.episodes, 1), float(best), float(demo), first, r.pretrain.iters if r.pretrain else 0))
        history += [(arm, e.episode, float(e.reward), float(e.cost), e.stopped) for e in r.history]
    return (
        spark.createDataFrame(summary, "arm string, episodes int, wall_s double, spent double, stop_rate double, best_cost double, demo_cost double, first_as_good int, pretrain_iters int"),
        spark.createDataFrame(history, "arm string, episode int, reward double, cost double, stopped boolean"),
    )


def sweep_m(spark: SparkSession, sf_dir: str, dataset: str = "geo_hot", ms: tuple[int, ...] = (2, 4, 8, 16), cfg: TrainConfig = SMALL) -> DataFrame:
    """m, demo_cost, learned_cost: choosing the number of regions."""
    rows = []
    for m in ms:
        r = trained(spark, sf_dir, dataset, "small", True, m, cfg)
        f = Workload.of(dataset, "small").freqs
        rows.append((m, float(workload_time(r.demo_times, f)), float(workload_time(r.best_times, f))))
    return spark.createDataFrame(rows, "m int, demo_cost double, learned_cost double")


def train_measured(spark: SparkSession, sf_dir: str, dataset: str = "geo_hot", skew: str = "small", local_index: bool = True, cfg: TrainConfig = TrainConfig(), m: int = 8) -> DataFrame:
    """arm, episodes, stopped, demo_s, best_s, demo_again_s, best_again_s, wall_s, layout: learning against seconds of
    real joins over all points, with the execution stop and without. The demonstration and the best layout are measured
    again in turn at the end, because the smallest of several noisy times is not an estimate."""
    w, rows = Workload.of(dataset, skew), []
    spec, _, hist, demo = setting(spark, sf_dir, dataset, cfg.g, m)
    kept = points(spark, sf_dir, dataset).persist()
    p = kept.coalesce(4 * spark.sparkContext.defaultParallelism)
    for arm, change in (("stop", {}), ("no_stop", {"exec_stop": False})):
        arm_cfg = replace(cfg, **change)
        cost = MeasuredCost(p, spec, Environment(m, local_index), cfg.repeats)
        r = Learner(hist, m, arm_cfg).train(demo, w, cost)
        again = {"demo": [], "best": []}
        for _ in range(cfg.repeats):
            for name, layout in (("demo", demo.layout), ("best", r.best)):
                cost.forget(layout)
                again[name].append(workload_time(cost.evaluate(layout, w).times, w.freqs))
        seconds = (workload_time(r.demo_times, w.freqs), workload_time(r.best_times, w.freqs), *(statistics.median(again[k]) for k in ("demo", "best")), r.wall)
        rows.append((arm, r.episodes, sum(e.stopped for e in r.history), *map(float, seconds), str([tuple(map(int, x)) for x in r.best.rects])))
    kept.unpersist()
    return spark.createDataFrame(rows, "arm string, episodes int, stopped int, demo_s double, best_s double, demo_again_s double, best_again_s double, wall_s double, layout string")


__all__ = ["THRESHOLDS", "ablation", "layout_table", "layouts", "runtime_table", "setting", "sweep_m", "train_measured", "trained"]
