"""What a layout costs: measured seconds of joins, or a model on counts that gives the same number every time."""

from __future__ import annotations

import contextlib
import statistics
import threading
import time
import uuid
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cutlearn.config import Environment, TrainConfig, Workload
from cutlearn.plans.grid import GridSpec, prefix
from cutlearn.plans.layout import Layout


@dataclass(frozen=True)
class CostResult:
    times: tuple[float, ...]
    stopped: bool = False


def reward(best: tuple[float, ...], now: tuple[float, ...], freqs: tuple[float, ...], kind: str = "mean_of_ratios") -> float:
    """Over 1 if the layout is better than the best so far."""
    if kind == "mean_of_ratios":
        return sum(f * b / max(c, 1e-9) for f, b, c in zip(freqs, best, now, strict=True)) ** 2
    if kind == "ratio_of_means":
        return (sum(f * b for f, b in zip(freqs, best, strict=True)) / max(sum(f * c for f, c in zip(freqs, now, strict=True)), 1e-9)) ** 2
    raise ValueError(kind)


def workload_time(times: tuple[float, ...], freqs: tuple[float, ...]) -> float:
    return sum(f * t for f, t in zip(freqs, times, strict=True))


@dataclass
class ModelledCost:
    """Straggler plus communication on a fine histogram: for each threshold the largest, over regions, of rows owned
    and received and candidate pairs, plus the rows sent across borders. Points are taken as even inside a fine cell.
    No Spark job runs for a layout, and equal layouts share one result."""

    fine: np.ndarray
    spec: GridSpec
    env: Environment = field(default_factory=Environment)
    c_row: float = 1.0
    c_pair: float = 1 / 64
    c_net: float = 4.0
    memo: dict = field(default_factory=dict)

    def __post_init__(self) -> None:
        self.times = len(self.fine) // self.spec.g
        self.sums = prefix(self.fine.astype(np.float64))
        self.total = float(self.fine.sum())

    def _mass(self, r0: float, r1: float, c0: float, c1: float) -> float:
        """Count in a box of fine-cell coordinates, linear between lines."""
        k = len(self.fine)

        def at(r: float, c: float) -> float:
            r, c = min(max(r, 0), k), min(max(c, 0), k)
            i, j = min(int(r), k - 1), min(int(c), k - 1)
            a, b, s = r - i, c - j, self.sums
            return (1 - a) * (1 - b) * s[i, j] + a * (1 - b) * s[i + 1, j] + (1 - a) * b * s[i, j + 1] + a * b * s[i + 1, j + 1]

        return at(r1, c1) - at(r0, c1) - at(r1, c0) + at(r0, c0)

    def region(self, r, d: int) -> tuple[float, float, float]:
        """(owned, received, candidate pairs) of a rectangle of cells."""
        t, k = self.times, len(self.fine)
        dr, dc = d * k / self.spec.height, d * k / self.spec.width
        own = self._mass(r.r0 * t, r.r1 * t, r.c0 * t, r.c1 * t)
        got = self._mass(r.r0 * t - dr, r.r1 * t + dr, r.c0 * t - dc, r.c1 * t + dc)
        if not self.env.local_index:
            return own, got, own * got
        cells = self.fine[r.r0 * t : r.r1 * t, r.c0 * t : r.c1 * t].astype(np.float64)
        return own, got, float((cells * cells).sum() * min(1.0, 9 * dr * dc) + cells.sum() * max(0.0, 9 * dr * dc - 1) * self.total / k**2)

    def query(self, layout: Layout, d: int) -> float:
        parts = [self.region(r, d) for r in layout.rects]
        straggler = max(self.c_row * (a + b) + self.c_pair * c for a, b, c in parts)
        return straggler + self.c_net * max(0.0, sum(b for _, b, _ in parts) - self.total)

    def evaluate(self, layout: Layout, workload: Workload, best: tuple[float, ...] | None = None, cfg: TrainConfig | None = None) -> CostResult:
        if layout.key not in self.memo:
            self.memo[layout.key] = tuple(self.query(layout, q.d) for q in workload.queries)
        times = self.memo[layout.key]
        stop = best is not None and cfg is not None and cfg.exec_stop and any(t > cfg.stop_factor * b for t, b in zip(times, best, strict=True))
        return CostResult(times, stop)

    def forget(self, layout: Layout) -> None:
        self.memo.pop(layout.key, None)


#: Settings under which layouts are compared: nothing may repair a bad layout behind its back.
PINNED = {
    "spark.sql.adaptive.skewJoin.enabled": "false",
    "spark.sql.adaptive.coalescePartitions.enabled": "false",
    "spark.sql.autoBroadcastJoinThreshold": "-1",
}


@contextlib.contextmanager
def pinned(spark: SparkSession, conf: dict[str, str]):
    before = {k: spark.conf.get(k, None) for k in conf}
    for k, v in conf.items():
        spark.conf.set(k, v)
    try:
        yield
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)


@dataclass
class MeasuredCost:
    """Median seconds of each join on placed points. A join is described once, and each run plans and runs it anew, so no
    finished stage is used again; a run over stop_factor times the best layout's time is cancelled and ends the workload. A run counts its pairs
    in the tasks that find them, so the join is measured and not the handing out of rows; a layout on which a join finds
    another number of pairs than on the first is an error."""

    points: DataFrame
    spec: GridSpec
    env: Environment = field(default_factory=Environment)
    repeats: int = 3
    warm: bool = False
    memo: dict = field(default_factory=dict)
    found: dict[int, tuple] = field(default_factory=dict)  # by threshold: pairs, and a sum over their distances

    def _once(self, df: DataFrame, limit: float | None, d: int) -> tuple[float, bool]:
        sc, group = df.sparkSession.sparkContext, f"cutlearn-{uuid.uuid4().hex}"
        result: dict = {}

        def work() -> None:
            sc.setJobGroup(group, "distance join", True)
            began = time.monotonic()
            try:
                result["found"] = tuple(df.agg(F.count("*"), F.sum(F.col("d2") % 1_000_003)).first())
            except Exception as e:  # a cancelled job; anything else is raised below
                result["error"] = e
            result["s"] = time.monotonic() - began

        from pyspark import InheritableThread

        thread = InheritableThread(target=work)
        thread.start()
        thread.join(limit)
        stopped = thread.is_alive()
        while thread.is_alive():
            sc.cancelJobGroup(group)
            thread.join(0.2)
        if not stopped and "error" in result:
            raise result["error"]
        if not stopped and self.found.setdefault(d, result["found"]) != result["found"]:
            raise RuntimeError(f"joins within {d} find {self.found[d]} and {result['found']} on two layouts")
        return result["s"], stopped

    def evaluate(self, layout: Layout, workload: Workload, best: tuple[float, ...] | None = None, cfg: TrainConfig | None = None) -> CostResult:
        from cutlearn.operators.joins import distance_join

        cfg = cfg or TrainConfig()
        if best is None and layout.key in self.memo:
            return self.memo[layout.key]
        spark = self.points.sparkSession
        times: list[float | None] = [None] * len(workload.queries)
        order = sorted(range(len(times)), key=lambda k: -workload.queries[k].freq)
        with pinned(spark, PINNED | {"spark.sql.shuffle.partitions": str(self.env.m)}):
            make = lambda d: distance_join(self.points, None, d, layout, self.spec, self.env.local_index, m=self.env.m)
            if not self.warm:
                self._once(make(workload.queries[0].d), None, workload.queries[0].d)
                self.warm = True
            for k in order:
                limit = cfg.stop_factor * best[k] if best is not None and cfg.exec_stop else None
                runs, join = [], make(workload.queries[k].d)
                for _ in range(self.repeats):
                    s, stopped = self._once(join, limit, workload.queries[k].d)
                    if stopped:
                        return CostResult(tuple(t if t is not None else float("inf") for t in times), True)
                    runs.append(s)
                times[k] = statistics.median(runs)
        out = CostResult(tuple(times))
        self.memo[layout.key] = out
        return out

    def forget(self, layout: Layout) -> None:
        """The next evaluation measures the layout again."""
        self.memo.pop(layout.key, None)


def calibrate(model: ModelledCost, measured: MeasuredCost, layouts: list[Layout], workload: Workload) -> tuple[float, float, float]:
    """Least-squares (c_row, c_pair, c_net) in seconds from measured layouts; negative ones become 0."""
    rows, seconds = [], []
    for layout in layouts:
        for q, s in zip(workload.queries, measured.evaluate(layout, workload).times, strict=True):
            parts = [model.region(r, q.d) for r in layout.rects]
            worst = max(parts, key=lambda p: model.c_row * (p[0] + p[1]) + model.c_pair * p[2])
            rows.append((worst[0] + worst[1], worst[2], sum(p[1] for p in parts) - model.total))
            seconds.append(s)
    fit = np.linalg.lstsq(np.array(rows), np.array(seconds), rcond=None)[0]
    return tuple(float(max(v, 0)) for v in fit)


def dp_optimum(model: ModelledCost, d: int, m: int, objective: str = "max") -> tuple[float, Layout]:
    """Cheapest guillotine layout for a cost that each rectangle has by itself: the largest of the regions' costs, or
    their sum. Exact, by dynamic programming over rectangles and region counts; for small grids."""
    g, memo = model.spec.g, {}

    def one(r) -> float:
        a, b, c = model.region(r, d)
        return model.c_row * (a + b) + model.c_pair * c

    def solve(r, k: int) -> tuple[float, tuple]:
        if k > r.area:
            return float("inf"), ()
        if (r, k) not in memo:
            best = (one(r), (r,)) if k == 1 else (float("inf"), ())
            if k > 1:
                cuts = [(r._replace(r1=i), r._replace(r0=i)) for i in range(r.r0 + 1, r.r1)] + [(r._replace(c1=j), r._replace(c0=j)) for j in range(r.c0 + 1, r.c1)]
                for a, b in cuts:
                    for n in range(1, k):
                        (x, p), (y, q) = solve(a, n), solve(b, k - n)
                        z = max(x, y) if objective == "max" else x + y
                        if z < best[0]:
                            best = (z, p + q)
            memo[r, k] = best
        return memo[r, k]

    from cutlearn.plans.layout import Rect

    value, rects = solve(Rect(0, g, 0, g), m)
    return value, Layout(rects, g)
