"""One object for users: points, grid, demonstration, learned layout, and what can be done with it."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, SparkSession

from cutlearn.config import Environment, TrainConfig, Workload
from cutlearn.learning.learner import Learner, TrainResult
from cutlearn.operators import joins, physical, search
from cutlearn.plans.cost import ModelledCost
from cutlearn.plans.demo import Demo, make_demo
from cutlearn.plans.grid import GridSpec, cell_histogram, dense, fit_grid
from cutlearn.plans.layout import Layout, assign


@dataclass
class CutLayout:
    """A layout with the grid that it cuts."""

    spec: GridSpec
    layout: Layout
    result: TrainResult | None = None

    def assign(self, df: DataFrame) -> DataFrame:
        return assign(df, self.spec, self.layout)

    def place(self, df: DataFrame) -> DataFrame:
        return physical.place(df, self.spec, self.layout)

    def write(self, df: DataFrame, path: str) -> None:
        physical.write_regions(df, self.spec, self.layout, path)

    def distance_join(self, a: DataFrame, d: int, b: DataFrame | None = None, **options) -> DataFrame:
        return joins.distance_join(a, b, d, self.layout, self.spec, **options)

    def range_query(self, stored: DataFrame, x0: int, y0: int, x1: int, y1: int) -> DataFrame:
        return search.range_query(stored, x0, y0, x1, y1, self.spec, self.layout)

    def views(self, spark: SparkSession) -> None:
        self.layout.to_df(spark).createOrReplaceTempView("layout")

    def explain(self) -> str:
        return "\n".join(f"region {k}: rows {r.r0}-{r.r1}, columns {r.c0}-{r.c1}" for k, r in enumerate(self.layout.rects))


class CutSession:
    def __init__(self, points: DataFrame, g: int = 30, fine: int = 4):
        self.points = points
        self.spec = fit_grid(points, g)
        self.fine = dense(cell_histogram(points, self.spec.finer(fine)), g * fine)
        self.hist: np.ndarray = self.fine.reshape(g, fine, g, fine).sum(axis=(1, 3))

    def demo(self, source: str = "kdb", m: int = 8, workload: Workload | None = None) -> Demo:
        model = ModelledCost(self.fine, self.spec, Environment(m))
        cost = (lambda l: sum(q.freq * t for q, t in zip(workload.queries, model.evaluate(l, workload).times, strict=True))) if workload else None
        return make_demo(self.points, self.spec, self.hist, m, source, cost)

    def learn(self, workload: Workload, env: Environment | None = None, cfg: TrainConfig | None = None, cost=None, source: str = "kdb") -> CutLayout:
        env, cfg = env or Environment(), cfg or TrainConfig(g=self.spec.g)
        cost = cost or ModelledCost(self.fine, self.spec, env)
        result = Learner(self.hist, env.m, cfg).train(self.demo(source, env.m, workload), workload, cost)
        return CutLayout(self.spec, result.best, result)
