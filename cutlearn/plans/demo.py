"""Demonstrations: a classical layout replayed as cuts of the game."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame

from cutlearn.config import GridTooCoarse, InvalidLayout
from cutlearn.learning.env import DOWN, RIGHT, Board, Cut
from cutlearn.plans import baselines
from cutlearn.plans.grid import GridSpec, prefix
from cutlearn.plans.layout import Layout, Rect


@dataclass(frozen=True)
class Demo:
    layout: Layout
    actions: tuple[int, ...]
    source: str


def cut_order(layout: Layout) -> tuple[int, ...]:
    """Actions that rebuild a layout from the whole map, parents first. InvalidLayout if no sequence of edge-to-edge
    cuts makes it (a pinwheel)."""
    board, todo, actions = Board(layout.g), [(Rect(0, layout.g, 0, layout.g), list(layout.rects))], []
    while todo:
        box, parts = todo.pop(0)
        if len(parts) == 1:
            continue
        for direction, lo, hi in ((DOWN, "c0", "c1"), (RIGHT, "r0", "r1")):
            lines = sorted({getattr(r, lo) for r in parts} - {getattr(box, lo)})
            clear = [k for k in lines if all(getattr(r, hi) <= k or getattr(r, lo) >= k for r in parts)]
            if clear:
                k = clear[len(clear) // 2]
                cut = Cut(box.r0, k, DOWN) if direction == DOWN else Cut(k, box.c0, RIGHT)
                action = board.action_id(cut)
                board.step(action)
                actions.append(action)
                todo += [(box._replace(**{hi: k}), [r for r in parts if getattr(r, hi) <= k]), (box._replace(**{lo: k}), [r for r in parts if getattr(r, lo) >= k])]
                break
        else:
            raise InvalidLayout("not made by edge-to-edge cuts")
    return tuple(actions)


def with_regions(layout: Layout, hist: np.ndarray, m: int) -> Layout:
    """Splits the fullest regions near their median, or joins the lightest neighbours, until there are m."""
    rects, sums = list(layout.rects), prefix(hist)
    mass = lambda r: int(sums[r.r1, r.c1] - sums[r.r0, r.c1] - sums[r.r1, r.c0] + sums[r.r0, r.c0])
    while len(rects) < m:
        open_ = [r for r in rects if r.area > 1]
        if not open_:
            raise GridTooCoarse("no region is left to split")
        r = max(open_, key=lambda r: (mass(r), [-v for v in r]))
        x = [(abs(2 * mass(r._replace(c1=j)) - mass(r)), 0, j) for j in range(r.c0 + 1, r.c1)]
        y = [(abs(2 * mass(r._replace(r1=i)) - mass(r)), 1, i) for i in range(r.r0 + 1, r.r1)]
        _, axis, k = min(x + y)
        rects.remove(r)
        rects += [r._replace(r1=k), r._replace(r0=k)] if axis else [r._replace(c1=k), r._replace(c0=k)]
    while len(rects) > m:
        pairs = [(mass(a) + mass(b), i, j) for i, a in enumerate(rects) for j, b in enumerate(rects) if i < j and _mergeable(a, b)]
        _, i, j = min(pairs)
        a, b = rects[i], rects[j]
        rects = [r for k, r in enumerate(rects) if k not in (i, j)] + [Rect(min(a.r0, b.r0), max(a.r1, b.r1), min(a.c0, b.c0), max(a.c1, b.c1))]
    return Layout(tuple(sorted(rects)), layout.g)


def _mergeable(a: Rect, b: Rect) -> bool:
    same_rows, same_cols = (a.r0, a.r1) == (b.r0, b.r1), (a.c0, a.c1) == (b.c0, b.c1)
    return same_rows and (a.c1 == b.c0 or b.c1 == a.c0) or same_cols and (a.r1 == b.r0 or b.r1 == a.r0)


def make_demo(points: DataFrame, spec: GridSpec, hist: np.ndarray, m: int, source: str = "kdb", cost=None) -> Demo:
    """source: uniform, quad, kdb, or best (the cheapest of these by cost(layout))."""
    if m > spec.g**2:
        raise GridTooCoarse(f"{m} regions from {spec.g ** 2} cells")
    if source == "best":
        demos = [make_demo(points, spec, hist, m, s) for s in ("kdb", "quad", "uniform")]
        return min(demos, key=lambda d: cost(d.layout))
    if source == "uniform":
        layout = baselines.uniform(spec, m)
    elif source == "quad":
        layout = with_regions(baselines.quad(hist, m), hist, m)
    elif source == "kdb":
        layout = baselines.snapped_kdb(points, spec, m)
    else:
        raise ValueError(source)
    return Demo(layout, cut_order(layout), source)
