"""Classical partitioners. Those that look at points do so by aggregates whose size the grid or M bounds."""

from __future__ import annotations

import math
from dataclasses import dataclass
from functools import partial

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cutlearn.config import GridTooCoarse
from cutlearn.learning.env import Board
from cutlearn.plans.grid import GridSpec, prefix
from cutlearn.plans.layout import Layout, Rect

BINS = 4096


def uniform(spec: GridSpec, m: int, rows: int | None = None, cols: int | None = None) -> Layout:
    """rows by cols equal parts of the grid; by default the factors of m nearest to the map's shape."""
    if rows is None or cols is None:
        shape = math.log(spec.width / spec.height)
        rows, cols = min(((r, m // r) for r in range(1, m + 1) if m % r == 0), key=lambda rc: (abs(math.log(rc[1] / rc[0]) - shape), rc))
    if rows > spec.g or cols > spec.g:
        raise GridTooCoarse(f"{rows} x {cols} parts of a {spec.g}-cell grid")
    lines = lambda k: [i * spec.g // k for i in range(k + 1)]
    y, x = lines(rows), lines(cols)
    return Layout(tuple(Rect(y[i], y[i + 1], x[j], x[j + 1]) for i in range(rows) for j in range(cols)), spec.g)


def quad(hist: np.ndarray, m: int, stop: str = "at_most", capacity: int | None = None) -> Layout:
    """Splits the fullest leaf at its midpoint into four, while the leaves stay within m ("at_most"), until they reach
    m ("at_least"), or until no leaf is over the capacity."""
    g, sums = len(hist), prefix(hist)
    count = lambda r: int(sums[r.r1, r.c1] - sums[r.r0, r.c1] - sums[r.r1, r.c0] + sums[r.r0, r.c0])
    leaves = [Rect(0, g, 0, g)]
    while True:
        if capacity is None and (len(leaves) + 3 > m if stop == "at_most" else len(leaves) >= m):
            break
        open_ = [r for r in leaves if r.r1 - r.r0 > 1 and r.c1 - r.c0 > 1 and (capacity is None or count(r) > capacity)]
        if not open_:
            break
        r = max(open_, key=lambda r: (count(r), [-v for v in r]))
        i, j = (r.r0 + r.r1) // 2, (r.c0 + r.c1) // 2
        leaves.remove(r)
        leaves += [Rect(r.r0, i, r.c0, j), Rect(r.r0, i, j, r.c1), Rect(i, r.r1, r.c0, j), Rect(i, r.r1, j, r.c1)]
    return Layout(tuple(sorted(leaves)), g)


def _ranked_values(points: DataFrame, leaf, axis: dict[int, str], ranks: dict[int, int], lo: dict[int, int], hi: dict[int, int]) -> dict[int, int]:
    """For each node the coordinate of the point of that rank (from 0). Histograms of BINS bins narrow the range down
    until a bin is one coordinate wide: a few aggregates, no sort, exact however many points there are. leaf(f): f(k) for
    the node k of a point. Node and bin leave as one number, so Spark's code for a point stays short and evaluates it once."""
    lo, hi, ranks, place = dict(lo), dict(hi), dict(ranks), {k: i for i, k in enumerate(lo)}
    while any(lo[k] < hi[k] for k in lo):
        width = {k: max(1, -(-(hi[k] - lo[k] + 1) // BINS)) for k in lo}

        def slot(k: int) -> F.Column:
            if k not in place:
                return F.lit(None).cast("long")
            v = F.col(axis[k])
            return F.when(v.between(lo[k], hi[k]), F.floor((v - lo[k]) / F.lit(width[k])).cast("long") + place[k] * BINS)

        bins = {k: [] for k in lo}
        for at, n in points.groupBy(leaf(slot).alias("slot")).agg(F.count("*").alias("n")).collect():
            if at is not None:
                bins[list(place)[at // BINS]].append((at % BINS, n))
        for k in lo:
            left = ranks[k]
            for b, n in sorted(bins[k]):
                if left < n:
                    lo[k], hi[k], ranks[k] = lo[k] + b * width[k], min(hi[k], lo[k] + (b + 1) * width[k] - 1), left
                    break
                left -= n
    return lo


@dataclass
class Node:
    """A node of a cut tree: regions below it, its rectangle of cells (snapped trees), and its cut. Smaller
    coordinates, or lower line numbers, go to the first child."""

    regions: int
    rect: Rect
    axis: str = ""
    value: int = 0  # coordinate of the cut
    line: int = 0  # grid line nearest to it
    children: tuple[int, int] = ()


def _side(spec: GridSpec, n: Node, snap: bool) -> F.Column:
    """Whether a point goes to the first child."""
    if snap:
        return spec.col(F.col("x")) < n.line if n.axis == "x" else spec.row(F.col("y")) < n.line
    return F.col(n.axis) < n.value


def node_column(spec: GridSpec, tree: list[Node], snap: bool, k: int = 0, leaf=F.lit) -> F.Column:
    """leaf(k) for the leaf k of each point, by default its number, as nested conditions."""
    n = tree[k]
    if not n.children:
        return leaf(k)
    a, b = (node_column(spec, tree, snap, c, leaf) for c in n.children)
    return F.when(_side(spec, n, snap), a).otherwise(b)


def kdb(points: DataFrame, spec: GridSpec, m: int, snap: bool = False, mode: str = "exact") -> list[Node]:
    """Axes alternate, x first; a node of r regions and n points is cut at the coordinate of the point of rank
    n * (r // 2) // r (from 0). mode: "exact", or "approx" by a quantile sketch. With snap the grid line nearest to
    the cut is taken instead, and deeper levels rank the points of the snapped regions. One aggregate counts a level
    and a few more find its cuts; no level sorts or gathers points."""
    tree, level = [Node(m, Rect(0, spec.g, 0, spec.g))], 0
    ends = {"x": (spec.x0, spec.x1), "y": (spec.y0, spec.y1)}
    while todo := [k for k, n in enumerate(tree) if n.regions > 1 and not n.children]:
        node = node_column(spec, tree, snap)
        axis = {k: _open_axis("xy"[level % 2], tree[k].rect) if snap else "xy"[level % 2] for k in todo}
        counts = dict(points.groupBy(node.alias("node")).agg(F.count("*").alias("n")).collect())
        full = [k for k in todo if counts.get(k)]
        share = {k: tree[k].regions // 2 for k in todo}
        if mode == "exact":
            ranks = {k: counts[k] * share[k] // tree[k].regions for k in full}
            value = _ranked_values(points, partial(node_column, spec, tree, snap, 0), {k: axis[k] for k in full}, ranks, {k: ends[axis[k]][0] for k in full}, {k: ends[axis[k]][1] for k in full})
        else:
            cols = [F.percentile_approx(F.when(node == k, F.col(axis[k])), share[k] / tree[k].regions, 10_000) for k in full]
            value = dict(zip(full, points.agg(*cols).first(), strict=True)) if cols else {}
        for k in todo:
            n = tree[k]
            n.axis, n.value = axis[k], value.get(k, sum(ends[axis[k]]) // 2)
            a = b = n.rect
            if snap:
                n.line = nearest_line(spec, n.axis, n.value, n.rect)
                a, b = (a._replace(c1=n.line), b._replace(c0=n.line)) if n.axis == "x" else (a._replace(r1=n.line), b._replace(r0=n.line))
            n.children = (len(tree), len(tree) + 1)
            first = share[k] if not snap or n.axis == "x" else n.regions - share[k]
            tree += [Node(first, a), Node(n.regions - first, b)]
        level += 1
    return tree


def leaves(tree: list[Node]) -> list[int]:
    return [k for k, n in enumerate(tree) if not n.children]


def kdb_parts(points: DataFrame, spec: GridSpec, m: int, mode: str = "exact") -> DataFrame:
    """points with part, the leaf of an unsnapped tree (numbered from 0 in tree order)."""
    tree = kdb(points, spec, m, False, mode)
    number = {k: i for i, k in enumerate(leaves(tree))}
    part = F.element_at(F.create_map(*[F.lit(v) for kv in number.items() for v in kv]), node_column(spec, tree, False))
    return points.withColumn("part", part)


def snapped_kdb(points: DataFrame, spec: GridSpec, m: int) -> Layout:
    tree = kdb(points, spec, m, True)
    return Layout(tuple(tree[k].rect for k in leaves(tree)), spec.g)


def hist_kdb(hist: np.ndarray, m: int) -> Layout:
    """A KDB-tree whose cuts are grid lines next to the median of the counts; one histogram, then driver only."""
    sums, g = prefix(hist), len(hist)
    mass = lambda r: int(sums[r.r1, r.c1] - sums[r.r0, r.c1] - sums[r.r1, r.c0] + sums[r.r0, r.c0])
    done, open_ = [], [(Rect(0, g, 0, g), m, 0)]
    while open_:
        r, k, level = open_.pop(0)
        if k == 1:
            done.append(r)
            continue
        axis = _open_axis("xy"[level % 2], r)
        want = mass(r) * (k // 2) / k
        if axis == "x":
            line = min(range(r.c0 + 1, r.c1), key=lambda j: (abs(mass(r._replace(c1=j)) - want), j))
            a, b = r._replace(c1=line), r._replace(c0=line)
        else:
            line = min(range(r.r0 + 1, r.r1), key=lambda i: (abs(mass(r._replace(r1=i)) - want), i))
            a, b = r._replace(r1=line), r._replace(r0=line)
        open_ += [(a, k // 2, level + 1), (b, k - k // 2, level + 1)]
    return Layout(tuple(done), g)


def str_tiles(points: DataFrame, m: int) -> DataFrame:
    """points with tile: slabs of equal counts along x, then tiles of equal counts along y in each slab. An optional
    packing whose number of tiles is only near m. Quantile sketches give the borders, so nothing is sorted as a whole."""
    slabs = max(1, math.isqrt(m))
    per = -(-m // slabs)
    cut = lambda df, c, k: [v for v in df.agg(F.percentile_approx(c, [i / k for i in range(1, k)], 10_000)).first()[0]] if k > 1 else []
    xs = cut(points, "x", slabs)
    slab = sum((F.when(F.col("x") > v, 1).otherwise(0) for v in xs), F.lit(0))
    rows = points.groupBy(slab.alias("slab")).agg(F.percentile_approx("y", [i / per for i in range(1, per)], 10_000).alias("ys")).collect() if per > 1 else []
    tile = slab * per
    for r in rows:
        tile = tile + F.when(slab == r["slab"], sum((F.when(F.col("y") > v, 1).otherwise(0) for v in r["ys"] or []), F.lit(0))).otherwise(0)
    return points.withColumn("tile", tile)


def random_cuts(g: int, m: int, seed: int) -> Layout:
    rng, board = np.random.default_rng(seed), Board(g)
    for _ in range(m - 1):
        valid = np.flatnonzero(board.mask())
        if not len(valid):
            raise GridTooCoarse(f"{m} regions from {g * g} cells")
        board.step(int(rng.choice(valid)))
    return board.layout


def hash_place(points: DataFrame, m: int) -> DataFrame:
    """points with part by a hash of the id: balanced, blind to place."""
    return points.withColumn("part", F.pmod(F.xxhash64("pid"), F.lit(m)).cast("int"))


def _open_axis(axis: str, r: Rect) -> str:
    if (r.c1 - r.c0 if axis == "x" else r.r1 - r.r0) > 1:
        return axis
    other = "y" if axis == "x" else "x"
    if (r.c1 - r.c0 if other == "x" else r.r1 - r.r0) > 1:
        return other
    raise GridTooCoarse("a region of one cell can't be cut")


def nearest_line(spec: GridSpec, axis: str, cut: float, r: Rect) -> int:
    """The interior grid line of r nearest to a coordinate, the lower one of two equally near."""
    lines = range(r.c0 + 1, r.c1) if axis == "x" else range(r.r0 + 1, r.r1)
    at = spec.x_line if axis == "x" else spec.y_line
    return min(lines, key=lambda k: (abs(at(k) - cut), k))
