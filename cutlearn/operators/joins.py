"""Distance joins on a layout, and their variants.

The left row lives in the region that owns it; the right row is copied to each region that its box of half side d
touches. So every pair within d meets in exactly one region, the left row's. With the local index the join is an equi-join on the
region and on square buckets of side d with the distance as residual; without, the rows of a region are swept in the order of x. Each
region is a task of its own, as in the published set-up; `deal="bucket"` (with the index) deals by region and block of buckets instead, so
tasks are as many as the session's shuffle partitions, and `deal="place"` by block alone, so that two layouts' pairs meet where they are found. A left row probes nine buckets (five of an unordered self-join, where opposite
buckets give the same pairs); it travels once to each task that holds some of them. `salt` divides the left rows of every bucket and
copies the right ones before they are dealt, so a hot bucket spreads over tasks.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from cutlearn.plans.grid import GridSpec
from cutlearn.plans.layout import Layout, replica_parts


def separation(metric: str = "l2") -> Column:
    """The distance between (ax, ay) and (bx, by); squared for l2."""
    dx, dy = F.col("ax") - F.col("bx"), F.col("ay") - F.col("by")
    return {"l2": dx * dx + dy * dy, "l1": F.abs(dx) + F.abs(dy), "linf": F.greatest(F.abs(dx), F.abs(dy))}[metric]


def bound(d: int, metric: str = "l2") -> int:
    return d * d if metric == "l2" else d


def bucket(v: Column, origin: int, side: int) -> Column:
    """Whole-number bucket of a coordinate, counted from the map's corner; off the map it is negative or large."""
    return F.floor((v - origin) / F.lit(max(side, 1))).cast("long")


def _pair_filter(pairs: str, same: bool) -> Column | None:
    if not same or pairs == "with_self":
        return None
    return F.col("pid_a") < F.col("pid_b") if pairs == "unordered" else F.col("pid_a") != F.col("pid_b")


def _finish(joined: DataFrame, d: int, metric: str, pairs: str, same: bool, more: tuple[str, ...] = ()) -> DataFrame:
    out = joined.withColumn("d2", separation(metric)).where(F.col("d2") <= bound(d, metric))
    keep = _pair_filter(pairs, same)
    return (out if keep is None else out.where(keep)).select("pid_a", "pid_b", "d2", *more)


#: Of the nine buckets around a point its own, and one of each pair of opposite ones: an unordered pair meets in one of them.
_HALF = ((0, 0), (1, 0), (1, 1), (0, 1), (-1, 1))


def _finish_half(joined: DataFrame, d: int, metric: str = "l2", more: tuple[str, ...] = ()) -> DataFrame:
    """Pairs of a probe of _HALF (own: of the point's own bucket), the smaller id first; rows of one id are no pair."""
    found = joined.where((~F.col("own") & (F.col("pid_a") != F.col("pid_b"))) | (F.col("pid_a") < F.col("pid_b"))).withColumn("d2", separation(metric)).where(F.col("d2") <= bound(d, metric))
    return found.select(F.least("pid_a", "pid_b").alias("pid_a"), F.greatest("pid_a", "pid_b").alias("pid_b"), "d2", *more)


def _left(a: DataFrame) -> DataFrame:
    return a.select(F.col("pid").alias("pid_a"), F.col("x").alias("ax"), F.col("y").alias("ay"))


def _right(b: DataFrame) -> DataFrame:
    return b.select(F.col("pid").alias("pid_b"), F.col("x").alias("bx"), F.col("y").alias("by"))


def owners(a: DataFrame, spec: GridSpec, layout: Layout) -> DataFrame:
    return a.select("pid", "x", "y", layout.part(spec.row(F.col("y")), spec.col(F.col("x"))).alias("part"))


def replicas(b: DataFrame, spec: GridSpec, layout: Layout, d: int) -> DataFrame:
    """A row for each region that a point's box touches."""
    return b.select("pid", "x", "y", F.explode(replica_parts(spec, layout, d)).alias("part"))


def _tile_side(d: int) -> int:
    return max(d // 4, 1)


def _tiles(right: DataFrame, keys: list[str], d: int, spec: GridSpec, *more: str) -> DataFrame:
    """keys, tx, ty, rows: the right rows of a bucket packed by square tiles, four to a side of it."""
    side = {"tx": bucket(F.col("bx"), spec.x0, _tile_side(d)), "ty": bucket(F.col("by"), spec.y0, _tile_side(d))}
    return right.withColumns(side).groupBy(*keys, "tx", "ty").agg(F.sort_array(F.collect_list(F.struct("pid_b", "bx", "by", *more))).alias("rows"))


def _left_tiles(left: DataFrame, keys: list[str], d: int, spec: GridSpec) -> DataFrame:
    """keys, hx, hy, sx, sy, mine: the left rows packed by their bucket and tile."""
    side = {f"{h}{v}": bucket(F.col(f"a{v}"), {"x": spec.x0, "y": spec.y0}[v], w) for h, w in (("h", d), ("s", _tile_side(d))) for v in "xy"}
    return left.withColumns(side).groupBy(*keys, *side).agg(F.sort_array(F.collect_list(F.struct("ax", "ay", "pid_a"))).alias("mine"))


def _packed_join(left: DataFrame, tiles: DataFrame, keys: list[str], d: int, spec: GridSpec, strategy: str, metric: str, more: tuple[str, ...] = ()) -> DataFrame:
    """_tile_join for packed left rows: tile meets tile before any row is read, and the pairs of two tiles leave together. So the
    same few ids come again and again, which takes much less room in a columnar file than pairs in the order of the left rows."""
    s = _tile_side(d)
    gx, gy = (F.greatest(F.abs(F.col(t) - F.col(u)) - 1, F.lit(0)) * s for t, u in (("tx", "sx"), ("ty", "sy")))
    met = left.join(tiles.hint(strategy), keys).where(_gap(gx, gy, metric) <= bound(d, metric))
    return _near_rows(met.select("own", "tx", "ty", "rows", *more, F.inline("mine")), ["own", "ax", "ay", "pid_a", *more], d, spec, metric)


def _gap(gx: Column, gy: Column, metric: str) -> Column:
    return {"l2": gx * gx + gy * gy, "l1": gx + gy, "linf": F.greatest(gx, gy)}[metric]


def _near_rows(met: DataFrame, keep: list[str], d: int, spec: GridSpec, metric: str) -> DataFrame:
    """The rows of a tile beside a left row, unless the whole tile is too far off."""
    s = _tile_side(d)
    gap = lambda v, t, origin: F.greatest(F.col(t) * s + origin - F.col(v), F.col(v) - (F.col(t) + 1) * s - origin, F.lit(0))
    near = met.where(_gap(gap("ax", "tx", spec.x0), gap("ay", "ty", spec.y0), metric) <= bound(d, metric))
    return near.select(*keep, F.inline("rows"))


def _tile_join(left: DataFrame, tiles: DataFrame, keys: list[str], d: int, spec: GridSpec, strategy: str, metric: str = "l2") -> DataFrame:
    """Left rows beside the right rows of each tile within d. The rows of a tile are read one after the other from one array,
    many times faster than a chain of equal keys in a hash table, and tiles too far off are not read."""
    return _near_rows(left.join(tiles.hint(strategy), keys), [c for c in left.columns if c not in keys], d, spec, metric)


def distance_join(a: DataFrame, b: DataFrame | None, d: int, layout: Layout | list[Layout], spec: GridSpec, local_index: bool = True, pairs: str = "unordered", metric: str = "l2", m: int | None = None, salt: int = 1, strategy: str = "shuffle_hash", deal: str = "region", tasks: int | None = None) -> DataFrame:
    """pid_a, pid_b, d2 of all pairs within d (inclusive). b None: a self-join with pairs "unordered", "ordered" or
    "with_self". strategy: "shuffle_hash", or "merge" where a region doesn't fit a worker's memory. tasks: of a dealt join, instead of the session's shuffle
    partitions. deal "place": layout is a list, and each of them is joined on by itself; the rows also have nth, their layout's place
    in the list, and unit, the task that found them: the same one for every layout."""
    if (deal == "place") != isinstance(layout, list) or deal == "place" and not local_index:
        raise ValueError("joins are dealt by place with the index, on a list of layouts")
    if deal == "place":
        return _join_by_place(a, b, d, layout, spec, pairs, metric, salt, strategy, tasks)
    same, m = b is None, m or len(layout.rects)
    if not local_index and salt == 1:
        rows = _regions(a, b, d, layout, spec).repartitionById(m, F.col("k0")).sortWithinPartitions("k0", "x")
        return _swept(rows, 1, d, metric, pairs if same else "two_sided")
    left = owners(a, spec, layout)
    right = replicas(a if same else b, spec, layout, d)
    left = left.select(F.col("pid").alias("pid_a"), F.col("x").alias("ax"), F.col("y").alias("ay"), "part")
    right = right.select(F.col("pid").alias("pid_b"), F.col("x").alias("bx"), F.col("y").alias("by"), "part")
    half = same and pairs == "unordered" and local_index
    if local_index and (salt > 1 or deal != "region"):
        joined = _dealt_join(left, right, d, spec, half, salt, strategy, metric, tasks=tasks)
        return _finish_half(joined, d, metric) if half else _finish(joined, d, metric, pairs, same)
    keys = ["part"]
    if salt == 1 and deal == "region":
        left, right = left.repartitionById(m, F.col("part")), right.repartitionById(m, F.col("part"))
    if local_index:
        right = right.withColumns({"kx": bucket(F.col("bx"), spec.x0, d), "ky": bucket(F.col("by"), spec.y0, d)})
        left = _left_tiles(left, keys, d, spec).withColumn("s", F.explode(_steps(half))).select("part", "sx", "sy", "mine", "s.*")
        keys += ["kx", "ky"]
    if salt > 1:
        left = left.withColumn("salt", F.pmod(F.xxhash64("pid_a"), F.lit(salt)).cast("int"))
        right = right.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(salt - 1))))
        keys.append("salt")
    joined = _packed_join(left, _tiles(right, keys, d, spec), keys, d, spec, strategy, metric) if local_index else left.join(right.hint(strategy), keys)
    if half:
        return _finish_half(joined, d, metric)
    return _finish(joined, d, metric, pairs, same)


#: Buckets to a side of a block; the blocks are what dealt joins deal over tasks. Of eight to a side, one held most of a hot spot.
_BLOCK_SIDE = 2


def _probes(half: bool, kx: Column, ky: Column) -> list[tuple[Column, Column, bool]]:
    """kx, ky, own of each bucket that the left rows of a bucket probe."""
    steps = _HALF if half else [(i, j) for i in (-1, 0, 1) for j in (-1, 0, 1)]
    return [(kx + i, ky + j, (i, j) == (0, 0)) for i, j in steps]


def _steps(half: bool) -> Column:
    """The probes of packed left rows as an array of structs."""
    return F.array(*[F.struct(kx.alias("kx"), ky.alias("ky"), F.lit(own).alias("own")) for kx, ky, own in _probes(half, F.col("hx"), F.col("hy"))])


def _dealt_join(left: DataFrame, right: DataFrame, d: int, spec: GridSpec, half: bool, salt: int, strategy: str, metric: str, by_region: bool = True, tasks: int | None = None, more: tuple[str, ...] = ()) -> DataFrame:
    """Left rows beside right rows that may be near, dealt over the shuffle partitions by region, block of buckets and salt. A
    left row travels once to each unit that its probes touch, not once a probe, and is spread to its probes there; a right row
    travels once to each unit that one of its block's salts is dealt to. Not by_region: by block and salt alone, so that joins on
    several layouts find a pair in the same unit (which of its rows is the left one, and both buckets, don't depend on a layout)."""
    n = tasks or int(left.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    block = lambda k: F.floor(k / F.lit(_BLOCK_SIDE))
    region = [F.col("part")] if by_region else []
    unit = lambda kx, ky, s: F.pmod(F.xxhash64(*region, block(kx), block(ky), s), F.lit(n)).cast("int")
    salted = F.pmod(F.xxhash64("pid_a"), F.lit(salt)).cast("int")
    here = bucket(F.col("ax"), spec.x0, d), bucket(F.col("ay"), spec.y0, d)
    left = left.withColumn("unit", F.explode(F.array_distinct(F.array(*[unit(kx, ky, salted) for kx, ky, _ in _probes(half, *here)])))).repartitionById(n, F.col("unit"))
    left = _left_tiles(left.withColumn("salt", salted), ["unit", "part", "salt"], d, spec).withColumn("s", F.explode(_steps(half)))
    left = left.where(unit(F.col("s.kx"), F.col("s.ky"), F.col("salt")) == F.col("unit")).select("unit", "part", "sx", "sy", "mine", "s.*")
    side = {"kx": bucket(F.col("bx"), spec.x0, d), "ky": bucket(F.col("by"), spec.y0, d)}
    right = right.withColumn("unit", F.explode(F.array_distinct(F.array(*[unit(side["kx"], side["ky"], F.lit(k)) for k in range(salt)])))).repartitionById(n, F.col("unit")).withColumns(side)
    keys = ["unit", "part", "kx", "ky"]
    return _packed_join(left, _tiles(right, keys, d, spec), keys, d, spec, strategy, metric, more)


def _plus(n: int):
    return lambda v: v + n


def _join_by_place(a: DataFrame, b: DataFrame | None, d: int, layouts: list[Layout], spec: GridSpec, pairs: str, metric: str, salt: int, strategy: str, tasks: int | None) -> DataFrame:
    """The joins on several layouts side by side: their regions are counted on from layout to layout, and rows meet within a region."""
    same, half, most = b is None, b is None and pairs == "unordered", max(len(l.rects) for l in layouts)
    here = [l.part(spec.row(F.col("y")), spec.col(F.col("x"))) + k * most for k, l in enumerate(layouts)]
    touched = [F.transform(replica_parts(spec, l, d), _plus(k * most)) for k, l in enumerate(layouts)]
    left = a.select(F.col("pid").alias("pid_a"), F.col("x").alias("ax"), F.col("y").alias("ay"), F.explode(F.array(*here)).alias("part"))
    right = (a if same else b).select(F.col("pid").alias("pid_b"), F.col("x").alias("bx"), F.col("y").alias("by"), F.explode(F.concat(*touched)).alias("part"))
    more = ("unit", "part")
    joined = _dealt_join(left, right, d, spec, half, salt, strategy, metric, False, tasks, more)
    found = _finish_half(joined, d, metric, more) if half else _finish(joined, d, metric, pairs, same, more)
    return found.withColumn("nth", F.floor(F.col("part") / most).cast("int")).drop("part")


def union_of_layouts(a: DataFrame, d: int, layouts: list[Layout], spec: GridSpec) -> DataFrame:
    """pid_a, pid_b, d2 of the unordered pairs that a self-join on one layout or another finds, each once. The joins share
    their probes, and a pair is held against every layout where it is found: in the region that owns its left row, if the
    right row has a copy there. So no pair is shuffled to meet its like from another layout."""
    own = [f"own{k}" for k in range(len(layouts))]
    copies = [f"copies{k}" for k in range(len(layouts))]
    side = {"kx": bucket(F.col("x"), spec.x0, d), "ky": bucket(F.col("y"), spec.y0, d)}
    part = [l.part(spec.row(F.col("y")), spec.col(F.col("x"))).alias(n) for l, n in zip(layouts, own)]
    steps = F.array(*[F.struct(F.lit(i).alias("i"), F.lit(j).alias("j")) for i, j in _HALF])
    left = a.select(F.col("pid").alias("pid_a"), F.col("x").alias("ax"), F.col("y").alias("ay"), *part, *[v.alias(k) for k, v in side.items()], F.explode(steps).alias("s"))
    left = left.withColumns({"kx": F.col("kx") + F.col("s.i"), "ky": F.col("ky") + F.col("s.j"), "own": (F.col("s.i") == 0) & (F.col("s.j") == 0)}).drop("s")
    right = a.select(F.col("pid").alias("pid_b"), F.col("x").alias("bx"), F.col("y").alias("by"), *[replica_parts(spec, l, d).alias(n) for l, n in zip(layouts, copies)], *[v.alias(k) for k, v in side.items()])
    tiles = _tiles(right.repartition("kx", "ky"), ["kx", "ky"], d, spec, *copies)
    joined = _tile_join(left, tiles, ["kx", "ky"], d, spec, "shuffle_hash").where(separation() <= bound(d))
    found = F.lit(False)
    for o, c in zip(own, copies):
        found = found | F.array_contains(c, F.col(o))
    return _finish_half(joined.where(found), d)


def half_join(a: DataFrame, d: int, spec: GridSpec) -> DataFrame:
    """Unordered self-join that probes five of the nine buckets: its own, and one of each pair of opposite ones. No
    layout: the bucket is the shuffle key, thousands of them to a task."""
    side = {"kx": bucket(F.col("x"), spec.x0, d), "ky": bucket(F.col("y"), spec.y0, d)}
    steps = F.array(*[F.struct(F.lit(i).alias("i"), F.lit(j).alias("j")) for i, j in _HALF])
    left = a.withColumns(side).withColumn("s", F.explode(steps)).select(F.col("pid").alias("pid_a"), F.col("x").alias("ax"), F.col("y").alias("ay"), (F.col("kx") + F.col("s.i")).alias("kx"), (F.col("ky") + F.col("s.j")).alias("ky"), ((F.col("s.i") == 0) & (F.col("s.j") == 0)).alias("own"))
    right = a.withColumns(side).select(F.col("pid").alias("pid_b"), F.col("x").alias("bx"), F.col("y").alias("by"), "kx", "ky")
    return _finish_half(left.join(right, ["kx", "ky"]), d)


def refpoint_join(a: DataFrame, d: int, layout: Layout, spec: GridSpec) -> DataFrame:
    """Both sides are copied to the regions they touch; a pair counts only in the owner of its left point."""
    left = replicas(a, spec, layout, d).withColumn("own", layout.part(spec.row(F.col("y")), spec.col(F.col("x"))))
    left = left.select(F.col("pid").alias("pid_a"), F.col("x").alias("ax"), F.col("y").alias("ay"), "part", "own")
    right = replicas(a, spec, layout, d).select(F.col("pid").alias("pid_b"), F.col("x").alias("bx"), F.col("y").alias("by"), "part")
    near = F.sequence(F.lit(-1), F.lit(1))
    left = left.where("own = part").withColumn("ox", F.explode(near)).withColumn("oy", F.explode(near)).withColumns({"kx": bucket(F.col("ax"), spec.x0, d) + F.col("ox"), "ky": bucket(F.col("ay"), spec.y0, d) + F.col("oy")})
    right = right.withColumns({"kx": bucket(F.col("bx"), spec.x0, d), "ky": bucket(F.col("by"), spec.y0, d)})
    return _finish(left.join(right, ["part", "kx", "ky"]), d, "l2", "unordered", True)


def broadcast_join(a: DataFrame, b: DataFrame, d: int, spec: GridSpec, max_rows: int = 100_000) -> DataFrame:
    """Small side broadcast by buckets, so the large side isn't shuffled. A side over max_rows isn't broadcast."""
    near = F.sequence(F.lit(-1), F.lit(1))
    small = _right(b).withColumn("ox", F.explode(near)).withColumn("oy", F.explode(near)).withColumns({"kx": bucket(F.col("bx"), spec.x0, d) + F.col("ox"), "ky": bucket(F.col("by"), spec.y0, d) + F.col("oy")})
    large = _left(a).withColumns({"kx": bucket(F.col("ax"), spec.x0, d), "ky": bucket(F.col("ay"), spec.y0, d)})
    fits = b.limit(max_rows + 1).count() <= max_rows
    return _finish(large.join(F.broadcast(small) if fits else small, ["kx", "ky"]), d, "l2", "ordered", False)


def brute_force(a: DataFrame, d: int, pairs: str = "unordered", metric: str = "l2", max_rows: int | None = None) -> DataFrame:
    """The truth for other joins, without layout or buckets: strips of x, d wide, and every pair of rows of a strip and the
    next ones is tested. No other pair can be near, as its x alone lie further apart. With max_rows a larger input is refused."""
    if max_rows is not None and a.limit(max_rows + 1).count() > max_rows:
        raise ValueError(f"brute force takes at most {max_rows} points")
    left = _left(a).withColumn("o", F.explode(F.sequence(F.lit(-1), F.lit(1)))).withColumn("strip", bucket(F.col("ax"), 0, d) + F.col("o")).drop("o")
    return _finish(left.join(_right(a).withColumn("strip", bucket(F.col("bx"), 0, d)), "strip"), d, metric, pairs, True)


def hash_placed_join(a: DataFrame, d: int, m: int, spec: GridSpec) -> DataFrame:
    """What hash placement costs a distance join: every right row goes to every part."""
    part = F.pmod(F.xxhash64("pid_a"), F.lit(m)).cast("int")
    left = _left(a).withColumn("part", part)
    right = _right(a).withColumn("part", F.explode(F.sequence(F.lit(0), F.lit(m - 1))))
    near = F.sequence(F.lit(-1), F.lit(1))
    left = left.withColumn("ox", F.explode(near)).withColumn("oy", F.explode(near)).withColumns({"kx": bucket(F.col("ax"), spec.x0, d) + F.col("ox"), "ky": bucket(F.col("ay"), spec.y0, d) + F.col("oy")})
    right = right.withColumns({"kx": bucket(F.col("bx"), spec.x0, d), "ky": bucket(F.col("by"), spec.y0, d)})
    return _finish(left.join(right, ["part", "kx", "ky"]), d, "l2", "unordered", True)


BLOCK = 1 << 19  # distances that a sweep tests at once


def _runs(batches, keys: int, far: int, metric: str, pairs: str):
    """(ids a, ids b, distances) of near pairs, from Arrow batches sorted by keys and x: k0.., x, y, pid, l, r, home. A row is
    tested against those of the same keys at most `far` before it in x; it keeps only these between batches, and tests
    BLOCK pairs at once. l, r: it may stand left, right; a pair needs a home row."""
    import numpy as np

    names = [f"k{i}" for i in range(keys)] + ["x", "y", "pid", "l", "r", "home"]
    kept, limit = None, far * far if metric == "l2" else far

    def found(a, i, j, dist):
        """Pairs of positions i (left) and j in both orders; by ids, flags and mode."""
        p, l, r, ids = a["pid"], a["l"], a["r"], None
        for u, v in ((i, j), (j, i)):
            ok = l[u] & r[v]
            if pairs == "unordered":
                ok &= p[u] < p[v]
            elif pairs == "ordered":
                ok &= p[u] != p[v]
            if ok.any():
                ids = p[u[ok]], p[v[ok]], dist[ok]
                yield ids

    for batch in batches:
        fresh = {n: batch.column(k).to_numpy(zero_copy_only=False) for k, n in enumerate(names)}
        a = fresh if kept is None else {n: np.concatenate([kept[n], fresh[n]]) for n in names}
        n, old = len(a["x"]), 0 if kept is None else len(kept["x"])
        if n == old:
            continue
        x, y, home = a["x"], a["y"], a["home"]
        new = np.zeros(n, bool)
        new[0] = True
        for k in range(keys):
            new[1:] |= a[f"k{k}"][1:] != a[f"k{k}"][:-1]
        starts = np.flatnonzero(new)
        for g, stop in zip(starts, [*starts[1:], n]):
            lo = max(g, old)
            s = lo
            while s < stop:
                w0 = g + int(np.searchsorted(x[g:stop], x[s] - far, "left"))
                e = s + max(1, min(stop - s, BLOCK // (s - w0 + 1)))
                while e - s > 1 and (e - s) * (e - w0) > 2 * BLOCK:
                    e = s + (e - s) // 2
                for c in range(w0, e, BLOCK):  # one row of the block may have more than BLOCK before it
                    ce = min(e, c + BLOCK)
                    dx, dy = x[s:e, None] - x[None, c:ce], y[s:e, None] - y[None, c:ce]
                    dist = dx * dx + dy * dy if metric == "l2" else np.abs(dx) + np.abs(dy) if metric == "l1" else np.maximum(np.abs(dx), np.abs(dy))
                    i, j = np.nonzero(dist <= limit)
                    dist = dist[i, j]
                    i, j = i + s, j + c
                    ok = (j < i) & (home[i] | home[j])
                    yield from found(a, i[ok], j[ok], dist[ok])
                s = e
            if pairs == "with_self":
                i = np.arange(lo, stop)
                i = i[a["l"][lo:stop] & a["r"][lo:stop] & home[lo:stop]]
                if len(i):
                    yield a["pid"][i], a["pid"][i], np.zeros(len(i), np.int64)
        g = int(starts[-1])
        g = max(g, g + int(np.searchsorted(x[g:], x[-1] - far, "left")))
        kept = {k: v[g:] for k, v in a.items()}


def _swept(rows: DataFrame, keys: int, d: int, metric: str, pairs: str) -> DataFrame:
    """pid_a, pid_b, d2 from rows sorted for _runs."""
    kind = rows.schema["pid"].dataType.simpleString()

    def emit(batches):
        import pyarrow as pa

        for a, b, dist in _runs(batches, keys, d, metric, pairs):
            for k in range(0, len(a), 1 << 16):
                yield pa.RecordBatch.from_arrays([pa.array(v[k : k + (1 << 16)]) for v in (a, b, dist)], ["pid_a", "pid_b", "d2"])

    return rows.mapInArrow(emit, f"pid_a {kind}, pid_b {kind}, d2 long")


def _strips(a: DataFrame, d: int, layout: Layout, spec: GridSpec) -> DataFrame:
    """Rows of a self-join for a sweep: each in the regions its box touches, there in its strip of y, d high, and as a guest in
    the next strip; the regions' strips are dealt over the shuffle partitions. Only the owner's copy stands left."""
    here = owners(a, spec, layout).select("pid", "x", "y", F.col("part").alias("own"), F.explode(replica_parts(spec, layout, d)).alias("part"))
    rows = here.withColumn("up", F.explode(F.sequence(F.lit(0), F.lit(1))))
    rows = rows.select(F.col("part").alias("k0"), (bucket(F.col("y"), spec.y0, d) + F.col("up")).alias("k1"), F.col("x").cast("long").alias("x"), F.col("y").cast("long").alias("y"), "pid", (F.col("own") == F.col("part")).alias("l"), F.lit(True).alias("r"), (F.col("up") == 0).alias("home"))
    return rows.repartition("k0", "k1").sortWithinPartitions("k0", "k1", "x")


def _regions(a: DataFrame, b: DataFrame | None, d: int, layout: Layout, spec: GridSpec) -> DataFrame:
    """Rows for a sweep of whole regions. Of a self-join a row serves both sides where its owner is."""
    row = lambda df, l, r: df.select(F.col("part").alias("k0"), F.col("x").cast("long").alias("x"), F.col("y").cast("long").alias("y"), "pid", l.alias("l"), F.lit(r).alias("r"), F.lit(True).alias("home"))
    if b is not None:
        return row(owners(a, spec, layout), F.lit(True), False).union(row(replicas(b, spec, layout, d), F.lit(False), True))
    here = owners(a, spec, layout).select("pid", "x", "y", F.col("part").alias("own"), F.explode(replica_parts(spec, layout, d)).alias("part"))
    return row(here, F.col("own") == F.col("part"), True)


def sweep_join(a: DataFrame, d: int, layout: Layout, spec: GridSpec) -> DataFrame:
    """Region by region, and there strip by strip, a sweep over sorted x in numpy: another access path inside a worker. It
    holds the rows within d of the line and a bounded block of tested pairs, whatever the region's size."""
    return _swept(_strips(a, d, layout, spec), 2, d, "l2", "unordered")


def pair_bands(a: DataFrame, d: int, width: int, layout: Layout, spec: GridSpec) -> DataFrame:
    """band, n: the pairs within d by whole multiples of width, counted where the sweep finds them."""

    def count(batches):
        import numpy as np
        import pyarrow as pa

        ends = np.arange(1, d // width + 1, dtype=np.int64) * width
        n = np.zeros(len(ends) + 1, np.int64)
        for _, _, dist in _runs(batches, 2, d, "l2", "unordered"):
            n += np.bincount(np.searchsorted(ends * ends, dist, "right"), minlength=len(n))
        at = np.flatnonzero(n)
        yield pa.RecordBatch.from_arrays([pa.array(at), pa.array(n[at])], ["band", "n"])

    return _strips(a, d, layout, spec).mapInArrow(count, "band long, n long").groupBy("band").agg(F.sum("n").alias("n"))


def neighbour_counts(a: DataFrame, d: int, layout: Layout, spec: GridSpec) -> DataFrame:
    """pid, neighbours: how many other points lie within d, 0 included."""
    pairs = distance_join(a, None, d, layout, spec, pairs="ordered")
    found = pairs.groupBy("pid_a").agg(F.count("*").alias("n"))
    return a.join(found, a.pid == found.pid_a, "left").select("pid", F.coalesce("n", F.lit(0)).alias("neighbours"))


def with_neighbour(a: DataFrame, d: int, layout: Layout, spec: GridSpec, has: bool = True) -> DataFrame:
    """Points that have (or lack) another point within d."""
    pairs = distance_join(a, None, d, layout, spec, pairs="ordered").select("pid_a")
    return a.join(pairs, a.pid == pairs.pid_a, "left_semi" if has else "left_anti").select("pid")
