"""DuckDB SQL that says the same as the queries: each text is complete and computes its own points and layouts."""

from __future__ import annotations

from cutlearn.sources.points import DUCKDB, POINT_SETS

G = 30


def pts(name: str) -> str:
    return POINT_SETS[name].sql(DUCKDB)


def cells(name: str, g: int = G) -> str:
    """CTEs p (points), b (map) and c (points with their cell)."""
    return f"""p AS ({pts(name)}),
b AS (SELECT min(x) AS x0, max(x) AS x1, min(y) AS y0, max(y) AS y1 FROM p),
c AS (SELECT pid, x, y, ((x - x0) * {g}) // (x1 - x0 + 1) AS col, ((y1 - y) * {g}) // (y1 - y0 + 1) AS rw FROM p, b)"""


def uniform_rects(m: int = 8, g: int = G) -> str:
    pairs = ", ".join(f"({r}, {m // r})" for r in range(1, m + 1) if m % r == 0)
    return f"""shape AS (SELECT nr, nc FROM (VALUES {pairs}) AS t(nr, nc), b
  ORDER BY abs(ln(nc * 1.0 / nr) - ln((x1 - x0 + 1) * 1.0 / (y1 - y0 + 1))), nr LIMIT 1),
rects AS (SELECT i * nc + j AS part, i * {g} // nr AS r0, (i + 1) * {g} // nr AS r1, j * {g} // nc AS c0, (j + 1) * {g} // nc AS c1
  FROM shape, range({m}) AS a(i), range({m}) AS z(j) WHERE i < nr AND j < nc)"""


def quad_rects(g: int = G) -> str:
    """At most 8 leaves: the map in four, and the fullest of them in four."""
    h = g // 2
    return f"""quads AS (SELECT * FROM (VALUES (0, {h}, 0, {h}), (0, {h}, {h}, {g}), ({h}, {g}, 0, {h}), ({h}, {g}, {h}, {g})) AS t(r0, r1, c0, c1)),
fullest AS (SELECT q.r0, q.r1, q.c0, q.c1 FROM quads q LEFT JOIN c ON c.rw >= q.r0 AND c.rw < q.r1 AND c.col >= q.c0 AND c.col < q.c1
  GROUP BY ALL ORDER BY count(c.pid) DESC, q.r0, q.r1, q.c0, q.c1 LIMIT 1),
leafs AS (SELECT * FROM quads EXCEPT SELECT * FROM fullest
  UNION ALL SELECT CASE WHEN i = 0 THEN r0 ELSE (r0 + r1) // 2 END, CASE WHEN i = 0 THEN (r0 + r1) // 2 ELSE r1 END,
    CASE WHEN j = 0 THEN c0 ELSE (c0 + c1) // 2 END, CASE WHEN j = 0 THEN (c0 + c1) // 2 ELSE c1 END FROM fullest, range(2) AS a(i), range(2) AS z(j)),
rects AS (SELECT row_number() OVER (ORDER BY r0, r1, c0, c1) - 1 AS part, * FROM leafs)"""


def kdb_levels() -> str:
    """CTE k3: pid, x, y and part, the leaf of an eight-leaf tree cut at exact ranks."""
    out, before = [], "(SELECT pid, x, y, 0 AS node FROM p)"
    for level, axis in enumerate("xyx"):
        out.append(f"v{level} AS (SELECT node, list_sort(list({axis}))[count(*) // 2 + 1] AS v FROM {before} t GROUP BY node)")
        out.append(f"k{level + 1} AS (SELECT pid, x, y, 2 * t.node + CASE WHEN {axis} < v THEN 0 ELSE 1 END AS node FROM {before} t JOIN v{level} USING (node))")
        before = f"k{level + 1}"
    return ",\n".join(out)


def demo_rects(g: int = G) -> str:
    """CTE rects: the eight-leaf tree snapped to grid lines level by level."""
    out = [f"s0 AS (SELECT pid, x, y, rw, col, 0 AS node FROM c)", f"n0 AS (SELECT 0 AS node, 0 AS r0, {g} AS r1, 0 AS c0, {g} AS c1)"]
    for k, axis in enumerate("xyx"):
        lo, hi, cell = ("c0", "c1", "col") if axis == "x" else ("r0", "r1", "rw")
        at = f"b.x0 + j * (b.x1 - b.x0 + 1) / {g}.0" if axis == "x" else f"b.y1 - j * (b.y1 - b.y0 + 1) / {g}.0"
        out.append(f"m{k} AS (SELECT node, list_sort(list({axis}))[count(*) // 2 + 1] AS v FROM s{k} GROUP BY node)")
        out.append(f"l{k} AS (SELECT n.*, j AS line, row_number() OVER (PARTITION BY n.node ORDER BY abs({at} - v), j) AS nth FROM n{k} n JOIN m{k} USING (node), b, range(1, {g}) AS t(j) WHERE j > {lo} AND j < {hi})")
        keep = {c: c for c in ("r0", "r1", "c0", "c1")}
        first, second = dict(keep), dict(keep)
        first[hi], second[lo] = "line", "line"
        row = lambda d: ", ".join(f"{v} AS {c}" for c, v in d.items())
        out.append(f"n{k + 1} AS (SELECT 2 * node AS node, {row(first)} FROM l{k} WHERE nth = 1 UNION ALL SELECT 2 * node + 1, {row(second)} FROM l{k} WHERE nth = 1)")
        out.append(f"s{k + 1} AS (SELECT pid, x, y, rw, col, 2 * s.node + CASE WHEN {cell} < line THEN 0 ELSE 1 END AS node FROM s{k} s JOIN l{k} l ON s.node = l.node AND l.nth = 1)")
    return ",\n".join([*out, "rects AS (SELECT node AS part, r0, r1, c0, c1 FROM n3)"])


LAYOUTS = {"uniform": uniform_rects(), "quad": quad_rects(), "demo": demo_rects()}
PLACED = "placed AS (SELECT pid, x, y, part FROM c JOIN rects ON rw >= r0 AND rw < r1 AND col >= c0 AND col < c1)"


def assign(name: str, layout: str) -> str:
    if layout == "kdb":
        return f"WITH p AS ({pts(name)}),\n{kdb_levels()}\nSELECT pid, CAST(node AS INT) AS part FROM k3"
    return f"WITH {cells(name)},\n{LAYOUTS[layout]},\n{PLACED}\nSELECT pid, CAST(part AS INT) AS part FROM placed"


def balance(name: str, layout: str) -> str:
    if layout == "kdb":
        head = f"WITH p AS ({pts(name)}),\n{kdb_levels()},\ncounts AS (SELECT node AS part, count(*) AS n FROM k3 GROUP BY node)"
    else:
        head = f"WITH {cells(name)},\n{LAYOUTS[layout]},\n{PLACED},\ncounts AS (SELECT r.part, count(q.pid) AS n FROM rects r LEFT JOIN placed q ON q.part = r.part GROUP BY r.part)"
    return f"""{head},
ranked AS (SELECT n, row_number() OVER (ORDER BY n, part) AS k FROM counts)
SELECT count(*) AS parts, CAST(sum(n) AS BIGINT) AS total, max(n) AS largest, round(max(n) * count(*) / CAST(sum(n) AS DOUBLE), 6) AS max_over_mean,
  round(stddev_pop(n), 4) AS stddev, round(CAST(2 * sum(k * n) AS DOUBLE) / CAST(count(*) * sum(n) AS DOUBLE) - (count(*) + 1) / CAST(count(*) AS DOUBLE), 6) AS gini FROM ranked"""


def _clamp(e: str, g: int = G) -> str:
    return f"least(greatest({e}, 0), {g - 1})"


def copies(d: int, g: int = G) -> str:
    """CTE copied: a row for each region that the box of a point touches."""
    r = lambda v: _clamp(f"CAST(floor((y1 - ({v})) * {g} / CAST(y1 - y0 + 1 AS DOUBLE)) AS BIGINT)")
    c = lambda v: _clamp(f"CAST(floor((({v}) - x0) * {g} / CAST(x1 - x0 + 1 AS DOUBLE)) AS BIGINT)")
    return f"""boxes AS (SELECT pid, x, y, {r(f'y + {d}')} AS a0, {r(f'y - {d}')} AS a1, {c(f'x - {d}')} AS z0, {c(f'x + {d}')} AS z1 FROM p, b),
copied AS (SELECT pid, x, y, part FROM boxes JOIN rects ON a0 < r1 AND a1 >= r0 AND z0 < c1 AND z1 >= c0)"""


def replication(name: str, layout: str, d: int) -> str:
    return f"""WITH {cells(name)},
{LAYOUTS[layout]},
{PLACED},
{copies(d)}
SELECT CAST(r.part AS INT) AS part, (SELECT count(*) FROM placed q WHERE q.part = r.part) AS owned, (SELECT count(*) FROM copied q WHERE q.part = r.part) AS received FROM rects r"""


def modelled_cost(name: str, layout: str, d: int, index: bool) -> str:
    k = lambda v, o: f"CAST(floor(({v} - {o}) / {d}.0) AS BIGINT)"
    cand = "owned * received"
    extra = ""
    if index:
        extra = f""",
lb AS (SELECT part, {k('x', 'x0')} AS kx, {k('y', 'y0')} AS ky, count(*) AS n FROM placed, b GROUP BY ALL),
rb AS (SELECT part, {k('x', 'x0')} AS kx, {k('y', 'y0')} AS ky, count(*) AS n FROM copied, b GROUP BY ALL),
cand AS (SELECT lb.part, sum(lb.n * rb.n) AS k FROM lb JOIN rb ON lb.part = rb.part AND abs(lb.kx - rb.kx) <= 1 AND abs(lb.ky - rb.ky) <= 1 GROUP BY lb.part)"""
        cand = "coalesce((SELECT k FROM cand WHERE cand.part = r.part), 0)"
    return f"""WITH {cells(name)},
{LAYOUTS[layout]},
{PLACED},
{copies(d)}{extra},
r AS (SELECT part, (SELECT count(*) FROM placed q WHERE q.part = t.part) AS owned, (SELECT count(*) FROM copied q WHERE q.part = t.part) AS received FROM rects t)
SELECT CAST({d} AS BIGINT) AS d, CAST(max(64 * (owned + received) + {cand}) + 256 * (sum(received) - sum(owned)) AS BIGINT) AS cost_64 FROM r"""


def pairs(name: str, d: int, other: str | None = None, mode: str = "unordered", metric: str = "l2") -> str:
    """All pairs within d by square buckets."""
    dist = {"l2": "(a.x - z.x) * (a.x - z.x) + (a.y - z.y) * (a.y - z.y)", "l1": "abs(a.x - z.x) + abs(a.y - z.y)", "linf": "greatest(abs(a.x - z.x), abs(a.y - z.y))"}[metric]
    far = d * d if metric == "l2" else d
    keep = "" if other or mode == "with_self" else (" AND a.pid < z.pid" if mode == "unordered" else " AND a.pid <> z.pid")
    key = f"CAST(floor(x / {d}.0) AS BIGINT) AS kx, CAST(floor(y / {d}.0) AS BIGINT) AS ky"
    return f"""WITH p AS ({pts(name)}), q AS ({pts(other or name)}),
l AS (SELECT pid, x, y, {key} FROM p),
r AS (SELECT pid, x, y, kx + i AS kx, ky + j AS ky FROM (SELECT pid, x, y, {key} FROM q), range(-1, 2) AS s(i), range(-1, 2) AS t(j))
SELECT a.pid AS pid_a, z.pid AS pid_b, {dist} AS d2 FROM l a JOIN r z ON a.kx = z.kx AND a.ky = z.ky WHERE {dist} <= {far}{keep}"""
