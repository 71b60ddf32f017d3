"""SQL for the index, the cleaner, bounds, chains of searches and streams: the same trees by recursion, level by level."""

from __future__ import annotations

from . import oracle as sql
from .oracle import _each, boxes, cell_sql, default_dims, dist, hausdorff, pts, top
from .sources.repositories import repository_sql


def tree(handle: str, f: int = 10, d: int = 2) -> str:
    """raw points, every node that a point lies in (st), leaves with radii (leaf) and points with their leaf (placed)."""
    wide = "greatest(" + _each(d, "hi{i} - lo{i}") + ")"
    dim = "CASE " + " ".join(f"WHEN hi{i} - lo{i} = wide THEN {i}" for i in range(d)) + " END"
    pick = lambda x: "CASE dim " + " ".join(f"WHEN {i} THEN {x.format(i=i)}" for i in range(d)) + " END"
    w = "OVER (PARTITION BY dataset_id, path)"
    coords = _each(d, "c{i}")
    away = lambda a: "sqrt(" + " + ".join(f"(c{i} - {a}.o{i}) * (c{i} - {a}.o{i})" for i in range(d)) + ")"
    return f"""RECURSIVE raw AS ({repository_sql(handle, d)}),
st AS (SELECT dataset_id, point_id, {coords}, CAST('' AS VARCHAR) AS path FROM raw
  UNION ALL SELECT dataset_id, point_id, {coords}, path || CASE WHEN x > mid THEN '1' ELSE '0' END FROM (
    SELECT *, {pick('c{i}')} AS x, {pick('(lo{i} + hi{i}) / 2')} AS mid, {pick('hi{i}')} AS hi FROM (
      SELECT *, {dim} AS dim FROM (
        SELECT *, {wide} AS wide FROM (SELECT *, count(*) {w} AS n, {_each(d, f'min(c{{i}}) {w} AS lo{{i}}')}, {_each(d, f'max(c{{i}}) {w} AS hi{{i}}')} FROM st) a) b) c) e
  WHERE n > {f} AND wide > 0 AND mid < hi AND length(path) < 64),
mean AS (SELECT dataset_id, path, count(*) AS n, {_each(d, 'avg(c{i}) AS o{i}')}, {_each(d, 'min(c{i}) AS lo{i}')}, {_each(d, 'max(c{i}) AS hi{i}')} FROM st GROUP BY dataset_id, path),
ends AS (SELECT dataset_id, point_id, max(length(path)) AS deepest FROM st GROUP BY dataset_id, point_id),
node AS (SELECT m.dataset_id, m.path, any_value(m.n) AS n, max({away('m')}) AS radius, {_each(d, 'any_value(m.o{i}) AS o{i}')}, {_each(d, 'any_value(m.lo{i}) AS lo{i}')}, {_each(d, 'any_value(m.hi{i}) AS hi{i}')}, max(e.deepest) = length(m.path) AS is_leaf
  FROM st JOIN mean m ON st.dataset_id = m.dataset_id AND st.path = m.path JOIN ends e ON st.dataset_id = e.dataset_id AND st.point_id = e.point_id GROUP BY m.dataset_id, m.path),
leaf AS (SELECT dataset_id, path, radius FROM node WHERE is_leaf),
placed AS (SELECT st.*, {away('m')} AS away, l.radius AS leaf_radius FROM st JOIN leaf l ON st.dataset_id = l.dataset_id AND st.path = l.path JOIN mean m ON st.dataset_id = m.dataset_id AND st.path = m.path)"""


def knee(order: str = "DESC", radii: str = "SELECT radius FROM leaf") -> str:
    """ranked radii with the gap below the chord, and the radius of the largest gap."""
    first, last = ("max", "min") if order == "DESC" else ("min", "max")
    return f"""phi AS (SELECT radius, row_number() OVER (ORDER BY radius {order}) - 1 AS rank, count(*) OVER () AS n, {first}(radius) OVER () AS a, {last}(radius) OVER () AS b FROM ({radii}) r),
gaps AS (SELECT rank, radius, a - rank * (a - b) / n - radius AS gap FROM phi),
knee AS (SELECT radius AS t FROM gaps WHERE rank >= 1 ORDER BY gap DESC, rank LIMIT 1)"""


def clean(handle: str, f: int = 10, d: int = 2) -> str:
    """The repository without the points beyond the knee; a dataset that would lose all keeps them."""
    return f"""{tree(handle, f, d)}, {knee()},
marked AS (SELECT *, leaf_radius <= (SELECT t FROM knee) OR away <= (SELECT t FROM knee) AS kept FROM placed),
p AS (SELECT dataset_id, point_id, path, {_each(d, 'c{i}')} FROM (SELECT *, bool_or(kept) OVER (PARTITION BY dataset_id) AS any_kept FROM marked) m WHERE kept OR NOT any_kept),
me AS (SELECT min(dataset_id) AS q FROM p)"""


def cleaned(handle: str, statement: str) -> str:
    """A statement over a repository, over the cleaned one."""
    return statement.replace(pts(handle), clean(handle), 1)


def cleaned_cells(handle: str, statement: str) -> str:
    """The same, with the grid over the raw points."""
    return cleaned(handle, statement).replace("AS w1 FROM p)", "AS w1 FROM raw)", 1)


#: Means of values of two digits often end in a half of the last digit shown; this moves them off it in both engines.
OFF_HALF = 3.14e-9
NODE = "dataset_id, path, n, round(radius, 6) AS radius, is_leaf, " + _each(2, f"round(o{{i}} + {OFF_HALF}, 6) AS o{{i}}") + ", " + _each(2, "round(lo{i}, 6) AS lo{i}") + ", " + _each(2, "round(hi{i}, 6) AS hi{i}")


def tree_nodes(handle: str, f: int = 10) -> str:
    return f"WITH {tree(handle, f)} SELECT {NODE} FROM node"


def tree_points(handle: str, f: int = 10) -> str:
    return f"WITH {tree(handle, f)} SELECT dataset_id, point_id, path AS leaf_path, round(away, 6) AS leaf_distance FROM placed"


def gap_profile(handle: str, order: str = "DESC") -> str:
    return f"WITH {tree(handle)}, {knee(order)} SELECT rank, round(radius, 6) AS radius, round(gap, 6) AS gap FROM gaps"


def threshold(handle: str, order: str = "DESC") -> str:
    return f"WITH {tree(handle)}, {knee(order)} SELECT round(t, 6) AS threshold FROM knee"


def outliers(handle: str) -> str:
    return f"WITH {clean(handle)} SELECT dataset_id, point_id FROM raw EXCEPT SELECT dataset_id, point_id FROM p"


def per_dataset_threshold(handle: str) -> str:
    return f"""WITH {tree(handle)},
phi AS (SELECT dataset_id, radius, row_number() OVER (PARTITION BY dataset_id ORDER BY radius DESC) - 1 AS rank, count(*) OVER w AS n, max(radius) OVER w AS a, min(radius) OVER w AS b FROM leaf WINDOW w AS (PARTITION BY dataset_id)),
gaps AS (SELECT *, a - rank * (a - b) / n - radius AS gap, rank >= 1 AND n > 2 AND a <> b AS bend FROM phi),
best AS (SELECT dataset_id, radius, row_number() OVER (PARTITION BY dataset_id ORDER BY bend DESC, CASE WHEN bend THEN gap END DESC, rank) AS r FROM gaps)
SELECT dataset_id, round(radius, 6) AS threshold FROM best WHERE r = 1"""


def refreshed_roots(handle: str) -> str:
    return f"WITH {clean(handle)}, o AS (SELECT dataset_id, count(*) AS n, avg(c0) AS o0, avg(c1) AS o1, min(c0) AS lo0, min(c1) AS lo1, max(c0) AS hi0, max(c1) AS hi1 FROM p GROUP BY dataset_id) SELECT o.dataset_id, any_value(n) AS n, round(max(sqrt((c0 - o0) * (c0 - o0) + (c1 - o1) * (c1 - o1))), 6) AS radius, {_each(2, f'round(any_value(o{{i}}) + {OFF_HALF}, 6) AS o{{i}}')}, {_each(2, 'round(any_value(lo{i}), 6) AS lo{i}')}, {_each(2, 'round(any_value(hi{i}), 6) AS hi{i}')} FROM o JOIN p ON o.dataset_id = p.dataset_id GROUP BY o.dataset_id"


def refreshed_nodes(handle: str) -> str:
    """Count and box of every node after cleaning: its points are those whose leaf lies below it."""
    return f"WITH {clean(handle)}, up AS (SELECT dataset_id, c0, c1, left(path, k) AS path FROM (SELECT *, unnest(range(0, length(path) + 1)) AS k FROM p) x) SELECT dataset_id, path, count(*) AS n, {_each(2, 'round(min(c{i}), 6) AS lo{i}')}, {_each(2, 'round(max(c{i}), 6) AS hi{i}')} FROM up GROUP BY dataset_id, path"


def radius_bins(handle: str, bins: int = 20) -> str:
    return f"WITH {tree(handle)}, h AS (SELECT max(radius) / {bins}.0 AS w FROM leaf) SELECT CAST(least(floor(radius / w), {bins - 1}) AS BIGINT) AS bin, count(*) AS leaves, max(length(path)) AS max_depth FROM leaf, h GROUP BY 1"


def space(handle: str) -> str:
    return f"WITH {tree(handle)}, p AS (SELECT * FROM raw), {cell_sql(5, 2)} SELECT 'tree' AS part, (SELECT count(*) FROM node) + (SELECT count(*) FROM raw) AS n_rows UNION ALL SELECT 'roots', (SELECT count(DISTINCT dataset_id) FROM raw) UNION ALL SELECT 'members', (SELECT count(DISTINCT dataset_id) FROM raw) UNION ALL SELECT 'cells', (SELECT count(*) FROM cells)"


def summary(handle: str) -> str:
    return f"WITH {pts(handle)}, {balls()} SELECT dataset_id, n, round(radius, 6) AS radius FROM root"


def balls() -> str:
    """root(dataset_id, n, o, lo, hi, radius) from p."""
    return f"{boxes(2)}, o AS (SELECT dataset_id, avg(c0) AS o0, avg(c1) AS o1 FROM p GROUP BY dataset_id), far AS (SELECT p.dataset_id, max(sqrt((c0 - o0) * (c0 - o0) + (c1 - o1) * (c1 - o1))) AS radius FROM p JOIN o ON p.dataset_id = o.dataset_id GROUP BY p.dataset_id), root AS (SELECT box.*, o0, o1, radius FROM box JOIN o ON box.dataset_id = o.dataset_id JOIN far ON box.dataset_id = far.dataset_id)"


def ball_bounds(handle: str) -> str:
    between = "sqrt((a.o0 - b.o0) * (a.o0 - b.o0) + (a.o1 - b.o1) * (a.o1 - b.o1))"
    return f"WITH {pts(handle)}, {balls()} SELECT b.dataset_id, round(greatest({between} - b.radius, 0), 6) AS lower, round(sqrt({between} * {between} + b.radius * b.radius) + a.radius, 6) AS upper, round(greatest({between} - a.radius - b.radius, 0), 6) AS gap FROM root a JOIN root b ON a.dataset_id <> b.dataset_id WHERE a.dataset_id = (SELECT q FROM me)"


def box_bounds(handle: str) -> str:
    """The farthest face of the query's box from D's box; the nearest face of D's box from its farthest place."""
    faces = [(i, s) for i in (0, 1) for s in ("lo", "hi")]
    side = lambda t, i, s: tuple(tuple(f"{t}.{s if j == i else x}{j}" for j in (0, 1)) for x in ("lo", "hi"))
    apart = []
    for i, s in faces:
        lo, hi = side("a", i, s)
        gaps = [f"greatest({lo[j]} - b.hi{j}, b.lo{j} - {hi[j]}, 0)" for j in (0, 1)]
        apart.append("sqrt(" + " + ".join(f"{g} * {g}" for g in gaps) + ")")
    reach = []
    for i, s in faces:
        lo, hi = side("b", i, s)
        far = ["greatest(" + ", ".join(f"abs(a.{x}{j} - {y[j]})" for x in ("lo", "hi") for y in (lo, hi)) + ")" for j in (0, 1)]
        reach.append("sqrt(" + " + ".join(f"{g} * {g}" for g in far) + ")")
    return f"WITH {pts(handle)}, {boxes(2)} SELECT b.dataset_id, round(greatest({', '.join(apart)}), 6) AS lower, round(least({', '.join(reach)}), 6) AS upper FROM box a JOIN box b ON a.dataset_id <> b.dataset_id WHERE a.dataset_id = (SELECT q FROM me)"


def upper(f: int = 10) -> str:
    """un: the nodes above every dataset of root; the widest side of the united boxes is halved, or that of the centres."""
    w = "OVER (PARTITION BY path)"
    pick = lambda c, x: f"CASE WHEN {c}0 >= {c}1 THEN {x.format(i=0)} ELSE {x.format(i=1)} END"
    return f"""un AS (SELECT dataset_id, o0, o1, lo0, lo1, hi0, hi1, CAST('' AS VARCHAR) AS path FROM root
  UNION ALL SELECT dataset_id, o0, o1, lo0, lo1, hi0, hi1, path || CASE WHEN CASE WHEN u1 IN (0, n) THEN s2 ELSE s1 END THEN '1' ELSE '0' END FROM (
    SELECT *, sum(CAST(s1 AS INTEGER)) {w} AS u1, sum(CAST(s2 AS INTEGER)) {w} AS u2 FROM (
      SELECT *, {pick('e', 'o{i} > (a{i} + b{i}) / 2')} AS s1, {pick('g', 'o{i} > (x{i} + y{i}) / 2')} AS s2 FROM (
        SELECT *, b0 - a0 AS e0, b1 - a1 AS e1, y0 - x0 AS g0, y1 - x1 AS g1 FROM (
          SELECT *, count(*) {w} AS n, {_each(2, f'min(lo{{i}}) {w} AS a{{i}}')}, {_each(2, f'max(hi{{i}}) {w} AS b{{i}}')}, {_each(2, f'min(o{{i}}) {w} AS x{{i}}')}, {_each(2, f'max(o{{i}}) {w} AS y{{i}}')} FROM un) t1) t2) t3) t4
  WHERE n > {f} AND length(path) < 64 AND NOT (u1 IN (0, n) AND u2 IN (0, n)))"""


def upper_nodes(handle: str) -> str:
    return f"WITH RECURSIVE {pts(handle)}, {balls()}, {upper()} SELECT path, count(*) AS n_datasets, CAST(sum(r.n) AS BIGINT) AS n, {_each(2, 'round(min(un.lo{i}), 6) AS lo{i}')}, {_each(2, 'round(max(un.hi{i}), 6) AS hi{i}')}, {_each(2, f'round(sum(un.o{{i}} * r.n) / sum(r.n) + {OFF_HALF}, 6) AS o{{i}}')} FROM un JOIN root r ON un.dataset_id = r.dataset_id GROUP BY path"


def upper_cells(handle: str) -> str:
    return f"WITH RECURSIVE {pts(handle)}, {balls()}, {upper()}, {cell_sql(5, 2)} SELECT path, count(DISTINCT cell) AS n_cells FROM un JOIN cells ON un.dataset_id = cells.dataset_id GROUP BY path"


def upper_bounds(handle: str) -> str:
    """Per node the area its box shares with the query's and the query's cells found below it."""
    area = "greatest(least(any_value(q.hi0), max(un.hi0)) - greatest(any_value(q.lo0), min(un.lo0)), 0.0) * greatest(least(any_value(q.hi1), max(un.hi1)) - greatest(any_value(q.lo1), min(un.lo1)), 0.0)"
    return f"WITH RECURSIVE {pts(handle)}, {balls()}, {upper()}, {cell_sql(5, 2)}, q AS (SELECT * FROM root WHERE dataset_id = (SELECT q FROM me)), qc AS (SELECT cell FROM cells WHERE dataset_id = (SELECT q FROM me)), a AS (SELECT path, {area} AS ia FROM un, q GROUP BY path), c AS (SELECT path, count(DISTINCT cells.cell) AS gbo FROM un JOIN cells ON un.dataset_id = cells.dataset_id JOIN qc ON cells.cell = qc.cell GROUP BY path) SELECT a.path, round(ia, 6) AS ia_bound, coalesce(gbo, 0) AS gbo_bound FROM a LEFT JOIN c ON a.path = c.path"


def z_corners(handle: str, theta: int = 5) -> str:
    """Cells and the lower and upper corners of their boxes."""
    n = 1 << theta
    bits = lambda i: " + ".join(f"(((cell >> {2 * b + i}) & 1) << {b})" for b in range(theta))
    return f"WITH {pts(handle)}, {cell_sql(theta, 2)}, u AS (SELECT DISTINCT cell FROM cells) SELECT cell, {_each(2, 'round(elo{i} + x{i} * w{i}, 6) AS lo{i}')}, {_each(2, 'round(elo{i} + (x{i} + 1) * w{i}, 6) AS hi{i}')} FROM (SELECT cell, {bits(0)} AS x0, {bits(1)} AS x1 FROM u) t, ext".replace(f"/ {n}.0", f"/ {n}.0")


def all_pairs(handle: str) -> str:
    """haus(q, dataset_id, distance) between all datasets."""
    return f"near AS (SELECT a.dataset_id AS q, b.dataset_id, a.point_id, min({dist(2)}) AS m FROM p a JOIN p b ON b.dataset_id <> a.dataset_id GROUP BY 1, 2, 3), haus AS (SELECT q, dataset_id, max(m) AS v FROM near GROUP BY 1, 2)"


def batch(handle: str, source: str, order: str, k: int, shown: str, where: str = "") -> str:
    return f"SELECT q AS query_id, CAST(rank AS INTEGER) AS rank, dataset_id, {shown} AS score FROM (SELECT *, row_number() OVER (PARTITION BY q ORDER BY {order}, dataset_id) AS rank FROM {source} {where}) t WHERE rank <= {k}"


def hausdorff_batch(handle: str, k: int) -> str:
    return f"WITH {pts(handle)}, {all_pairs(handle)} " + batch(handle, "haus", "v", k, "round(v, 6)")


def ia_batch(handle: str, k: int) -> str:
    area = "greatest(least(a.hi0, b.hi0) - greatest(a.lo0, b.lo0), 0.0) * greatest(least(a.hi1, b.hi1) - greatest(a.lo1, b.lo1), 0.0)"
    return f"WITH {pts(handle)}, {boxes(2)}, s AS (SELECT a.dataset_id AS q, b.dataset_id, {area} AS v FROM box a JOIN box b ON a.dataset_id <> b.dataset_id) " + batch(handle, "s", "v DESC", k, "round(v, 6)", "WHERE v > 0")


def gbo_batch(handle: str, k: int) -> str:
    return f"WITH {pts(handle)}, {cell_sql(5, 2)}, s AS (SELECT a.dataset_id AS q, b.dataset_id, count(*) AS v FROM cells a JOIN cells b ON a.cell = b.cell AND a.dataset_id <> b.dataset_id GROUP BY 1, 2) " + batch(handle, "s", "v DESC", k, "CAST(v AS DOUBLE)")


def exemplars(handle: str, k: int) -> str:
    """The three measures side by side, and how many of the others' results each result is among."""
    area = "greatest(least(a.hi0, b.hi0) - greatest(a.lo0, b.lo0), 0.0) * greatest(least(a.hi1, b.hi1) - greatest(a.lo1, b.lo1), 0.0)"
    return f"""WITH {hausdorff(handle)}, {boxes(2)}, {cell_sql(5, 2)},
ia AS (SELECT b.dataset_id, {area} AS v FROM box a JOIN box b ON a.dataset_id <> b.dataset_id WHERE a.dataset_id = (SELECT q FROM me)),
gbo AS (SELECT b.dataset_id, count(*) AS v FROM cells a JOIN cells b ON a.cell = b.cell AND a.dataset_id <> b.dataset_id WHERE a.dataset_id = (SELECT q FROM me) GROUP BY b.dataset_id),
r AS (SELECT 'ia' AS method, dataset_id, v, row_number() OVER (ORDER BY v DESC, dataset_id) AS rank FROM ia WHERE v > 0
  UNION ALL SELECT 'gbo', dataset_id, v, row_number() OVER (ORDER BY v DESC, dataset_id) FROM gbo
  UNION ALL SELECT 'hausdorff', dataset_id, distance, row_number() OVER (ORDER BY distance, dataset_id) FROM haus),
best AS (SELECT * FROM r WHERE rank <= {k})
SELECT (SELECT q FROM me) AS query_id, method, CAST(rank AS INTEGER) AS rank, dataset_id, round(v, 6) AS value, (SELECT count(*) FROM best b WHERE b.dataset_id = best.dataset_id AND b.method <> best.method) AS shared_with FROM best"""


def filtered(handle: str, where: str, k: int = 10) -> str:
    return f"WITH {pts(handle)}, keep AS (SELECT DISTINCT dataset_id FROM p WHERE {where} OR dataset_id = (SELECT q FROM me)), " + hausdorff(handle).removeprefix(pts(handle) + ", ") + f", h2 AS (SELECT haus.* FROM haus JOIN keep ON haus.dataset_id = keep.dataset_id) " + top("h2", "distance", "distance", k, "round(distance, 6) AS distance")


def centre_topk(handle: str, k: int) -> str:
    return f"WITH {pts(handle)}, {balls()}, s AS (SELECT b.dataset_id, sqrt((a.o0 - b.o0) * (a.o0 - b.o0) + (a.o1 - b.o1) * (a.o1 - b.o1)) AS v FROM root a JOIN root b ON a.dataset_id <> b.dataset_id WHERE a.dataset_id = (SELECT q FROM me)) " + top("s", "v", "v", k, "round(v, 6) AS distance")


def approximate(handle: str, k: int) -> str:
    """The true distances, for a comparison of errors."""
    return f"WITH {hausdorff(handle)} SELECT dataset_id, round(distance, 6) AS exact, true AS within FROM haus"


def middle(handle: str, share: float = 0.25) -> str:
    return f"r AS (SELECT lo0 + (hi0 - lo0) * {share} AS a0, hi0 - (hi0 - lo0) * {share} AS b0, lo1 + (hi1 - lo1) * {share} AS a1, hi1 - (hi1 - lo1) * {share} AS b1 FROM box WHERE dataset_id = (SELECT q FROM me))"


def range_points_all(handle: str) -> str:
    return f"WITH {pts(handle)}, {boxes(2)}, {middle(handle)} SELECT dataset_id, point_id, round(c0, 6) AS c0, round(c1, 6) AS c1 FROM p, r WHERE c0 BETWEEN a0 AND b0 AND c1 BETWEEN a1 AND b1"


def drill_down(handle: str, k: int) -> str:
    """The k datasets that share most area with the query, and their points in the middle of its box."""
    area = "greatest(least(a.hi0, b.hi0) - greatest(a.lo0, b.lo0), 0.0) * greatest(least(a.hi1, b.hi1) - greatest(a.lo1, b.lo1), 0.0)"
    return f"WITH {pts(handle)}, {boxes(2)}, {middle(handle)}, s AS (SELECT b.dataset_id, {area} AS v FROM box a JOIN box b ON a.dataset_id <> b.dataset_id WHERE a.dataset_id = (SELECT q FROM me)), t AS (SELECT dataset_id FROM s WHERE v > 0 ORDER BY v DESC, dataset_id LIMIT {k}) SELECT p.dataset_id, point_id, round(c0, 6) AS c0, round(c1, 6) AS c1 FROM p JOIN t ON p.dataset_id = t.dataset_id, r WHERE c0 BETWEEN a0 AND b0 AND c1 BETWEEN a1 AND b1"


def enriched(handle: str) -> str:
    return f"SELECT n.q_point_id, n.d_point_id, e.event_type FROM ({sql.nearest(handle)}) n JOIN events e ON n.d_point_id = e.event_id"


def rtree(handle: str, fanout: int) -> str:
    """Leaves of the bulk-loaded boxes: slabs along the first dimension, runs along the second."""
    return f"""WITH {pts(handle)}, a AS (SELECT *, count(*) OVER (PARTITION BY dataset_id) AS m, row_number() OVER (PARTITION BY dataset_id ORDER BY c0, c1, point_id) - 1 AS r FROM p),
b AS (SELECT *, CAST(floor(r / (ceil(sqrt(ceil(m / {fanout}.0))) * {fanout})) AS BIGINT) AS slab FROM a),
c AS (SELECT *, CAST(floor((row_number() OVER (PARTITION BY dataset_id, slab ORDER BY c1, c0, point_id) - 1) / {fanout}.0) AS BIGINT) AS run FROM b),
g AS (SELECT dataset_id, slab, run, count(*) AS n, {_each(2, 'min(c{i}) AS lo{i}')}, {_each(2, 'max(c{i}) AS hi{i}')} FROM c GROUP BY 1, 2, 3)
SELECT dataset_id, row_number() OVER (PARTITION BY dataset_id ORDER BY slab, run) - 1 AS node, n, {_each(2, 'round(lo{i}, 6) AS lo{i}')}, {_each(2, 'round(hi{i}, 6) AS hi{i}')} FROM g"""


def neighbours(handle: str, radius: float, least: int) -> str:
    return f"WITH {pts(handle)} SELECT a.dataset_id, a.point_id FROM p a JOIN p b ON a.dataset_id = b.dataset_id AND a.point_id <> b.point_id WHERE {dist(2)} <= {radius} GROUP BY 1, 2 HAVING count(*) >= {least}"


def emd(handle: str, k: int) -> str:
    """Per axis the summed difference of the cumulative shares of cells, averaged over the axes."""
    n = 32
    return f"""WITH {pts(handle)}, ext AS (SELECT {_each(2, 'min(c{i}) AS e{i}')}, {_each(2, f'(max(c{{i}}) - min(c{{i}})) / {n}.0 AS w{{i}}')} FROM p),
bins AS ({' UNION ALL '.join(f"SELECT dataset_id, {i} AS axis, CAST(greatest(least(floor((c{i} - e{i}) / w{i}), {n - 1}), 0) AS BIGINT) AS bin FROM p, ext" for i in (0, 1))}),
h AS (SELECT dataset_id, axis, bin, count(*) * 1.0 / sum(count(*)) OVER (PARTITION BY dataset_id, axis) AS share FROM bins GROUP BY 1, 2, 3),
grid AS (SELECT d.dataset_id, a.axis, b.bin FROM (SELECT DISTINCT dataset_id FROM p) d, (VALUES (0), (1)) a(axis), range(0, {n}) b(bin)),
f AS (SELECT g.dataset_id, g.axis, g.bin, sum(coalesce(h.share, 0)) OVER (PARTITION BY g.dataset_id, g.axis ORDER BY g.bin) AS c FROM grid g LEFT JOIN h ON g.dataset_id = h.dataset_id AND g.axis = h.axis AND g.bin = h.bin),
s AS (SELECT b.dataset_id, sum(abs(a.c - b.c)) / 2 AS v FROM f a JOIN f b ON a.axis = b.axis AND a.bin = b.bin AND a.dataset_id <> b.dataset_id WHERE a.dataset_id = (SELECT q FROM me) GROUP BY b.dataset_id) """ + top("s", "v", "v", k, "round(v, 6) AS distance")


def isolated_sizes(handle: str) -> str:
    return f"WITH {pts(handle)} SELECT dataset_id, count(*) AS n FROM p GROUP BY dataset_id"


def sql_functions(handle: str) -> str:
    far = "greatest(sqrt((c0 - 0.0) * (c0 - 0.0) + (c1 - 0.0) * (c1 - 0.0)) - 1.0 - 2.0, 0)"
    cell = lambda c: f"greatest(least(CAST(floor({c} / 2.0) AS BIGINT), 31), 0)"
    bits = " + ".join(f"((({cell(c)} >> {b}) & 1) << {2 * b + i})" for b in range(5) for i, c in enumerate(("c0", "c1")))
    return f"WITH {pts(handle)} SELECT dataset_id, round(max(sqrt(c0 * c0 + c1 * c1)), 6) AS length, CAST(min({bits}) AS BIGINT) AS cell FROM p GROUP BY dataset_id".replace("{far}", far)


def table_function(handle: str, k: int) -> str:
    return f"WITH {hausdorff(handle)} SELECT CAST(rank AS INTEGER) AS rank, dataset_id, value FROM (SELECT dataset_id, round(distance, 6) AS value, row_number() OVER (ORDER BY distance, dataset_id) AS rank FROM haus) t WHERE rank <= {k}"


def stream_roots(handle: str) -> str:
    return f"WITH {pts(handle)} SELECT dataset_id, count(*) AS n, round(min(c1), 6) AS lo1, round(max(c1), 6) AS hi1, round(sqrt((max(c0) - min(c0)) * (max(c0) - min(c0)) + (max(c1) - min(c1)) * (max(c1) - min(c1))), 6) AS radius_bound FROM p GROUP BY dataset_id"


def stream_slices() -> str:
    return "SELECT CAST(user_id AS VARCHAR) AS dataset_id, strftime(time_bucket(INTERVAL 1 DAY, ts, TIMESTAMP '2024-01-01'), '%Y-%m-%d') AS start, count(*) AS n, round(min(value), 6) AS lo1, round(max(value), 6) AS hi1 FROM events GROUP BY 1, 2"


def stream_box(handle: str) -> str:
    return f"WITH {pts(handle)} SELECT dataset_id, point_id FROM p WHERE c0 BETWEEN 10 AND 300 AND c1 BETWEEN 5 AND 40"


def stream_fences(handle: str) -> str:
    return f"WITH {pts(handle)} SELECT dataset_id, point_id, fence FROM p JOIN (VALUES ('a', 0, 0, 100, 20), ('b', 50, 10, 400, 60)) f(fence, x0, y0, x1, y1) ON c0 BETWEEN x0 AND x1 AND c1 BETWEEN y0 AND y1"


def stream_gbo(handle: str) -> str:
    return f"WITH {pts(handle)}, {cell_sql(5, 2)} SELECT b.dataset_id, count(*) AS score FROM cells a JOIN cells b ON a.cell = b.cell WHERE a.dataset_id = (SELECT q FROM me) GROUP BY b.dataset_id"


def trips(gap_ms: int) -> str:
    return f"""WITH e AS (SELECT CAST(user_id AS VARCHAR) AS dataset_id, epoch_us(ts) // 1000 AS ms FROM events),
m AS (SELECT *, CASE WHEN ms - lag(ms) OVER (PARTITION BY dataset_id ORDER BY ms) > {gap_ms} THEN 1 ELSE 0 END AS new FROM e),
t AS (SELECT *, sum(new) OVER (PARTITION BY dataset_id ORDER BY ms ROWS UNBOUNDED PRECEDING) AS trip FROM m),
g AS (SELECT dataset_id, trip, count(*) AS n, min(ms) AS first_ms, max(ms) AS last_ms FROM t GROUP BY 1, 2)
SELECT dataset_id, CAST(trip AS BIGINT) AS trip, n, first_ms, last_ms FROM g"""


def slices() -> str:
    return "SELECT strftime(time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '2024-01-01'), '%Y-%m-%d %H:%M') AS slice, count(*) AS n FROM events GROUP BY 1"


def around(handle: str, r: float, theta: int = 5) -> str:
    """Points in a rectangle of r cells to each side around the query's centre."""
    n = 1 << theta
    return f"WITH {pts(handle)}, ext AS (SELECT {_each(2, f'(max(c{{i}}) - min(c{{i}})) / {n}.0 AS w{{i}}')} FROM p), o AS (SELECT avg(c0) AS o0, avg(c1) AS o1 FROM p WHERE dataset_id = (SELECT q FROM me)) SELECT dataset_id, point_id FROM p, ext, o WHERE c0 BETWEEN o0 - w0 * {r} AND o0 + w0 * {r} AND c1 BETWEEN o1 - w1 * {r} AND o1 + w1 * {r}"


def rescaled(handle: str) -> str:
    return f"WITH {pts(handle)}, e AS (SELECT {_each(2, 'min(c{i}) AS a{i}')}, {_each(2, 'max(c{i}) AS b{i}')} FROM p) SELECT dataset_id, point_id, {_each(2, 'round((c{i} - a{i}) / (b{i} - a{i}), 6) AS c{i}')} FROM p, e"


def files() -> str:
    """Points of three datasets that went through files; a file is a dataset, so only coordinates come back."""
    return "SELECT p_brand AS brand, round(CAST(p_size AS DOUBLE), 6) AS c0, round(p_retailprice, 6) AS c1 FROM part WHERE p_brand IN (SELECT DISTINCT p_brand FROM part ORDER BY p_brand LIMIT 3)"


__all__ = [n for n in dir() if not n.startswith("_")] + ["default_dims"]
