"""SQL for the queries, over the tables as views; it states what a result is, not how the engine finds it."""

from __future__ import annotations

from .sources.repositories import default_dims, in_dialect, repository_sql

EPS = "0.0000005"


def pts(handle: str, d: int | None = None) -> str:
    return f"p AS ({repository_sql(handle, d)}), me AS (SELECT min(dataset_id) AS q FROM p)"


def _each(d: int, fmt: str, sep: str = ", ") -> str:
    return sep.join(fmt.format(i=i) for i in range(d))


def boxes(d: int) -> str:
    return f"box AS (SELECT dataset_id, count(*) AS n, {_each(d, 'min(c{i}) AS lo{i}')}, {_each(d, 'max(c{i}) AS hi{i}')} FROM p GROUP BY dataset_id)"


def cell_sql(theta: int, d: int) -> str:
    """cells(dataset_id, cell) from p."""
    n = 1 << theta
    extent = f"ext AS (SELECT {_each(d, 'min(c{i}) AS elo{i}')}, {_each(d, f'(max(c{{i}}) - min(c{{i}})) / {n}.0 AS w{{i}}')} FROM p)"
    index = f"idx AS (SELECT dataset_id, {_each(d, f'CAST(greatest(least(floor((c{{i}} - elo{{i}}) / w{{i}}), {n - 1}), 0) AS BIGINT) AS x{{i}}')} FROM p, ext)"
    bits = " + ".join(f"(((x{i} >> {b}) & 1) << {b * d + i})" for b in range(theta) for i in range(d))
    return f"{extent}, {index}, cells AS (SELECT DISTINCT dataset_id, CAST({bits} AS BIGINT) AS cell FROM idx)"


def dist(d: int, a: str = "a", b: str = "b") -> str:
    return "sqrt(" + " + ".join(f"({a}.c{i} - {b}.c{i}) * ({a}.c{i} - {b}.c{i})" for i in range(d)) + ")"


def hausdorff(handle: str, d: int | None = None) -> str:
    """haus(dataset_id, distance) from the query dataset to all others."""
    d = d or default_dims(handle)
    return f"{pts(handle, d)}, near AS (SELECT b.dataset_id, a.point_id, min({dist(d)}) AS m FROM p a JOIN p b ON b.dataset_id <> a.dataset_id WHERE a.dataset_id = (SELECT q FROM me) GROUP BY b.dataset_id, a.point_id), haus AS (SELECT dataset_id, max(m) AS distance FROM near GROUP BY dataset_id)"


def top(source: str, score: str, order: str, k: int, shown: str) -> str:
    return f"SELECT dataset_id, {shown}, rank FROM (SELECT dataset_id, {score}, row_number() OVER (ORDER BY {order}, dataset_id) AS rank FROM {source}) t WHERE rank <= {k}"


def dataset_boxes(handle: str) -> str:
    d = default_dims(handle)
    return f"WITH {pts(handle)}, {boxes(d)} SELECT dataset_id, n, {_each(d, 'round(lo{i}, 6) AS lo{i}')}, {_each(d, 'round(hi{i}, 6) AS hi{i}')} FROM box"


def z_signatures(handle: str, theta: int = 5) -> str:
    return f"WITH {pts(handle)}, {cell_sql(theta, default_dims(handle))} SELECT dataset_id, cell FROM cells"


def z_rollup(handle: str, theta: int = 5) -> str:
    return f"WITH {pts(handle)}, {cell_sql(theta, 2)} SELECT CAST(cell >> 2 AS BIGINT) AS cell, count(*) AS n FROM cells GROUP BY cell >> 2"


def ia_topk(handle: str, k: int = 10) -> str:
    area = "greatest(least(a.hi0, b.hi0) - greatest(a.lo0, b.lo0), 0.0) * greatest(least(a.hi1, b.hi1) - greatest(a.lo1, b.lo1), 0.0)"
    return f"WITH {pts(handle)}, {boxes(2)}, s AS (SELECT b.dataset_id, {area} AS v FROM box a JOIN box b ON a.dataset_id <> b.dataset_id WHERE a.dataset_id = (SELECT q FROM me)), s2 AS (SELECT * FROM s WHERE v > 0) " + top("s2", "v", "v DESC", k, "round(v, 6) AS score")


def gbo_topk(handle: str, theta: int = 5, k: int = 10) -> str:
    return f"WITH {pts(handle)}, {cell_sql(theta, default_dims(handle))}, s AS (SELECT b.dataset_id, count(*) AS v FROM cells a JOIN cells b ON a.cell = b.cell AND a.dataset_id <> b.dataset_id WHERE a.dataset_id = (SELECT q FROM me) GROUP BY b.dataset_id) " + top("s", "v", "v DESC", k, "v AS score")


def haus_topk(handle: str, k: int = 10, d: int | None = None) -> str:
    return f"WITH {hausdorff(handle, d)} " + top("haus", "distance", "distance", k, "round(distance, 6) AS distance")


def haus_pair(handle: str) -> str:
    return f"WITH {hausdorff(handle)} SELECT dataset_id, round(distance, 6) AS distance FROM haus WHERE dataset_id = (SELECT max(dataset_id) FROM p)"


def haus_within(handle: str, k: int) -> str:
    return f"WITH {hausdorff(handle)} " + top("haus", "distance", "distance", k, "true AS within").replace(", rank FROM (", " FROM (", 1)


def symmetric(handle: str, k: int) -> str:
    d = default_dims(handle)
    back = f"back AS (SELECT dataset_id, max(m) AS there FROM (SELECT b.dataset_id, b.point_id, min({dist(d)}) AS m FROM p a JOIN p b ON b.dataset_id <> a.dataset_id WHERE a.dataset_id = (SELECT q FROM me) GROUP BY b.dataset_id, b.point_id) x GROUP BY dataset_id)"
    return f"WITH {hausdorff(handle)}, {back}, s AS (SELECT dataset_id, greatest(distance, there) AS v FROM haus JOIN back USING (dataset_id)) " + top("s", "v", "v", k, "round(v, 6) AS distance")


def range_datasets(handle: str, grow: float) -> str:
    """Boxes that meet the query's box grown by a share of the extent."""
    return f"WITH {pts(handle)}, {boxes(2)}, ext AS (SELECT max(c0) - min(c0) AS e0, max(c1) - min(c1) AS e1 FROM p), r AS (SELECT lo0 - {grow} * e0 AS a0, hi0 + {grow} * e0 AS b0, lo1 - {grow} * e1 AS a1, hi1 + {grow} * e1 AS b1 FROM box, ext WHERE dataset_id = (SELECT q FROM me)) SELECT dataset_id, n FROM box, r WHERE lo0 <= b0 AND a0 <= hi0 AND lo1 <= b1 AND a1 <= hi1"


def range_batch(handle: str) -> str:
    return f"WITH {pts(handle)}, {boxes(2)}, qs AS (SELECT * FROM box) SELECT qs.dataset_id AS query_id, b.dataset_id FROM qs JOIN box b ON b.lo0 <= qs.hi0 AND qs.lo0 <= b.hi0 AND b.lo1 <= qs.hi1 AND qs.lo1 <= b.hi1"


def range_points(handle: str) -> str:
    """Points of the query dataset in the middle half of its box."""
    return f"WITH {pts(handle)}, {boxes(2)}, r AS (SELECT lo0 + (hi0 - lo0) * 0.25 AS a0, hi0 - (hi0 - lo0) * 0.25 AS b0, lo1 + (hi1 - lo1) * 0.25 AS a1, hi1 - (hi1 - lo1) * 0.25 AS b1 FROM box WHERE dataset_id = (SELECT q FROM me)) SELECT dataset_id, point_id, round(c0, 6) AS c0, round(c1, 6) AS c1 FROM p, r WHERE dataset_id = (SELECT q FROM me) AND c0 BETWEEN a0 AND b0 AND c1 BETWEEN a1 AND b1"


def nearest(handle: str, k: int = 1) -> str:
    return f"WITH {pts(handle)}, j AS (SELECT a.point_id AS q_point_id, b.point_id AS d_point_id, {dist(2)} AS dd, b.c0, b.c1 FROM p a JOIN p b ON b.dataset_id = (SELECT max(dataset_id) FROM p) WHERE a.dataset_id = (SELECT q FROM me)), r AS (SELECT *, row_number() OVER (PARTITION BY q_point_id ORDER BY dd, c0, c1, d_point_id) AS rank FROM j) SELECT q_point_id, rank, d_point_id, round(dd, 6) AS distance FROM r WHERE rank <= {k}"


def nearest_union(handle: str) -> str:
    return f"WITH {pts(handle)}, ids AS (SELECT DISTINCT dataset_id FROM p WHERE dataset_id <> (SELECT max(dataset_id) FROM p)), j AS (SELECT a.dataset_id AS a_id, a.point_id AS q_point_id, {dist(2)} AS dd FROM p a JOIN p b ON b.dataset_id = (SELECT max(dataset_id) FROM p) WHERE a.dataset_id IN (SELECT dataset_id FROM ids)) SELECT q_point_id, round(min(dd), 6) AS distance FROM j GROUP BY a_id, q_point_id"


def gbo_accuracy(handle: str, k: int = 10) -> str:
    return f"WITH {hausdorff(handle)}, {cell_sql(5, 2)}, s AS (SELECT b.dataset_id, count(*) AS v FROM cells a JOIN cells b ON a.cell = b.cell AND a.dataset_id <> b.dataset_id WHERE a.dataset_id = (SELECT q FROM me) GROUP BY b.dataset_id), g AS (SELECT dataset_id FROM s ORDER BY v DESC, dataset_id LIMIT {k}), h AS (SELECT dataset_id FROM haus ORDER BY distance, dataset_id LIMIT {k}) SELECT count(*) / {k}.0 AS accuracy FROM g JOIN h USING (dataset_id)"


def scale(handle: str) -> str:
    return f"WITH {pts(handle)}, s AS (SELECT dataset_id, count(*) AS c FROM p GROUP BY dataset_id) SELECT CAST(least(floor(log2(c)), 16) AS BIGINT) AS size_log2, count(*) AS n_datasets, CAST(sum(c) AS BIGINT) AS n_points FROM s GROUP BY 1"


def similar_pairs(handle: str, t: float) -> str:
    return f"WITH {pts(handle)}, near AS (SELECT a.dataset_id AS q_id, b.dataset_id, a.point_id, min({dist(2)}) AS m FROM p a JOIN p b ON b.dataset_id <> a.dataset_id GROUP BY a.dataset_id, b.dataset_id, a.point_id) SELECT q_id, dataset_id, round(max(m), 6) AS distance FROM near GROUP BY q_id, dataset_id HAVING max(m) <= {t}"


__all__ = [n for n in dir() if not n.startswith("_")] + ["in_dialect"]
