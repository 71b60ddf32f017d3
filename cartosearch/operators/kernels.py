"""NumPy kernels for what has no relational form: tree building, best-first Hausdorff, early-break search,
isolation scores. Each works on one dataset, or one pair, of bounded size."""

from __future__ import annotations

import functools
import heapq
import itertools
from collections import deque
from dataclasses import dataclass

import numpy as np

MAX_DEPTH = 64


@dataclass
class Tree:
    """Nodes level by level (0 is the root); points follow as balls of radius 0 numbered from len(path), leaf by leaf. The
    children of node i are the balls first[i] to last[i] - 1."""

    path: list[str]
    n: np.ndarray
    radius: np.ndarray
    centre: np.ndarray
    lo: np.ndarray
    hi: np.ndarray
    leaf: np.ndarray
    first: np.ndarray
    last: np.ndarray
    points: np.ndarray
    ids: np.ndarray
    point_distance: np.ndarray
    split_dim: np.ndarray | None = None
    split_at: np.ndarray | None = None

    @functools.cached_property
    def balls(self) -> np.ndarray:
        return np.vstack((self.centre, self.points))

    @functools.cached_property
    def radii(self) -> np.ndarray:
        return np.concatenate((self.radius, np.zeros(len(self.points))))

    @property
    def point_leaf(self) -> np.ndarray:
        at = np.flatnonzero(self.leaf)
        return np.repeat(at, (self.last - self.first)[at])

    def below(self, ball: int) -> np.ndarray:
        return np.arange(self.first[ball], self.last[ball])

    def below_all(self, nodes: np.ndarray) -> np.ndarray:
        """The children of all of the nodes."""
        sizes = self.last[nodes] - self.first[nodes]
        return np.repeat(self.first[nodes] - np.concatenate(([0], np.cumsum(sizes)[:-1])), sizes) + np.arange(sizes.sum())


def linked(path: list[str], leaf: np.ndarray, point_leaf: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(first, last, order of the points) of nodes that stand level by level; point_leaf is each point's node."""
    m = len(path)
    of = {p: i for i, p in enumerate(path)}
    first, last = np.zeros(m, np.int64), np.zeros(m, np.int64)
    if m > 1:
        parent = np.array([of[p[:-1]] for p in path[1:]])
        values, begin, count = np.unique(parent, return_index=True, return_counts=True)
        first[values], last[values] = begin + 1, begin + 1 + count
    order = np.argsort(point_leaf, kind="stable")
    at = np.flatnonzero(leaf)
    count = np.bincount(point_leaf, minlength=m)[at]
    last[at] = m + np.cumsum(count)
    first[at] = last[at] - count
    return first, last, order


def pack(t: Tree) -> bytes:
    """The tree as one value: a header, then its arrays end to end."""
    d = t.points.shape[1]
    head = np.array([len(t.path), len(t.points), d], np.int64)
    arrays = [t.n.astype(np.int64), t.radius, t.centre, t.lo, t.hi, t.leaf.astype(np.int64), t.first, t.last, t.points, t.ids.astype(np.int64), t.point_distance]
    return b"".join(np.ascontiguousarray(x).tobytes() for x in (head, *arrays))


def unpack(data: bytes) -> Tree:
    m, k, d = np.frombuffer(data, np.int64, 3).tolist()
    at = 24

    def take(rows: int, columns: int, kind) -> np.ndarray:
        nonlocal at
        got = np.frombuffer(data, kind, rows * columns, at)
        at += 8 * rows * columns
        return got.reshape(rows, columns) if columns > 1 else got

    i, x = np.int64, np.float64
    n, radius, centre, lo, hi = take(m, 1, i), take(m, 1, x), take(m, d, x), take(m, d, x), take(m, d, x)
    leaf, first, last, points, ids, away = take(m, 1, i) > 0, take(m, 1, i), take(m, 1, i), take(k, d, x), take(k, 1, i), take(k, 1, x)
    return Tree([""] * m, n, radius, centre, lo, hi, leaf, first, last, points, ids, away)


def build_tree(points: np.ndarray, f: int = 10, splitter: str = "midpoint", ids: np.ndarray | None = None) -> Tree:
    """Halve the widest dimension at its midpoint (or median, or by the two far ends) until at most f points are left.
    Points of no extent stay together however many they are."""
    nodes, leaf_of, dist = [], np.zeros(len(points), np.int64), np.zeros(len(points))
    todo = deque([(np.arange(len(points)), "")])
    while todo:
        index, path = todo.popleft()
        p = points[index]
        lo, hi, centre = p.min(axis=0), p.max(axis=0), p.mean(axis=0)
        away = np.sqrt(((p - centre) ** 2).sum(axis=1))
        wide = hi - lo
        dim = int(wide.argmax())
        me = len(nodes)
        is_leaf = len(index) <= f or wide[dim] <= 0 or len(path) >= MAX_DEPTH
        at = np.nan
        if not is_leaf:
            if splitter == "farthest_pair":
                a = p[away.argmax()]
                b = p[((p - a) ** 2).sum(axis=1).argmax()]
                up = ((p - b) ** 2).sum(axis=1) < ((p - a) ** 2).sum(axis=1)
            else:
                at = (lo[dim] + hi[dim]) / 2 if splitter == "midpoint" else float(np.median(p[:, dim]))
                up = p[:, dim] > at
            is_leaf = not up.any() or up.all()
        nodes.append((path, len(index), away.max(), centre, lo, hi, -1 if is_leaf else dim, at, is_leaf))
        if is_leaf:
            leaf_of[index], dist[index] = me, away
        else:
            todo += [(index[~up], path + "0"), (index[up], path + "1")]
    path, n, radius, centre, lo, hi, dim, at, leaf = zip(*nodes)
    leaf = np.array(leaf)
    first, last, order = linked(list(path), leaf, leaf_of)
    ids = np.arange(len(points)) if ids is None else ids
    return Tree(list(path), np.array(n), np.array(radius), np.array(centre), np.array(lo), np.array(hi), leaf, first, last, points[order], ids[order], dist[order], np.array(dim), np.array(at))


@dataclass
class Forest:
    """The nodes of many trees, level by level: `owner` is the tree's number; of each point its leaf and the distance from its centre."""

    owner: np.ndarray
    path: list[str]
    n: np.ndarray
    radius: np.ndarray
    centre: np.ndarray
    lo: np.ndarray
    hi: np.ndarray
    leaf: np.ndarray
    split_dim: np.ndarray
    split_at: np.ndarray
    leaf_of: np.ndarray
    point_distance: np.ndarray


def build_forest(points: np.ndarray, sizes: np.ndarray, f: int = 10) -> Forest:
    """The trees that build_tree makes by midpoints, of many datasets at once: `points` has one dataset after the other, of the
    sizes given. All nodes of a level are cut together."""
    d, depth, made = points.shape[1], 0, 0
    places, owner, paths = np.arange(len(points)), np.arange(len(sizes)), [""] * len(sizes)
    leaf_of, dist, levels = np.zeros(len(points), np.int64), np.zeros(len(points)), []
    while len(sizes):
        p, starts, node = points[places], np.cumsum(sizes) - sizes, np.arange(len(sizes))
        of = np.repeat(node, sizes)
        lo, hi = np.minimum.reduceat(p, starts, axis=0), np.maximum.reduceat(p, starts, axis=0)
        # Added up in the order of the points, as a mean of rows is.
        centre = np.column_stack([np.bincount(of, p[:, j]) for j in range(d)]) / sizes[:, None]
        away = np.sqrt(((p - centre[of]) ** 2).sum(axis=1))
        wide = hi - lo
        dim = wide.argmax(axis=1)
        at = (lo[node, dim] + hi[node, dim]) / 2
        cut = (sizes > f) & (wide[node, dim] > 0) & (depth < MAX_DEPTH)
        up = p[np.arange(len(p)), dim[of]] > at[of]
        above = np.add.reduceat(up, starts, dtype=np.int64)
        leaf = ~cut | (above == 0) | (above == sizes)
        levels.append((owner, paths, sizes, np.maximum.reduceat(away, starts), centre, lo, hi, leaf, np.where(leaf, -1, dim), np.where(cut, at, np.nan)))
        ends = leaf[of]
        leaf_of[places[ends]], dist[places[ends]] = made + of[ends], away[ends]
        made, depth = made + len(sizes), depth + 1
        places = places[~ends][np.argsort((2 * of + up)[~ends], kind="stable")]
        sizes = np.column_stack(((sizes - above)[~leaf], above[~leaf])).ravel()
        owner, paths = np.repeat(owner[~leaf], 2), [paths[i] + side for i in np.flatnonzero(~leaf).tolist() for side in "01"]
    columns = list(zip(*levels))
    flat = [np.concatenate(c) if i != 1 else [x for level in c for x in level] for i, c in enumerate(columns)]
    return Forest(*flat, leaf_of, dist)


def refresh_forest(owner: np.ndarray, path: np.ndarray, points: np.ndarray) -> tuple[Forest, np.ndarray]:
    """(trees of points whose tree and leaf path, as bytes, are known; the order of the points that leaf_of is in). Nodes are
    the paths above the leaves; below a node stand neighbours in the order of tree and path."""
    order = np.lexsort((path, owner))
    owner, path, points = owner[order], path[order], points[order]
    new = np.concatenate(([True], (owner[1:] != owner[:-1]) | (path[1:] != path[:-1])))
    first, leaf_of = np.flatnonzero(new), np.cumsum(new) - 1
    tree, text = owner[first], path[first]
    letters = np.ascontiguousarray(text).view(np.uint8).reshape(len(text), -1)
    length = (letters > 0).sum(axis=1)
    # Leading letters that a leaf shares with the one before it in its tree.
    shared = np.concatenate(([-1], np.where(tree[1:] == tree[:-1], (letters[1:] != letters[:-1]).argmax(axis=1), -1)))
    d, made, levels = points.shape[1], 0, []
    node_of, dist = np.zeros(len(points), np.int64), np.zeros(len(points))
    for depth in range(int(length.max()) + 1):
        on = length >= depth
        place = (np.cumsum(shared < depth) - 1)[on]
        begin = np.flatnonzero(np.concatenate(([True], place[1:] != place[:-1])))
        node = np.full(len(first), -1)
        node[on] = np.repeat(np.arange(len(begin)), np.diff(np.append(begin, len(place))))
        held = np.flatnonzero(on[leaf_of])
        p, of = points[held], node[leaf_of[held]]
        n = np.bincount(of)
        starts = np.cumsum(n) - n
        centre = np.column_stack([np.bincount(of, p[:, j]) for j in range(d)]) / n[:, None]
        away = np.sqrt(((p - centre[of]) ** 2).sum(axis=1))
        head = np.flatnonzero(on)[begin]
        leaf = np.maximum.reduceat(length[on], begin) == depth
        names = [x[:depth].decode() for x in text[head].tolist()]
        none = np.full(len(begin), -1)
        levels.append((tree[head], names, n, np.maximum.reduceat(away, starts), centre, np.minimum.reduceat(p, starts, axis=0), np.maximum.reduceat(p, starts, axis=0), leaf, none, np.full(len(begin), np.nan)))
        ends = leaf[of]
        node_of[held[ends]], dist[held[ends]] = made + of[ends], away[ends]
        made += len(begin)
    flat = [np.concatenate(c) if i != 1 else [x for level in c for x in level] for i, c in enumerate(zip(*levels))]
    return Forest(*flat, node_of, dist), order


def tree_from_rows(path: list[str], kind: np.ndarray, n: np.ndarray, radius: np.ndarray, is_leaf: list, o: np.ndarray, lo: np.ndarray, hi: np.ndarray, ids: np.ndarray | None = None) -> Tree:
    """A stored tree: nodes (kind 0) and points (kind 1) in any order."""
    node = np.flatnonzero(kind == 0)
    node = np.array(sorted(node.tolist(), key=lambda i: (len(path[i]), path[i])), np.int64)
    of = {path[i]: k for k, i in enumerate(node.tolist())}
    point = np.flatnonzero(kind == 1)
    leaf = np.array([bool(is_leaf[i]) for i in node.tolist()])
    paths = [path[i] for i in node.tolist()]
    first, last, order = linked(paths, leaf, np.array([of[path[i]] for i in point.tolist()], np.int64))
    point = point[order]
    return Tree(paths, n[node], radius[node], o[node], lo[node], hi[node], leaf, first, last, o[point], np.arange(len(point)) if ids is None else ids[point], radius[point])


@dataclass
class Outcome:
    distance: float | None  # None: beyond the threshold
    evaluations: int
    expansions: int
    frontier: list


def best_first(q: Tree, d: Tree, tau: float = np.inf, mode: str = "exact", eps: float = 0.0, returns: str = "center", bounds: str = "ball") -> Outcome:
    """Directed Hausdorff distance from q to d.

    Q parts wait by decreasing upper bound of their points' distance to D; each keeps the D parts that its
    points may be nearest to. The head's larger side is split until the head is a point and its D parts are points
    (exact), or it and its nearest part are narrower than eps (approx). D parts are ordered by the lower bound that holds
    for the whole of D, and dropped only where the gap between the two balls (or boxes) exceeds the head's upper bound.
    All D parts of the head that are wider than it are split in one step, and children are bounded as one block.
    """
    qb, qr, db, dr = q.balls, q.radii, d.balls, d.radii
    qn, dn = len(q.path), len(d.path)
    if bounds == "box":
        qlo, qhi = np.vstack((q.lo, q.points)), np.vstack((q.hi, q.points))
        dlo, dhi = np.vstack((d.lo, d.points)), np.vstack((d.hi, d.points))
    evaluations = expansions = 0
    number = itertools.count()
    heap: list = []

    def push(parts_of_q: np.ndarray, parts: np.ndarray) -> None:
        """Bound each Q part against the D parts, all at once, and queue it with those it may be nearest to."""
        nonlocal evaluations
        evaluations += len(parts_of_q) * len(parts)
        if bounds == "box":
            a, b = qlo[parts_of_q][:, None], qhi[parts_of_q][:, None]
            gap = np.sqrt((np.maximum(0, np.maximum(a - dhi[parts], dlo[parts] - b)) ** 2).sum(axis=2))
            upper = np.sqrt((np.maximum(np.abs(a - dhi[parts]), np.abs(b - dlo[parts])) ** 2).sum(axis=2))
            order = gap
        else:
            square = ((qb[parts_of_q][:, None] - db[parts]) ** 2).sum(axis=2)
            far, r, own = np.sqrt(square), dr[parts], qr[parts_of_q][:, None]
            upper, order, gap = np.sqrt(square + r * r) + own, np.maximum(far - r, 0), np.maximum(far - r - own, 0)
        best = upper.min(axis=1)
        keep = gap <= best[:, None]
        for i, u, k, o, g, w in zip(parts_of_q.tolist(), best.tolist(), keep, order, gap, upper):
            heapq.heappush(heap, (-u, next(number), i, parts[k], o[k], g[k], w[k]))

    push(np.array([0]), np.array([0]))
    while True:
        head = heapq.heappop(heap)
        minus, _, i, parts, order, gap, upper = head
        if gap.min() > tau:
            return Outcome(None, evaluations, expansions, [])
        k = int(np.lexsort((-dr[parts], order))[0])
        j = int(parts[k])
        q_point, d_point = i >= qn, j >= dn
        if q_point and (parts >= dn).all():
            heapq.heappush(heap, head)
            return Outcome(-minus, evaluations, expansions, [(e[0], e[2], e[3]) for e in heap])
        if mode == "approx" and qr[i] < eps and dr[j] < eps:
            heapq.heappush(heap, head)
            distance = float(np.sqrt(((db[j] - qb[i]) ** 2).sum())) if returns == "center" else -minus
            return Outcome(distance, evaluations, expansions, [(e[0], e[2], e[3]) for e in heap])
        expansions += 1
        # D parts wider than the Q part are replaced together, else the Q part is: by its children, each with all D parts.
        wide = (parts < dn) & (q_point | (dr[parts] > qr[i]))
        if mode == "approx":
            wide &= (dr[parts] >= eps) | (parts == j)
        if wide.any() and (q_point or not d_point):
            push(np.array([i]), np.concatenate((parts[~wide], d.below_all(parts[wide]))))
        elif q_point:
            push(np.array([i]), np.concatenate((parts[parts >= dn], d.below_all(parts[parts < dn]))))
        else:
            push(q.below(i), parts)


def squares(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Squared distances of all pairs, one dimension after the other."""
    out = (a[:, 0][:, None] - b[:, 0]) ** 2
    for j in range(1, a.shape[1]):
        out += (a[:, j][:, None] - b[:, j]) ** 2
    return out


def all_pairs(q: np.ndarray, points: np.ndarray, block: int = 4096, width: int = 16) -> float:
    """The directed Hausdorff distance from all pairs of points, in blocks that stay in a core's cache."""
    near = np.full(len(q), np.inf)
    for at in range(0, len(points), block):
        some = points[at : at + block].T.copy()
        a, c = np.empty((width, some.shape[1])), np.empty((width, some.shape[1]))
        for first in range(0, len(q), width):
            own = q[first : first + width]
            x, y = a[: len(own)], c[: len(own)]
            np.subtract(own[:, :1], some[0], out=x)
            np.multiply(x, x, out=x)
            for j in range(1, len(some)):
                np.subtract(own[:, j : j + 1], some[j], out=y)
                np.multiply(y, y, out=y)
                np.add(x, y, out=x)
            np.minimum(near[first : first + width], x.min(axis=1), out=near[first : first + width])
    return float(np.sqrt(near.max()))


def parts_of(t: Tree, most: int) -> list[tuple[int, np.ndarray]]:
    """(node, places of its points) of the topmost nodes of at most `most` points, or leaves: each point once."""
    top = np.full(len(t.path), -1)
    for i in range(len(t.path)):
        if top[i] < 0 and (t.n[i] <= most or t.leaf[i]):
            top[i] = i
        if not t.leaf[i]:
            top[t.first[i] : t.last[i]] = top[i]
    at = np.flatnonzero(t.leaf)
    owner = np.repeat(top[at], (t.last - t.first)[at])
    order = np.argsort(owner, kind="stable")
    nodes, begin = np.unique(owner[order], return_index=True)
    return list(zip(nodes.tolist(), np.split(order, begin[1:])))


@dataclass
class Outline:
    """A few nodes of a tree that hold each point once, and the node of each point."""

    centre: np.ndarray
    radius: np.ndarray
    owner: np.ndarray


def outline(t: Tree, parts: int = 16) -> Outline:
    got = parts_of(t, len(t.points) // parts)
    owner = np.zeros(len(t.points), np.int64)
    for number, (_, places) in enumerate(got):
        owner[places] = number
    nodes = [i for i, _ in got]
    return Outline(t.centre[nodes], t.radius[nodes], owner)


def by_parts(q: Tree, d: Tree, tau: float = np.inf, parts: list | None = None, reached: float = 0.0, slack: float = 0.0) -> tuple[float | None, float, int, int]:
    """(distance or None beyond tau, what it is at most, evaluations, expansions): the distance that best_first gives, for trees
    of many points. Parts of Q (see parts_of), those far from D's centre first and few at first, go down D's tree together, each
    as one ball. A part whose points are sure to be within the largest distance so far (`reached` is one known from below) and
    the slack is left, and the pair is given up where a part lies beyond tau."""
    parts = parts_of(q, 64) if parts is None else parts
    evaluations = expansions = 0
    dn, found, most = len(d.path), reached, 0.0
    starts = lambda sizes: np.cumsum(sizes) - sizes
    nodes = np.array([i for i, _ in parts])
    order = np.argsort(-((q.centre[nodes] - d.centre[0]) ** 2).sum(axis=1), kind="stable")
    at, size = 0, 8
    while at < len(order):
        now = order[at : at + size]
        at, size = at + len(now), min(4 * size, 256)
        centre, own, open_ = q.centre[nodes[now]], q.radius[nodes[now]], np.zeros(len(now), np.int64)
        held = np.ones(len(now), np.int64)  # D's open nodes of each part, side by side
        while len(now):
            owner, first = np.repeat(np.arange(len(now)), held), starts(held)
            square = ((d.centre[open_] - centre[owner]) ** 2).sum(axis=1)
            evaluations, expansions = evaluations + len(open_), expansions + len(now)
            r = d.radius[open_]
            upper = (np.sqrt(np.minimum.reduceat(square + r * r, first)) + own) * (1 + 1e-12)
            gap = np.sqrt(square) - r - own[owner]
            within = upper <= found + slack
            if (~within & (np.minimum.reduceat(gap, first) > tau * (1 + 1e-12))).any():
                return None, np.inf, evaluations, expansions
            most = max(most, float(upper[within].max(initial=0.0)))
            keep = (gap <= upper[owner]) & ~within[owner]
            inner = ~d.leaf[open_] & keep
            last = ~within & ~np.logical_or.reduceat(inner, first)
            for k in np.flatnonzero(last)[np.argsort(-upper[last], kind="stable")].tolist():
                if upper[k] <= found + slack:
                    most = max(most, float(upper[k]))
                    continue
                leaves = open_[first[k] : first[k] + held[k]][keep[first[k] : first[k] + held[k]]]
                points, places = d.points[d.below_all(leaves) - dn], parts[now[k]][1]
                step = max(1, 2_000_000 // len(points))
                for start in range(0, len(places), step):
                    square = squares(q.points[places[start : start + step]], points)
                    evaluations += square.size
                    found = max(found, float(np.sqrt(square.min(axis=1).max())))
                    if found > tau:
                        return None, np.inf, evaluations, expansions
            left = ~within & ~last
            keep &= left[owner]
            open_, inner, owner = open_[keep], inner[keep], owner[keep]
            sizes = np.where(inner, d.last[open_] - d.first[open_], 1)
            held = np.bincount(owner, sizes, len(now)).astype(np.int64)[left]
            open_ = np.repeat(np.where(inner, d.first[open_], open_) - starts(sizes), sizes) + np.arange(sizes.sum())
            now, centre, own = now[left], centre[left], own[left]
    return found, max(found, most), evaluations, expansions


def drain(q: Tree, d: Tree, frontier: list) -> np.ndarray:
    """For every point of q its nearest point of d, from the parts that a best-first run has left."""
    nearest = np.zeros(len(q.points), np.int64)
    qn, dn = len(q.path), len(d.path)
    stack = [(e[1], e[2]) for e in frontier]  # (upper bound, Q part, D parts)
    below_d: dict[int, np.ndarray] = {}

    def points_below(tree: Tree, ball: int, n: int) -> np.ndarray:
        if ball >= n:
            return np.array([ball - n])
        return np.concatenate([points_below(tree, int(c), n) for c in tree.below(ball)])

    order = np.lexsort((d.ids, *d.points.T[::-1]))
    rank = np.empty(len(order), np.int64)
    rank[order] = np.arange(len(order))
    for ball, parts in stack:
        candidates = np.concatenate([below_d.setdefault(int(p), points_below(d, int(p), dn)) for p in parts])
        for i in points_below(q, ball, qn):
            far = ((d.points[candidates] - q.points[i]) ** 2).sum(axis=1)
            nearest[i] = candidates[np.lexsort((rank[candidates], far))[0]]
    return nearest


def nearest_in_tree(q: np.ndarray, d: Tree, k: int, block: int = 64) -> tuple[np.ndarray, np.ndarray, int]:
    """(places in d.points, distances, evaluations) of the k nearest points for each point of q; ties by coordinates, then
    id. Neighbouring points go down the tree as a ball: nodes whose gap exceeds the bound that enough points lie within go."""
    order = np.lexsort((d.ids, *d.points.T[::-1]))
    rank = np.empty(len(order), np.int64)
    rank[order] = np.arange(len(order))
    dn, k_there = len(d.path), min(k, len(d.points))
    index, dist = np.zeros((len(q), k_there), np.int64), np.zeros((len(q), k_there))
    evaluations = 0
    todo = [np.arange(len(q))] if len(q) else []
    while todo:
        rows = todo.pop()
        p = q[rows]
        if len(rows) > block:
            wide = int((p.max(axis=0) - p.min(axis=0)).argmax())
            by = np.argsort(p[:, wide], kind="stable")
            todo += [rows[by[: len(by) // 2]], rows[by[len(by) // 2 :]]]
            continue
        centre = p.mean(axis=0)
        radius = np.sqrt(((p - centre) ** 2).sum(axis=1)).max()
        parts = np.array([0])
        while True:
            far = np.sqrt(((d.centre[parts] - centre) ** 2).sum(axis=1))
            evaluations += len(parts)
            r = d.radius[parts]
            by = np.argsort(far + r, kind="stable")
            enough = np.searchsorted(np.cumsum(d.n[parts[by]]), k_there)
            limit = (far + r)[by[min(enough, len(by) - 1)]] + radius
            parts = parts[far - r - radius <= limit * (1 + 1e-12)]
            inner = ~d.leaf[parts]
            if not inner.any():
                break
            parts = np.concatenate((parts[~inner], d.below_all(parts[inner])))
        points = d.below_all(parts) - dn
        for start in range(0, len(rows), max(1, 2_000_000 // max(1, len(points)))):
            own = rows[start : start + max(1, 2_000_000 // max(1, len(points)))]
            square = ((q[own][:, None] - d.points[points]) ** 2).sum(axis=2)
            evaluations += square.size
            away = np.sqrt(square)
            best = np.lexsort((np.broadcast_to(rank[points], away.shape), away), axis=1)[:, :k_there] if k_there > 1 else _first(away, rank[points])
            index[own] = points[best]
            dist[own] = np.take_along_axis(away, best, axis=1)
    return index, dist, evaluations


def _first(away: np.ndarray, rank: np.ndarray) -> np.ndarray:
    """The column of the least distance of each row, of the least rank among equals."""
    least = away.min(axis=1, keepdims=True)
    return np.where(away == least, rank, np.iinfo(np.int64).max).argmin(axis=1)[:, None]


def early_break(q: np.ndarray, d: np.ndarray, k: int = 1) -> tuple[np.ndarray, np.ndarray, int]:
    """(indexes, distances, coordinates looked at): scan D for each q, dimension by dimension, giving a point up
    as soon as its partial distance is beyond the k-th best so far."""
    index, dist, looked = np.zeros((len(q), k), np.int64), np.zeros((len(q), k)), 0
    block = 256
    for a, p in enumerate(q):
        best: list[tuple[float, int]] = []
        for start in range(0, len(d), block):
            part = np.arange(start, min(start + block, len(d)))
            total = np.zeros(len(part))
            limit = best[k - 1][0] if len(best) >= k else np.inf
            for j in range(d.shape[1]):
                looked += len(part)
                total = total + (d[part, j] - p[j]) ** 2
                near = total <= limit
                part, total = part[near], total[near]
            best = sorted([*best, *zip(total.tolist(), part.tolist())])[:k]
        got = best + [(np.inf, -1)] * (k - len(best))
        dist[a], index[a] = np.sqrt([x for x, _ in got]), [i for _, i in got]
    return index, dist, looked


def isolation_scores(points: np.ndarray, samples: list[np.ndarray]) -> np.ndarray:
    """Mean over samples: 1 outside all spheres, else how much smaller the sphere of the nearest neighbour of the
    smallest covering sphere's centre is. A sphere reaches to its centre's nearest neighbour in the sample."""
    score = np.zeros(len(points))
    for s in samples:
        if len(s) < 2:
            score += 1
            continue
        between = np.sqrt(((s[:, None] - s[None]) ** 2).sum(axis=2))
        np.fill_diagonal(between, np.inf)
        next_, size = between.argmin(axis=1), between.min(axis=1)
        ratio = np.where(size > 0, size[next_] / np.where(size > 0, size, 1), 1.0)
        away = np.sqrt(((points[:, None] - s[None]) ** 2).sum(axis=2))
        cover = np.where(away <= size, size, np.inf)
        best = cover.argmin(axis=1)
        score += np.where(np.isinf(cover.min(axis=1)), 1.0, 1 - ratio[best])
    return score / max(1, len(samples))
