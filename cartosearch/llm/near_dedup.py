"""MinHash near-dedup with BagMinHash signatures.

A document is the multiset of its runs of five words. Every run drives a Poisson process over (time, weight,
signature component): its weight axis is cut into the dyadic intervals [0,1), [1,2), [2,4), [4,8), ... and each
interval has its own process of a rate equal to its length, so a run of weight w costs log w processes rather
than w. A point counts if its discretised weight lies below w. The earliest point of each component is the
signature; two signatures agree in a component with the probability of the weighted Jaccard similarity.

Signatures are cut into bands. Documents that share a band are linked to the smallest of them, connected
components of these links are clusters, and inside a cluster the exact similarity of the multisets decides.
There the distance 1 - J obeys the triangle inequality: each document is compared with pivots, and members of
two pivots are compared only where the pivots' distances allow a link. Classes are the connected components
of all pairs of similarity `least` or more within clusters; pairs are never listed.

Texts that share a passage can chain into one cluster without being similar. Texts of similarity `least` share one
of their first items in any common order, as many as are left when `least` of them are taken away. With the rare items first
these heads cut a cluster into parts. Parts still beyond the bounds of a task lose the balls of pivots; what is left is dealt
into blocks that meet two by two, each two of them in a task.

Texts that are equal form one node before anything else. Null text is an empty one; empty texts are one class.
A text of one to four words is one run. Null doc_id: kept, carries its class; it names a class only where no
document with an id is in it (then class_id is null). Repeated rows share their class.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..checkpoints import checkpoint_dir, checkpointed
from . import textblocks as tb
from . import unique_texts as ut

WIDTH = 5
BANDS = 28
BAND_ROWS = 5
LEAST = 0.8
#: Texts of a cluster, and runs of them (about 100 bytes each), that one task compares; larger clusters are cut first.
MOST_IN_TASK = 20_000
MOST_RUNS_IN_TASK = 3_000_000
#: Edges of a node beyond which it counts as a hub, and edges / HUBS where those are more: a bound on the number of hubs.
HUB_ROWS = 200
HUBS = 5_000
#: Items counted as frequent when large clusters are cut; they go to every task.
FREQUENT = 65_536
#: Bytes of pivot distances that a task keeps; those of further pivots are computed again.
KEPT_BYTES = 64 << 20

_DRAW = 0xA0761D6478BD642F


def runs_of(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(document, hash) of every run of five words, in document order; shorter documents are one run."""
    starts, ends, rows = tb.word_bounds(data, offsets)
    words = tb.word_hashes(data, starts, ends)
    n = np.diff(rows)
    doc = np.repeat(np.arange(len(n)), n)
    hashes = tb.shingle_hashes(words, WIDTH)
    at = np.arange(len(hashes))
    whole = doc[at] == doc[at + WIDTH - 1] if len(hashes) else np.zeros(0, bool)
    runs, of = hashes[whole], doc[at][whole]
    short = np.flatnonzero((n > 0) & (n < WIDTH))
    if len(short):
        one = np.array([tb.shingle_hashes(words[rows[d] : rows[d + 1]], int(n[d]))[0] ^ np.uint64(n[d]) for d in short], np.uint64)
        order = np.argsort(np.concatenate((of, short)), kind="stable")
        runs, of = np.concatenate((runs, one))[order], np.concatenate((of, short))[order]
    return of, runs


def weighted_runs(doc: np.ndarray, runs: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(document, run, weight) without repetition."""
    order = np.lexsort((runs, doc))
    doc, runs = doc[order], runs[order]
    first = np.flatnonzero(np.concatenate(([True], (doc[1:] != doc[:-1]) | (runs[1:] != runs[:-1])))) if len(doc) else np.zeros(0, np.int64)
    return doc[first], runs[first], np.diff(np.append(first, len(doc)))


def signatures(doc: np.ndarray, runs: np.ndarray, weight: np.ndarray, docs: int, size: int) -> np.ndarray:
    """docs x size arrival times; rows of documents without runs are infinite."""
    out = np.full((docs, size), np.inf)
    total = np.bincount(doc, weight, docs)
    # One process per dyadic interval that the weight reaches into.
    level, pieces = 0, []
    while True:
        low, length = (0, 1) if level == 0 else (1 << (level - 1), 1 << (level - 1))
        in_reach = np.flatnonzero(weight > low)
        if not len(in_reach):
            break
        pieces.append((in_reach, np.full(len(in_reach), low), np.full(len(in_reach), length), tb.mix(runs[in_reach] + np.uint64((level + 1) * 0xE7037ED1A0B428DB % 2**64))))
        level += 1
    if not pieces:
        return out
    item, low, length, key = (np.concatenate(x) for x in zip(*pieces))
    limit = np.full(docs, np.inf)
    has = total > 0
    limit[has] = (np.log(size) + 5) / total[has]
    active = has.copy()
    while active.any():
        alive = np.flatnonzero(active[doc[item]])
        time, draw = np.zeros(len(alive)), 0
        while len(alive):
            draw += 1
            h = tb.mix(key[alive] + np.uint64(draw * _DRAW % 2**64))
            time = time - np.log1p(-(h >> np.uint64(11)).astype(np.float64) * 2.0**-53) / (size * length[alive])
            near = time < limit[doc[item[alive]]]
            alive, time, h = alive[near], time[near], h[near]
            other = tb.mix(h ^ np.uint64(0x8EBC6AF09C88C6E3))
            height = low[alive] + ((other >> np.uint64(32)).astype(np.int64) * length[alive] >> 32)
            counts = np.flatnonzero(height < weight[item[alive]])
            component = ((other[counts] & np.uint64(0xFFFFFFFF)) * np.uint64(size) >> np.uint64(32)).astype(np.int64)
            np.minimum.at(out, (doc[item[alive[counts]]], component), time[counts])
        active &= np.isinf(out).any(axis=1)
        limit[active] *= 2
    return out


def band_keys(signature: np.ndarray) -> np.ndarray:
    """One 64-bit key for each band of each document."""
    bits = np.ascontiguousarray(signature).view(np.uint64).reshape(len(signature), BANDS, BAND_ROWS)
    key = np.full(bits.shape[:2], 0, np.uint64) + np.arange(1, BANDS + 1, dtype=np.uint64)
    for k in range(BAND_ROWS):
        key = tb.mix(key * np.uint64(0x5851F42D4C957F2D) + bits[:, :, k])
    return key


def _banded(keyed: DataFrame) -> DataFrame:
    """(node, n_runs, bands) of each text, once per input partition; texts without words have no bands."""
    schema = "node binary, n_runs long, bands array<long>"

    def run(batches):
        seen: set[bytes] = set()
        for batch in batches:
            for part in tb.text_slices(batch):
                keys = tb.column(part, "tkey").to_pylist()
                new = [i for i, k in enumerate(keys) if k not in seen and not seen.add(k)]
                if not new:
                    continue
                part = part.take(pa.array(new))
                doc, runs, weight = weighted_runs(*runs_of(*tb.flat_bytes(part)))
                keys64 = band_keys(signatures(doc, runs, weight, len(new), BANDS * BAND_ROWS)).view(np.int64)
                n = np.bincount(doc, weight, len(new)).astype(np.int64)
                lists = pa.ListArray.from_arrays(np.concatenate(([0], np.cumsum(np.where(n > 0, BANDS, 0)))).astype(np.int32), pa.array(keys64[n > 0].ravel(), pa.int64()))
                yield pa.RecordBatch.from_arrays([pa.array([keys[i][:16] for i in new], pa.binary()), pa.array(n, pa.int64()), lists.cast(pa.list_(pa.field("element", pa.int64())))], names=["node", "n_runs", "bands"])

    return keyed.select("text", "tkey").mapInArrow(run, schema)


def _told(rows: DataFrame, least: DataFrame, total: int) -> DataFrame:
    """rows joined with least (a, m, n) on a. Nodes of so many rows that they would fill a task, fewer than 2 * HUBS
    of them by their degrees, are broadcast, so that rows of a hub stay where they are."""
    hubs = F.broadcast(least.filter(F.col("n") > max(HUB_ROWS, total // HUBS)).select("a", F.col("m").alias("hub_m")))
    marked = rows.join(hubs, "a", "left")
    others = marked.filter("hub_m IS NULL").drop("hub_m").join(least.select("a", "m"), "a")
    return marked.filter("hub_m IS NOT NULL").withColumnRenamed("hub_m", "m").unionByName(others)


def components(edges: DataFrame, most_rounds: int = 40) -> DataFrame:
    """(node, root) for every node of edges (a, b): the smallest node of its connected component.

    Alternates the two star operations: every node tells its larger neighbours, then its smaller ones, of the
    smallest node it knows. Rounds grow with the logarithm of the longest path; only counts reach the driver.
    """
    state = checkpointed(edges.filter("a != b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct())
    for _ in range(most_rounds):
        total = state.count()
        both = state.select("a", "b").union(state.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.min("b").alias("m"), F.count(F.lit(1)).alias("n")).select("a", F.least("a", "m").alias("m"), "n")
        large = _told(both.filter("b > a"), least, total).select(F.col("b").alias("a"), F.col("m").alias("b"))
        small_least = large.groupBy("a").agg(F.min("b").alias("m"), F.count(F.lit(1)).alias("n"))
        small = _told(large, small_least, total).select(F.col("b").alias("a"), F.col("m").alias("b")).filter("a != b").union(small_least.select("a", F.col("m").alias("b"))).distinct()
        after = checkpointed(small)
        changed = after.exceptAll(state).limit(1).count() + state.exceptAll(after).limit(1).count()
        state = after
        if not changed:
            break
    else:
        raise RuntimeError("components did not settle")
    return state.select(F.col("a").alias("node"), F.col("b").alias("root")).union(state.select(F.col("b").alias("node"), F.col("b").alias("root")).distinct())


def head_items(owner: np.ndarray, at: np.ndarray, size: np.ndarray, least: float, *order: np.ndarray) -> np.ndarray:
    """Positions of the first items of each text in an order of items: two texts of similarity `least` share one of them."""
    by = np.lexsort((*reversed(order), owner))
    most = np.minimum(size - np.ceil(least * size - 1e-6).astype(np.int64) + 1, size)
    return by[np.arange(len(owner)) - at[owner] < most[owner]]


class Multisets:
    """The runs of a cluster's texts as sets of (run, occurrence), so that |A & B| / |A | B| is the weighted Jaccard."""

    def __init__(self, z: list[bytes]):
        parts, owners = [], []
        for first, raw in ut.group_slices(z):
            doc, runs, weight = weighted_runs(*runs_of(*ut.flat_of(raw)))
            nth = (np.arange(weight.sum()) - np.repeat(np.cumsum(weight) - weight, weight)).astype(np.uint64)
            parts.append(tb.mix(np.repeat(runs, weight) + nth * np.uint64(0x9FB21C651E98DF25)))
            owners.append(np.repeat(doc, weight) + first)
        self.items, owner = np.concatenate(parts), np.concatenate(owners)
        self.size = np.bincount(owner, minlength=len(z))
        self.at = np.concatenate(([0], np.cumsum(self.size)))
        self.owner = owner
        # Items as dense numbers, so that membership in one text is a look into a table of flags.
        values, self.code = np.unique(self.items, return_inverse=True)
        self.flag = np.zeros(len(values), bool)

    def subset(self, members: np.ndarray) -> Multisets:
        """Some of the texts; items keep their numbers."""
        part = object.__new__(Multisets)
        part.size = self.size[members]
        part.at = np.concatenate(([0], np.cumsum(part.size)))
        part.code = np.concatenate([self.code[self.at[j] : self.at[j + 1]] for j in members])
        part.owner = np.repeat(np.arange(len(members)), part.size)
        part.flag = self.flag
        return part

    def parts(self, least: float) -> np.ndarray:
        """For each text the smallest text of its part: connected by items that are in the heads of both."""
        count = np.bincount(self.code, minlength=len(self.flag))
        head = head_items(self.owner, self.at, self.size, least, count[self.code], self.code)
        code, owner = self.code[head], self.owner[head]
        label = np.arange(len(self.size))
        while True:
            low = np.full(len(self.flag), len(label))
            np.minimum.at(low, code, label[owner])
            new = label.copy()
            np.minimum.at(new, owner, low[code])
            np.minimum.at(new, label, new.copy())
            new = new[new]
            if (new == label).all():
                return label
            label = new

    def similarity(self, i: int, others: np.ndarray | None = None) -> np.ndarray:
        """Of text i to all texts, or to the given ones."""
        own = self.code[self.at[i] : self.at[i + 1]]
        self.flag[own] = True
        if others is None:
            code, owner, size = self.code, self.owner, self.size
        else:
            size = self.size[others]
            code = np.concatenate([self.code[self.at[j] : self.at[j + 1]] for j in others])
            owner = np.repeat(np.arange(len(others)), size)
        shared = np.bincount(owner[self.flag[code]], minlength=len(size))
        self.flag[own] = False
        return shared / (len(own) + size - shared)


def classes(z: list[bytes], least: float = LEAST, kept: int = KEPT_BYTES) -> np.ndarray:
    """For each text the smallest index of its class: connected by pairs of similarity `least` or more."""
    sets, n = Multisets(z), len(z)
    parent = np.arange(n)

    def root(i: int) -> int:
        while parent[i] != i:
            parent[i] = parent[parent[i]]
            i = parent[i]
        return i

    def join(a: int, b: int) -> None:
        a, b = root(a), root(b)
        parent[max(a, b)] = min(a, b)

    # A few texts are compared as they are.
    part = sets.parts(least) if n > 64 else np.zeros(n, np.int64)
    order = np.argsort(part, kind="stable")
    for members in np.split(order, np.flatnonzero(np.diff(part[order])) + 1):
        if len(members) > 1:
            _link(sets if len(members) == n else sets.subset(members), members.tolist(), least, kept, root, join)
    return np.array([root(i) for i in range(n)])


def _link(sets: Multisets, names: list[int], least: float, kept: int, root, join) -> None:
    """Join the names of similar texts: those in the balls of pivots, then pivots through members of their balls."""
    n, reach, slack = len(names), 1 - least, 1e-9
    home, pivots, far = np.full(n, -1), [], {}

    def distances(i: int) -> np.ndarray:
        d = 1 - sets.similarity(i)
        d[i] = 0
        return d

    for i in range(n):
        if home[i] >= 0:
            continue
        d = distances(i)
        inside = d <= reach + slack
        for j in np.flatnonzero(inside):
            join(names[i], names[j])
        home[inside & (home < 0)] = len(pivots)
        if (len(far) + 1) * n * 4 <= kept:
            far[len(pivots)] = d.astype(np.float32)
        pivots.append(i)
    at = np.array(pivots)
    for b in range(1, len(at)):
        db = far[b] if b in far else distances(pivots[b])
        of_b = np.flatnonzero(home == b)
        for a in np.flatnonzero(db[at[:b]] <= 3 * reach + 1e-6).tolist():
            if root(names[pivots[a]]) == root(names[pivots[b]]):
                continue
            left = np.flatnonzero((home == a) & (db <= 2 * reach + 1e-6))
            if not len(left):
                continue
            da = far[a][of_b] if a in far else 1 - sets.similarity(pivots[a], of_b)
            right = of_b[da <= 2 * reach + 1e-6]
            if not len(right):
                continue
            if len(left) > len(right):
                left, right = right, left
            for i in left:
                if (sets.similarity(int(i), right) >= least - slack).any():
                    join(names[pivots[a]], names[pivots[b]])
                    break


def _cluster(table: pa.Table) -> pa.Table:
    seen: dict[bytes, bytes] = {}
    for node, z in zip(table.column("node").to_pylist(), table.column("z").to_pylist()):
        seen[node] = z
    nodes = sorted(seen)
    got = classes([seen[x] for x in nodes])
    return pa.table({"node": pa.array(nodes, pa.binary()), "label": pa.array([nodes[i] for i in got], pa.binary())})


def _pair_distance(z: bytes, pivot: Multisets) -> float:
    """1 - J of a text and the pivot, which is alone in its multisets."""
    own = Multisets([z])
    items, other = np.sort(own.items), pivot.items
    shared = int((items[np.minimum(np.searchsorted(items, other), len(items) - 1)] == other).sum())
    return 1 - shared / (len(items) + len(other) - shared)


def _pivot_distances(rows: DataFrame) -> DataFrame:
    """rows (root, node, z, n_runs, passive, pivot, pivot_z) with d in place of pivot_z; each row is compared with its pivot alone."""
    names = ["root", "node", "z", "n_runs", "passive", "pivot"]

    def run(batches):
        known: dict[bytes, Multisets] = {}
        for b in batches:
            d = []
            for z, pivot, pivot_z in zip(*(tb.column(b, c).to_pylist() for c in ("z", "pivot", "pivot_z"))):
                if pivot not in known:
                    known.clear()
                    known[pivot] = Multisets([pivot_z])
                d.append(_pair_distance(z, known[pivot]))
            yield pa.RecordBatch.from_arrays([*(tb.column(b, c) for c in names), pa.array(d, pa.float64())], names=[*names, "d"])

    return rows.mapInArrow(run, "root binary, node binary, z binary, n_runs long, passive boolean, pivot binary, d double")


def _large(rows: DataFrame, most: int, most_runs: int, *more: Column) -> DataFrame:
    """The clusters beyond the bounds of a task: so few, at the most texts / most and runs / most_runs, that they are broadcast."""
    sums = rows.groupBy("root").agg(F.count(F.lit(1)).alias("n"), F.sum("n_runs").alias("runs"), *more)
    return sums.filter((F.col("n") > most) | (F.col("runs") > most_runs))


def _sets_by_runs(batches, limit: int = 1 << 19):
    """(slice of a batch, its multisets), each of about `limit` runs."""
    for b in batches:
        cut = np.cumsum(tb.column(b, "n_runs").to_numpy(zero_copy_only=False)) // limit
        for at in np.split(np.arange(len(cut)), np.flatnonzero(np.diff(cut)) + 1):
            if len(at):
                part = b.slice(int(at[0]), len(at))
                yield part, Multisets(tb.column(part, "z").to_pylist())


def most_frequent(counts: DataFrame, most: int) -> DataFrame:
    """The about `most` rows of counts (item, n) of the largest n, items being hashes.

    A sorted limit would send as many rows of every partition to the driver. Here a histogram over eighths of powers of two
    goes there; whole classes of it are taken from the top, and of the class that they leave no room for a share, by item.
    """
    level = F.floor(F.log2("n") * 8).cast("int")
    sizes = counts.groupBy(level.alias("level")).count().orderBy(F.desc("level")).collect()
    left, at = most, None
    for r in sizes:
        if r["count"] > left:
            at = r["level"]
            break
        left -= r["count"]
    if at is None:
        return counts
    share = left * (1 << 20) // next(r["count"] for r in sizes if r["level"] == at)
    return counts.filter((level > at) | ((level == at) & (F.pmod("item", F.lit(1 << 20)) < share)))


def _cut_by_heads(rows: DataFrame) -> DataFrame:
    """rows by parts of clusters in place of clusters; texts that are similar to no other are left out.

    The order of items is the same for all: those not frequent by their hash, then the frequent ones by their count.
    """
    spark = rows.sparkSession

    def count(batches):
        for _, sets in _sets_by_runs(batches):
            items, n = np.unique(sets.items, return_counts=True)
            yield pa.RecordBatch.from_arrays([pa.array(items.view(np.int64)), pa.array(n, pa.int64())], names=["item", "n"])

    counts = rows.mapInArrow(count, "item long, n long").groupBy("item").agg(F.sum("n").alias("n")).filter("n > 1")
    frequent = most_frequent(checkpointed(counts), FREQUENT).toArrow()
    n, known = (frequent.column(c).to_numpy() for c in ("n", "item"))
    known = known[np.lexsort((known, -n))].view(np.uint64)
    by_item = np.argsort(known)
    shared = spark.sparkContext.broadcast((known[by_item], len(known) - by_item))

    def heads(batches):
        known, rank = shared.value
        for part, sets in _sets_by_runs(batches):
            place = np.zeros(len(sets.items), np.int64)
            if len(known):
                found = np.minimum(np.searchsorted(known, sets.items), len(known) - 1)
                place = np.where(known[found] == sets.items, rank[found], 0)
            head = head_items(sets.owner, sets.at, sets.size, LEAST, place, sets.items)
            of = sets.owner[head]
            root = np.array([int.from_bytes(r[:8], "little") for r in tb.column(part, "root").to_pylist()], np.uint64)
            key = tb.mix(sets.items[head] ^ root[of]).view(np.int64)
            yield pa.RecordBatch.from_arrays([tb.column(part, "node").take(pa.array(of)), pa.array(key)], names=["node", "key"])

    found = checkpointed(rows.mapInArrow(heads, "node binary, key long"))
    hubs = found.groupBy("key").agg(F.min("node").alias("hub"), F.max("node").alias("last")).filter("hub != last").select("key", "hub")
    edges = found.join(hubs, "key").filter("node != hub").select(F.col("node").alias("a"), F.col("hub").alias("b")).distinct()
    return checkpointed(rows.drop("root").join(components(edges), "node").select("root", "node", "z", "n_runs"))


def _strip(rows: DataFrame, most: int, most_runs: int, rounds: int) -> tuple[DataFrame, DataFrame | None]:
    """(rows that are left, links found on the way).

    While a cluster is too large for a task, all its texts are compared with one of them, spread over all tasks.
    What is similar to that pivot is linked to it and done; of it, only texts that the triangle inequality lets be
    similar to one outside stay, as passive rows that become no pivots. Clusters shrink by what each pivot takes.
    """
    reach, links = 1 - LEAST + 1e-9, None
    rows = rows.withColumn("passive", F.lit(False))
    for _ in range(rounds):
        large = _large(rows, most, most_runs, F.min(F.when(~F.col("passive"), F.col("node"))).alias("pivot")).filter(F.col("pivot").isNotNull())
        if not large.limit(1).count():
            break
        large = checkpointed(large.select("root", "pivot"))
        pivots = rows.select(F.col("node").alias("pivot"), F.col("z").alias("pivot_z"), F.col("root").alias("_root")).join(F.broadcast(large), "pivot").filter("_root = root").select("root", "pivot", "pivot_z")
        measured = checkpointed(_pivot_distances(rows.join(F.broadcast(pivots), "root").select("root", "node", "z", "n_runs", "passive", "pivot", "pivot_z").sortWithinPartitions("pivot")))
        found = measured.filter((F.col("d") <= reach) & (F.col("node") != F.col("pivot"))).select(F.greatest("node", "pivot").alias("a"), F.least("node", "pivot").alias("b"))
        links = found if links is None else links.union(found)
        outside = measured.filter(F.col("d") > reach).groupBy("root").agg(F.min("d").alias("low"))
        left = measured.join(F.broadcast(outside), "root").filter(F.col("passive") | (F.col("d") >= F.col("low") - reach))
        rows = checkpointed(rows.join(F.broadcast(large), "root", "left_anti").unionByName(left.select("root", "node", "z", "n_runs", (F.col("passive") | (F.col("d") <= reach)).alias("passive"))))
    return rows.drop("passive"), links


def in_blocks(rows: DataFrame, most: int, most_runs: int) -> DataFrame:
    """rows with a part of their root for each task: what is too large is dealt into blocks of a quarter of the bounds,
    and a row goes with its block to each other block."""
    share = F.greatest(F.col("n") / most, F.col("runs") / most_runs)
    large = _large(rows, most, most_runs).select("root", F.ceil(share * 4).cast("long").alias("blocks"))
    dealt = rows.join(F.broadcast(large), "root", "left").withColumn("own", F.pmod(F.xxhash64("node"), F.coalesce("blocks", F.lit(1))))
    dealt = dealt.withColumn("other", F.explode(F.sequence(F.lit(0).cast("long"), F.coalesce("blocks", F.lit(1)) - 1))).filter("blocks IS NULL OR other != own")
    return dealt.withColumn("part", F.least("own", "other") * F.coalesce("blocks", F.lit(1)) + F.greatest("own", "other")).select("root", "part", "node", "z")


def node_classes(docs: DataFrame, most: int = MOST_IN_TASK, most_runs: int = MOST_RUNS_IN_TASK) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(keyed documents with node, the texts' n_runs, (node, label) of texts that share a class with another)."""
    checkpoint_dir(docs.sparkSession)
    keyed = ut.keyed(docs).withColumn("node", F.substring("tkey", 1, 16))
    banded = checkpointed(_banded(keyed).groupBy("node").agg(F.max("n_runs").alias("n_runs"), F.first("bands").alias("bands")))
    shared = banded.select("node", F.explode("bands").alias("band"))
    hubs = shared.groupBy("band").agg(F.min("node").alias("hub"), F.max("node").alias("last")).filter("hub != last").select("band", "hub")
    edges = shared.join(hubs, "band").filter("node != hub").select(F.col("node").alias("a"), F.col("hub").alias("b")).distinct()
    members = components(edges)
    # Each text once per input partition, compressed, however many rows repeat it.
    sent = ut.unique_texts(keyed.select(F.lit(None).cast("long").alias("doc_id"), "text", "tkey")).select(F.substring("tkey", 1, 16).alias("node"), "z")
    rows = sent.join(members, "node").select("root", "node", "z")
    large = _large(members.join(banded, "node"), most, most_runs).select("root")
    if large.limit(1).count():
        large = F.broadcast(checkpointed(large))
        rows = checkpointed(rows.dropDuplicates(["node"]).join(banded.select("node", "n_runs"), "node").select("root", "node", "z", "n_runs"))
        parts, links = _strip(_cut_by_heads(rows.join(large, "root", "left_semi")), most, most_runs, 12)
        rows = in_blocks(parts.unionByName(rows.join(large, "root", "left_anti")), most, most_runs)
        labels = rows.groupBy("root", "part").applyInArrow(_cluster, "node binary, label binary")
        both = labels.select(F.greatest("node", "label").alias("a"), F.least("node", "label").alias("b"))
        both = both if links is None else both.union(links)
        labels = components(both).select("node", F.col("root").alias("label"))
    else:
        labels = rows.groupBy("root").applyInArrow(_cluster, "node binary, label binary")
    return keyed, banded.select("node", "n_runs"), labels


def near_duplicates(docs: DataFrame, most: int = MOST_IN_TASK) -> DataFrame:
    """doc_id, class_id (smallest doc_id of its class) and n_runs, one row per document."""
    keyed, sizes, labels = node_classes(docs, most)
    nodes = keyed.groupBy("node").agg(F.min("doc_id").alias("first_doc"))
    known = nodes.join(sizes, "node").join(labels, "node", "left").withColumn("label", F.coalesce("label", "node"))
    known = checkpointed(known)
    named = known.groupBy("label").agg(F.min("first_doc").alias("class_id"))
    return keyed.select("doc_id", "node").join(known.join(named, "label").select("node", "class_id", "n_runs"), "node").select("doc_id", "class_id", "n_runs")


def one_of_each(docs: DataFrame) -> DataFrame:
    """The rows of docs that stand for their class: the smallest doc_id, one row; columns as given, whatever their names."""
    node = F.substring(F.unhex(F.sha2(F.coalesce(F.col("text"), F.lit("")), 256)), 1, 16)
    # The row travels as one column, so that none of its names can meet one of ours.
    marked = docs.select(F.struct("*").alias("row"), node.alias("node"), F.col("doc_id").cast("long").alias("id"))
    _, _, labels = node_classes(docs)
    first = marked.groupBy("node").agg(F.min(F.struct(F.col("id").isNull().alias("none"), F.col("id"))).alias("first"))
    labelled = first.join(labels, "node", "left").withColumn("label", F.coalesce("label", "node"))
    chosen = labelled.groupBy("label").agg(F.min(F.struct("first", "node")).alias("c")).select(F.col("c.node").alias("node"), F.coalesce(F.col("c.first.id").cast("string"), F.lit("")).alias("k"))
    # Rows that repeat both doc_id and text are one document; one of them stays.
    rows = marked.select("row", "node", F.coalesce(F.col("id").cast("string"), F.lit("")).alias("k"))
    return rows.dropDuplicates(["node", "k"]).join(chosen, ["node", "k"], "left_semi").select("row.*")
