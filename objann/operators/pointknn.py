"""Point nearest-neighbour baselines and their fusion by rank votes."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from objann.operators.gamma import NO_QUERY, _sides, in_batches
from objann.operators.hashing import Projections
from objann.operators.kernel import CloseAt, QuerySet, bit_places, blocks
from objann.sources.families import Family, object_sizes

KNN = ["q_obj", "q_id", "rank", "object_id", "point_id", "sq_dist"]
FOUND = "q_obj long, q_id long, object_id long, point_id long, sq_dist long"


LISTED = 1 << 21  # entries of all lists that a task holds


def linear_knn(points: DataFrame, queries: DataFrame, k_prime: int) -> DataFrame:
    """Exact: a task keeps its k' best for each query point over all its blocks, the rest is one window.  Order: distance, object, point.

    A block gives a list only what is no farther than the list's last entry.  Tasks are few, as each sends whole lists.
    """

    def scan(q: QuerySet | None) -> DataFrame:
        q, source = (q, points) if q else (NO_QUERY, points.where("false"))

        def best(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            held = Nearest(q.vec, k_prime) if len(q.vec) else None
            waiting, n = [], 0
            for block in blocks(batches, 1):
                waiting.append(block)
                n += len(block[0])
                if n * block[2].shape[1] >= HELD:
                    held.add(*map(np.concatenate, zip(*waiting)))
                    waiting, n = [], 0
            if waiting:
                held.add(*map(np.concatenate, zip(*waiting)))
            if held is not None:
                for rows, d, obj, pid in held.lists():
                    yield pa.RecordBatch.from_arrays([pa.array(x) for x in (q.q_obj[rows], q.q_id[rows], obj, pid, d)], ["q_obj", "q_id", "object_id", "point_id", "sq_dist"])

        near = source.select("object_id", "point_id", "vec").coalesce(max(1, points.sparkSession.sparkContext.defaultParallelism)).mapInArrow(best, FOUND)
        ranked = near.withColumn("rank", F.row_number().over(Window.partitionBy("q_obj", "q_id").orderBy("sq_dist", "object_id", "point_id")))
        return ranked.where(F.col("rank") <= k_prime).select(*KNN)

    return in_batches(queries, scan, max(1, LISTED // k_prime))


HELD = 1 << 21  # components of the points that meet all query points at once
LEAF = 64  # query points, near each other, that go through the points together


def leaves(x: np.ndarray, most: int) -> list[np.ndarray]:
    """Rows in groups of at most ``most`` that lie near each other: halves along the widest component, again and again."""
    out, todo = [], [np.arange(len(x))]
    while todo:
        rows = todo.pop()
        if len(rows) <= most:
            out.append(rows)
            continue
        own = x[rows]
        order = np.argpartition(own[:, (own.max(axis=0) - own.min(axis=0)).argmax()], len(rows) // 2)
        todo += [rows[order[: len(rows) // 2]], rows[order[len(rows) // 2 :]]]
    return out


class Nearest:
    """The k nearest points of each query point so far, by (distance, object, point).

    Query points and points are grouped by place.  A group of query points meets groups of points from the nearest
    on, as far as the boxes of both can be no farther apart than the last entries of its lists.
    """

    def __init__(self, q: np.ndarray, k: int):
        self.k, self.groups = k, leaves(q, LEAF)
        self.boxes = [(q[g].min(axis=0), q[g].max(axis=0)) for g in self.groups]
        self.sides = [_sides(q[g], True) for g in self.groups]
        # by group: row in it, distance, object, point; and the last distance of each list
        self.held = [(np.zeros(0, np.int64),) * 4 for _ in self.groups]
        self.last = [np.full(len(g), np.inf) for g in self.groups]

    def add(self, obj: np.ndarray, pid: np.ndarray, vec: np.ndarray) -> None:
        parts = leaves(vec, 256)
        low, high = (np.array([f(vec[p], axis=0) for p in parts]) for f in (np.min, np.max))
        order = np.concatenate(parts)
        obj, pid, x = obj[order], pid[order], _sides(vec[order], False)
        begins = np.append(0, np.cumsum([len(p) for p in parts]))
        for g, (below, above) in enumerate(self.boxes):
            gap = np.maximum(0, np.maximum(low - above, below - high)).astype(np.float64)
            apart = (gap * gap).sum(axis=1)  # whole numbers, as the distances
            near = np.argsort(apart, kind="stable")
            at, step = 0, 1 + self.k // 64
            while at < len(near) and apart[near[at]] <= self.last[g].max():
                some = near[at : at + step]
                at, step = at + step, min(32, 2 * step)
                some = some[apart[some] <= self.last[g].max()]
                rows = np.concatenate([np.arange(begins[p], begins[p + 1]) for p in some])
                d = self.sides[g] @ x[rows].T
                within = d <= self.last[g][:, None]
                if len(rows) > self.k and np.count_nonzero(within) > 2 * self.k * len(d):
                    within &= d <= np.partition(d, self.k - 1, axis=1)[:, [self.k - 1]]
                mine, cols = np.nonzero(within)
                if len(mine):
                    self._merge(g, mine, d[mine, cols].astype(np.int64), obj[rows[cols]], pid[rows[cols]])

    def _merge(self, g: int, *more: np.ndarray) -> None:
        rows, d, obj, pid = (np.concatenate(c) for c in zip(self.held[g], more))
        order = np.lexsort((pid, obj, d, rows))
        rows = rows[order]
        place = np.arange(len(rows)) - np.searchsorted(rows, rows)
        keep = place < self.k
        order, rows, full = order[keep], rows[keep], rows[place == self.k - 1]
        self.held[g] = rows, d[order], obj[order], pid[order]
        self.last[g][full] = d[order][place[keep] == self.k - 1]

    def lists(self) -> Iterator[tuple[np.ndarray, ...]]:
        for group, (rows, d, obj, pid) in zip(self.groups, self.held):
            yield group[rows], d, obj, pid


def hashed_knn(points: DataFrame, queries: DataFrame, family: Family, proj: Projections, k_prime: int, beta_points: float | None = None) -> DataFrame:
    """Static-bucket or query-centred point search: collision counting with a stop for each query point.

    Stops at k' + beta n close points (beta 100 / n), or at the end of a level with k' of them within
    c times the radius; ranks what is close by then by true distance.  One pass counts close points
    by query point and event, which gives the stops; a second keeps each block's k' best up to them.  So what is
    moved is bounded by events and by k', not by the close pairs.  A block goes on to no further level
    once it alone stops all its query points.
    """
    return hashed_lists(points, queries, family, proj, (k_prime,), beta_points).select(*KNN)


def hashed_lists(points: DataFrame, queries: DataFrame, family: Family, proj: Projections, k_primes: tuple[int, ...], beta_points: float | None = None) -> DataFrame:
    """``hashed_knn`` for several k' in the same two passes, with k_prime."""
    n = points.count() if beta_points is not None else 0
    more = 100 if beta_points is None else math.ceil(beta_points * n)
    return in_batches(queries, lambda q: _hashed(points if q else points.where("false"), q or NO_QUERY, family, proj, sorted(k_primes), more))


def _hashed(points: DataFrame, q: QuerySet, family: Family, proj: Projections, k_primes: list[int], more: int) -> DataFrame:
    m, top = proj.params.m, proj.levels
    hashed = proj.hashes(q.vec) if len(q.q_obj) else np.zeros((0, m), np.int64)
    radii = np.array(proj.squared_radii(family.unit, proj.params.c))
    last = top * (m + 1) + m

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        # the largest k' stops last
        enough = k_primes[-1] + more
        near, stops = ClosePairs(q.vec, hashed, proj), Stops(len(hashed), enough, k_primes[-1], last)
        for _, _, vec in _gathered(batches, near.most):
            block = near.block(vec)
            stops.lower(block.reached(stops.at, enough))
            rows, _, keys, d = block.pairs(stops.at)
            # a pair counts at its event, and from the end of the first level that holds both its event and its distance
            level = np.maximum(keys // (m + 1), np.searchsorted(radii, d))
            stops.add(rows, keys, level * (m + 1) + m)
        for slot, kind, key, n in stops.counts():
            yield pa.RecordBatch.from_arrays([pa.array(x.astype(np.int64)) for x in (slot, kind, key, n)], ["slot", "kind", "key", "n"])

    source = points.select("object_id", "point_id", "vec")
    counts = source.mapInArrow(count, "slot long, kind long, key long, n long").groupBy("slot", "kind", "key").agg(F.sum("n").alias("n"))
    upto = F.sum("n").over(Window.partitionBy("slot", "kind").orderBy("key"))
    first = [F.min(F.when(F.col("upto") >= F.when(F.col("kind") == 0, k + more).otherwise(k), F.col("key"))) for k in k_primes]
    stop = np.full((len(k_primes), len(hashed)), last, np.int64)
    for slot, *keys in counts.withColumn("upto", upto).groupBy("slot").agg(*first).collect():  # a number for each query point of the batch and k'
        stop[:, slot] = [last if key is None else key for key in keys]

    def best(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        near = ClosePairs(q.vec, hashed, proj)
        held = [[np.zeros(0, np.int64)] * 4 for _ in k_primes]  # row, distance, point, object: the k' best of each row so far
        for obj, pid, vec in _gathered(batches, near.most):
            rows, cols, keys, d = near.block(vec).pairs(stop.max(axis=0))
            for i, k in enumerate(k_primes):
                fine = keys <= stop[i][rows]
                new = rows[fine], d[fine], pid[cols[fine]], obj[cols[fine]]
                own = [np.concatenate(c) for c in zip(held[i], new)]
                order = np.lexsort((own[3], own[2], own[1], own[0]))
                order = order[np.arange(len(order)) - np.searchsorted(own[0][order], own[0][order]) < k]
                held[i] = [c[order] for c in own]
        for k, (rows, d, own, ids) in zip(k_primes, held):
            yield pa.RecordBatch.from_arrays([pa.array(x) for x in (np.full(len(rows), k), q.q_obj[rows], q.q_id[rows], ids, own, d)], ["k_prime", "q_obj", "q_id", "object_id", "point_id", "sq_dist"])

    # tasks are few, as each sends whole lists
    found = source.coalesce(max(1, points.sparkSession.sparkContext.defaultParallelism)).mapInArrow(best, f"k_prime long, {FOUND}")
    ranked = found.withColumn("rank", F.row_number().over(Window.partitionBy("k_prime", "q_obj", "q_id").orderBy("sq_dist", "point_id", "object_id")))
    return ranked.where(F.col("rank") <= F.col("k_prime")).select("k_prime", *KNN)


def _gathered(batches: Iterator[pa.RecordBatch], most: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """``blocks`` of as many points as ``most``, but for the last one."""
    waiting, n = [], 0
    for block in blocks(batches, 1, most):
        waiting.append(block)
        n += len(block[0])
        if n >= most:
            yield tuple(map(np.concatenate, zip(*waiting)))
            waiting, n = [], 0
    if waiting:
        yield tuple(map(np.concatenate, zip(*waiting)))


class Stops:
    """By query point: how many close pairs a task met by event, and the event after which its search does not go on for what
    the task alone has met."""

    def __init__(self, n: int, enough: int, k_prime: int, last: int):
        self.at, self.wanted, self.last = np.full(n, last, np.int64), (enough, k_prime), last
        self.held = [(np.zeros(0, np.int64),) * 3 for _ in self.wanted]  # row, key, pairs

    def lower(self, at: np.ndarray) -> None:
        self.at = np.minimum(self.at, at)

    def add(self, rows: np.ndarray, *keys: np.ndarray) -> None:
        for kind, key in enumerate(keys):
            own, known, n = (np.concatenate(c) for c in zip(self.held[kind], (rows, key, np.ones(len(rows), np.int64))))
            fine = known <= self.at[own]
            codes, place = np.unique(own[fine] * (self.last + 1) + known[fine], return_inverse=True)
            n = np.bincount(place, n[fine], len(codes)).astype(np.int64)
            own, known = codes // (self.last + 1), codes % (self.last + 1)
            total = np.cumsum(n)
            upto = total - (total - n)[np.searchsorted(own, own)]
            enough = np.flatnonzero(upto >= self.wanted[kind])
            some, first = np.unique(own[enough], return_index=True)
            self.at[some] = np.minimum(self.at[some], known[enough[first]])
            self.held[kind] = own, known, n

    def counts(self) -> Iterator[tuple[np.ndarray, ...]]:
        for kind, (own, known, n) in enumerate(self.held):
            fine = known <= self.at[own]
            yield own[fine], np.full(int(fine.sum()), kind), known[fine], n[fine]


STEP = 8  # projections between the events at which query points are counted together


class ClosePairs:
    """Pairs of query points and points that are close by an event of each query point, with their own events."""

    def __init__(self, q: np.ndarray, hashed: np.ndarray, proj: Projections):
        self.q, self.hashed, self.proj, self.limits = q, hashed, proj, proj.limits()
        self.cells = [hashed // size for size in self.limits] if proj.static else []
        self.close = CloseAt(hashed, np.zeros(1, np.int64), proj.limits(), proj.params.m, proj.params.l, proj.static)
        self.most = 1 << 14  # points of a block

    def block(self, vec: np.ndarray) -> "ClosePairsOfBlock":
        return ClosePairsOfBlock(self, vec)


class ClosePairsOfBlock:
    def __init__(self, near: ClosePairs, vec: np.ndarray):
        self.near, self.vec, self.hashes = near, vec, near.proj.hashes(vec)
        self.bits = near.close.block(self.hashes, None, np.zeros(1, np.int64), np.array([len(vec)]))
        self.cells: dict[int, np.ndarray] = {}

    def reached(self, stop: np.ndarray, enough: int) -> np.ndarray:
        """The first events at which this block alone has enough close pairs of query points that are not stopped before the last event."""
        m, last = self.near.proj.params.m, self.near.proj.levels * (self.near.proj.params.m + 1) + self.near.proj.params.m
        rows = np.flatnonzero(stop == last)
        out = stop.copy()
        if len(self.vec) < enough or not len(rows):
            return out
        todo = [(rows, -1, last)]  # too few at the first event; at the second, or none needed
        while todo:
            rows, low, high = todo.pop()
            if high - low <= STEP:
                out[rows] = high
                continue
            level = max(low, high // (m + 1) * (m + 1) - 1)  # the end of the level before, then halves
            middle = level if low < level < high else (low + high) // 2
            n = np.zeros(len(rows), np.int64)
            for a, b, bits in self.bits.close_to(rows, middle):
                n[a:b] = np.bitwise_count(bits).sum(axis=1, dtype=np.int64)
            for some, ends in ((rows[n >= enough], (low, middle)), (rows[n < enough], (middle, high))):
                if len(some):
                    todo.append((some, *ends))
        return out

    def pairs(self, stop: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """(query row, point row, event, squared distance) of the pairs that are close by their query point's event."""
        m = self.near.proj.params.m
        level, upto = stop // (m + 1), stop % (m + 1)
        counted = level * (m + 1) + np.minimum(m, -(-upto // STEP) * STEP)
        found = []
        for key in np.unique(counted).tolist():
            rows = np.flatnonzero(counted == key)
            for a, _, bits in self.bits.close_to(rows, key):
                own, cols = bit_places(bits)
                for x in range(0, len(own), MOST):
                    mine, other = rows[a + own[x : x + MOST]], cols[x : x + MOST]
                    events = self.events(mine, other, key // (m + 1))
                    fine = events <= stop[mine]
                    mine, other = mine[fine], other[fine]
                    diff = self.near.q[mine] - self.vec[other]
                    found.append((mine, other, events[fine], (diff * diff).sum(axis=1)))
        return tuple(np.concatenate(c) for c in zip(*found)) if found else (np.zeros(0, np.int64),) * 4

    def events(self, rows: np.ndarray, cols: np.ndarray, level: int) -> np.ndarray:
        """The event of each pair: of its projections' first collisions in order, the one that makes it close; none is after ``level``."""
        m, limits = self.near.proj.params.m, self.near.limits
        after = np.zeros((len(rows), m), np.int32)  # levels at which there is no collision
        apart = None if self.near.proj.static else 2 * np.abs(self.near.hashed[rows] - self.hashes[cols])
        for t in range(level + 1):
            if apart is not None:
                after += apart > limits[t]
                continue
            if t not in self.cells:
                self.cells[t] = self.hashes // limits[t]
            after += self.near.cells[t][rows] != self.cells[t][cols]
        codes = after * np.int32(m + 1) + np.arange(1, m + 1, dtype=np.int32)
        codes.partition(self.near.proj.params.l - 1, axis=1)
        return codes[:, self.near.proj.params.l - 1].astype(np.int64)


MOST = 1 << 15  # pairs whose events are worked out at once


def borda(knn: DataFrame, k_prime: int, k: int, scheme: str = "positional", points: DataFrame | None = None) -> DataFrame:
    """(q_obj, rank, object_id, score): objects by the ranks of their points in the lists.

    positional: sum of k' + 1 - rank; votes: list entries; best_rank: each list's best entry only;
    size_normalised: positional over the object's points (needs ``points``).
    """
    weight = F.lit(k_prime + 1) - F.col("rank")
    if scheme == "votes":
        scored = knn.groupBy("q_obj", "object_id").agg(F.count("*").cast("double").alias("score"))
    elif scheme == "best_rank":
        scored = knn.groupBy("q_obj", "q_id", "object_id").agg(F.max(weight).alias("w")).groupBy("q_obj", "object_id").agg(F.sum("w").cast("double").alias("score"))
    else:
        scored = knn.groupBy("q_obj", "object_id").agg(F.sum(weight).cast("double").alias("score"))
        if scheme == "size_normalised":
            scored = scored.join(object_sizes(points), "object_id").select("q_obj", "object_id", (F.col("score") / F.col("n_points")).alias("score"))
    ranked = scored.withColumn("rank", F.row_number().over(Window.partitionBy("q_obj").orderBy(F.desc("score"), "object_id")))
    return ranked.where(F.col("rank") <= k).select("q_obj", "rank", "object_id", "score")
