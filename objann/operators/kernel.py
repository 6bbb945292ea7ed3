"""Block kernels: query points on the driver against blocks of stored points, exact in integers."""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

BATCH_POINTS = 20_000  # query points that go to every task at once; one object of more is a batch of its own
BLOCK = 1 << 22  # cells of one distance block
CELLS = 1 << 23  # pairs of one collision block


@dataclass(frozen=True)
class QuerySet:
    """One batch of query points, in the order of their objects and ids."""

    q_obj: np.ndarray
    q_id: np.ndarray
    vec: np.ndarray

    def __post_init__(self):
        check_range(self.vec)

    def objects(self) -> list[tuple[int, int, int]]:
        """(query object, first row, end row)."""
        ids, first = np.unique(self.q_obj, return_index=True)
        return list(zip(ids.tolist(), first.tolist(), [*first[1:].tolist(), len(self.q_obj)]))

    def sizes(self) -> dict[int, int]:
        return {o: b - a for o, a, b in self.objects()}


def query_batches(queries: DataFrame, most: int = BATCH_POINTS) -> Iterator[QuerySet]:
    """Whole query objects in batches of at most ``most`` points; what a driver and a task hold is one batch."""
    sizes = sorted(tuple(r) for r in queries.groupBy("object_id").count().collect())  # one row for each query object
    names, held = [], 0
    for name, size in [*sizes, (None, 0)]:
        if names and (name is None or held + size > most):
            rows = queries.where(F.col("object_id").isin(names)).select("object_id", "point_id", "vec").toArrow()
            obj, pid = rows.column(0).to_numpy(), rows.column(1).to_numpy()
            flat = rows.column(2).combine_chunks().flatten().to_numpy(zero_copy_only=False).astype(np.int64)
            order = np.lexsort((pid, obj))
            yield QuerySet(obj[order], pid[order], flat.reshape(len(obj), -1)[order])
            names, held = [], 0
        if name is not None:
            names.append(name)
            held += size


def side_by_side(q: QuerySet, most: int = 8) -> QuerySet:
    """The same points, those of an object ordered so that near ones follow each other: halves along the widest component, down to ``most`` points."""
    order, todo = [], [np.arange(a, b) for _, a, b in reversed(q.objects())]
    while todo:
        rows = todo.pop()
        if len(rows) <= most:
            order.append(rows)
            continue
        vec = q.vec[rows]
        rows = rows[np.argsort(vec[:, np.argmax(vec.max(axis=0) - vec.min(axis=0))], kind="stable")]
        todo += [rows[len(rows) // 2 :], rows[: len(rows) // 2]]
    order = np.concatenate([*order, np.zeros(0, np.int64)])
    return QuerySet(q.q_obj[order], q.q_id[order], q.vec[order])


def check_range(vec: np.ndarray) -> None:
    """Products and sums must be exact in double precision."""
    if len(vec) and 4 * vec.shape[1] * int(np.abs(vec).max()) ** 2 >= 1 << 53:
        raise ValueError("vectors exceed the exact range")


def block_sq_dist(q: np.ndarray, x: np.ndarray) -> np.ndarray:
    a, b = q.astype(np.float64), x.astype(np.float64)
    out = a @ (-2 * b.T)
    out += (a * a).sum(1)[:, None]
    out += (b * b).sum(1)[None, :]
    return out.astype(np.int64)


def blocks(batches: Iterator[pa.RecordBatch], n_query: int, cells: int = BLOCK):
    """(object ids, point ids, vectors) in blocks that bound n_query x rows."""
    step = max(1, cells // max(1, n_query))
    for batch in batches:
        if not batch.num_rows:
            continue
        vec = np.array(batch.column(2).flatten().to_numpy(zero_copy_only=False), dtype=np.int64).reshape(batch.num_rows, -1)
        check_range(vec)
        obj, pid = batch.column(0).to_numpy(), batch.column(1).to_numpy()
        for a in range(0, len(obj), step):
            yield obj[a : a + step], pid[a : a + step], vec[a : a + step]


def run_lengths(values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(first place, end) of each run of equal values."""
    first = np.flatnonzero(np.concatenate([[True], values[1:] != values[:-1]])) if len(values) else np.zeros(0, np.int64)
    return first, np.concatenate([first[1:], [len(values)]]).astype(np.int64)


class Collisions:
    """Which stored points of a block collide with which query points, as bit matrices by level and projection.

    ``hx`` holds the block's hashes, one row for a bit position; ``present`` tells which of them are
    known.  Query points of one cell share a bit row, so a cell is compared with the block once.
    """

    def __init__(self, hq: np.ndarray, hx: np.ndarray, present: np.ndarray | None, limits: list[int], static: bool):
        pad = -len(hx) % 64
        self.hq, self.static, self.limits = hq, static, limits
        self.hx = np.concatenate([hx, np.zeros((pad, hx.shape[1]), hx.dtype)]) if pad else hx
        known = np.ones(hx.shape, bool) if present is None else present
        self.known = np.concatenate([known, np.zeros((pad, hx.shape[1]), bool)]) if pad else known
        self.words = len(self.hx) // 64

    def bits(self, level: int, j: int) -> np.ndarray:
        """(query points, words) of 64 points each."""
        x, q = self.hx[:, j], self.hq[:, j]
        if self.static:
            size = self.limits[level]
            cells, own = np.unique(q // size, return_inverse=True)
            hit = cells[:, None] == (x // size)[None, :]
        else:
            values, own = np.unique(q, return_inverse=True)
            hit = 2 * np.abs(values[:, None] - x[None, :]) <= self.limits[level]
        hit &= self.known[:, j][None, :]
        return np.packbits(hit, axis=1).view(np.uint64)[own]


def close_events(pairs: Collisions, m: int, threshold: int, levels: range, mode: str = "carry", upto: int | None = None) -> Iterator[tuple[int, int, np.ndarray]]:
    """(turn, key, bits): the pairs that have ``threshold`` collisions at each event key level * (m + 1) + projection.

    Counts are kept bit by bit for 64 pairs a word, and begin so far below a power of two that the
    threshold overflows them: the carry out of the top bit is the set of pairs that reach it.
    carry: counts go on over levels.  For levels that begin after 0, all that was reached before
    comes as one event at the end of the level before.  restart: counts begin anew at each level,
    so a pair has an event in each (turn: the level).  The last level may end after ``upto`` projections.
    """
    planes = max(1, threshold.bit_length())
    start = (1 << planes) - threshold
    shape = (len(pairs.hq), pairs.words)

    def fresh():
        full = np.uint64(0xFFFFFFFFFFFFFFFF)
        return [np.full(shape, full if start >> p & 1 else 0, np.uint64) for p in range(planes)], np.zeros(shape, np.uint64)

    def add(counts, done, bits):
        carry = bits & ~done
        for plane in counts:
            if not carry.any():
                return None
            after = plane & carry
            np.bitwise_xor(plane, carry, out=plane)
            carry = after
        if not carry.any():
            return None
        done |= carry
        return carry

    if threshold > m:
        return
    counts, done = fresh()
    if mode == "carry" and levels.start > 0:
        for j in range(m):
            add(counts, done, pairs.bits(levels.start - 1, j))
        if done.any():
            yield -1, (levels.start - 1) * (m + 1) + m, done.copy()
    for t in levels:
        if mode == "restart":
            counts, done = fresh()
        for j in range(m if upto is None or t < levels.stop - 1 else upto):
            bits = pairs.bits(t, j)
            if mode == "carry" and t > 0:
                bits &= ~pairs.bits(t - 1, j)
            if (reached := add(counts, done, bits)) is not None:
                yield -1 if mode == "carry" else t, t * (m + 1) + j + 1, reached


def bit_places(bits: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(query row, point row) of all set bits."""
    words = np.flatnonzero(bits)
    own, places = np.nonzero(np.unpackbits(np.ascontiguousarray(bits).ravel()[words].view(np.uint8).reshape(-1, 8), axis=1))
    return words[own] // bits.shape[1], words[own] % bits.shape[1] * 64 + places


WORDS = 1 << 15  # words of one bit matrix of ``CloseAt``: few, so that a core's cache helps, and enough for one call on them


class CloseAt:
    """How many pairs of each (query object, object) are close at given events, under carried counts of static buckets or windows.

    ``close_events`` goes through all events up to one; here the collisions at one event are added up by themselves:
    those of its level up to its projection, those of the level below for the projections after it.  A static cell that all query
    points share is added once for a block and event, one that those of a few rows share once for these rows.
    """

    def __init__(self, hq: np.ndarray, first: np.ndarray, limits: list[int], m: int, threshold: int, static: bool = True):
        self.hq, self.limits, self.m, self.threshold, self.static = hq, limits, m, threshold, static
        self.groups = list(zip(first.tolist(), [*first[1:].tolist(), len(hq)]))
        self._cells: dict[tuple[int, int], tuple[np.ndarray, np.ndarray]] = {}

    def _of(self, level: int, j: int) -> tuple[np.ndarray, np.ndarray]:
        if (level, j) not in self._cells:
            cells, own = np.unique(self.hq[:, j] // self.limits[level], return_inverse=True)
            self._cells[level, j] = cells, own.astype(np.int32)
        return self._cells[level, j]

    def block(self, hashes: np.ndarray, present: np.ndarray | None, begins: np.ndarray, ends: np.ndarray) -> "CloseBlock":
        return CloseBlock(self, hashes, present, begins, ends)


class CloseBlock:
    """A block of points for ``CloseAt``; ``begins`` and ``ends`` are the objects' places, in whole bytes of bits."""

    def __init__(self, at: CloseAt, hashes: np.ndarray, present: np.ndarray | None, begins: np.ndarray, ends: np.ndarray):
        self.at, self.begins, self.ends, self.whole = at, begins, ends, None
        pad = -len(hashes) % 64
        known = np.ones(hashes.shape, bool) if present is None else present
        self.hx = np.ascontiguousarray(np.pad(hashes, ((0, pad), (0, 0))).T)
        self.known = np.ascontiguousarray(np.pad(known, ((0, pad), (0, 0))).T)
        self.words = self.hx.shape[1] // 64
        self._bits: dict[tuple[int, int], np.ndarray] = {}
        self._shared: dict[int, tuple] = {}

    def _of(self, level: int, j: int) -> np.ndarray:
        """Bits of the points by cell of the query points, for one projection."""
        if self.whole is not None:
            own = self.whole._of(level, j).view(np.uint8)
            out = np.zeros((len(own), 8 * self.words), np.uint8)
            np.take(own, self.bytes, axis=1, out=out[:, : len(self.bytes)], mode="clip")
            return out.view(np.uint64)
        if (level, j) not in self._bits:
            cells, _ = self.at._of(level, j)
            x = self.hx[j] // self.at.limits[level]
            hit = (cells[:, None] == x[None, :]) & self.known[j][None, :]
            self._bits[level, j] = np.packbits(hit, axis=1).view(np.uint64)
        return self._bits[level, j]

    def some(self, objects: np.ndarray) -> "CloseBlock":
        """The same block with some of its objects only: whole bytes of its bits."""
        out = object.__new__(CloseBlock)
        sizes = (self.ends[objects] - self.begins[objects]) // 8
        ends = np.cumsum(sizes)
        places = np.repeat(self.begins[objects] // 8 - (ends - sizes), sizes) + np.arange(sizes.sum())
        out.at, out.whole = self.at, self.whole or self
        out.bytes = places if self.whole is None else self.bytes[places]
        out.begins, out.ends, out.words, out._shared = (ends - sizes) * 8, ends * 8, -(-len(places) // 8), {}
        return out

    def events_of_level(self, group: int, key: int) -> Iterator[tuple[int, np.ndarray]]:
        """(event, pairs by object): for each event of a level up to ``key`` at which pairs with the points of a query object
        become close, how many; those that are close before the level come first, at the end of the level before.  Static buckets.
        """
        a, b = self.at.groups[group]
        m, threshold = self.at.m, self.at.threshold
        level, upto = divmod(key, m + 1)
        planes = max(1, threshold.bit_length())
        states, step = [], max(1, WORDS // max(1, self.words))
        for r in range(a, b, step):
            e = min(b, r + step)
            rows = ((self._of(level - 1, j), self.at._of(level - 1, j)[1][r:e]) for j in range(m if level else 0))
            states.append((slice(r, e), *close_bits(rows, (e - r, self.words), planes, (1 << planes) - threshold)))
        if level:
            yield level * (m + 1) - 1, sum((self.by_object(done) for _, _, done in states), np.zeros(len(self.begins), np.int64))
        for j in range(upto):
            bits, (_, own) = self._of(level, j), self.at._of(level, j)
            more = []
            for rows, counts, done in states:
                carry = bits[own[rows]]
                if level:
                    carry &= ~self._of(level - 1, j)[self.at._of(level - 1, j)[1][rows]]
                carry &= ~done
                for plane in counts:
                    if not carry.any():
                        break
                    after = plane & carry
                    np.bitwise_xor(plane, carry, out=plane)
                    carry = after
                if carry.any():
                    np.bitwise_or(done, carry, out=done)
                    more.append(self.by_object(carry))
            if more:
                yield level * (m + 1) + j + 1, sum(more)

    def close(self, group: int, key: int) -> Iterator[tuple[int, int, np.ndarray]]:
        """(first row, end, bits): the pairs with the points of a query object that are close at event ``key``; none if none can be."""
        a, b = self.at.groups[group]
        yield from self.close_to(np.arange(a, b), key)

    def close_to(self, rows: np.ndarray, key: int) -> Iterator[tuple[int, int, np.ndarray]]:
        """``close`` for any rows of the query points; first row and end count among these."""
        m, threshold, words = self.at.m, self.at.threshold, self.words
        level, upto = divmod(key, m + 1)
        used = [(level if j < upto else level - 1, j) for j in range(m) if j < upto or level > 0]
        if len(used) < threshold:
            return
        planes, start = max(1, threshold.bit_length()), (1 << max(1, threshold.bit_length())) - threshold
        step = max(1, WORDS // max(1, words))
        if not self.at.static:
            for r in range(0, len(rows), step):
                some = rows[r : r + step]
                yield r, r + len(some), close_bits(((self._window(t, j, some), np.arange(len(some))) for t, j in used), (len(some), words), planes, start)[1]
            return
        first, one = np.zeros(1, np.int64), (1, words)
        if key not in self._shared:
            cells = [len(self.at._of(*u)[0]) for u in used]
            common = close_bits(((self._of(*u), first) for u, n in zip(used, cells) if n == 1), one, planes, start)
            left = [u for u, n in zip(used, cells) if n > 1]
            self._shared = {key: (common, [self._of(*u) for u in left], np.stack([self.at._of(*u)[1] for u in left]) if left else np.zeros((0, len(self.at.hq)), np.int32))}
        common, bits, own = self._shared[key]
        for r in range(0, len(rows), step):
            cells = own[:, rows[r : r + step]]
            same = (cells == cells[:, :1]).all(axis=1) if cells.shape[1] > 1 else np.zeros(len(bits), bool)
            before = close_bits(((bits[i], cells[i, :1]) for i in np.flatnonzero(same)), one, planes, start, common)
            yield r, r + cells.shape[1], close_bits(((bits[i], cells[i]) for i in np.flatnonzero(~same)), (cells.shape[1], words), planes, start, before)[1]

    def _window(self, level: int, j: int, rows: np.ndarray) -> np.ndarray:
        """Bits of the points in the windows of some query points, for one projection."""
        reach = self.at.limits[level] // 2
        hit = (self.hx[j][None, :] - (self.at.hq[rows, j] - reach)[:, None]).view(np.uint64) <= np.uint64(2 * reach)
        hit &= self.known[j][None, :]
        return np.packbits(hit, axis=1).view(np.uint64)

    def by_object(self, bits: np.ndarray) -> np.ndarray:
        """Bits that are set, by object."""
        kind = np.uint8 if 8 * len(bits) < 1 << 8 else np.uint16 if 8 * len(bits) < 1 << 16 else np.int64  # the least that holds a byte's count
        ones = np.bitwise_count(bits.view(np.uint8)).sum(axis=0, dtype=kind).astype(np.int64)
        return np.add.reduceat(np.append(ones, 0), np.stack([self.begins, self.ends], axis=1).ravel() // 8)[::2]

    def counts(self, group: int, key: int) -> np.ndarray:
        """By object: the pairs with the points of a query object that are close at event ``key``."""
        out = np.zeros(len(self.begins), np.int64)
        for _, _, done in self.close(group, key):
            out += self.by_object(done)
        return out


def close_bits(rows: Iterable[tuple[np.ndarray, np.ndarray]], shape: tuple[int, int], planes: int, start: int, before: tuple | None = None) -> tuple[list[np.ndarray], np.ndarray]:
    """(counters, where the sum of bit matrices and ``start`` has reached 2 ^ ``planes``): carry-save counters, two matrices of a weight at a time.

    ``before`` is what an earlier call gave, of one row for all rows here: its sums go on.
    """
    if before is None:
        full = np.uint64(0xFFFFFFFFFFFFFFFF)
        sums, done = [np.full(shape, full if start >> p & 1 else 0, np.uint64) for p in range(planes)], np.zeros(shape, np.uint64)
    else:
        sums, done = [np.broadcast_to(x, shape).copy() for x in before[0]], np.broadcast_to(before[1], shape).copy()
    waiting: list[np.ndarray | None] = [None] * planes
    free, both = [], np.empty(shape, np.uint64)

    def add(p: int, new: np.ndarray) -> None:
        while p < planes:
            if (other := waiting[p]) is None:
                waiting[p] = new
                return
            waiting[p], total = None, sums[p]
            np.bitwise_xor(total, other, out=both)
            np.bitwise_and(total, other, out=other)
            np.bitwise_xor(both, new, out=total)
            np.bitwise_and(both, new, out=new)
            np.bitwise_or(new, other, out=new)
            free.append(other)
            p += 1
        np.bitwise_or(done, new, out=done)
        free.append(new)

    for bits, own in rows:
        new = free.pop() if free else np.empty(shape, np.uint64)
        bits.take(own, axis=0, out=new, mode="clip")
        add(0, new)
    for p in range(planes):
        if (new := waiting[p]) is not None:
            waiting[p], total = None, sums[p]
            np.bitwise_and(total, new, out=both)
            np.bitwise_xor(total, new, out=total)
            np.copyto(new, both)
            add(p + 1, new)  # the last one of a weight
    return sums, done
