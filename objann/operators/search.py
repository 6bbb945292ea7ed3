"""k nearest objects by collision index over the stored bucket index, with early stops."""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass, replace
from fractions import Fraction
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from objann.operators.gamma import LARGE, batch_distances, by_object, object_distances, query_sizes, whole_objects
from objann.operators.hashing import Projections
from objann.operators.index import NO_OBJECT, Block, Index, directories, read_blocks, read_postings, wanted_directories
from objann.operators.kernel import CELLS, CloseAt, CloseBlock, Collisions, QuerySet, close_events, query_batches, run_lengths, side_by_side
from objann.sources.families import Family, object_sizes
from objann.sources.tables import written

STATS = "q_obj long, status string, stop_level int, stop_proj int, n_candidates long"
RESULT = "q_obj long, rank int, object_id long, sq_dist long"
COUNTS = "q_obj long, object_id long, turn long, key long, n long"


@dataclass
class ObjectKnnResult:
    result: DataFrame  # q_obj, rank, object_id, sq_dist
    stats: DataFrame  # q_obj, status, stop_level, stop_proj, n_candidates


def block_events(block: Block, q: QuerySet, hashed: np.ndarray, proj: Projections, levels: range, mode: str, upto: int | None) -> Iterator[pa.RecordBatch]:
    """Counts of a block's pairs by query object, object and event."""
    step = max(1, CELLS // len(block.hashes))
    for a in range(0, len(hashed), step):
        first, _ = run_lengths(q.q_obj[a : a + step])
        names = q.q_obj[a : a + step][first]
        pairs = Collisions(hashed[a : a + step], block.hashes, block.present, proj.limits(), proj.static)
        out: list[tuple] = []
        for turn, key, bits in close_events(pairs, proj.params.m, proj.params.l, levels, mode, upto):
            ones = np.bitwise_count(bits.view(np.uint8)).astype(np.int32)
            held = np.add.reduceat(np.add.reduceat(ones, first, axis=0), block.first_byte, axis=1)
            x, y = np.nonzero(held)
            out.append((names[x], block.objects[y], np.full(len(x), turn), np.full(len(x), key), held[x, y].astype(np.int64)))
        if out:
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in zip(*out)], ["q_obj", "object_id", "turn", "key", "n"])


def close_counts(rows: DataFrame, index: Index, q: QuerySet, levels: range, mode: str, upto: int | None = None) -> DataFrame:
    """(q_obj, object_id, turn, key, n): pairs of the query object and the object that become close at each event.

    ``rows`` are the posting lists that were read.  They and the directories meet by block; a block's
    task counts collisions of its pairs in bit matrices, so no pair ever is a row.
    """
    proj, hashed = index.proj, index.proj.hashes(q.vec)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for block in read_blocks(batches, proj):
            yield from block_events(block, q, hashed, proj, levels, mode, upto)

    dealt = rows.union(directories(index)).repartition("block").sortWithinPartitions("block", "proj")
    return dealt.mapInArrow(count, COUNTS).groupBy("q_obj", "object_id", "turn", "key").agg(F.sum("n").alias("n"))


def located(block: CloseBlock, group: int, m: int, need: np.ndarray, key: int, n: np.ndarray, enough: int | None = None) -> list[tuple[int, int, int]]:
    """(object's number, event, close pairs) for objects that are candidates at ``key`` with ``n`` pairs.

    The level is found from the last one down, the event by adding the level's projections one by one.  Objects that become
    candidates after ``enough`` others here are left out.
    """
    spans, some, number = [], block, np.arange(len(need))  # of objects whose first event is in one level: their block, numbers, events
    while True:
        events = some.events_of_level(group, key)
        before, now = next(events) if key > m else (-1, np.zeros(len(number), np.int64))
        early = now >= need[number]
        if enough is None or early.sum() < enough:
            spans.append((number, now, ~early, events))
        if not early.any():
            break
        if not early.all():
            some, number = some.some(np.flatnonzero(early)), number[early]
        key = before
    found: list[tuple[int, int, int]] = []
    for objects, pairs, wanted, events in reversed(spans):
        if not wanted.any() or (enough is not None and len(found) >= enough):
            continue
        for event, more in events:
            pairs = pairs + more
            now = wanted & (pairs >= need[objects])
            if now.any():
                found += [(int(o), event, int(x)) for o, x in zip(objects[now], pairs[now])]
                wanted &= ~now
                if not wanted.any() or (enough is not None and len(found) >= enough):
                    break
    return found


def first_counts(rows: DataFrame, index: Index, q: QuerySet, gamma: tuple[int, int], eps: tuple[int, int], enough: int, exclude_self: bool = False, chosen: bool = False, known: dict[int, int] | None = None) -> DataFrame:
    """What ``close_counts`` gives under carried counts of static buckets, as far as a search needs it: objects that are whole
    in a block have one row, the event at which they become candidates with the close pairs by then.

    A task keeps the events of the ``enough`` first candidates of each query object that it met.  No search goes on
    after the last of them, so other objects are counted at that event only, and left out unless they are candidates by then.
    ``known`` are events by query object after which, too, no search goes on.
    Objects in several blocks have all their events.
    """
    proj, limits = index.proj, index.proj.limits()
    q = side_by_side(q)
    hashed, m, last = proj.hashes(q.vec), proj.params.m, proj.levels * (proj.params.m + 1) + proj.params.m
    num, den = (eps[1] - eps[0]) * gamma[0], eps[1] * gamma[1]
    groups = q.objects()

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at = CloseAt(hashed, np.array([a for _, a, _ in groups]), limits, m, proj.params.l)
        best = [np.zeros(0, np.int64) for _ in groups]
        for block in read_blocks(batches, proj):
            if len(block.objects) == 1:
                if block.objects[0] != NO_OBJECT:
                    yield from block_events(block, q, hashed, proj, range(proj.levels + 1), "carry", None)
                continue
            begins = block.first_byte * 8
            wanted = np.flatnonzero(block.objects != NO_OBJECT)
            if not len(wanted):
                continue
            own = at.block(block.hashes, block.present, begins, begins + -(-block.sizes // 8) * 8)
            if len(wanted) < len(begins):
                own = own.some(wanted)
            names, sizes = block.objects[wanted], block.sizes[wanted]
            out = []
            for g, (name, a, b) in enumerate(groups):
                need = -(-(b - a) * sizes * num // den)
                key = min((known or {}).get(name, last), int(best[g][enough - 1]) if len(best[g]) >= enough else last)
                n = own.counts(g, key)
                some = np.flatnonzero(n >= need)
                if not len(some):
                    continue
                found = located(own.some(some), g, m, need[some], key, n[some], enough + exclude_self)
                out += [(name, int(names[some[o]]), -1, event, pairs) for o, event, pairs in found]
                events = [event for o, event, _ in found if not (exclude_self and names[some[o]] == name)]
                best[g] = np.sort(np.append(best[g], events))[:enough].astype(np.int64)
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(np.array(c, np.int64)) for c in zip(*out)], ["q_obj", "object_id", "turn", "key", "n"])

    held = wanted_directories(index) if chosen else directories(index)
    dealt = rows.union(held).repartition("block").sortWithinPartitions("block", "proj")
    return dealt.mapInArrow(count, COUNTS).groupBy("q_obj", "object_id", "turn", "key").agg(F.sum("n").alias("n"))


def candidate_keys(counts: DataFrame, index: Index, q: QuerySet, gamma: tuple[int, int], eps: tuple[int, int] = (1, 5)) -> DataFrame:
    """(q_obj, object_id, key): the event level * (m + 1) + projection at which an object becomes a candidate."""
    upto = F.sum("n").over(Window.partitionBy("q_obj", "object_id", "turn").orderBy("key"))
    sizes = F.broadcast(query_sizes(counts.sparkSession, q))
    placed = counts.withColumn("upto", upto).join(sizes, "q_obj").join(index.sizes, "object_id")
    num, den = (eps[1] - eps[0]) * gamma[0], eps[1] * gamma[1]
    return placed.where(F.col("upto") * den >= F.col("n_query") * F.col("n_points") * num).groupBy("q_obj", "object_id").agg(F.min("key").alias("key"))


def object_knn(
    index: Index,
    queries: DataFrame,
    family: Family,
    gamma: tuple[int, int] = (1, 4),
    k: int = 25,
    eps: tuple[int, int] = (1, 5),
    count_mode: str = "carry",
    t2_bound: str = "R",
    order_by: str = "distance",
    mode: str = "onepass",
    proj_batch: int | None = None,
    exclude_self: bool = False,
    where: DataFrame | None = None,
    filter_mode: str = "pre",
) -> ObjectKnnResult:
    """The k nearest objects of each query object, with what stopped each search.

    onepass: the posting lists of all levels are read at once; the stop is an order statistic of the
    candidate events.  iterative: one round per level (or per ``proj_batch`` projections of it) reads
    only the ring of buckets that the level adds; query objects that have stopped leave.  Both
    give the same rows, under ``carry`` and under ``restart`` counts.
    T1: enough candidates, tested after each projection.  T2: at the end of a level k
    candidates lie within the radius (``cR``: c times it).  Neither by the end of the ladder: ``exhausted``.
    Distances are worked out for candidates only.  ``order_by`` is distance or collision (the event).
    ``where`` (object_id) limits the objects: ``pre`` searches among them alone, so it is exact and
    the number of objects is theirs; ``post`` filters the k found, so fewer may be left.
    """
    if where is not None and filter_mode == "pre":
        sizes = written(index.sizes.join(where, "object_id", "left_semi"), "object-sizes")
        index = replace(index, sizes=sizes, n_objects=sizes.count())
    search = _Search(index, family, gamma, k, eps, count_mode, t2_bound, order_by, exclude_self, where is not None and filter_mode == "pre")
    found = [search.onepass(q) if mode == "onepass" else search.iterative(q, proj_batch) for q in query_batches(queries)]
    spark = index.table.sparkSession
    result, stats = spark.createDataFrame([], RESULT), spark.createDataFrame([], STATS)
    for more in found:
        result, stats = (more.result, more.stats) if more is found[0] else (result.union(more.result), stats.union(more.stats))
    if where is not None and filter_mode == "post":
        order = Window.partitionBy("q_obj").orderBy("rank")
        result = result.join(where, "object_id", "left_semi").withColumn("rank", F.row_number().over(order)).select("q_obj", "rank", "object_id", "sq_dist")
    return ObjectKnnResult(result, stats)


def object_knn_of(index: Index, queries: DataFrame, family: Family, gamma: tuple[int, int], ks: tuple[int, ...]) -> dict[int, DataFrame]:
    """The results of ``object_knn`` in one pass by each of several k: the search of the largest counts for all of them.

    What it meets after the stop of a smaller k comes after that stop, so it changes nothing there.
    """
    searches = {k: _Search(index, family, gamma, k, (1, 5), "carry", "R", "distance", False) for k in ks}
    found: dict[int, list[DataFrame]] = {k: [] for k in ks}
    for q in query_batches(queries):
        keys, distances = searches[max(ks)].counted(q)
        for k in ks:
            found[k].append(searches[k].finish(keys, distances, q, searches[k].top).result)
    empty = index.table.sparkSession.createDataFrame([], RESULT)
    return {k: reduce(DataFrame.union, parts) if parts else empty for k, parts in found.items()}


@dataclass
class _Search:
    index: Index
    family: Family
    gamma: tuple[int, int]
    k: int
    eps: tuple[int, int]
    count_mode: str
    t2_bound: str
    order_by: str
    exclude_self: bool
    chosen: bool = False  # the index's sizes hold a part of its objects only

    def __post_init__(self):
        self.proj: Projections = self.index.proj
        self.m, self.top = self.proj.params.m, self.proj.levels
        self.enough = self.k + math.ceil(min(Fraction(25, max(1, self.index.n_objects)), Fraction(999, 1000)) * self.index.n_objects)

    def keys(self, rows: DataFrame, q: QuerySet, levels: range, upto: int | None = None) -> DataFrame:
        found = candidate_keys(close_counts(rows, self.index, q, levels, self.count_mode, upto), self.index, q, self.gamma, self.eps)
        return found.where("object_id <> q_obj") if self.exclude_self else found

    def first_keys(self, rows: DataFrame, q: QuerySet, known: dict[int, int]) -> DataFrame:
        counts = first_counts(rows, self.index, q, self.gamma, self.eps, self.enough, self.exclude_self, self.chosen, known)
        found = candidate_keys(counts, self.index, q, self.gamma, self.eps)
        return found.where("object_id <> q_obj") if self.exclude_self else found

    def sampled_stops(self, rows: DataFrame, q: QuerySet) -> dict[int, int]:
        """T1 by query object over an eighth of the blocks: the search over all of them stops no later."""
        blocks = sorted(r.block for r in directories(self.index).select("block").collect())[::8]  # one number for each block
        if len(blocks) < 4:
            return {}
        own = replace(self, index=replace(self.index, table=self.index.table.where(F.col("block").isin(blocks))))
        own.enough = self.enough
        return {r.q_obj: r.t1 for r in own.t1(own.first_keys(rows.where(F.col("block").isin(blocks)), q, {})).collect()}

    def t1(self, keys: DataFrame) -> DataFrame:
        order = Window.partitionBy("q_obj").orderBy("key", "object_id")
        return keys.withColumn("at", F.row_number().over(order)).where(F.col("at") == self.enough).select("q_obj", F.col("key").alias("t1"))

    def distances(self, pairs: DataFrame, q: QuerySet) -> DataFrame:
        """(q_obj, object_id, sq_dist) of the pairs."""
        points = self.index.points.join(pairs.select("object_id").distinct(), "object_id", "left_semi")
        large = [r.object_id for r in self.index.sizes.where(F.col("n_points") > LARGE).select("object_id").collect()]  # few, by their size
        found = object_distances(points.where(~F.col("object_id").isin(large)) if large else points, q, self.gamma)
        if large:
            found = found.union(batch_distances(points.where(F.col("object_id").isin(large)), q, self.family, self.gamma))
        found = found.select("q_obj", "object_id", "sq_dist")
        return found.join(pairs.select("q_obj", "object_id"), ["q_obj", "object_id"], "left_semi")

    def onepass(self, q: QuerySet) -> ObjectKnnResult:
        return self.finish(*self.counted(q), q, self.top)

    def counted(self, q: QuerySet) -> tuple[DataFrame, DataFrame]:
        """(events, distances) of one pass: what ``finish`` needs for this search, and for searches of fewer objects."""
        hashed = self.proj.hashes(q.vec)
        rows = read_postings(self.index, hashed, self.top)
        if self.proj.static and self.count_mode == "carry":
            keys = written(self.first_keys(rows, q, self.sampled_stops(rows, q)), "keys")
        else:
            keys = written(self.keys(rows, q, range(self.top + 1)), "keys")
        # what comes after T1 can neither be returned nor stop the search
        needed = keys.join(self.t1(keys), "q_obj", "left").where(F.col("t1").isNull() | (F.col("key") <= F.col("t1"))).select("q_obj", "object_id", "key")
        return keys, written(self.distances(written(needed, "candidates"), q), "distances")

    def iterative(self, q: QuerySet, proj_batch: int | None) -> ObjectKnnResult:
        spark = self.index.table.sparkSession
        held: DataFrame | None = None
        keys = distances = None
        found: list[ObjectKnnResult] = []
        for level in range(self.top + 1):
            hashed = self.proj.hashes(q.vec)
            for start in range(0, self.m, proj_batch or self.m):
                upto = min(start + (proj_batch or self.m), self.m)
                ring = read_postings(self.index, hashed, level, level - 1 if level else None).where(f"proj > {start} AND proj <= {upto}")
                held = written(ring if held is None else held.union(ring), "postings-read")
                now = self.keys(held, q, range(level, level + 1), upto)
                if keys is not None:
                    now = keys.union(now.join(keys, ["q_obj", "object_id"], "left_anti"))
                seen = written(now, "keys")
                if upto < self.m and self.t1(seen).count() == len(q.sizes()):
                    break
            keys = seen
            fresh = keys if distances is None else keys.join(distances, ["q_obj", "object_id"], "left_anti")
            more = self.distances(written(fresh, "candidates"), q)
            distances = written(more if distances is None else distances.union(more), "distances")
            done = self.finish(keys, distances, q, level)
            status = {r.q_obj: r for r in done.stats.collect()}  # one row for each open query object
            over = [o for o, r in status.items() if r.status != "exhausted" or level == self.top]
            if over:
                found.append(ObjectKnnResult(done.result.where(F.col("q_obj").isin(over)), done.stats.where(F.col("q_obj").isin(over))))
                left = ~np.isin(q.q_obj, over)
                q = QuerySet(q.q_obj[left], q.q_id[left], q.vec[left])
                keys, distances = keys.where(~F.col("q_obj").isin(over)), distances.where(~F.col("q_obj").isin(over))
            if not len(q.q_obj):
                break
        result, stats = spark.createDataFrame([], RESULT), spark.createDataFrame([], STATS)
        for more in found:
            result, stats = (more.result, more.stats) if more is found[0] else (result.union(more.result), stats.union(more.stats))
        return ObjectKnnResult(result, stats)

    def finish(self, keys: DataFrame, distances: DataFrame, q: QuerySet, levels: int) -> ObjectKnnResult:
        m = self.m
        stops = self.stops(keys, distances, q, levels)
        inside = keys.join(stops, "q_obj").where("key <= stop").join(distances, ["q_obj", "object_id"])
        first = ["sq_dist", "object_id"] if self.order_by == "distance" else ["key", "object_id"]
        ranked = inside.withColumn("rank", F.row_number().over(Window.partitionBy("q_obj").orderBy(*first)))
        result = ranked.where(F.col("rank") <= self.k).select("q_obj", "rank", "object_id", "sq_dist")
        counted = inside.groupBy("q_obj").agg(F.count("*").alias("n"))
        stats = stops.join(counted, "q_obj", "left").select(
            "q_obj", "status", F.expr(f"cast(stop div {m + 1} as int)").alias("stop_level"), F.expr(f"cast(stop % {m + 1} as int)").alias("stop_proj"), F.coalesce("n", F.lit(0)).cast("long").alias("n_candidates")
        )
        return ObjectKnnResult(result, stats)

    def stops(self, keys: DataFrame, distances: DataFrame, q: QuerySet, levels: int) -> DataFrame:
        m = self.m
        # each candidate counts from the later of its entry level and the first level whose radius holds it
        entered = keys.join(distances, ["q_obj", "object_id"]).withColumn("entry", F.expr(f"key div {m + 1}"))
        reach = F.lit(levels + 1)
        for t, limit in reversed(list(enumerate(self.proj.squared_radii(self.family.unit, self.proj.params.c if self.t2_bound == "cR" else 1)[: levels + 1]))):
            reach = F.when(F.col("sq_dist") <= limit, F.lit(t)).otherwise(reach)
        order = Window.partitionBy("q_obj").orderBy("level", "object_id")
        near = entered.withColumn("level", F.greatest("entry", reach)).withColumn("at", F.row_number().over(order))
        t2 = near.where((F.col("at") == self.k) & (F.col("level") <= levels)).select("q_obj", (F.col("level") * (m + 1) + m).alias("t2"))
        both = query_sizes(keys.sparkSession, q).select("q_obj").join(self.t1(keys), "q_obj", "left").join(t2, "q_obj", "left")
        last = levels * (m + 1) + m
        first = F.coalesce("t1", F.lit(last + 1)) <= F.coalesce("t2", F.lit(last + 1))
        status = F.when(F.col("t1").isNull() & F.col("t2").isNull(), "exhausted").when(first, "T1").otherwise("T2")
        return both.select("q_obj", status.alias("status"), F.least(F.coalesce("t1", F.lit(last)), F.coalesce("t2", F.lit(last))).cast("long").alias("stop"))


PIECE, POINTS = 512, 1 << 14  # points of an object in one row of ``whole_rows``; points of one block here
FEW, SHARES = 4, (64, 8)  # query objects whose stop is worked out at once; samples: one of so many objects


def whole_rows(points: DataFrame, dim: int) -> DataFrame:
    """(object_id, n_points, vecs): a row an object, of four bytes a component; objects of over PIECE points in several rows."""

    def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for obj, sizes, vec in whole_objects(batches, dim):
            rows, begins = [], np.cumsum(sizes) - sizes
            for o, n, a in zip(obj.tolist(), sizes.tolist(), begins.tolist()):
                rows += [(o, n, vec[x : min(x + PIECE, a + n)].astype(np.int32).tobytes()) for x in range(a, a + n, PIECE)]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), (pa.int64(), pa.int64(), pa.binary()))], ["object_id", "n_points", "vecs"])

    return by_object(points).mapInArrow(merge, "object_id long, n_points long, vecs binary")


def entry_levels(rows: DataFrame, q: QuerySet, proj: Projections, levels: list[int], gamma: tuple[int, int], eps: tuple[int, int], enough: int) -> DataFrame:
    """(q_obj, object_id, level): objects of ``whole_rows`` that are candidates by the end of one of ``levels``, with the first such.

    Carried counts of static buckets.  A task goes on to no level of a query object after one with ``enough`` candidates that it knows.
    """
    hashed, m, groups, dim = proj.hashes(q.vec), proj.params.m, q.objects(), q.vec.shape[1]
    num, den = (eps[1] - eps[0]) * gamma[0], eps[1] * gamma[1]

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at = CloseAt(hashed, np.array([a for _, a, _ in groups]), proj.limits(), m, proj.params.l)
        known = np.zeros((len(groups), len(levels)), np.int64)  # candidates by the end of each level

        def counted(held: list[tuple[int, int, np.ndarray]]) -> pa.RecordBatch:
            names, totals = (np.array([h[x] for h in held], np.int64) for x in (0, 1))
            sizes = np.array([len(h[2]) for h in held])
            ends = np.cumsum(-(-sizes // 8) * 8)
            begins = ends - -(-sizes // 8) * 8
            place = np.repeat(begins - (np.cumsum(sizes) - sizes), sizes) + np.arange(sizes.sum())
            hashes, present = np.zeros((ends[-1], m), np.int64), np.zeros((ends[-1], m), bool)
            hashes[place], present[place] = proj.hashes(np.concatenate([h[2] for h in held])), True
            block, whole, out = at.block(hashes, present, begins, ends), sizes == totals, []
            for g, (name, a, b) in enumerate(groups):
                need, before = -(-(b - a) * totals * num // den), np.zeros(len(held), bool)
                for i, t in enumerate(levels):
                    if known[g, max(0, i - 1)] >= enough:
                        break
                    n = block.counts(g, t * (m + 1) + m)
                    some = np.flatnonzero(np.where(whole, (n >= need) & ~before, n > 0))
                    known[g, i:] += int((whole & (n >= need) & ~before).sum())
                    before |= whole & (n >= need)
                    out.append((np.full(len(some), name), names[some], np.full(len(some), t), totals[some], n[some]))
            columns = [np.concatenate(c).astype(np.int64) for c in zip(*out)] if out else [np.zeros(0, np.int64)] * 5
            return pa.RecordBatch.from_arrays([pa.array(c) for c in columns], ["q_obj", "object_id", "level", "n_points", "n"])

        held, size = [], 0
        for batch in batches:
            for o, n, vecs in zip(*(batch.column(c).to_pylist() for c in range(3))):
                held.append((o, n, np.frombuffer(vecs, np.int32).reshape(-1, dim).astype(np.int64)))
                size += len(held[-1][2]) + 8
                if size >= POINTS:
                    yield counted(held)
                    held, size = [], 0
        if held:
            yield counted(held)

    raw = rows.mapInArrow(count, "q_obj long, object_id long, level long, n_points long, n long")
    summed = raw.groupBy("q_obj", "object_id", "level").agg(F.sum("n").alias("n"), F.first("n_points").alias("n_points"))
    summed = summed.join(F.broadcast(query_sizes(rows.sparkSession, q)), "q_obj").where(F.col("n") * den >= F.col("n_query") * F.col("n_points") * num)
    return summed.groupBy("q_obj", "object_id").agg(F.min("level").alias("level"))


def highest_stop(points: DataFrame, queries: DataFrame, family: Family, proj: Projections, gamma: tuple[int, int], k: int, eps: tuple[int, int] = (1, 5)) -> int:
    """The highest level at which ``object_knn`` stops for any of the query objects, under carried counts of static buckets.

    A search has stopped by a level if some objects, of however few, are enough candidates there.  So most query
    objects are settled by a sample of the objects; those with the fewest candidates in it are searched among all
    objects, which raises the level or leaves it.  What no sample settles meets all objects.
    """
    n_objects = object_sizes(points).count()
    enough = k + math.ceil(min(Fraction(25, max(1, n_objects)), Fraction(999, 1000)) * n_objects)
    rows = written(whole_rows(points, family.dim), "objects")
    radii, levels = proj.squared_radii(family.unit), list(range(proj.levels + 1))
    highest = 0

    def part(q: QuerySet, names) -> QuerySet:
        own = np.isin(q.q_obj, list(names))
        return QuerySet(q.q_obj[own], q.q_id[own], q.vec[own])

    def settled(q: QuerySet, share: int) -> dict[int, int]:
        """Candidates by query object at the highest level so far, among one of ``share`` objects."""
        some = rows.where(F.pmod(F.xxhash64("object_id"), F.lit(share)) == 0) if share > 1 else rows
        found = entry_levels(some, q, proj, [highest], gamma, eps, enough).groupBy("q_obj").count().collect()  # one number for each query object
        return dict.fromkeys(q.sizes(), 0) | {r.q_obj: r["count"] for r in found}

    def stop_level(q: QuerySet) -> int:
        """The highest exact stop of a few query objects."""
        order = Window.partitionBy("q_obj").orderBy("level", "object_id")
        first = entry_levels(rows, q, proj, levels, gamma, eps, enough).withColumn("at", F.row_number().over(order)).where(F.col("at") <= enough)
        first = written(first, "candidates")
        own = points.join(first.select("object_id").distinct(), "object_id", "left_semi")
        near = batch_distances(own, q, family, gamma).select("q_obj", "object_id", "sq_dist")
        stops = dict.fromkeys(q.sizes(), levels[-1])
        inside: dict[int, list[int]] = {}
        for r in first.join(near, ["q_obj", "object_id"]).collect():  # ``enough`` rows for each of a few query objects
            if r["at"] == enough:
                stops[r.q_obj] = min(stops[r.q_obj], r.level)
            inside.setdefault(r.q_obj, []).append(max(r.level, next((t for t in levels if r.sq_dist <= radii[t]), len(levels))))
        return max(min(stop, sorted(inside.get(o, []))[k - 1] if len(inside.get(o, [])) >= k else stop) for o, stop in stops.items())

    for batch in query_batches(queries):
        names = sorted(batch.sizes())
        if not highest:
            highest, names = stop_level(part(batch, names[:FEW])), names[FEW:]
        for share in [s for s in SHARES if n_objects >= 2 * s * enough] + [1]:
            while names and highest < levels[-1]:
                found = settled(part(batch, names), share)
                names = sorted((o for o in names if found[o] < enough), key=lambda o: (found[o], o))
                few = names[:FEW] if share > 1 else names
                names, before = names[len(few) :], highest
                if few:
                    highest = max(highest, stop_level(part(batch, few)))
                if highest == before:
                    break
    return highest


def schedule_costs(index: Index, queries: DataFrame, level: int) -> DataFrame:
    """(q_obj, joint, independent): buckets read at a level when all query points go on together, and when each goes alone."""
    from objann.operators.hashing import inverted, level_bucket

    radius = index.proj.limits()[level]
    own = inverted(queries, index.proj).select(F.col("object_id").alias("q_obj"), F.col("point_id").alias("q_id"), "proj", level_bucket(F.col("bucket"), radius).alias("cell"))
    stored = index.table.where("proj > 0").select("proj", "bucket", level_bucket(F.col("bucket"), radius).alias("cell")).distinct()
    read = own.join(stored, ["proj", "cell"])
    return read.groupBy("q_obj").agg(F.countDistinct("proj", "bucket").alias("joint"), F.count("*").alias("independent"))
