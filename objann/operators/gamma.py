"""Object similarity, share distance, collision index and their exact ranking."""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from objann.operators.kernel import BATCH_POINTS, QuerySet, block_sq_dist, blocks, check_range, query_batches, run_lengths
from objann.sources.families import Family, object_sizes


def counted_batch(q: QuerySet, obj: np.ndarray, cells: np.ndarray, keep: np.ndarray | None = None) -> pa.RecordBatch:
    """Counts by (query object, object, cell) of a (query point x point) matrix, each pair coded as one integer."""
    objects, own = np.unique(obj, return_inverse=True)
    parts = []
    for name, a, b in q.objects():
        part = cells[a:b]
        where = np.broadcast_to(own[None, :], part.shape)
        if keep is not None:
            part, where = part[keep[a:b]], where[keep[a:b]]
        part, where = part.ravel(), where.ravel()
        if not len(part):
            continue
        low = int(part.min())
        span = int(part.max()) - low + 1
        if span * len(objects) <= 4 * len(part) + 65_536:
            counts = np.bincount(where * span + (part - low), minlength=span * len(objects))
            codes = np.flatnonzero(counts)
            number, cell, n = codes // span, codes % span + low, counts[codes]
        else:
            order = np.lexsort((part, where))
            where, part = where[order], part[order]
            first = np.flatnonzero(np.concatenate([[True], (where[1:] != where[:-1]) | (part[1:] != part[:-1])]))
            number, cell, n = where[first], part[first], np.diff(np.append(first, len(part)))
        parts.append((np.full(len(number), name), objects[number], cell, n))
    columns = [np.concatenate(c) for c in zip(*parts)] if parts else [np.zeros(0, np.int64)] * 4
    return pa.RecordBatch.from_arrays([pa.array(c.astype(np.int64)) for c in columns], ["q_obj", "object_id", "cell", "n"])


def _histogram(points: DataFrame, q: QuerySet, cell_of) -> DataFrame:
    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for obj, _, vec in blocks(batches, len(q.q_obj)):
            yield counted_batch(q, obj, cell_of(block_sq_dist(q.vec, vec)))

    raw = points.select("object_id", "point_id", "vec").mapInArrow(count, "q_obj long, object_id long, cell long, n long")
    return raw.groupBy("q_obj", "object_id", "cell").agg(F.sum("n").alias("n"))


def in_batches(queries: DataFrame, make, most: int = BATCH_POINTS) -> DataFrame:
    """The union of ``make`` over batches of whole query objects; ``make(None)`` for none at all."""
    made = [make(q) for q in query_batches(queries, most)]
    return reduce(DataFrame.union, made) if made else make(None)


NO_QUERY = QuerySet(np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros((0, 0), np.int64))


def query_sizes(spark, q: QuerySet) -> DataFrame:
    return spark.createDataFrame(list(q.sizes().items()), "q_obj long, n_query long")


def object_similarity(points: DataFrame, queries: DataFrame, family: Family, radius: int) -> DataFrame:
    """(q_obj, object_id, num, den): point pairs within the radius, of all pairs."""
    limit = (radius * family.unit) ** 2

    def similar(q: QuerySet | None) -> DataFrame:
        near = _histogram(points if q else points.where("false"), q or NO_QUERY, lambda d: (d <= limit).astype(np.int64))
        return near.groupBy("q_obj", "object_id").agg(F.sum(F.when(F.col("cell") == 1, F.col("n")).otherwise(0)).alias("num"), F.sum("n").alias("den"))

    return in_batches(queries, similar)


def share_rank(gamma: tuple[int, int]):
    """Rank of the pair distance that a share gamma = (numerator, denominator) picks, as a column of n_query and n_points."""
    n, d = gamma
    pairs = F.col("n_query") * F.col("n_points") * n
    return F.greatest(F.lit(1).cast("long"), ((pairs + (d - 1)) - F.pmod(pairs + (d - 1), F.lit(d))) / d).cast("long")


def gamma_distance(points: DataFrame, queries: DataFrame, family: Family, gamma: tuple[int, int], k: int | None = None) -> DataFrame:
    """(q_obj, object_id, rank_in_pairs, sq_dist): the share-th smallest pair distance, squared.

    An object's points meet in one task, which picks the rank among its pairs with each query object, so
    one row leaves a pair of objects.  Objects of over LARGE points are spread over tasks by histograms.  With ``k``, a
    task keeps each query object's k nearest only, and ranks no object that cannot be one of them.
    """
    large = [r.object_id for r in object_sizes(points).where(F.col("n_points") > LARGE).select("object_id").collect()]  # few, by their size
    usual = points.where(~F.col("object_id").isin(large)) if large else points

    def whole(q: QuerySet | None) -> DataFrame:
        found = object_distances(usual if q else points.where("false"), q or NO_QUERY, gamma, k)
        return found.union(batch_distances(points.where(F.col("object_id").isin(large)), q, family, gamma)) if q and large else found

    return in_batches(queries, whole, QUERY_POINTS)


LARGE = 1 << 16  # points of an object that one task ranks alone
QUERY_POINTS = 100_000  # query points of a batch here: a task goes through its query objects one by one
PAIRS, MOST_PAIRS = 1 << 18, 1 << 24  # pairs of one block; pairs of two objects that are ranked at once
RUN, HELD = 32, 1 << 18  # points of an object in one row of the shuffle; points of whole objects that a task holds


def by_object(points: DataFrame) -> DataFrame:
    """(object_id, vecs): points of four bytes a component, all of an object in one partition and side by side."""

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            obj = batch.column(0).to_numpy()
            vec = np.array(batch.column(1).flatten().to_numpy(zero_copy_only=False), dtype=np.int64).reshape(len(obj), -1)
            check_range(vec)
            first, end = run_lengths(obj)
            cuts = np.concatenate([np.arange(a, b, RUN) for a, b in zip(first.tolist(), end.tolist())])
            ends = np.append(cuts, len(obj)) * vec.shape[1] * 4
            data = pa.Array.from_buffers(pa.binary(), len(cuts), [None, pa.py_buffer(ends.astype(np.int32)), pa.py_buffer(vec.astype(np.int32))])
            yield pa.RecordBatch.from_arrays([pa.array(obj[cuts]), data], ["object_id", "vecs"])

    spark = points.sparkSession
    parts = max(int(spark.conf.get("spark.sql.shuffle.partitions")), spark.sparkContext.defaultParallelism)  # by number: small rows, much work
    packed = points.select("object_id", "vec").mapInArrow(pack, "object_id long, vecs binary")
    return packed.repartition(parts, "object_id").sortWithinPartitions("object_id")


def whole_objects(batches: Iterator[pa.RecordBatch], dim: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(object ids, sizes, vectors) of whole objects, ordered by size, in sets of about HELD points."""

    def close(obj: np.ndarray, vec: np.ndarray):
        first, end = run_lengths(obj)
        order = np.argsort(end - first, kind="stable")
        sizes = (end - first)[order]
        begins = np.cumsum(sizes) - sizes
        return obj[first][order], sizes, vec[np.repeat(first[order] - begins, sizes) + np.arange(len(obj))]

    ids, vecs, held = [], [], 0
    for batch in batches:
        rows = batch.column(1).to_pylist()
        ids.append(np.repeat(batch.column(0).to_numpy(), [len(r) // (4 * dim) for r in rows]))
        vecs.append(np.frombuffer(b"".join(rows), np.int32).reshape(-1, dim))
        held += len(ids[-1])
        if held >= HELD:
            obj, vec = np.concatenate(ids), np.concatenate(vecs)
            if cut := int(np.searchsorted(obj, obj[-1])):  # the last object may go on
                yield close(obj[:cut], vec[:cut])
            ids, vecs, held = [obj[cut:]], [vec[cut:]], len(obj) - cut
    if held:
        yield close(np.concatenate(ids), np.concatenate(vecs))


def object_blocks(batches: Iterator[pa.RecordBatch], dim: int, most: int = 1 << 14) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
    """(object ids, sizes, begins, vectors) of whole objects, of about ``most`` points at once.  Objects begin at multiples of eight; the places between hold zeros."""
    for obj, sizes, vec in whole_objects(batches, dim):
        padded = -(-sizes // 8) * 8
        ends, last = np.cumsum(sizes), np.cumsum(padded)
        a = 0
        while a < len(obj):
            b = max(a + 1, int(np.searchsorted(last, (last[a - 1] if a else 0) + most, "right")))
            own, begins = sizes[a:b], last[a:b] - padded[a:b] - (last[a - 1] if a else 0)
            out = np.zeros((padded[a:b].sum(), dim), np.int64)
            out[np.repeat(begins - (np.cumsum(own) - own), own) + np.arange(own.sum())] = vec[ends[a] - sizes[a] : ends[b - 1]]
            yield obj[a:b], own, begins, out
            a = b


def _sides(vec: np.ndarray, query: bool, kind=np.float64) -> np.ndarray:
    """Vectors with two more components, so that the products of both sides are squared distances; exact in double precision."""
    v = vec.astype(np.float64)
    square, one = (v * v).sum(axis=1)[:, None], np.ones((len(v), 1))
    return np.concatenate([-2 * v, one, square] if query else [v, square, one], axis=1).astype(kind)


def _ranked_in_slices(x: np.ndarray, q: np.ndarray, rank: int, most: int) -> int:
    """The rank-th smallest product of rows of two sides whose pairs are too many at once: counts by cell, then the values of one cell."""
    step = max(1, most // len(q))
    low, high = 0, 1 << 53
    while high - low > 1:  # counts of up to 4096 cells between two ends at a time
        width = max(1, -(-(high - low) // 4096))
        counts, below = np.zeros(4097, np.int64), 0
        for a in range(0, len(x), step):
            d = (x[a : a + step] @ q.T).ravel().astype(np.int64)
            below += int((d < low).sum())
            counts += np.bincount((d[(d >= low) & (d < high)] - low) // width, minlength=4097)
        cell = int(np.searchsorted(below + np.cumsum(counts), rank))
        low, high = low + cell * width, min(high, low + (cell + 1) * width)
    return low


def share_distances(x: np.ndarray, sizes: np.ndarray, q: np.ndarray, ranks: np.ndarray) -> np.ndarray:
    """The rank-th smallest squared distance to each object; ``x`` and ``q`` as ``_sides``, objects ordered by size."""
    out, begins = np.empty(len(sizes), np.int64), np.cumsum(sizes) - sizes
    for a, b in zip(*map(np.ndarray.tolist, run_lengths(sizes))):
        n, rank = int(sizes[a]), int(ranks[a])
        pairs = n * len(q)
        for c in range(a, b, per := max(1, PAIRS // pairs)):
            e = min(b, c + per)
            if pairs > MOST_PAIRS:
                out[c] = _ranked_in_slices(x[begins[c] : begins[c] + n], q, rank, MOST_PAIRS)
                continue
            d = (x[begins[c] : begins[c] + (e - c) * n] @ q.T).reshape(e - c, pairs)
            d.partition(rank - 1, axis=1)
            out[c:e] = d[:, rank - 1]
    return out


def object_distances(points: DataFrame, q: QuerySet, gamma: tuple[int, int], k: int | None = None) -> DataFrame:
    """``gamma_distance`` of one batch, an object a task.

    With ``k``: once k objects are known, pairs within the k-th distance are counted in single precision with a margin over
    its error, and an object with fewer of them than the rank is left out.
    """

    def measure(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = [(name, _sides(q.vec[a:b], True)) for name, a, b in q.objects()]
        dim = q.vec.shape[1]
        near: dict[int, tuple[np.ndarray, ...]] = {}
        for obj, sizes, vec in whole_objects(batches, dim):
            x, x32 = _sides(vec, False), _sides(vec, False, np.float32) if k else None
            begins = np.append(0, np.cumsum(sizes))
            margin = 4e-7 * (dim + 4) * (x[:, dim].max() + max(s[:, dim + 1].max() for _, s in known)) if k else 0
            for name, side in known:
                ranks = np.maximum(1, -(-sizes * len(side) * gamma[0] // gamma[1]))
                if k is None:
                    yield pa.RecordBatch.from_arrays([pa.array(c) for c in (np.full(len(obj), name), obj, ranks, share_distances(x, sizes, side, ranks))], NAMES)
                    continue
                best = near.get(name, (np.zeros(0, np.int64),) * 3)
                pad = np.zeros((-len(side) % 8, dim + 2), np.float32)
                pad[:, dim:] = 1, np.inf  # no pair of these is near
                side32, at = np.concatenate([side.astype(np.float32), pad]), 0
                while at < len(obj):
                    if len(best[0]) < k or sizes[at] * len(side) > MOST_PAIRS:
                        end = min(len(obj), at + k)
                        some = np.arange(at, end)
                    else:
                        end = max(at + 1, int(np.searchsorted(begins, begins[at] + 2 * PAIRS // len(side32), "right")) - 1)
                        within = x32[begins[at] : begins[end]] @ side32.T <= np.float32((best[0][k - 1] + margin) * (1 + 1e-6))
                        ones = np.bitwise_count(np.packbits(within.ravel()))
                        counts = np.add.reduceat(ones, (begins[at:end] - begins[at]) * (len(side32) // 8), dtype=np.int64)
                        some = at + np.flatnonzero(counts >= ranks[at:end])
                    if len(some):
                        rows = np.repeat(begins[some] - (np.cumsum(sizes[some]) - sizes[some]), sizes[some]) + np.arange(sizes[some].sum())
                        found = share_distances(x[rows], sizes[some], side, ranks[some]), obj[some], ranks[some]
                        best = tuple(np.concatenate(c) for c in zip(best, found))
                        order = np.lexsort((best[1], best[0]))[:k]
                        best = tuple(c[order] for c in best)
                    at = end
                near[name] = best
        for name, (d, own, rank) in near.items():
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in (np.full(len(d), name), own, rank, d)], NAMES)

    return by_object(points).mapInArrow(measure, "q_obj long, object_id long, rank_in_pairs long, sq_dist long")


NAMES = ["q_obj", "object_id", "rank_in_pairs", "sq_dist"]


def batch_distances(points: DataFrame, q: QuerySet, family: Family, gamma: tuple[int, int]) -> DataFrame:
    """``gamma_distance`` of one batch for objects of any size, by mergeable histograms in two passes.

    Cells of 1/16 radius find the cell that holds the rank, then only pairs in that cell are counted exactly.
    The objects' sizes come from the first histogram, which holds every pair.
    """
    width = family.unit / 16

    def cell_of(d):
        return np.floor(np.sqrt(d.astype(np.float64)) / width).astype(np.int64)

    coarse = _histogram(points, q, cell_of)
    pair = Window.partitionBy("q_obj", "object_id")
    summed = coarse.withColumns({"upto": F.sum("n").over(pair.orderBy("cell")), "pairs": F.sum("n").over(pair)})
    n, d = gamma
    rank = F.greatest(F.lit(1), F.expr(f"(pairs * {n} + {d - 1}) div {d}")).cast("long")
    target = summed.withColumn("rank_in_pairs", rank).where((F.col("upto") >= F.col("rank_in_pairs")) & (F.col("upto") - F.col("n") < F.col("rank_in_pairs")))
    target = target.select("q_obj", "object_id", F.col("cell").alias("goal"), (F.col("rank_in_pairs") - F.col("upto") + F.col("n")).alias("rest"), "rank_in_pairs")
    goals = target.groupBy("object_id").agg(F.sort_array(F.collect_list(F.struct("q_obj", "goal"))).alias("goals"))
    names = [o for o, _, _ in q.objects()]

    def exact(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known = np.array(names, np.int64)
        step = max(1, (1 << 22) // max(1, len(q.q_obj)))
        for whole in batches:
            for a in range(0, whole.num_rows, step):
                batch = whole.slice(a, step)
                obj = batch.column(0).to_numpy()
                x = batch.column(1).flatten().to_numpy(zero_copy_only=False).astype(np.int64).reshape(len(obj), -1)
                lists = batch.column(2)
                inner, lengths = lists.flatten(), lists.value_lengths().to_numpy()
                goal = np.full((len(known), len(obj)), -1, np.int64)
                goal[np.searchsorted(known, inner.field(0).to_numpy()), np.repeat(np.arange(len(obj)), lengths)] = inner.field(1).to_numpy()
                dist = block_sq_dist(q.vec, x)
                keep = cell_of(dist) == goal[np.searchsorted(known, q.q_obj)]
                yield counted_batch(q, obj, dist, keep)

    fine = points.join(goals, "object_id").select("object_id", "vec", "goals").mapInArrow(exact, "q_obj long, object_id long, sq_dist long, n long")
    fine = fine.groupBy("q_obj", "object_id", "sq_dist").agg(F.sum("n").alias("n"))
    found = fine.withColumn("upto", F.sum("n").over(pair.orderBy("sq_dist"))).join(target, ["q_obj", "object_id"])
    found = found.where((F.col("upto") >= F.col("rest")) & (F.col("upto") - F.col("n") < F.col("rest")))
    return found.select("q_obj", "object_id", "rank_in_pairs", "sq_dist")


def gamma_distance_sketch(points: DataFrame, queries: DataFrame, family: Family, gamma: tuple[int, int], cells: int = 16) -> DataFrame:
    """(q_obj, object_id, low, high): radii between which the share distance lies, 1 / ``cells`` of the radius unit apart."""
    cell = F.floor(F.sqrt(F.col("sq_dist").cast("double")) / (family.unit / cells))
    found = gamma_distance(points, queries, family, gamma)
    return found.select("q_obj", "object_id", (cell / cells).alias("low"), ((cell + 1) / cells).alias("high"))


def exact_object_knn(points: DataFrame, queries: DataFrame, family: Family, gamma: tuple[int, int], k: int) -> DataFrame:
    """(q_obj, rank, object_id, sq_dist): the true nearest objects, ties to the smaller id."""
    order = Window.partitionBy("q_obj").orderBy("sq_dist", "object_id")
    ranked = gamma_distance(points, queries, family, gamma, k).withColumn("rank", F.row_number().over(order))
    return ranked.where(F.col("rank") <= k).select("q_obj", "rank", "object_id", "sq_dist")


def collision_index(counts: DataFrame, points: DataFrame, queries: DataFrame, threshold: int) -> DataFrame:
    """(q_obj, object_id, num, den): pairs with enough collisions, of all pairs; objects without any are left out."""
    close = counts.where(F.col("cc") >= threshold).groupBy("q_obj", "object_id").agg(F.count("*").alias("num"))
    sizes = object_sizes(points)
    own = object_sizes(queries).select(F.col("object_id").alias("q_obj"), F.col("n_points").alias("n_query"))
    return close.join(sizes, "object_id").join(own, "q_obj").select("q_obj", "object_id", "num", (F.col("n_points") * F.col("n_query")).alias("den"))


def gamma_candidates(index: DataFrame, gamma: tuple[int, int], eps: tuple[int, int] = (1, 5)) -> DataFrame:
    """Objects whose collision index reaches (1 - eps) gamma, in integers."""
    return index.where(F.col("num") * (gamma[1] * eps[1]) >= F.col("den") * ((eps[1] - eps[0]) * gamma[0]))


def gamma_false_positives(index: DataFrame, distances: DataFrame, family: Family, gamma: tuple[int, int], n_objects: int, radius: int, c: int = 2) -> DataFrame:
    """Objects with an index of at least gamma + beta/2 whose distance is over c times the radius; beta = 25 / n_objects."""
    d = 2 * gamma[1] * n_objects
    high = F.col("num") * d >= F.col("den") * (2 * n_objects * gamma[0] + 25 * gamma[1])
    return index.where(high).join(distances.select("q_obj", "object_id", "sq_dist"), ["q_obj", "object_id"]).where(F.col("sq_dist") > (c * radius * family.unit) ** 2).select("q_obj", "object_id", "num", "den", "sq_dist")
