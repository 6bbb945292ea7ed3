"""The experiment workloads on the given tables."""

from __future__ import annotations

import time
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from objann.functions.params import derive_params, fp_bound, gamma_min, point_error_rates
from objann.operators import buffers
from objann.operators.gamma import by_object, gamma_distance, object_blocks
from objann.operators.hashing import Projections, make_projections
from objann.operators.index import Index, build_index
from objann.operators.kernel import CloseAt, QuerySet, block_sq_dist, query_batches, side_by_side
from objann.operators.metrics import object_ratio
from objann.operators.pointknn import borda, hashed_knn, hashed_lists, linear_knn
from objann.operators.search import _Search, highest_stop, located, object_knn, object_knn_of
from objann.sources.families import DOC, EMB, SUPP, TWIN, USER, Family, object_sizes, pick_queries, points
from objann.sources.tables import load_table, written

HALF, QUARTER = (1, 2), (1, 4)
# the stated query sets; they grow with the tables, but for the fixed objects of the planted pairs
QUERIES = {"twin": "object_id IN (8, 98, 23, 77, 17, 80)", "user": "object_id % 150 = 3", "doc": "object_id % 250 = 7", "supp": "object_id % 500 = 1", "emb": "object_id % 10 = 0"}
# share of false positives: 25 over the number of objects at scale 0.01
BETA = {"twin": 0.25, "user": 25 / 150, "doc": 0.025, "supp": 0.25, "emb": 0.999}
FAMILIES = {f.name: f for f in (TWIN, USER, DOC, SUPP, EMB)}

_indexes: dict[tuple, Index] = {}


def projections(name: str, kind: str = "static", **options) -> Projections:
    return make_projections(FAMILIES[name], derive_params(kind, beta=BETA[name]), **options)


def family_points(spark: SparkSession, sf_dir: str, name: str) -> tuple[DataFrame, DataFrame]:
    """All points of a family, and those of its stated query set."""
    return points(spark, sf_dir, FAMILIES[name]), points(spark, sf_dir, FAMILIES[name], QUERIES[name])


def stored_index(spark: SparkSession, sf_dir: str, name: str, kind: str = "static", **options) -> Index:
    """The family's index, built once in a session, as an index is built offline."""
    key = (spark.sparkContext.applicationId, sf_dir, name, kind, tuple(sorted(options.items())))
    if key in _indexes:
        try:
            _indexes[key].sizes.isEmpty()
        except Exception:  # the folder it lay in is gone
            del _indexes[key]
    if key not in _indexes:
        _indexes[key] = build_index(points(spark, sf_dir, FAMILIES[name]), projections(name, kind, **options))
    return _indexes[key]


def union(parts) -> DataFrame:
    return reduce(DataFrame.union, parts)


def random_queries(p: DataFrame, n: int = 10) -> DataFrame:
    """The points of n objects in the order of a hash of their ids."""
    return written(p.join(F.broadcast(pick_queries(p, n)), "object_id", "left_semi"), "queries")


def timed(make) -> tuple[DataFrame, float]:
    """(the rows, written, and the seconds that took)."""
    began = time.time()
    return written(make(), "timed"), round(time.time() - began, 3)


def method_grid(spark: SparkSession, sf_dir: str, name: str, gamma: tuple[int, int] = QUARTER, k: int = 25, k_primes=(25, 50, 100), n_queries: int = 10) -> DataFrame:
    """(method, k_prime, q_obj, object_ratio, coverage, n_undefined, seconds): object search against the three fused
    baselines, for random query objects of one family.  Seconds are of the whole query set, without building the index; a
    baseline's lists are made once for all k', and their seconds are in each row's."""
    family, index = FAMILIES[name], stored_index(spark, sf_dir, name)
    q = random_queries(index.points, n_queries)
    proj, centred = index.proj, projections(name, "query")
    distances = written(gamma_distance(index.points, q, family, gamma), "distances")
    order = Window.partitionBy("q_obj").orderBy("sq_dist", "object_id")
    truth = distances.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("q_obj", "rank", "object_id", "sq_dist")

    def row(method: str, k_prime: int, make, before: float = 0) -> DataFrame:
        found, seconds = timed(make)
        return object_ratio(found.select("q_obj", "object_id"), truth, distances).select(F.lit(method).alias("method"), F.lit(k_prime).alias("k_prime"), "*", F.lit(round(before + seconds, 3)).alias("seconds"))

    out = [row("object_search", 0, lambda: object_knn(index, q, family, gamma, k).result)]
    # a list of the largest k' begins with those of the others; hashed ones stop at different events of the same passes
    linear = timed(lambda: linear_knn(index.points, q, max(k_primes)))
    hashed = {method: timed(lambda p=p: hashed_lists(index.points, q, family, p, tuple(k_primes))) for method, p in (("static", proj), ("query_centred", centred))}
    for k_prime in k_primes:
        lists = {"linear": (linear[0].where(F.col("rank") <= k_prime), linear[1])}
        lists |= {method: (every.where(F.col("k_prime") == k_prime), took) for method, (every, took) in hashed.items()}
        out += [row(method, k_prime, lambda own=own: borda(own, k_prime, k), took) for method, (own, took) in lists.items()]
    return union(out)


def k_sweep(spark: SparkSession, sf_dir: str, name: str, gamma: tuple[int, int] = QUARTER, ks=(1, 5, 10, 25, 50, 100), k_prime: int = 50) -> DataFrame:
    """(method, k, object_ratio, seconds) of object search and of fused static-bucket lists: means over the stated query set.

    The counts of the search, as the lists, are made once for all k; their seconds are in each row's.
    """
    family, index = FAMILIES[name], stored_index(spark, sf_dir, name)
    q = written(index.points.where(QUERIES[name]), "queries")
    distances = written(gamma_distance(index.points, q, family, gamma), "distances")
    order = Window.partitionBy("q_obj").orderBy("sq_dist", "object_id")
    ranked = written(distances.withColumn("rank", F.row_number().over(order)), "ranked")
    lists, list_seconds = timed(lambda: hashed_knn(index.points, q, family, index.proj, k_prime))
    began = time.time()
    searched = object_knn_of(index, q, family, gamma, tuple(ks))
    search_seconds = time.time() - began
    out = []
    for k in ks:
        truth = ranked.where(F.col("rank") <= k)
        mine, seconds = timed(lambda k=k: searched[k])
        fused, fuse_seconds = timed(lambda k=k: borda(lists, k_prime, k))
        for method, found, took in (("object_search", mine, round(search_seconds + seconds, 3)), ("static", fused, round(list_seconds + fuse_seconds, 3))):
            ratio = object_ratio(found.select("q_obj", "object_id"), truth, distances)
            out.append(ratio.agg(F.lit(method).alias("method"), F.lit(k).alias("k"), F.round(F.avg("object_ratio"), 6).alias("object_ratio"), F.lit(took).alias("seconds")))
    return union(out)


# buffer-conscious processing


def stop_levels(points: DataFrame, queries: DataFrame, name: str, gamma: tuple[int, int] = QUARTER, k: int = 25) -> int:
    """The highest level at which a search of the query set stops: what its trace reads."""
    return highest_stop(points, queries, FAMILIES[name], projections(name), gamma, k)


class BufferRuns:
    """Traces of a family's query set up to the level where its searches stop, and their replay at a share of the index."""

    def __init__(self, spark: SparkSession, sf_dir: str, name: str, n_random: int = 500):
        self.name, self.proj = name, projections(name)
        self.points, self.queries = family_points(spark, sf_dir, name)
        self.points, self.queries = written(self.points, "points"), written(self.queries, "queries")
        self.levels = stop_levels(self.points, self.queries, name)
        self.entries = self.points.count() * self.proj.params.m * buffers.ENTRY_BYTES
        self.catalog = written(buffers.bucket_catalog(self.points, self.proj), "catalog")
        self.sample = buffers.random_points(self.points, n_random, FAMILIES[name].dim)
        self.n_query = self.queries.count() / max(1, self.queries.select("object_id").distinct().count())
        self._needs = None

    def estimate(self, **options) -> DataFrame:
        sample = written(self.sample, "sample")
        return buffers.estimated_frequency(self.points, sample, self.proj, self.n_query, max(1, sample.count()), levels=self.levels, catalog=self.catalog, **options)

    def costs(self, replays: list[buffers.Replay], shapes=("equal_width",)) -> DataFrame:
        """Costs by query object of each replay; a column of the pages by the name of each shape holds its estimates."""
        pages = self.catalog.select("proj", "bucket", "bytes")
        for shape in shapes:
            pages = pages.join(self.estimate(shape=shape).select("proj", "bucket", F.col("est_freq").alias(shape)), ["proj", "bucket"])
        # as many rows as the index has buckets, which the width of a bucket and the ladder bound
        return buffers.replayed_costs(self.queries, pages.toPandas(), self.proj, self.levels, replays)

    def proposed(self, share: float, name: str = "proposed", n_splits: int = buffers.SPLITS, shape: str = "equal_width", frequencies: str = "estimated", **options) -> buffers.Replay:
        return buffers.Replay(name, "frequency", self.capacity(share), n_splits, estimate=shape, options=tuple({"frequencies": frequencies, **options}.items()))

    def capacity(self, share: float) -> int:
        return int(share * self.entries)


def buffer_costs(spark: SparkSession, sf_dir: str, name: str, share: float = 0.096) -> DataFrame:
    """Modelled cost by query object of LRU, one load per bucket, and the proposed eviction on split queries: with frequencies
    estimated offline as a real query has them, and with exact ones as a bound."""
    runs = BufferRuns(spark, sf_dir, name)
    plain = [buffers.Replay(policy, policy, runs.capacity(share)) for policy in ("lru", "per_bucket")]
    return runs.costs([*plain, runs.proposed(share), runs.proposed(share, "proposed_exact", frequencies="exact")])


def buffer_size_sweep(spark: SparkSession, sf_dir: str, name: str, shares=(0.064, 0.096, 0.128, 0.16)) -> DataFrame:
    """(policy, share, seeks, mb, alg_ms, io_ms, total_ms): the proposed strategy against point searches with an LRU buffer; 20 to 50 MB of the index that the shares stand for."""
    runs = BufferRuns(spark, sf_dir, name)
    replays = [r for share in shares for r in (runs.proposed(share), buffers.Replay("static_lru", "lru", runs.capacity(share), schedule="independent"))]
    sizes = F.create_map(*[F.lit(x) for share in shares for x in (runs.capacity(share), share)])
    costs = runs.costs(replays).withColumn("share", sizes[F.col("buffer_bytes")])
    return _mean_costs(costs, "policy", "share").select("policy", *MEANS, "share")


MEANS = ("hits", "seeks", "evictions", "mb", "alg_ms", "io_ms", "total_ms")


def _mean_costs(costs: DataFrame, *by: str) -> DataFrame:
    return costs.groupBy(*(by or ("policy",))).agg(*[F.round(F.avg(c), 6).alias(c) for c in MEANS])


def split_sweep(spark: SparkSession, sf_dir: str, name: str, splits=(1, 2, 5, 10, 20, 50), share: float = 0.096) -> DataFrame:
    """(n_splits, seeks, mb, alg_ms, io_ms, total_ms, picked): the proposed strategy by number of slices, and the number that an index would keep."""
    runs = BufferRuns(spark, sf_dir, name)
    costs = _mean_costs(runs.costs([runs.proposed(share, str(n), n) for n in splits]))
    costs = written(costs.select(*MEANS, F.col("policy").cast("int").alias("n_splits")), "split-costs")
    return costs.withColumn("picked", F.col("n_splits") == buffers.pick_split(costs))


def buffer_ablation(spark: SparkSession, sf_dir: str, name: str, share: float = 0.096) -> DataFrame:
    """Mean costs of the proposed eviction, and with each of its criteria, the estimate's form and the splits changed."""
    runs = BufferRuns(spark, sf_dir, name)
    changed = {
        "proposed": {},
        "no_recency": {"recent_frac": 0.0},
        "no_distance": {"far_frac": 0.0},
        "no_frequency": {"use_frequency": False},
        "equal_depth": {"shape": "equal_depth"},
        "unsplit": {"n_splits": 1},
        "exact": {"frequencies": "exact"},
    }
    return _mean_costs(runs.costs([runs.proposed(share, n, **options) for n, options in changed.items()], ("equal_width", "equal_depth")))


def exact_counts(runs: BufferRuns, queries: DataFrame) -> DataFrame:
    return buffers.bucket_needs(runs.points, queries, runs.proj, runs.levels, runs.catalog).groupBy("proj", "bucket").agg(F.count("*").alias("exact_freq"))


def frequency_curves(spark: SparkSession, sf_dir: str, name: str, proj: int = 1) -> DataFrame:
    """(bucket, region, real, random, est_freq) on one projection: how often each bucket is needed by the points of a real query
    object, by as many random points, and by the estimate."""
    runs = BufferRuns(spark, sf_dir, name)
    first = runs.queries.agg(F.min("object_id")).first()[0]
    one = runs.queries.where(F.col("object_id") == first)
    n, total = one.count(), max(1, runs.sample.count())
    real = exact_counts(runs, one).withColumnRenamed("exact_freq", "real")
    random = exact_counts(runs, runs.sample).select("proj", "bucket", F.round(F.col("exact_freq") * n / total, 6).alias("random"))
    curves = runs.estimate().where(F.col("proj") == proj).join(real, ["proj", "bucket"], "left").join(random, ["proj", "bucket"], "left")
    return curves.select("bucket", "region", F.coalesce("real", F.lit(0)).alias("real"), F.coalesce("random", F.lit(0.0)).alias("random"), "est_freq")


def frequency_errors(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """(shape, proj, mae, corr) of the estimates against the exact accesses of the query set, per query object."""
    runs = BufferRuns(spark, sf_dir, name)
    objects = max(1, runs.queries.select("object_id").distinct().count())
    exact = written(exact_counts(runs, runs.queries).withColumn("exact_freq", F.col("exact_freq") / objects), "exact")
    return union([buffers.frequency_error(exact, runs.estimate(shape=shape)).select(F.lit(shape).alias("shape"), "*") for shape in ("equal_width", "equal_depth")])


# the guarantee


RATES = ["hit", "inside", "fp", "near", "near_close", "far", "far_close"]


def close_rates(p: DataFrame, q: QuerySet, family: Family, projs: list[Projections], levels: list[int], gamma: tuple[int, int], eps: tuple[int, int]) -> DataFrame:
    """(seed, level, q_obj, hit, inside, fp, near, near_close, far, far_close) for every set of projections and level.

    Of the objects within the radius (inside) those that are candidates (hit), and the false positives (fp); of the pairs within
    the radius and beyond c times it, those that reach the threshold.  An object's points meet in one task: it is within the
    radius if as many of its pairs as the share's rank are, so sums over objects leave a task, not objects.
    """
    params, q = projs[0].params, side_by_side(q)
    near_limits, far_limits = (projs[0].squared_radii(family.unit, step) for step in (1, params.c))
    groups, m = q.objects(), params.m
    begin = np.array([a for _, a, _ in groups])

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at = [CloseAt(proj.hashes(q.vec), begin, proj.limits(), m, params.l) for proj in projs]
        sums = np.zeros((len(projs), len(levels), len(groups), len(RATES)), np.int64)
        for _, sizes, begins, vec in object_blocks(batches, family.dim):
            known = np.zeros(len(vec), bool)
            known[np.repeat(begins - (np.cumsum(sizes) - sizes), sizes) + np.arange(sizes.sum())] = True
            ends = begins + -(-sizes // 8) * 8
            pad = -len(vec) % 64
            bits = {}
            for s, proj in enumerate(projs):
                own = at[s].block(proj.hashes(vec), np.repeat(known[:, None], m, axis=1), begins, ends)
                for g, (_, a, b) in enumerate(groups):
                    pairs = (b - a) * sizes
                    if not s:
                        d = np.pad(block_sq_dist(q.vec[a:b], vec), ((0, 0), (0, pad)))
                        real = np.pad(known, (0, pad))
                        for i, t in enumerate(levels):
                            near, far = (np.packbits(x & real, axis=1).view(np.uint64) for x in (d <= near_limits[t], d > far_limits[t]))
                            bits[g, i] = near, far, own.by_object(near), own.by_object(far)
                    rank = np.maximum(1, -(-pairs * gamma[0] // gamma[1]))
                    for i, t in enumerate(levels):
                        near, far, n_near, n_far = bits[g, i]
                        close, near_close, far_close = np.zeros(len(sizes), np.int64), 0, 0
                        for x, e, done in own.close(g, t * (m + 1) + m):
                            close += own.by_object(done)
                            near_close += int(np.bitwise_count(done & near[x:e]).sum(dtype=np.int64))
                            far_close += int(np.bitwise_count(done & far[x:e]).sum(dtype=np.int64))
                        candidate = close * (eps[1] * gamma[1]) >= pairs * ((eps[1] - eps[0]) * gamma[0])
                        high = close >= pairs * (gamma[0] / gamma[1] + params.beta / 2)
                        within, beyond = n_near >= rank, pairs - n_far < rank
                        sums[s, i, g] += [(within & candidate).sum(), within.sum(), (high & beyond).sum(), n_near.sum(), near_close, n_far.sum(), far_close]
        s, i, g = (x.ravel() for x in np.indices(sums.shape[:3]))
        columns = [s, np.array(levels)[i], np.array([name for name, _, _ in groups])[g], *sums.reshape(-1, len(RATES)).T]
        yield pa.RecordBatch.from_arrays([pa.array(np.ascontiguousarray(c).astype(np.int64)) for c in columns], ["seed", "level", "q_obj", *RATES])

    raw = by_object(p).mapInArrow(count, "seed long, level long, q_obj long, " + ", ".join(f"{c} long" for c in RATES))
    return raw.groupBy("seed", "level", "q_obj").agg(*[F.sum(c).alias(c) for c in RATES])


def guarantee_rates(spark: SparkSession, sf_dir: str, name: str, gamma: tuple[int, int] = QUARTER, seeds: int = 20, eps=(1, 5)) -> DataFrame:
    """(seed, level, p1, p1_target, false_positives, allowed, p2, fp_bound, near_rate, near_target, far_miss_rate, far_target).

    For every seed, at each level that separates near from far objects: p1 is the share of the
    objects within the radius that are candidates; p2 tells whether the false positives of every query object
    stay within beta S; the last four are the point rates behind them, with the least rates proven.
    """
    family = FAMILIES[name]
    p, queries = family_points(spark, sf_dir, name)
    p = written(p, "points")
    queries = written(queries, "queries")
    distances = gamma_distance(p, queries, family, gamma)
    sizes = object_sizes(p).agg(F.count("*").alias("s"), F.min("n_points").alias("least")).first()
    params = derive_params("static", beta=BETA[name])
    projs = [make_projections(family, params, seed=seed) for seed in range(seeds)]
    near_target, far_target = point_error_rates(params)
    radii = projs[0].squared_radii(family.unit)
    spread = distances.agg(F.min(F.when(F.col("q_obj") != F.col("object_id"), F.col("sq_dist"))).alias("low"), F.max("sq_dist").alias("high")).first()
    levels = separating_levels(radii, spread.low, spread.high)
    each, least_query = [], []
    for q in query_batches(queries):
        least_query.append(min(q.sizes().values()))
        each.append(close_rates(p, q, family, projs, levels or [0], gamma, eps))
    allowed = min(params.beta, 0.999) * sizes.s
    return (
        union(each)
        .groupBy("seed", F.col("level").cast("int").alias("level"))
        .agg(
            F.round(F.try_divide(F.sum("hit"), F.sum("inside")), 6).alias("p1"),
            F.lit(round(1 - params.delta, 6)).alias("p1_target"),
            F.max("fp").alias("false_positives"),
            F.lit(round(allowed, 6)).alias("allowed"),
            (F.max("fp") <= allowed).alias("p2"),
            F.lit(round(fp_bound(sizes.s, params.beta, gamma[0] / gamma[1], min(least_query), sizes.least), 6)).alias("fp_bound"),
            F.round(F.try_divide(F.sum("near_close"), F.sum("near")), 6).alias("near_rate"),
            F.lit(round(near_target, 6)).alias("near_target"),
            F.round(1 - F.try_divide(F.sum("far_close"), F.sum("far")), 6).alias("far_miss_rate"),
            F.lit(round(far_target, 6)).alias("far_target"),
        )
    )


def separating_levels(radii: list[int], low: int | None, high: int | None) -> list[int]:
    """All levels from the first whose squared radius holds an object to the one after the first that holds them all."""
    if low is None or high is None:
        return []
    last = 1 + next((t for t, r in enumerate(radii) if r >= high), len(radii) - 1)
    return [t for t, r in enumerate(radii) if low <= r and t <= last]


def c2_rates(spark: SparkSession, sf_dir: str, name: str, gamma: tuple[int, int] = QUARTER, seeds: int = 20) -> DataFrame:
    """(seed, q_obj, c2): whether the object returned, the query itself left out, is within c squared of the nearest one.

    The counts of all seeds come from one pass over the points: a query object and a seed make one query.
    """
    family = FAMILIES[name]
    p, queries = family_points(spark, sf_dir, name)
    p, queries = written(p, "points"), written(queries, "queries")
    params = derive_params("static", beta=BETA[name])
    projs = [make_projections(family, params, seed=seed) for seed in range(seeds)]
    sizes = written(object_sizes(p), "object-sizes")
    distances = written(gamma_distance(p, queries, family, gamma).where("q_obj <> object_id"), "distances")
    truth = distances.groupBy("q_obj").agg(F.min("sq_dist").alias("best"))
    index = Index(p, p, sizes, projs[0], sizes.count(), 0)
    search = _Search(index, family, gamma, 1, (1, 5), "carry", "R", "distance", True)
    out = []
    for q in query_batches(queries):
        named = QuerySet(np.concatenate([q.q_obj * seeds + s for s in range(seeds)]), np.tile(q.q_id, seeds), np.tile(q.vec, (seeds, 1)))
        known = seeded_stops(p, sizes, q, projs, gamma, search.enough)
        keys = written(seeded_keys(p, q, projs, gamma, search.enough, known), "keys")
        many = keys.select("q_obj", "object_id", F.expr(f"q_obj div {seeds}").alias("own")).join(distances.withColumnRenamed("q_obj", "own"), ["own", "object_id"])
        found = search.finish(keys, written(many.select("q_obj", "object_id", "sq_dist"), "key-distances"), named, projs[0].levels).result
        split = found.select(F.expr(f"q_obj % {seeds}").alias("seed"), F.expr(f"q_obj div {seeds}").alias("q_obj"), "sq_dist")
        out.append(split.join(truth, "q_obj").select("seed", "q_obj", (F.col("sq_dist") <= F.col("best") * params.c**4).cast("int").alias("c2")))
    return union(out)


SHARE = 16  # one of so many objects is searched first
KEYED = 1 << 15  # points of a block of ``seeded_keys``


def seeded_stops(p: DataFrame, sizes: DataFrame, q: QuerySet, projs: list[Projections], gamma: tuple[int, int], enough: int) -> dict[int, int]:
    """By query of ``seeded_keys``, the event by which one of SHARE objects are ``enough`` candidates: among all objects there are as many no later."""
    if sizes.count() < 2 * SHARE * enough:
        return {}
    some = p.where(F.pmod(F.xxhash64("object_id"), F.lit(SHARE)) == 0)
    order = Window.partitionBy("q_obj").orderBy("key", "object_id")
    keys = seeded_keys(some, q, projs, gamma, enough, few=True).withColumn("at", F.row_number().over(order))
    return {r.q_obj: r.key for r in keys.where(F.col("at") == enough).collect()}  # one number for each query


def seeded_keys(
    p: DataFrame, q: QuerySet, projs: list[Projections], gamma: tuple[int, int], enough: int, known: dict[int, int] | None = None, few: bool = False, eps: tuple[int, int] = (1, 5)
) -> DataFrame:
    """(q_obj, object_id, key) of all seeds in one pass over the points, without a query object itself; query object o and
    seed s are query o * seeds + s.

    A task leaves out what becomes a candidate after ``enough`` others that it knows, as no search goes on to there, or after
    the event that ``known`` has for a query.  ``few`` objects are dealt to no more tasks than run at once.
    """
    q = side_by_side(q)
    m, levels, groups = projs[0].params.m, [proj.levels for proj in projs], q.objects()
    num, den = (eps[1] - eps[0]) * gamma[0], eps[1] * gamma[1]
    begin = np.array([a for _, a, _ in groups])

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at = [CloseAt(proj.hashes(q.vec), begin, proj.limits(), m, proj.params.l) for proj in projs]
        best = {(s, g): np.zeros(0, np.int64) for s in range(len(projs)) for g in range(len(groups))}
        guess = 1 << 62  # the end of the level at which the last search had enough
        for names, sizes, begins, vec in object_blocks(batches, q.vec.shape[1], KEYED):
            real = np.zeros((len(vec), m), bool)
            real[np.repeat(begins - (np.cumsum(sizes) - sizes), sizes) + np.arange(sizes.sum())] = True
            out = []
            for s, proj in enumerate(projs):
                own = at[s].block(proj.hashes(vec), real, begins, begins + -(-sizes // 8) * 8)
                for g, (name, a, b) in enumerate(groups):
                    need, first = -(-(b - a) * sizes * num // den), best[s, g]
                    last = (known or {}).get(name * len(projs) + s, levels[s] * (m + 1) + m)
                    key = min(last, int(first[enough - 1])) if len(first) >= enough else last
                    n = own.counts(g, min(key, guess))
                    if guess < key:
                        if ((n >= need) & (names != name)).sum() >= enough:
                            key = guess
                        else:
                            n = own.counts(g, key)
                    some = np.flatnonzero((n >= need) & (names != name))
                    if len(some):
                        found = located(own.some(some), g, m, need[some], key, n[some], enough)
                        out += [(name * len(projs) + s, int(names[some[o]]), event) for o, event, _ in found]
                        best[s, g] = np.sort(np.append(first, [event for _, event, _ in found]))[:enough].astype(np.int64)
                        if len(best[s, g]) == enough:
                            guess = int(best[s, g][-1]) // (m + 1) * (m + 1) + m
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(np.array(c, np.int64)) for c in zip(*out)], ["q_obj", "object_id", "key"])

    dealt = by_object(p)
    return (dealt.coalesce(p.sparkSession.sparkContext.defaultParallelism) if few else dealt).mapInArrow(count, "q_obj long, object_id long, key long")


def parameter_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(family, n_objects, static_m, static_l, query_m, query_l) for beta = 25 over the number of objects that the tables hold."""
    lines, events = load_table(spark, sf_dir, "lineitem"), load_table(spark, sf_dir, "events")
    counts = union([t.agg(F.lit(name).alias("family"), F.countDistinct(key).alias("n")) for name, t, key in (("supp", lines, "l_suppkey"), ("part", lines, "l_partkey"), ("order", lines, "l_orderkey"), ("user", events, "user_id"))])
    rows = []
    for r in counts.collect():
        a, b = (derive_params(kind, beta=25 / max(1, r.n)) for kind in ("static", "query"))
        rows.append((r.family, r.n, a.m, a.l, b.m, b.l))
    return spark.createDataFrame(rows, "family string, n_objects int, static_m int, static_l int, query_m int, query_l int")


def gamma_bounds(sizes: DataFrame, delta: float = 0.1, eps: float = 0.2) -> DataFrame:
    """(n_objects, least_size, mean_size, bound) of one family, from its object sizes (one row)."""
    r = sizes.agg(F.count("*").alias("s"), F.min("n_points").alias("least"), F.avg("n_points").alias("mean")).first()
    beta = min(0.999, 25 / r.s)
    return sizes.sparkSession.createDataFrame([(r.s, r.least, round(r.mean, 6), round(gamma_min(r.mean, r.least, delta, eps, beta), 6))], "n_objects long, least_size long, mean_size double, bound double")
