"""Access traces of a bucket index, buffer replacement models and their cost."""

from __future__ import annotations

from collections import OrderedDict
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from objann.functions.fixedpoint import floor_div
from objann.operators.hashing import Projections, inverted, level_bucket
from objann.operators.kernel import blocks

SEEK_MS, MB_PER_MS = 8.5, 0.156  # fixed values of the disk model
ENTRY_BYTES = 8
REGIONS, SPLITS = 10, 10
STEP_MS = 0.001  # modelled time of one lookup or one bucket handed to a query
POLICIES = ("lru", "per_bucket", "frequency")


def bucket_catalog(points: DataFrame, proj: Projections) -> DataFrame:
    """(proj, bucket, n_points, bytes); a task counts a batch of points, so what is moved are buckets, not points by projection."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, _, vec in blocks(batches, proj.params.m):
            yield bucket_counts(proj.hashes(vec))

    raw = points.select("object_id", "point_id", "vec").mapInArrow(count, "proj int, bucket long, n long")
    return raw.groupBy("proj", "bucket").agg(F.sum("n").alias("n_points"), (F.sum("n") * ENTRY_BYTES).alias("bytes"))


def bucket_counts(hashes: np.ndarray) -> pa.RecordBatch:
    """(proj, bucket, n) of the hashes of some points."""
    low = hashes.min(axis=0)
    span, m = int((hashes - low).max()) + 1, hashes.shape[1]
    if span <= 16 * len(hashes):
        codes = hashes - low + np.arange(m) * span
        counts = np.bincount(codes.ravel(), minlength=m * span)
        found = np.flatnonzero(counts)
        proj, bucket, n = found // span, found % span + low[found // span], counts[found]
    else:
        parts = [np.unique(hashes[:, j], return_counts=True) for j in range(m)]
        proj, bucket, n = np.repeat(np.arange(m), [len(p[0]) for p in parts]), np.concatenate([p[0] for p in parts]), np.concatenate([p[1] for p in parts])
    return pa.RecordBatch.from_arrays([pa.array((proj + 1).astype(np.int32)), pa.array(bucket.astype(np.int64)), pa.array(n.astype(np.int64))], ["proj", "bucket", "n"])


def bucket_needs(points: DataFrame, queries: DataFrame, proj: Projections, levels: int | None = None, catalog: DataFrame | None = None) -> DataFrame:
    """(q_obj, level, proj, q_id, low, length, bucket, bytes): what each query point needs anew at each level.

    A level's bucket is a range of base buckets from ``low``; only the part that the level before
    did not have is read.  Joined by the widest level's bucket, so it is an equi-join.  A search that
    stops at level t needs ``levels`` = t.  ``catalog`` is the points' ``bucket_catalog``, where that is known.
    """
    c, top = int(proj.params.c), proj.levels if levels is None else levels
    catalog = (bucket_catalog(points, proj) if catalog is None else catalog).withColumn("cell", level_bucket(F.col("bucket"), c**top))
    own = inverted(queries, proj).select(F.col("object_id").alias("q_obj"), F.col("point_id").alias("q_id"), "proj", F.col("bucket").alias("own"))
    own = own.withColumn("cell", level_bucket(F.col("own"), c**top))
    level = F.lit(top)
    for t in range(top - 1, -1, -1):
        level = F.when(level_bucket(F.col("own"), c**t) == level_bucket(F.col("bucket"), c**t), F.lit(t)).otherwise(level)
    radius = F.pow(F.lit(c), F.col("level")).cast("long")
    found = own.join(catalog, ["proj", "cell"]).withColumn("level", level)
    return found.withColumn("low", F.col("own") - F.pmod(F.col("own"), radius)).withColumn("length", radius).select("q_obj", "level", "proj", "q_id", "low", "length", "bucket", "bytes")


def sliced(needs: DataFrame, n_splits: int) -> DataFrame:
    """``needs`` with split_id and the split's start: each query point's own range in equal slices."""
    slices = F.least(F.lit(n_splits).cast("long"), F.col("length"))
    size = F.ceil(F.col("length") / slices).cast("long")
    return needs.withColumn("split_id", floor_div(F.col("bucket") - F.col("low"), size).cast("int")).withColumn("start", F.col("low") + F.col("split_id") * size)


def access_trace(points: DataFrame, queries: DataFrame, proj: Projections, n_splits: int = 1, levels: int | None = None, schedule: str = "joint", catalog: DataFrame | None = None) -> DataFrame:
    """``bucket_needs`` in order.

    joint: per level and projection, slices of all query points' ranges by start and point.
    independent: one query point after the other, as point searches run.
    """
    cut = sliced(bucket_needs(points, queries, proj, levels, catalog), n_splits)
    first = ["level", "proj", "start", "q_id", "bucket"] if schedule == "joint" else ["q_id", "level", "proj", "bucket"]
    order = Window.partitionBy("q_obj").orderBy(*first)
    return cut.select("q_obj", F.row_number().over(order).cast("long").alias("seq"), "level", "proj", "q_id", "bucket", "bytes", "split_id", "start")


def exact_frequency(trace: DataFrame) -> DataFrame:
    """The trace with how often each bucket is still needed from here on."""
    rest = Window.partitionBy("q_obj", "proj", "bucket").orderBy("seq").rowsBetween(0, Window.unboundedFollowing)
    return trace.withColumn("remaining", F.count("*").over(rest))


def region_of(bucket: Column, low: Column, high: Column, regions: int = REGIONS) -> Column:
    return F.least(F.lit(regions - 1), floor_div((bucket - low) * regions, high - low + 1).cast("int"))


def estimated_frequency(points: DataFrame, sample: DataFrame, proj: Projections, n_query: int, n_random: int, regions: int = REGIONS, shape: str = "equal_width", levels: int | None = None, catalog: DataFrame | None = None) -> DataFrame:
    """(proj, bucket, region, est_freq): mean accesses by random query points over each region, for n_query points.

    Worked out offline, from any ``sample`` of n_random points: no query is known.  Regions cut a
    projection into equal widths, or (``equal_depth``) into equal numbers of buckets.
    """
    catalog = bucket_catalog(points, proj) if catalog is None else catalog
    if shape == "equal_width":
        span = catalog.groupBy("proj").agg(F.min("bucket").alias("low"), F.max("bucket").alias("high"))
        placed = catalog.join(F.broadcast(span), "proj").withColumn("region", region_of(F.col("bucket"), F.col("low"), F.col("high"), regions))
    else:
        placed = catalog.withColumn("region", F.ntile(regions).over(Window.partitionBy("proj").orderBy("bucket")) - 1)
    used = bucket_needs(points, sample, proj, levels, catalog).groupBy("proj", "bucket").agg(F.count("*").alias("used"))
    seen = placed.join(used, ["proj", "bucket"], "left").withColumn("used", F.coalesce("used", F.lit(0)))
    mean = seen.groupBy("proj", "region").agg(F.round(F.sum("used") * n_query / (F.count("*") * n_random), 6).alias("est_freq"))
    return placed.join(F.broadcast(mean), ["proj", "region"]).select("proj", "bucket", "region", "est_freq")


def random_points(points: DataFrame, n: int, dim: int, seed: int = 11, source: str = "data") -> DataFrame:
    """About n query points for the estimate: points of the data by a hash of their ids, or (``box``) uniform in the data's bounding box."""
    if source == "data":
        total = max(1, points.count())
        picked = points.where(F.pmod(F.xxhash64("point_id", F.lit(seed)), F.lit(1_000_000)) < int(1_000_000 * min(1.0, n / total)))
        return picked.select(F.lit(0).cast("long").alias("object_id"), "point_id", "vec")
    ends = points.agg(*[f(F.col("vec")[k]).alias(f"{name}{k}") for k in range(dim) for f, name in ((F.min, "low"), (F.max, "high"))]).first()
    rng = np.random.default_rng(seed)
    rows = [(0, i, [int(rng.integers(ends[f"low{k}"], ends[f"high{k}"] + 1)) for k in range(dim)]) for i in range(n)]
    return points.sparkSession.createDataFrame(rows, "object_id long, point_id long, vec array<long>")


def frequency_error(exact: DataFrame, estimate: DataFrame) -> DataFrame:
    """(proj, mae, corr) of exact against estimated access counts of all buckets; a bucket without accesses has none."""
    both = estimate.join(exact, ["proj", "bucket"], "left").withColumn("exact_freq", F.coalesce("exact_freq", F.lit(0)))
    spread = F.stddev_pop("exact_freq") * F.stddev_pop("est_freq")  # 0 where one of them is the same everywhere: no correlation then
    return both.groupBy("proj").agg(F.round(F.avg(F.abs(F.col("exact_freq") - F.col("est_freq"))), 6).alias("mae"), F.round(F.try_divide(F.covar_pop("exact_freq", "est_freq"), spread), 6).alias("corr"))


class FrequencyBuffer:
    """Evicts, of what is neither recent nor near, the page with the least remaining use.

    The newest ``recent_frac`` of the pages stay; of the rest those at least as far from the wanted
    bucket as the ``far_frac`` quantile count (pages of another projection are farthest); the least
    remaining use goes, ties to the farther, then the older.  Pages are columns of numbers in order of
    arrival, with the places of those that went until these are too many, so one choice is a few passes over them.
    """

    def __init__(self, capacity: int, remaining: dict, recent_frac: float = 0.1, far_frac: float = 0.5, use_frequency: bool = True):
        self.capacity, self.left = capacity, dict(remaining)
        self.size, self.recent, self.far, self.use_frequency = 0, recent_frac, far_frac, use_frequency
        self.slot: dict[tuple, int] = {}  # held pages
        self.sizes: dict[tuple, int] = {}
        self.pages: list[tuple] = []
        self.columns = np.zeros((3, 1024))  # projection, bucket, remaining use
        self.held = np.zeros(1024, bool)

    def access(self, page: tuple, size: int) -> tuple[bool, int]:
        """(hit, evictions)"""
        rest = self.left[page] = max(0, self.left.get(page, 0) - 1)
        if (at := self.slot.get(page)) is not None:
            self.columns[2, at] = rest
            return True, 0
        if size > self.capacity:
            return False, 0
        gone = 0
        while self.size + size > self.capacity:
            self._drop(self._victim(page))
            gone += 1
        at = len(self.pages)
        if at == len(self.held):
            at = self._pack()
        self.columns[:, at] = page[0], page[1], rest
        self.held[at] = True
        self.slot[page], self.sizes[page] = at, size
        self.pages.append(page)
        self.size += size
        return False, gone

    def _pack(self) -> int:
        """Held pages only, with as many free places at least."""
        old = np.flatnonzero(self.held)
        room = max(1024, 2 * len(old))
        self.columns = np.pad(self.columns[:, old], ((0, 0), (0, room - len(old))))
        self.held = np.arange(room) < len(old)
        self.pages = [self.pages[at] for at in old]
        self.slot = {page: at for at, page in enumerate(self.pages)}
        return len(old)

    def _drop(self, at: int) -> None:
        page = self.pages[at]
        self.size -= self.sizes.pop(page)
        del self.slot[page]
        self.held[at] = False

    def _victim(self, page: tuple) -> int:
        n = len(self.slot)
        old = np.flatnonzero(self.held[: len(self.pages)])[: n - int(n * self.recent)]
        projs, buckets, rest = self.columns
        far = np.abs(buckets[old] - page[1])
        far[projs[old] != page[0]] = np.inf
        limit = int((n - int(n * self.recent) - 1) * self.far)
        keep = np.flatnonzero(far >= np.partition(far, limit)[limit])
        if self.use_frequency:
            use = rest[old[keep]]
            keep = keep[use == use.min()]
        return int(old[keep[far[keep].argmax()]])


def replay(trace: pd.DataFrame, policy: str, capacity: int, frequencies: str = "exact", **options) -> dict:
    """Hits, misses, evictions, seeks, bytes read and lookups of one trace in order.

    frequency: ``frequencies`` is ``estimated`` (column est_freq of the trace, known offline) or
    ``exact`` (the accesses still to come, which no real query knows).  alg_cost counts lookups of
    a range or slice and buckets handed to a query point; per_bucket looks every loaded bucket up
    for all query points of its projection.
    """
    projs, buckets = trace["proj"].to_numpy(), trace["bucket"].to_numpy()
    pages = list(zip(projs.tolist(), buckets.tolist()))
    sizes, levels = trace["bytes"].tolist(), trace["level"].to_numpy()
    hits = misses = evictions = read = 0
    starts = np.stack([levels, projs, *[trace[c].to_numpy() for c in ("q_id", "split_id") if c in trace]], axis=1)
    lookups = int((starts[1:] != starts[:-1]).any(axis=1).sum()) + 1 if len(trace) else 0
    work = lookups + len(pages)
    if policy == "per_bucket":
        served = trace.drop_duplicates(["level", "proj", "bucket"])
        misses, read = len(served), int(served["bytes"].sum())
        hits = len(pages) - misses
        askers = trace.groupby(["level", "proj"])["q_id"].nunique() if "q_id" in trace else trace.groupby(["level", "proj"]).size()
        work = int(sum(askers[key] for key in zip(served["level"], served["proj"])))
    elif policy == "lru":
        held, size_held = OrderedDict(), 0
        for page, size in zip(pages, sizes):
            if page in held:
                held.move_to_end(page)
                hits += 1
                continue
            misses, read = misses + 1, read + size
            if size <= capacity:
                while size_held + size > capacity:
                    size_held -= held.popitem(last=False)[1]
                    evictions += 1
                held[page] = size
                size_held += size
    else:
        if frequencies == "estimated":
            known = dict(zip(pages, trace["est_freq"].tolist()))
        else:
            names, counts = np.unique(np.stack([projs, buckets], axis=1), axis=0, return_counts=True)
            known = dict(zip(map(tuple, names.tolist()), counts.tolist()))
        buffer = FrequencyBuffer(capacity, known, **options)
        for page, size in zip(pages, sizes):
            hit, gone = buffer.access(page, size)
            hits, evictions = hits + hit, evictions + gone
            if not hit:
                misses, read = misses + 1, read + size
    return {"hits": hits, "misses": misses, "evictions": evictions, "seeks": misses, "bytes_read": read, "alg_cost": work}


def simulate_buffer(trace: DataFrame, policy: str, capacity: int, name: str | None = None, **options) -> DataFrame:
    """(q_obj, policy, buffer_bytes, hits, misses, evictions, seeks, mb, alg_cost, alg_ms, io_ms, total_ms), one query object a group.

    A buffer is sequential, so a group is the trace of one query object, which the query's own
    size and the catalog bound; groups run in parallel.
    """

    def run(part: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame([_cost(part["q_obj"].iloc[0], part.sort_values("seq"), policy, capacity, name or policy, options)])

    return trace.groupBy("q_obj").applyInPandas(run, COSTS)


COSTS = "q_obj long, policy string, buffer_bytes long, hits long, misses long, evictions long, seeks long, alg_cost long, mb double, alg_ms double, io_ms double, total_ms double"


def _cost(q_obj: int, trace: pd.DataFrame, policy: str, capacity: int, name: str, options: dict) -> dict:
    found = replay(trace, policy, capacity, **options)
    mb = found.pop("bytes_read") / 1e6
    alg, io = found["alg_cost"] * STEP_MS, io_ms(found["seeks"], mb)
    return {"q_obj": q_obj, "policy": name, "buffer_bytes": capacity, **found, "mb": mb, "alg_ms": alg, "io_ms": io, "total_ms": alg + io}


@dataclass(frozen=True)
class Replay:
    """One way to replay the traces of query objects; ``estimate`` is the column of the pages that holds estimated frequencies."""

    name: str
    policy: str
    capacity: int
    n_splits: int = 1
    schedule: str = "joint"
    estimate: str | None = None
    options: tuple = ()


def object_trace(q_id: np.ndarray, hashes: np.ndarray, pages: dict[int, tuple[int, np.ndarray]], proj: Projections, levels: int, n_splits: int, schedule: str) -> pd.DataFrame:
    """``access_trace`` of one query object in order; ``page`` is a page's place, ``pages`` hold the first place and the buckets of each projection."""
    c, names, parts = int(proj.params.c), ["level", "proj", "start", "q_id", "bucket", "split_id", "page"], []
    for j, (place, buckets) in pages.items():
        own = hashes[:, j - 1]
        first, end = (np.searchsorted(buckets, (own // c**levels + x) * c**levels) for x in (0, 1))
        rows = np.repeat(np.arange(len(own)), end - first)
        at = np.arange(len(rows)) + np.repeat(first - (np.cumsum(end - first) - (end - first)), end - first)
        mine, bucket = own[rows], buckets[at]
        level = np.full(len(rows), levels)
        for t in range(levels - 1, -1, -1):
            level[mine // c**t == bucket // c**t] = t
        length = c**level
        low = mine - mine % length
        size = -(-length // np.minimum(n_splits, length))
        split = (bucket - low) // size
        parts.append((level, np.full(len(rows), j), low + split * size, q_id[rows], bucket, split, place + at))
    columns = dict(zip(names, map(np.concatenate, zip(*parts))))
    order = np.lexsort([columns[x] for x in (("bucket", "q_id", "start", "proj", "level") if schedule == "joint" else ("bucket", "proj", "level", "q_id"))])
    return pd.DataFrame({name: column[order] for name, column in columns.items()})


def replayed_costs(queries: DataFrame, pages: pd.DataFrame, proj: Projections, levels: int, replays: list[Replay]) -> DataFrame:
    """What ``simulate_buffer`` gives for each of ``replays``.  A query object's trace is made where it is replayed, from its
    points and the pages (proj, bucket, bytes and estimates), so no trace is moved or written."""
    pages = pages.sort_values(["proj", "bucket"], ignore_index=True)
    own = {int(j): (int(part.index[0]), part["bucket"].to_numpy()) for j, part in pages.groupby("proj")}
    data = {name: pages[name].to_numpy() for name in pages if name not in ("proj", "bucket")}

    def run(part: pd.DataFrame) -> pd.DataFrame:
        hashes, traces, out = proj.hashes(np.stack(part["vec"].to_list())), {}, []
        for r in replays:
            if (r.n_splits, r.schedule) not in traces:
                made = traces[r.n_splits, r.schedule] = object_trace(part["point_id"].to_numpy(), hashes, own, proj, levels, r.n_splits, r.schedule)
                made["bytes"] = data["bytes"][made["page"].to_numpy()]
            trace = traces[r.n_splits, r.schedule]
            if r.estimate:
                trace = trace.assign(est_freq=data[r.estimate][trace["page"].to_numpy()])
            out.append(_cost(int(part["object_id"].iloc[0]), trace, r.policy, r.capacity, r.name, dict(r.options)))
        return pd.DataFrame(out)

    spark = queries.sparkSession
    parts = 4 * max(int(spark.conf.get("spark.sql.shuffle.partitions")), spark.sparkContext.defaultParallelism)  # by number: few rows, much work
    return queries.select("object_id", "point_id", "vec").repartition(parts, "object_id").groupBy("object_id").applyInPandas(run, COSTS)


def io_ms(seeks, mb):
    """Modelled disk time of numbers or columns."""
    return seeks * SEEK_MS + mb / MB_PER_MS


def reuse_distances(trace: DataFrame) -> DataFrame:
    """(q_obj, seq, distance): different pages since the page's last use, null at its first; a buffer of more equal pages hits under LRU."""

    def run(part: pd.DataFrame) -> pd.DataFrame:
        part = part.sort_values("seq")
        recent: OrderedDict = OrderedDict()
        out = []
        for page in zip(part["proj"].tolist(), part["bucket"].tolist()):
            if page in recent:
                names = list(reversed(recent))
                out.append(names.index(page))
                recent.move_to_end(page)
            else:
                out.append(None)
                recent[page] = True
        return pd.DataFrame({"q_obj": part["q_obj"], "seq": part["seq"], "distance": pd.array(out, dtype="Int64")})

    return trace.groupBy("q_obj").applyInPandas(run, "q_obj long, seq long, distance long")


def lru_by_reuse_distance(trace: DataFrame, pages: int) -> DataFrame:
    """(q_obj, hits, misses) of an LRU buffer of equal pages: a hit has fewer than ``pages`` other pages since its last use."""
    hit = F.coalesce(F.col("distance") < pages, F.lit(False))
    return reuse_distances(trace).groupBy("q_obj").agg(F.sum(hit.cast("long")).alias("hits"), F.sum((~hit).cast("long")).alias("misses"))


def pick_split(costs: DataFrame) -> int:
    """The number of splits of the least mean total time, ties to the fewer, from rows of (n_splits, total_ms)."""
    best = costs.groupBy("n_splits").agg(F.avg("total_ms").alias("total_ms")).orderBy("total_ms", "n_splits").first()
    return int(best.n_splits)
