"""The stored bucket index: posting lists by projection and bucket, for blocks of points clustered by object."""

from __future__ import annotations

import json
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from objann.functions.fixedpoint import floor_div
from objann.operators.hashing import Projections
from objann.operators.kernel import check_range, run_lengths
from objann.sources.families import object_sizes
from objann.sources.tables import written

BLOCK_POINTS = 16_384  # at most 2^16 with the padding, so that a place in a block is two bytes
POSTINGS = "block long, proj int, bucket long, n int, members binary, hashes binary"


@dataclass
class Index:
    """(block, proj, bucket, n, members, hashes) posting lists, and (block, proj 0) directories.

    ``members`` are places in the block, two bytes each; ``hashes`` the projection values in the same
    order, for query-centred windows only.  A directory row holds the objects of the block and
    the byte at which each begins: objects begin at whole bytes of the bit matrices.
    """

    table: DataFrame
    points: DataFrame
    sizes: DataFrame
    proj: Projections
    n_objects: int
    n_points: int


def _posted(block: int, obj: np.ndarray, hashes: np.ndarray, proj: Projections) -> pa.RecordBatch:
    first, end = run_lengths(obj)
    padded = -(-(end - first) // 8) * 8
    begins = np.cumsum(padded) - padded
    place = np.repeat(begins - first, end - first) + np.arange(len(obj))
    blocks, projs, buckets, counts, members, values = [block], [0], [0], [int(padded.sum())], [begins.astype(np.int64).tobytes() + (end - first).astype(np.int64).tobytes()], [obj[first].astype(np.int64).tobytes()]
    for j in range(hashes.shape[1]):
        own = hashes[:, j]
        cells = own if proj.static else own // proj.width
        order = np.argsort(cells, kind="stable")
        a, b = run_lengths(cells[order])
        spots = place[order].astype(np.uint16)
        blocks += [block] * len(a)
        projs += [j + 1] * len(a)
        buckets += cells[order][a].tolist()
        counts += (b - a).tolist()
        members += [spots[x:y].tobytes() for x, y in zip(a.tolist(), b.tolist())]
        values += [None] * len(a) if proj.static else [own[order][x:y].tobytes() for x, y in zip(a.tolist(), b.tolist())]
    kinds = (pa.int64(), pa.int32(), pa.int64(), pa.int32(), pa.binary(), pa.binary())
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip((blocks, projs, buckets, counts, members, values), kinds)], ["block", "proj", "bucket", "n", "members", "hashes"])


def postings(points: DataFrame, proj: Projections, block_points: int = BLOCK_POINTS) -> DataFrame:
    """The rows of an index: one shuffle by object, then a block at a time.  Several objects of a block are whole; an object
    larger than a block lies in blocks of its own."""
    clustered = points.select("object_id", "point_id", "vec").repartitionByRange("object_id").sortWithinPartitions("object_id", "point_id")
    most = block_points - 16

    def post(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, made = TaskContext.get().partitionId(), 0
        held: list[tuple[np.ndarray, np.ndarray]] = []  # whole objects of the open block
        last: list[tuple[np.ndarray, np.ndarray]] = []  # pieces of the object that may go on
        room = size = 0

        def close():
            nonlocal held, room, made
            obj, hashes = (np.concatenate(c) for c in zip(*held))
            held, room, made = [], 0, made + 1
            return _posted((part << 32) + made, obj, hashes, proj)

        def place():
            """The last object is whole: it goes to the open block where it fits."""
            nonlocal held, last, room, size
            need = -(-size // 8) * 8 + 8
            if held and room + need > block_points:
                yield close()
            held, last, room, size = held + last, [], room + need, 0

        for batch in batches:
            obj = batch.column(0).to_numpy()
            vec = np.array(batch.column(2).flatten().to_numpy(zero_copy_only=False), dtype=np.int64).reshape(len(obj), -1)
            check_range(vec)
            first, end = run_lengths(obj)
            for a, b in zip(first.tolist(), end.tolist()):
                if last and last[0][0][0] != obj[a]:
                    yield from place()
                while a < b:
                    if size == most:  # too large for one block: what is there is a block of its own
                        if held:
                            yield close()
                        yield from place()
                        yield close()
                    stop = min(b, a + most - size)
                    last.append((obj[a:stop], proj.hashes(vec[a:stop])))
                    size += stop - a
                    a = stop
        if last:
            yield from place()
        if held:
            yield close()

    return clustered.mapInArrow(post, POSTINGS)


def build_index(points: DataFrame, proj: Projections, block_points: int = BLOCK_POINTS) -> Index:
    """Hashes every point once, offline, and writes the posting lists, sorted by projection and bucket in each file."""
    points = written(points, "points")
    table = postings(points, proj, block_points).sortWithinPartitions("proj", "bucket")
    sizes = written(object_sizes(points), "object-sizes")
    total = sizes.agg(F.count("*"), F.coalesce(F.sum("n_points"), F.lit(0))).first()
    return Index(written(table, "postings"), points, sizes, proj, total[0], total[1])


def save_index(index: Index, path: str) -> None:
    """The index as files: posting lists partitioned by projection, sizes, points, and the projections with their parameters."""
    index.table.repartition("proj").sortWithinPartitions("bucket").write.mode("overwrite").partitionBy("proj").parquet(f"{path}/postings")
    index.sizes.write.mode("overwrite").parquet(f"{path}/sizes")
    index.points.write.mode("overwrite").parquet(f"{path}/points")
    p = index.proj
    meta = {"a": p.a.tolist(), "b": p.b.tolist(), "width": p.width, "levels": p.levels, "params": p.params.__dict__, "n_objects": index.n_objects, "n_points": index.n_points}
    index.table.sparkSession.createDataFrame([(json.dumps(meta),)], "value string").coalesce(1).write.mode("overwrite").text(f"{path}/meta")


def load_index(spark: SparkSession, path: str) -> Index:
    from objann.functions.params import Params

    meta = json.loads(spark.read.text(f"{path}/meta").first().value)
    proj = Projections(np.array(meta["a"], np.int64), np.array(meta["b"], np.int64), meta["width"], Params(**meta["params"]), meta["levels"])
    table = spark.read.schema(POSTINGS).parquet(f"{path}/postings").select("block", F.col("proj").cast("int").alias("proj"), "bucket", "n", "members", "hashes")
    return Index(table, spark.read.parquet(f"{path}/points"), spark.read.parquet(f"{path}/sizes"), proj, meta["n_objects"], meta["n_points"])


def bucket_catalog(index: Index) -> DataFrame:
    """(proj, bucket, n_points): the size of every stored bucket."""
    return index.table.where("proj > 0").groupBy("proj", "bucket").agg(F.sum("n").cast("long").alias("n_points"))


def index_stats(index: Index) -> DataFrame:
    """(postings, buckets, entries, bytes): what the index holds; an entry is a point on a projection."""
    held = index.table.where("proj > 0")
    size = F.length("members") + F.coalesce(F.length("hashes"), F.lit(0))
    return held.agg(F.count("*").alias("postings"), F.countDistinct("proj", "bucket").alias("buckets"), F.sum("n").cast("long").alias("entries"), F.sum(size).cast("long").alias("bytes"))


def query_cells(hq: np.ndarray, proj: Projections, level: int) -> dict[tuple[int, int], None]:
    """The (projection, level cell) pairs that the query points read at a level; for windows with both neighbours."""
    if proj.static:
        cells = hq // proj.limits()[level]
    else:
        step = max(1, -(-proj.limits()[level] // (2 * proj.width)))
        cells = (hq // proj.width) // step
    found = {}
    for j in range(hq.shape[1]):
        for c in np.unique(cells[:, j]).tolist():
            for near in (c,) if proj.static else (c - 1, c, c + 1):
                found[j + 1, near] = None
    return found


def read_postings(index: Index, hq: np.ndarray, level: int, after: int | None = None) -> DataFrame:
    """The posting lists that the query points need at a level, less what they needed at level ``after``.

    An equi-join on (projection, level cell) with the distinct cells of the query batch, which its
    size bounds; the span of wanted buckets on each side goes to the scan as a filter.
    """
    spark, proj = index.table.sparkSession, index.proj

    def wanted(t: int) -> tuple[DataFrame, int]:
        step = proj.limits()[t] if proj.static else max(1, -(-proj.limits()[t] // (2 * proj.width)))
        rows = list(query_cells(hq, proj, t))
        return F.broadcast(spark.createDataFrame(pa.table({"proj": pa.array([r[0] for r in rows], pa.int32()), "cell": pa.array([r[1] for r in rows], pa.int64())}))), step

    cells, step = wanted(level)
    base = hq if proj.static else hq // proj.width
    reach = 2 * step if not proj.static else step
    low, high = int(base.min()) - reach, int(base.max()) + reach
    held = index.table.where((F.col("proj") > 0) & F.col("bucket").between(low, high))
    found = held.withColumn("cell", floor_div(F.col("bucket"), step)).join(cells, ["proj", "cell"], "left_semi").drop("cell")
    if after is not None:
        cells, step = wanted(after)
        found = found.withColumn("cell", floor_div(F.col("bucket"), step)).join(cells, ["proj", "cell"], "left_anti").drop("cell")
    return found.select("block", "proj", "bucket", "n", "members", "hashes")


def directories(index: Index) -> DataFrame:
    return index.table.where("proj = 0").select("block", "proj", "bucket", "n", "members", "hashes")


NO_OBJECT = -(1 << 63)  # in the place of an object's id: not wanted


def wanted_directories(index: Index) -> DataFrame:
    """``directories`` where the index's sizes hold a part of the objects only: NO_OBJECT stands for the others."""

    def ids(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            own = [np.frombuffer(b, np.int64) for b in batch.column(1).to_pylist()]
            block = np.repeat(batch.column(0).to_numpy(), [len(o) for o in own])
            yield pa.RecordBatch.from_arrays([pa.array(block), pa.array(np.concatenate([*own, np.zeros(0, np.int64)]))], ["block", "object_id"])

    def mark(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            marked = [np.where(np.isin(own := np.frombuffer(b, np.int64), w or ()), own, NO_OBJECT).tobytes() for b, w in zip(batch.column(5).to_pylist(), batch.column(6).to_pylist())]
            yield pa.RecordBatch.from_arrays([*batch.columns[:5], pa.array(marked, pa.binary())], ["block", "proj", "bucket", "n", "members", "hashes"])

    held = directories(index)
    wanted = held.select("block", "hashes").mapInArrow(ids, "block long, object_id long").join(index.sizes.select("object_id"), "object_id", "left_semi")
    listed = wanted.groupBy("block").agg(F.collect_list("object_id").alias("wanted"))
    return held.join(listed, "block", "left").select("block", "proj", "bucket", "n", "members", "hashes", "wanted").mapInArrow(mark, POSTINGS)


@dataclass
class Block:
    """One block as read for a query batch: hashes by place, which of them were read, and the objects."""

    objects: np.ndarray
    first_byte: np.ndarray
    sizes: np.ndarray
    hashes: np.ndarray
    present: np.ndarray


def read_blocks(batches: Iterator[pa.RecordBatch], proj: Projections) -> Iterator[Block]:
    """Blocks from rows sorted by (block, proj); those without any posting are left out."""
    m = proj.params.m
    held, current, directory = [], None, None

    def close():
        begins, sizes = np.frombuffer(directory[1], np.int64).reshape(2, -1)
        hashes, present = np.zeros((directory[0], m), np.int64), np.zeros((directory[0], m), bool)
        for j, bucket, members, values in held:
            at = np.frombuffer(members, np.uint16)
            hashes[at, j - 1] = bucket if values is None else np.frombuffer(values, np.int64)
            present[at, j - 1] = True
        return Block(np.frombuffer(directory[2], np.int64), begins // 8, sizes, hashes, present)

    for batch in batches:
        rows = zip(*(batch.column(k).to_pylist() for k in range(6)))
        for block, j, bucket, n, members, values in rows:
            if block != current:
                if directory is not None and held:
                    yield close()
                current, held, directory = block, [], None
            if j == 0:
                directory = (n, members, values)
            else:
                held.append((j, bucket, members, values))
    if directory is not None and held:
        yield close()
