"""Random projections: buckets, windows and levels."""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from objann.functions.fixedpoint import DIRECTION_SCALE, floor_div
from objann.functions.params import Params, radius_ladder
from objann.operators.kernel import blocks
from objann.sources.families import Family


@dataclass(frozen=True)
class Projections:
    """Integer directions and offsets; they are data and are stored with an index."""

    a: np.ndarray
    b: np.ndarray
    width: int
    params: Params
    levels: int

    def values(self, vec: np.ndarray) -> np.ndarray:
        return (vec.astype(np.float64) @ self.a.T.astype(np.float64)).astype(np.int64)

    def hashes(self, vec: np.ndarray) -> np.ndarray:
        """Bucket numbers (static) or projection values (query-centred)."""
        h = self.values(vec)
        return (h + self.b) // self.width if self.params.kind == "static" else h

    @property
    def static(self) -> bool:
        return self.params.kind == "static"

    def limits(self) -> list[int]:
        """By level: base buckets in a bucket (static), or the width of the window (query-centred), which any real c > 1 allows."""
        if self.static:
            return [int(self.params.c) ** t for t in range(self.levels + 1)]
        return [math.floor(self.width * self.params.c**t) for t in range(self.levels + 1)]

    def squared_radii(self, unit: int, step: float = 1) -> list[int]:
        """By level: the largest squared distance within ``step`` radii."""
        return [math.floor((step * self.params.c**t * unit) ** 2) for t in range(self.levels + 1)]


def make_projections(family: Family, params: Params, levels: int | None = None, seed: int = 7, offset_span: str = "ladder") -> Projections:
    """Standard normal directions; offsets within one bucket (base) or the widest level's bucket (ladder).

    Without ``levels`` the ladder of radii goes on until the radius passes the widest span that the family's
    points can have on any direction.
    """
    rng = np.random.default_rng(seed)
    a = np.floor(rng.standard_normal((params.m, family.dim)) * DIRECTION_SCALE + 0.5).astype(np.int64)
    width = round(params.w * family.unit * DIRECTION_SCALE)
    if levels is None:
        longest = float(np.sqrt((a.astype(np.float64) ** 2).sum(axis=1).max(initial=1))) / DIRECTION_SCALE
        levels = len(radius_ladder(params.c, longest * family.diameter / params.w)) - 1
    span = math.floor(width * params.c**levels) if offset_span == "ladder" else width
    return Projections(a, rng.integers(0, span, size=params.m), width, params, levels)


def hash_points(points: DataFrame, proj: Projections) -> DataFrame:
    """Signature form: (object_id, point_id, hashes array<long>), one narrow pass."""

    def sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for obj, pid, vec in blocks(batches, proj.params.m):
            h = proj.hashes(vec)
            ends = np.arange(0, h.size + 1, h.shape[1], dtype=np.int32)
            yield pa.RecordBatch.from_arrays([pa.array(obj), pa.array(pid), pa.ListArray.from_arrays(pa.array(ends), pa.array(h.ravel()))], ["object_id", "point_id", "hashes"])

    return points.select("object_id", "point_id", "vec").mapInArrow(sign, "object_id long, point_id long, hashes array<long>")


def inverted(points: DataFrame, proj: Projections) -> DataFrame:
    """Inverted form: (proj, bucket, object_id, point_id), projections from 1."""
    signed = hash_points(points, proj).select("object_id", "point_id", F.posexplode("hashes").alias("at", "bucket"))
    return signed.select((F.col("at") + 1).alias("proj"), "bucket", "object_id", "point_id")


def level_bucket(bucket: Column, radius: int) -> Column:
    return floor_div(bucket, radius)


def collision_counts(points: DataFrame, queries: DataFrame, proj: Projections, level: int) -> DataFrame:
    """(q_obj, q_id, object_id, point_id, cc): shared level buckets, by equi-join on (projection, level bucket)."""
    if proj.params.kind != "static":
        raise ValueError("static buckets only; see window_hits")
    radius = int(proj.params.c) ** level
    left = inverted(points, proj).withColumn("cell", level_bucket(F.col("bucket"), radius)).drop("bucket")
    right = inverted(queries, proj).select("proj", level_bucket(F.col("bucket"), radius).alias("cell"), F.col("object_id").alias("q_obj"), F.col("point_id").alias("q_id"))
    return left.join(right, ["proj", "cell"]).groupBy("q_obj", "q_id", "object_id", "point_id").agg(F.count("*").cast("int").alias("cc"))


def window_hits(points: DataFrame, queries: DataFrame, proj: Projections, level: int) -> DataFrame:
    """(proj, q_obj, q_id, object_id, point_id) within the query-centred window, as a cell join with a residual test."""
    reach = math.floor(proj.width * proj.params.c**level)
    cell = (reach + 1) // 2
    left = inverted(points, proj).withColumn("cell", floor_div(F.col("bucket"), cell))
    right = inverted(queries, proj).select("proj", F.col("bucket").alias("centre"), F.col("object_id").alias("q_obj"), F.col("point_id").alias("q_id"))
    right = right.withColumn("cell", F.explode(F.transform(F.array(F.lit(-1), F.lit(0), F.lit(1)), lambda s: floor_div(F.col("centre"), cell) + s)))
    return left.join(right, ["proj", "cell"]).where(2 * F.abs(F.col("bucket") - F.col("centre")) <= reach).select("proj", "q_obj", "q_id", "object_id", "point_id")


def signature_collisions(a: Column, b: Column, radius: int = 1) -> Column:
    """Collisions of two signatures of buckets at a level, as a SQL expression."""
    same = F.zip_with(a, b, lambda x, y: (floor_div(x, radius) == floor_div(y, radius)).cast("int"))
    return F.aggregate(same, F.lit(0), lambda acc, x: acc + x)
