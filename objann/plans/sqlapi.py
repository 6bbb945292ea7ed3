"""Functions for SQL users: distances, signatures, the share distance as an aggregate, nearest points as a table function."""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf, udtf

from objann.functions.fixedpoint import sq_dist
from objann.operators.hashing import Projections, signature_collisions
from objann.plans.search_sql import Sql, floor_div
from objann.plans.workloads import FAMILIES, QUERIES, family_points, projections


def distance_function():
    """``sq_dist(a, b)``: squared distance of two integer vectors, whole columns at a time."""

    @pandas_udf("long")
    def distance(a: pd.Series, b: pd.Series) -> pd.Series:
        if not len(a):
            return pd.Series([], dtype="int64")
        return pd.Series(((np.stack(a.to_numpy()).astype(np.int64) - np.stack(b.to_numpy()).astype(np.int64)) ** 2).sum(axis=1))

    return distance


def signature_function(proj: Projections):
    """``hash_signature(vec)``: the bucket (or projection value) of a vector on every projection."""

    @pandas_udf("array<long>")
    def signature(vec: pd.Series) -> pd.Series:
        return pd.Series(list(proj.hashes(np.stack(vec.to_numpy()).astype(np.int64)))) if len(vec) else pd.Series([], dtype=object)

    return signature


def share_distance_function():
    """``gamma_distance_agg(sq_dist, n, d)``: the share-th smallest value of a group, share n / d.

    An aggregate of a whole group: for pairs of two objects that fit a task; ``gamma_distance`` has no such bound.
    """

    @pandas_udf("long")
    def share(values: pd.Series, n: pd.Series, d: pd.Series) -> int:
        rank = max(1, math.ceil(int(n.iloc[0]) * len(values) / int(d.iloc[0]) - 1e-9))
        return int(np.partition(values.to_numpy(), rank - 1)[rank - 1])

    return share


@udtf(returnType="object_id long, point_id long, sq_dist long")
class Neighbours:
    """``neighbours(TABLE(points) PARTITION BY (object_id), query, k)``: the k points of each object that are nearest to a vector."""

    def __init__(self):
        self.rows, self.query, self.k = [], None, 0

    def eval(self, row, query, k):
        self.query, self.k = query, k
        self.rows.append((row["object_id"], row["point_id"], row["vec"]))

    def terminate(self):
        if self.rows:
            vec = np.array([r[2] for r in self.rows], dtype=np.int64)
            d = ((vec - np.array(self.query, dtype=np.int64)) ** 2).sum(axis=1)
            for j in np.lexsort(([r[1] for r in self.rows], d))[: self.k].tolist():
                yield int(self.rows[j][0]), int(self.rows[j][1]), int(d[j])


def register(spark: SparkSession, proj: Projections) -> None:
    spark.udf.register("sq_dist", distance_function())
    spark.udf.register("hash_signature", signature_function(proj))
    spark.udf.register("gamma_distance_agg", share_distance_function())
    spark.udtf.register("neighbours", Neighbours)


def _prepared(spark: SparkSession, sf_dir: str) -> SparkSession:
    register(spark, projections("twin"))
    points, queries = family_points(spark, sf_dir, "twin")
    points.createOrReplaceTempView("twin_points")
    queries.createOrReplaceTempView("twin_queries")
    return spark


def udf_sq_dist(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _prepared(spark, sf_dir).sql("SELECT q.point_id AS q_id, x.point_id, sq_dist(q.vec, x.vec) AS d FROM twin_queries q JOIN twin_points x ON q.object_id = x.object_id")


def udf_signature(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _prepared(spark, sf_dir).sql("SELECT object_id, point_id, array_join(hash_signature(vec), ',') AS signature FROM twin_points")


def signature_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Collisions at level 3 between the signatures of a query object's points and the points of its pair, without a join of buckets."""
    _prepared(spark, sf_dir)
    signed = spark.sql("SELECT object_id, point_id, hash_signature(vec) AS s FROM twin_points")
    pair = F.expr("object_id div 2")
    left = signed.where(QUERIES["twin"]).select(pair.alias("pair"), F.col("point_id").alias("q_id"), F.col("s").alias("a"))
    return left.join(signed.select(pair.alias("pair"), "point_id", F.col("s").alias("b")), "pair").select("q_id", "point_id", signature_collisions(F.col("a"), F.col("b"), 8).alias("cc"))


def udaf_gamma(spark: SparkSession, sf_dir: str) -> DataFrame:
    points, queries = family_points(_prepared(spark, sf_dir), sf_dir, "twin")
    pairs = queries.select(F.col("object_id").alias("q_obj"), F.col("vec").alias("q")).join(points, how="cross")
    pairs.select("q_obj", "object_id", sq_dist(F.col("q"), F.col("vec")).alias("d")).createOrReplaceTempView("twin_pairs")
    return spark.sql("SELECT q_obj, object_id, gamma_distance_agg(d, 1, 2) AS sq_dist FROM twin_pairs GROUP BY q_obj, object_id")


def udtf_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    vec = _prepared(spark, sf_dir).sql("SELECT vec FROM twin_queries ORDER BY point_id LIMIT 1").first().vec
    literal = ", ".join(f"{v}L" for v in vec)
    near = spark.sql(f"SELECT * FROM neighbours(TABLE(twin_points) PARTITION BY (object_id), array({literal}), 25)")
    return near.withColumn("rank", F.row_number().over(Window.orderBy("sq_dist", "object_id", "point_id"))).where("rank <= 25")


def queries() -> dict:
    return {"udf_sq_dist": udf_sq_dist, "udf_signature": udf_signature, "signature_collisions": signature_counts, "udaf_gamma": udaf_gamma, "udtf_neighbours": udtf_neighbours}


def oracles() -> dict[str, str]:
    twin, proj = Sql(FAMILIES["twin"], QUERIES["twin"]), projections("twin")
    flat = f"{twin.points}, {twin.hashes(proj)}"
    return {
        "udf_sq_dist": f"WITH {twin.pairs} SELECT q_id, point_id, sq_dist AS d FROM pairs WHERE q_obj = object_id",
        "udf_signature": f"WITH {flat} SELECT object_id, point_id, string_agg(CAST(bucket AS VARCHAR), ',' ORDER BY proj) AS signature FROM h GROUP BY 1, 2",
        "signature_collisions": f"WITH {flat} SELECT q.point_id AS q_id, x.point_id, CAST(sum(CASE WHEN {floor_div('q.bucket', 8)} = {floor_div('x.bucket', 8)} THEN 1 ELSE 0 END) AS INTEGER) AS cc FROM h q JOIN h x ON q.proj = x.proj AND q.object_id // 2 = x.object_id // 2 WHERE q.{twin.queries} GROUP BY 1, 2",
        "udaf_gamma": f"WITH {twin.distances(1, 2)} SELECT q_obj, object_id, sq_dist FROM gd",
        "udtf_neighbours": f"WITH {twin.linear(25)} SELECT object_id, point_id, sq_dist, rank FROM knn WHERE q_id = (SELECT min(q_id) FROM qp)",
    }
