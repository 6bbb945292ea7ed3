"""Accuracy measures and empirical checks of the guarantee."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def object_ratio(result: DataFrame, truth: DataFrame, distances: DataFrame | None = None) -> DataFrame:
    """(q_obj, object_ratio, coverage, n_undefined): mean of returned over true share distance by rank.

    ``result`` has sq_dist, or ``distances`` gives it by (q_obj, object_id); ranks are by distance.
    0/0 counts 1, x/0 is left out and counted; missing ranks lower the coverage.
    """
    from pyspark.sql import Window

    if distances is not None:
        result = result.drop("sq_dist").join(distances.select("q_obj", "object_id", "sq_dist"), ["q_obj", "object_id"])
    by = Window.partitionBy("q_obj").orderBy("sq_dist", "object_id")
    mine = result.select("q_obj", F.row_number().over(by).alias("rank"), F.col("sq_dist").alias("got"))
    both = truth.select("q_obj", "rank", F.col("sq_dist").alias("true")).join(mine, ["q_obj", "rank"], "left")
    ratio = F.when((F.col("true") == 0) & (F.col("got") == 0), 1.0).when(F.col("true") == 0, None).otherwise(F.sqrt(F.col("got").cast("double")) / F.sqrt(F.col("true").cast("double")))
    undefined = ((F.col("true") == 0) & (F.col("got") > 0)).cast("int")
    return both.groupBy("q_obj").agg(F.round(F.avg(ratio), 6).alias("object_ratio"), F.round(F.count("got") / F.count("*"), 6).alias("coverage"), F.sum(F.coalesce(undefined, F.lit(0))).alias("n_undefined"))


def recall_at_k(result: DataFrame, truth: DataFrame) -> DataFrame:
    hit = truth.select("q_obj", "object_id").join(result.select("q_obj", "object_id", F.lit(1).alias("hit")), ["q_obj", "object_id"], "left")
    return hit.groupBy("q_obj").agg(F.round(F.count("hit") / F.count("*"), 6).alias("recall"))


def is_c_approx(result: DataFrame, truth: DataFrame, c: float) -> DataFrame:
    both = truth.select("q_obj", "rank", F.col("sq_dist").alias("true")).join(result.select("q_obj", "rank", "sq_dist"), ["q_obj", "rank"], "left")
    return both.groupBy("q_obj").agg(F.min(F.coalesce((F.col("sq_dist") <= c * c * F.col("true")), F.lit(False)).cast("int")).alias("c_approx"))
