"""The given tables as bags of integer vectors: (object_id, point_id, vec)."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from objann.functions.fixedpoint import q16
from objann.sources.tables import load_table


@dataclass(frozen=True)
class Family:
    name: str
    dim: int
    unit: int  # the integer length of radius 1
    diameter: float = 16.0  # the widest distance of two points, in radii


UNIT = 8192
TWIN = Family("twin", 64, 163840, 24.0)  # 2 x (20 + 3 + 7) / 20 unit lengths
EMB, LABEL = Family("emb", 64, UNIT), Family("label", 64, UNIT)  # unit vectors
SUPP, PART, ORDER, CUST = (Family(n, 5, UNIT, 20.0) for n in ("supp", "part", "order", "cust"))
USER = Family("user", 8, UNIT, 24.0)
DOC, PAGE, CONV, BENCH = (Family(n, 32, UNIT) for n in ("doc", "page", "conv", "bench"))  # unit vectors


def embedding_points(spark: SparkSession, sf_dir: str, by_label: bool = False) -> DataFrame:
    e = load_table(spark, sf_dir, "embeddings")
    key = F.col("label").cast("long") if by_label else F.floor(F.col("vec_id") / 20).cast("long")
    return e.select(key.alias("object_id"), F.col("vec_id").alias("point_id"), F.transform("embedding", q16).alias("vec"))


def twin_points(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Planted pairs: of n vectors (n / 5 objects of 12 points), each the sum of the pair's vector, one of two
    from the last fifth, and one that goes round the whole table."""
    e = load_table(spark, sf_dir, "embeddings").select("vec_id", F.transform("embedding", q16).alias("v"))
    n = e.count()
    ids = spark.range(n // 5 * 12).select(F.col("id").alias("point_id"), F.expr("id div 12").alias("j"), F.expr("id % 12").alias("i"))
    ids = ids.select("point_id", "j", F.expr("j div 2").alias("a"), F.expr(f"{n * 4 // 5} + j % 2").alias("b"), F.expr(f"(12 * j + 7 * i + 100) % {n}").alias("c"))
    for name in "abc":
        ids = ids.join(e.select(F.col("vec_id").alias(name), F.col("v").alias(f"v{name}")), name)
    vec = F.zip_with(F.zip_with("va", "vb", lambda x, y: 20 * x + 3 * y), "vc", lambda x, y: x + 7 * y)
    return ids.select(F.col("j").alias("object_id"), "point_id", vec.alias("vec"))


def line_points(spark: SparkSession, sf_dir: str, key: str) -> DataFrame:
    """Line items of a supplier, part, order or customer; the line key repeats, so rows are numbered by all columns.

    Point ids hold 2^20 lines of a key; a key of more would repeat ids and is an error.
    """
    lines = load_table(spark, sf_dir, "lineitem")
    if key == "o_custkey":
        orders = load_table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey")
        lines = lines.join(orders, "l_orderkey")
    columns = ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_returnflag", "l_linestatus", "l_shipdate"]
    number = F.row_number().over(Window.partitionBy(key).orderBy(*columns)).cast("long")
    days = F.datediff(F.col("l_shipdate").cast("date"), F.lit("1992-01-01").cast("date")).cast("double")
    vec = F.array(q16(F.col("l_quantity") / 50.0), q16(F.col("l_extendedprice") / 105000.0), q16(F.col("l_discount") * 10.0), q16(F.col("l_tax") * 12.5), q16(days / 2500.0))
    return lines.select(F.col(key).alias("object_id"), (F.col(key) * (1 << 20) + F.when(number < 1 << 20, number).otherwise(F.raise_error(F.lit("too many lines of one key")))).alias("point_id"), vec.alias("vec"))


def user_points(spark: SparkSession, sf_dir: str) -> DataFrame:
    events = load_table(spark, sf_dir, "events")
    return events.select(F.col("user_id").alias("object_id"), F.col("event_id").alias("point_id"), event_vector().alias("vec"))


def event_vector() -> Column:
    kinds = [F.when(F.col("event_type") == k, 1.0).otherwise(0.0) for k in ("view", "click", "signup", "error", "purchase")]
    k = F.get_json_object("props", "$.k").cast("double")
    return F.array(q16(F.sqrt(1.0 + F.col("value")) / 22.0), q16(F.hour("ts").cast("double") / 24.0), *map(q16, kinds), q16(k / 100.0))


PARTS = 10_000  # parts of one text that point ids hold
CODES = 1 << 20  # characters that are counted at once


def text_points(df: DataFrame, key: str, text: Column) -> DataFrame:
    """Sentences and lines of at least 20 characters as signed 3-gram counts in 32 bins, at unit length.

    Point ids hold PARTS sentences and lines of a text; a text of more is an error, as ids would repeat.
    """
    parts = df.select(F.col(key).alias("object_id"), F.posexplode(F.split(text, "[.\n]")).alias("at", "part")).withColumn("part", F.trim("part"))
    long = parts.where(F.length("part") >= 20)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            lengths = pc.utf8_length(batch.column(2)).to_numpy()
            ends = np.cumsum(lengths)
            a = 0
            while a < batch.num_rows:
                b = max(a + 1, int(np.searchsorted(ends, (ends[a - 1] if a else 0) + CODES, "right")))
                yield counted(batch.slice(a, b - a), lengths[a:b])
                a = b

    def counted(batch: pa.RecordBatch, lengths: np.ndarray) -> pa.RecordBatch:
        codes = np.frombuffer("".join(batch.column(2).to_pylist()).encode("utf-32-le"), dtype=np.uint32).astype(np.int64)
        h = (codes[:-2] * 961 + codes[1:-1] * 31 + codes[2:]) % 1000003
        part = np.repeat(np.arange(len(lengths)), lengths)
        own = part[:-2] == part[2:]  # grams that lie in one part
        bins = np.bincount(part[:-2][own] * 32 + h[own] % 32, weights=1 - 2 * (h[own] // 32 % 2), minlength=32 * len(lengths)).reshape(-1, 32)
        square = (bins * bins).sum(axis=1)
        keep = np.flatnonzero(square)
        vectors = np.floor(bins[keep] / np.sqrt(square[keep])[:, None] * 65536 + 0.5).astype(np.int64)
        ids = batch.take(pa.array(keep, pa.int64()))
        number = pc.add(pc.multiply(ids.column(0), PARTS), ids.column(1))
        vec = pa.ListArray.from_arrays(pa.array(np.arange(0, vectors.size + 1, 32, dtype=np.int32)), pa.array(vectors.ravel()))
        return pa.RecordBatch.from_arrays([ids.column(0), number, vec], ["object_id", "point_id", "vec"])

    at = F.when(F.col("at") < PARTS, F.col("at").cast("long")).otherwise(F.raise_error(F.lit("too many parts of one text")))
    long = long.select(F.col("object_id").cast("long").alias("object_id"), at.alias("at"), "part")
    return long.mapInArrow(count, "object_id long, point_id long, vec array<long>")


def points(spark: SparkSession, sf_dir: str, family: Family, only: str | None = None) -> DataFrame:
    """A family's points, or those with a condition on object_id; documents are chosen before their texts are cut."""
    load = lambda name: load_table(spark, sf_dir, name)
    if only:
        if family.name != "doc":
            return points(spark, sf_dir, family).where(only)
        return text_points(load("documents").withColumn("object_id", F.col("doc_id")).where(only), "doc_id", F.col("text"))
    makers = {
        "twin": lambda: twin_points(spark, sf_dir),
        "emb": lambda: embedding_points(spark, sf_dir),
        "label": lambda: embedding_points(spark, sf_dir, True),
        "supp": lambda: line_points(spark, sf_dir, "l_suppkey"),
        "part": lambda: line_points(spark, sf_dir, "l_partkey"),
        "order": lambda: line_points(spark, sf_dir, "l_orderkey"),
        "cust": lambda: line_points(spark, sf_dir, "o_custkey"),
        "user": lambda: user_points(spark, sf_dir),
        "doc": lambda: text_points(load("documents"), "doc_id", F.col("text")),
        "page": lambda: text_points(load("pages"), "page_id", F.regexp_replace("html", "<[^>]*>", "\n")),
        "conv": lambda: conversation_points(load("conversations")),
        "bench": lambda: text_points(load("benchmark"), "item_id", F.col("text")),
    }
    return makers[family.name]()


TURNS = 100  # turns of one conversation that slots hold


def conversation_points(turns: DataFrame) -> DataFrame:
    """A conversation's turns in one object: each turn is numbered apart; more than TURNS of them are an error."""
    turn = F.when(F.col("turn") < TURNS, F.col("turn")).otherwise(F.raise_error(F.lit("too many turns of one conversation")))
    own = text_points(turns.withColumn("slot", F.col("conv_id") * TURNS + turn), "slot", F.col("text"))
    return own.select(F.expr(f"object_id div {TURNS}").alias("object_id"), "point_id", "vec")


def validate_points(df: DataFrame, dim: int, mode: str = "fail") -> DataFrame:
    """Rejects null ids and vectors, null components and wrong lengths: an error, or dropped rows."""
    fine = F.col("object_id").isNotNull() & F.col("point_id").isNotNull() & (F.size("vec") == dim) & F.forall("vec", lambda x: x.isNotNull())
    fine = F.coalesce(fine, F.lit(False))
    if mode == "drop":
        return df.where(fine)
    if not df.where(~fine).isEmpty():
        raise ValueError("points with nulls or of another dimension")
    return df


def object_sizes(df: DataFrame) -> DataFrame:
    return df.groupBy("object_id").agg(F.count("*").alias("n_points"))


def pick_queries(df: DataFrame, n: int, seed: int = 7) -> DataFrame:
    """n objects in the order of a hash of their ids."""
    return object_sizes(df).select("object_id").orderBy(F.xxhash64("object_id", F.lit(seed)), "object_id").limit(n)
