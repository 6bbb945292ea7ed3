"""All queries of the library, and the SQL that recomputes them."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from objann.functions.fixedpoint import sq_dist
from objann.operators import buffers, gamma, hashing
from objann.operators.index import bucket_catalog, index_stats, load_index, save_index
from objann.operators.metrics import object_ratio, recall_at_k
from objann.operators.pointknn import borda, hashed_knn, linear_knn
from objann.operators.search import object_knn, schedule_costs
from objann.plans import relational, search_sql, sqlapi, workloads
from objann.plans.search_sql import Sql
from objann.plans.workloads import FAMILIES, HALF, QUARTER, QUERIES, family_points, projections, stored_index
from objann.sources import families
from objann.sources.families import BENCH, DOC, SUPP, TWIN, object_sizes, points
from objann.sources.tables import load_table, read_any, work_folder, write_report
from objann.streaming import events as streams

ALL_FAMILIES = (families.TWIN, families.EMB, families.LABEL, families.SUPP, families.PART, families.ORDER, families.CUST, families.USER, families.DOC, families.PAGE, families.CONV, families.BENCH)
LRU_PAGES, LRU_LEVEL = 200, 2


def _shown(df: DataFrame) -> DataFrame:
    return df.select("object_id", "point_id", F.array_join(F.transform("vec", lambda x: x.cast("string")), ",").alias("vec"))


def family_query(family):
    return lambda spark, sf: _shown(points(spark, sf, family))


def on(name: str, make):
    """A query over a family's points and those of its stated query set."""
    return lambda spark, sf: make(*family_points(spark, sf, name))


def on_twin(make):
    return on("twin", make)


def searched(name: str, share, k: int, part: str = "result", kind: str = "static", offsets: dict | None = None, **options):
    """Object search over a family's stored index."""

    def run(spark, sf) -> DataFrame:
        index = stored_index(spark, sf, name, kind, **(offsets or {}))
        return getattr(object_knn(index, index.points.where(QUERIES[name]), FAMILIES[name], share, k, **options), part)

    return run


def level_buckets(p: DataFrame, q: DataFrame) -> DataFrame:
    flat = hashing.inverted(p, projections("twin"))
    return flat.select("proj", "object_id", "point_id", "bucket", *[hashing.level_bucket(F.col("bucket"), 2**t).alias(f"level{t}") for t in (1, 3)])


def compared(name: str, measure):
    """A measure of object search against the exact ranking, k = 25."""

    def run(spark, sf) -> DataFrame:
        p, q = family_points(spark, sf, name)
        share = HALF if name == "twin" else QUARTER
        return measure(searched(name, share, 25)(spark, sf), gamma.exact_object_knn(p, q, FAMILIES[name], share, 25))

    return run


def filtered(mode: str):
    """Nearest suppliers among those of one region, before the ranking (exact) or after it (may be fewer)."""

    def run(spark, sf) -> DataFrame:
        nations = load_table(spark, sf, "nation").join(F.broadcast(load_table(spark, sf, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
        chosen = load_table(spark, sf, "supplier").join(F.broadcast(nations), F.col("s_nationkey") == F.col("n_nationkey")).where("r_name = 'EUROPE'").select(F.col("s_suppkey").alias("object_id"))
        index = stored_index(spark, sf, "supp")
        return object_knn(index, index.points.where(QUERIES["supp"]), SUPP, QUARTER, 5 if mode == "pre" else 25, where=chosen, filter_mode=mode).result

    return run


def filtered_exact(spark, sf) -> DataFrame:
    """Nearest users among those with a purchase, ranked exactly."""
    p, q = family_points(spark, sf, "user")
    buyers = load_table(spark, sf, "events").where("event_type = 'purchase' AND value > 50").select(F.col("user_id").alias("object_id")).distinct()
    return gamma.exact_object_knn(p.join(buyers, "object_id", "left_semi"), q, families.USER, QUARTER, 5)


def filtered_quality(spark, sf) -> DataFrame:
    """Nearest documents of good quality."""
    p, q = family_points(spark, sf, "doc")
    good = load_table(spark, sf, "labels").where("quality = 1").select(F.col("doc_id").alias("object_id")).distinct()
    return gamma.exact_object_knn(p.join(good, "object_id", "left_semi"), q, DOC, (1, 20), 3)


def benchmark_in_documents(spark, sf) -> DataFrame:
    """The documents nearest to each benchmark passage, which is no object of the database: by a small share."""
    return gamma.exact_object_knn(points(spark, sf, DOC), points(spark, sf, BENCH), DOC, (1, 50), 3)


def sources_roundtrip(spark, sf) -> DataFrame:
    """nation written and read as JSON, CSV, ORC and Parquet under its declared schema: (format, columns)."""
    nation, folder = load_table(spark, sf, "nation"), f"{work_folder(spark)}/objann-search/formats"
    schema = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in nation.schema.fields)
    out = []
    for fmt in ("json", "csv", "orc", "parquet"):
        write_report(nation, f"{folder}/{fmt}", fmt)
        out.append(read_any(spark, f"{folder}/{fmt}", fmt, schema, **({"header": True} if fmt == "csv" else {})).select(F.lit(fmt).alias("format"), "*"))
    return workloads.union(out)


def index_roundtrip(spark, sf) -> DataFrame:
    """Object search over an index saved to files and loaded again."""
    folder = f"{work_folder(spark)}/objann-search/saved-index"
    save_index(stored_index(spark, sf, "twin"), folder)
    index = load_index(spark, folder)
    return object_knn(index, index.points.where(QUERIES["twin"]), TWIN, HALF, 2).result


def interval_join(spark, sf) -> DataFrame:
    """Errors and the same user's views in the ten minutes before, by a join on the time cell."""
    e = load_table(spark, sf, "events")
    size = 600
    left = e.where("event_type = 'error'").select(F.col("event_id").alias("error_id"), "user_id", F.unix_timestamp("ts").alias("t")).withColumn("cell", F.explode(F.array(F.expr(f"t div {size}"), F.expr(f"t div {size} - 1"))))
    right = e.where("event_type = 'view'").select(F.col("event_id").alias("view_id"), "user_id", F.unix_timestamp("ts").alias("u")).withColumn("cell", F.expr(f"u div {size}"))
    return left.join(right, ["user_id", "cell"]).where(f"u <= t AND u > t - {size}").select("error_id", "view_id")


def counts_at(p: DataFrame, q: DataFrame, level: int) -> DataFrame:
    return hashing.collision_counts(p, q, projections("twin"), level)


def index_at(p: DataFrame, q: DataFrame, level: int) -> DataFrame:
    return gamma.collision_index(counts_at(p, q, level), p, q, projections("twin").params.l)


def candidates(spark, sf, how: str) -> DataFrame:
    """Objects that are candidates of some query object at level 3 (semi), or of none (anti)."""
    p, q = family_points(spark, sf, "twin")
    found = gamma.gamma_candidates(index_at(p, q, 3), HALF).select("object_id")
    return object_sizes(p).join(found, "object_id", how)


def false_positives(p: DataFrame, q: DataFrame) -> DataFrame:
    return gamma.gamma_false_positives(index_at(p, q, 4), gamma.gamma_distance(p, q, TWIN, QUARTER), TWIN, QUARTER, object_sizes(p).count(), 2)


def equal_pages(p: DataFrame, q: DataFrame, run) -> DataFrame:
    return run(buffers.access_trace(p, q, projections("twin"), levels=LRU_LEVEL).withColumn("bytes", F.lit(1).cast("long")))


def per_bucket(p: DataFrame, q: DataFrame) -> DataFrame:
    costs = buffers.simulate_buffer(buffers.access_trace(p, q, projections("twin")), "per_bucket", 0)
    return costs.select("q_obj", "hits", "misses", F.round("mb", 6).alias("mb"), F.round("io_ms", 3).alias("io_ms"))


def queries() -> dict:
    static, centred = (lambda: projections("twin")), (lambda: projections("twin", "query"))
    out = {f"fam_{f.name}_points": family_query(f) for f in ALL_FAMILIES}
    out |= {
        "object_sizes": on_twin(lambda p, q: object_sizes(p)),
        "object_similarity": on_twin(lambda p, q: gamma.object_similarity(p, q, TWIN, 8)),
        "gamma_distance": on_twin(lambda p, q: gamma.gamma_distance(p, q, TWIN, HALF)),
        "gamma_distance_quarter": on_twin(lambda p, q: gamma.gamma_distance(p, q, TWIN, QUARTER)),
        "gamma_distance_user": on("user", lambda p, q: gamma.gamma_distance(p, q, families.USER, QUARTER)),
        "gamma_distance_sketch": on("user", lambda p, q: gamma.gamma_distance_sketch(p, q, families.USER, QUARTER)),
        "exact_object_knn": on_twin(lambda p, q: gamma.exact_object_knn(p, q, TWIN, HALF, 5)),
        "exact_object_knn_user": on("user", lambda p, q: gamma.exact_object_knn(p, q, families.USER, QUARTER, 25)),
        "exact_object_knn_doc": on("doc", lambda p, q: gamma.exact_object_knn(p, q, DOC, (1, 20), 10)),
        "exact_object_knn_supp": on("supp", lambda p, q: gamma.exact_object_knn(p, q, SUPP, QUARTER, 25)),
        "exact_object_knn_emb": on("emb", lambda p, q: gamma.exact_object_knn(p, q, families.EMB, (1, 10), 3)),
        "hash_static_buckets": on_twin(lambda p, q: hashing.inverted(p, static())),
        "level_buckets": on_twin(level_buckets),
        "query_window_hits": on_twin(lambda p, q: hashing.window_hits(p, q, centred(), 2).groupBy("q_obj", "q_id", "object_id", "point_id").agg(F.count("*").alias("cc"))),
        "collision_counts": on_twin(lambda p, q: counts_at(p, q, 3)),
        "collision_index": on_twin(lambda p, q: index_at(p, q, 3)),
        "gamma_candidates": on_twin(lambda p, q: gamma.gamma_candidates(index_at(p, q, 3), HALF)),
        "gamma_false_positives": on_twin(false_positives),
        "candidates_semi": lambda spark, sf: candidates(spark, sf, "left_semi"),
        "untouched_anti": lambda spark, sf: candidates(spark, sf, "left_anti"),
        "stored_buckets": lambda spark, sf: bucket_catalog(stored_index(spark, sf, "twin")),
        "index_stats": lambda spark, sf: index_stats(stored_index(spark, sf, "twin")),
        "index_roundtrip": index_roundtrip,
        "schedule_costs": lambda spark, sf: schedule_costs(stored_index(spark, sf, "twin"), family_points(spark, sf, "twin")[1], 2),
        "object_knn_onepass": searched("twin", HALF, 2),
        "object_knn_iterative": searched("twin", HALF, 2, mode="iterative"),
        "object_knn_batched": searched("twin", HALF, 2, "stats", mode="iterative", proj_batch=32),
        "object_knn_stats": searched("twin", HALF, 2, "stats"),
        "object_knn_k25": searched("twin", HALF, 25),
        "object_knn_by_collisions": searched("twin", HALF, 25, order_by="collision"),
        "object_knn_restart": searched("twin", HALF, 2, "stats", count_mode="restart"),
        "object_knn_restart_iterative": searched("twin", HALF, 2, "stats", count_mode="restart", mode="iterative"),
        "object_knn_cr_bound": searched("twin", HALF, 2, "stats", t2_bound="cR"),
        "object_knn_base_offset": searched("twin", HALF, 2, "stats", offsets={"offset_span": "base"}),
        "object_knn_query_centred": searched("twin", HALF, 2, "stats", "query"),
        "object_knn_exclude_self": searched("twin", HALF, 1, mode="iterative", exclude_self=True),
        "object_knn_exhausted": searched("twin", (1, 1), 90, "stats"),
        "object_knn_user": searched("user", QUARTER, 5),
        "object_knn_user_stats": searched("user", QUARTER, 25, "stats"),
        "object_knn_doc": searched("doc", (1, 20), 5),
        "object_knn_supp": searched("supp", QUARTER, 25),
        "object_knn_emb": searched("emb", (1, 10), 3, "stats"),
        "linear_knn": on_twin(lambda p, q: linear_knn(p, q, 25)),
        "linear_knn_user": on("user", lambda p, q: linear_knn(p, q, 100)),
        "linear_knn_supp": on("supp", lambda p, q: linear_knn(p, q, 25)),
        "static_knn": on_twin(lambda p, q: hashed_knn(p, q, TWIN, static(), 25)),
        "static_knn_user": on("user", lambda p, q: hashed_knn(p, q, families.USER, projections("user"), 50)),
        "query_centred_knn": on_twin(lambda p, q: hashed_knn(p, q, TWIN, centred(), 25)),
        "borda_linear": on_twin(lambda p, q: borda(linear_knn(p, q, 50), 50, 5)),
        "borda_votes": on_twin(lambda p, q: borda(linear_knn(p, q, 50), 50, 5, "votes")),
        "borda_best_rank": on_twin(lambda p, q: borda(linear_knn(p, q, 50), 50, 5, "best_rank")),
        "borda_size_normalised": on_twin(lambda p, q: borda(linear_knn(p, q, 50), 50, 5, "size_normalised", p)),
        "borda_static": on_twin(lambda p, q: borda(hashed_knn(p, q, TWIN, static(), 25), 25, 5)),
        "borda_query_centred": on_twin(lambda p, q: borda(hashed_knn(p, q, TWIN, centred(), 25), 25, 5)),
        "borda_user": on("user", lambda p, q: borda(linear_knn(p, q, 100), 100, 25)),
        "object_ratio": compared("twin", object_ratio),
        "object_ratio_user": compared("user", object_ratio),
        "recall_at_k": compared("twin", recall_at_k),
        "recall_at_k_user": compared("user", recall_at_k),
        "trace_accesses": on_twin(lambda p, q: buffers.access_trace(p, q, static())),
        "query_split_order": on_twin(lambda p, q: buffers.access_trace(p, q, static(), 10)),
        "freq_exact": on_twin(lambda p, q: buffers.exact_frequency(buffers.access_trace(p, q, static()))),
        "freq_estimated": on_twin(lambda p, q: buffers.estimated_frequency(p, p.where("point_id % 10 = 3"), static(), 12, 120)),
        "buffer_lru": on_twin(lambda p, q: equal_pages(p, q, lambda t: buffers.simulate_buffer(t, "lru", LRU_PAGES).select("q_obj", "hits", "misses"))),
        "buffer_lru_reuse": on_twin(lambda p, q: equal_pages(p, q, lambda t: buffers.lru_by_reuse_distance(t, LRU_PAGES))),
        "buffer_per_bucket": on_twin(per_bucket),
        "param_table": lambda spark, sf: workloads.parameter_table(spark, sf),
        "gamma_min_bound": lambda spark, sf: workloads.gamma_bounds(object_sizes(points(spark, sf, SUPP))),
        "filtered_knn_region": filtered("pre"),
        "filtered_knn_region_post": filtered("post"),
        "filtered_knn_buyers": filtered_exact,
        "filtered_knn_quality": filtered_quality,
        "benchmark_in_documents": benchmark_in_documents,
        "near_copy_hits": on("doc", lambda p, q: gamma.exact_object_knn(p, q, DOC, (1, 20), 3)),
        "sources_roundtrip": sources_roundtrip,
        "interval_join_events": interval_join,
        "events_tumbling": lambda spark, sf: streams.tumbling_counts(load_table(spark, sf, "events")),
        "events_sliding": lambda spark, sf: streams.sliding_counts(load_table(spark, sf, "events")),
        "session_objects": lambda spark, sf: streams.session_objects(load_table(spark, sf, "events")),
        "expression_sq_dist": on_twin(lambda p, q: p.alias("a").join(p.alias("b"), F.col("a.object_id") == F.col("b.object_id")).select(F.col("a.point_id").alias("a"), F.col("b.point_id").alias("b"), sq_dist(F.col("a.vec"), F.col("b.vec")).alias("d"))),
    }
    for name in ("twin", "user", "doc", "supp", "emb"):
        share = HALF if name == "twin" else (1, 20) if name == "doc" else (1, 10) if name == "emb" else QUARTER
        out[f"method_grid_{name}"] = lambda spark, sf, name=name, share=share: workloads.method_grid(spark, sf, name, share)
    for name in ("twin", "user"):
        out |= {
            f"k_sweep_{name}": lambda spark, sf, name=name: workloads.k_sweep(spark, sf, name, HALF if name == "twin" else QUARTER),
            f"buffer_costs_{name}": lambda spark, sf, name=name: workloads.buffer_costs(spark, sf, name),
            f"buffer_size_sweep_{name}": lambda spark, sf, name=name: workloads.buffer_size_sweep(spark, sf, name),
            f"split_sweep_{name}": lambda spark, sf, name=name: workloads.split_sweep(spark, sf, name),
            f"buffer_ablation_{name}": lambda spark, sf, name=name: workloads.buffer_ablation(spark, sf, name),
            f"freq_curves_{name}": lambda spark, sf, name=name: workloads.frequency_curves(spark, sf, name),
            f"freq_error_{name}": lambda spark, sf, name=name: workloads.frequency_errors(spark, sf, name),
        }
    for name in ("supp", "user"):
        out[f"guarantee_rates_{name}"] = lambda spark, sf, name=name: workloads.guarantee_rates(spark, sf, name)
    out["c2_rate"] = lambda spark, sf: workloads.c2_rates(spark, sf, "user")
    out |= sqlapi.queries() | streams.queries() | relational.queries()
    return out | {name: (lambda spark, sf, t=text: relational.run_text(spark, sf, t)) for name, text in relational.TEXTS.items()}


def oracle_sql() -> dict[str, str]:
    s, w = projections("twin"), projections("twin", "query")
    twin, user, doc, supp, emb = (Sql(FAMILIES[n], QUERIES[n]) for n in ("twin", "user", "doc", "supp", "emb"))
    u = projections("user")
    fd = search_sql.floor_div
    flat = f"{twin.points}, {twin.hashes(s)}"

    def counts(level: int, before: str | None = None) -> str:
        cell = fd("bucket", 2**level)
        return f"""{before or twin.pairs}, {twin.hashes(s)}, cc AS (
      SELECT q.object_id AS q_obj, q.point_id AS q_id, x.object_id, x.point_id, CAST(count(*) AS INTEGER) AS cc
      FROM (SELECT *, {cell} AS cell FROM h) q JOIN (SELECT *, {cell} AS cell FROM h) x USING (proj, cell)
      WHERE q.{twin.queries} GROUP BY ALL
    ), ci AS (SELECT q_obj, object_id, count(*) AS num, any_value(nx * nq) AS den FROM cc JOIN sz USING (object_id) JOIN qz USING (q_obj) WHERE cc >= {s.params.l} GROUP BY 1, 2)"""

    def search(sql: Sql, p, n: int, d: int, tail: str, k: int, **options) -> str:
        return f"WITH {sql.search(p, n, d, k, **options)} {tail}"

    found = "SELECT * FROM found"
    base = projections("twin", offset_span="base")
    buyers = load_table(spark, sf, "events").where("event_type = 'purchase' AND value > 50").select(F.col("user_id").alias("object_id")).distinct()
    return gamma.exact_object_knn(p.join(buyers, "object_id", "left_semi"), q, families.USER, QUARTER, 5)


def filtered_quality(spark, sf) -> DataFrame:
    """Nearest documents of good quality."""
    p, q = family_points(spark, sf, "doc")
    good = load_table(spark, sf, "labels").where("quality = 1").select(F.col("doc_id").alias("object_id")).distinct()
    return gamma.exact_object_knn(p.join(good, "object_id", "left_semi"), q, DOC, (1, 20), 3)


def benchmark_in_documents(spark, sf) -> DataFrame:
    """The documents nearest to each benchmark passage, which is no object of the database: by a small share."""
    return gamma.exact_object_knn(points(spark, sf, DOC), points(spark, sf, BENCH), DOC, (1, 50), 3)


def sources_roundtrip(spark, sf) -> DataFrame:
    """nation written and read as JSON, CSV, ORC and Parquet under its declared schema: (format, columns)."""
    nation, folder = load_table(spark, sf, "nation"), f"{work_folder(spark)}/objann-search/formats"
    schema = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in nation.schema.fields)
    out = []
    for fmt in ("json", "csv", "orc", "parquet"):
        write_report(nation, f"{folder}/{fmt}", fmt)
        out.append(read_any(spark, f"{folder}/{fmt}", fmt, schema, **({"header": True} if fmt == "csv" else {})).select(F.lit(fmt).alias("format"), "*"))
    return workloads.union(out)


def index_roundtrip(spark, sf) -> DataFrame:
    """Object search over an index saved to files and loaded again."""
    folder = f"{work_folder(spark)}/objann-search/saved-index"
    save_index(stored_index(spark, sf, "twin"), folder)
    index = load_index(spark, folder)
    return object_knn(index, index.points.where(QUERIES["twin"]), TWIN, HALF, 2).result


def interval_join(spark, sf) -> DataFrame:
    """Errors and the same user's views in the ten minutes before, by a join on the time cell."""
    e = load_table(spark, sf, "events")
    size = 600
    left = e.where("event_type = 'error'").select(F.col("event_id").alias("error_id"), "user_id", F.unix_timestamp("ts").alias("t")).withColumn("cell", F.explode(F.array(F.expr(f"t div {size}"), F.expr(f"t div {size} - 1"))))
    right = e.where("event_type = 'view'").select(F.col("event_id").alias("view_id"), "user_id", F.unix_timestamp("ts").alias("u")).withColumn("cell", F.expr(f"u div {size}"))
    return left.join(right, ["user_id", "cell"]).where(f"u <= t AND u > t - {size}").select("error_id", "view_id")


def counts_at(p: DataFrame, q: DataFrame, level: int) -> DataFrame:
    return hashing.collision_counts(p, q, projections("twin"), level)


def index_at(p: DataFrame, q: DataFrame, level: int) -> DataFrame:
    return gamma.collision_index(counts_at(p, q, level), p, q, projections("twin").params.l)


def candidates(spark, sf, how: str) -> DataFrame:
    """Objects that are candidates of some query object at level 3 (semi), or of none (anti)."""
    p, q = family_points(spark, sf, "twin")
    found = gamma.gamma_candidates(index_at(p, q, 3), HALF).select("object_id")
    return object_sizes(p).join(found, "object_id", how)


def false_positives(p: DataFrame, q: DataFrame) -> DataFrame:
    return gamma.gamma_false_positives(index_at(p, q, 4), gamma.gamma_distance(p, q, TWIN, QUARTER), TWIN, QUARTER, object_sizes(p).count(), 2)


def equal_pages(p: DataFrame, q: DataFrame, run) -> DataFrame:
    return run(buffers.access_trace(p, q, projections("twin"), levels=LRU_LEVEL).withColumn("bytes", F.lit(1).cast("long")))


def per_bucket(p: DataFrame, q: DataFrame) -> DataFrame:
    costs = buffers.simulate_buffer(buffers.access_trace(p, q, projections("twin")), "per_bucket", 0)
    return costs.select("q_obj", "hits", "misses", F.round("mb", 6).alias("mb"), F.round("io_ms", 3).alias("io_ms"))


def queries() -> dict:
    static, centred = (lambda: projections("twin")), (lambda: projections("twin", "query"))
    out = {f"fam_{f.name}_points": family_query(f) for f in ALL_FAMILIES}
    out |= {
        "object_sizes": on_twin(lambda p, q: object_sizes(p)),
        "object_similarity": on_twin(lambda p, q: gamma.object_similarity(p, q, TWIN, 8)),
        "gamma_distance": on_twin(lambda p, q: gamma.gamma_distance(p, q, TWIN, HALF)),
        "gamma_distance_quarter": on_twin(lambda p, q: gamma.gamma_distance(p, q, TWIN, QUARTER)),
        "gamma_distance_user": on("user", lambda p, q: gamma.gamma_distance(p, q, families.USER, QUARTER)),
        "gamma_distance_sketch": on("user", lambda p, q: gamma.gamma_distance_sketch(p, q, families.USER, QUARTER)),
        "exact_object_knn": on_twin(lambda p, q: gamma.exact_object_knn(p, q, TWIN, HALF, 5)),
        "exact_object_knn_user": on("user", lambda p, q: gamma.exact_object_knn(p, q, families.USER, QUARTER, 25)),
        "exact_object_knn_doc": on("doc", lambda p, q: gamma.exact_object_knn(p, q, DOC, (1, 20), 10)),
        "exact_object_knn_supp": on("supp", lambda p, q: gamma.exact_object_knn(p, q, SUPP, QUARTER, 25)),
        "exact_object_knn_emb": on("emb", lambda p, q: gamma.exact_object_knn(p, q, families.EMB, (1, 10), 3)),
        "hash_static_buckets": on_twin(lambda p, q: hashing.inverted(p, static())),
        "level_buckets": on_twin(level_buckets),
        "query_window_hits": on_twin(lambda p, q: hashing.window_hits(p, q, centred(), 2).groupBy("q_obj", "q_id", "object_id", "point_id").agg(F.count("*").alias("cc"))),
        "collision_counts": on_twin(lambda p, q: counts_at(p, q, 3)),
        "collision_index": on_twin(lambda p, q: index_at(p, q, 3)),
        "gamma_candidates": on_twin(lambda p, q: gamma.gamma_candidates(index_at(p, q, 3), HALF)),
        "gamma_false_positives": on_twin(false_positives),
        "candidates_semi": lambda spark, sf: candidates(spark, sf, "left_semi"),
        "untouched_anti": lambda spark, sf: candidates(spark, sf, "left_anti"),
        "stored_buckets": lambda spark, sf: bucket_catalog(stored_index(spark, sf, "twin")),
        "index_stats": lambda spark, sf: index_stats(stored_index(spark, sf, "twin")),
        "index_roundtrip": index_roundtrip,
        "schedule_costs": lambda spark, sf: schedule_costs(stored_index(spark, sf, "twin"), family_points(spark, sf, "twin")[1], 2),
        "object_knn_onepass": searched("twin", HALF, 2),
        "object_knn_iterative": searched("twin", HALF, 2, mode="iterative"),
        "object_knn_batched": searched("twin", HALF, 2, "stats", mode="iterative", proj_batch=32),
        "object_knn_stats": searched("twin", HALF, 2, "stats"),
        "object_knn_k25": searched("twin", HALF, 25),
        "object_knn_by_collisions": searched("twin", HALF, 25, order_by="collision"),
        "object_knn_restart": searched("twin", HALF, 2, "stats", count_mode="restart"),
        "object_knn_restart_iterative": searched("twin", HALF, 2, "stats", count_mode="restart", mode="iterative"),
        "object_knn_cr_bound": searched("twin", HALF, 2, "stats", t2_bound="cR"),
        "object_knn_base_offset": searched("twin", HALF, 2, "stats", offsets={"offset_span": "base"}),
        "object_knn_query_centred": searched("twin", HALF, 2, "stats", "query"),
        "object_knn_exclude_self": searched("twin", HALF, 1, mode="iterative", exclude_self=True),
        "object_knn_exhausted": searched("twin", (1, 1), 90, "stats"),
        "object_knn_user": searched("user", QUARTER, 5),
        "object_knn_user_stats": searched("user", QUARTER, 25, "stats"),
        "object_knn_doc": searched("doc", (1, 20), 5),
        "object_knn_supp": searched("supp", QUARTER, 25),
        "object_knn_emb": searched("emb", (1, 10), 3, "stats"),
        "linear_knn": on_twin(lambda p, q: linear_knn(p, q, 25)),
        "linear_knn_user": on("user", lambda p, q: linear_knn(p, q, 100)),
        "linear_knn_supp": on("supp", lambda p, q: linear_knn(p, q, 25)),
        "static_knn": on_twin(lambda p, q: hashed_knn(p, q, TWIN, static(), 25)),
        "static_knn_user": on("user", lambda p, q: hashed_knn(p, q, families.USER, projections("user"), 50)),
        "query_centred_knn": on_twin(lambda p, q: hashed_knn(p, q, TWIN, centred(), 25)),
        "borda_linear": on_twin(lambda p, q: borda(linear_knn(p, q, 50), 50, 5)),
        "borda_votes": on_twin(lambda p, q: borda(linear_knn(p, q, 50), 50, 5, "votes")),
        "borda_best_rank": on_twin(lambda p, q: borda(linear_knn(p, q, 50), 50, 5, "best_rank")),
        "borda_size_normalised": on_twin(lambda p, q: borda(linear_knn(p, q, 50), 50, 5, "size_normalised", p)),
        "borda_static": on_twin(lambda p, q: borda(hashed_knn(p, q, TWIN, static(), 25), 25, 5)),
        "borda_query_centred": on_twin(lambda p, q: borda(hashed_knn(p, q, TWIN, centred(), 25), 25, 5)),
        "borda_user": on("user", lambda p, q: borda(linear_knn(p, q, 100), 100, 25)),
        "object_ratio": compared("twin", object_ratio),
        "object_ratio_user": compared("user", object_ratio),
        "recall_at_k": compared("twin", recall_at_k),
        "recall_at_k_user": compared("user", recall_at_k),
        "trace_accesses": on_twin(lambda p, q: buffers.access_trace(p, q, static())),
        "query_split_order": on_twin(lambda p, q: buffers.access_trace(p, q, static(), 10)),
        "freq_exact": on_twin(lambda p, q: buffers.exact_frequency(buffers.access_trace(p, q, static()))),
        "freq_estimated": on_twin(lambda p, q: buffers.estimated_frequency(p, p.where("point_id % 10 = 3"), static(), 12, 120)),
        "buffer_lru": on_twin(lambda p, q: equal_pages(p, q, lambda t: buffers.simulate_buffer(t, "lru", LRU_PAGES).select("q_obj", "hits", "misses"))),
        "buffer_lru_reuse": on_twin(lambda p, q: equal_pages(p, q, lambda t: buffers.lru_by_reuse_distance(t, LRU_PAGES))),
        "buffer_per_bucket": on_twin(per_bucket),
        "param_table": lambda spark, sf: workloads.parameter_table(spark, sf),
        "gamma_min_bound": lambda spark, sf: workloads.gamma_bounds(object_sizes(points(spark, sf, SUPP))),
        "filtered_knn_region": filtered("pre"),
        "filtered_knn_region_post": filtered("post"),
        "filtered_knn_buyers": filtered_exact,
        "filtered_knn_quality": filtered_quality,
        "benchmark_in_documents": benchmark_in_documents,
        "near_copy_hits": on("doc", lambda p, q: gamma.exact_object_knn(p, q, DOC, (1, 20), 3)),
        "sources_roundtrip": sources_roundtrip,
        "interval_join_events": interval_join,
        "events_tumbling": lambda spark, sf: streams.tumbling_counts(load_table(spark, sf, "events")),
        "events_sliding": lambda spark, sf: streams.sliding_counts(load_table(spark, sf, "events")),
        "session_objects": lambda spark, sf: streams.session_objects(load_table(spark, sf, "events")),
        "expression_sq_dist": on_twin(lambda p, q: p.alias("a").join(p.alias("b"), F.col("a.object_id") == F.col("b.object_id")).select(F.col("a.point_id").alias("a"), F.col("b.point_id").alias("b"), sq_dist(F.col("a.vec"), F.col("b.vec")).alias("d"))),
    }
    for name in ("twin", "user", "doc", "supp", "emb"):
        share = HALF if name == "twin" else (1, 20) if name == "doc" else (1, 10) if name == "emb" else QUARTER
        out[f"method_grid_{name}"] = lambda spark, sf, name=name, share=share: workloads.method_grid(spark, sf, name, share)
    for name in ("twin", "user"):
        out |= {
            f"k_sweep_{name}": lambda spark, sf, name=name: workloads.k_sweep(spark, sf, name, HALF if name == "twin" else QUARTER),
            f"buffer_costs_{name}": lambda spark, sf, name=name: workloads.buffer_costs(spark, sf, name),
            f"buffer_size_sweep_{name}": lambda spark, sf, name=name: workloads.buffer_size_sweep(spark, sf, name),
            f"split_sweep_{name}": lambda spark, sf, name=name: workloads.split_sweep(spark, sf, name),
            f"buffer_ablation_{name}": lambda spark, sf, name=name: workloads.buffer_ablation(spark, sf, name),
            f"freq_curves_{name}": lambda spark, sf, name=name: workloads.frequency_curves(spark, sf, name),
            f"freq_error_{name}": lambda spark, sf, name=name: workloads.frequency_errors(spark, sf, name),
        }
    for name in ("supp", "user"):
        out[f"guarantee_rates_{name}"] = lambda spark, sf, name=name: workloads.guarantee_rates(spark, sf, name)
    out["c2_rate"] = lambda spark, sf: workloads.c2_rates(spark, sf, "user")
    out |= sqlapi.queries() | streams.queries() | relational.queries()
    return out | {name: (lambda spark, sf, t=text: relational.run_text(spark, sf, t)) for name, text in relational.TEXTS.items()}


def oracle_sql() -> dict[str, str]:
    s, w = projections("twin"), projections("twin", "query")
    twin, user, doc, supp, emb = (Sql(FAMILIES[n], QUERIES[n]) for n in ("twin", "user", "doc", "supp", "emb"))
    u = projections("user")
    fd = search_sql.floor_div
    flat = f"{twin.points}, {twin.hashes(s)}"

    def counts(level: int, before: str | None = None) -> str:
        cell = fd("bucket", 2**level)
        return f"""{before or twin.pairs}, {twin.hashes(s)}, cc AS (
      SELECT q.object_id AS q_obj, q.point_id AS q_id, x.object_id, x.point_id, CAST(count(*) AS INTEGER) AS cc
      FROM (SELECT *, {cell} AS cell FROM h) q JOIN (SELECT *, {cell} AS cell FROM h) x USING (proj, cell)
      WHERE q.{twin.queries} GROUP BY ALL
    ), ci AS (SELECT q_obj, object_id, count(*) AS num, any_value(nx * nq) AS den FROM cc JOIN sz USING (object_id) JOIN qz USING (q_obj) WHERE cc >= {s.params.l} GROUP BY 1, 2)"""

    def search(sql: Sql, p, n: int, d: int, tail: str, k: int, **options) -> str:
        return f"WITH {sql.search(p, n, d, k, **options)} {tail}"

    found = "SELECT * FROM found"
    base = projections("twin", offset_span="base")
    param_rows = ", ".join(str(r) for r in [(50, 62, 32, 35, 23), (100, 75, 39, 43, 29), (150, 82, 43, 46, 31), (200, 87, 46, 49, 33), (1000, 112, 61, 63, 44), (2000, 122, 67, 69, 49), (9994, 144, 80, 81, 58), (24980, 156, 87, 88, 63), (28049, 158, 88, 89, 64)])
    buyers = "SELECT user_id FROM events WHERE event_type = 'purchase' AND value > 50"
    seen = f"SELECT DISTINCT object_id FROM ci WHERE num * 10 >= den * 4"
    out = {f"fam_{f.name}_points": search_sql.shown(f.name) for f in ALL_FAMILIES}
    out |= {
        "object_sizes": f"WITH {twin.points} SELECT object_id, count(*) AS n_points FROM pts GROUP BY 1",
        "object_similarity": f"WITH {twin.pairs} SELECT q_obj, object_id, sum(CASE WHEN sq_dist <= {(8 * TWIN.unit) ** 2} THEN 1 ELSE 0 END)::BIGINT AS num, count(*) AS den FROM pairs GROUP BY 1, 2",
        "gamma_distance": f"WITH {twin.distances(1, 2)} SELECT * FROM gd",
        "gamma_distance_quarter": f"WITH {twin.distances(1, 4)} SELECT * FROM gd",
        "gamma_distance_user": f"WITH {user.distances(1, 4)} SELECT * FROM gd",
        "gamma_distance_sketch": f"WITH {user.distances(1, 4)} SELECT q_obj, object_id, floor(sqrt(CAST(sq_dist AS DOUBLE)) / 512) / 16 AS low, (floor(sqrt(CAST(sq_dist AS DOUBLE)) / 512) + 1) / 16 AS high FROM gd",
        "exact_object_knn": f"WITH {twin.truth(1, 2, 5)} SELECT * FROM truth",
        "exact_object_knn_user": f"WITH {user.truth(1, 4, 25)} SELECT * FROM truth",
        "exact_object_knn_doc": f"WITH {doc.truth(1, 20, 10)} SELECT * FROM truth",
        "exact_object_knn_emb": f"WITH {emb.truth(1, 10, 3)} SELECT * FROM truth",
        "near_copy_hits": f"WITH {doc.truth(1, 20, 3)} SELECT * FROM truth",
        "hash_static_buckets": f"WITH {flat} SELECT proj, bucket, object_id, point_id FROM h",
        "level_buckets": f"WITH {flat} SELECT proj, object_id, point_id, bucket, {fd('bucket', 2)} AS level1, {fd('bucket', 8)} AS level3 FROM h",
        "query_window_hits": f"WITH {twin.points}, {twin.hashes(w)} SELECT q.object_id AS q_obj, q.point_id AS q_id, x.object_id, x.point_id, count(*) AS cc FROM h q JOIN h x USING (proj) WHERE q.{twin.queries} AND 2 * abs(q.bucket - x.bucket) <= {w.width * 4} GROUP BY ALL",
        "collision_counts": f"WITH {counts(3)} SELECT * FROM cc",
        "collision_index": f"WITH {counts(3)} SELECT * FROM ci",
        "gamma_candidates": f"WITH {counts(3)} SELECT * FROM ci WHERE num * 10 >= den * 4",
        "gamma_false_positives": f"WITH {counts(4, twin.distances(1, 4))} SELECT q_obj, object_id, num, den, sq_dist FROM ci JOIN gd USING (q_obj, object_id) WHERE num * 8 * (SELECT count(*) FROM sz) >= den * (2 * (SELECT count(*) FROM sz) + 100) AND sq_dist > {(4 * TWIN.unit) ** 2}",
        "candidates_semi": f"WITH {counts(3)} SELECT object_id, nx AS n_points FROM sz WHERE object_id IN ({seen})",
        "untouched_anti": f"WITH {counts(3)} SELECT object_id, nx AS n_points FROM sz WHERE object_id NOT IN ({seen})",
        "stored_buckets": f"WITH {flat} SELECT proj, bucket, count(*) AS n_points FROM h GROUP BY 1, 2",
        "schedule_costs": f"""WITH {flat}, cells AS (SELECT DISTINCT proj, bucket, {fd('bucket', 4)} AS cell FROM h)
          SELECT q.object_id AS q_obj, count(DISTINCT (q.proj, c.bucket)) AS joint, count(*) AS independent FROM h q JOIN cells c ON q.proj = c.proj AND {fd('q.bucket', 4)} = c.cell WHERE q.{twin.queries} GROUP BY 1""",
        "object_knn_onepass": search(twin, s, 1, 2, found, 2),
        "object_knn_iterative": search(twin, s, 1, 2, found, 2),
        "index_roundtrip": search(twin, s, 1, 2, found, 2),
        "object_knn_batched": search(twin, s, 1, 2, twin.stats(s), 2),
        "object_knn_stats": search(twin, s, 1, 2, twin.stats(s), 2),
        "object_knn_k25": search(twin, s, 1, 2, found, 25),
        "object_knn_by_collisions": search(twin, s, 1, 2, "SELECT q_obj, CAST(row_number() OVER (PARTITION BY q_obj ORDER BY key, object_id) AS INTEGER) AS rank, object_id, sq_dist FROM inside QUALIFY rank <= 25", 25),
        "object_knn_restart": search(twin, s, 1, 2, twin.stats(s), 2, mode="restart"),
        "object_knn_restart_iterative": search(twin, s, 1, 2, twin.stats(s), 2, mode="restart"),
        "object_knn_cr_bound": search(twin, s, 1, 2, twin.stats(s), 2, step=2),
        "object_knn_base_offset": search(twin, base, 1, 2, twin.stats(base), 2),
        "object_knn_query_centred": search(twin, w, 1, 2, twin.stats(w), 2),
        "object_knn_exclude_self": search(twin, s, 1, 2, found, 1, exclude_self=True),
        "object_knn_exhausted": search(twin, s, 1, 1, twin.stats(s), 90),
        "object_knn_user": search(user, u, 1, 4, found, 5),
        "object_knn_user_stats": search(user, u, 1, 4, user.stats(u), 25),
        "object_knn_doc": search(doc, d := projections("doc"), 1, 20, found, 5),
        "object_knn_emb": search(emb, e := projections("emb"), 1, 10, emb.stats(e), 3),
        "linear_knn": f"WITH {twin.linear(25)} SELECT * FROM knn",
        "linear_knn_user": f"WITH {user.linear(100)} SELECT * FROM knn",
        "static_knn": f"WITH {twin.hashed_knn(s, 25)} SELECT * FROM knn",
        "static_knn_user": f"WITH {user.hashed_knn(u, 50)} SELECT * FROM knn",
        "query_centred_knn": f"WITH {twin.hashed_knn(w, 25)} SELECT * FROM knn",
        "borda_linear": twin.borda(twin.linear(50), twin.positional(50), 5),
        "borda_votes": twin.borda(twin.linear(50), "SELECT q_obj, object_id, CAST(count(*) AS DOUBLE) AS score FROM knn GROUP BY 1, 2", 5),
        "borda_best_rank": twin.borda(twin.linear(50), "SELECT q_obj, object_id, CAST(sum(w) AS DOUBLE) AS score FROM (SELECT q_obj, q_id, object_id, max(51 - rank) AS w FROM knn GROUP BY 1, 2, 3) GROUP BY 1, 2", 5),
        "borda_size_normalised": twin.borda(twin.linear(50), "SELECT q_obj, object_id, CAST(sum(51 - rank) AS DOUBLE) / 12 AS score FROM knn GROUP BY 1, 2", 5),
        "borda_static": twin.borda(twin.hashed_knn(s, 25), twin.positional(25), 5),
        "borda_query_centred": twin.borda(twin.hashed_knn(w, 25), twin.positional(25), 5),
        "borda_user": user.borda(user.linear(100), user.positional(100), 25),
        "object_ratio": f"{twin.with_truth(s, 1, 2, 25)} {Sql.RATIO}",
        "object_ratio_user": f"{user.with_truth(u, 1, 4, 25)} {Sql.RATIO}",
        "recall_at_k": f"{twin.with_truth(s, 1, 2, 25)} {Sql.RECALL}",
        "recall_at_k_user": f"{user.with_truth(u, 1, 4, 25)} {Sql.RECALL}",
        "trace_accesses": f"WITH {twin.trace(s)} SELECT * FROM trace",
        "query_split_order": f"WITH {twin.trace(s, 10)} SELECT * FROM trace",
        "freq_exact": f"WITH {twin.trace(s)} SELECT *, count(*) OVER (PARTITION BY q_obj, proj, bucket ORDER BY seq ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS remaining FROM trace",
        "buffer_per_bucket": f"WITH {twin.trace(s)}, served AS (SELECT q_obj, count(*) AS misses, sum(bytes) / 1000000.0::DOUBLE AS mb FROM (SELECT DISTINCT q_obj, level, proj, bucket, bytes FROM trace) GROUP BY 1) SELECT q_obj, n - misses AS hits, misses, round(mb, 6) AS mb, round(misses * 8.5::DOUBLE + mb / 0.156::DOUBLE, 3) AS io_ms FROM served JOIN (SELECT q_obj, count(*) AS n FROM trace GROUP BY 1) USING (q_obj)",
        "buffer_lru": twin.lru(s, LRU_PAGES, LRU_LEVEL),
        "buffer_lru_reuse": twin.lru(s, LRU_PAGES, LRU_LEVEL),
        "param_table": search_sql.parameters(),
        "gamma_min_bound": f"""WITH {supp.points}, z AS (SELECT object_id, count(*) AS n FROM pts GROUP BY 1), r AS (SELECT count(*) AS s, min(n) AS least, avg(n) AS mean, least(0.999::DOUBLE, 25.0::DOUBLE / count(*)) AS beta FROM z)
          SELECT s AS n_objects, least AS least_size, round(mean, 6) AS mean_size, round(sqrt(greatest(ln(10.0::DOUBLE) / (0.01::DOUBLE * mean * least), 2 * ln(2 / beta) / (beta * beta * mean * least))), 6) AS bound FROM r""",
        "filtered_knn_buyers": f"WITH {user.truth(1, 4, 5)} SELECT q_obj, CAST(row_number() OVER (PARTITION BY q_obj ORDER BY sq_dist, object_id) AS INTEGER) AS rank, object_id, sq_dist FROM gd WHERE object_id IN ({buyers}) QUALIFY rank <= 5",
        "filtered_knn_quality": f"WITH {doc.truth(1, 20, 3)} SELECT q_obj, CAST(row_number() OVER (PARTITION BY q_obj ORDER BY sq_dist, object_id) AS INTEGER) AS rank, object_id, sq_dist FROM gd WHERE object_id IN (SELECT doc_id FROM labels WHERE quality = 1) QUALIFY rank <= 3",
        "sources_roundtrip": "SELECT format, n.* FROM nation n, (VALUES ('json'), ('csv'), ('orc'), ('parquet')) f(format)",
        "interval_join_events": "SELECT e.event_id AS error_id, v.event_id AS view_id FROM (SELECT *, CAST(floor(epoch(ts)) AS BIGINT) AS t FROM events) e JOIN (SELECT *, CAST(floor(epoch(ts)) AS BIGINT) AS u FROM events) v ON e.user_id = v.user_id AND e.event_type = 'error' AND v.event_type = 'view' AND u <= t AND u > t - 600",
        "events_tumbling": "SELECT date_trunc('hour', ts) AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2",
        "events_sliding": "SELECT date_trunc('hour', ts) - INTERVAL (h) HOUR AS start, count(*) AS n FROM events, range(2) r(h) GROUP BY 1",
        "session_objects": """SELECT user_id, min(ts) AS start, count(*) AS n_points FROM (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS session FROM (
          SELECT user_id, ts, event_id, CASE WHEN lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 30 MINUTE > ts THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, session""",
        "expression_sq_dist": f"WITH {twin.points} SELECT a.point_id AS a, b.point_id AS b, CAST(list_sum(list_transform(range(1, 65), lambda i: (a.vec[i] - b.vec[i]) * (a.vec[i] - b.vec[i]))) AS BIGINT) AS d FROM pts a JOIN pts b USING (object_id)",
    }
    out |= sqlapi.oracles() | streams.oracles() | relational.oracles()
    return out | {name: relational.duckdb_text(text) for name, text in relational.TEXTS.items()}
