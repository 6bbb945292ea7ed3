"""Exact top-k inner-product search by three phases with a uniform threshold (operator 5)."""

from __future__ import annotations

from collections.abc import Iterator
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from objann.llm.shared import read_table, scratch, written

SCALE = 1024
BANDS = 8
BLOCK_BYTES = 4_000_000  # of one block of candidates
BATCH_BYTES = 32_000_000  # of the query vectors that go to every task at once
TILE_CELLS = 1 << 21  # scores held at once
FIRST_SHARE = 8  # one row in so many of each block is scored whole in the first phase
SPARSE = 0.3  # share of entries still open from which they are followed one by one


def integer_vectors(df: DataFrame, key: str, vector: str, scale: int = SCALE) -> DataFrame:
    """(id, dim, vec array<long>): floor(scale * x) per component, x as double.  Rows whose vector is
    null, empty, or holds a null or non-finite component, or whose id is null, take no part."""
    x = F.transform(F.col(vector), lambda v: v.cast("double"))
    fine = F.col(key).isNotNull() & (F.size(vector) > 0) & F.forall(x, lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < float("inf")))
    return df.where(fine).select(F.col(key).cast("long").alias("id"), F.size(vector).alias("dim"), F.transform(x, lambda v: F.floor(v * scale).cast("long")).alias("vec"))


def _blocks(rows: DataFrame, block_bytes: int) -> DataFrame:
    """Rows packed into blocks of about ``block_bytes`` of one dimension: (block, dim, n, ids, data)."""

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, made = TaskContext.get().partitionId(), 0
        held: dict[int, list] = {}

        def close(dim):
            nonlocal made
            ids, data = zip(*held.pop(dim))
            made += 1
            return pa.RecordBatch.from_arrays(
                [pa.array([(part << 32) + made]), pa.array([dim], pa.int32()), pa.array([len(ids)], pa.int32()), pa.array([np.array(ids, np.int64).tobytes()]), pa.array([np.stack(data).tobytes()])],
                ["block", "dim", "n", "ids", "data"],
            )

        for batch in batches:
            flat, ends = batch.column(2).values.to_numpy(), batch.column(2).offsets.to_numpy()
            for k, (i, dim) in enumerate(zip(batch.column(0).to_pylist(), batch.column(1).to_pylist())):
                held.setdefault(dim, []).append((i, flat[ends[k] : ends[k + 1]]))
                if len(held[dim]) * dim * 8 >= block_bytes:
                    yield close(dim)
        for dim in list(held):
            yield close(dim)

    return rows.select("id", "dim", "vec").mapInArrow(pack, "block long, dim int, n int, ids binary, data binary")


class Banded:
    """Integer vectors of one dimension cut into bands, with the length of what follows each band."""

    def __init__(self, ids: np.ndarray, vec: np.ndarray):
        self.ids, self.reach = ids, int(np.abs(vec).max(initial=0))
        self.cuts = [c for c in np.array_split(np.arange(vec.shape[1]), min(BANDS, vec.shape[1])) if len(c)]
        # products and sums of doubles are exact below 2^53; wider numbers stay integers
        self.parts = [np.ascontiguousarray(vec[:, c]) for c in self.cuts]
        squares = np.stack([(p.astype(np.float64) ** 2).sum(axis=1) for p in self.parts], axis=1)
        tails = np.cumsum(squares[:, ::-1], axis=1)[:, ::-1]
        self.rest = np.sqrt(np.concatenate([tails[:, 1:], np.zeros((len(vec), 1))], axis=1)) * (1 + 1e-9)


def _kind(q: Banded, x: Banded):
    return np.float64 if q.reach * x.reach * sum(map(len, q.cuts)) < 1 << 53 else np.int64


def _best_of(rows: np.ndarray, ids: np.ndarray, scores: np.ndarray, k: int) -> np.ndarray:
    """Places of each row's k best entries, ties to the smaller id."""
    order = np.lexsort((ids, -scores, rows))
    sorted_rows = rows[order]
    begin = np.searchsorted(sorted_rows, sorted_rows)
    return order[np.arange(len(order)) - begin < k]


def _tiles(q: Banded, n: int):
    step = max(1, TILE_CELLS // max(1, n))
    return ((a, min(a + step, len(q.ids))) for a in range(0, len(q.ids), step))


def whole_scores(q: Banded, x: Banded, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, int]:
    """(query places, ids, scores, band scores worked out): each query's k best of ``x``."""
    kind, out, work = _kind(q, x), [], 0
    for a, b in _tiles(q, len(x.ids)):
        tile = sum(mine[a:b].astype(kind) @ part.astype(kind).T for mine, part in zip(q.parts, x.parts)).astype(np.int64)
        work += tile.size * len(x.parts)
        own = q.ids[a:b, None] == x.ids[None, :]
        tile[own] = np.iinfo(np.int64).min
        if len(x.ids) > k:
            rows = np.repeat(np.arange(len(tile)), len(x.ids)).reshape(tile.shape)
            keep = tile >= np.partition(tile, len(x.ids) - k, axis=1)[:, [len(x.ids) - k]]
            rows, cols = rows[keep], np.nonzero(keep)[1]
        else:
            rows, cols = (c.ravel() for c in np.indices(tile.shape))
        fine = ~own[rows, cols]
        rows, cols = rows[fine], cols[fine]
        best = _best_of(rows, x.ids[cols], tile[rows, cols], k)
        out.append((rows[best] + a, x.ids[cols[best]], tile[rows[best], cols[best]]))
    return *(np.concatenate(c) for c in zip(*out)), work


def scores_over(q: Banded, x: Banded, k: int, cutoff: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, int]:
    """(query places, ids, scores, band scores worked out): of the entries that reach their query's cutoff the k best.

    Bands are added one by one.  What the bands still to come can add is at most the product of the
    lengths of the two rests; an entry whose sum and that bound stay below the cutoff is closed.
    While most entries are open a band is worked out for all; from SPARSE on only for the open ones.
    """
    kind, out, work = _kind(q, x), [], 0
    mine, parts = [p.astype(kind) for p in q.parts], [p.astype(kind) for p in x.parts]
    for a, b in _tiles(q, len(x.ids)):
        goal = cutoff[a:b, None].astype(np.float64) - 1e-6 * (1 + np.abs(cutoff[a:b, None]))
        differ = q.ids[a:b, None] != x.ids[None, :]
        tile = np.zeros((b - a, len(x.ids)), dtype=kind)
        band = 0
        while True:
            tile += mine[band][a:b] @ parts[band].T
            work += tile.size
            band += 1
            # not before half the bands, where hardly any entry can be closed
            if band == len(parts) or 2 * band >= len(parts):
                opened = (tile + q.rest[a:b, [band - 1]] * x.rest[None, :, band - 1] >= goal) & differ
                if band == len(parts) or opened.mean() <= SPARSE:
                    break
        rows, cols = np.nonzero(opened)
        sums = tile[rows, cols]
        while band < len(parts) and len(rows):
            sums = sums + np.einsum("ij,ij->i", mine[band][a + rows], parts[band][cols])
            work += len(rows)
            left = sums + q.rest[a + rows, band] * x.rest[cols, band] >= goal[rows, 0]
            rows, cols, sums = rows[left], cols[left], sums[left]
            band += 1
        sums = sums.astype(np.int64)
        best = _best_of(rows, x.ids[cols], sums, k)
        out.append((rows[best] + a, x.ids[cols[best]], sums[best]))
    return *(np.concatenate(c) for c in zip(*out)), work


def top_k(df: DataFrame, queries: DataFrame, key: str = "vec_id", vector: str = "embedding", k: int = 10, scale: int = SCALE, batch_bytes: int = BATCH_BYTES) -> DataFrame:
    """(query_id, rank, vec_id, score): each query's k best rows of ``df`` by integer inner product.

    Query vectors go to all tasks in batches of at most ``batch_bytes`` (at least one block), so
    candidates are read where they lie and never shuffled or copied.  For each batch:

    1. Every task scores the first eighth of each block in whole and sends each query's k best of
       them.  The k-th of all these is a cutoff that at least k rows reach.
    2. The cutoffs, one number for each query of the batch, go back to all tasks.
    3. In the other rows the components' bands are added one by one, and only entries that can
       still reach the cutoff get the next band (see ``scores_over``).  What reaches it has its exact
       score and meets the lists of the first phase in the ranking.  No score is worked out twice.

    A row never answers its own id; repeated candidate rows count each, a repeated query row
    (same id and vector) is asked once.  Vectors of another dimension than the query's do not
    meet it.  Fewer than k candidates: all are returned.  Ties go to the smaller id.  An empty table has no
    answers.
    """
    with scratch():
        return _answers(df, queries, key, vector, k, scale, batch_bytes)


def _answers(df: DataFrame, queries: DataFrame, key: str, vector: str, k: int, scale: int, batch_bytes: int) -> DataFrame:
    spark = df.sparkSession
    blocks = written(_blocks(integer_vectors(df, key, vector, scale), BLOCK_BYTES), "topk-candidates")
    asked = integer_vectors(queries, key, vector, scale).dropDuplicates(["id", "vec"])
    asked = written(_blocks(asked, batch_bytes // 8), "topk-queries")
    results: list[DataFrame] = []
    for held in _batches(asked, batch_bytes):
        sets = {dim: Banded(np.frombuffer(b"".join(r["ids"] for r in rows), np.int64), np.frombuffer(b"".join(r["data"] for r in rows), np.int64).reshape(-1, dim)) for dim, rows in held.items()}
        first = dict(zip(sets, np.cumsum([0, *(len(s.ids) for s in sets.values())]).tolist()))  # slots by dimension
        n_slots = sum(len(s.ids) for s in sets.values())

        def read(row, tail: bool) -> Banded:
            ids, data = np.frombuffer(row["ids"], np.int64), np.frombuffer(row["data"], np.int64).reshape(row["n"], row["dim"])
            cut = -(-len(ids) // FIRST_SHARE)
            return Banded(ids[cut:], data[cut:]) if tail else Banded(ids[:cut], data[:cut])

        def run(batches: Iterator[pa.RecordBatch], cutoff: np.ndarray | None, sets=sets, first=first, read=read) -> Iterator[pa.RecordBatch]:
            held: list[list[np.ndarray]] = [[], [], []]

            def best():
                slots, ids, scores = map(np.concatenate, held)
                keep = _best_of(slots, ids, scores, k)
                held[:] = [[slots[keep]], [ids[keep]], [scores[keep]]]

            for batch in batches:
                for row in batch.to_pylist():
                    if (q := sets.get(row["dim"])) is None:
                        continue
                    x, at = read(row, cutoff is not None), first[row["dim"]]
                    if not len(x.ids):
                        continue
                    places, ids, scores, _ = whole_scores(q, x, k) if cutoff is None else scores_over(q, x, k, cutoff[at : at + len(q.ids)])
                    for column, more in zip(held, (places + at, ids, scores)):
                        column.append(more)
                    if sum(map(len, held[0])) > 4 * k * n_slots:
                        best()
            if held[0]:
                best()
                yield pa.RecordBatch.from_arrays([pa.array(c[0], pa.int64()) for c in held], ["slot", "vec_id", "score"])

        entry = "slot long, vec_id long, score long"
        lists = written(blocks.mapInArrow(partial(run, cutoff=None), entry), "topk-lists")
        best_first = F.row_number().over(Window.partitionBy("slot").orderBy(F.desc("score"), "vec_id"))
        cutoff = np.full(n_slots, np.iinfo(np.int64).min // 4, dtype=np.int64)
        for r in lists.withColumn("at", best_first).where(F.col("at") == k).select("slot", "score").collect():  # one row for each query of the batch
            cutoff[r.slot] = r.score
        rest = blocks.mapInArrow(partial(run, cutoff=cutoff), entry)
        asked_ids = np.concatenate([s.ids for s in sets.values()])

        def name(batches: Iterator[pa.RecordBatch], asked_ids=asked_ids) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                yield pa.RecordBatch.from_arrays([pa.array(asked_ids[batch.column(0).to_numpy()]), *batch.columns[1:]], ["query_id", "rank", "vec_id", "score"])

        ranked = lists.union(rest).withColumn("rank", best_first).where(F.col("rank") <= k)
        ranked = ranked.select("slot", "rank", "vec_id", "score").mapInArrow(name, "query_id long, rank int, vec_id long, score long")
        results.append(written(ranked, "topk-answers", lasting=True))
    if not results:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score long")
    out = results[0]
    for more in results[1:]:
        out = out.union(more)
    return out


def _batches(asked: DataFrame, batch_bytes: int) -> Iterator[dict[int, list]]:
    """The query blocks in batches by dimension, each of at most ``batch_bytes`` or one block."""
    sizes = asked.select("block", "dim", (F.length("data") + F.length("ids")).alias("size")).collect()  # three numbers for each block
    sizes.sort(key=lambda r: (r.dim, r.block))
    names, size = [], 0
    for row in [*sizes, None]:
        if names and (row is None or size + row.size > batch_bytes):
            held: dict[int, list] = {}
            for r in asked.where(F.col("block").isin(names)).orderBy("dim", "block").collect():
                held.setdefault(r.dim, []).append(r.asDict())
            yield held
            names, size = [], 0
        if row is not None:
            names.append(row.block)
            size += row.size


def op5_topk(spark, sf_dir: str) -> DataFrame:
    rows = read_table(spark, sf_dir, "embeddings")
    return top_k(rows, rows.where(F.col("vec_id") % 100 == 0))


OP5_SQL = """
WITH v AS (
  SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(1024 * CAST(x AS DOUBLE)) AS BIGINT)) AS vec FROM embeddings
  WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR isnan(x) OR isinf(x))) = 0
), pairs AS (
  SELECT q.vec_id AS query_id, c.vec_id AS vec_id,
         CAST(list_sum(list_transform(list_zip(q.vec, c.vec), lambda p: p[1] * p[2])) AS BIGINT) AS score
  FROM v q JOIN v c ON q.vec_id % 100 = 0 AND q.vec_id <> c.vec_id
), ranked AS (
  SELECT *, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank FROM pairs
)
SELECT query_id, rank, vec_id, score FROM ranked WHERE rank <= 10
"""
