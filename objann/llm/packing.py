"""Packing token streams into fixed windows: concatenate and cut (operator 4)."""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from objann.llm.bpe import FastEncoder, vocabulary
from objann.llm.bpe_codec import DEFAULT_VOCABULARY
from objann.llm.shared import read_table, text_or_empty, written

WINDOW = 2048
END_ID = 1
MAX_PART_TOTALS = 1_000_000  # rows of the broadcast: one per input partition


@lru_cache(maxsize=4)
def fast_encoder(vocabulary_name: str) -> FastEncoder:
    return FastEncoder(vocabulary(vocabulary_name))


def token_stream(df: DataFrame, key: str, text: str, vocabulary_name: str, end_id: int) -> DataFrame:
    """(key, part, part_start, doc_tokens, ids): each document's ids with the end id, and how many
    ids come before it in its partition.  The table is written, so that part and order are fixed
    once: a task that runs again gives the same rows."""

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder, part, before = fast_encoder(vocabulary_name), TaskContext.get().partitionId(), 0
        width = "<u2" if coder.vocab.size <= 1 << 16 and end_id < 1 << 16 else "<u4"
        for batch in batches:
            rows = [np.append(ids, np.uint32(end_id)) for ids in coder.rows(batch.column(1))]
            sizes = np.array([len(r) for r in rows], dtype=np.int64)
            starts = before + np.cumsum(sizes) - sizes
            before += int(sizes.sum())
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array(np.full(len(rows), part, np.int64)), pa.array(starts), pa.array(sizes), pa.array([r.astype(width).tobytes() for r in rows], pa.binary())],
                ["key", "part", "part_start", "doc_tokens", "ids"],
            )

    kind = df.schema[key].dataType.simpleString()
    return df.select(F.col(key).alias("key"), text_or_empty(text).alias("text")).mapInArrow(encode, f"key {kind}, part long, part_start long, doc_tokens long, ids binary")


def pack(
    df: DataFrame,
    key: str = "doc_id",
    text: str = "text",
    window: int = WINDOW,
    end_id: int = END_ID,
    vocabulary_name: str = DEFAULT_VOCABULARY,
    with_ids: bool = False,
) -> DataFrame:
    """Pieces of all documents in windows of ``window`` ids.

    Pass 1 writes the token stream with each partition's own prefix sums; the totals of the
    partitions, summed in order, give every partition its place in the whole stream; pass 2 cuts
    each document where a window ends.  A document over a border gives one record for each
    window it touches.  All windows but the last are full, so at most ``window - 1`` places are
    padding, whatever the input.

    Columns: key, start, length, ids_crc32, doc_tokens, sequence_id, offset (and ids array<int>
    if ``with_ids``).  Null and empty texts are documents of the end id alone.  Repeated rows are
    packed as often as they occur.  An empty table gives no pieces.  Other columns are left out.
    """
    stream = written(token_stream(df, key, text, vocabulary_name, end_id), "packing-stream")
    totals = stream.groupBy("part").agg(F.sum("doc_tokens").alias("total"))
    before = totals.select("part", (F.sum("total").over(Window.orderBy("part")) - F.col("total")).alias("before"))
    if totals.count() <= MAX_PART_TOTALS:
        before = F.broadcast(before)
    placed = stream.join(before, "part").select("key", (F.col("before") + F.col("part_start")).alias("at"), "doc_tokens", "ids")

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        narrow = vocabulary(vocabulary_name).size <= 1 << 16 and end_id < 1 << 16
        for batch in batches:
            keys, starts, lengths, crcs, totals, sequences, offsets, pieces = ([] for _ in range(8))
            rows = zip(batch.column(1).to_pylist(), batch.column(2).to_pylist(), batch.column(3))
            for row, (at, n, data) in enumerate(rows):
                ids = np.frombuffer(data.as_buffer(), dtype="<u2" if narrow else "<u4").astype("<u4")
                begin = 0
                while begin < n:
                    sequence, offset = divmod(at + begin, window)
                    end = min(n, begin + window - offset)
                    keys.append(row)
                    starts.append(begin)
                    lengths.append(end - begin)
                    crcs.append(zlib.crc32(ids[begin:end].tobytes()))
                    totals.append(n)
                    sequences.append(sequence)
                    offsets.append(offset)
                    if with_ids:
                        pieces.append(ids[begin:end].astype(np.int32))
                    begin = end
            columns = [batch.column(0).take(pa.array(keys, pa.int64()))]
            columns += [pa.array(x, pa.int64()) for x in (starts, lengths, crcs, totals, sequences, offsets)]
            names = ["key", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"]
            if with_ids:
                columns.append(pa.array(pieces, pa.list_(pa.int32())))
                names.append("ids")
            yield pa.RecordBatch.from_arrays(columns, names)

    kind = df.schema[key].dataType.simpleString()
    schema = f"key {kind}, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long" + ", ids array<int>" * with_ids
    out = placed.mapInArrow(cut, schema)
    return out.select(F.col("key").alias(key), *[c for c in out.columns if c != "key"])


def op4_packing(spark, sf_dir: str) -> DataFrame:
    return pack(read_table(spark, sf_dir, "documents"))
