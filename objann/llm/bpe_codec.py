"""BPE encoding and decoding of whole texts (operator 2)."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from objann.llm.bpe import IndexedEncoder, vocabulary
from objann.llm.shared import read_table, text_or_empty

DEFAULT_VOCABULARY = "byte_bpe_50k.json"


@lru_cache(maxsize=4)
def indexed_encoder(vocabulary_name: str) -> IndexedEncoder:
    return IndexedEncoder(vocabulary(vocabulary_name))


def encode_texts(df: DataFrame, key: str = "doc_id", text: str = "text", vocabulary_name: str = DEFAULT_VOCABULARY) -> DataFrame:
    """(key, ids array<int>): each text's ids.  Null text: no ids.  Every row gives one row, so
    repeated rows repeat; other columns, whatever their names, are left out."""

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = indexed_encoder(vocabulary_name)
        for batch in batches:
            rows = [r.astype(np.int32) for r in coder.rows(batch.column(1))]
            ends = np.concatenate([[0], np.cumsum([len(r) for r in rows])]).astype(np.int32)
            flat = np.concatenate(rows) if rows else np.zeros(0, np.int32)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.ListArray.from_arrays(pa.array(ends), pa.array(flat))], ["key", "ids"])

    kind = df.schema[key].dataType.simpleString()
    coded = df.select(F.col(key).alias("key"), text_or_empty(text).alias("text")).mapInArrow(encode, f"key {kind}, ids array<int>")
    return coded.select(F.col("key").alias(key), "ids")


def decode_ids(df: DataFrame, key: str = "doc_id", ids: str = "ids", vocabulary_name: str = DEFAULT_VOCABULARY) -> DataFrame:
    """(key, text): the text of each id list; null ids: empty text; bytes that are no UTF-8 become U+FFFD."""

    def decode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vocab = vocabulary(vocabulary_name)
        for batch in batches:
            texts = [vocab.decode(x or ()).decode("utf-8", "replace") for x in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(texts, pa.string())], ["key", "text"])

    kind = df.schema[key].dataType.simpleString()
    out = df.select(F.col(key).alias("key"), F.col(ids).alias("ids")).mapInArrow(decode, f"key {kind}, text string")
    return out.select(F.col("key").alias(key), "text")


def round_trip(df: DataFrame, key: str = "doc_id", text: str = "text", vocabulary_name: str = DEFAULT_VOCABULARY) -> DataFrame:
    """(key, n_tokens, ids_sha256, decoded_sha256): encode and decode in one pass, digests only.

    Ids are hashed as little-endian unsigned 32-bit integers, decoded text as UTF-8.  The plan is
    one narrow stage; a lost executor's tasks are simply run again.
    """

    def digest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = indexed_encoder(vocabulary_name)
        for batch in batches:
            counts, id_hashes, text_hashes = [], [], []
            for ids in coder.rows(batch.column(1)):
                counts.append(len(ids))
                id_hashes.append(hashlib.sha256(ids.astype("<u4").tobytes()).hexdigest())
                decoded = coder.vocab.decode(ids.tolist()).decode("utf-8", "replace")
                text_hashes.append(hashlib.sha256(decoded.encode()).hexdigest())
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array(counts, pa.int64()), pa.array(id_hashes, pa.string()), pa.array(text_hashes, pa.string())],
                ["key", "n_tokens", "ids_sha256", "decoded_sha256"],
            )

    kind = df.schema[key].dataType.simpleString()
    out = df.select(F.col(key).alias("key"), text_or_empty(text).alias("text")).mapInArrow(
        digest, f"key {kind}, n_tokens long, ids_sha256 string, decoded_sha256 string"
    )
    return out.select(F.col("key").alias(key), "n_tokens", "ids_sha256", "decoded_sha256")


def op2_bpe_codec(spark, sf_dir: str) -> DataFrame:
    return round_trip(read_table(spark, sf_dir, "documents"))
