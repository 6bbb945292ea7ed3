"""Media columns in content-defined chunks, deduplicated and read back (operator 7)."""

from __future__ import annotations

import hashlib
import zlib
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from objann.llm.shared import byte_slices, read_table, release_shuffles, scratch, text_or_empty, written

WIDTH = 192
FILL = b" "
MIN_CHUNK, MASK_BITS, MAX_CHUNK = 512, 11, 8192
WINDOW = 32
SLICE_BYTES = 4_000_000
LEVEL = 6
DICTIONARY_BYTES = 110_000
SAMPLE_ROWS, SAMPLE_BYTES = 2_000, 16_000_000  # bounds of what the compression dictionary is made from


def gear_table() -> np.ndarray:
    """A fixed random 32-bit number for each byte, from a digest of the byte."""
    return np.array([int.from_bytes(hashlib.sha256(bytes([b])).digest()[:4], "little") for b in range(256)], dtype=np.uint32)


def to_image(payload: bytes) -> bytes:
    """The payload as an 8-bit grey image (binary PGM), 192 samples a row."""
    return b"P5\n%d %d\n255\n" % (WIDTH, len(payload) // WIDTH) + payload


def from_image(media: bytes) -> tuple[int, int, bytes]:
    """(width, height, samples) of such an image; raises if it is none or is cut short."""
    magic, size, depth, samples = media.split(b"\n", 3)
    width, height = map(int, size.split())
    if magic != b"P5" or depth != b"255" or len(samples) != width * height:
        raise ValueError("not a whole 8-bit grey image")
    return width, height, samples


def payload_of(text: bytes) -> bytes:
    return text + FILL * (-len(text) % WIDTH or (0 if text else WIDTH))


def cut_points(buffers: list[bytes], gear: np.ndarray) -> list[list[int]]:
    """Ends of the chunks of each buffer.

    The rolling gear hash of the last 32 bytes is the sum of their gear numbers, each shifted by
    its age; five doublings give it at every byte.  A chunk ends where its top bits are zero,
    not before MIN_CHUNK and at MAX_CHUNK at the latest.  The first bytes of a buffer, whose window
    would reach into the one before, lie under MIN_CHUNK.
    """
    data = np.frombuffer(b"".join(buffers), dtype=np.uint8)
    hashed = gear[data]
    span = 1
    while span < WINDOW:
        shifted = hashed[:-span] << np.uint32(span)
        hashed = hashed.copy()
        hashed[span:] += shifted
        span *= 2
    places = np.flatnonzero((hashed >> np.uint32(32 - MASK_BITS)) == 0) + 1
    out, base = [], 0
    for buffer in buffers:
        ends, last, size = [], 0, len(buffer)
        own = places[np.searchsorted(places, base + 1) : np.searchsorted(places, base + size)] - base
        for place in [*own.tolist(), size]:
            while place - last > MAX_CHUNK:
                last += MAX_CHUNK
                ends.append(last)
            if place - last >= MIN_CHUNK or place == size:
                if place > last:
                    ends.append(place)
                last = place
        out.append(ends)
        base += size
    return out


def _digest(chunk: bytes) -> bytes:
    return hashlib.blake2b(chunk, digest_size=16).digest()


def chunked(texts: pa.Array, gear: np.ndarray):
    """(row, key, media, chunks) of each text, slice by slice; the key is the media's SHA-256."""
    group, size, first = [], 0, 0
    for k, text in enumerate(texts):
        media = to_image(payload_of(text.as_buffer().to_pybytes()))
        group.append(media)
        size += len(media)
        if size >= SLICE_BYTES or k == len(texts) - 1:
            for j, (m, ends) in enumerate(zip(group, cut_points(group, gear))):
                yield first + j, hashlib.sha256(m).digest(), m, [m[a:b] for a, b in zip([0, *ends], ends)]
            group, size, first = [], 0, k + 1


def feature_of(width: int, height: int, samples: bytes) -> str:
    """Image features as text: size, mean and spread of the samples, entropy, and the mean step between neighbours."""
    grey = np.frombuffer(samples, dtype=np.uint8)
    counts = np.bincount(grey, minlength=256)
    p = counts[counts > 0] / len(grey)
    steps = np.abs(np.diff(grey.astype(np.int16)))
    return f"{width}x{height} mean={grey.mean():.4f} std={grey.std():.4f} entropy={-(p * np.log2(p)).sum():.4f} step={steps.mean():.4f}"


def shared_dictionary(texts: DataFrame) -> bytes:
    """A compression dictionary for short media, from at most SAMPLE_ROWS texts of up to 64 KB in hash order and SAMPLE_BYTES of them; empty where that is too little."""
    picked = texts.where("length(text) BETWEEN 1 AND 65536").select("text").orderBy(F.xxhash64("text"), "text").limit(SAMPLE_ROWS)
    held, size = [], 0
    for row in picked.toLocalIterator():
        held.append(to_image(payload_of(bytes(row.text))))
        size += len(held[-1])
        if size >= SAMPLE_BYTES:
            break
    try:
        return zstandard.train_dictionary(DICTIONARY_BYTES, held).as_bytes() if len(held) >= 32 else b""
    except zstandard.ZstdError:  # the texts have too little in common
        return b""


class Packer:
    """Compresses and restores pieces with one shared dictionary."""

    def __init__(self, dictionary: bytes):
        known = zstandard.ZstdCompressionDict(dictionary) if dictionary else None
        if known is not None:
            known.precompute_compress(level=LEVEL)
        self._pack, self._unpack = zstandard.ZstdCompressor(level=LEVEL, dict_data=known), zstandard.ZstdDecompressor(dict_data=known)

    def pack(self, data: bytes) -> bytes:
        return self._pack.compress(data)

    def unpack(self, data: bytes) -> bytes:
        return self._unpack.decompress(data)


PACK, CHUNK, DICTIONARY = 0, 1, 2  # kinds of rows of a chunk store
ROUNDS = 4  # media are shuffled in so many shares, one after the other, so that a share's shuffle files go before the next
STORE = "kind int, name binary, digests array<binary>, sizes array<int>, shared array<int>, data binary"


def chunk_lists(df: DataFrame, key: str, text: str) -> DataFrame:
    """(id, n_bytes, media, digests, sizes): each row's medium, and its ordered chunk list where the task had not met it before."""
    gear = gear_table()

    def list_chunks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        met: set[bytes] = set()
        for batch in (part for whole in batches for part in byte_slices(whole, 1, SLICE_BYTES)):
            keys, digests, sizes = [], [], []
            for _, name, _, chunks in chunked(batch.column(1), gear):
                keys.append(name)
                digests.append(None if name in met else [_digest(c) for c in chunks])
                sizes.append(None if name in met else [len(c) for c in chunks])
                met.add(name)
            columns = [batch.column(0), pc.binary_length(batch.column(1)).cast(pa.int64()), pa.array(keys, pa.binary()), pa.array(digests, pa.list_(pa.binary())), pa.array(sizes, pa.list_(pa.int32()))]
            yield pa.RecordBatch.from_arrays(columns, ["id", "n_bytes", "media", "digests", "sizes"])

    kind = df.schema[key].dataType.simpleString()
    return _texts(df, key, text).mapInArrow(list_chunks, f"id {kind}, n_bytes long, media binary, digests array<binary>, sizes array<int>")


def _texts(df: DataFrame, key: str, text: str) -> DataFrame:
    return df.select(F.col(key).alias("id"), text_or_empty(text).cast("binary").alias("text"))


def chunk_store(df: DataFrame, listed: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """The store of all media as a written table: every different chunk once, and no medium whole.

    A row of kind PACK is one distinct medium: its ordered list of chunk digests and sizes, the places
    whose chunks are kept elsewhere, and its other chunks.  A row of kind CHUNK is a chunk with more than one use, by its
    digest.  Joins on digests find these; the least (medium, place) of the uses hands its chunk in.
    A round handles the media of one share of the digests' checksums.  One row holds the dictionary that all pieces are compressed with.
    """
    spark = df.sparkSession
    source = _texts(df, key, text)
    dictionary = shared_dictionary(source)
    lists = written(listed.where("digests IS NOT NULL").select("media", "digests", "sizes").dropDuplicates(["media"]), "media-manifests")
    places = lists.select("media", F.posexplode("digests").alias("place", "digest"))
    owners = places.groupBy("digest").agg(F.count("*").alias("uses"), F.min(F.struct("media", "place")).alias("owner")).where("uses > 1")
    uses = places.join(written(owners, "media-owners"), "digest").select("media", "place", (F.struct("media", "place") == F.col("owner")).alias("lends"))
    uses = written(uses.groupBy("media").agg(F.collect_list(F.struct("place", "lends")).alias("uses")), "media-uses")
    manifests = lists.join(uses, "media", "left")
    release_shuffles(spark)  # before the one large shuffle

    def compress_share(share: int):
        def compress(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            met: set[bytes] = set()
            packer = Packer(dictionary)
            for batch in (part for whole in batches for part in byte_slices(whole, 0, SLICE_BYTES)):
                keys, data = [], []
                for text in batch.column(0):
                    media = to_image(payload_of(text.as_buffer().to_pybytes()))
                    name = hashlib.sha256(media).digest()
                    if zlib.crc32(name) % ROUNDS == share and name not in met:
                        met.add(name)
                        keys.append(name)
                        data.append(packer.pack(media))
                yield pa.RecordBatch.from_arrays([pa.array(keys, pa.binary()), pa.array(data, pa.binary())], ["media", "data"])

        return compress

    def keep(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        packer = Packer(dictionary)
        manifest = last = None
        for batch in (part for whole in batches for part in byte_slices(whole, 4, SLICE_BYTES // 4)):
            rows = []
            for k in range(batch.num_rows):
                name = batch.column(0)[k].as_py()
                if (data := batch.column(4)[k].as_py()) is None:
                    manifest = (name, *(batch.column(c)[k].as_py() for c in (1, 2, 3)))
                    continue
                if name == last:  # the same medium from another task
                    continue
                last, (known, digests, sizes, uses) = name, manifest
                whole = packer.unpack(data)
                ends = np.cumsum(sizes).tolist()
                chunks = [whole[a:b] for a, b in zip([0, *ends], ends)]
                shared = {u["place"]: u["lends"] for u in uses or ()}
                rows.append((PACK, known, digests, sizes, sorted(shared), packer.pack(b"".join(c for p, c in enumerate(chunks) if p not in shared))))
                rows += [(CHUNK, digests[p], None, None, None, packer.pack(chunks[p])) for p, lends in sorted(shared.items()) if lends]
            columns = list(zip(*rows)) or [()] * 6
            kinds = (pa.int32(), pa.binary(), pa.list_(pa.binary()), pa.list_(pa.int32()), pa.list_(pa.int32()), pa.binary())
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, kinds)], ["kind", "name", "digests", "sizes", "shared", "data"])

    def kept(share: int) -> DataFrame:
        media = source.select("text").mapInArrow(compress_share(share), "media binary, data binary")
        # a medium's manifest and its data, once from each task that met it, lie side by side in one partition
        own = manifests.where(F.crc32("media") % ROUNDS == share)
        meet = own.select("media", "digests", "sizes", "uses", F.lit(None).cast("binary").alias("data")).unionByName(media, allowMissingColumns=True)
        return meet.repartition("media").sortWithinPartitions("media", F.col("data").isNotNull()).mapInArrow(keep, STORE)

    parts = [written(spark.createDataFrame([(DICTIONARY, bytearray(b"dictionary"), None, None, None, bytearray(dictionary))], STORE), "media-store", lasting=True)]
    for share in range(ROUNDS):
        parts.append(written(kept(share), "media-store", lasting=True))
        release_shuffles(spark)
    return reduce(DataFrame.union, parts)


def read_back(store: DataFrame) -> DataFrame:
    """(media, payload_bytes, payload_sha256, tail_crc32, media_bytes, media_sha256, n_chunks, feature) of every medium of a store.

    A medium is put together from its ordered chunk list alone: its own chunks, and the shared ones by
    a join on digests, each fetched once however often the medium repeats it.  Every chunk and the whole are checked; a missing or altered chunk is an error.
    Media without shared chunks are read where they lie; no other data is moved.
    """
    dictionary = bytes(store.where(F.col("kind") == DICTIONARY).first().data)
    packs = store.where(F.col("kind") == PACK).select(F.col("name").alias("media"), "digests", "sizes", "shared", "data")
    alone = packs.where(F.size("shared") == 0).withColumn("borrowed", F.expr("cast(null as array<struct<digest:binary,data:binary>>)"))
    some = packs.where(F.size("shared") > 0)
    digests = F.array_distinct(F.transform("shared", lambda place: F.col("digests")[place]))
    wanted = some.select("media", F.explode(digests).alias("digest"))
    chunks = store.where(F.col("kind") == CHUNK).select(F.col("name").alias("digest"), "data")
    borrowed = wanted.join(chunks, "digest", "left").groupBy("media").agg(F.collect_list(F.struct("digest", "data")).alias("borrowed"))
    names = ["media", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "n_chunks", "feature"]

    def rebuild(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        packer = Packer(dictionary)
        for batch in (part for whole in batches for part in byte_slices(whole, 4, SLICE_BYTES // 4)):
            rows = []
            for k in range(batch.num_rows):
                name, digests, sizes, shared, data, borrowed = (batch.column(c)[k].as_py() for c in range(6))
                own, at, elsewhere = packer.unpack(data), 0, {b["digest"]: b["data"] for b in borrowed or ()}
                chunks, kept = [], set(shared)
                for place, size in enumerate(sizes):
                    if place in kept:
                        if elsewhere.get(digests[place]) is None:
                            raise ValueError("a chunk is missing from the store")
                        chunks.append(packer.unpack(elsewhere[digests[place]]))
                    else:
                        chunks.append(own[at : at + size])
                        at += size
                    if _digest(chunks[-1]) != digests[place]:
                        raise ValueError("a chunk does not match its digest")
                whole = b"".join(chunks)
                digest = hashlib.sha256(whole)
                if digest.digest() != name:
                    raise ValueError("a medium does not match its digest")
                width, height, samples = from_image(whole)
                rows.append((name, len(samples), hashlib.sha256(samples).hexdigest(), zlib.crc32(samples[-16:]), len(whole), digest.hexdigest(), len(chunks), feature_of(width, height, samples)))
            columns = list(zip(*rows)) or [()] * len(names)
            kinds = [pa.binary(), pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.string()]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds)], names)

    schema = "media binary, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, n_chunks long, feature string"
    order = ["media", "digests", "sizes", "shared", "data", "borrowed"]
    parts = [alone.select(*order), some.join(borrowed, "media", "left").select(*order)]
    return parts[0].mapInArrow(rebuild, schema).union(parts[1].mapInArrow(rebuild, schema))


def store_and_read(df: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, n_bytes, payload_bytes, payload_sha256, tail_crc32, media_bytes, media_sha256, n_chunks, feature).

    1. One pass lists each medium's chunks.  2. ``chunk_store`` writes every different chunk once; media go to their key's
    partition once, compressed.  3. ``read_back`` puts every medium together from the store alone,
    checks it, and computes the features from the samples read back.  4. A join on the medium's
    key gives each document its row.

    No step gathers a group of copies: counts are partial aggregates, and the joins with a hot
    digest or key read written tables on both sides, which the adaptive planner splits.
    Null and empty texts are one row of fill.  Equal texts have equal values; repeated rows
    repeat; an empty table gives no rows; other columns are left out.
    """
    listed = written(chunk_lists(df, key, text), "media-lists", lasting=True)
    with scratch():
        store = chunk_store(df, listed, key, text)
    release_shuffles(df.sparkSession)
    read = written(read_back(store), "media-read", lasting=True)
    return listed.select("id", "n_bytes", "media").join(read, "media").select(F.col("id").alias(key), "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "n_chunks", "feature")


def op7_media_chunks(spark, sf_dir: str) -> DataFrame:
    return store_and_read(read_table(spark, sf_dir, "documents"))
