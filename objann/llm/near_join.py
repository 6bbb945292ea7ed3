"""Similarity join of texts on word n-grams: MinHash bands, then full Jaccard checks (operator 1)."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from objann.llm.graph import connected_components
from objann.llm.shared import WrittenTable, read_table, scratch, text_or_empty, written

NGRAM = 5
THRESHOLD = 0.8
TARGET_RECALL = 0.99999
MAX_HASHES = 160
SLICE_BYTES = 4_000_000
MAX_STAR_ROUNDS = 3
SPREAD_GRAMS = 200_000
BLOCK_SETS = 2_000  # sets, and grams of sets, of a component that are compared with as many others at once
BLOCK_GRAMS = 600_000
WORD_BREAK = r"[^\p{L}\p{M}\p{N}_]+"


def set_name(grams: np.ndarray, text: pa.Scalar) -> tuple[int, int]:
    """128 bits, as two signed numbers, that name a gram set; a text without words is named by its bytes."""
    digest = xxhash.xxh3_128_intdigest(grams.tobytes()) if len(grams) else xxhash.xxh3_128_intdigest(text.as_py() or "", seed=1)
    return (digest >> 64) - (1 << 63), (digest & (1 << 64) - 1) - (1 << 63)


def choose_bands(threshold: float = THRESHOLD, recall: float = TARGET_RECALL, max_hashes: int = MAX_HASHES) -> tuple[int, int]:
    """(bands, rows): the most selective banding that finds a pair at the threshold with the recall.

    A pair of similarity s meets in at least one of b bands of r rows with probability
    1 - (1 - s^r)^b.  More rows let fewer dissimilar pairs through, so the largest r whose
    least b stays within the number of hashes is taken.
    """
    best = None
    for rows in range(1, max_hashes + 1):
        bands = math.ceil(math.log(1 - recall) / math.log(1 - threshold**rows)) if threshold < 1 else 1
        if bands * rows <= max_hashes:
            best = (bands, rows)
    if best is None:
        raise ValueError(f"no banding within {max_hashes} hashes reaches recall {recall}")
    return best


def multipliers(n: int, seed: int = 20) -> np.ndarray:
    return (np.random.default_rng(seed).integers(0, 1 << 31, size=n, dtype=np.int64) * 2 + 1).astype(np.uint32)


def shingle_sets(texts: pa.Array, n: int = NGRAM) -> Iterator[np.ndarray]:
    """Sorted distinct 64-bit hashes of each text's word n-grams.

    Words are runs of letters, marks, digits and underscores in lower case.  A text of fewer than
    n words has one gram of all its words; one without words has none.
    """
    texts = pc.fill_null(texts.cast(pa.string()), "")
    ends = np.cumsum(pc.binary_length(texts).to_numpy(zero_copy_only=False).astype(np.int64))
    mix = np.array([xxhash.xxh3_64_intdigest(f"place {k}") | 1 for k in range(n)], dtype=np.uint64)
    first = 0
    while first < len(texts):
        done = ends[first - 1] if first else 0
        stop = max(first + 1, int(np.searchsorted(ends, done + SLICE_BYTES, side="right")))
        plain = pc.replace_substring_regex(pc.utf8_lower(texts.slice(first, stop - first)), WORD_BREAK, " ")
        lists = pc.split_pattern(pc.utf8_trim(plain, " "), " ")
        offsets = lists.offsets.to_numpy().astype(np.int64)
        offsets -= offsets[0]
        coded = lists.flatten().dictionary_encode()
        words = coded.dictionary.to_numpy(zero_copy_only=False)
        hashes = np.fromiter(map(xxhash.xxh3_64_intdigest, words), dtype=np.uint64, count=len(words))[coded.indices.to_numpy()]
        grams = np.zeros(max(0, len(hashes) - n + 1), dtype=np.uint64)
        for k in range(n):
            grams = (grams ^ hashes[k : k + len(grams)]) * mix[k]
            grams ^= grams >> np.uint64(31)
        for a, b in zip(offsets.tolist(), offsets[1:].tolist()):
            if b - a >= n:
                yield np.unique(grams[a : b - n + 1])
            elif b - a == 1 and hashes[a] == _EMPTY:
                yield np.zeros(0, np.uint64)
            else:
                short = np.zeros(1, dtype=np.uint64)
                for k in range(a, b):
                    short = (short ^ hashes[k]) * mix[k - a]
                    short ^= short >> np.uint64(31)
                yield short
        del plain, lists, coded, words, hashes, grams
        pa.default_memory_pool().release_unused()
        first = stop


_EMPTY = np.uint64(xxhash.xxh3_64_intdigest(""))


def band_keys(grams: np.ndarray, factors: np.ndarray, bands: int, rows: int) -> np.ndarray:
    """One signed 64-bit key per band: a hash of the band's MinHash values and its number."""
    small = (grams >> np.uint64(32)).astype(np.uint32)
    least = np.full(len(factors), np.uint32(0xFFFFFFFF))
    for a in range(0, len(small), 4096):
        np.minimum(least, (factors[:, None] * small[None, a : a + 4096]).min(axis=1), out=least)
    values = least.reshape(bands, rows).astype(np.uint64)
    key = np.arange(1, bands + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    for r in range(rows):
        key = (key ^ values[:, r]) * np.uint64(0xD6E8FEB86659FD93)
        key ^= key >> np.uint64(32)
    return key.view(np.int64)


def classify(df: DataFrame, key: str = "doc_id", text: str = "text", threshold: float = THRESHOLD, n: int = NGRAM, recall: float = TARGET_RECALL, with_links: bool = True) -> DataFrame:
    """(key, class_id, n_links, n_copies, text_hash) of every row; n_links only where ``with_links``.

    class_id is the least key of the connected component of the graph whose links are pairs of
    texts with Jaccard similarity of at least the threshold on word n-grams.  n_copies counts the rows with
    the same gram set, the row itself among them; n_links counts the different gram sets that this
    row's set is linked with (0: the class is this text's copies alone).

    1. Rows of one gram set are copies; the least key stands for them.  A gram set is named by
       128 bits of a digest, and gets a number of its own.  A text without words is a copy of equal texts only.
    2. MinHash bands of the representatives are shuffled on the band hash; band and row counts
       follow from the threshold and the target recall.  A pair must also pass the size bound.
    3. In each bucket every member is checked against the bucket's centre on the full gram sets;
       later rounds take centres per component, and members already connected with all others of
       their bucket leave.  When few pairs of different components are left, they are all checked.
       If many are left after the rounds, those of the members that have no rare gram in common
       cannot reach the threshold (see ``_prefix_pairs``); the others are all checked.  So no pair
       within a group is made that cannot change the components, and no link between components
       of a common bucket is lost.
    4. Connected components of the links.
    5. n_links is counted afresh: every set is compared with all others of its component, outside
       of which it has no link (see ``_link_counts``), so it hangs on no round and no bucket.

    Null and empty texts are copies of each other.  Null keys keep a row each, in a class of their
    gram set (null where all keys of the class are null).  An empty table gives no rows; other columns are left out.
    """
    bands, rows = choose_bands(threshold, recall)
    factors = multipliers(bands * rows)
    kind = df.schema[key].dataType.simpleString()
    source = df.select(F.col(key).alias("id"), text_or_empty(text).alias("text"))

    def sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        met: set[tuple[int, int]] = set()
        for batch in batches:
            high, low, sizes, keys = [], [], [], []
            for grams, text in zip(shingle_sets(batch.column(1), n), batch.column(1)):
                name = set_name(grams, text)
                high.append(name[0])
                low.append(name[1])
                sizes.append(len(grams))
                keys.append(None if name in met or not len(grams) else band_keys(grams, factors, bands, rows))
                met.add(name)
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), batch.column(2), pa.array(high, pa.int64()), pa.array(low, pa.int64()), pa.array(sizes, pa.int32()), pa.array(keys, pa.list_(pa.int64()))],
                ["id", "text_hash", "high", "low", "size", "bands"],
            )

    signed = source.select("id", "text", F.xxhash64("text").alias("text_hash")).mapInArrow(sign, f"id {kind}, text_hash long, high long, low long, size int, bands array<long>")
    signed = written(signed, "near-signatures", lasting=True)
    named = signed.select("id", "high", "low", "text_hash")
    with scratch():
        final, counted = _classes(source, signed, threshold, n, with_links)
    return named.join(final, ["high", "low"]).select(F.col("id").alias(key), "class_id", *counted, "n_copies", "text_hash")


def _classes(source: DataFrame, signed: DataFrame, threshold: float, n: int, with_links: bool) -> tuple[DataFrame, list[str]]:
    """(high, low, class_id, n_links, n_copies) of every gram set as a written table, and the names of the optional columns."""
    whole = signed.groupBy("high", "low").agg(F.min("id").alias("rep"), F.count("*").alias("n_copies"), F.first("size").alias("size"), F.first("bands", ignorenulls=True).alias("bands"))
    # a set's number is given once, when the table is written: 64 bits that no two sets share
    groups = written(whole.withColumn("node", F.monotonically_increasing_id()), "near-groups")
    exploded = groups.where("bands IS NOT NULL").select("node", "size", F.explode("bands").alias("band"))
    shared = exploded.groupBy("band").agg(F.count("*").alias("members")).where("members > 1").select("band")
    buckets = WrittenTable(exploded.join(shared, "band"), "near-buckets")
    members = groups.select("high", "low", "node").join(buckets.df.select("node").distinct(), "node", "left_semi")

    def grams_of(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        met: set[tuple[int, int]] = set()
        for batch in batches:
            high, low, sets = [], [], []
            for grams in shingle_sets(batch.column(0), n):
                if not len(grams) or (name := set_name(grams, None)) in met:
                    continue
                met.add(name)
                high.append(name[0])
                low.append(name[1])
                sets.append(grams.tobytes())
            yield pa.RecordBatch.from_arrays([pa.array(high, pa.int64()), pa.array(low, pa.int64()), pa.array(sets, pa.binary())], ["high", "low", "grams"])

    sets = source.select("text").mapInArrow(grams_of, "high long, low long, grams binary")
    sets = sets.join(members, ["high", "low"]).select("node", "grams").dropDuplicates(["node"])
    sets = written(sets.withColumn("n_grams", F.length("grams") / 8), "near-sets")

    def verify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = []
            for a, b in zip(batch.column(2), batch.column(3)):
                x, y = np.frombuffer(a.as_buffer(), np.uint64), np.frombuffer(b.as_buffer(), np.uint64)
                both = len(np.intersect1d(x, y, assume_unique=True))
                keep.append(both >= threshold * (len(x) + len(y) - both) - 1e-9)
            kept = batch.filter(pa.array(keep, pa.bool_()))
            yield pa.RecordBatch.from_arrays([kept.column(0), kept.column(1)], ["a", "b"])

    def linked(pairs: DataFrame) -> DataFrame:
        left = sets.select(F.col("node").alias("a"), F.col("grams").alias("a_grams"))
        right = sets.select(F.col("node").alias("b"), F.col("grams").alias("b_grams"))
        return pairs.join(left, "a").join(right, "b").select("a", "b", "a_grams", "b_grams").mapInArrow(verify, "a long, b long")

    close = F.least("a_size", "b_size") >= threshold * F.greatest("a_size", "b_size")
    links: DataFrame | None = None
    tried: DataFrame | None = None
    state = buckets
    for turn in range(MAX_STAR_ROUNDS + 1):
        if state.df.isEmpty():
            break
        current = state.df if "component" in state.df.columns else state.df.withColumn("component", F.col("node"))
        order = F.xxhash64("node", F.lit(turn)) if turn else F.col("node")
        few = _few_pairs(current)
        if turn < MAX_STAR_ROUNDS and not few:
            centres = current.groupBy("band").agg(F.min_by(F.struct("node", "size", "component"), order).alias("centre"))
            stars = current.join(written(centres, "near-centres"), "band").where(F.col("component") != F.col("centre.component"))
            pairs = stars.select(F.col("node").alias("a"), F.col("size").alias("a_size"), F.col("centre.node").alias("b"), F.col("centre.size").alias("b_size"))
            last = False
        else:
            pairs = _bucket_pairs(current) if few else _prefix_pairs(current, sets, threshold)
            last = True
        pairs = pairs.where(close).select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
        if tried is not None:
            pairs = pairs.join(tried, ["a", "b"], "left_anti")
        pairs = written(pairs, "near-pairs")
        found = written(linked(pairs), "near-links")
        links = found if links is None else written(links.union(found), "near-links")
        if last:
            break
        tried = pairs if tried is None else written(tried.union(pairs), "near-tried")
        components = written(connected_components(links, "a", "b"), "near-components")
        placed = buckets.df.join(components, "node", "left").select("band", "node", "size", F.coalesce("component", "node").alias("component"))
        open_bands = placed.groupBy("band").agg(F.min("component").alias("low"), F.max("component").alias("high")).where("low <> high").select("band")
        state = WrittenTable(placed.join(open_bands, "band", "left_semi"), "near-open")

    if links is None:
        links = sets.select(F.col("node").alias("a"), F.col("node").alias("b")).where("false")
    components = written(connected_components(links, "a", "b"), "near-components")
    per_group = groups.join(components, "node", "left")
    counted: list[str] = []
    if with_links:
        per_group = per_group.join(_link_counts(components, sets, threshold), "node", "left").withColumn("n_links", F.coalesce("n_links", F.lit(0)).cast("long"))
        counted = ["n_links"]
    per_group = written(per_group.select("high", "low", "rep", "n_copies", F.coalesce("component", "node").alias("component"), *counted), "near-placed")
    heads = per_group.groupBy("component").agg(F.min("rep").alias("class_id"))
    return written(per_group.join(heads, "component").select("high", "low", "class_id", *counted, "n_copies"), "near-classes", lasting=True), counted


def similarity_classes(df: DataFrame, key: str = "doc_id", text: str = "text", **options) -> DataFrame:
    """(key, class_id, n_links, n_copies) of every row; see ``classify``."""
    return classify(df, key, text, **options).drop("text_hash")


def common_counts(left: list[np.ndarray], right: list[np.ndarray]) -> np.ndarray:
    """How many grams each set of ``left`` has in common with each set of ``right``.

    Grams of many holders are multiplied as columns of a 0/1 matrix, those of few are paired off.
    """
    grams = np.concatenate([*left, *right])
    owner = np.repeat(np.arange(len(left) + len(right)), [len(x) for x in (*left, *right)])
    _, code, holders = np.unique(grams, return_inverse=True, return_counts=True)
    often = holders * 32 >= len(left) + len(right)
    both = np.zeros((len(left), len(right)), dtype=np.float32)
    for dense in (True, False):
        number = np.cumsum((holders > 1) & (often == dense)) - 1
        own = ((holders > 1) & (often == dense))[code]
        order = np.argsort(number[code[own]], kind="stable")
        codes, owners = number[code[own]][order], owner[own][order]
        on_left = owners < len(left)
        lc, lo, rc, ro = codes[on_left], owners[on_left], codes[~on_left], owners[~on_left] - len(left)
        if not len(lc) or not len(rc):
            continue
        if dense:
            for first in range(0, int(codes[-1]) + 1, 2048):
                a, b = np.zeros((len(left), 2048), np.float32), np.zeros((len(right), 2048), np.float32)
                for matrix, c, o in ((a, lc, lo), (b, rc, ro)):
                    x, y = np.searchsorted(c, (first, first + 2048))
                    matrix[o[x:y], c[x:y] - first] = 1
                both += a @ b.T
            continue
        begin, end = np.searchsorted(rc, lc), np.searchsorted(rc, lc, side="right")
        reach = np.cumsum(end - begin)
        at = 0
        while at < len(lc):
            stop = max(at + 1, int(np.searchsorted(reach, (reach[at - 1] if at else 0) + 1_000_000, side="right")))
            times = (end - begin)[at:stop]
            places = np.arange(times.sum()) - np.repeat(np.cumsum(times) - times, times) + np.repeat(begin[at:stop], times)
            np.add.at(both, (np.repeat(lo[at:stop], times), ro[places]), 1)
            at = stop
    return both


def block_links(left: list[np.ndarray], right: list[np.ndarray], threshold: float) -> tuple[np.ndarray, np.ndarray]:
    """Links of each set of ``left`` to sets of ``right``, and of each of ``right`` to ``left``."""
    both = common_counts(left, right)
    x, y = (np.array([len(s) for s in side], dtype=np.float64) for side in (left, right))
    to_right, to_left = np.zeros(len(left), dtype=np.int64), np.zeros(len(right), dtype=np.int64)
    for a in range(0, len(left), 256):
        part = both[a : a + 256].astype(np.float64)
        link = part >= threshold * (x[a : a + 256, None] + y[None, :] - part) - 1e-9
        to_right[a : a + 256] = link.sum(axis=1)
        to_left += link.sum(axis=0)
    return to_right, to_left


def _link_counts(components: DataFrame, sets: DataFrame, threshold: float) -> DataFrame:
    """(node, n_links) of every node of a component: the members whose sets reach the threshold with its own.

    A component is cut into blocks by a hash of the node, and every pair of blocks is one piece of
    work, so a row is copied once for each block of its component and pairs never become rows.
    Two nodes that make up a component have one link.
    """
    held = components.join(sets.select("node", "n_grams"), "node").groupBy("component").agg(F.count("*").alias("members"), F.sum("n_grams").alias("held"))
    parts = F.ceil(F.greatest(F.col("members") / BLOCK_SETS, F.col("held") / BLOCK_GRAMS)).cast("int")
    placed = written(components.join(held.select("component", "members", parts.alias("parts")), "component"), "near-members")
    own = F.pmod(F.xxhash64("node"), F.col("parts")).cast("int").alias("own")
    spread = placed.where("members > 2").select("component", "node", own, F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("other"))
    spread = spread.select("component", F.least("own", "other").alias("low"), F.greatest("own", "other").alias("high"), "own", "node")
    work = spread.join(sets.select("node", "grams"), "node").repartition("component", "low", "high").sortWithinPartitions("component", "low", "high")

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        piece, held = None, ([], [], [], [])

        def counted() -> pa.RecordBatch:
            left_nodes, left, right_nodes, right = held
            if piece[1] == piece[2]:
                nodes, found = left_nodes, block_links(left, left, threshold)[0] - 1  # but for itself
            elif left and right:
                nodes, found = left_nodes + right_nodes, np.concatenate(block_links(left, right, threshold))
            else:
                nodes, found = [], np.zeros(0, dtype=np.int64)
            return pa.RecordBatch.from_arrays([pa.array(nodes, pa.int64()), pa.array(found, pa.int64())], ["node", "n_links"])

        for batch in batches:
            component, low, high, own, node = (batch.column(batch.schema.get_field_index(c)).to_pylist() for c in ("component", "low", "high", "own", "node"))
            for k, grams in enumerate(batch.column(batch.schema.get_field_index("grams"))):
                if (component[k], low[k], high[k]) != piece:
                    if piece is not None:
                        yield counted()
                    piece, held = (component[k], low[k], high[k]), ([], [], [], [])
                side = 0 if own[k] == low[k] else 2
                held[side].append(node[k])
                held[side + 1].append(np.frombuffer(grams.as_py(), np.uint64))
        if piece is not None:
            yield counted()

    found = work.mapInArrow(count, "node long, n_links long").groupBy("node").agg(F.sum("n_links").alias("n_links"))
    return found.union(placed.where("members = 2").select("node", F.lit(1).cast("long").alias("n_links")))


def _few_pairs(current: DataFrame) -> bool:
    """Whether the pairs of different components within buckets are at most as many as the bucket rows."""
    parts = current.groupBy("band", "component").agg(F.count("*").cast("double").alias("n"))
    per_band = parts.groupBy("band").agg(F.sum("n").alias("n"), F.sum(F.col("n") * F.col("n")).alias("squares"))
    total = per_band.agg(F.sum((F.col("n") * F.col("n") - F.col("squares")) / 2), F.sum("n")).first()
    return (total[0] or 0) <= (total[1] or 0)


def _bucket_pairs(current: DataFrame) -> DataFrame:
    """All pairs (a, b) of different components within buckets, with their sizes."""
    left = current.select("band", F.col("node").alias("a"), F.col("size").alias("a_size"), F.col("component").alias("a_component"))
    right = current.select("band", F.col("node").alias("b"), F.col("size").alias("b_size"), F.col("component").alias("b_component"))
    return left.join(right, "band").where((F.col("a") < F.col("b")) & (F.col("a_component") != F.col("b_component")))


def _prefix_pairs(current: DataFrame, sets: DataFrame, threshold: float) -> DataFrame:
    """Pairs (a, b) of different components, with their sizes, that can still reach the threshold.

    Every set's grams are put in one order, rare ones first.  Sets of sizes x and y at the
    threshold t have at least o = t / (1 + t) (x + y) grams in common, so the first of these is
    among the first x - o + 1 of the one set and the first y - o + 1 of the other: pairs without
    such a gram are left out and no link is.  A gram that only one set has matches nothing, and one
    that only one component has joins nothing new, so a large group of texts that merely share
    passages makes no pairs.
    """
    nodes = current.select("node", "size", "component").distinct()

    def spread(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            first, lengths = 0, pc.binary_length(batch.column(3)).to_numpy() // 8
            ends = np.cumsum(lengths, dtype=np.int64)
            while first < batch.num_rows:
                done = ends[first - 1] if first else 0
                stop = max(first + 1, int(np.searchsorted(ends, done + SPREAD_GRAMS, side="right")))
                part = batch.slice(first, stop - first)
                owner = np.repeat(np.arange(stop - first), lengths[first:stop])
                grams = np.frombuffer(b"".join(part.column(3).to_pylist()), np.int64)
                yield pa.RecordBatch.from_arrays([part.column(0).take(pa.array(owner)), part.column(1).take(pa.array(owner)), part.column(2).take(pa.array(owner)), pa.array(grams)], ["node", "size", "component", "gram"])
                first = stop

    grams = written(nodes.join(sets, "node").select("node", "size", "component", "grams").mapInArrow(spread, "node long, size int, component long, gram long"), "near-grams")
    spans = grams.groupBy("gram").agg(F.count("*").alias("holders"), F.min("component").alias("low"), F.max("component").alias("high")).where("holders > 1")
    one = Window.partitionBy("node")
    place = F.col("size") - F.count("*").over(one) + F.row_number().over(one.orderBy("holders", "gram"))
    longest = F.col("size") - F.ceil(threshold * F.col("size") - 1e-9) + 1
    entries = grams.join(spans, "gram").withColumn("place", place).where((F.col("place") <= longest) & (F.col("low") != F.col("high")))
    entries = written(entries.select("gram", "node", "size", "component", "place"), "near-prefixes")
    left, right = (entries.select("gram", *[F.col(c).alias(f"{side}_{c}") for c in ("node", "size", "component", "place")]) for side in "ab")
    shared = F.ceil(threshold / (1 + threshold) * (F.col("a_size") + F.col("b_size")) - 1e-9)
    reach = (F.col("a_place") <= F.col("a_size") - shared + 1) & (F.col("b_place") <= F.col("b_size") - shared + 1)
    met = left.join(right, "gram").where((F.col("a_node") < F.col("b_node")) & (F.col("a_component") != F.col("b_component")) & reach)
    return met.select(F.col("a_node").alias("a"), "a_size", F.col("b_node").alias("b"), "b_size")


def keep_one(df: DataFrame, key: str = "doc_id", text: str = "text", **options) -> DataFrame:
    """``df`` with one row of each class: the least by key, then by text hash.

    Where that row repeats, one of the repeats stays; a null key is kept only where its class has
    no other key.  The rows are found by a join on key and text hash, so texts are not regrouped.
    """
    rows = written(classify(df, key, text, with_links=False, **options).select(F.col(key).alias("k"), "class_id", "n_copies", "text_hash"), "near-rows")
    member = F.struct(F.col("k").isNull().alias("none"), "k", "text_hash")
    # rows without any key in their class fall back to one per text hash
    part = F.when(F.col("class_id").isNull(), F.col("text_hash")).alias("part")
    best = rows.groupBy("class_id", part).agg(F.min(member).alias("best"))
    repeats = rows.groupBy("k", "text_hash").agg(F.count("*").alias("repeats"))
    best = best.select(F.col("best.k").alias("__k"), F.col("best.text_hash").alias("__h")).distinct()
    best = written(best.join(repeats, F.col("__k").eqNullSafe(F.col("k")) & (F.col("__h") == F.col("text_hash"))).select("__k", "__h", "repeats"), "near-kept")
    hashed = F.xxhash64(text_or_empty(text))
    same = (hashed == F.col("__h")) & F.col(key).eqNullSafe(F.col("__k"))
    once = df.join(best.where("repeats = 1"), same, "left_semi")
    many = best.where("repeats > 1")
    if many.isEmpty():
        return once
    return once.unionByName(df.join(many, same, "left_semi").dropDuplicates([key, text]))


def op1_near_join(spark, sf_dir: str) -> DataFrame:
    return similarity_classes(read_table(spark, sf_dir, "documents"))
