"""Exact token counts at every prefix by dynamic programming (operator 6)."""

from __future__ import annotations

from collections.abc import Iterator
from functools import lru_cache

import ahocorasick
import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from objann.llm.bpe import CACHE_ENTRIES, ColumnCodec, PairIndex, Vocabulary, vocabulary, white_space
from objann.llm.bpe_codec import DEFAULT_VOCABULARY
from objann.llm.shared import read_table, text_or_empty


class PrefixCounter(ColumnCodec):
    """Token counts of all prefixes of a pre-token, and of texts by adding pre-tokens.

    The ids of a prefix are the ids of a shorter prefix and one last token.  Of the tokens that
    end there, exactly one makes a stable pair with the shorter prefix's last token (merging the
    two tokens' bytes alone gives the two back), so a pass over the bytes keeps, for each
    position, the last token and the count; nothing is encoded again.
    """

    def __init__(self, vocab: Vocabulary):
        super().__init__(vocab)
        self.pairs = PairIndex(vocab)
        self.tokens_ending = ahocorasick.Automaton()  # all vocabulary tokens that end at a byte
        for token, i in vocab.id_of.items():
            self.tokens_ending.add_word(token.decode("latin-1"), (i, len(token)))
        self.tokens_ending.make_automaton()
        self.stable: dict[int, bool] = {}
        self.counts: dict[str, int] = {}
        self.parts = {merged: (r, left, right) for r, (left, right, merged) in enumerate(vocab.merges)}
        self.edges: dict[tuple[int, int], list[tuple[int, int, int]]] = {}

    def edge(self, token: int, side: int) -> list[tuple[int, int, int]]:
        """The symbols at one end of a token while it is built: (symbol, rank that makes it, rank that uses it)."""
        found = self.edges.get((token, side))
        if found is None:
            found, used, symbol = [], len(self.vocab.merges), token
            while True:
                part = self.parts.get(symbol)
                found.append((symbol, part[0] if part else -1, used))
                if part is None:
                    break
                used, symbol = part[0], part[1 + side]
            self.edges[token, side] = found
        return found

    def pair(self, left: int, right: int) -> bool:
        """Whether the two tokens side by side stay as they are.

        They do unless some symbol at the left token's end and some symbol at the right token's
        begin exist at the same time and their own merge comes before either is used otherwise.
        Of two equal merges the one further left goes first.
        """
        if len(self.stable) > 4 * CACHE_ENTRIES:
            self.stable.clear()
        rank = self.vocab.rank.get
        fine = True
        begins = self.edge(right, 0)
        for a, made_a, used_a in self.edge(left, 1):
            for b, made_b, used_b in begins:
                r = rank((a << 20) | b)
                if r is not None and made_a < r < used_a and made_b < r <= used_b:
                    fine = False
        self.stable[(left + 1 << 20) | right] = fine
        return fine

    def whole(self, token: int) -> bool:
        fine = self.stable.get(token)
        if fine is None:
            fine = self.stable[token] = self.pairs.ids(self.vocab.token_bytes[token]) == (token,)
        return fine

    def word_prefixes(self, word: bytes) -> list[int]:
        """Count at every byte prefix of one pre-token: element i for the first i bytes."""
        stable = self.stable.get
        last, counts = [-1] * (len(word) + 1), [0] * (len(word) + 1)
        for at, (token, size) in self.tokens_ending.iter(word.decode("latin-1")):
            end = at + 1
            if counts[end]:
                continue
            begin = end - size
            if begin == 0:
                if self.whole(token):
                    last[end], counts[end] = token, 1
                continue
            fine = stable((last[begin] + 1 << 20) | token)
            if fine is None:
                fine = self.pair(last[begin], token)
            if fine:
                last[end], counts[end] = token, counts[begin] + 1
        return counts

    def count_word(self, word: str) -> int:
        n = self.counts.get(word)
        if n is None:
            if len(self.counts) > CACHE_ENTRIES:
                self.counts.clear()
            n = self.counts[word] = self.word_prefixes(word.encode())[-1]
        return n

    def count_text(self, text: str) -> int:
        return sum(map(self.count_word, self.vocab.pre_token.findall(text)))

    def column_counts(self, texts: pa.Array) -> np.ndarray:
        """Token count of every row."""
        found = [np.zeros(0, np.int64)]
        for _, part in self.slices(texts):
            irregular, offsets, numbers, rest, firsts = self.chunks(part)
            words, ends = self.pre_tokens(rest)
            of_words = np.fromiter(map(self.count_word, words), dtype=np.int64, count=len(words))
            of_rest = np.diff(np.concatenate([[0], np.cumsum(of_words)])[ends], prepend=0)
            table = np.concatenate([of_rest, np.array([self.count_text(c) for c in firsts.to_pylist()], dtype=np.int64)])
            counts = np.zeros(len(part), np.int64)
            if len(offsets) > 1:
                counts[~irregular] = np.add.reduceat(table[numbers], offsets[:-1])
            for k, text in zip(np.flatnonzero(irregular), part.filter(pa.array(irregular)).to_pylist()):
                pieces = self.split_special.split(text) if self.split_special else [text]
                counts[k] = sum(1 if j % 2 else self.count_text(p) for j, p in enumerate(pieces))
            found.append(counts)
        return np.concatenate(found)

    def prefixes(self, text: str) -> np.ndarray:
        """Exact token count of text[:i] for every i from 0 to len(text), as if each were encoded alone."""
        out = np.zeros(len(text) + 1, dtype=np.int64)
        at = before = 0
        for j, piece in enumerate(self.split_special.split(text) if self.split_special else [text]):
            if j % 2:
                opened = self.prefixes_plain(piece)
                out[at + 1 : at + len(piece)] = self._joined_prefix(text, at, piece, before, opened)
                before += 1
                at += len(piece)
                out[at] = before
                continue
            if piece:
                out[at : at + len(piece) + 1] = before + self.prefixes_plain(piece)
                at += len(piece)
                before = int(out[at])
        return out

    def _joined_prefix(self, text: str, at: int, special: str, before: int, opened: np.ndarray) -> list[int]:
        """Counts where a prefix ends inside a special string, which is ordinary text there."""
        start = max((m.end() for m in self.split_special.finditer(text, 0, at)), default=0) if self.split_special else 0
        base = self.prefixes(text[:start])[-1] if start else 0
        return [int(base) + int(self.prefixes_plain(text[start : at + k])[-1]) for k in range(1, len(special))]

    def prefixes_plain(self, text: str) -> np.ndarray:
        out = np.zeros(len(text) + 1, dtype=np.int64)
        before = 0
        spans = [m.span() for m in self.vocab.pre_token.finditer(text)]
        k = 0
        while k < len(spans):
            a, b = spans[k]
            word = text[a:b]
            ends = np.cumsum([len(c.encode()) for c in word])
            counts = self.word_prefixes(word.encode())
            out[a + 1 : b + 1] = [before + counts[e] for e in ends]
            if word[0] == "'" and len(word) == 3 and word in ("'re", "'ve", "'ll"):
                out[a + 2] = before + self.count_word(word[0]) + self.count_word(word[1])
            if k + 1 < len(spans) and white_space.fullmatch(word) and white_space.match(text, b):
                # A run of white space is cut before its last character only if something follows;
                # a prefix that ends with that character has the run as one pre-token.
                run = text[a : b + 1]
                longer = self.word_prefixes(run.encode())[-1]
                total = before + counts[-1]
                a2, b2 = spans[k + 1]
                nxt = text[a2:b2]
                ends2 = np.cumsum([len(c.encode()) for c in nxt])
                counts2 = self.word_prefixes(nxt.encode())
                out[a2 + 1 : b2 + 1] = [total + counts2[e] for e in ends2]
                out[b + 1] = before + longer
                before = total + counts2[-1]
                k += 2
                continue
            before += counts[-1]
            k += 1
        return out


@lru_cache(maxsize=4)
def prefix_counter(vocabulary_name: str) -> PrefixCounter:
    return PrefixCounter(vocabulary(vocabulary_name))


def token_counts(df: DataFrame, key: str = "doc_id", text: str = "text", limit: int = 512, vocabulary_name: str = DEFAULT_VOCABULARY) -> DataFrame:
    """(key, n_bytes, n_tokens, over_limit) of each row.

    Null and empty texts have 0 bytes and 0 tokens.  Repeated rows repeat; other columns are left
    out whatever their names.  One narrow stage.
    """

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counter = prefix_counter(vocabulary_name)
        for batch in batches:
            n = counter.column_counts(batch.column(1))
            n_bytes = pc.binary_length(batch.column(1)).cast(pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column(0), n_bytes, pa.array(n, pa.int64()), pa.array(n > limit)], ["key", "n_bytes", "n_tokens", "over_limit"])

    kind = df.schema[key].dataType.simpleString()
    out = df.select(F.col(key).alias("key"), text_or_empty(text).alias("text")).mapInArrow(count, f"key {kind}, n_bytes long, n_tokens long, over_limit boolean")
    return out.select(F.col("key").alias(key), "n_bytes", "n_tokens", "over_limit")


def prefix_table(df: DataFrame, key: str = "doc_id", text: str = "text", vocabulary_name: str = DEFAULT_VOCABULARY) -> DataFrame:
    """(key, prefix_tokens array<int>): element i is the exact token count of the first i code points."""

    def table(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counter = prefix_counter(vocabulary_name)
        for batch in batches:
            rows = [counter.prefixes(t).tolist() for t in batch.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(rows, pa.list_(pa.int32()))], ["key", "prefix_tokens"])

    kind = df.schema[key].dataType.simpleString()
    out = df.select(F.col(key).alias("key"), text_or_empty(text).alias("text")).mapInArrow(table, f"key {kind}, prefix_tokens array<int>")
    return out.select(F.col("key").alias(key), "prefix_tokens")


def longest_prefix_within(prefix_tokens: str, budget: int):
    """Column: the most code points whose count is within the budget, from a prefix table.

    Counts of prefixes may fall by one where a merge completes, so the last fitting place counts.
    """
    fitting = F.transform(F.col(prefix_tokens), lambda n, i: F.when(n <= budget, i).otherwise(-1))
    return F.array_max(fitting)


def op6_token_counts(spark, sf_dir: str) -> DataFrame:
    return token_counts(read_table(spark, sf_dir, "documents"))
