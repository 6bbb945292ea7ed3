"""Byte-level BPE over Arrow columns.

The vocabulary file (tokenizers JSON) is a parameter; nothing is trained here.  A column of
texts is cut at single spaces between non-space characters.  Such a space always starts a new
pre-token of the byte-level pattern, and the piece before it ends in a non-space character, so
each piece ("chunk") can be encoded alone and every text is the concatenation of its chunks.
Chunks repeat heavily, so a slice of the column encodes each distinct chunk once and gathers
ids with numpy.  Texts with other white space next to a space, or with a special string, take
the whole-text path; both give the ids of the library.
"""

from __future__ import annotations

import heapq
import json
import re
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import regex
import tiktoken

SLICE_BYTES = 12_000_000
LONG_PIECE = 1500
CACHE_ENTRIES = 700_000

# The public byte-level pre-token pattern.
PRE_TOKEN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"

# The same for the regex module, whose \\s has four control characters more than the library's.
_SPACE = r"[^\S\x1c-\x1f]"
PYTHON_PRE_TOKEN = rf"'s|'t|'re|'ve|'m|'ll|'d| ?\p{{L}}+| ?\p{{N}}+| ?(?:[^\s\p{{L}}\p{{N}}]|[\x1c-\x1f])+|{_SPACE}+(?![\S\x1c-\x1f])|{_SPACE}+"
white_space = regex.compile(f"{_SPACE}+")

SPACE_CLASS = r"[\s\x0b\x{1c}-\x{1f}\x{85}\p{Z}]"
_long_run = re.compile(rf"\S{{{LONG_PIECE}}}|\s{{{LONG_PIECE}}}")


def vocabulary_path(name_or_path: str) -> str:
    """A file name of the installed public vocabularies, or a path of one's own."""
    if "/" in name_or_path:
        return name_or_path
    import public_tokenizers

    return public_tokenizers.path(name_or_path)


def byte_letters() -> list[str]:
    """The letter that stands for each byte in a byte-level vocabulary file.

    Printable Latin-1 bytes stand for themselves; the others take code points from 256 on.
    """
    plain = {*range(ord("!"), ord("~") + 1), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
    spare = iter(range(256, 512))
    return [chr(b) if b in plain else chr(next(spare)) for b in range(256)]


class Vocabulary:
    """Ids, merges and special strings of a byte-level BPE file."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as file:
            spec = json.load(file)
        model, letters = spec["model"], byte_letters()
        to_byte = {letter: byte for byte, letter in enumerate(letters)}
        ids = model["vocab"]
        self.specials = {t["content"]: t["id"] for t in spec.get("added_tokens", []) if t.get("special")}
        self.size = 1 + max([*ids.values(), *self.specials.values()])
        self.token_bytes = [b""] * self.size
        for token, i in ids.items():
            if token not in self.specials:
                self.token_bytes[i] = bytes(to_byte[c] for c in token)
        for token, i in self.specials.items():
            self.token_bytes[i] = token.encode()
        self.byte_id = [ids[letter] for letter in letters]
        self.id_of = {b: i for i, b in enumerate(self.token_bytes) if b and i not in set(self.specials.values())}
        self.merges = []  # by rank: (left, right, merged)
        for merge in model["merges"]:
            left, right = merge.split(" ") if isinstance(merge, str) else merge
            self.merges.append((ids[left], ids[right], ids[left + right]))
        self.rank = {(a << 20) | b: r for r, (a, b, _) in enumerate(self.merges)}
        self.token_length = np.array([len(b) for b in self.token_bytes], dtype=np.int64)
        self.longest = int(self.token_length.max())
        self.special_pattern = "|".join(re.escape(s) for s in sorted(self.specials, key=len, reverse=True))
        self.pre_token = regex.compile(PYTHON_PRE_TOKEN)
        self._tik = None

    @property
    def tik(self) -> tiktoken.Encoding:
        if self._tik is None:
            self._tik = tiktoken.Encoding("corpus", pat_str=PRE_TOKEN, mergeable_ranks=self.id_of, special_tokens={})
        return self._tik

    def decode(self, ids) -> bytes:
        return b"".join(map(self.token_bytes.__getitem__, ids))


@lru_cache(maxsize=4)
def vocabulary(name_or_path: str) -> Vocabulary:
    return Vocabulary(vocabulary_path(name_or_path))


class PairIndex:
    """BPE merging through an index of pair occurrences.

    All words of a batch lie in one symbol list.  The index maps the rank of every mergeable
    pair to the positions where it occurs.  Ranks are taken in ascending order; a merge puts the
    two new neighbouring pairs into the lists of their own ranks, which are always higher, so
    each rank is handled once.  Work is proportional to the merges, not to ranks times symbols.
    """

    def __init__(self, vocab: Vocabulary):
        self.vocab = vocab
        self.byte_ids = np.array(vocab.byte_id, dtype=np.int64)
        pairs = np.full((256, 256), -1, dtype=np.int64)
        byte_of = {i: b for b, i in enumerate(vocab.byte_id)}
        for r, (left, right, _) in enumerate(vocab.merges):
            if left in byte_of and right in byte_of:
                pairs[byte_of[left], byte_of[right]] = r
        self.byte_pairs = pairs

    def encode(self, words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """Flat uint32 ids and the end of each word's ids; an empty word has none."""
        sizes = np.fromiter(map(len, words), dtype=np.int64, count=len(words))
        data = np.frombuffer(b"".join(words), dtype=np.uint8)
        if not len(data):
            return np.zeros(0, np.uint32), np.zeros(len(words), np.int64)
        ends = np.cumsum(sizes)
        after_end = np.arange(1, len(data) + 1)
        after_end[ends[sizes > 0] - 1] = -1
        before_begin = np.arange(-1, len(data) - 1)
        before_begin[(ends - sizes)[sizes > 0]] = -1
        ranks = self.byte_pairs[data[:-1], data[1:]]
        ranks[after_end[:-1] < 0] = -1
        places = np.flatnonzero(ranks >= 0)
        places = places[np.argsort(ranks[places], kind="stable")]
        found, begins = np.unique(ranks[places], return_index=True)
        index = dict(zip(found.tolist(), map(np.ndarray.tolist, np.split(places, begins[1:])))) if len(found) else {}
        symbols = self.byte_ids[data].tolist()
        self._merge(symbols, after_end.tolist(), before_begin.tolist(), index)
        flat = np.array(symbols, dtype=np.int64)
        alive = flat >= 0
        return flat[alive].astype(np.uint32), np.concatenate([[0], np.cumsum(alive)])[ends]

    def _merge(self, symbols: list[int], after: list[int], before: list[int], index: dict[int, list[int]]) -> None:
        rank_of, merges = self.vocab.rank.get, self.vocab.merges
        active = list(index)
        heapq.heapify(active)
        while active:
            left, right, merged = merges[r := heapq.heappop(active)]
            places = index.pop(r)
            places.sort()
            high = merged << 20
            for p in places:
                if symbols[p] != left or (q := after[p]) < 0 or symbols[q] != right:
                    continue
                symbols[p] = merged
                symbols[q] = -1
                after[p] = n = after[q]
                if n >= 0:
                    before[n] = p
                    if (new := rank_of(high | symbols[n])) is not None:
                        if new in index:
                            index[new].append(p)
                        else:
                            index[new] = [p]
                            heapq.heappush(active, new)
                if (b := before[p]) >= 0 and (new := rank_of((symbols[b] << 20) | merged)) is not None:
                    if new in index:
                        index[new].append(b)
                    else:
                        index[new] = [b]
                        heapq.heappush(active, new)

    def ids(self, word: bytes) -> tuple[int, ...]:
        return tuple(self.encode([word])[0].tolist())


class ColumnCodec:
    """Cuts a text column into chunks and joins what a chunk coder gives for each.

    ``encode_chunks(list[str]) -> (flat values, int64 offsets)`` codes chunks;
    ``encode_text(str) -> values`` codes a whole text without special strings.
    """

    def __init__(self, vocab: Vocabulary):
        self.vocab = vocab
        edge = rf"^ | $|{SPACE_CLASS} | {SPACE_CLASS}"
        self.irregular = f"{vocab.special_pattern}|{edge}" if vocab.special_pattern else edge
        self.split_special = re.compile(f"({vocab.special_pattern})") if vocab.special_pattern else None

    def slices(self, texts: pa.Array):
        """Runs of rows of about SLICE_BYTES each: (first row, array)."""
        texts = texts.cast(pa.large_string()) if not pa.types.is_large_string(texts.type) else texts
        texts = pc.fill_null(texts, "")
        ends = np.cumsum(pc.binary_length(texts).to_numpy(zero_copy_only=False).astype(np.int64))
        first = 0
        while first < len(texts):
            done = ends[first - 1] if first else 0
            stop = max(first + 1, int(np.searchsorted(ends, done + SLICE_BYTES, side="right")))
            yield first, texts.slice(first, stop - first)
            first = stop

    def whole_text(self, text: str, encode_text) -> list[int]:
        out: list[int] = []
        for k, part in enumerate(self.split_special.split(text) if self.split_special else [text]):
            if k % 2:
                out.append(self.vocab.specials[part])
            elif part:
                out += encode_text(part)
        return out

    def chunks(self, texts: pa.Array):
        """(regular row flags, position offsets per regular row, chunk number per position, chunks)."""
        irregular = pc.match_substring_regex(texts, self.irregular).to_numpy(zero_copy_only=False).astype(bool)
        regular = texts.filter(pa.array(~irregular))
        lists = pc.split_pattern(regular, " ")
        offsets = lists.offsets.to_numpy().astype(np.int64)
        offsets -= offsets[0] if len(offsets) else 0
        values = lists.flatten()
        later = np.ones(len(values), dtype=bool)
        later[offsets[:-1]] = False  # a first chunk has no space before it and may begin with white space
        coded = values.filter(pa.array(later)).dictionary_encode()
        first_coded = values.take(pa.array(offsets[:-1])).dictionary_encode()
        numbers = np.empty(len(values), dtype=np.int64)
        numbers[later] = coded.indices.to_numpy()
        numbers[~later] = len(coded.dictionary) + first_coded.indices.to_numpy()
        return irregular, offsets, numbers, coded.dictionary, first_coded.dictionary

    def joined(self, chunks: pa.Array) -> str:
        """The chunks, each with its space, as one text."""
        return " " + " ".join(chunks.to_numpy(zero_copy_only=False)) if len(chunks) else ""

    def pre_tokens(self, chunks: pa.Array):
        """All chunks' pre-tokens in order, and where each chunk's end among them."""
        words = self.vocab.pre_token.findall(self.joined(chunks))
        at = np.cumsum(np.fromiter(map(len, words), dtype=np.int64, count=len(words)))
        chars = pc.utf8_length(chunks).to_numpy(zero_copy_only=False).astype(np.int64) + 1
        return words, np.searchsorted(at, np.cumsum(chars)) + 1

    def encode(self, texts: pa.Array, encode_rest, encode_text):
        """Flat uint32 ids and int64 offsets of all rows of one slice."""
        irregular, offsets, numbers, rest, firsts = self.chunks(texts)
        ids, ends = encode_rest(rest)
        first_ids = [encode_text(t) if t else [] for t in firsts.to_pylist()]
        lengths = np.concatenate([np.diff(ends, prepend=0), np.array([len(x) for x in first_ids], dtype=np.int64)])
        table = np.concatenate([ids, np.array([i for x in first_ids for i in x], dtype=np.uint32)])
        begins = np.cumsum(lengths) - lengths
        n_at = lengths[numbers]
        flat = ragged_take(table, begins[numbers], n_at)
        n_regular = np.add.reduceat(n_at, offsets[:-1]) if len(offsets) > 1 else np.zeros(0, np.int64)
        if not irregular.any():
            return flat, np.concatenate([[0], np.cumsum(n_regular)])
        parts, counts, at, k = [], [], 0, 0
        slow = iter(texts.filter(pa.array(irregular)).to_pylist())
        for odd in irregular:
            if odd:
                parts.append(np.array(self.whole_text(next(slow), encode_text), dtype=np.uint32))
                counts.append(len(parts[-1]))
            else:
                parts.append(flat[at : at + n_regular[k]])
                at, k = at + n_regular[k], k + 1
                counts.append(len(parts[-1]))
        return np.concatenate(parts), np.concatenate([[0], np.cumsum(counts)])


def ragged_take(table: np.ndarray, begins: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """Concatenation of table[b : b + n] over all (b, n)."""
    total = int(lengths.sum())
    shift = (begins - (np.cumsum(lengths) - lengths)).astype(np.int32 if max(total, len(table)) < 2**31 else np.int64)
    return table[np.repeat(shift, lengths) + np.arange(total, dtype=shift.dtype)]


class FastEncoder(ColumnCodec):
    """Ids through the compiled merger, with the pair index for very long pre-tokens."""

    def __init__(self, vocab: Vocabulary):
        super().__init__(vocab)
        self.pairs = PairIndex(vocab)

    def encode_text(self, text: str) -> list[int]:
        if len(text) >= LONG_PIECE and _long_run.search(text):
            return self.pairs.encode([w.encode() for w in self.vocab.pre_token.findall(text)])[0].tolist()
        return self.vocab.tik.encode_ordinary(text)

    def encode_rest(self, chunks: pa.Array):
        """All chunks in one call: with a space before each they form a text that is cut there."""
        if not len(chunks):
            return np.zeros(0, np.uint32), np.zeros(0, np.int64)
        sizes = pc.binary_length(chunks).to_numpy(zero_copy_only=False).astype(np.int64)
        coder = self.encode_text if sizes.max() >= LONG_PIECE else self.vocab.tik.encode_ordinary
        ids = np.array(coder(self.joined(chunks)), dtype=np.uint32)
        ends = np.searchsorted(np.cumsum(self.vocab.token_length[ids]), np.cumsum(sizes + 1)) + 1
        return ids, ends

    def rows(self, texts: pa.Array):
        """(ids of one row) for each row, in order."""
        for _, part in self.slices(texts):
            flat, ends = self.encode(part, self.encode_rest, self.encode_text)
            for a, b in zip(ends, ends[1:]):
                yield flat[a:b]


class IndexedEncoder(FastEncoder):
    """Ids through the pair occurrence index alone; chunks met before come from a bounded cache."""

    def __init__(self, vocab: Vocabulary):
        super().__init__(vocab)
        self.known: dict[str, bytes] = {}

    def learn(self, words: set[str]) -> None:
        new = [w for w in words if w not in self.known]
        if len(self.known) + len(new) > CACHE_ENTRIES:
            self.known = {}
            new = list(words)
        for a in range(0, len(new), 100_000):
            part = new[a : a + 100_000]
            flat, ends = self.pairs.encode([w.encode() for w in part])
            data, cuts = flat.tobytes(), [0, *(4 * ends).tolist()]
            self.known.update(zip(part, (data[x:y] for x, y in zip(cuts, cuts[1:]))))

    def encode_text(self, text: str) -> list[int]:
        words = self.vocab.pre_token.findall(text)
        self.learn(set(words))
        return np.frombuffer(b"".join([self.known[w] for w in words]), dtype=np.uint32).tolist()

    def encode_rest(self, chunks: pa.Array):
        words, ends = self.pre_tokens(chunks)
        self.learn(set(words))
        coded = [self.known[w] for w in words]
        sizes = np.fromiter(map(len, coded), dtype=np.int64, count=len(coded)) // 4
        return np.frombuffer(b"".join(coded), dtype=np.uint32), np.concatenate([[0], np.cumsum(sizes)])[ends]
