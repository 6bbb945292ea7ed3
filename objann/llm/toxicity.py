"""Toxicity scores from a learned lexicon, fuzzy matching and context windows (operator 9)."""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass, field
from functools import cached_property

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from objann.llm.near_join import shingle_sets
from objann.llm.shared import read_table, scratch, text_or_empty, written

MAX_LABELLED = 8000  # bound of the sample of labelled rows that a model is fitted on
STEM = range(4, 9)  # letters of a word's beginning
MIN_LIFT = 20.0
MIN_EVIDENCE = 26.0  # keeps chance out among millions of features
ORDINARY = 3  # clean texts with a word that show it to be no misspelling, where the toxic ones do not outweigh them
BELIEF = 10.0  # texts that the exact term's record counts as, beside the texts with its misspellings
KNOWN_WORDS = 200_000  # words whose match is remembered in a task
CONTEXT = 8
SLICE_BYTES = 12_000_000

_word = re.compile(r"[^\W_]+(?:[@$!*0-9]+[^\W_]+)*")
_runs = re.compile(r"(.)\1{2,}")
_cue = re.compile(r"\b(?:quot\w*|wrote|writes|said|says|cited?|zitat\w*|schrieb|sagte|dijo|escribi\w*|cita|dit|écrit|citation)\b")
_plain = str.maketrans("01345@$!", "oieasasi")
ODD = r"[\p{L}][0-9@$!*]+[\p{L}]|(^|[^\p{L}])[0-9@$!]+\p{L}\p{L}|(.)(?:aaa|eee|iii|ooo|uuu)"  # words that may be spelled with other signs or drawn out
OPEN_QUOTES, CLOSE_QUOTES = "\"“„«‹", "\"”“»›"


class Automaton:
    """Levenshtein automaton of one word, with its states made as they are met.

    A state holds one bit set for each number of edits: bit j is set where the letters read so far are that
    many edits from the word's first j letters.  Transitions are kept by (state, places of the
    letter in the word), so a letter is followed by one look-up once its state has been met.
    """

    def __init__(self, word: str, bound: int):
        self.size, self.bound = len(word), bound
        self.places: dict[str, int] = {}
        for k, letter in enumerate(word):
            self.places[letter] = self.places.get(letter, 0) | (1 << k)
        self.full = (1 << (self.size + 1)) - 1
        self.start = tuple(min(self.full, (1 << (d + 1)) - 1) for d in range(bound + 1))
        self.moves: dict[tuple, tuple] = {}

    def step(self, state: tuple, letter: str) -> tuple:
        at = self.places.get(letter, 0)
        new = self.moves.get((state, at))
        if new is None:
            rows = [(state[0] & at) << 1]
            for d in range(1, self.bound + 1):
                # the same letter; another letter, one too many, one left out
                rows.append((((state[d] & at) << 1) | (state[d - 1] << 1) | state[d - 1] | (rows[d - 1] << 1)) & self.full)
            new = self.moves[state, at] = tuple(rows)
        return new

    def whole(self, state: tuple) -> int | None:
        """Edits between the whole word and the letters read, None beyond the bound."""
        return next((d for d, row in enumerate(state) if row >> self.size), None)

    def beginning(self, state: tuple) -> int | None:
        """Edits between the letters read and the nearest beginning of the word."""
        return next((d for d, row in enumerate(state) if row), None)


class Trie:
    """Trie of words and stems, walked together with a word's Levenshtein automaton.

    A branch is left as soon as the automaton has no state left, so only the part of the lexicon
    that the word can still match is visited.
    """

    def __init__(self, words: list[str], stems: list[str] = ()):
        self.root: dict = {}
        for mark, terms in (("=", words), ("+", stems)):
            for term in terms:
                node = self.root
                for letter in term:
                    node = node.setdefault(letter, {})
                node[mark * 2] = term
        self.most = max((edits(t) for t in (*words, *stems)), default=0)

    def within(self, word: str) -> tuple[str, int] | None:
        """(term, distance) of the nearest term within its number of edits of the word, or of a beginning of it where
        the term is a stem; ties to the smaller term."""
        automaton = Automaton(word, self.most)
        found: tuple[int, str] | None = None
        stack = [(self.root, automaton.start)]
        while stack:
            node, state = stack.pop()
            for letter, child in node.items():
                if letter in ("==", "++"):
                    far = automaton.whole(state) if letter == "==" else automaton.beginning(state)
                    if far is not None and far <= edits(child) and (found is None or (far, child) < found):
                        found = (far, child)
                    continue
                new = automaton.step(state, letter)
                if any(new):
                    stack.append((child, new))
        return (found[1], found[0]) if found else None


def edits(term: str) -> int:
    """Misspellings allowed for a term: none under 5 letters, one up to 7, two beyond."""
    return 0 if len(term) < 5 else 1 if len(term) < 8 else 2


@dataclass
class Lexicon:
    """Terms with their strengths: the log odds that a text is toxic, for the term itself and for its misspellings.

    All words and stems are in the trie; one whose misspellings speak for nothing (strength 0) can
    be left out of it without any change to a score.
    """

    words: list[str]
    stems: list[str]
    strength: dict[str, float] = field(default_factory=dict)
    spelled: dict[str, float] | None = None  # strength of a misspelling by term; None: as the term itself
    ordinary: frozenset[str] = frozenset()  # words that only look like misspelled terms
    met: dict[str, float] = field(default_factory=dict, repr=False, compare=False)

    def misspelled(self, term: str) -> float:
        return MISSPELLED * (self.strength.get(term, 1.0) if self.spelled is None else min(self.strength.get(term, 1.0), self.spelled.get(term, 0.0)))

    @cached_property
    def trie(self) -> Trie:
        return Trie([w for w in self.words if self.misspelled(w) > 0], [s for s in self.stems if self.misspelled(s) > 0])

    @cached_property
    def known(self) -> frozenset[str]:
        return frozenset(self.words)

    @cached_property
    def beginnings(self) -> tuple[frozenset[str], list[int]]:
        return frozenset(self.stems), sorted({len(s) for s in self.stems}, reverse=True)

    @cached_property
    def fragments(self) -> str | None:
        """Pattern of what a matching word must hold: one of its term's parts is intact."""
        begins, ends, inner = {*self.words, *self.stems}, set(), set()
        if not begins:
            return None
        for term in [*self.words, *self.stems]:
            if self.misspelled(term) <= 0 or not edits(term):
                continue
            parts = edits(term) + 1
            cuts = [len(term) * k // parts for k in range(parts + 1)]
            pieces = [term[a:b] for a, b in zip(cuts, cuts[1:])]
            begins.add(pieces[0])
            if term in self.known:
                ends.add(pieces[-1])
                inner.update(pieces[1:-1])
            else:
                inner.update(pieces[1:])
        group = lambda words: "|".join(sorted(map(re.escape, words)))
        out = rf"(?:^|[^\p{{L}}\p{{N}}])(?:{group(begins)})"
        if ends:
            out += rf"|(?:{group(ends)})(?:[^\p{{L}}\p{{N}}]|$)"
        if inner:
            out += f"|{group(inner)}"
        return out

    def exact(self, word: str) -> str | None:
        if word in self.known:
            return word
        stems, lengths = self.beginnings
        return next((word[:n] for n in lengths if word[:n] in stems), None)

    def fuzzy(self, word: str) -> str | None:
        """The term that a word that is none looks like a misspelling of."""
        if word in self.ordinary:
            return None
        plain = _runs.sub(r"\1", word.translate(_plain)) if not word.isdigit() else word
        if plain != word and (term := self.exact(plain)) is not None:
            return term
        found = self.trie.within(plain.replace("*", "?"))
        return found[0] if found else None

    def match(self, word: str) -> float:
        """Strength of one lower-case word, 0 where it is neither a term nor a misspelled one."""
        if (known := self.met.get(word)) is not None:
            return known
        if (term := self.exact(word)) is not None:
            out = self.strength.get(term, 1.0)
        else:
            term = self.fuzzy(word)
            out = self.misspelled(term) if term is not None else 0.0
        if len(self.met) >= KNOWN_WORDS:
            self.met.clear()
        self.met[word] = out
        return out


def context_score(chunks: list[str], at: int) -> float:
    """How much the words around a hit speak of quotation: 1 inside quotation marks, 0.5 after a verb of saying, else 0."""
    left, right = " ".join(chunks[max(0, at - CONTEXT) : at]), " ".join(chunks[at + 1 : at + 1 + CONTEXT])
    own = chunks[at]
    opened = any(c in left + own[:1] for c in OPEN_QUOTES)
    closed = any(c in own[1:] + right for c in CLOSE_QUOTES)
    if opened and closed:
        before = left + " " + own[:1]
        if before.count('"') % 2 or any(before.rfind(o) > before.rfind(c) for o, c in (("“", "”"), ("„", "“"), ("«", "»"), ("‹", "›")) if o in before):
            return 1.0
    return 0.5 if _cue.search(left) else 0.0


FEATURES = 3
MISSPELLED = 0.9  # what a misspelled term counts beside an exact one
STRONGEST = 6.0
WEAKEST = 1.0  # log odds from which a term's misspellings speak for abuse at all


def text_features(texts: pa.Array, lexicon: Lexicon) -> np.ndarray:
    """Per text: the strongest abusive term, the log sum of all abusive terms' strengths, and that of the quoted ones."""
    out = np.zeros((len(texts), FEATURES))
    if lexicon.fragments is None:
        return out
    texts = pc.fill_null(texts.cast(pa.string()), "")
    ends = np.cumsum(pc.binary_length(texts).to_numpy(zero_copy_only=False).astype(np.int64))
    first = 0
    while first < len(texts):
        done = ends[first - 1] if first else 0
        stop = max(first + 1, int(np.searchsorted(ends, done + SLICE_BYTES, side="right")))
        lists = pc.split_pattern(pc.utf8_lower(texts.slice(first, stop - first)), " ")
        offsets = lists.offsets.to_numpy().astype(np.int64)
        offsets -= offsets[0]
        coded = lists.flatten().dictionary_encode()
        chunks, numbers = coded.dictionary, coded.indices.to_numpy()
        likely = pc.or_(pc.match_substring_regex(chunks, lexicon.fragments), pc.match_substring_regex(chunks, ODD))
        hits: dict[int, list[float]] = {}
        for number in np.flatnonzero(likely.to_numpy(zero_copy_only=False)).tolist():
            strengths = [k for w in _word.findall(chunks[number].as_py()) if (k := lexicon.match(w)) > 0]
            if strengths:
                hits[number] = strengths
        if hits:
            is_hit = np.zeros(len(chunks), dtype=bool)
            is_hit[list(hits)] = True
            places = np.flatnonzero(is_hit[numbers])
            rows = np.searchsorted(offsets, places, side="right") - 1
            for row in np.unique(rows).tolist():
                a, b = offsets[row], offsets[row + 1]
                own = places[rows == row] if len(places) < 64 else places[np.searchsorted(places, a) : np.searchsorted(places, b)]
                most = abuse = mentioned = 0.0
                for p in own.tolist():
                    low = max(a, p - CONTEXT)
                    near = chunks.take(pa.array(numbers[low : min(b, p + CONTEXT + 1)])).to_pylist()
                    quoted = context_score(near, p - low)
                    for strength in hits[int(numbers[p])]:
                        most = max(most, (1 - quoted) * strength)
                        abuse += (1 - quoted) * strength
                        mentioned += quoted * strength
                out[first + row] = most, np.log1p(abuse), np.log1p(mentioned)
        first = stop
    return out


@dataclass
class ToxicityModel:
    lexicon: Lexicon
    weights: list[float]  # intercept, then one per feature

    def score(self, features: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.weights[0] + features @ np.array(self.weights[1:]), -30, 30)))


def fit_weights(features: np.ndarray, labels: np.ndarray, ridge: float = 0.1, steps: int = 60) -> list[float]:
    """Ridge logistic regression by damped Newton steps; without both classes all scores are the base rate."""
    x = np.column_stack([np.ones(len(features)), features])
    w = np.zeros(x.shape[1])
    if len(labels) == 0:
        return [-3.0] + [0.0] * features.shape[1]
    penalty = np.diag([1e-3] + [ridge] * features.shape[1])
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        step = np.linalg.solve((x * (p * (1 - p))[:, None]).T @ x + penalty, x.T @ (labels - p) - penalty @ w)
        w += step * min(1.0, 3.0 / max(1e-9, np.abs(step).max()))
        if np.abs(step).max() < 1e-7:
            break
    return w.tolist()


def choose_terms(counts: dict[str, tuple[int, int]], n_toxic: int, n_clean: int) -> Lexicon:
    """Terms from counts of (toxic, clean) texts by feature: ``word$`` for words, bare for word beginnings.

    A feature qualifies with enough toxic texts and at least MIN_LIFT times the clean rate.  From
    the shortest qualifying beginning one goes on to the longest that keeps 95 % of its texts, so
    a term is a whole word where one word explains the beginning, and a stem otherwise.
    """
    support = max(5, n_toxic // 100)
    share = (n_toxic + 1) / (n_toxic + n_clean + 2)

    def evidence(f: str) -> float:
        """Likelihood ratio statistic of the feature's texts against the base rate."""
        t, c = counts[f]
        gain = lambda k, p: k * np.log(k / (t + c) / p) if k else 0.0
        return 2 * (gain(t, share) + gain(c, 1 - share))

    lift = lambda f: ((counts[f][0] + 0.5) / (n_toxic + 1)) / ((counts[f][1] + 0.5) / (n_clean + 1))
    good = {f for f, (t, _) in counts.items() if t >= support and lift(f) >= MIN_LIFT and evidence(f) >= MIN_EVIDENCE}
    words, stems = set(), set()
    for f in sorted(good, key=lambda f: (len(f), f)):
        bare = f.rstrip("$")
        if bare[:-1] in good and len(bare) > STEM[0] and not f.endswith("$"):
            continue  # a shorter beginning leads here
        if f.endswith("$") and any(bare[:n] in good for n in STEM if n <= len(bare)):
            continue
        if f.endswith("$"):
            words.add(bare)
            continue
        branch = [f]
        while branch:
            g = branch.pop()
            longer = [h for h in good if h.startswith(g) and h != g and counts[h][0] >= 0.95 * counts[f][0]]
            whole = [h for h in longer if h.endswith("$")]
            if whole:
                words.add(max(whole, key=lambda h: (counts[h][0], h)).rstrip("$"))
            elif longer:
                branch.append(max(longer, key=lambda h: (len(h), h)))
            else:
                stems.add(g)
    odds = lambda f: float(np.clip(np.log((counts[f][0] + 0.5) / (counts[f][1] + 0.5)), 0.0, STRONGEST))
    return Lexicon(sorted(words), sorted(stems), {**{s: odds(s) for s in stems}, **{w: odds(w + "$") for w in words}})


def weigh_misspellings(lexicon: Lexicon, rows: list[tuple[str, str, int, int]], counts: dict[str, tuple[int, int]]) -> Lexicon:
    """The lexicon with a strength for each term's misspellings, from rows of (word, term, toxic, clean texts).

    Words that stand in at least ORDINARY clean texts and more often there than in toxic ones are
    ordinary words, no misspellings.  The texts of the others join BELIEF texts of the term's own
    record, so a term without any misspelling in the sample has nearly its own strength, and one
    whose neighbourhood is everyday language has none.
    """
    ordinary = frozenset(w for w, _, t, c in rows if c >= ORDINARY and c > t)
    seen: dict[str, list[int]] = {}
    for word, term, t, c in rows:
        if word not in ordinary:
            own = seen.setdefault(term, [0, 0])
            own[0], own[1] = own[0] + t, own[1] + c
    spelled = {}
    for term in [*lexicon.words, *lexicon.stems]:
        t, c = counts[term + "$" if term in lexicon.known else term]
        share = (t + 0.5) / (t + c + 1)
        tf, cf = seen.get(term, (0, 0))
        odds = float(np.log((tf + BELIEF * share) / (cf + BELIEF * (1 - share))))
        spelled[term] = odds if odds >= WEAKEST else 0.0
    return Lexicon(lexicon.words, lexicon.stems, lexicon.strength, spelled, ordinary)


def training_rows(documents: DataFrame, labels: DataFrame, most: int = MAX_LABELLED) -> DataFrame:
    """(text, toxic): at most ``most`` labelled texts outside the held-out fold, in hash order of their ids."""
    usable = labels.where(F.col("toxic").isNotNull() & (F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 != 0))
    picked = usable.groupBy("doc_id").agg(F.max("toxic").alias("toxic")).orderBy(F.xxhash64("doc_id"), "doc_id").limit(most)
    rows = documents.select("doc_id", text_or_empty().alias("text")).join(F.broadcast(picked), "doc_id")
    return rows.select("text", F.col("toxic").cast("int").alias("toxic"))


def each_once(rows: DataFrame) -> DataFrame:
    """``rows`` (text, toxic) with about one text of each group of copies and near copies, by the least of two hashes of its word n-grams.

    The words of one toxic text that has many copies would else look like terms.  Of a group the
    least by hash, label and text stays, so the choice does not depend on the order of rows.
    """

    def sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            least = [(int(s.min()), int((s * np.uint64(0x9E3779B97F4A7C15)).min())) if len(s) else (0, 0) for s in shingle_sets(batch.column(0))]
            signs = [pa.array(np.array([x[k] for x in least], np.uint64).view(np.int64)) for k in (0, 1)]
            yield pa.RecordBatch.from_arrays([*batch.columns, *signs], ["text", "toxic", "one", "two"])

    out = rows.mapInArrow(sign, "text string, toxic int, one long, two long")
    for name in ("one", "two"):
        first = F.struct(F.xxhash64("text").alias("h"), "toxic", "text", "two")
        out = out.groupBy(name).agg(F.min(first).alias("kept")).select("kept.text", "kept.toxic", "kept.two")
    return out.select("text", "toxic")


def fit(documents: DataFrame, labels: DataFrame, most: int = MAX_LABELLED) -> ToxicityModel:
    """Lexicon and weights from a bounded sample of labelled rows (parameter ``most``).

    Groups of copies count about once.  1. Words and word beginnings by toxic and clean texts give the terms.  2. All words of the sample are
    matched against all terms with the automaton; what they match in toxic and in clean texts gives
    each term's strength when misspelled.  3. The features of the sample's texts give the weights.
    What comes to the driver are the features of enough toxic texts, the words that look like
    misspelled terms and one row of numbers for each labelled text.
    """
    with scratch():
        return _fitted(documents, labels, most)


def _fitted(documents: DataFrame, labels: DataFrame, most: int) -> ToxicityModel:
    sample = written(each_once(training_rows(documents, labels, most)), "toxicity-sample")

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found: dict[str, list[int]] = {}
        for batch in batches:
            for text, toxic in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                words = set(_word.findall(text.lower()))
                for f in {w[:n] for w in words for n in STEM if len(w) >= n} | {w + "$" for w in words if len(w) >= STEM[0]}:
                    found.setdefault(f, [0, 0])[0 if toxic else 1] += 1
        yield pa.RecordBatch.from_arrays([pa.array(list(found), pa.string()), pa.array([x[0] for x in found.values()], pa.int64()), pa.array([x[1] for x in found.values()], pa.int64())], ["feature", "toxic", "clean"])

    n_toxic, n_clean = sample.agg(F.coalesce(F.sum(F.when(F.col("toxic") == 1, 1).otherwise(0)), F.lit(0)), F.coalesce(F.sum(F.when(F.col("toxic") == 1, 0).otherwise(1)), F.lit(0))).first()
    labelled = sample.select("text", (F.col("toxic") == 1).cast("int").alias("toxic"))
    counts = labelled.mapInArrow(count, "feature string, toxic long, clean long").groupBy("feature").agg(F.sum("toxic").alias("toxic"), F.sum("clean").alias("clean"))
    counts = written(counts, "toxicity-counts")
    kept = counts.where((F.col("toxic") >= max(5, n_toxic // 100)) & (F.col("toxic") * max(1, n_clean) >= F.col("clean") * n_toxic))
    table = {r.feature: (r.toxic, r.clean) for r in kept.collect()}
    plain = choose_terms(table, n_toxic, n_clean)

    def misspelled(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            words = pc.utf8_slice_codeunits(batch.column(0), 0, -1)
            batch = batch.filter(pc.or_(pc.match_substring_regex(words, plain.fragments), pc.match_substring_regex(words, ODD)))
            rows = [(w[:-1], t, c) for w, t, c in zip(*(batch.column(k).to_pylist() for k in range(3)))]
            rows = [(w, term, t, c) for w, t, c in rows if plain.exact(w) is None and (term := plain.fuzzy(w)) is not None]
            columns = list(zip(*rows)) or [()] * 4
            kinds = (pa.string(), pa.string(), pa.int64(), pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds)], ["word", "term", "toxic", "clean"])

    lexicon = plain
    if plain.words or plain.stems:
        near = counts.where(F.endswith("feature", F.lit("$"))).repartition("feature").mapInArrow(misspelled, "word string, term string, toxic long, clean long")
        lexicon = weigh_misspellings(plain, [tuple(r) for r in near.collect()], table)

    def features(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = text_features(batch.column(0), lexicon)
            yield pa.RecordBatch.from_arrays([batch.column(1), *[pa.array(x[:, k]) for k in range(FEATURES)]], ["toxic", *[f"x{k}" for k in range(FEATURES)]])

    schema = "toxic int, " + ", ".join(f"x{k} double" for k in range(FEATURES))
    rows = labelled.mapInArrow(features, schema).collect()
    x = np.array([[r[f"x{k}"] for k in range(FEATURES)] for r in rows]).reshape(len(rows), FEATURES)
    y = np.array([r.toxic for r in rows], dtype=float)
    order = np.lexsort((*x.T, y)) if len(y) else []
    return ToxicityModel(lexicon, fit_weights(x[order], y[order]) if len(y) else fit_weights(x, y))


def score_texts(df: DataFrame, model: ToxicityModel, text: str = "text") -> DataFrame:
    """``df`` with ``toxicity`` (0 to 1) added.  Null and empty texts have the score of a text
    without hits.  Only the text is read for the score.  An input column named toxicity is replaced."""
    kept = [c for c in df.columns if c != "toxicity"]

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            scores = model.score(text_features(batch.column(batch.schema.get_field_index("__text")), model.lexicon))
            columns = [batch.column(k) for k, name in enumerate(batch.schema.names) if name != "__text"]
            yield pa.RecordBatch.from_arrays([*columns, pa.array(scores)], [*kept, "toxicity"])

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema.fields if f.name != "toxicity") + ", toxicity double"
    return df.select(*[F.col(f"`{c}`") for c in kept], text_or_empty(text).alias("__text")).mapInArrow(score, schema)


def op9_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    documents = read_table(spark, sf_dir, "documents")
    model = fit(documents, read_table(spark, sf_dir, "labels"))
    scored = score_texts(documents.select("doc_id", "text"), model)
    held_out = F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 == 0
    return scored.select("doc_id", held_out.alias("held_out"), F.col("toxicity").alias("score"), (F.col("toxicity") >= 0.5).cast("int").alias("predicted"))
