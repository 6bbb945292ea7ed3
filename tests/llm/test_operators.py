"""Operators against libraries, brute force and hand cases, with nulls, empty texts, ties and repeats."""

import hashlib
import random
import zlib

import numpy as np
import public_tokenizers
import pyarrow as pa
import pytest
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from objann.llm import bpe, bpe_codec, graph, html_extract, media_chunks, near_join, packing, pii, token_counts, topk_search, toxicity, url_filter

TEXTS = [None, "", " ", "a b  c\n\nd", "it's we'll <|endoftext|> x", "é" * 40 + "  日本 \x1c\x85 y", "word " * 3000, "a" * 4000, "word " * 3000]


@pytest.fixture(scope="module")
def library():
    return Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame([(k, t, "other") for k, t in enumerate(TEXTS)], "doc_id long, text string, ids string")


def ids_of(library, text):
    return library.encode(text or "", add_special_tokens=False).ids


def noise(n, seed=3):
    rng = random.Random(seed)
    parts = [" ", "  ", "\n", "\t", "a", "é", "the", " th", "'s", "'re", "'", "!", "<|endoftext|>", "<|endof", "12", "日本", " ", "\x1c", "\x85", "😀", "\r\n"]
    return ["".join(rng.choice(parts) for _ in range(rng.randint(0, 14))) for _ in range(n)]


def test_encoders_match_the_library(library):
    texts = noise(3000)
    want = [ids_of(library, t) for t in texts]
    vocab = bpe.vocabulary("byte_bpe_50k.json")
    for coder in (bpe.FastEncoder(vocab), bpe.IndexedEncoder(vocab)):
        assert [r.tolist() for r in coder.rows(pa.array(texts))] == want
    counter = token_counts.PrefixCounter(vocab)
    assert counter.column_counts(pa.array(texts)).tolist() == [len(w) for w in want]
    for t in texts[:200]:
        assert counter.prefixes(t).tolist() == [len(ids_of(library, t[:i])) for i in range(len(t) + 1)]


def test_codec_counts_and_packing(docs, library):
    rows = {r.doc_id: r for r in bpe_codec.round_trip(docs).collect()}
    counts = {r.doc_id: r for r in token_counts.token_counts(docs).collect()}
    for k, t in enumerate(TEXTS):
        ids = ids_of(library, t)
        assert rows[k].ids_sha256 == hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest()
        assert rows[k].decoded_sha256 == hashlib.sha256((t or "").encode()).hexdigest()
        assert counts[k][1:] == (len((t or "").encode()), len(ids), len(ids) > 512)
    pieces = sorted(packing.pack(docs, window=64).collect(), key=lambda r: (r.sequence_id, r.offset))
    at = 0
    for p in pieces:
        assert p.sequence_id * 64 + p.offset == at
        ids = ids_of(library, TEXTS[p.doc_id]) + [1]
        assert p.doc_tokens == len(ids) and p.ids_crc32 == zlib.crc32(np.array(ids[p.start : p.start + p.length], "<u4").tobytes())
        at += p.length
    assert at == sum(len(ids_of(library, t)) + 1 for t in TEXTS)
    assert packing.pack(docs.where("false")).count() == 0


def test_near_join_against_brute_force(spark):
    rng = random.Random(1)
    base = [[f"w{rng.randrange(4000)}" for _ in range(60)] for _ in range(12)]
    texts = [None, "", "!!!", "???"]
    for words in base:
        for changes in (0, 0, 1, 2, 4):
            own = list(words)
            for _ in range(changes):
                own[rng.randrange(60)] = f"x{rng.randrange(9999)}"
            texts.append(" ".join(own))
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    sets = [set(x.tolist()) for x in near_join.shingle_sets(pa.array(texts, pa.string()))]
    label = list(range(len(texts)))
    for a in range(len(texts)):
        for b in range(a):
            both = len(sets[a] & sets[b])
            if (sets[a] and both >= 0.8 * len(sets[a] | sets[b])) or (texts[a] or "") == (texts[b] or ""):
                low, high = sorted((label[a], label[b]))
                label = [low if x == high else x for x in label]
    got = {r.doc_id: r.class_id for r in near_join.similarity_classes(df).collect()}
    assert got == dict(enumerate(label))
    assert {r.doc_id for r in near_join.keep_one(df).collect()} == set(label)
    assert near_join.similarity_classes(df.where("false")).count() == 0
    bands, rows = near_join.choose_bands()
    assert 1 - (1 - 0.8**rows) ** bands >= near_join.TARGET_RECALL


def test_prefix_pairs_lose_no_link(spark):
    rng = np.random.default_rng(5)
    base = rng.integers(0, 1 << 62, 90)
    sets = []
    for _ in range(150):
        kept = base[rng.random(90) > rng.choice([0.02, 0.08, 0.2, 0.4])]
        own = rng.integers(0, 1 << 62, rng.integers(0, 25))
        sets.append(np.unique(np.concatenate([kept, own, rng.choice(base, 1)])))
    part = [int(x) for x in rng.integers(0, 60, len(sets))]
    nodes = spark.createDataFrame([(b, k, len(x), part[k]) for k, x in enumerate(sets) for b in range(2)], "band long, node long, size int, component long")
    stored = spark.createDataFrame([(k, bytearray(x.tobytes())) for k, x in enumerate(sets)], "node long, grams binary")
    found = {(r.a, r.b) for r in near_join._prefix_pairs(nodes, stored, 0.8).collect()}
    links, made = set(), 0
    for a in range(len(sets)):
        for b in range(a + 1, len(sets)):
            both = len(np.intersect1d(sets[a], sets[b]))
            made += part[a] != part[b]
            if part[a] != part[b] and both >= 0.8 * (len(sets[a]) + len(sets[b]) - both):
                links.add((a, b))
    assert links and links <= found and len(found) < made
    assert all(part[a] != part[b] for a, b in found)
    assert near_join._prefix_pairs(nodes.where("false"), stored, 0.8).count() == 0


def test_near_join_classes_do_not_depend_on_the_last_step(spark, monkeypatch):
    rng = random.Random(9)
    words = [f"w{k}" for k in range(4000)]
    base = [rng.choice(words) for _ in range(120)]
    texts = []
    for _ in range(80):
        edited = list(base)
        for _ in range(rng.choice([0, 1, 2, 3, 8])):
            edited[rng.randrange(120)] = rng.choice(words)
        texts.append(" ".join(edited))
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    plain = {r.doc_id: r.class_id for r in near_join.similarity_classes(df).collect()}
    monkeypatch.setattr(near_join, "MAX_STAR_ROUNDS", 0)
    monkeypatch.setattr(near_join, "_few_pairs", lambda current: False)
    assert {r.doc_id: r.class_id for r in near_join.similarity_classes(df).collect()} == plain


@pytest.mark.parametrize("few", [True, False])
def test_links_are_counted_as_by_brute_force(spark, monkeypatch, few):
    rng = random.Random(11)
    texts = []
    for size, edits in ((40, [0, 1, 2]), (25, [1, 3, 5]), (3, [1]), (2, [1]), (1, [0])):
        base = [f"w{rng.randrange(9000)}" for _ in range(100)]
        for _ in range(size):
            own = list(base)
            for _ in range(rng.choice(edits)):
                own[rng.randrange(100)] = f"x{rng.randrange(9999)}"
            texts.append(" ".join(own))
    distinct = {x.tobytes(): x for x in near_join.shingle_sets(pa.array(texts))}
    want = []
    for x in near_join.shingle_sets(pa.array(texts)):
        both = [(len(np.intersect1d(x, y)), len(np.union1d(x, y))) for name, y in distinct.items() if name != x.tobytes()]
        want.append(sum(b >= 0.8 * u for b, u in both))
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    monkeypatch.setattr(near_join, "_few_pairs", lambda current: few)
    assert {r.doc_id: r.n_links for r in near_join.similarity_classes(df).collect()} == dict(enumerate(want))
    if few:
        monkeypatch.setattr(near_join, "BLOCK_SETS", 7)
        assert {r.doc_id: r.n_links for r in near_join.similarity_classes(df).collect()} == dict(enumerate(want))


def test_common_counts_of_rare_and_frequent_grams():
    rng = np.random.default_rng(8)
    often = rng.integers(0, 1 << 62, 30)
    sets = [np.unique(np.concatenate([often[rng.random(30) < 0.6], rng.integers(0, 3000, 40)])) for _ in range(260)]
    left, right = sets[:150], sets[150:]
    want = [[len(np.intersect1d(x, y)) for y in right] for x in left]
    assert near_join.common_counts(left, right).tolist() == want


def test_components_both_ways(spark):
    edges = spark.createDataFrame([(k, k + 1) for k in range(30) if k % 7] + [(100, 50), (5, 5)], "src long, dst long")
    small = {tuple(r) for r in graph.connected_components(edges).collect()}
    assert small == {tuple(r) for r in graph.connected_components(edges, one_task_edges=0).collect()}
    assert (100, 50) in small and (7, 1) in small


def test_personal_data(spark):
    texts = [None, "", "x a.b@c-d.org y", "300.1.1.1 1.2.3.4", "card 4111 1111 1111 1111", "+1 (415) 555-2671 1 2 3", "1 " * 5000, "a" * 50000]
    rows = pii.personal_data(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()
    found = {r.doc_id: r for r in rows}
    assert [tuple(found[k][1:5]) for k in range(8)] == [(0,) * 4, (0,) * 4, (1, 0, 0, 0), (0, 1, 0, 0), (0, 0, 1, 0), (0, 0, 0, 1), (0,) * 4, (0,) * 4]
    assert found[2].spans == "email:2:13" and found[3].spans == "ip:10:17"
    assert found[2].base_sha256 == hashlib.sha256(b"email:2:13").hexdigest()
    clean = {r.doc_id: r.text for r in pii.sanitise(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()}
    assert clean[2] == "x [EMAIL] y" and clean[0] is None


def test_revealing_terms(spark):
    texts = [f"note {k} secretword {k} me@x.org lots {k} of filler text number {k}" for k in range(8)] + [f"plain note filler text of number {k} and lots more" for k in range(200)]
    rows = pii.personal_data(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()
    marked = {r.doc_id: r.spans for r in rows if "term:" in r.spans}
    assert marked == {k: "term:7:17,email:20:28" for k in range(8)}


def test_topk_against_brute_force(spark):
    rng = np.random.default_rng(2)
    vectors = [rng.normal(size=16).astype(np.float32).tolist() for _ in range(300)] + [[0.5] * 16] * 30 + [None, [None] * 16, [float("nan")] * 16]
    df = spark.createDataFrame(list(enumerate(vectors)), "vec_id long, embedding array<float>")
    ints = {k: np.floor(1024 * np.array(v, dtype=np.float32).astype(float)).astype(np.int64) for k, v in enumerate(vectors[:330])}
    got = {}
    for r in topk_search.top_k(df, df.where("vec_id % 50 = 0")).collect():
        got.setdefault(r.query_id, []).append((r.rank, r.vec_id, r.score))
    for q in range(0, 330, 50):
        best = sorted((-int(ints[q] @ ints[k]), k) for k in ints if k != q)[:10]
        assert sorted(got[q]) == [(n + 1, k, -s) for n, (s, k) in enumerate(best)]


def test_media_round_trip(docs):
    rows = {r.doc_id: r for r in media_chunks.store_and_read(docs).collect()}
    for k, t in enumerate(TEXTS):
        data = media_chunks.payload_of((t or "").encode())
        assert rows[k].payload_sha256 == hashlib.sha256(data).hexdigest() and rows[k].tail_crc32 == zlib.crc32(data[-16:])
        assert rows[k].n_bytes == len((t or "").encode()) and rows[k].payload_bytes % 192 == 0
    assert rows[6][2:] == rows[8][2:]


def test_url_rules_and_aliases(spark):
    link = '<link rel="canonical" href="{}">'
    pages = [(1, "http://a.example.com/en/1", None), (2, "http://x.info/1", link.format("http://a.example.com/en/1")), (3, "no url", ""), (4, None, None), (5, "http://EXAMPLE.com/en/7?q", ""), (6, "http://y.info/", link.format("http://example.com/en/7")), (7, "http://notexample.net/de/8", "")]
    rows = {r.page_id: r for r in url_filter.judge(spark.createDataFrame(pages, "page_id long, url string, html string")).collect()}
    assert [rows[k].verdict for k in range(1, 8)] == ["block", "block", "allow", "allow", "allow", "allow", "allow"]
    assert rows[5].rule == "example.com/en/7" and rows[7].rule == "net/de/" and rows[3].host == ""


def test_toxicity_parts():
    trie = toxicity.Trie(["idiot", "disgusting"], ["lowei"])
    assert trie.within("idiott") == ("idiot", 1)
    assert trie.within("disgustng") == ("disgusting", 1)
    assert trie.within("ideal") is None
    assert trie.within("lowreisch") == ("lowei", 1)
    assert toxicity.context_score(["he", 'said', '"you', "idiot", 'fool"'], 3) == 1.0
    assert toxicity.context_score(["you", "idiot"], 1) == 0.0
    lexicon = toxicity.Lexicon(["idiot"], ["lowei"])
    x = toxicity.text_features(pa.array([None, "", "You IDIOT!", "an id1ot here", "loweisch", "clean words"]), lexicon)
    assert (x[:, 0] > 0).tolist() == [False, False, True, True, True, False]


def test_html_consensus(spark):
    page = '<html><head><title>t</title></head><body><nav><a href="/">menu</a></nav><article><h1>Head {0}</h1><p>First &amp; long paragraph of page {0}<br>goes on<p>Second one</article><div class="comments"><p>reader {0}</p></div><footer>foot</footer></body></html>'
    pages = [(k, "http://h.org/", page.format(k)) for k in range(3)] + [(9, None, None), (10, "http://h.org/", "")]
    rows = {r.page_id: r for r in html_extract.extract(spark.createDataFrame(pages, "page_id long, url string, html string")).collect()}
    assert rows[1].text == "Head 1\n\nFirst & long paragraph of page 1 goes on\n\nSecond one" and rows[1].n_chars == len(rows[1].text)
    assert rows[9].text == "" and rows[10].text == ""
    assert html_extract.extract(spark.createDataFrame(pages, "page_id long, url string, html string").where(F.lit(False))).count() == 0


def test_html_articles_of_sections_lists_and_tables_are_whole(spark):
    line = "A sentence of the article that is long enough to count. "
    inner = [
        f"<section class='one'><p>First {line * 18}</p></section><div class='share'>Share this</div><section class='two'><p>Second {line * 12}</p></section>",
        f"<h1>Title</h1><p>First {line * 2}</p><ul><li>Second {line * 9}</li><li>Third {line * 9}</li></ul>",
        f"<p>First {line * 2}</p><table><tr><td>Second {line * 9}</td><td>Third {line * 9}</td></tr></table>",
        f"<p>First {line * 3}</p><blockquote>Second {line * 9}</blockquote><div id='more'><p>Third {line * 4}</p></div>",
    ]
    page = "<html><body><nav><a href='/'>Home</a> <a href='/x'>Section list of the site</a></nav><article>{}</article><footer>Imprint and more words of the footer</footer></body></html>"
    rows = [(h * 10 + k, f"http://h{h}.org/{k}", page.format(body)) for h, bodies in enumerate([*([x] * 3 for x in inner), inner]) for k, body in enumerate(bodies)]
    for r in html_extract.extract(spark.createDataFrame(rows, "page_id long, url string, html string")).collect():
        body = next(html for key, _, html in rows if key == r.page_id)
        assert [w in r.text for w in ("Title", "First", "Second", "Third")] == [w in body for w in ("Title", "First", "Second", "Third")]
        assert not any(w in r.text for w in ("Share", "Home", "Imprint"))
