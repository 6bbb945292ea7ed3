"""Edge cases and brute-force versions of the operators: nulls, empties, repeats, ties, clashing names, both sides of each switch."""

import hashlib
import random
from types import SimpleNamespace

import numpy as np
import pyarrow as pa
import pytest
import regex
from pyspark.sql import functions as F

from objann.llm import bpe_codec, graph, html_extract, media_chunks, near_join, packing, pii, shared, token_counts, topk_search, toxicity, url_filter

DOCS = "doc_id long, text string"


def rows_by(df, key="doc_id"):
    return {r[key]: r for r in df.collect()}


# shared folder and components


def test_no_folder_of_one_machine_on_a_cluster(monkeypatch):
    monkeypatch.setattr(shared, "_own_folder", None)
    none = SimpleNamespace(isDefined=lambda: False)
    session = lambda master, named: SimpleNamespace(conf=SimpleNamespace(get=lambda k, d: named), sparkContext=SimpleNamespace(master=master, _jsc=SimpleNamespace(sc=lambda: SimpleNamespace(getCheckpointDir=lambda: none)), setCheckpointDir=lambda p: None))
    with pytest.raises(RuntimeError):
        shared.shared_folder(session("spark://host:7077", None))
    with pytest.raises(RuntimeError):
        shared.shared_folder(session("local-cluster[3,2,1000]", None))
    assert shared.shared_folder(session("yarn", "hdfs://x/y/")) == "hdfs://x/y"


def test_scratch_tables_go_and_lasting_ones_stay(spark):
    with shared.scratch():
        gone = shared.WrittenTable(spark.range(3), "gone")
        kept = shared.written(spark.range(3), "kept", lasting=True)
    assert kept.count() == 3
    with pytest.raises(Exception):
        spark.read.parquet(gone.path).count()


def test_components_that_are_not_stable_are_an_error(spark):
    edges = spark.createDataFrame([(k, k + 1) for k in range(200)], "src long, dst long")
    with pytest.raises(RuntimeError):
        graph.connected_components(edges, max_rounds=1, one_task_edges=0)


# near join


def test_near_join_nulls_repeats_names_and_long_texts(spark):
    long = " ".join(f"w{k}" for k in range(60_000))
    rows = [(None, "a b c d e f g", 1), (3, "a b c d e f g", 2), (3, "a b c d e f g", 2), (4, None, 3), (5, "", 4), (6, long, 5), (7, long + " end", 6), (None, "only here it stands at all", 7)]
    df = spark.createDataFrame(rows, "doc_id long, text string, class_id int")
    got = near_join.similarity_classes(df).collect()
    assert len(got) == len(rows) and got[0].__fields__ == ["doc_id", "class_id", "n_links", "n_copies"]
    by = {}
    for r in got:
        by.setdefault(r.doc_id, set()).add((r.class_id, r.n_links, r.n_copies))
    assert by[3] == {(3, 0, 3)} and by[4] == by[5] == {(4, 0, 2)} and by[6] == by[7] == {(6, 1, 1)}
    assert by[None] == {(3, 0, 3), (None, 0, 1)}
    kept = near_join.keep_one(df)
    assert sorted((r.doc_id, r.class_id) for r in kept.collect() if r.doc_id) == [(3, 2), (4, 3), (6, 5)]
    assert kept.count() == 4


# tokens


def test_token_operators_on_empty_tables_and_repeats(spark):
    df = spark.createDataFrame([(1, "a b", 5), (1, "a b", 5), (None, None, 6)], "doc_id long, text string, n_tokens int")
    for make in (bpe_codec.round_trip, token_counts.token_counts):
        assert make(df.where("false")).count() == 0
        got = [tuple(r) for r in make(df).collect()]
        assert len(got) == 3 and len(set(got)) == 2 and make(df).columns.count("n_tokens") == 1
    pieces = packing.pack(df).collect()
    assert len(pieces) == 3 and [p.doc_tokens for p in sorted(pieces, key=lambda p: p.offset)][-1] in (1, 3)


# personal data

BASE = [r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", r"[0-9]([ -]?[0-9])+", r"\+[0-9][ ().0-9-]+[0-9]"]


def luhn(digits):
    return sum(sum(divmod(2 * int(d), 10)) if k % 2 else int(d) for k, d in enumerate(reversed(digits))) % 10 == 0


def base_spans(text):
    out = []
    for kind, pattern in enumerate(BASE):
        for m in regex.finditer(pattern, text):
            digits = regex.sub("[^0-9]", "", m.group())
            fine = [True, all(int(p) <= 255 for p in m.group().split(".")) if kind == 1 else True, 12 <= len(digits) <= 19 and luhn(digits), 9 <= len(digits) <= 15][kind]
            if fine:
                out.append((m.start(), kind, m.end(), m.group()))
    return sorted(out)


def revealing(texts):
    """The disclosure rule by plain loops: (text, start, end) of all terms that are marked."""
    texts = [t or "" for t in texts]
    word = regex.compile(pii.WORD)
    n, near = {}, []
    for t in texts:
        for m in word.finditer(t.lower()):
            n[m.group()] = n.get(m.group(), 0) + 1
    for t in texts:
        spans = base_spans(t)
        for s, kind, e, value in spans:
            entity = (kind, regex.sub("[^0-9]", "", value) if kind >= 2 else value.lower())
            left, right = t[max(0, s - pii.WINDOW) : s], t[e : e + pii.WINDOW]
            for side, at in ((left, s - len(left)), (right, e)):
                for m in word.finditer(side):
                    a, b = at + m.start(), at + m.end()
                    cut = (side is left and a == s - pii.WINDOW) or (side is right and b == e + pii.WINDOW)
                    if not cut and not any(x < b and y > a for x, _, y, _ in spans):
                        near.append((t, entity, (left, right), m.group().lower(), a, b))
    total, weight, c, contexts = sum(n.values()), {}, {}, {}
    for _, entity, context, term, _, _ in near:
        weight[entity] = weight.get(entity, 0) + 1
        c[entity, term] = c.get((entity, term), 0) + 1
        contexts.setdefault((entity, term), set()).add(context)
    marked = set()
    for (entity, term), k in c.items():
        if term not in n:
            continue  # the end of a word that the window cuts
        m = len(contexts[entity, term])
        chance = min(1.0, k / n[term]) * m / (m + 1)
        if weight[entity] < total and np.log2(chance) >= -pii.RESIDUE and np.log2(chance * total / weight[entity]) / np.log2(total / weight[entity]) >= pii.DISCLOSURE:
            marked.add((entity, term))
    return {(t, a, b) for t, entity, _, term, a, b in near if (entity, term) in marked}


def pii_texts():
    rng = random.Random(4)
    words = [f"{a}{b}" for a in ("ka", "lo", "mi", "ne", "tu") for b in ("ra", "se", "vo", "xi")] + ["O'Brien", "Jean-Luc", "été"]
    bits = ["me@x.org", "ada.l@mail-1.example.com", "10.20.30.40", "300.1.1.1", "4111 1111 1111 1111", "+1 (415) 555-2671", "a@b.c-4111 1111 1111 1111", "1.2.3.4 111 1111 1111 1111", "(kowalski)", "\"Novak\"", "12", "."]
    texts = [" ".join(rng.choice(bits) if rng.random() < 0.08 else rng.choice(words) for _ in range(rng.randint(0, 60))) for _ in range(150)]
    texts += ["write to Zebrowski at zeb@y.org for ka lo", "ka lo ka lo mi ra", "zeb@y.org knows Zebrowski", None, "", "x" * 30_000, "1 " * 5_000]
    return texts


def test_personal_data_against_brute_force(spark):
    texts = pii_texts()
    df = spark.createDataFrame([(k, t, "x") for k, t in enumerate(texts)], "doc_id long, text string, spans string")
    got = rows_by(pii.personal_data(df))
    marked = revealing(texts)
    assert any(t[a:b] == "Zebrowski" for t, a, b in marked)
    for k, t in enumerate(texts):
        base = base_spans(t or "")
        want = sorted([(s, kind, e) for s, kind, e, _ in base] + [(a, 4, b) for u, a, b in marked if u == t])
        assert got[k].spans == ",".join(f"{pii.KINDS[kind]}:{s}:{e}" for s, kind, e in want), t
        assert [got[k][f"n_{kind}"] for kind in pii.KINDS[:4]] == [sum(x[1] == j for x in base) for j in range(4)]


def test_cleaned_text_keeps_no_part_of_a_span(spark):
    texts = pii_texts() + ["ip 1.2.3.4 111 1111 1111 1111 end", "a@b.c-4111 1111 1111 1111 x"]
    df = spark.createDataFrame(list(enumerate(texts)), DOCS)
    spans, clean = rows_by(pii.personal_data(df)), rows_by(pii.sanitise(df))
    for k, t in enumerate(texts):
        if t is None:
            assert clean[k].text is None
            continue
        out, at = "", 0
        for kind, s, e in (x.split(":") for x in spans[k].spans.split(",") if x):
            if int(s) >= at:
                out += t[at : int(s)] + f"[{kind.upper()}]"
            at = max(at, int(e))
        assert clean[k].text == out + t[at:]
    assert clean[len(texts) - 1].text.count("1111") == 0 and "1111" not in clean[len(texts) - 2].text


def test_personal_data_empty_table_repeats_and_both_joins(spark, monkeypatch):
    df = spark.createDataFrame([(1, "call Novak me@x.org", 1)] * 3 + [(2, "me@x.org Novak again", 2)] + [(k, "other words stand here too", 3) for k in range(3, 30)], "doc_id long, text string, term int")
    assert pii.personal_data(df.where("false")).count() == 0 and pii.sanitise(df.where("false")).count() == 0
    got = [tuple(r) for r in pii.personal_data(df).collect() if r.doc_id == 1]
    assert len(got) == 3 and len(set(got)) == 1 and "term:5:10" in got[0][6]
    plain = sorted(map(tuple, pii.sanitise(df).collect()))
    monkeypatch.setattr(pii, "MAX_BROADCAST_ROWS", 0)
    assert sorted(map(tuple, pii.sanitise(df).collect())) == plain and plain[0] == (1, "[TERM] [TERM] [EMAIL]", 1)


# search


def test_topk_small_tables_ties_and_batches(spark):
    rng = np.random.default_rng(3)
    rows = [(k, rng.normal(size=8).astype(np.float32).tolist()) for k in range(120)] + [(5, [1.0] * 8), (5, [1.0] * 8), (200, [float("inf")] * 8), (None, [1.0] * 8), (201, []), (202, [0.5] * 4), (203, [0.25] * 4)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>").withColumn("rank", F.lit("x"))
    ints = [(k, np.floor(1024 * np.array(v, dtype=np.float32).astype(float)).astype(np.int64)) for k, v in rows if k is not None and len(v) and np.isfinite(v).all()]
    asked = df.where("vec_id % 5 = 0 OR vec_id > 200")
    want = {}
    for key, q in {(k, tuple(v)) for k, v in ints if k % 5 == 0 or k > 200}:
        best = sorted((-int(np.array(q) @ x), k) for k, x in ints if k != key and len(x) == len(q))[:10]
        want.setdefault(key, []).append([(n + 1, k, -s) for n, (s, k) in enumerate(best)])
    for size in (1, 32_000_000):
        got = {}
        for r in topk_search.top_k(df, asked, batch_bytes=size).collect():
            got.setdefault(r.query_id, []).append((r.rank, r.vec_id, r.score))
        assert {k: sorted(v) for k, v in got.items()} == {k: sorted(sum(v, [])) for k, v in want.items()}
    assert topk_search.top_k(df.where("false"), asked).count() == 0 and topk_search.top_k(df, asked.where("false")).count() == 0


def test_topk_works_out_fewer_scores_than_brute_force():
    rng = np.random.default_rng(1)
    x = rng.normal(size=(12_000, 64))
    whole = np.floor(1024 * x / np.linalg.norm(x, axis=1)[:, None]).astype(np.int64)
    ids, n = np.arange(len(whole)), len(whole) // topk_search.FIRST_SHARE
    q = topk_search.Banded(ids[::100], whole[::100])
    first = topk_search.whole_scores(q, topk_search.Banded(ids[:n], whole[:n]), 10)
    cutoff = np.array([np.sort(first[2][first[0] == j])[-10] for j in range(len(q.ids))])
    rest = topk_search.scores_over(q, topk_search.Banded(ids[n:], whole[n:]), 10, cutoff)
    assert first[3] + rest[3] < 0.9 * len(q.ids) * len(whole) * topk_search.BANDS
    places, found, scores = (np.concatenate(c) for c in zip(first[:3], rest[:3]))
    best = topk_search._best_of(places, found, scores, 10)
    for j in range(0, len(q.ids), 17):
        want = sorted((-int(whole[100 * j] @ whole[k]), k) for k in ids if k != 100 * j)[:10]
        assert [(-s, k) for k, s in zip(found[best][places[best] == j], scores[best][places[best] == j])] == want


# media


def media_docs(spark):
    rng = random.Random(2)
    part = lambda n: " ".join(str(rng.random()) for _ in range(n))
    common = part(900)
    texts = [common + part(300) for _ in range(6)] + [part(400) for _ in range(40)] + [common, common, "word " * 9000, None, ""]
    return spark.createDataFrame([(k, t, b"x") for k, t in enumerate(texts)], "doc_id long, text string, data binary"), texts


def test_media_come_from_the_store_alone(spark):
    df, texts = media_docs(spark)
    listed = media_chunks.chunk_lists(df, "doc_id", "text")
    store = media_chunks.chunk_store(df, listed)
    chunks = store.where(F.col("kind") == media_chunks.CHUNK)
    assert chunks.count() == chunks.select("name").distinct().count() > 0
    whole = sum(len(media_chunks.to_image(media_chunks.payload_of((t or "").encode()))) for t in texts)
    packer = media_chunks.Packer(bytes(store.where("kind = 2").first().data))
    kept = sum(len(packer.unpack(bytes(r.data))) for r in store.where("kind < 2").collect())
    assert kept < 0.9 * whole
    assert media_chunks.read_back(store).count() == len({t or "" for t in texts})
    victim = chunks.first().name
    missing = store.where(~((F.col("kind") == 1) & (F.col("name") == F.lit(bytes(victim)))))
    with pytest.raises(Exception, match="missing"):
        media_chunks.read_back(missing).collect()
    other = bytearray(packer.pack(b"other bytes"))
    altered = store.withColumn("data", F.when((F.col("kind") == 1) & (F.col("name") == F.lit(bytes(victim))), F.lit(bytes(other))).otherwise(F.col("data")))
    with pytest.raises(Exception, match="digest"):
        media_chunks.read_back(altered).collect()


def test_media_are_stored_in_rounds_that_release_their_shuffles(spark, monkeypatch):
    df, texts = media_docs(spark)
    released, tables = [], []
    monkeypatch.setattr(media_chunks, "release_shuffles", lambda s: released.append(s))
    whole = media_chunks.written
    monkeypatch.setattr(media_chunks, "written", lambda d, name, **options: tables.append((name, whole(d, name, **options))) or tables[-1][1])
    media_chunks.chunk_store(df, media_chunks.chunk_lists(df, "doc_id", "text"))
    rounds = [{bytes(r.name) for r in t.where("kind = 0").collect()} for name, t in tables if name == "media-store"][1:]
    assert len(rounds) == media_chunks.ROUNDS == len(released) - 1
    names = {hashlib.sha256(media_chunks.to_image(media_chunks.payload_of((t or "").encode()))).digest() for t in texts}
    assert set().union(*rounds) == names and sum(map(len, rounds)) == len(names) and max(map(len, rounds)) < len(names)


def test_media_empty_table_and_other_columns(spark):
    df, texts = media_docs(spark)
    assert media_chunks.store_and_read(df.where("false")).count() == 0
    assert media_chunks.store_and_read(df.union(df)).count() == 2 * len(texts)


# url filter


def judged(spark, pages):
    return rows_by(url_filter.judge(spark.createDataFrame(pages, "page_id long, url string, html string")), "page_id")


def test_alias_links_of_all_forms(spark):
    link, blocked = '<link rel="canonical" href="{}">', "http://a.example.com/en/1"
    pages = [
        (1, blocked, None),
        (2, "http://x.info/1", link.format(blocked)),
        (3, "http://a.example.com/fr/x/p", "<link href='../../en/1' rel=canonical>"),
        (4, "http://a.example.com/fr/p?x=1&y=2", "<html>"),
        (5, "http://q.info/5", link.format("http://a.example.com/fr/p?x=1&amp;y=2")),
        (6, "http://a.example.com/fr/p", "<meta content=\"0;url='http://a.example.com/en/1'\" http-equiv=Refresh>"),
        (7, "http://a.example.com/fr/p?x=1&y=2#top", link.format("?x=9")),
        (8, "http://a.example.com/fr/p?x=9", "<base href='/en/'><link rel=canonical href='1'>"),
        (9, "http://c.info/9", f"<!-- {link.format(blocked)} --><script>x='{link.format(blocked)}'</script>"),
        (10, "http://d.info/10", link.format("http://e.info/1") + link.format("http://&#97;.example.com/&#x65;n/1")),
        (11, "http://f.info/1", link.format("mailto:x@y.z") + link.format("") + "<link rel=canonical>"),
        (12, "HTTP://A.example.com/fr/p/", "<link rel='canonical' href='./../p'>"),
        (13, None, link.format(blocked)),
        (14, "http://e.info/1#part", ""),
        (14, "http://e.info/1#part", ""),
    ]
    rows = judged(spark, pages)
    assert {k for k, r in rows.items() if r.verdict == "allow"} == {9, 11, 13}
    assert rows[12].host == "a.example.com" and rows[12].path == "/fr/p/"
    assert url_filter.judge(spark.createDataFrame(pages, "page_id long, url string, html string")).count() == len(pages)


def test_allow_goes_before_block_in_a_group_and_along_chains(spark):
    link = '<link rel="canonical" href="{}">'
    chain = [(k, f"http://c{k}.info/", link.format(f"http://c{k + 1}.info/")) for k in range(40)]
    mixed = [(100, "http://m.info/", link.format("http://a.example.com/en/1")), (101, "http://n.info/", link.format("http://m.info/")), (102, "http://example.com/en/7", link.format("http://n.info/")), (103, "http://a.example.com/en/1", "")]
    rows = judged(spark, [*chain, (40, "http://c40.info/", link.format("http://x.org/es/1")), *mixed])
    assert {rows[k].verdict for k in range(41)} == {"block"}
    assert [rows[k].verdict for k in (100, 101, 102, 103)] == ["allow", "allow", "allow", "block"]
    assert url_filter.judge(spark.createDataFrame([], "page_id long, url string, html string")).count() == 0


def test_rules_in_one_expression(spark):
    rules = [("block", f"h{k}.org", "/") for k in range(300)]
    df = spark.createDataFrame([(1, "http://a.h299.org/x", ""), (2, "http://h300.org/", "")], "page_id long, url string, html string")
    assert [r.verdict for r in sorted(url_filter.judge(df, rules).collect())] == ["block", "allow"]
    with pytest.raises(ValueError):
        url_filter.best_rule(F.lit(""), F.lit(""), [("block", "x", "/")] * (url_filter.MAX_RULES + 1))


# toxicity


def levenshtein(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        new = [i]
        for j, y in enumerate(b, 1):
            new.append(min(new[-1] + 1, row[j] + 1, row[j - 1] + (x != y)))
        row = new
    return row


def test_automaton_and_trie_against_brute_force():
    rng = random.Random(6)
    make = lambda n: "".join(rng.choice("abc") for _ in range(n))
    words, stems = sorted({make(rng.randint(4, 10)) for _ in range(40)}), sorted({make(rng.randint(5, 8)) for _ in range(15)})
    trie = toxicity.Trie(words, stems)
    for _ in range(600):
        word = make(rng.randint(1, 12))
        near = [(levenshtein(word, t)[-1], t) for t in words] + [(min(levenshtein(s, word)), s) for s in stems]
        near = [(d, t) for d, t in near if d <= toxicity.edits(t)]
        got = trie.within(word)
        assert (got is None) == (not near) and (got is None or (got[1], got[0]) == min(near))
    for bound in range(3):
        for _ in range(200):
            a, b = make(rng.randint(0, 7)), make(rng.randint(0, 7))
            automaton = toxicity.Automaton(a, bound)
            state = automaton.start
            for letter in b:
                state = automaton.step(state, letter)
            far, begins = levenshtein(a, b)[-1], min(levenshtein(b, a))
            assert automaton.whole(state) == (far if far <= bound else None)
            assert automaton.beginning(state) == (begins if begins <= bound else None)


@pytest.fixture(scope="module")
def labelled(spark):
    rng = random.Random(8)
    plain = [f"{a}{b}{c}" for a in ("gar", "lop", "min", "set") for b in ("ad", "ul", "en") for c in ("o", "is", "um", "ery")]
    rows = []
    for k in range(900):
        words = [rng.choice(plain) for _ in range(25)]
        toxic = k % 4 == 0
        if toxic:
            for _ in range(rng.randint(1, 3)):
                words[rng.randrange(25)] = rng.choice(["blockhead", "nitwits", "dunderbrain"])
        rows.append((k, " ".join(words), int(toxic)))
    rows += [(901, None, 0), (902, "", 0), (903, None, 1)]
    return spark.createDataFrame(rows, "doc_id long, text string, toxic int")


def test_toxicity_model_finds_terms_and_misspelled_ones(spark, labelled):
    documents, labels = labelled.select("doc_id", "text", F.lit(1.0).alias("toxicity")), labelled.select("doc_id", "toxic")
    model = toxicity.fit(documents, labels)
    assert set(model.lexicon.words) | set(model.lexicon.stems) >= {"dunderbrain"}
    tests = ["garado blockhead lopulis", "garado blokhead lopulis minenum setadery", "dunderbrian", "dund3rbrain lopulis", "garado lopulis minenum", None, "", 'he said "you blockhead" lopulis', "x" * 50_000]
    scored = rows_by(toxicity.score_texts(spark.createDataFrame([(k, t, 7) for k, t in enumerate(tests)], "doc_id long, text string, toxicity int"), model))
    got = [scored[k].toxicity >= 0.5 for k in range(len(tests))]
    assert got == [True, True, True, True, False, False, False, False, False]
    assert scored[5].toxicity == scored[6].toxicity == scored[8].toxicity
    assert toxicity.score_texts(documents.where("false"), model).count() == 0


def test_toxicity_labels_of_one_class_or_none(spark, labelled):
    documents = labelled.select("doc_id", "text")
    for condition in ("toxic = 0", "toxic = 1", "false"):
        model = toxicity.fit(documents, labelled.select("doc_id", "toxic").where(condition))
        scores = [r.toxicity for r in toxicity.score_texts(documents, model).collect()]
        assert len(scores) == documents.count() and all(0 <= s <= 1 for s in scores)
    nulls = labelled.select("doc_id", F.lit(None).cast("int").alias("toxic")).union(labelled.select("doc_id", "toxic")).union(labelled.select("doc_id", "toxic"))
    assert toxicity.training_rows(documents, nulls).count() <= documents.count()


# html


def test_html_titles_links_formulas_and_deep_pages(spark):
    nav = "<nav><a href=x>menu</a></nav>"
    pages = [
        f'<body>{nav}<article class="post"><div class="post-header"><h1>Title</h1><span>by me</span></div><p>Some text here</p><p>x <math><mi>a</mi></math> y</p></article><footer>f</footer></body>',
        f"<body>{nav}<article><p><a href=y>The whole article is a link</a></p></article><footer>f</footer></body>",
        '<body><div class="post"><div class="post-header"><h1>Title</h1></div><p>Some text here</p></div><div class=sidebar>side</div></body>',
        "<body><ul><li><a>x</a></li></ul></body>",
        "<div>" * 16_000 + "<p>deep text</p>",
        "<article><p>never closed<div><p>and more &lt;b&gt;",
        "plain text without any tag",
    ]
    want = ["Title\n\nSome text here\n\nx a y", "The whole article is a link", "Title\n\nSome text here", "", "deep text", "never closed\n\nand more <b>", "plain text without any tag"]
    df = spark.createDataFrame([(k, f"http://h{k}.org/", h, "x") for k, h in enumerate(pages)] * 2, "page_id long, url string, html string, text string")
    got = html_extract.extract(df)
    assert [rows_by(got, "page_id")[k].text for k in range(len(pages))] == want and got.count() == 2 * len(pages)


def test_html_articles_of_random_pages(spark, monkeypatch):
    rng = random.Random(12)
    words = ["and", "of", "river", "stone", "café", "R&D", "a<b", "five"]
    line = lambda n: " ".join(rng.choice(words) for _ in range(n))
    esc = lambda t: t.replace("&", "&amp;").replace("<", "&lt;")
    noise = ["<nav><ul><li><a href=/>Home</a></li></ul></nav>", "<header><h2>Site name</h2></header>", "<div class='cookie-notice'>We use cookies here</div>", "<aside>Side words</aside>", "<form>Search <input></form>", "<script>var a='<p>no</p>';</script>", "<style>p{}</style>", "<!-- <p>no</p> -->", "<div id='ad-1'>Buy this</div>"]
    rows, want = [], {}
    for k in range(120):
        host = k % 6
        blocks, html = [], ""
        for _ in range(rng.randint(1, 7)):
            tag = rng.choice(["p", "h2", "li", "blockquote", "td"])
            text = line(rng.randint(6, 40))
            blocks.append(text)
            own = f"<{tag}>{esc(text)}</{tag}>" if rng.random() < 0.8 else f"<{tag}>{esc(text[:5])}<b>{esc(text[5:])}</b></{tag}>"
            html += f"<ul>{own}</ul>" if tag == "li" else f"<table><tr>{own}</tr></table>" if tag == "td" else own
        wrap = [("<article>", "</article>"), ("<main>", "</main>"), ("<div class='post'>", "</div>"), ("<div id='content'>", "</div>"), ("<article class='x'><section>", "</section></article>"), ("<div class='entry'>", "</div>")][host]
        top, low = (rng.sample(noise, 4) for _ in range(2))
        rows.append((k, f"http://h{host}.org/{k}", f"<html><head><title>T</title></head><body>{''.join(top)}{wrap[0]}{html}{wrap[1]}{''.join(low)}<footer>Foot words</footer></body></html>"))
        want[k] = "\n\n".join(" ".join(b.split()) for b in blocks)
    df = spark.createDataFrame(rows, "page_id long, url string, html string")
    got = {r.page_id: r.text for r in html_extract.extract(df).collect()}
    assert got == want
    monkeypatch.setattr(html_extract, "MAX_BROADCAST_HOSTS", 0)
    assert {r.page_id: r.text for r in html_extract.extract(df).collect()} == want


def test_html_two_templates_on_a_host(spark):
    a = "<body><nav><a>m</a></nav><article><p>First form {0} with words enough to count</p></article></body>"
    b = "<body><nav><a>m</a></nav><div class='story'><p>Second form {0} with words enough to count</p></div></body>"
    df = spark.createDataFrame([(k, "http://h.org/", (a if k % 3 else b).format(k)) for k in range(12)], "page_id long, url string, html string")
    assert all(f"form {k} with" in t for k, t in ((r.page_id, r.text) for r in html_extract.extract(df).collect()))


def test_every_text_has_one_gram_set():
    assert [len(x) for x in near_join.shingle_sets(pa.array([None, "", "!!", "a b c", "a b c d e f"]))] == [0, 0, 0, 1, 2]
