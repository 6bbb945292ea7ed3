"""The corpus pipeline on a small corpus with planted cases: what each stage keeps, and nulls, empty tables and further columns."""

import random

import public_tokenizers
import pytest
from tokenizers import Tokenizer

import corpus_pipeline
from objann.llm import pii

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


def corpus():
    rng = random.Random(5)
    plain = [f"{a}{b}{c}" for a in ("gar", "lop", "min", "set") for b in ("ad", "ul", "en") for c in ("o", "is", "um", "ery")]
    line = lambda n: [rng.choice(plain) for _ in range(n)]
    texts, labels = {}, {}
    for k in range(600):
        words = line(30)
        labels[k] = int(k % 4 == 0)
        if labels[k]:
            for place in rng.sample(range(30), 2):
                words[place] = rng.choice(["blockhead", "dunderbrain"])
        texts[k] = " ".join(words)
    base = line(80)
    for k in range(700, 706):
        texts[k] = " ".join(base if k < 703 else [*base[: k - 700], f"x{k}", *base[k - 699 :]])
    texts |= {800: None, 801: "", 802: "write to Zebrowski at zeb@y.org or 1.2.3.4 111 1111 1111 1111 now", 803: " ".join(line(4000)), 804: "a dunderbrian and blockhead"}
    return texts, labels


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    path = str(tmp_path_factory.mktemp("corpus"))
    texts, labels = corpus()
    rows = [(k, t, "en", "src", len(t or "")) for k, t in texts.items()]
    spark.createDataFrame(rows, SCHEMA).write.parquet(f"{path}/documents.parquet")
    spark.createDataFrame([(k, 1, t) for k, t in labels.items()], "doc_id long, quality int, toxic int").write.parquet(f"{path}/labels.parquet")
    return path


def test_stages_against_what_was_planted(spark, folder):
    texts, labels = corpus()
    docs = spark.read.parquet(f"{folder}/documents.parquet")
    stages = dict(corpus_pipeline.STAGES)
    clean = stages["toxicity"](spark, docs, folder)
    assert clean.columns == docs.columns
    left = {r.doc_id: r.text for r in clean.collect()}
    assert set(left) == {k for k in texts if not labels.get(k) and k != 804} and all(left[k] == texts[k] for k in left)
    single = stages["near_duplicates"](spark, clean, folder)
    kept = {r.doc_id for r in single.collect()}
    assert kept == set(left) - {701, 702, 703, 704, 705, 801} and single.columns == docs.columns
    private = stages["personal_data"](spark, single, folder)
    after = {r.doc_id: (r.text, r.n_chars) for r in private.collect()}
    assert set(after) == kept and private.columns == docs.columns
    spans = {r.doc_id: r.spans for r in pii.personal_data(single).collect()}
    assert all(after[k][0] == left[k] for k in kept if not spans[k])
    assert "1111" not in after[802][0] and "zeb" not in after[802][0].lower() and after[802][1] == len(after[802][0])
    pieces = stages["packing"](spark, private, folder).collect()
    library = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    total = sum(len(library.encode(t or "", add_special_tokens=False).ids) + 1 for t, _ in after.values())
    places = sorted((p.sequence_id * 2048 + p.offset, p.length) for p in pieces)
    assert sum(n for _, n in places) == total and all(a + n == b for (a, n), (b, _) in zip(places, places[1:]))


def test_whole_run_equals_its_stages_and_takes_other_columns(spark, folder):
    docs = spark.read.parquet(f"{folder}/documents.parquet")
    whole = corpus_pipeline.run(spark, folder).collect()
    for _, stage in corpus_pipeline.STAGES:
        docs = stage(spark, docs.selectExpr("*", "1 AS toxicity", "2 AS class_id") if "text" in docs.columns else docs, folder)
    assert sum(r.length for r in whole) == sum(r.length for r in docs.collect())
    assert {r.doc_id for r in whole} == {r.doc_id for r in docs.collect()}


def test_empty_tables_and_null_columns(spark, folder, tmp_path):
    docs = spark.read.parquet(f"{folder}/documents.parquet")
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, docs.where("false"), folder).count() == 0
    nulls = spark.createDataFrame([(None, None, None, None, None), (1, "some words stand here now", None, None, None)], SCHEMA)
    for _, stage in corpus_pipeline.STAGES[:3]:
        assert stage(spark, nulls, folder).count() == 2
    assert corpus_pipeline.STAGES[3][1](spark, nulls, folder).count() == 2
    docs.where("false").write.parquet(f"{tmp_path}/documents.parquet")
    spark.read.parquet(f"{folder}/labels.parquet").where("false").write.parquet(f"{tmp_path}/labels.parquet")
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == 0
