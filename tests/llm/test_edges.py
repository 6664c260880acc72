"""Nulls, empty and long texts, ties, repeated rows, empty tables and clashing columns, for every operator."""

import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from rotquant.llm import decontaminate, licences, neardup, packing, pii, quality, secrets, tokens, topk, toxicity
from rotquant.llm.gru import Network

LONG = "word and other things of the kind that go on. " * 3000
ROWS = [(1, None), (2, ""), (3, "   \n "), (4, "The same text of a few words."), (5, "The same text of a few words."), (5, "The same text of a few words."), (6, LONG), (None, "no id at all"), (7, "héé ✓ 𝔘 mixed")]
EXTRA = ["rank", "value", "part", "spans", "base", "cands", "rid", "n", "cid", "found", "score", "kept", "length", "component"]


@pytest.fixture(scope="module")
def docs(spark):
    d = spark.createDataFrame(ROWS, "doc_id long, text string")
    for c in EXTRA:
        d = d.withColumn(c, F.lit("x"))
    return d.withColumn("lang", F.lit(None).cast("string")).withColumn("source", F.lit(None).cast("string")).withColumn("n_chars", F.lit(None).cast("long"))


@pytest.fixture(scope="module")
def labels(spark):
    return spark.createDataFrame([(4, 0), (5, 1), (6, None), (None, 1), (4, 0)], "doc_id long, toxic int")


@pytest.fixture(scope="module")
def items(spark):
    return spark.createDataFrame([(1, None), (2, ""), (3, "short"), (4, "The same text of a few words."), (4, "The same text of a few words.")], "item_id long, text string")


def operators(spark, labels, items):
    net = Network()
    return {
        "tokens": lambda d: tokens.length_histogram(tokens.with_lengths(d)),
        "quality": lambda d: quality.quality_scores(d),
        "decontaminate": lambda d: decontaminate.benchmark_matches(d, items),
        "toxicity": lambda d: toxicity.toxicity(d, net),
        "secrets": lambda d: secrets.secret_spans(d),
        "neardup": lambda d: neardup.near_duplicates(d, 2),
        "packing": lambda d: packing.pack(d),
        "pii": lambda d: pii.personal_data(d),
        "licences": lambda d: licences.licence_matches(d),
    }


PER_ROW = ("quality", "toxicity", "secrets", "neardup", "pii")


@pytest.mark.parametrize("name", ["tokens", "quality", "decontaminate", "toxicity", "secrets", "neardup", "packing", "pii", "licences"])
def test_odd_rows_and_empty_tables(spark, docs, labels, items, name):
    op = operators(spark, labels, items)[name]
    rows = op(docs).collect()
    if name in PER_ROW:
        assert len(rows) == len(ROWS)
    got = {r["doc_id"]: r for r in rows} if name != "tokens" else {}
    if name == "neardup":
        assert got[5]["component_id"] == got[4]["component_id"] == 4 and got[4]["kept"] and not got[5]["kept"]
        assert all(got[i]["n_shingles"] == 0 and got[i]["component_id"] == i and got[i]["kept"] for i in (1, 2, 3))
        assert got[None]["component_id"] is None and got[None]["kept"]
    if name == "tokens":
        assert sum(r["n_docs"] for r in rows) == len(ROWS) and min(r["length"] for r in rows) == 0
    if name == "quality":
        assert not got[1]["kept"] and not got[3]["kept"] and got[4]["score"] == got[5]["score"]
    if name == "toxicity":
        assert got[1]["score"] == got[2]["score"] == got[3]["score"] == 0 and got[4]["score"] == got[5]["score"]
    if name == "decontaminate":
        assert {(r["doc_id"], r["item_id"]) for r in rows} == {(4, 4), (5, 4)}
    if name in ("secrets", "pii"):
        assert all(not r["spans"] for r in rows)
    if name == "licences":
        assert rows == []
    if name == "packing":
        assert sum(r["length"] for r in rows if r["doc_id"] == 1) == 1 and {r["doc_id"] for r in rows} >= {1, 2, 3, 4, 5, 6, 7}
    assert op(docs.limit(0)).collect() == []


def test_training_without_labels(spark, docs, labels):
    texts, y = toxicity.training_rows(docs, labels, 100)
    assert len(texts) == len(y)
    net = toxicity.fit(docs, labels.limit(0), rounds=1, steps=1)
    scores = {r["score"] for r in toxicity.toxicity(docs, net).where("doc_id IN (4, 5, 6, 7)").collect()}
    assert len(scores) == 1 and scores.pop() == pytest.approx(0, abs=1e-6)


def test_found_spans_of_repeated_and_long_rows(spark):
    """Repeated rows each report, and a place behind a long text is right."""
    long = "é " * 50_000
    rows = [(1, long + "mail a.b@c.de token=abcdef12"), (1, long + "mail a.b@c.de token=abcdef12"), (None, "a.b@c.de token=abcdef12"), (2, None), (3, "")]
    df = spark.createDataFrame(rows, "doc_id long, text string").withColumn("spans", F.lit(1)).withColumn("base", F.lit(2))
    at = {None: 0, 1: 100_005}
    for found, kind, size, off in ((pii.personal_data(df), "email", 8, 0), (secrets.secret_spans(df), "assign", 14, 9)):
        got = sorted(((r["doc_id"], [(s["start"], s["kind"], s["end"]) for s in r["spans"]]) for r in found.collect()), key=repr)
        want = sorted([(d, [(at[d] + off, kind, at[d] + off + size)]) for d in (1, 1, None)] + [(2, []), (3, [])], key=repr)
        assert got == want


def test_top_k_drops_vectors_that_are_not_whole(spark):
    v = spark.createDataFrame(
        [(0, [1.0, 0.5]), (1, [1.0, 0.5]), (2, [1.0, 0.5]), (3, None), (4, [None, 1.0]), (5, [float("nan"), 1.0]), (6, [float("inf"), 1.0]), (20, [0.5]), (None, [1.0, 1.0]), (7, []), (2, [1.0, 0.5])],
        "vec_id long, embedding array<float>",
    )
    rows = [tuple(r) for r in topk.top_k(v, F.col("vec_id") % 20 == 0, 2).orderBy("query_id", "rank").collect()]
    assert rows == [(0, 1, 1, 5120), (0, 2, 2, 5120)]
    assert topk.top_k(v.limit(0), F.col("vec_id") % 20 == 0).collect() == []


def test_stages_keep_columns(spark, docs, sf):
    d = docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        d2 = stage(spark, d, sf)
        assert d2.columns == docs.columns, name
        assert d2.count() <= d.count()
        d = d2
    left = {r["doc_id"] for r in d.collect()}
    assert 5 not in left and 1 not in left
    assert corpus_pipeline.STAGES[-1][1](spark, d, sf).count() > 0
    assert corpus_pipeline.STAGES[-1][1](spark, d.limit(0), sf).count() == 0


def test_repeated_rows_of_one_id_leave_one(spark, docs):
    left = neardup.one_of_each(docs.where("doc_id >= 5").withColumn("__id", F.lit("mine")).withColumn("__ID_", F.lit("too")))
    assert left.where("doc_id = 5").count() == 1
    assert {(r["__id"], r["__ID_"]) for r in left.collect()} == {("mine", "too")}


@pytest.mark.parametrize("stage", ["quality", "near_dedup", "decontaminate", "secrets"])
def test_stages_take_empty_tables(spark, docs, sf, stage):
    assert dict(corpus_pipeline.STAGES)[stage](spark, docs.limit(0), sf).collect() == []
