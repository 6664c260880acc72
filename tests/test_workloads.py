"""Queries against a second engine, streams against batches, caches against full precision."""

import math

import duckdb
import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry_module
from rotquant.functions.passages import Passages
from rotquant.model import QuantizerSpec
from rotquant.operators import cache as C
from rotquant.operators import relational
from rotquant.operators.codec import codec
from rotquant.operators.quantize import encode
from rotquant.operators.search import exact_topk, split, topk, topk_by_method
from rotquant.plans import registry
from rotquant.plans.tasks import WEIGHTS, task_groups
from rotquant.sources.tables import VECTOR_SCHEMA, read_stream, read_table, read_vectors
from rotquant.streaming.codes import encode_stream, growing_cache, write_stream
from rotquant.streaming.windows import sessions, sliding, tumbling, without_repeats

SF = "/root/testdata/sf0.01"
TABLES = "embeddings documents events conversations benchmark labels".split()
CHEAP = ["normalize_vectors", "exact_topk", "rotate_relational", "gs_codes_b3", "gr_sweep_codes_b3", "gr_ladder_codes_b2", "bb1_codes_b2", "bb3_codes_b2", "codes_catalyst_b2", "mse_by_method", "ip_error_stats", "ratio_law", "failure_rate", "recall_2bit", "recall_signbit", "decode_bb3", "norm_roundtrip", "error_cdf", "seed_summary", "lookup_agreement", "theory_computed", "full_sphere_bounds", "signbit_estimate_stats", "needle_positions", "pack_unpack", "text_vectors_192", "cache_outliers", "event_sessions", "event_asof", "theory_table", "shannon_gap"]


@pytest.fixture(scope="module")
def duck():
    c = duckdb.connect()
    for t in TABLES:
        c.sql(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    return c


def plain(df: pd.DataFrame) -> list:
    one = lambda v: None if pd.isna(v) else float(v) if isinstance(v, (int, float)) and not isinstance(v, bool) else v
    return sorted(repr([one(v) for v in r]) for r in df[sorted(df.columns)].astype(object).values.tolist())


@pytest.mark.parametrize("name", CHEAP)
def test_two_engines_agree(spark, duck, name):
    sql = registry.SQL[name]
    assert plain(registry.queries()[name](spark, SF).toPandas()) == plain(duck.sql(sql if isinstance(sql, str) else sql()).df())


MOVED = ["theory_table", "theory_computed", "shannon_gap", "full_sphere_bounds", "effective_bits", "codebook_distortion", "chebyshev", "bit_curves"]


@pytest.mark.parametrize("name", MOVED)
def test_closed_forms_stand_beside_a_table(spark, duck, name):
    """Spark reads a given table for these, and another engine finds the same in it."""
    got, sql = registry.queries()[name](spark, SF), registry.SQL[name]
    assert got.inputFiles()
    assert plain(got.toPandas()) == plain(duck.sql(sql if isinstance(sql, str) else sql()).df())


def test_entry(spark):
    rows = entry_module.entry(spark).collect()
    assert [r["k"] for r in rows] == [1, 2, 4, 8, 16, 32, 64] and rows[-1]["recall"] > 0.9


def test_exact_scan_plan(spark):
    """Only the columns that are used are read, and no shuffle comes before the merge."""
    v = encode(read_vectors(spark, SF).where("vec_id % 10 <> 0"), QuantizerSpec("ball_block", "raw", 64, 3, 2))
    plan = v._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan and "label" not in plan


# caches ---------------------------------------------------------------------------


@pytest.fixture(scope="module")
def tokens(spark):
    return C.token_rows(read_table(spark, "/root/testdata/sf0.001", "conversations", "conv_id", "turn", "text").where("conv_id < 6"))


def test_outlier_channels_are_those_that_were_scaled(tokens):
    got = {(r["head"], r["channel"]) for r in C.outlier_channels(tokens).collect()}
    assert got == {(h, c) for h in range(C.HEADS) for c in range(C.WIDTH) if C.channel_scale(h, c) > 1}


def test_attention_in_parts_is_attention(spark, tokens, monkeypatch):
    specs = {"gauss_scalar": C.CacheSpec("gauss_scalar", 1), "signbit": C.CacheSpec("sphere_scalar_signbit", 1, "raw"), "fine": C.CacheSpec("gauss_scalar", 1, "best", b_hi=8, b_lo=8, b_value=8)}
    out = C.attend(tokens, C.outlier_channels(tokens), specs)
    rows = tokens.orderBy("pos").collect()
    for r in out.where("method = 'exact'").collect():
        words = [x["token"] for x in rows if x["seq_id"] == r["seq_id"]]
        k, v, q = (C.states(w, kind, r["head"]) for w, kind in ((words, "k"), (words, "v"), (words[-1:], "q")))
        w = np.exp(k @ q[0] / math.sqrt(C.WIDTH))
        assert np.allclose(r["out"], w @ v / w.sum())
    err = {r["method"]: r["logit_error"] for r in C.attention_error(out).collect()}
    assert err["fine"] < err["gauss_scalar"] < err["signbit"]


def test_attention_errors_by_token_are_those_of_all_positions(spark, tokens, monkeypatch):
    """Blocks of any size; a token that comes in many sequences, and often in one, is coded once in each block."""
    monkeypatch.setattr(C, "PAIRS", 64)
    specs = {"gauss_scalar:0": C.CacheSpec("gauss_scalar", 1), "gauss_scalar:1": C.CacheSpec("gauss_scalar", 1, seed=1), "signbit:0": C.CacheSpec("sphere_scalar_signbit", 1, "raw")}
    rows = tokens.unionByName(spark.range(3000).selectExpr("7L AS seq_id", "id AS pos", "CASE WHEN id % 3 = 0 THEN 'a' ELSE 'the' END AS token"))
    own = C.outlier_channels(rows)
    want = {r["method"]: r for r in C.attention_error(C.attend(rows, own, specs)).collect()}
    for block in (1, 1 << 20):
        got = C.attention_error_by_token(rows, own, specs, block).collect()
        assert {r["method"]: r["n"] for r in got} == {m: r["n"] for m, r in want.items()}
        for r in got:
            assert (r["output_error"], r["logit_error"]) == pytest.approx((want[r["method"]]["output_error"], want[r["method"]]["logit_error"]), rel=1e-9)


def test_needles_are_found_at_full_precision(spark):
    docs, items = read_table(spark, SF, "documents", "doc_id", "text"), read_table(spark, SF, "benchmark", "item_id", "text")
    hits = C.needle_hits(docs, items, {"coarse": C.CacheSpec("sphere_scalar", 1)}).cache()
    score = {r["method"]: r["s"] for r in hits.groupBy("method").agg(F.avg("hit").alias("s")).collect()}
    assert score["exact"] == 1 and score["coarse"] > 0.9
    assert hits.where("method = 'exact'").count() == C.needle_positions(docs, items).count()
    hits.unpersist()


def test_passages_are_found_at_their_first_place():
    texts = ["", "ab", "x the passage y the passage", "é the passage", "short ab"]
    look = Passages([(7, "the passage"), (8, "ab"), (9, ""), (10, "the passage y")])
    for t in texts:
        want = [(k, t.find(item)) for k, (_, item, _) in enumerate(look.items) if item in t]
        assert look.find(t) == want
    assert look.find(None) == []


def test_cache_scales_have_sixteen_bits():
    x = np.random.default_rng(0).standard_normal((5, 32))
    for m in ("gauss_scalar", "sphere_scalar_signbit"):
        c = codec(C.CacheSpec(m, 1, "raw").part(32, 3))
        near = C.stored(c, x)
        e = c.encode(x)
        assert np.allclose(near, c.decode(e), rtol=2e-3, atol=2e-3) and not np.array_equal(near, c.decode(e))


def test_one_scan_serves_all_methods(spark):
    """The best rows of one scan are those of stored codes, whatever the number of partitions."""
    v = read_vectors(spark, SF)
    q, db = split(v, 10)
    s = QuantizerSpec("sphere_scalar", "unbiased", 64, 1, 2)
    both = topk_by_method(q, db.repartition(5), {"exact": None, "ss": s}, 5)
    one = {tuple(r) for r in topk(q, encode(db, s), s, 5).collect()}
    assert {tuple(r)[1:] for r in both.where("method = 'ss'").collect()} == one
    assert {tuple(r)[1:] for r in both.where("method = 'exact'").collect()} == {tuple(r) for r in exact_topk(q, db, 5).collect()}


def test_split_does_not_depend_on_the_folder(spark, tmp_path):
    read_table(spark, SF, "embeddings").write.parquet(str(tmp_path / "other" / "embeddings.parquet"))
    here, there = (sorted(map(tuple, registry.queries()["split_queries"](spark, x).collect())) for x in (SF, str(tmp_path / "other")))
    assert here == there


def test_large_query_sets_are_not_broadcast(spark, monkeypatch):
    monkeypatch.setattr(relational, "QUERY_BYTES", 1000)
    with pytest.raises(ValueError):
        relational.exact_pairs(*split(read_vectors(spark, SF), 10))


def test_task_groups_of_the_exact_method(spark):
    """Near copies are all found at full precision; the other groups lie between chance and one."""
    got = {r["task"]: r["score"] for r in task_groups(spark, "/root/testdata/sf0.001", {"exact": None}, 128).collect()}
    assert set(got) == set(WEIGHTS) and got["near_copy"] == 1 and all(0 <= x <= 1 for x in got.values()) and got["lang"] > 0.7


# streams --------------------------------------------------------------------------


def drained(df, spark, name, mode="append"):
    q = df.writeStream.outputMode(mode).format("memory").queryName(name).start()
    q.processAllAvailable()
    q.stop()
    return spark.table(name)


def test_streamed_codes_equal_batch_codes(spark, sf, tmp_path):
    v = read_vectors(spark, sf)
    v.repartition(3).write.parquet(str(tmp_path / "in"))
    s = QuantizerSpec("ball_block", "unbiased", 64, 3, 2)
    stream = read_stream(spark, str(tmp_path / "in"), VECTOR_SCHEMA)
    got = drained(encode_stream(stream, s), spark, "codes")
    batch = encode(v, s)
    near = lambda x: x.select("vec_id", "code", *[F.round(c, 9) for c in ("norm", "rho", "zbar_sq")])  # noqa: E731  (sums of batches of other sizes differ in their last bits)
    assert got.count() == batch.count() and near(got).exceptAll(near(batch)).count() == 0
    q = write_stream(encode_stream(read_stream(spark, str(tmp_path / "in"), VECTOR_SCHEMA), s), s, str(tmp_path / "out"), str(tmp_path / "ck"))
    q.processAllAvailable()
    q.stop()
    assert spark.read.parquet(str(tmp_path / "out/codes")).select("vec_id").distinct().count() == v.count()


def test_streamed_windows_equal_batch_windows(spark, sf, tmp_path):
    e = read_table(spark, sf, "events", "event_id", "ts", "user_id", "event_type", "value")
    e.repartition(2).write.parquet(str(tmp_path / "ev"))
    stream = lambda: read_stream(spark, str(tmp_path / "ev"), e.schema, files=1)
    for name, f in (("tumble", lambda x, late: tumbling(x, "1 day", late)), ("slide", lambda x, late: sliding(x, "2 days", "1 day", late)), ("session", lambda x, late: sessions(x, "6 hours", late))):
        got = drained(f(stream(), "60 days"), spark, name, "complete")
        want = f(e, None)
        assert got.agg(F.count("*"), F.sum("n")).first() == want.agg(F.count("*"), F.sum("n")).first(), name
    twice = drained(without_repeats(stream(), "60 days"), spark, "once")
    assert twice.count() == e.count()


def test_growing_cache_counts_codes(spark, tmp_path):
    spark.createDataFrame([(1, [1, 2]), (1, [3, 4]), (2, [5, 6])], "seq_id long, code array<int>").coalesce(1).write.parquet(str(tmp_path / "a"))
    s = growing_cache(spark.readStream.schema("seq_id long, code array<int>").parquet(str(tmp_path / "a")))
    assert {r["seq_id"]: r["cached"] for r in drained(s, spark, "grown", "update").collect()} == {1: 2, 2: 1}
