"""Quantizers on sphere samples, and their DataFrame forms."""

import itertools
from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import functions as F

from rotquant.functions import theory
from rotquant.functions.sql import register_functions
from rotquant.model import QuantizerSpec, normalize, quarantined
from rotquant.operators import metrics as M
from rotquant.operators.codec import Codec, codec, grid_ladder, grid_sweep
from rotquant.operators.quantize import Quantizer, decode, encode, fit_block_book, pack_codes, unpack_codes
from rotquant.operators.search import best_rows, exact_topk, pairs, split, topk
from rotquant.sources.stores import read_codes, write_codes
from rotquant.sources.tables import read_vectors

D = 64
ALL = [("gauss_scalar", 1), ("sphere_scalar", 1), ("grid_dir", 1), ("ball_block", 2), ("ball_block", 3)]


@pytest.fixture(scope="module")
def x():
    v = np.random.default_rng(3).standard_normal((1500, D))
    return v / np.linalg.norm(v, axis=1, keepdims=True)


@pytest.fixture(scope="module")
def scalars(x):
    return {(f, p, b): Codec(QuantizerSpec(f, "raw", D, p, b)).encode(x) for f, p in ALL for b in (1, 2, 3)}


def errors(e):
    rho, sq = e["rho"], e["zbar_sq"]
    return {"raw": 1 - 2 * rho + sq, "best": 1 - rho**2 / sq, "unbiased": sq / rho**2 - 1}


def test_shortcut_errors_are_the_explicit_ones(x, scalars):
    for (f, p, b), e in scalars.items():
        for r, want in errors(e).items():
            back = Codec(QuantizerSpec(f, r, D, p, b)).decode(e)
            assert np.allclose(((back - x) ** 2).sum(axis=1), want, atol=1e-9)
            if r == "unbiased":
                assert np.allclose((back * x).sum(axis=1), 1)
        assert (errors(e)["best"] <= errors(e)["raw"] + 1e-12).all()


def test_order_of_methods_and_lower_bound(scalars):
    mse = {k: {r: v.mean() for r, v in errors(e).items()} for k, e in scalars.items()}
    for b in (2, 3):
        for r in ("best", "unbiased"):
            three, two, one = (mse[f, p, b][r] for f, p in (("ball_block", 3), ("ball_block", 2), ("sphere_scalar", 1)))
            assert three < two < one and mse["gauss_scalar", 1, b][r] == pytest.approx(one, rel=0.02)
    for (f, p, b), v in mse.items():
        assert v["raw"] > theory.shannon_lower(b, D)
        if f != "grid_dir":
            assert v["best"] == pytest.approx(theory.mse(f, p, b), rel=0.09)


def test_one_bit_codes_agree(x):
    a, b, c = (Codec(QuantizerSpec(f, "best", D, 1, 1)) for f in ("gauss_scalar", "sphere_scalar", "grid_dir"))
    assert np.allclose(a.decode(a.encode(x)), b.decode(b.encode(x))) and np.allclose(a.decode(a.encode(x)), c.decode(c.encode(x)))


def test_block_of_one_is_the_scalar(x):
    a, b = Codec(QuantizerSpec("ball_block", "raw", D, 1, 3)), Codec(QuantizerSpec("sphere_scalar", "raw", D, 1, 3))
    assert np.array_equal(a.encode(x)["code"], b.encode(x)["code"])


def test_grid_sweep_is_the_best_word():
    z = np.random.default_rng(1).standard_normal((60, 4))
    z /= np.linalg.norm(z, axis=1, keepdims=True)
    words = np.array(list(itertools.product(range(4), repeat=4))) - 1.5
    best = (z @ (words / np.linalg.norm(words, axis=1, keepdims=True)).T).max(axis=1)
    for find, tol in ((grid_sweep, 1e-12), (grid_ladder, 0.02)):
        g = find(z, 2) - 1.5
        cos = (z * g).sum(axis=1) / np.linalg.norm(g, axis=1)
        assert (cos <= best + 1e-12).all() and (cos >= best - tol).all()


def test_ratio_law_bias_and_sign_bits(x):
    q = x[:40]
    for spec in (QuantizerSpec("ball_block", "unbiased", D, 3, 2), QuantizerSpec("sphere_scalar_signbit", "raw", D, 1, 2)):
        e = []
        for seed in range(4):
            c = Codec(replace(spec, seed=seed))
            e.append(c.estimate(c.encode(x[40:]), q) - x[40:] @ q.T)
        e = np.array(e)
        assert abs(e.mean()) < 5 * e.std() / np.sqrt(e.size / 40)
        want = theory.ip("sphere_scalar_signbit" if spec.rescale == "raw" else "ball_block", spec.p, 2, D)
        assert (e**2).mean() == pytest.approx(want, rel=0.1)


def test_padding_and_hadamard(x):
    pad = Codec(QuantizerSpec("ball_block", "best", D, 3, 2, tail="pad"))
    had = Codec(QuantizerSpec("ball_block", "best", D, 3, 2, rotation="hadamard"))
    for c in (pad, had):
        assert ((c.decode(c.encode(x)) - x) ** 2).sum(axis=1).mean() == pytest.approx(0.1, rel=0.1)
    assert pad.encode(x)["code"].shape[1] == 22


def test_norms_are_kept_apart(x):
    c = Codec(QuantizerSpec("ball_block", "unbiased", D, 3, 2))
    a, b = c.encode(x), c.encode(x * 7)
    assert np.array_equal(a["code"], b["code"]) and np.allclose(b["norm"], 7) and np.allclose(c.decode(b), 7 * c.decode(a))


# DataFrames -----------------------------------------------------------------------


def test_bad_rows_are_quarantined(spark):
    rows = [(1, [1.0, 2.0]), (2, None), (3, [float("nan"), 1.0]), (4, [0.0, 0.0]), (5, [1.0]), (6, [None, 1.0])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    good, bad = quarantined(df, 2)
    assert [r[0] for r in good.collect()] == [1] and sorted(r[0] for r in bad.collect()) == [2, 3, 4, 5, 6]
    assert encode(df, QuantizerSpec("sphere_scalar", "raw", 2 + 1, 1, 2)).count() == 0
    assert {r["vec_id"]: r["is_zero"] for r in normalize(df).collect()}[4]


def test_frames_equal_batches(spark, sf, tmp_path):
    v = read_vectors(spark, sf)
    rows = v.orderBy("vec_id").toPandas()
    x = np.stack(rows["embedding"])
    for s in (QuantizerSpec("ball_block", "unbiased", D, 3, 2), QuantizerSpec("sphere_scalar_signbit", "raw", D, 1, 2)):
        q = Quantizer(s, spark).fit()
        e, codes = codec(s).encode(x), q.encode(v)
        got = codes.orderBy("vec_id").toPandas()
        assert np.array_equal(np.stack(got["code"]), e["code"]) and np.allclose(got["rho"], e["rho"])
        back = unpack_codes(pack_codes(codes, s), s).orderBy("vec_id").toPandas()
        assert np.array_equal(np.stack(back["code"]), e["code"])
        hat = decode(codes, s).orderBy("vec_id").toPandas()
        assert np.allclose(np.stack(hat["xhat"]), codec(s).decode(e))
        err = M.recon_error(v, decode(codes, s)).agg(F.avg("err")).first()[0]
        assert err == pytest.approx(((codec(s).decode(e) - x) ** 2).sum(axis=1).mean())
        write_codes(codes, s, str(tmp_path / s.spec_id))
        again, spec = read_codes(spark, str(tmp_path / s.spec_id))
        assert spec == s and again.count() == len(x)


def test_search_and_pairs(spark, sf):
    q, db = split(read_vectors(spark, sf), 10)
    exact = exact_topk(q, db, 5).toPandas()
    a, b = np.stack(q.orderBy("vec_id").toPandas()["embedding"]), np.stack(db.orderBy("vec_id").toPandas()["embedding"])
    best = np.sort(a @ b.T, axis=1)[:, ::-1][:, :5]
    assert np.allclose(exact.sort_values(["query_id", "rank"])["score"].to_numpy().reshape(-1, 5), best)
    s = QuantizerSpec("ball_block", "unbiased", D, 3, 4, assign="top")
    found = topk(q, encode(db, s), s, 64)
    r = {x["k"]: x["recall"] for x in M.recall_at(exact_topk(q, db, 1), found, (1, 4, 64)).collect()}
    assert r[1] <= r[4] <= r[64] and r[64] >= 0.95
    p = pairs(q, db, QuantizerSpec("ball_block", "unbiased", D, 3, 2)).agg(F.count("*"), F.avg(F.expr("pow(ip_hat - ip, 2)"))).first()
    assert p[0] == len(a) * len(b) and p[1] * (D - 1) == pytest.approx(0.11, rel=0.15)


def test_best_rows_break_ties_by_id():
    score, ids = np.array([[1.0], [2.0], [2.0], [2.0], [0.0]]), np.array([5, 9, 3, 7, 1])
    r, _ = best_rows(score, ids, 2)
    assert ids[r].tolist() == [3, 7]


def test_recall_grows_with_bits(spark, sf):
    q, db = split(read_vectors(spark, sf), 10)
    exact, got = exact_topk(q, db, 1), []
    for b in (1, 2, 4):
        s = QuantizerSpec("sphere_scalar", "unbiased", D, 1, b)
        got.append(M.recall_at(exact, topk(q, encode(db, s), s, 8), (8,)).first()["recall"])
    assert got[0] < got[1] <= got[2]


def test_spark_fit_of_a_codebook(spark):
    from rotquant.functions.codebooks import ball_block, distortion, sample_block

    z = sample_block(2, D, 40_000, 9)
    assert distortion(z, fit_block_book(spark, D, 2, 2, n=40_000, rounds=12, parts=4)) == pytest.approx(distortion(z, ball_block(D, 2, 2)), rel=0.04)


def test_sql_functions(spark, sf):
    s = QuantizerSpec("ball_block", "unbiased", D, 3, 2)
    register_functions(spark, s)
    read_vectors(spark, sf).createOrReplaceTempView("vectors")
    spark.sql("SELECT vec_id, embedding, e.* FROM (SELECT vec_id, embedding, rq_encode(embedding) AS e FROM vectors)").createOrReplaceTempView("coded")
    r = spark.sql("SELECT avg(rq_score(code, rho, zbar_sq, norm, embedding)) AS own, avg(size(rq_decode(code, rho, zbar_sq, norm))) AS d FROM coded").first()
    assert r["own"] == pytest.approx(1, abs=1e-6) and r["d"] == D
    assert spark.sql("SELECT count(*) FROM codebook_table('ball_block', 64, 2, 2)").first()[0] == 16
    assert spark.sql("SELECT count(*) FROM rotation_table(8, 1)").first()[0] == 64
    assert spark.sql("SELECT value FROM theory_table(64) WHERE method = 'ball_block' AND p = 3 AND b = 2 AND criterion = 'mse'").first()[0] == 0.101
