"""Coding and attention in fewer steps: the results are those of the plain ways."""

import hashlib

import numpy as np
import pytest

from rotquant.functions.lookup import cells
from rotquant.operators import cache as C
from rotquant.operators import codec as K


def test_states_are_hashed_many_at_once(monkeypatch):
    """Digests of short tokens come from array steps; long ones and any characters give the same states as the library's."""
    words = ["a", "ß", "\ud800", "x" * 45, *("y" * n for n in range(46, 60)), "z" * 300]

    def plain(w, kind, head):
        name = f"{w}:{kind}{head}:".encode("utf-8", "surrogatepass")
        x = np.frombuffer(b"".join(hashlib.md5(name + str(g).encode()).digest() for g in range(32)), ">u4") / 4294967296.0 - 0.5
        return x * C.channel_scales(head) if kind == "k" else x

    for kind in "kvq":
        assert (C.states(words, kind, 1) == np.array([plain(w, kind, 1) for w in words])).all()
    want = C.states(words[:3], "v", 0)
    monkeypatch.setattr(C.hashlib, "md5", None)
    assert (C.states(words[:3], "v", 0) == want).all() and C.states([], "k", 0).shape == (0, C.WIDTH)


def test_grid_words_are_found_with_ties(monkeypatch):
    """Equal coordinates, zeros and rows in several parts; every word that a scale rounds to is tried by hand."""
    g = np.random.default_rng(5)
    z = np.vstack([g.standard_normal((20, 8)), np.repeat(g.standard_normal((5, 4)), 2, axis=1), np.eye(8), g.integers(-2, 3, (20, 8)) + 0.0])
    z = z[(z != 0).any(axis=1)]
    z /= np.linalg.norm(z, axis=1, keepdims=True)
    monkeypatch.setattr(K, "SWEEP", 100)
    for b in (1, 2, 3):
        top = 2 ** (b - 1) - 1
        got = K.grid_sweep(z, b) - (2.0 ** (b - 1) - 0.5)
        for row, word in zip(z, got):
            a = np.abs(row)
            steps = np.unique([k / x for k in range(1, top + 1) for x in a[a > 0]] + [0.0])
            words = [np.minimum(np.floor(a * s * (1 + 1e-12)), top) + 0.5 for s in steps]
            best = max((w @ a) / np.linalg.norm(w) for w in words)
            assert (row @ word) / np.linalg.norm(word) == pytest.approx(best, abs=1e-12)


def test_few_words_of_a_list_are_compared():
    """A cell's list is shortened to words that can be its closest; what is found is the first closest of the whole list."""
    g = np.random.default_rng(6)
    for mode in ("top", "safe"):
        c = cells(64, 3, 2, 8, mode, 16)
        z = np.vstack([g.standard_normal((20_000, 3)) / 8, np.round(g.standard_normal((2000, 3)) * 8) / 64])  # points on the cells' borders too
        z = z[(z >= -c.half).all(axis=1) & (z < c.half).all(axis=1)]
        at = np.floor((z + c.half) * (c.per_axis / (2 * c.half))).astype(int)
        cand = c.lists[at @ (c.per_axis ** np.arange(2, -1, -1))]
        cost = (c.book * c.book).sum(axis=1)[cand] / 2 - np.einsum("ni,nci->nc", z, c.book[cand])
        found = np.take_along_axis(cost, (cand == c.assign(z)[:, None]).argmax(axis=1)[:, None], axis=1)[:, 0]
        assert np.allclose(found, cost.min(axis=1), atol=1e-14) and c.counts.mean() < c.sizes.mean()


def test_attention_does_not_depend_on_how_pairs_come(monkeypatch):
    """Common and rare tokens, large logits, many tokens of one sequence: sums are those of a softmax for each sequence."""
    import pyarrow as pa

    g = np.random.default_rng(7)
    ids, words = np.arange(40) * 3, [f"w{i:02}" for i in range(60)]
    rows = sorted((w, int(i), int(g.integers(1, 9))) for j, w in enumerate(words) for i in ids if g.random() < (0.9 if j < 20 else 0.05) or i == 0)
    q = g.standard_normal((len(ids), C.WIDTH)) * 40
    monkeypatch.setattr(C, "TOKENS", 7)
    for rare in (1, 3, 1 << 20):  # tokens of all sequences, of a third of them, and all tokens are common
        monkeypatch.setattr(C, "RARE", rare)
        sums, count = {"exact": C.Attended(len(ids))}, np.zeros(len(ids))
        for a in range(0, len(rows), 100):
            t = rows[a : a + 100]
            C._attended(pa.table({"token": [r[0] for r in t], "seq_id": [r[1] for r in t], "n": [r[2] for r in t]}), ids, q, 0, {}, sums, count)
        for j, i in enumerate(ids):
            mine = [r for r in rows if r[1] == i]
            k, v = (C.states([r[0] for r in mine], kind, 0) for kind in "kv")
            n, logit = np.array([r[2] for r in mine]), k @ q[j]
            w = n * np.exp(logit - logit.max())
            assert count[j] == n.sum() and np.allclose(sums["exact"].out()[j], w @ v / w.sum(), rtol=1e-9, atol=1e-12)


def test_heads_and_seeds_are_tasks_of_their_own(spark):
    """Few sequences make one block; its heads and seeds still do not wait for each other in one task."""
    tokens = spark.createDataFrame([(i, p, f"w{(i * p) % 7}") for i in range(5) for p in range(20)], "seq_id long, pos long, token string")
    specs = {f"gauss_scalar:{k}": C.CacheSpec("gauss_scalar", 1, seed=k) for k in range(2)}
    out = C.errors_by_sequence(tokens, C.outlier_channels(tokens), specs)
    assert out.rdd.getNumPartitions() >= 2 * C.HEADS
    assert sorted((r["seq_id"], r["head"], r["method"]) for r in out.collect()) == sorted((i, h, m) for i in range(5) for h in range(C.HEADS) for m in specs)


def test_rows_are_rotated_once_for_all_methods(monkeypatch):
    """Methods with one rotation share the rotated rows; their left sides are those they have alone."""
    from rotquant.model import QuantizerSpec
    from rotquant.operators import search as R

    x = np.random.default_rng(8).standard_normal((50, 128))
    specs = [QuantizerSpec("gauss_scalar", "unbiased", 128, 1, 2), QuantizerSpec("grid_dir", "unbiased", 128, 1, 3), QuantizerSpec("sphere_scalar_signbit", "raw", 128, 1, 2), QuantizerSpec("gauss_scalar", "unbiased", 128, 1, 2, seed=1)]
    caches = [C.KeyValueCache(C.CacheSpec(f, 1, seed=k), {0: np.arange(32) + k}) for f in ("gauss_scalar", "grid_dir") for k in range(2)]
    methods = [K.codec(s) for s in specs] + caches
    alone = [R.left(c, x) for c in methods]
    calls, rotate = [], K.Codec.rotate
    monkeypatch.setattr(K.Codec, "rotate", lambda self, rows: calls.append(self.turn) or rotate(self, rows))
    shared = {}
    assert all((R.left(c, x, shared) == a).all() for c, a in zip(methods, alone))
    assert len(calls) == 2 + 2 * 2  # two seeds of codecs, two parts for each of two seeds of caches
