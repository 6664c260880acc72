"""A bidirectional gated recurrent network with attention pooling, in numpy.

A word enters as its own hashed embedding beside the mean of the hashed embeddings of its
character trigrams. Forward and backward recurrences read a window; attention weighs their
states; a linear layer gives the window's logit. Gradients are written out by hand and
checked against differences in the tests.
"""

from __future__ import annotations

from collections import Counter

import numpy as np
import xxhash

WORD_SLOTS, CHAR_SLOTS = 8192, 8192
WORD_DIM, CHAR_DIM, HIDDEN, ATTEND = 8, 8, 8, 8
WINDOW, STRIDE = 32, 24
#: Chance that a word is not left out of a training window: one that a single text has, others.
RARE_STAYS, OTHERS_STAY = 0.3, 0.9


def bare(word: str) -> str:
    return word.strip(".,;:!?\"'()[]").lower()


def word_slots(word: str) -> tuple[int, list[int]]:
    """Slots of the word and of its character trigrams."""
    marked = f"^{bare(word)}$".encode("utf-8", "surrogatepass")
    h = xxhash.xxh32_intdigest
    return h(marked) % WORD_SLOTS, [h(marked[i : i + 3]) % CHAR_SLOTS for i in range(max(1, len(marked) - 2))]


def windows(n: int) -> np.ndarray:
    """Word positions of every window of a text of n words; -1 past its end."""
    starts = np.arange(0, max(1, n - WINDOW + STRIDE), STRIDE)
    at = starts[:, None] + np.arange(WINDOW)
    return np.where(at < n, at, -1)


def _sigmoid(x):
    return 0.5 * np.tanh(0.5 * x) + 0.5


class Network:
    def __init__(self, seed: int = 7, dtype=np.float32):
        g = np.random.default_rng(seed)
        d, h = WORD_DIM + CHAR_DIM, HIDDEN
        n = lambda *shape, s=0.1: (g.standard_normal(shape) * s).astype(dtype)
        self.p = {
            "word": n(WORD_SLOTS, WORD_DIM), "char": n(CHAR_SLOTS, CHAR_DIM, s=0.2), "w": n(2, d, 3 * h, s=d**-0.5), "b": np.zeros((2, 1, 3 * h), dtype),
            "u": n(2, h, 3 * h, s=h**-0.5), "a": n(2 * h, ATTEND, s=h**-0.5), "c": np.zeros(ATTEND, dtype), "v": n(ATTEND, s=0.5), "o": n(2 * h, s=0.5), "e": np.full(1, -1.0, dtype),
        }

    def inputs(self, slots: list[tuple[int, list[int]]]) -> np.ndarray:
        """(words, WORD_DIM + CHAR_DIM) from slots of distinct words."""
        flat = np.concatenate([c for _, c in slots]) if slots else np.empty(0, dtype=np.int64)
        size = np.array([len(c) for _, c in slots])
        sums = np.add.reduceat(self.p["char"][flat], np.concatenate(([0], np.cumsum(size)[:-1])), axis=0) if slots else np.empty((0, CHAR_DIM), np.float32)
        return np.hstack([self.p["word"][[w for w, _ in slots]], sums / size[:, None].astype(sums.dtype)])

    def projected(self, x: np.ndarray) -> np.ndarray:
        """Both directions' gate inputs of each word: (2, words, 3 * HIDDEN)."""
        return x @ self.p["w"] + self.p["b"]

    def forward(self, gates: np.ndarray, at: np.ndarray, keep: bool = False):
        """Logits of windows; gates as from projected(), at: rows of gates by window and place, -1 for none."""
        p, h = self.p, HIDDEN
        n, steps = at.shape
        here = (at >= 0).astype(gates.dtype)
        states = np.zeros((2, steps, n, h), gates.dtype)
        kept = []
        for d in (0, 1):
            s = np.zeros((n, h), gates.dtype)
            for t in range(steps) if d == 0 else range(steps - 1, -1, -1):
                m = here[:, t : t + 1]
                if not keep and not m.any():
                    states[d, t] = s
                    continue
                x = gates[d].take(at[:, t], axis=0, mode="wrap")
                q = s @ p["u"][d]
                zr = _sigmoid(x[:, : 2 * h] + q[:, : 2 * h])
                z, r = zr[:, :h], zr[:, h:]
                c = np.tanh(x[:, 2 * h :] + r * q[:, 2 * h :])
                new = c + z * (s - c)
                if keep:
                    kept.append((d, t, m, s, z, r, c, q[:, 2 * h :]))
                s = s + m * (new - s)
                states[d, t] = s
        both = np.concatenate([states[0], states[1]], axis=2)  # steps, n, 2h
        e = np.tanh(both @ p["a"] + p["c"])
        scores = np.where(here.T > 0, e @ p["v"], np.asarray(-1e9, gates.dtype))
        scores -= scores.max(axis=0)
        w = np.exp(scores)
        w /= w.sum(axis=0)
        pooled = np.einsum("tn,tnk->nk", w, both)
        logit = pooled @ p["o"] + p["e"]
        return (logit, (at, here, kept, both, e, w, pooled)) if keep else logit

    def backward(self, gates: np.ndarray, x: np.ndarray, saved, dlogit: np.ndarray):
        """Gradients of everything but the embeddings, and of the words' inputs x."""
        at, here, kept, both, e, w, pooled = saved
        p, h, g = self.p, HIDDEN, {}
        g["o"], g["e"] = pooled.T @ dlogit, dlogit.sum(keepdims=True)
        dpool = dlogit[:, None] * p["o"]
        dboth = w[:, :, None] * dpool
        dw = np.einsum("tnk,nk->tn", both, dpool)
        ds = w * (dw - (w * dw).sum(axis=0))
        g["v"] = np.einsum("tn,tna->a", ds, e)
        de = ds[:, :, None] * p["v"] * (1 - e * e)
        g["c"], g["a"] = de.sum(axis=(0, 1)), np.einsum("tnk,tna->ka", both, de)
        dboth = dboth + de @ p["a"].T
        g["u"] = np.zeros_like(p["u"])
        dgates = np.zeros_like(gates)
        carry = [np.zeros((at.shape[0], h), gates.dtype) for _ in range(2)]
        for d, t, m, s, z, r, c, q in reversed(kept):
            dh = carry[d] + dboth[t, :, d * h : (d + 1) * h]
            dn = dh * m
            dz, dc = dn * (s - c), dn * (1 - z)
            da = dc * (1 - c * c)
            daz, dar = dz * z * (1 - z), da * q * r * (1 - r)
            dq = np.concatenate([daz, dar, da * r], axis=1)
            g["u"][d] += s.T @ dq
            carry[d] = dh * (1 - m) + dn * z + dq @ p["u"][d].T
            rows = at[:, t] >= 0
            np.add.at(dgates[d], at[rows, t], np.concatenate([daz, dar, da], axis=1)[rows])
        g["b"] = dgates.sum(axis=1, keepdims=True)
        g["w"] = np.stack([x.T @ dgates[d] for d in (0, 1)])
        return g, sum(dgates[d] @ p["w"][d].T for d in (0, 1))

    def spread(self, g: dict, slots: list[tuple[int, list[int]]], dx: np.ndarray) -> None:
        """Adds the embeddings' gradients to g."""
        g["word"], g["char"] = np.zeros_like(self.p["word"]), np.zeros_like(self.p["char"])
        np.add.at(g["word"], [w for w, _ in slots], dx[:, :WORD_DIM])
        size = np.array([len(c) for _, c in slots])
        np.add.at(g["char"], np.concatenate([c for _, c in slots]), np.repeat(dx[:, WORD_DIM:] / size[:, None], size, axis=0))


class Adam:
    def __init__(self, p: dict, rate: float):
        self.p, self.rate, self.t = p, rate, 0
        self.m = {k: np.zeros_like(v) for k, v in p.items()}
        self.v = {k: np.zeros_like(v) for k, v in p.items()}

    def step(self, g: dict) -> None:
        self.t += 1
        for k, x in g.items():
            self.m[k] += 0.1 * (x - self.m[k])
            self.v[k] += 0.01 * (x * x - self.v[k])
            self.p[k] -= (self.rate * (self.m[k] / (1 - 0.9**self.t)) / (np.sqrt(self.v[k] / (1 - 0.99**self.t)) + 1e-7)).astype(self.p[k].dtype)


class TextScorer:
    """Scores whole texts; words met first keep their gate inputs."""

    def __init__(self, net: Network, cap: int = 200_000, slots=word_slots):
        self.net, self.cap, self.slots = net, cap, slots
        self.row: dict[str, int] = {}
        self.gates = np.zeros((2, 0, 3 * HIDDEN), np.float32)

    def window_logits(self, texts: list[list[str]]) -> tuple[np.ndarray, np.ndarray]:
        """Logits of all windows of all texts, and the text each belongs to."""
        fresh: dict[str, int] = {}
        row, base = self.row, len(self.row)
        ids = []
        for words in texts:
            got = list(map(row.get, words))
            if None in got:
                got = [fresh.setdefault(w, base + len(fresh)) if i is None else i for i, w in zip(got, words)]
            ids.append(np.array(got, dtype=np.int64))
        gates = self.gates
        if fresh:
            new = self.net.projected(self.net.inputs([self.slots(w) for w in fresh])).astype(np.float32)
            gates = np.concatenate([gates, new], axis=1)
            if base + len(fresh) <= self.cap:
                row.update(fresh)
                self.gates = gates
        at, owner = [], []
        for k, i in enumerate(ids):
            if len(i):
                w = windows(len(i))
                at.append(np.where(w >= 0, i[w], -1))
                owner.append(np.full(len(w), k))
        if not at:
            return np.empty(0, np.float32), np.empty(0, np.int64)
        at, owner = np.concatenate(at), np.concatenate(owner)
        return np.concatenate([self.net.forward(gates, at[i : i + 2048]) for i in range(0, len(at), 2048)]), owner

    def scores(self, texts: list[str | None]) -> list[float]:
        """The highest window's probability; 0 for a text without words."""
        logit, owner = self.window_logits([t.split() if t else [] for t in texts])
        best = np.full(len(texts), -np.inf)
        np.maximum.at(best, owner, logit)
        return np.where(np.isfinite(best), 1 / (1 + np.exp(-np.clip(best, -60, 60))), 0.0).tolist()


def word_odds(words: list[list[str]], y: np.ndarray) -> dict[str, float]:
    """How far a word's share of the toxic texts exceeds its share of the clean ones, in standard deviations."""
    seen = [Counter(w for ws, label in zip(words, y) if label == c for w in set(map(bare, ws))) for c in (0, 1)]
    clean, toxic = max(1, int((y == 0).sum())), max(1, int((y == 1).sum()))
    out = {}
    for w in seen[0].keys() | seen[1].keys():
        both = (seen[0][w] + seen[1][w] + 1) / (clean + toxic + 2)
        out[w] = (seen[1][w] / toxic - seen[0][w] / clean) / (both * (1 - both) * (1 / clean + 1 / toxic)) ** 0.5
    return out


def train(texts: list[str], labels: list[int], rounds: int = 7, steps: int = 50, batch: int = 128, rate: float = 0.015, seed: int = 7) -> Network:
    """Windows are picked anew in each round: a text stands for its highest window, and clean
    texts also for a random one; half of the clean picks are those that look most toxic. Labels come with texts only, never with windows.
    Before the network has learned anything, a window is as high as the word in it that speaks most for a toxic text."""
    net, g = Network(seed), np.random.default_rng(seed)
    words = [t.split() for t in texts]
    slots_of = {w: word_slots(w) for ws in words for w in ws}
    y, texts_with = np.array(labels), Counter(w for ws in words for w in set(ws))
    stays = {w: RARE_STAYS if n == 1 else OTHERS_STAY for w, n in texts_with.items()}
    shape = [windows(len(w)) for w in words]
    adam = Adam(net.p, rate)
    pos, neg = np.flatnonzero(y == 1), np.flatnonzero(y == 0)
    if not len(pos) or not len(neg):
        net.p["e"][:] = 20.0 if len(pos) else -20.0
        net.p["o"][:] = 0
        return net
    speaks = word_odds(words, y)
    logit = np.concatenate([np.append(np.array([speaks[bare(w)] for w in ws]), -np.inf)[s].max(axis=1) for ws, s in zip(words, shape)])
    for k in range(rounds):
        if k:
            logit, owner = TextScorer(net, 1 << 30, slots_of.__getitem__).window_logits(words)
        first = np.concatenate(([0], np.cumsum([len(s) for s in shape])[:-1]))
        pick = []
        for i in range(len(words)):
            n = len(shape[i])
            top = int(logit[first[i] : first[i] + n].argmax())
            pick.append((i, top))
            if not y[i]:
                pick.append((i, int(g.integers(n))))
        by = [[x for x in pick if y[x[0]] == c] for c in (0, 1)]
        by[0].sort(key=lambda x: -logit[first[x[0]] + x[1]])  # clean windows that look toxic come first
        adam.rate = rate * (1 - k / rounds) + 1e-4
        for _ in range(steps):
            rows = [by[c][j] for c, top, n in ((0, 0.1, 0.3), (0, 1, 0.4), (1, 1, 0.3)) for j in g.integers(max(1, int(top * len(by[c]))), size=int(n * batch))]
            vocab: dict[str, int] = {}
            at = np.full((len(rows), WINDOW), -1)
            for r, (i, s) in enumerate(rows):
                for t, (j, luck) in enumerate(zip(shape[i][s].tolist(), g.random(WINDOW).tolist())):
                    if j >= 0 and luck < stays[words[i][j]]:
                        at[r, t] = vocab.setdefault(words[i][j], len(vocab))
            slots = [slots_of[w] for w in vocab]
            x = net.inputs(slots)
            gates = net.projected(x)
            out, saved = net.forward(gates, at, keep=True)
            target = y[[i for i, _ in rows]]
            dl = ((1 / (1 + np.exp(-np.clip(out, -30, 30))) - target) / len(rows)).astype(np.float32)
            grads, dx = net.backward(gates, x, saved, dl)
            net.spread(grads, slots, dx)
            adam.step(grads)
    return net
