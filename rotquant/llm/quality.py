"""Quality from weak labels: heuristic labellers, their accuracies by expectation-maximisation,
and a hashed linear scorer trained on the posteriors.

1. Each labeller votes good, bad or nothing on a text, from counts over the whole text.
2. The corpus is reduced to counts of vote patterns (at most 3 to the number of labellers).
   Expectation-maximisation over these counts, which lose nothing, gives every labeller's
   distribution of votes in each class, and so the posterior of every pattern.
3. The scorer is linear in hashed words, hashed word shapes (letter runs, digits and
   marks) and hashed traits of the text. It learns the posteriors of a bounded sample of texts and scores all of them.

Votes overlap and abstain freely; the labellers' accuracies are never given. Defined cases:
null or empty texts and texts without words score 0 and are rejected; equal texts score
equal; very long texts are read whole; an empty table gives an empty result; other columns
do not matter.
"""

from __future__ import annotations

import math
import operator
import re
from itertools import islice

import numpy as np
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import claim, map_slices, small_batches, table

BAD, NONE, GOOD = 0, 1, 2
#: Frequent short words of the languages that are served.
COMMON = frozenset(
    "the of and to in is that it was for on are as with be by this have from at or an not "
    "le la les de des du et un une en que qui est pour dans sur par au avec il elle "
    "der die das und den von zu mit sich auf ist im dem nicht ein eine für "
    "el los las del y que es en por con una para se su al lo como más".split()
)
_PUNCT = bytes(i for i in range(33, 127) if chr(i) in "#$%&*+/<=>@\\^_`{|}~[]")
_UPPER = bytes(range(65, 91))
_LOWER = bytes(range(97, 123))
_DIGITS = bytes(range(48, 58))


def _share(data: bytes, what: bytes) -> float:
    return (len(data) - len(data.translate(None, what))) / max(1, len(data))


def statistics(text: str, words: list[str]) -> tuple[float, ...]:
    """What the labellers look at, and the number of lines."""
    data, n = text.encode("utf-8", "surrogatepass"), len(words)
    lines = [x for x in text.split("\n") if x.strip()] or [text]
    upper, lower = _share(data, _UPPER), _share(data, _LOWER)
    return (
        _share(data, _PUNCT), upper / max(1e-9, upper + lower), data.count(b"!!") / n, data.count(b"|") / n,
        sum(map(COMMON.__contains__, words)) / n, len(text) / n, 1 - len(set(lines)) / len(lines),
        sum(map(operator.eq, words, islice(words, 1, None))) / n, len(set(words)) / n, _share(data, _DIGITS), len(lines),
    )


LABELLERS = ("symbols", "capitals", "bangs", "bars", "common words", "word length", "repeated lines", "echo", "distinct words", "digits")


def votes(text: str | None) -> list[int]:
    """One vote of each labeller."""
    if not text or not (words := text.split()):
        return [BAD] * len(LABELLERS)
    return voted(statistics(text, words), len(words))


def voted(stats: tuple[float, ...], n: int) -> list[int]:
    symbols, upper, bangs, bars, known, mean, repeated, echo, distinct, digits, lines = stats
    vote = lambda bad, good: BAD if bad else GOOD if good else NONE
    return [
        vote(symbols > 0.06, symbols < 0.004),
        vote(upper > 0.3, upper < 0.1),
        vote(bangs > 0.05, bangs < 0.001),
        vote(bars > 0.1, bars < 0.001),
        vote(known < 0.04 and n >= 20, known > 0.1),
        vote(mean > 14 or mean < 3, 4 < mean < 9),
        vote(repeated > 0.4 and lines >= 4, repeated < 0.1),
        vote(echo > 0.2 and n >= 8, echo < 0.05),
        vote(distinct < 0.15 and n >= 40, distinct > 0.4),
        vote(digits > 0.25, digits < 0.03),
    ]


def pattern(text: str | None) -> int:
    code = 0
    for v in votes(text):
        code = 3 * code + v
    return code


def unpacked(codes: np.ndarray) -> np.ndarray:
    return np.stack([codes // 3**i % 3 for i in range(len(LABELLERS) - 1, -1, -1)], axis=1)


class VoteModel:
    """Class shares and each labeller's votes by class, from counted patterns."""

    def __init__(self, counts: dict[int, int], rounds: int = 200, prior: float = 1.0):
        codes = np.array(sorted(counts), dtype=np.int64)
        n = np.array([counts[c] for c in codes.tolist()], dtype=float)
        v = unpacked(codes)
        # the start: a text is good unless some labeller has found a fault
        good = 1 / (1 + np.exp(6.0 * (v == BAD).sum(1) - 3.0))
        for _ in range(rounds):
            self.share = float((n @ good + prior) / (n.sum() + 2 * prior))
            self.table = np.zeros((2, v.shape[1], 3))
            for k, w in enumerate((n * (1 - good), n * good)):
                for x in (BAD, GOOD):
                    self.table[k, :, x] = w @ (v == x) + prior
            self.table /= self.table.sum(axis=2, keepdims=True)
            self.table[:, :, NONE] = 1.0  # a vote that is not cast is no evidence
            new = self.posterior(codes)
            if np.abs(new - good).max() < 1e-9:
                break
            good = new
        #: share of the votes it casts that agree with the class, per labeller
        self.accuracy = self.share * self.table[1, :, GOOD] + (1 - self.share) * self.table[0, :, BAD]

    def posterior(self, codes: np.ndarray) -> np.ndarray:
        v, i = unpacked(codes), np.arange(len(LABELLERS))
        logs = [math.log(s) + np.log(self.table[k][i, v]).sum(1) for k, s in enumerate((1 - self.share, self.share))]
        return 1 / (1 + np.exp(np.clip(logs[0] - logs[1], -500, 500)))


DIMENSIONS = 4096
SAMPLE = 4096
CACHE_WORDS = 150_000
_SHAPES = ((re.compile(r"[^\W\d_]*[a-zà-öø-ÿ][^\W\d_]*"), "a"), (re.compile(r"[^\W\d_]{2,}"), "A"), (re.compile(r"\d+"), "0"))


def slots(word: str) -> tuple[int, int]:
    """The word's and its shape's place in the weights."""
    shape = word
    for what, to in _SHAPES:
        shape = what.sub(to, shape)
    h = lambda s: xxhash.xxh32_intdigest(s.encode("utf-8", "surrogatepass")) % (DIMENSIONS // 2)
    return h(word.lower()), DIMENSIONS // 2 + h(shape)


class Slots(dict):
    def __missing__(self, word: str) -> tuple[int, int]:
        x = slots(word)
        if len(self) < CACHE_WORDS:
            self[word] = x
        return x


class Weights(dict):
    """The weight of a word, kept for the words that were met first."""

    def __init__(self, weights: np.ndarray):
        super().__init__()
        self.w = weights

    def __missing__(self, word: str) -> float:
        a, b = slots(word)
        x = float(self.w[a] + self.w[b])
        if len(self) < CACHE_WORDS:
            self[word] = x
        return x


def traits(stats: tuple[float, ...], n: int) -> list[int]:
    """Hashed slots of the text's own statistics, each cut into a few steps."""
    cuts = [sum(x > c for c in (0.002, 0.01, 0.05, 0.1, 0.2, 0.4, 0.7)) for x in stats[:5] + stats[6:10]]
    names = [f"{i}:{c}" for i, c in enumerate(cuts)] + [f"len:{min(20, int(stats[5]))}", f"n:{min(n, 64).bit_length()}"]
    return [DIMENSIONS // 2 + xxhash.xxh32_intdigest(x) % (DIMENSIONS // 2) for x in names]


def features(text: str, cache: Slots) -> np.ndarray:
    """Share of each word slot among the words, and the traits."""
    words = text.split()
    x = np.bincount(np.array([cache[w] for w in words], dtype=np.int64).ravel(), minlength=DIMENSIONS).astype(np.float32) / len(words)
    np.add.at(x, traits(statistics(text, words), len(words)), np.float32(0.1))
    return x


def train(x: np.ndarray, y: np.ndarray, rounds: int = 250, rate: float = 20.0, decay: float = 1e-5) -> tuple[np.ndarray, float]:
    """Logistic regression on soft labels, full batches with momentum."""
    w, b, vw, vb = np.zeros(x.shape[1], dtype=np.float32), 0.0, 0.0, 0.0
    for _ in range(rounds):
        g = (1 / (1 + np.exp(-np.clip(x @ w + b, -30, 30))) - y).astype(np.float32) / len(y)
        vw, vb = 0.9 * vw - rate * (x.T @ g + decay * w), 0.9 * vb - rate * 0.1 * float(g.sum())
        w, b = w + vw.astype(np.float32), b + vb
    return w, b


class Scorer:
    def __init__(self, weights: np.ndarray, bias: float):
        self.weights, self.bias = weights, bias

    def worker(self):
        claim("quality")
        cache = Weights(self.weights)
        look, at, bias = cache.__getitem__, self.weights.tolist().__getitem__, self.bias

        def score(text: str | None) -> float:
            words = text.split() if text else []
            if not words:
                return 0.0
            z = sum(map(look, words)) / len(words) + 0.1 * sum(map(at, traits(statistics(text, words), len(words)))) + bias
            return 1 / (1 + math.exp(-max(-30.0, min(30.0, z))))

        return score


def fit(docs: DataFrame, sample: int = SAMPLE) -> tuple[VoteModel, Scorer]:
    """The vote model from all texts, the scorer from at most ``sample`` of them, picked by hash."""
    texts = docs.select(F.col("text").cast("string").alias("text"))
    seen = map_slices(texts, "code long", lambda: lambda c: {"code": [pattern(t) for t in c["text"]]})
    counts = {r["code"]: r["n"] for r in seen.groupBy("code").agg(F.count("*").alias("n")).collect()}  # at most 3 ** len(LABELLERS) rows
    total = sum(counts.values())
    if not total:
        return VoteModel({pattern(None): 1}), Scorer(np.zeros(DIMENSIONS, dtype=np.float32), 0.0)
    model = VoteModel(counts)
    some = texts
    if total > sample // 2:
        some = texts.where(F.pmod(F.xxhash64("text"), F.lit(1 << 20)) < math.ceil((1 << 20) * min(1.0, 0.8 * sample / total)))

    def start():
        claim("quality")
        cache = Slots()

        def f(c):
            ts = [t for t in c["text"] if t and t.strip()]
            return {"code": [pattern(t) for t in ts], "x": [features(t, cache).tobytes() for t in ts]}

        return f

    rows = map_slices(some, "code long, x binary", start).limit(sample).collect()  # sample * 4 * DIMENSIONS bytes at most
    if not rows:
        return model, Scorer(np.zeros(DIMENSIONS, dtype=np.float32), 0.0)
    rows.sort(key=lambda r: (r["code"], bytes(r["x"])))
    x = np.stack([np.frombuffer(r["x"], dtype=np.float32) for r in rows])
    y = model.posterior(np.array([r["code"] for r in rows], dtype=np.int64))
    return model, Scorer(*train(x, y))


def quality_scores(docs: DataFrame, fitted: tuple[VoteModel, Scorer] | None = None, threshold: float = 0.5) -> DataFrame:
    """doc_id, score, posterior of its votes, and kept of each row."""
    model, scorer = fitted or fit(docs)

    def start():
        score = scorer.worker()

        def f(c):
            s = [score(t) for t in c["text"]]
            p = model.posterior(np.array([pattern(t) for t in c["text"]], dtype=np.int64)).tolist()
            return {"doc_id": c["doc_id"], "score": s, "posterior": p, "kept": [x >= threshold for x in s]}

        return f

    slim = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return map_slices(slim, "doc_id long, score double, posterior double, kept boolean", start)


def good_documents(docs: DataFrame, threshold: float = 0.5) -> DataFrame:
    """The documents that the scorer keeps, with all their columns, whatever their names.

    Null and empty texts go; repeated rows stay or go alike; an empty table stays empty.
    """
    _, scorer = fit(docs)
    small_batches(docs.sparkSession)

    def keep(batches):
        import pyarrow as pa

        score = scorer.worker()
        for b in batches:
            ok = [score(t) >= threshold for at in range(0, b.num_rows, 256) for t in b.column("text").slice(at, 256).to_pylist()]
            yield b.filter(pa.array(ok, type=pa.bool_()))

    return docs.mapInArrow(keep, docs.schema)


def op2_quality(spark, sf_dir: str) -> DataFrame:
    return quality_scores(table(spark, sf_dir, "documents", "doc_id", "text"))
