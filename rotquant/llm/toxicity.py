"""Toxicity by a bidirectional recurrent network over all overlapping windows of a text.

The network (see ``gru``) is trained on the driver from a bounded sample of labelled rows:
at most ``sample`` texts of at most ``TRAIN_CHARS`` characters whose crc32(doc_id as text)
mod 4 is not 2. It scores every window of every whole text; a text's score is its highest
window's. Only the text enters a score.

Defined cases: null or empty texts and texts without words score 0; equal texts score
equal; rows without a label only get scores; without labels, or with one class only,
every text of words gets the same score; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import claim, map_slices, table
from .gru import Network, TextScorer, train

SAMPLE = 4500
TRAIN_CHARS = 20_000
HELD_OUT = 2
THRESHOLD = 0.3


def held_out(doc_id) -> object:
    return F.coalesce(F.crc32(doc_id.cast("string")) % 4 == HELD_OUT, F.lit(False))


def training_rows(docs: DataFrame, labels: DataFrame, sample: int) -> tuple[list[str], list[int]]:
    """Texts and labels for training, a third of them toxic where there are enough."""
    known = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("toxic").cast("int").alias("toxic")).where("toxic IN (0, 1) AND doc_id IS NOT NULL")
    known = known.where(~held_out(F.col("doc_id")))
    count = {r["toxic"]: r["n"] for r in known.groupBy("toxic").agg(F.count("*").alias("n")).collect()}
    want = {1: sample // 3, 0: sample - sample // 3}
    share = F.when(F.col("toxic") == 1, min(1.0, want[1] / max(1, count.get(1, 0)))).otherwise(min(1.0, want[0] / max(1, count.get(0, 0))))
    some = known.where(F.pmod(F.xxhash64("doc_id"), F.lit(1 << 20)) < F.lit(1 << 20) * share).limit(2 * sample)
    rows = (
        docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
        .join(F.broadcast(some), "doc_id")  # at most 2 * sample rows
        .where((F.length("text") <= TRAIN_CHARS) & (F.length(F.trim("text")) > 0)).select("doc_id", "text", "toxic").limit(2 * sample).collect()
    )
    rows = sorted({(r["doc_id"], r["text"], r["toxic"]) for r in rows if r["text"].split()})
    return [r[1] for r in rows], [r[2] for r in rows]


def fit(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE, **options) -> Network:
    return train(*training_rows(docs, labels, sample), **options)


def toxicity(docs: DataFrame, net: Network, threshold: float = THRESHOLD) -> DataFrame:
    """doc_id, held_out, score, predicted of each row."""
    sent = docs.sparkSession.sparkContext.broadcast(net.p)  # of fixed size

    def start():
        claim("toxicity")
        own = Network()
        own.p = sent.value
        scorer = TextScorer(own)
        return lambda c: {"doc_id": c["doc_id"], "score": scorer.scores(c["text"])}

    slim = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    scored = map_slices(slim, "doc_id long, score double", start, rows=128)
    return scored.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))


def op4_toxicity(spark, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    return toxicity(docs, fit(docs, table(spark, sf_dir, "labels", "doc_id", "toxic")))
