"""Token counts from an exact length histogram.

Documents are encoded once and reduced to a histogram of encoded length; suffix sums over
it answer, for every context limit, how many documents are longer, how many tokens there
are in all, how many remain when each document is cut at the limit, and which quantile the
limit is. The histogram has at most one row for each distinct length, so nothing that is
shuffled after the map-side sums depends on the number of documents.

Defined cases: a null or empty text has length 0 (plus the end id if asked for); equal
documents count each; an empty table gives an empty histogram; other columns are ignored.
"""

from __future__ import annotations

from bisect import bisect_right

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import map_slices, written
from .wordbpe import encoder, public_path

#: Lengths that share one row of the coarse level of the suffix sums.
SPAN = 1024


def with_lengths(docs: DataFrame, path: str | None = None, text: str = "text", end_id: bool = False) -> DataFrame:
    """(n_tokens) of each document, in no order."""
    path = path or public_path()

    def start():
        enc = encoder(path)
        return lambda c: {"n_tokens": [len(x) // 4 + end_id for x in enc.encode(c["text"])]}

    return map_slices(docs.select(F.col(text).cast("string").alias("text")), "n_tokens long", start)


def length_histogram(lengths: DataFrame, col: str = "n_tokens") -> DataFrame:
    """Histogram with suffix sums: one row for each length that occurs, taken as a limit.

    n_docs: of exactly this length; docs_over, tokens_over: of greater length; total_docs,
    total_tokens: of all; truncated_total: tokens left if every document is cut at this
    length; quantile: share of documents no longer than it. Sums are made in two levels,
    spans of lengths and lengths in a span, so no task reads the whole histogram.
    """
    h = written(lengths.groupBy(F.col(col).alias("length")).agg(F.count("*").alias("n_docs")))  # both levels read it; texts are encoded once
    h = h.withColumn("span", F.floor(F.col("length") / SPAN)).withColumn("tok", F.col("length") * F.col("n_docs"))
    after = Window.orderBy(F.desc("span")).rowsBetween(Window.unboundedPreceding, -1)
    every = Window.partitionBy()
    coarse = (
        h.groupBy("span").agg(F.sum("n_docs").alias("d"), F.sum("tok").alias("t"))
        .select(
            "span",
            F.coalesce(F.sum("d").over(after), F.lit(0)).alias("d_after"),
            F.coalesce(F.sum("t").over(after), F.lit(0)).alias("t_after"),
            F.sum("d").over(every).alias("total_docs"), F.sum("t").over(every).alias("total_tokens"),
        )
    )
    inside = Window.partitionBy("span").orderBy(F.desc("length")).rowsBetween(Window.unboundedPreceding, -1)
    fine = h.withColumn("d_in", F.coalesce(F.sum("n_docs").over(inside), F.lit(0))).withColumn(
        "t_in", F.coalesce(F.sum("tok").over(inside), F.lit(0))
    )
    return fine.join(coarse, "span").select(
        "length", "n_docs", (F.col("d_in") + F.col("d_after")).alias("docs_over"), (F.col("t_in") + F.col("t_after")).alias("tokens_over"),
        "total_docs", "total_tokens",
    ).withColumn("truncated_total", F.col("total_tokens") - F.col("tokens_over") + F.col("length") * F.col("docs_over")).withColumn(
        "quantile", (F.col("total_docs") - F.col("docs_over")) / F.col("total_docs")
    )


class LengthTable:
    """Answers for any limit from a histogram's rows (bounded by the longest document)."""

    def __init__(self, histogram: DataFrame):
        rows = sorted(histogram.collect(), key=lambda r: r["length"])
        self.lengths = [r["length"] for r in rows]
        self.rows = rows
        self.docs = rows[0]["total_docs"] if rows else 0
        self.tokens = rows[0]["total_tokens"] if rows else 0

    def truncated(self, limit: int) -> int:
        """Tokens that remain when every document is cut at limit."""
        i = bisect_right(self.lengths, limit) - 1
        if i < 0:
            return limit * self.docs
        r = self.rows[i]
        return self.tokens - r["tokens_over"] + limit * r["docs_over"]

    def over(self, limit: int) -> int:
        """Documents longer than limit."""
        i = bisect_right(self.lengths, limit) - 1
        return self.docs if i < 0 else self.rows[i]["docs_over"]

    def quantile(self, share: float) -> int | None:
        """The smallest length that at least this share of the documents does not exceed."""
        return next((r["length"] for r in self.rows if self.docs - r["docs_over"] >= share * self.docs), None)


def op1_token_counts(spark, sf_dir: str) -> DataFrame:
    from .common import table

    return length_histogram(with_lengths(table(spark, sf_dir, "documents", "text")))
