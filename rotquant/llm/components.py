"""Connected components of an edge table, by alternating star contractions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Scratch, written


#: Most nodes whose minima are broadcast.
BROADCAST_NODES = 500_000


def components(edges: DataFrame, a: str = "a", b: str = "b", scratch: Scratch | None = None) -> DataFrame:
    """(node, component) of every node that has an edge; component is its smallest node.

    Each round hangs a node's larger neighbours, then its smaller ones, onto the smallest
    node in its neighbourhood; every round is written out, so lost executors cost a re-read.
    Minima are combined before they are shuffled, and up to a bound they are broadcast to the
    edges, so that a hub does not gather in one task; beyond it AQE splits a hub that is skewed.
    """
    now = written(edges.select(F.least(a, b).alias("u"), F.greatest(a, b).alias("v")).where("u < v").distinct(), scratch)
    while True:
        both = now.select(F.col("v").alias("n"), F.col("u").alias("m")).unionByName(now.select(F.col("u").alias("n"), F.col("v").alias("m")))
        low = both.groupBy("n").agg(F.min("m").alias("m0")).select("n", F.least("n", "m0").alias("low"))
        low = written(low, scratch)
        low = F.broadcast(low) if low.count() <= BROADCAST_NODES else low
        # larger neighbours to the lowest of the neighbourhood
        large = both.where("m > n").join(low, "n").select(F.col("low").alias("u"), F.col("m").alias("v"))
        large = large.where("u < v").distinct()
        # a node and its smaller neighbours to the lowest of those
        low2 = large.groupBy("v").agg(F.min("u").alias("low"))
        small = large.join(low2, "v").select(F.explode(F.array(F.struct(F.col("low").alias("u"), "v"), F.struct(F.col("low").alias("u"), F.col("u").alias("v")))).alias("e"))
        nxt = written(small.select("e.u", "e.v").where("u < v").distinct(), scratch)
        # a set of stars is a fixed point: every larger end occurs once and is never a smaller end
        stars = nxt.groupBy("v").agg(F.count("*").alias("k")).where("k > 1").limit(1).count() == 0
        if stars and nxt.select(F.col("u").alias("v")).join(nxt.select("v"), "v", "left_semi").limit(1).count() == 0:
            return nxt.select(F.col("v").alias("node"), F.col("u").alias("component")).unionByName(
                nxt.select(F.col("u").alias("node"), F.col("u").alias("component")).distinct()
            )
        now = nxt
