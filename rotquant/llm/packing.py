"""Packing into fixed sequences by cutting stock.

A document's ids are cut into whole sequences, one body whose length is a multiple of
``grid`` and one tail shorter than ``grid``. Bodies and tails are two cutting-stock
problems over histograms with at most ``seq_len / grid`` and ``grid - 1`` sizes: the plan
(column generation, rounding, largest-first for the remainder) is made on the driver from
these bounded histograms. Pieces of one size are ranked, and the plan sends ranks to
sequence and offset by arithmetic, so the assignment is a map. Ranks come from counts of
(task, size) and one window over those counts; texts and ids are never shuffled.

Only sequences that rounding leaves are not full; their number is bounded by the number of
sizes. They are padded to ``seq_len``, except those whose length is a power of two.

Defined cases: a null or empty text is its end id alone; equal documents are packed each;
an empty table gives no piece; very long texts give many whole sequences; other columns do
not matter.
"""

from __future__ import annotations

import zlib

import numpy as np
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import map_slices, table, written
from .cutting import cutting_plan
from .wordbpe import encoder, public_path

SEQ_LEN = 4096
GRID = 16
END_ID = 2


def pieces(docs: DataFrame, path: str, seq_len: int, grid: int, end_id: int, with_ids: bool) -> DataFrame:
    """Pieces of each document with their rank among this task's pieces of the same size."""

    def start():
        enc, tail, part = encoder(path), np.uint32(end_id).tobytes(), TaskContext.get().partitionId()
        seen: dict[int, int] = {}

        def f(c):
            out = {n: [] for n in ("doc_id", "start", "length", "ids_crc32", "doc_tokens", "part", "local", "ids")}
            for doc, ids in zip(c["doc_id"], enc.encode(c["text"])):
                ids = memoryview(ids + tail)
                n = len(ids) // 4
                full, rest = divmod(n, seq_len)
                sizes = [seq_len] * full + [x for x in (rest // grid * grid, rest % grid) if x]
                at = 0
                for size in sizes:
                    own = ids[4 * at : 4 * (at + size)]
                    rank = seen.get(size, 0)
                    seen[size] = rank + 1
                    for k, v in zip(out, (doc, at, size, zlib.crc32(own), n, part, rank, np.frombuffer(own, dtype="<u4").tolist() if with_ids else None)):
                        out[k].append(v)
                    at += size
            return out

        return f

    kinds = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, part int, local long, ids array<long>"
    made = map_slices(docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")), kinds, start)
    return made if with_ids else made.drop("ids")


def pack(
    docs: DataFrame, path: str | None = None, seq_len: int = SEQ_LEN, grid: int = GRID, end_id: int = END_ID, with_ids: bool = False
) -> DataFrame:
    """One row per piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset,
    and the ids themselves if asked for."""
    if seq_len % grid:
        raise ValueError("grid must divide seq_len")
    slim = written(pieces(docs, path or public_path(), seq_len, grid, end_id, with_ids))
    counts = slim.groupBy("part", "length").agg(F.count("*").alias("n"))
    before = Window.partitionBy("length").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    offsets = counts.select("part", "length", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("first"))
    hist = {r["length"]: r["n"] for r in counts.groupBy("length").agg(F.sum("n").alias("n")).collect()}  # at most seq_len / grid + grid rows
    whole = hist.pop(seq_len, 0)
    body = cutting_plan({s // grid: n for s, n in hist.items() if s % grid == 0}, seq_len // grid)
    tail = cutting_plan({s: n for s, n in hist.items() if s % grid}, seq_len)

    def start():
        def f(c):
            size, rank = np.array(c["length"], dtype=np.int64), np.array(c["rank"], dtype=np.int64)
            seq, off = rank.copy(), np.zeros_like(rank)
            for s in np.unique(size):
                m = size == s
                if s % grid:
                    seq[m], off[m] = tail.locate(int(s), rank[m], whole + body.bins)
                elif s < seq_len:
                    bins, units = body.locate(int(s // grid), rank[m], whole)
                    seq[m], off[m] = bins, units * grid
            return c | {"sequence_id": seq.tolist(), "offset": off.tolist()}

        return f

    ranked = slim.join(offsets, ["part", "length"]).withColumn("rank", F.col("local") + F.col("first")).drop("part", "local", "first")
    kinds = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long" + ", ids array<long>" * with_ids
    return map_slices(ranked, kinds, start, rows=8192)


def op7_packing(spark, sf_dir: str) -> DataFrame:
    return pack(table(spark, sf_dir, "documents", "doc_id", "text"))
