"""Exact top-k inner products by reading sorted lists in step, without random access.

Candidates are dealt to shards of bounded size and queries to blocks of bounded size; each
(shard, block) pair is one group. In a group every dimension is a list of its candidates
sorted by component. A query reads each list from the end its own sign prefers, a stretch
at a time, from the start on. What has been read gives a candidate's lower bound (the rest of
its dimensions at the worst value of their lists) and upper bound (the rest at the lists'
present fronts). Reading stops when no candidate outside the best k can reach the k-th lower
bound. The lists are then read on until the last entry of those k has come up, which resolves
their final scores. A group returns k rows a query, and a window over the groups' winners
ranks them.

Between two stretches bounds are compared for a block of queries at once; a query with few
candidates left compares only theirs. With many dimensions of like weight bounds part late: most
of each list is read before a query can stop.

Components are floor(scale * x) as integers, so scores are exact and ties go to the smaller
id. Defined cases: vectors that are null, or hold null or non-finite components, take no
part; vectors of another length than the query's never meet it; repeated vectors each
count; rows that repeat the query's id are the query's own; fewer than k candidates give fewer
rows; an empty table gives none; other columns, whatever their names, are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import table, written

SHARD_ROWS = 4096
BLOCK_ROWS = 1024
#: Shares of each list that have been read when bounds are compared.
STRETCHES = (1 / 2, 7 / 8, 31 / 32, 127 / 128, 511 / 512, 1.0)
#: A query whose candidates are at most this share of all compares only theirs, so many pairs at once.
FEW, PAIRS = 1 / 16, 1 << 15


class SortedLists:
    """One list per dimension over the candidates of a shard.

    What a query has read of a list is a share from one of its ends, and the end depends on
    the sign of the query's component only. So each stretch has two tables of what its read and
    unread entries are worth at least, and two of what they are worth at most, and the
    bounds of all queries of a block are products with their positive and negative parts.
    """

    def __init__(self, vectors: np.ndarray):
        n = len(vectors)
        order = np.argsort(vectors, axis=0, kind="stable")
        rank = np.empty_like(order)
        np.put_along_axis(rank, order, np.broadcast_to(np.arange(n)[:, None], order.shape), axis=0)
        self.vectors, self.rank, self.sorted = vectors, rank, np.take_along_axis(vectors, order, axis=0)

    def bounds(self, share: float, kind) -> tuple[np.ndarray, np.ndarray]:
        """Tables for lower and upper bounds once this share of every list is read."""
        x, n = self.vectors, len(self.vectors)
        upto = min(n, int(np.ceil(share * n)))
        from_top, from_bottom = self.rank >= n - upto, self.rank < upto
        low, high = self.sorted[0], self.sorted[-1]
        front_top, front_bottom = self.sorted[n - upto], self.sorted[upto - 1]
        pair = lambda a, b: np.hstack([np.where(from_top, x, a), np.where(from_bottom, x, b)]).astype(kind).T
        return pair(low, high), pair(front_top, front_bottom)

    def top(self, queries: np.ndarray, query_ids: np.ndarray, ids: np.ndarray, k: int) -> tuple[list[tuple[np.ndarray, np.ndarray]], np.ndarray]:
        """(ids, scores) of each query's k best candidates other than itself; the share of the lists it read."""
        n, d = self.vectors.shape
        largest = float(np.abs(self.vectors).max(initial=0)) * float(np.abs(queries).max(initial=0)) * d
        kind = np.float32 if largest < 2**24 else np.float64  # sums of whole numbers stay exact
        signed = np.hstack([np.maximum(queries, 0), np.minimum(queries, 0)]).astype(kind)
        own = query_ids[:, None] == ids[None, :]
        want = np.minimum(k, n - own.sum(axis=1))
        out, read = [(ids[:0], ids[:0])] * len(queries), np.zeros(len(queries))
        many = np.flatnonzero(want > 0)  # queries with many candidates left; of the others the pairs that are left
        q, c = np.empty(0, np.int64), np.empty(0, np.int64)
        for share in STRETCHES:
            lower_table, upper_table = self.bounds(share, kind)
            if len(many):
                lower = signed[many] @ lower_table
                lower[own[many]] = -np.inf
                kth = np.partition(lower, n - k, axis=1)[:, n - k] if n > k else np.full(len(many), -np.inf)
                kth = np.where(want[many] < k, -np.inf, kth)
                upper = signed[many] @ upper_table
                alive = (upper >= kth[:, None]) & ~own[many]
                few = (alive.sum(axis=1) <= max(4 * k, n * FEW)) | (share == 1)
                row, cand = np.nonzero(alive[few])
                q, c = np.concatenate([q, many[few][row]]), np.concatenate([c, cand])
                many = many[~few]
            lower, upper = self._pairs(signed, q, c, lower_table), self._pairs(signed, q, c, upper_table)
            order = np.lexsort((ids[c], -lower, q))
            q, c, lower, upper = q[order], c[order], lower[order], upper[order]
            first = np.searchsorted(q, q)  # where the pairs of the same query begin
            kth = lower[np.minimum(first + want[q], np.searchsorted(q, q, side="right")) - 1]
            keep = upper >= kth if share < 1 else np.arange(len(q)) - first < want[q]
            q, c = q[keep], c[keep]
            left = np.bincount(q, minlength=len(queries))
            done = left[q] == want[q]
            self._resolve(queries, q[done], c[done], ids, out, read, share)
            q, c = q[~done], c[~done]
            if not len(q) and not len(many):
                break
        return out, read

    def _pairs(self, signed: np.ndarray, q: np.ndarray, c: np.ndarray, table: np.ndarray) -> np.ndarray:
        rows = table.T
        parts = [np.einsum("pd,pd->p", signed[q[i : i + PAIRS]], rows[c[i : i + PAIRS]]) for i in range(0, len(q), PAIRS)]
        return np.concatenate(parts) if parts else np.empty(0, signed.dtype)

    def _resolve(self, queries: np.ndarray, q: np.ndarray, c: np.ndarray, ids: np.ndarray, out: list, read: np.ndarray, share: float) -> None:
        """Scores of the winners (c) of queries (q, in order), once the lists have been read down to their last entries."""
        n = len(self.vectors)
        for a in range(0, len(q), PAIRS):
            i, j = q[a : a + PAIRS], c[a : a + PAIRS]
            depth = np.where(queries[i] >= 0, n - self.rank[j], self.rank[j] + 1) * (queries[i] != 0)
            np.maximum.at(read, i, np.maximum(share, depth.max(axis=1) / n))
        score = np.concatenate([np.einsum("pd,pd->p", queries[q[a : a + PAIRS]], self.vectors[c[a : a + PAIRS]]) for a in range(0, len(q), PAIRS)]) if len(q) else q
        order = np.lexsort((ids[c], -score, q))
        q, c, score = q[order], c[order], score[order]
        at = np.flatnonzero(np.diff(q, prepend=-1))
        for x, y in zip(at, [*at[1:], len(q)]):
            out[q[x]] = (ids[c[x:y]], score[x:y])


def whole_components(vectors: DataFrame, scale: int) -> DataFrame:
    """(vec_id, v): integer components of the vectors that take part."""
    x = F.col("embedding")
    fine = F.col("vec_id").isNotNull() & x.isNotNull() & (F.size(x) > 0) & F.forall(
        x, lambda e: e.isNotNull() & ~F.isnan(e.cast("double")) & (F.abs(e.cast("double")) < F.lit(float("inf")))
    )
    return vectors.where(fine).select(
        F.col("vec_id").cast("long").alias("vec_id"), F.transform(x, lambda e: F.floor(F.lit(float(scale)) * e.cast("double")).cast("long")).alias("v")
    )


def top_k(vectors: DataFrame, is_query, k: int = 20, scale: int = 64, shard_rows: int = SHARD_ROWS, block_rows: int = BLOCK_ROWS, shares: bool = False) -> DataFrame:
    """query_id, rank, vec_id, score of each query's k best other rows; if asked for, also the
    largest share of a shard's lists that the query read."""
    rows = written(whole_components(vectors, scale).withColumn("q", is_query))
    total = rows.agg(F.count("*").alias("n"), F.count(F.when(F.col("q"), 1)).alias("m")).first()
    shards, blocks = max(1, -(-total["n"] // shard_rows)), max(1, -(-total["m"] // block_rows))
    spread = F.xxhash64("vec_id")
    every = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    cands = rows.select(F.pmod(spread, F.lit(shards)).cast("int").alias("shard"), every(blocks).alias("block"), "vec_id", "v")
    asks = rows.where("q").select(every(shards).alias("shard"), F.pmod(spread, F.lit(blocks)).cast("int").alias("block"), F.col("vec_id").alias("ask"), F.col("v").alias("w"))

    def split(t: pa.Table, name: str, vector: str) -> dict[int, tuple[np.ndarray, np.ndarray]]:
        """Ids and vectors by width."""
        v = t.column(vector).combine_chunks()
        ids, width, flat = t.column(name).to_numpy(), np.diff(v.offsets.to_numpy()), v.flatten().to_numpy()
        at = np.repeat(width, width)
        return {int(w): (ids[width == w], flat[at == w].reshape(-1, w)) for w in np.unique(width)}

    def run(_, left: pa.Table, right: pa.Table) -> pa.Table:
        rows = [(np.empty(0, np.int64),) * 3 + (np.empty(0),)]
        have = split(left, "vec_id", "v") if len(left) and len(right) else {}
        for w, (query_ids, queries) in (split(right, "ask", "w") if have else {}).items():
            if w in have:
                ids, vectors = have[w]
                got, read = SortedLists(vectors).top(queries, query_ids, ids, k)
                rows += [(np.full(len(i), q), i, s, np.full(len(i), r)) for q, (i, s), r in zip(query_ids, got, read)]
        kinds = {"query_id": pa.int64(), "vec_id": pa.int64(), "score": pa.int64(), "read": pa.float64()}
        return pa.table({n: pa.array(np.concatenate(x), type=t) for (n, t), x in zip(kinds.items(), zip(*rows))})

    won = cands.groupBy("shard", "block").cogroup(asks.groupBy("shard", "block")).applyInArrow(run, "query_id long, vec_id long, score long, read double")
    if not shares:
        won = won.drop("read")
    best = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    read = [F.max("read").over(Window.partitionBy("query_id")).alias("read")] if shares else []
    return won.select("*", F.row_number().over(best).cast("int").alias("rank"), *[x.alias("most") for x in read]).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score", *[F.col("most").alias("read")] * shares)


def op8_topk(spark, sf_dir: str) -> DataFrame:
    return top_k(table(spark, sf_dir, "embeddings", "vec_id", "embedding"), F.col("vec_id") % 20 == 0)


OP8_SQL = """
WITH v AS (
  SELECT CAST(vec_id AS BIGINT) AS vec_id,
         list_transform(embedding, lambda x: CAST(floor(64 * CAST(x AS DOUBLE)) AS BIGINT)) AS v
  FROM embeddings
  WHERE embedding IS NOT NULL AND len(embedding) > 0
    AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(CAST(x AS DOUBLE)))) = 0
), s AS (
  SELECT q.vec_id AS query_id, c.vec_id,
         CAST(list_sum(list_transform(list_zip(q.v, c.v), lambda p: p[1] * p[2])) AS BIGINT) AS score
  FROM v q JOIN v c ON q.vec_id <> c.vec_id AND len(q.v) = len(c.v)
  WHERE q.vec_id % 20 = 0
), r AS (
  SELECT query_id, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank, vec_id, score FROM s
)
SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 20
"""
