"""Rotation and scalar codes as built-in expressions only, for users who want no Python in the plan."""

from __future__ import annotations

import json

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.codebooks import gauss_scalar, sphere_scalar
from ..functions.rotation import haar_rotation


def rotate_relational(vectors: DataFrame, d: int, seed: int) -> DataFrame:
    """vec_id, z: each row of the rotation, a literal of d * d numbers, times the vector. Rows stay where they are."""
    r = F.from_json(F.lit(json.dumps(haar_rotation(d, seed).tolist())), "array<array<double>>")
    return vectors.select("vec_id", F.transform(r, lambda row: dot(row, "embedding")).alias("z"))


def scalar_codes(rotated: DataFrame, family: str, b: int, d: int) -> DataFrame:
    """vec_id, code: how many thresholds each coordinate exceeds."""
    q = (gauss_scalar if family == "gauss_scalar" else sphere_scalar)(b, d)
    cuts = [float(c) for c in (q[1:] + q[:-1]) / 2]

    def code(v: Column) -> Column:
        return sum((F.when(v > c, 1).otherwise(0) for c in cuts), F.lit(0))

    return rotated.select("vec_id", F.transform("z", code).alias("code"))


def dot(a: Column | str, b: Column | str) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, v: s + v)


#: Bytes of queries that a nested-loop join may broadcast.
QUERY_BYTES = 64 << 20


def exact_pairs(queries: DataFrame, database: DataFrame) -> DataFrame:
    """query_id, vec_id, ip of all pairs with a stated query set, by built-in expressions: a broadcast nested-loop join.

    The size of the query side is checked; larger sets go through search.topk or metrics.pair_sums, which take them in blocks.
    """
    size = queries.agg(F.sum(8 * F.size("embedding"))).first()[0] or 0
    if size > QUERY_BYTES:
        raise ValueError(f"{size} bytes of queries are more than the {QUERY_BYTES} that may be broadcast")
    q = queries.select(F.col("vec_id").alias("query_id"), F.col("embedding").alias("q"))
    return database.join(F.broadcast(q)).select("query_id", "vec_id", dot("embedding", "q").alias("ip"))
