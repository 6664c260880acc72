"""Block codebooks learned from data: the contrast to fixed ones. Nothing else uses them."""

from __future__ import annotations

import numpy as np
from pyspark.ml.clustering import KMeans
from pyspark.ml.functions import array_to_vector
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def trained_books(vectors: DataFrame, d: int, p: int, b: int, seed: int = 0, rounds: int = 15) -> list[np.ndarray]:
    """One codebook of 2^(bp) centroids for each block of p coordinates, by k-means over the table (one fit a block)."""
    books = []
    for a in range(0, d - d % p, p):
        x = vectors.select(array_to_vector(F.slice("embedding", a + 1, p)).alias("features"))
        books.append(np.array(KMeans(k=2 ** (b * p), seed=seed, maxIter=rounds).fit(x).clusterCenters()))
    return books


def trained_error(vectors: DataFrame, books: list[np.ndarray], p: int) -> DataFrame:
    """vec_id, err: squared error of the blocks under their learned codebooks."""
    import pyarrow as pa

    from ..functions.codebooks import nearest
    from . import arrow as A

    sent = vectors.sparkSession.sparkContext.broadcast(books)

    def run(batches):
        for batch in batches:
            if batch.num_rows:
                x, err = A.matrix(batch.column("embedding")), np.zeros(batch.num_rows)
                for j, book in enumerate(sent.value):
                    z = x[:, j * p : j * p + p]
                    err += ((z - book[nearest(z, book)]) ** 2).sum(axis=1)
                yield pa.RecordBatch.from_arrays([batch.column("vec_id"), pa.array(err)], ["vec_id", "err"])

    return vectors.select("vec_id", "embedding").mapInArrow(run, "vec_id long, err double")
