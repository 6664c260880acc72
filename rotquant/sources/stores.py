"""Codes and artifacts on disk. A folder of codes holds its spec, so another job can decode it."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession

from ..functions.codebooks import ball_block
from ..functions.rotation import haar_rotation
from ..model import QuantizerSpec
from ..operators.quantize import pack_codes, unpack_codes


def write_codes(codes: DataFrame, spec: QuantizerSpec, path: str) -> None:
    """Packed codes, in order of id within each file, and the spec beside them."""
    pack_codes(codes, spec).sortWithinPartitions("vec_id").write.mode("overwrite").option("compression", "zstd").parquet(f"{path}/codes")
    codes.sparkSession.createDataFrame([(spec.to_json(),)], "value string").coalesce(1).write.mode("overwrite").text(f"{path}/spec")


def read_codes(spark: SparkSession, path: str) -> tuple[DataFrame, QuantizerSpec]:
    spec = QuantizerSpec.from_json(spark.read.text(f"{path}/spec").first()[0])
    return unpack_codes(spark.read.parquet(f"{path}/codes"), spec), spec


def append_batch(path: str, spec: QuantizerSpec):
    """A foreachBatch function that writes each batch once, however often it is tried."""

    def write(batch: DataFrame, batch_id: int) -> None:
        pack_codes(batch, spec).write.mode("overwrite").parquet(f"{path}/codes/batch={batch_id}")

    return write


def rotation_frame(spark: SparkSession, d: int, seed: int) -> DataFrame:
    """row, col, v."""
    r = haar_rotation(d, seed)
    i, j = np.indices(r.shape)
    return spark.createDataFrame(list(zip(i.ravel().tolist(), j.ravel().tolist(), r.ravel().tolist())), "row int, col int, v double")


def codebook_frame(spark: SparkSession, d: int, p: int, b: int) -> DataFrame:
    """code, o."""
    return spark.createDataFrame([(i, o) for i, o in enumerate(ball_block(d, p, b).tolist())], "code int, o array<double>")
