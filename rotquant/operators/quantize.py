"""Encoding and decoding of DataFrames. Rows are mapped where they lie; nothing is shuffled."""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.codebooks import ball_block
from ..functions.packing import packed_rows, unpacked_rows
from ..model import CODES, RECON, SKETCHED, QuantizerSpec, quarantined
from . import arrow as A
from .codec import Codec, codec

ROWS = 4096


def shipped(spark: SparkSession, spec: QuantizerSpec):
    """The fitted codec, made once on the driver and broadcast; its size depends on the spec only."""
    return spark.sparkContext.broadcast(codec(spec))


def encode(df: DataFrame, spec: QuantizerSpec, id_col: str = "vec_id", vec_col: str = "embedding") -> DataFrame:
    """codes of every sound vector; the others are dropped here and can be had from quarantined()."""
    sent, signs = shipped(df.sparkSession, spec), spec.codebook == "sphere_scalar_signbit"
    good, _ = quarantined(df.select(F.col(id_col).cast("long").alias("vec_id"), F.col(vec_col).cast("array<double>").alias("v")), spec.d, "v")

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c: Codec = sent.value
        for batch in batches:
            for at in range(0, batch.num_rows, ROWS):
                part = batch.slice(at, ROWS)
                e = c.encode(A.matrix(part.column("v")))
                cols = [part.column("vec_id"), pa.array(e["norm"]), A.lists(e["code"], pa.int32()), pa.array(e["rho"]), pa.array(e["zbar_sq"])]
                names = ["vec_id", "norm", "code", "rho", "zbar_sq"]
                if signs:
                    cols += [A.lists(e["signs"], pa.int32()), pa.array(e["rnorm"])]
                    names += ["signs", "rnorm"]
                yield pa.RecordBatch.from_arrays(cols, names)

    return good.mapInArrow(run, SKETCHED if signs else CODES)


def as_codes(batch: pa.RecordBatch) -> dict[str, np.ndarray]:
    out = {"norm": A.vector(batch.column("norm")), "code": A.matrix(batch.column("code"), np.int64), "rho": A.vector(batch.column("rho")), "zbar_sq": A.vector(batch.column("zbar_sq"))}
    if "signs" in batch.schema.names:
        out["signs"], out["rnorm"] = A.matrix(batch.column("signs"), np.int64), A.vector(batch.column("rnorm"))
    return out


def decode(codes: DataFrame, spec: QuantizerSpec) -> DataFrame:
    """vec_id and reconstruction of each code row."""
    sent = shipped(codes.sparkSession, spec)

    def run(batches):
        c: Codec = sent.value
        for batch in batches:
            if batch.num_rows:
                yield pa.RecordBatch.from_arrays([batch.column("vec_id"), A.lists(c.decode(as_codes(batch)), pa.float64())], ["vec_id", "xhat"])

    return codes.mapInArrow(run, RECON)


def code_bits(spec: QuantizerSpec) -> list[int]:
    """Bits of each entry of a code."""
    return [spec.b * s for _, s in spec.layout] if spec.codebook != "sphere_scalar_signbit" else [max(spec.b - 1, 0)] * spec.width


def pack_codes(codes: DataFrame, spec: QuantizerSpec) -> DataFrame:
    """codes with code as bytes: exactly the spec's bits, filled up to a whole byte a row."""
    bits = code_bits(spec)

    def run(batches):
        for batch in batches:
            if batch.num_rows:
                rows = packed_rows(A.matrix(batch.column("code"), np.int64), bits)
                yield pa.RecordBatch.from_arrays([batch.column(n) for n in batch.schema.names if n != "code"] + [pa.array(rows, type=pa.binary())], [n for n in batch.schema.names if n != "code"] + ["packed"])

    kept = [f"{f.name} {f.dataType.simpleString()}" for f in codes.schema if f.name != "code"]
    return codes.mapInArrow(run, ", ".join([*kept, "packed binary"]))


def unpack_codes(packed: DataFrame, spec: QuantizerSpec) -> DataFrame:
    bits = code_bits(spec)

    def run(batches):
        for batch in batches:
            if batch.num_rows:
                code = unpacked_rows(batch.column("packed").to_pylist(), bits)
                yield pa.RecordBatch.from_arrays([batch.column(n) for n in batch.schema.names if n != "packed"] + [A.lists(code, pa.int32())], [n for n in batch.schema.names if n != "packed"] + ["code"])

    kept = [f"{f.name} {f.dataType.simpleString()}" for f in packed.schema if f.name != "packed"]
    return packed.mapInArrow(run, ", ".join([*kept, "code array<int>"]))


def fit_block_book(spark: SparkSession, d: int, p: int, b: int, n: int = 200_000, rounds: int = 10, parts: int = 8, seed: int = 0):
    """The block codebook by Spark jobs: draws are made in the tasks, sums of 2^(bp) rows come back each round."""
    from ..functions.codebooks import means, nearest, sample_block

    book, k = np.array(ball_block(d, p, 1)) if b == 1 else _spread(d, p, b), 2 ** (b * p)
    for _ in range(rounds):
        sent = spark.sparkContext.broadcast(book)

        def run(batches, sent=sent):
            for batch in batches:
                for i in batch.column("id").to_pylist():
                    z = sample_block(p, d, n // parts // 2, seed * parts + i)
                    z = np.concatenate([z, -z])
                    s, m = means(z, nearest(z, sent.value), k)
                    yield pa.RecordBatch.from_arrays([pa.array(np.arange(k)), A.lists(s, pa.float64()), pa.array(m)], ["code", "s", "m"])

        sums = spark.range(0, parts, 1, parts).mapInArrow(run, "code long, s array<double>, m double")
        rows = sums.select("code", "m", *[F.col("s")[j].alias(f"s{j}") for j in range(p)]).groupBy("code").agg(F.sum("m").alias("m"), *[F.sum(f"s{j}").alias(f"s{j}") for j in range(p)]).collect()
        for r in rows:
            if r["m"] > 0:
                book[r["code"]] = [r[f"s{j}"] / r["m"] for j in range(p)]
    return book


def _spread(d: int, p: int, b: int) -> np.ndarray:
    from ..functions.codebooks import sample_block, spread_start

    return spread_start(sample_block(p, d, 20_000, 1), 2 ** (b * p), 1)


class Quantizer:
    """A spec with its session: what a user holds."""

    def __init__(self, spec: QuantizerSpec, spark: SparkSession):
        self.spec, self.spark = spec, spark

    def fit(self) -> Quantizer:
        codec(self.spec)  # rotation and codebook; no data is read
        return self

    def encode(self, df: DataFrame, id_col: str = "vec_id", vec_col: str = "embedding") -> DataFrame:
        return encode(df, self.spec, id_col, vec_col)

    def decode(self, codes: DataFrame) -> DataFrame:
        return decode(codes, self.spec)

    def pairs(self, queries: DataFrame, codes: DataFrame) -> DataFrame:
        from .search import pairs

        return pairs(queries, codes, self.spec)

    def topk(self, queries: DataFrame, codes: DataFrame, k: int) -> DataFrame:
        from .search import topk

        return topk(queries, codes, self.spec, k)

    def encode_stream(self, stream: DataFrame, id_col: str = "vec_id", vec_col: str = "embedding") -> DataFrame:
        return encode(stream, self.spec, id_col, vec_col)
