"""Input tables and the vectors derived from them."""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


def read_table(spark: SparkSession, sf_dir: str, name: str, *cols: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*cols) if cols else df


def read_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """vec_id, embedding in double."""
    return read_table(spark, sf_dir, "embeddings", "vec_id", "embedding").withColumn("embedding", F.col("embedding").cast("array<double>"))


class TokenSlots(dict):
    """Coordinate and sign of a token from its md5 digest; the words met first are kept."""

    def __init__(self, d: int, keep: int = 400_000):
        super().__init__()
        self.d, self.keep = d, keep

    def __missing__(self, token: str) -> int:
        h = hashlib.md5(token.encode("utf-8", "surrogatepass")).hexdigest()
        x = int(h[:8], 16) % self.d
        x = x if int(h[8], 16) % 2 == 0 else -x - 1  # negative numbers stand for a minus sign
        if len(self) < self.keep:
            self[token] = x
        return x


def hashed(tokens: list[str], slots: TokenSlots) -> np.ndarray:
    at = np.fromiter(map(slots.__getitem__, tokens), dtype=np.int64, count=len(tokens))
    plus, minus = at[at >= 0], -at[at < 0] - 1
    return (np.bincount(plus, minlength=slots.d) - np.bincount(minus, minlength=slots.d)).astype(float)


#: What separates tokens, the same for every engine that must agree.
BLANKS = " \t\n\f\r"


def tokens(text: str | None) -> list[str]:
    if not text:
        return []
    return [x for x in text.lower().translate(_TO_BLANK).split(" ") if x]


_TO_BLANK = {ord(c): " " for c in BLANKS}


def hashed_rows(texts: list[str | None], slots: TokenSlots) -> tuple[np.ndarray, np.ndarray]:
    """Unit vectors of the texts that have one, and which these are."""
    v = np.array([hashed(tokens(t), slots) for t in texts]).reshape(len(texts), slots.d)
    n = np.sqrt((v * v).sum(axis=1))
    ok = n > 0
    return v[ok] / n[ok, None], ok


def text_vectors(docs: DataFrame, d: int, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """vec_id, embedding of unit length: signed hashed counts of the tokens. Texts whose counts cancel, or without tokens, give no row."""

    def run(batches):
        slots = TokenSlots(d)
        for batch in batches:
            for at in range(0, batch.num_rows, 512):
                part = batch.slice(at, 512)
                v, ok = hashed_rows(part.column("t").to_pylist(), slots)
                yield pa.RecordBatch.from_arrays([part.column("i").filter(pa.array(ok)), _lists(v)], ["vec_id", "embedding"])

    return docs.select(F.col(id_col).cast("long").alias("i"), F.col(text_col).alias("t")).mapInArrow(run, "vec_id long, embedding array<double>")


def _lists(v: np.ndarray) -> pa.Array:
    from ..operators.arrow import lists

    return lists(v, pa.float64()) if len(v) else pa.array([], type=pa.list_(pa.float64()))


VECTOR_SCHEMA = T.StructType([T.StructField("vec_id", T.LongType()), T.StructField("embedding", T.ArrayType(T.DoubleType()))])


def read_stream(spark: SparkSession, folder: str, schema: T.StructType = VECTOR_SCHEMA, glob: str = "*.parquet", files: int = 1) -> DataFrame:
    """A folder that grows, as a stream."""
    return spark.readStream.schema(schema).option("pathGlobFilter", glob).option("maxFilesPerTrigger", files).parquet(folder)
