"""Shared plumbing: tables, durable intermediates and Arrow batch maps."""

from __future__ import annotations

import atexit
import ctypes
import tempfile
import uuid
from collections.abc import Callable, Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

#: Rows that Arrow hands over at once. Texts have no bound, so a batch of Spark's default size may not fit.
BATCH_ROWS = 1000
#: Rows handled at once inside a Python worker, whatever the Arrow batch size is.
SLICE_ROWS = 256


def table(spark: SparkSession, sf_dir: str, name: str, *cols: str) -> DataFrame:
    """A test table with only the columns that are asked for."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*cols) if cols else df


_made: dict[str, str] = {}


def shared_dir(spark: SparkSession) -> str:
    """A folder of this application below spark.checkpoint.dir.

    The setting comes from the session; only where neither it nor a checkpoint
    folder is set (tests on one machine) is a temporary folder used.
    """
    sc = spark.sparkContext
    app = sc.applicationId
    if app not in _made:
        base = spark.conf.get("spark.checkpoint.dir", None)
        if not base:
            known = sc._jsc.sc().getCheckpointDir()
            base = known.get() if known.isDefined() else "file://" + tempfile.mkdtemp(prefix="rotquant-")
        _made[app] = f"{base.rstrip('/')}/rotquant-{app}"
        atexit.register(_drop, spark, _made[app])
    return _made[app]


def _drop(spark: SparkSession, path: str) -> None:
    sc = spark.sparkContext
    if sc._jsc is None:
        return
    try:
        p = sc._jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(sc._jsc.hadoopConfiguration()).delete(p, True)
    except Exception as e:  # the session is already down; say so and leave the folder
        print(f"left {path}: {type(e).__name__}")


def written(df: DataFrame, scratch: Scratch | None = None) -> DataFrame:
    """df written as Parquet in the shared folder and read back.

    It cuts the lineage with replicated storage behind it: executors that are lost
    later cost a re-read, not a recomputation. With a scratch it lives until that is dropped.
    """
    path = f"{scratch.path if scratch else shared_dir(df.sparkSession)}/{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


class Scratch:
    """A folder for intermediates that only the work inside a with-block reads.

    What leaves the block has to be written elsewhere before it ends.
    """

    def __init__(self, spark: SparkSession):
        self.spark, self.path = spark, f"{shared_dir(spark)}/{uuid.uuid4().hex}"

    def __enter__(self) -> Scratch:
        return self

    def __exit__(self, *_) -> None:
        _drop(self.spark, self.path)


_caches: dict[str, Callable[[], None]] = {}
_working: list[str] = []


def claim(name: str, clear: Callable[[], None] | None = None) -> None:
    """Says which operator works in this Python worker now: the caches of the others are emptied.

    Workers live on between tasks and take turns, and a cache that only another stage uses
    would take memory from this one. What was freed goes back to the system.
    """
    if clear is not None:
        _caches[name] = clear
    if _working == [name]:
        return
    for other, empty in _caches.items():
        if other != name:
            empty()
    if _working:
        pa.default_memory_pool().release_unused()
        trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
        if trim is not None:
            trim(0)
    _working[:] = [name]


def small_batches(spark: SparkSession) -> None:
    """Lowers the session's Arrow batch size to BATCH_ROWS, if it is larger."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    now = int(spark.conf.get(key))
    if now <= 0 or now > BATCH_ROWS:
        spark.conf.set(key, str(BATCH_ROWS))


def map_slices(
    df: DataFrame,
    schema: str | T.StructType,
    start: Callable[[], Callable[[dict[str, list]], dict[str, list]]],
    rows: int = SLICE_ROWS,
) -> DataFrame:
    """Map df in slices of bounded size through Python.

    ``start()`` runs once per task and returns the function for one slice: a dict of
    column lists in, a dict of column lists (any length) out.
    """
    out = T._parse_datatype_string(schema) if isinstance(schema, str) else schema
    arrow = to_arrow_schema(out)
    small_batches(df.sparkSession)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        f = start()
        for batch in batches:
            for at in range(0, batch.num_rows, rows):
                part = batch.slice(at, rows)
                got = f({n: part.column(i).to_pylist() for i, n in enumerate(part.schema.names)})
                arrays = [pa.array(got[x.name], type=x.type) for x in arrow]
                if len(arrays[0]):
                    yield pa.RecordBatch.from_arrays(arrays, schema=arrow)

    return df.mapInArrow(run, out)
