"""Codes of streams. Codebooks are fixed before any row arrives, so encoding keeps no state."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..model import QuantizerSpec
from ..operators.quantize import encode
from ..sources.stores import append_batch


def encode_stream(vectors: DataFrame, spec: QuantizerSpec) -> DataFrame:
    return encode(vectors, spec)


def write_stream(codes: DataFrame, spec: QuantizerSpec, path: str, checkpoint: str):
    """Starts a query that writes every batch of codes once."""
    return codes.writeStream.option("checkpointLocation", checkpoint).foreachBatch(append_batch(path, spec)).start()


def growing_cache(codes: DataFrame) -> DataFrame:
    """seq_id, cached, batches: codes per sequence so far. codes has seq_id and code.

    The state of a sequence is the number of its codes and of the batches that brought some; the codes themselves go to the sink.
    """

    def step(key, frames: Iterator[pd.DataFrame], state: GroupState):
        cached, batches = state.get if state.exists else (0, 0)
        cached, batches = cached + sum(len(f) for f in frames), batches + 1
        state.update((cached, batches))
        yield pd.DataFrame({"seq_id": [key[0]], "cached": [cached], "batches": [batches]})

    return codes.groupBy("seq_id").applyInPandasWithState(step, "seq_id long, cached long, batches long", "cached long, batches long", "update", GroupStateTimeout.NoTimeout)
