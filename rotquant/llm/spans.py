"""Digest columns of found spans, as the queries of secrets and personal data return them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def as_text(spans: Column) -> Column:
    """kind:start:end of each span, comma-joined."""
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def counted(spans: Column, kind: str) -> Column:
    return F.size(F.filter(spans, lambda s: s["kind"] == kind)).cast("long")


def digests(found: DataFrame, base: str | Column, every: str, kinds: tuple[str, ...]) -> DataFrame:
    """doc_id, a count of each kind and a digest of the base spans, and all spans as text."""
    base = F.col(base) if isinstance(base, str) else base
    return found.select(
        "doc_id", *(counted(base, k).alias(f"n_{k}") for k in kinds),
        F.sha2(as_text(base).cast("binary"), 256).alias("base_sha256"), as_text(F.col(every)).alias("spans"),
    )
