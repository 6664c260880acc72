"""The quantizers from SQL: functions of a spec, and tables of its artifacts."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from ..model import QuantizerSpec
from ..operators.codec import codec
from . import theory
from .codebooks import ball_block, gauss_scalar, sphere_scalar
from .rotation import haar_rotation


def register_functions(spark: SparkSession, spec: QuantizerSpec) -> None:
    """rq_encode(vec), rq_decode(code, rho, zbar_sq, norm), rq_score(code, rho, zbar_sq, norm, query) for the spec, and
    codebook_table, rotation_table and theory_table for FROM clauses."""
    from ..operators.quantize import shipped

    sent = shipped(spark, spec)

    @F.pandas_udf("code array<int>, rho double, zbar_sq double, norm double")
    def rq_encode(vec: pd.Series) -> pd.DataFrame:
        e = sent.value.encode(np.stack(vec.to_numpy()).astype(float))
        return pd.DataFrame({"code": list(e["code"].astype(np.int32)), "rho": e["rho"], "zbar_sq": e["zbar_sq"], "norm": e["norm"]})

    def codes(code, rho, zbar_sq, norm):
        return {"code": np.stack(code.to_numpy()).astype(np.int64), "rho": rho.to_numpy(), "zbar_sq": zbar_sq.to_numpy(), "norm": norm.to_numpy()}

    @F.pandas_udf("array<double>")
    def rq_decode(code: pd.Series, rho: pd.Series, zbar_sq: pd.Series, norm: pd.Series) -> pd.Series:
        return pd.Series(list(sent.value.decode(codes(code, rho, zbar_sq, norm))))

    @F.pandas_udf("double")
    def rq_score(code: pd.Series, rho: pd.Series, zbar_sq: pd.Series, norm: pd.Series, query: pd.Series) -> pd.Series:
        c = sent.value
        y = c.rotate(np.stack(query.to_numpy()).astype(float))
        e = codes(code, rho, zbar_sq, norm)
        return pd.Series((c.values(e["code"]) * y).sum(axis=1) * c.scale(e["rho"], e["zbar_sq"]) * e["norm"])

    for f in (rq_encode, rq_decode, rq_score):
        spark.udf.register(f.__name__, f)
    for name, f in (("codebook_table", CodebookTable), ("rotation_table", RotationTable), ("theory_table", TheoryTable)):
        spark.udtf.register(name, f)


@F.udtf(returnType="code int, o array<double>")
class CodebookTable:
    def eval(self, family: str, d: int, p: int, b: int):
        book = ball_block(d, p, b) if family == "ball_block" else (gauss_scalar if family == "gauss_scalar" else sphere_scalar)(b, d)[:, None]
        for i, o in enumerate(book.tolist()):
            yield i, o


@F.udtf(returnType="row int, col int, v double")
class RotationTable:
    def eval(self, d: int, seed: int):
        for i, r in enumerate(haar_rotation(d, seed).tolist()):
            for j, v in enumerate(r):
                yield i, j, v


@F.udtf(returnType="criterion string, method string, p int, b int, value double")
class TheoryTable:
    def eval(self, d: int):
        for r in theory.table(d):
            yield r["criterion"], r["method"], r["p"], r["b"], r["value"]



