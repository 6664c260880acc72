"""Specs, schemas and the checks on input vectors."""

from __future__ import annotations

import hashlib
import json
from dataclasses import asdict, dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

CODEBOOKS = ("gauss_scalar", "sphere_scalar", "grid_dir", "ball_block", "full_sphere", "sphere_scalar_signbit")
RESCALES = ("raw", "best", "unbiased")
CODES = "vec_id long, norm double, code array<int>, rho double, zbar_sq double"
SKETCHED = CODES + ", signs array<int>, rnorm double"
RECON = "vec_id long, xhat array<double>"
PAIRS = "query_id long, vec_id long, ip double, ip_hat double"
TOPK = "query_id long, rank int, vec_id long, score double"


@dataclass(frozen=True)
class QuantizerSpec:
    """A codebook and a dequantization rule, with everything that decoding needs."""

    codebook: str
    rescale: str = "raw"
    d: int = 64
    p: int = 1
    b: int = 2
    seed: int = 0
    assign: str = "exact"  # exact, top (approximate lists), safe (exact lists); for grid_dir: sweep, ladder
    tail: str = "mixed"  # mixed, error, pad: what to do when p does not divide d
    cells: int = 32
    n_cand: int = 16
    rotation: str = "haar"

    def __post_init__(self):
        if self.codebook not in CODEBOOKS:
            raise ValueError(f"unknown codebook {self.codebook}")
        if self.codebook == "sphere_scalar_signbit" and self.rescale != "raw":
            raise ValueError("the sign-bit sketch has its own estimator; it takes no rescaling")
        if self.rescale not in RESCALES:
            raise ValueError(f"unknown rescaling {self.rescale}")
        if self.b < 1 or self.d < 2 or self.p < 1 or self.p > self.d:
            raise ValueError("b and p must be positive, d at least 2, p at most d")
        if self.codebook == "ball_block" and self.tail == "error" and self.d % self.p:
            raise ValueError(f"block size {self.p} does not divide {self.d}")
        if self.codebook == "full_sphere" and self.b * self.d > 16:
            raise ValueError("full_sphere needs b * d of 16 at most")

    @property
    def width(self) -> int:
        """Dimensions that are rotated and coded: d, or d with padding."""
        if self.codebook == "ball_block" and self.tail == "pad":
            return -(-self.d // self.p) * self.p
        return self.d

    @property
    def layout(self) -> list[tuple[int, int]]:
        """(first coordinate, size) of each block; sizes other than p appear where p does not divide the width."""
        if self.codebook == "full_sphere":
            return [(0, self.d)]
        if self.codebook != "ball_block":
            return [(i, 1) for i in range(self.d)]
        w, p = self.width, self.p
        whole, rest = divmod(w, p)
        sizes = [p] * whole + ([rest] if rest else [])
        if rest == 1 and p == 3 and whole:  # two blocks of two instead of three and one
            sizes = [3] * (whole - 1) + [2, 2]
        starts, out = 0, []
        for s in sizes:
            out.append((starts, s))
            starts += s
        return out

    @property
    def spec_id(self) -> str:
        return hashlib.sha1(self.to_json().encode()).hexdigest()[:12]

    def to_json(self) -> str:
        return json.dumps(asdict(self), sort_keys=True)

    @staticmethod
    def from_json(text: str) -> QuantizerSpec:
        return QuantizerSpec(**json.loads(text))


def sound(vec: Column, d: int) -> Column:
    """Whether a vector can be coded: d finite components, not all zero."""
    fine = F.forall(vec, lambda x: x.isNotNull() & ~F.isnan(x.cast("double")) & (F.abs(x.cast("double")) < F.lit(float("inf"))))
    return vec.isNotNull() & (F.size(vec) == d) & fine & F.exists(vec, lambda x: x != 0)


def quarantined(df: DataFrame, d: int, vec: str = "embedding") -> tuple[DataFrame, DataFrame]:
    """(rows that can be coded, the others)."""
    ok = F.coalesce(sound(F.col(vec), d), F.lit(False))
    return df.where(ok), df.where(~ok)


def normalize(df: DataFrame, vec: str = "embedding") -> DataFrame:
    """df with norm and the unit direction in place of vec; a zero vector stays as it is and is flagged."""
    x = F.transform(vec, lambda v: v.cast("double"))
    norm = F.sqrt(F.aggregate(x, F.lit(0.0), lambda a, v: a + v * v))
    out = df.withColumn("norm", norm)
    return out.withColumn("is_zero", F.col("norm") == 0).withColumn(vec, F.when(F.col("norm") > 0, F.transform(x, lambda v: v / F.col("norm"))).otherwise(x))
