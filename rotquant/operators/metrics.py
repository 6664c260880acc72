"""Accuracy and cost measures. Each reads its input once for all the specs compared."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.codebooks import nearest
from ..functions.packing import packed_rows
from ..model import QuantizerSpec, quarantined
from . import arrow as A
from .codec import Codec, codec
from .quantize import code_bits

ROWS = 2048
SCALARS = "method string, p int, b int, seed int, vec_id long, norm double, rho double, zbar_sq double"


def _rows(df: DataFrame, d: int, id_col: str, vec_col: str) -> DataFrame:
    return quarantined(df.select(F.col(id_col).cast("long").alias("vec_id"), F.col(vec_col).cast("array<double>").alias("v")), d, "v")[0]


def side_scalars(df: DataFrame, specs: list[QuantizerSpec], id_col: str = "vec_id", vec_col: str = "embedding") -> DataFrame:
    """The two scalars that all reconstruction errors follow from, for each spec and vector, in one scan."""
    sent = df.sparkSession.sparkContext.broadcast([codec(s) for s in specs])

    def run(batches):
        for batch in batches:
            for at in range(0, batch.num_rows, ROWS):
                part = batch.slice(at, ROWS)
                x, ids = A.matrix(part.column("v")), part.column("vec_id")
                for c in sent.value:
                    e, s, n = c.encode(x), c.spec, part.num_rows
                    yield pa.RecordBatch.from_arrays(
                        [pa.array([s.codebook] * n), pa.array([s.p] * n, pa.int32()), pa.array([s.b] * n, pa.int32()), pa.array([s.seed] * n, pa.int32()), ids, pa.array(e["norm"]), pa.array(e["rho"]), pa.array(e["zbar_sq"])],
                        ["method", "p", "b", "seed", "vec_id", "norm", "rho", "zbar_sq"],
                    )

    return _rows(df, specs[0].d, id_col, vec_col).mapInArrow(run, SCALARS)


def squared_error(rescale: str) -> Column:
    """Squared error of the reconstruction of a unit vector, from rho and zbar_sq."""
    rho, sq = F.col("rho"), F.col("zbar_sq")
    return {"raw": 1 - 2 * rho + sq, "best": 1 - rho * rho / sq, "unbiased": sq / (rho * rho) - 1}[rescale]


def errors(scalars: DataFrame, rescales: tuple[str, ...] = ("raw", "best", "unbiased")) -> DataFrame:
    """method, p, b, seed, rescale, vec_id, err."""
    each = F.array(*[F.struct(F.lit(r).alias("rescale"), squared_error(r).alias("err")) for r in rescales])
    return scalars.select("method", "p", "b", "seed", "vec_id", F.explode(each).alias("x")).select("method", "p", "b", "seed", "vec_id", "x.rescale", "x.err")


def recon_error(original: DataFrame, recon: DataFrame, id_col: str = "vec_id", vec_col: str = "embedding") -> DataFrame:
    """vec_id, err by subtraction, for any reconstruction."""
    x = original.select(F.col(id_col).alias("vec_id"), F.col(vec_col).cast("array<double>").alias("x"))
    diff = F.zip_with("x", "xhat", lambda a, b: (a - b) * (a - b))
    return x.join(recon, "vec_id").select("vec_id", F.aggregate(diff, F.lit(0.0), lambda s, v: s + v).alias("err"))


def error_histogram(df: DataFrame, col: str, lo: float, hi: float, bins: int, by: tuple[str, ...] = ()) -> DataFrame:
    """Counts by bin; bin 0 is below lo, bins + 1 is hi and above."""
    return df.groupBy(*by, F.width_bucket(F.col(col), F.lit(lo), F.lit(hi), F.lit(bins)).cast("int").alias("bin")).agg(F.count("*").alias("n"))


PAIR_SUMS = ("n", "e", "ee", "ip", "hat", "ip_ip", "ip_hat", "pred")


def pair_sums(
    queries: DataFrame, database: DataFrame, specs: list[QuantizerSpec], edges: tuple[float, float, int] = (-0.5, 0.5, 20), eps: tuple[float, ...] = (),
    id_col: str = "vec_id", vec_col: str = "embedding",
) -> DataFrame:
    """Sums over all pairs of a stated query set with the database, for each spec.

    Each batch gives one row a spec: counts and sums of the error, its square, and what slope
    and the ratio law need, counts by bin and by eps. Pairs themselves never leave a task.
    """
    from .search import query_blocks

    lo, hi, bins = edges
    sc, outs = database.sparkSession.sparkContext, None
    sent = sc.broadcast([codec(s) for s in specs])
    kinds = "method string, p int, b int, rescale string, seed int, " + ", ".join(f"{c} double" for c in PAIR_SUMS) + ", bins array<long>, beyond array<long>"
    for _, vectors in query_blocks(queries, id_col, vec_col):
        block = sc.broadcast(vectors)

        def run(batches, block=block):
            q = block.value
            for batch in batches:
                rows = []
                for at in range(0, batch.num_rows, 512):
                    x = A.matrix(batch.column("v").slice(at, 512))
                    ip = x @ q.T
                    for c in sent.value:
                        codes, s = c.encode(x), c.spec
                        hat = c.estimate(codes, q)
                        e = hat - ip
                        eta = ip / (codes["norm"][:, None] * np.linalg.norm(q, axis=1)[None, :])
                        with np.errstate(divide="ignore", invalid="ignore"):  # a sketch may leave nothing but its residual
                            law = (1 - eta**2) / (s.d - 1) * (codes["zbar_sq"] / codes["rho"] ** 2 - 1)[:, None]
                        bin_ = np.where(e < lo, 0, np.where(e >= hi, bins + 1, np.floor((e - lo) * (bins / (hi - lo))) + 1)).astype(np.int64)
                        sums = (e.size, e.sum(), (e * e).sum(), ip.sum(), hat.sum(), (ip * ip).sum(), (ip * hat).sum(), law.sum())
                        rows.append((s.codebook, s.p, s.b, s.rescale, s.seed, *map(float, sums), np.bincount(bin_.ravel(), minlength=bins + 2).tolist(), [int((np.abs(e) > t).sum()) for t in eps]))
                if rows:
                    cols = list(zip(*rows))
                    types = [pa.string(), pa.int32(), pa.int32(), pa.string(), pa.int32(), *[pa.float64()] * len(PAIR_SUMS), pa.list_(pa.int64()), pa.list_(pa.int64())]
                    yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(cols, types)], ["method", "p", "b", "rescale", "seed", *PAIR_SUMS, "bins", "beyond"])

        got = _rows(database, specs[0].d, id_col, vec_col).mapInArrow(run, kinds)
        outs = got if outs is None else outs.unionByName(got)
    return outs if outs is not None else database.sparkSession.createDataFrame([], kinds)


KEYS = ("method", "p", "b", "rescale", "seed")


def ip_stats(sums: DataFrame, d: int, by: tuple[str, ...] = KEYS) -> DataFrame:
    """Mean squared error (as is and times d - 1), bias, slope of estimate on truth, and the ratio law's prediction."""
    t = sums.groupBy(*by).agg(*[F.sum(c).alias(c) for c in PAIR_SUMS])
    n = F.col("n")
    slope = (F.col("ip_hat") - F.col("ip") * F.col("hat") / n) / (F.col("ip_ip") - F.col("ip") * F.col("ip") / n)
    return t.select(
        *by, n.cast("long").alias("pairs"), (F.col("ee") / n).alias("mse"), (F.col("ee") / n * (d - 1)).alias("scaled"), (F.col("e") / n).alias("bias"), slope.alias("slope"), (F.col("pred") / n).alias("law")
    )


def ip_bins(sums: DataFrame, by: tuple[str, ...] = KEYS) -> DataFrame:
    return sums.select(*by, F.posexplode("bins").alias("bin", "k")).groupBy(*by, "bin").agg(F.sum("k").alias("n")).where("n > 0")


def failure_rate(sums: DataFrame, eps: tuple[float, ...], by: tuple[str, ...] = KEYS) -> DataFrame:
    """Share of pairs whose error is beyond each eps."""
    x = sums.select(*by, "n", F.posexplode("beyond").alias("i", "k"))
    x = x.groupBy(*by, "i").agg((F.sum("k") / F.sum("n")).alias("failure"))
    return x.select(*by, F.element_at(F.array(*map(F.lit, eps)), F.col("i") + 1).alias("eps"), "failure")


def bits_needed(failures: DataFrame, delta: float) -> DataFrame:
    """The fewest bits at which a method fails in at most delta of the pairs, for each eps; null where none does."""
    return failures.groupBy("method", "p", "rescale", "eps").agg(F.min(F.when(F.col("failure") <= delta, F.col("b"))).alias("bits"))


def recall_at(exact: DataFrame, found: DataFrame, ks: tuple[int, ...]) -> DataFrame:
    """Share of queries whose exact best row is among the first k estimated ones."""
    top = exact.where("rank = 1").select("query_id", F.col("vec_id").alias("best"))
    hit = top.join(found.select("query_id", "vec_id", F.col("rank").alias("r")), (F.col("best") == F.col("vec_id")) & (top["query_id"] == found["query_id"]), "left").select(top["query_id"], "r")
    return hit.agg(*[F.avg(F.when(F.col("r") <= k, 1.0).otherwise(0.0)).alias(str(k)) for k in ks]).select(
        F.explode(F.array(*[F.struct(F.lit(k).alias("k"), F.col(str(k)).alias("recall")) for k in ks])).alias("x")
    ).select("x.k", "x.recall")


def recall_by_method(found: DataFrame, ks: tuple[int, ...], exact: str = "exact", by: tuple[str, ...] = ("method",)) -> DataFrame:
    """method, k, recall from one table of ranked rows of all methods, the exact one among them. Nothing is joined."""
    top = F.max(F.when((F.col("method") == exact) & (F.col("rank") == 1), F.col("vec_id"))).over(Window.partitionBy("query_id"))
    hits = found.withColumn("best", top).where(F.col("method") != exact)
    first = hits.groupBy(*by, "query_id").agg(F.min(F.when(F.col("vec_id") == F.col("best"), F.col("rank"))).alias("r"))
    each = first.groupBy(*by).agg(*[F.avg(F.when(F.col("r") <= k, 1.0).otherwise(0.0)).alias(str(k)) for k in ks])
    return each.select(*by, F.explode(F.array(*[F.struct(F.lit(k).alias("k"), F.col(str(k)).alias("recall")) for k in ks])).alias("x")).select(*by, "x.k", "x.recall")


def recall_of_ranks(ranks: DataFrame, ks: tuple[int, ...], by: tuple[str, ...] = ("method",)) -> DataFrame:
    """method, k, recall from the rank of each query's best row."""
    each = ranks.groupBy(*by).agg(*[F.avg(F.when(F.col("rank") <= k, 1.0).otherwise(0.0)).alias(str(k)) for k in ks])
    return each.select(*by, F.explode(F.array(*[F.struct(F.lit(k).alias("k"), F.col(str(k)).alias("recall")) for k in ks])).alias("x")).select(*by, "x.k", "x.recall")


def effective_bits(spec: QuantizerSpec, side_bits: int | None = None) -> float:
    """Stored bits a dimension of the source, side scalars included."""
    code = sum(code_bits(spec))
    if spec.codebook == "sphere_scalar_signbit":
        code += spec.width
        side = 32
    else:
        side = 0 if spec.rescale == "raw" else 32
    return (code + (side if side_bits is None else side_bits)) / spec.d


def stored_bytes(df: DataFrame, specs: list[QuantizerSpec], id_col: str = "vec_id", vec_col: str = "embedding") -> DataFrame:
    """method, p, b, vectors, coordinates, bytes: what the packed codes of all sound vectors take, without side scalars."""
    sent = df.sparkSession.sparkContext.broadcast([codec(s) for s in specs])
    kinds = "method string, p int, b int, vectors long, coordinates long, bytes long"

    def run(batches):
        for batch in batches:
            if batch.num_rows:
                x = A.matrix(batch.column("v"))
                cols = list(zip(*[(c.spec.codebook, c.spec.p, c.spec.b, len(x), x.size, sum(map(len, packed_rows(c.encode(x)["code"], code_bits(c.spec))))) for c in sent.value]))
                yield pa.RecordBatch.from_arrays([pa.array(v, t) for v, t in zip(cols, (pa.string(), pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.int64()))], [k.split()[0] for k in kinds.split(", ")])

    return _rows(df, specs[0].d, id_col, vec_col).mapInArrow(run, kinds).groupBy("method", "p", "b").agg(*[F.sum(c).alias(c) for c in ("vectors", "coordinates", "bytes")])


def compression_ratio(spec: QuantizerSpec, full_bits: int = 32) -> float:
    return full_bits / effective_bits(spec)


def seed_summary(df: DataFrame, value: str, by: tuple[str, ...]) -> DataFrame:
    """Mean and standard deviation over seeds."""
    return df.groupBy(*by).agg(F.count("*").alias("seeds"), F.avg(value).alias("mean"), F.stddev_samp(value).alias("std"))


def weighted_score(scores: dict[str, float], weights: dict[str, float]) -> float:
    return sum(scores[k] * w for k, w in weights.items()) / sum(weights.values())


def lookup_quality(df: DataFrame, specs: list[QuantizerSpec], id_col: str = "vec_id", vec_col: str = "embedding") -> DataFrame:
    """Of blocks coded with cell lists: agreement with the full search, excess error, candidates a block against the whole book."""
    from dataclasses import replace

    sent = df.sparkSession.sparkContext.broadcast([(codec(s), codec(replace(s, assign="exact"))) for s in specs])
    kinds = "assign string, p int, b int, blocks double, same double, err double, err_exact double, candidates double, book double"

    def run(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            x, rows = A.matrix(batch.column("v")), []
            x = x / np.linalg.norm(x, axis=1, keepdims=True)
            for fast, full in sent.value:
                z, s = fast.rotate(x), fast.spec
                a, b = fast.assign(z), full.assign(z)
                err = [float(((z - c.values(k)) ** 2).sum()) for c, k in ((fast, a), (full, b))]
                t = fast.tables[s.p]
                rows.append((s.assign, s.p, s.b, float(a.size), float((a == b).sum()), *err, float(t.sizes.mean()) * a.size, float(len(t.book)) * a.size))
            cols = list(zip(*rows))
            yield pa.RecordBatch.from_arrays([pa.array(cols[0]), pa.array(cols[1], pa.int32()), pa.array(cols[2], pa.int32()), *[pa.array(c, pa.float64()) for c in cols[3:]]], [k.split()[0] for k in kinds.split(", ")])

    got = _rows(df, specs[0].d, id_col, vec_col).mapInArrow(run, kinds).groupBy("assign", "p", "b").agg(*[F.sum(c).alias(c) for c in ("blocks", "same", "err", "err_exact", "candidates", "book")])
    return got.select(
        "assign", "p", "b", F.col("blocks").cast("long").alias("blocks"), (F.col("same") / F.col("blocks")).alias("agreement"), (F.col("err") / F.col("err_exact") - 1).alias("excess"),
        (F.col("candidates") / F.col("blocks")).alias("candidates"), (F.col("book") / F.col("blocks")).alias("book"),
    )


def block_distortion(df: DataFrame, spec: QuantizerSpec, books: dict, unit: bool = False, id_col: str = "vec_id", vec_col: str = "embedding") -> DataFrame:
    """p, b, n, mse: mean squared distance of the blocks of rotated unit vectors to the nearest word of each book, named (p, b); unit: of the blocks' directions."""
    sent = df.sparkSession.sparkContext.broadcast((codec(spec), books))

    def run(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            (c, books), x, rows = sent.value, A.matrix(batch.column("v")), []
            z = c.rotate(x / np.linalg.norm(x, axis=1, keepdims=True))
            for (p, b), book in books.items():
                w = z[:, : z.shape[1] // p * p].reshape(-1, p)
                if unit:
                    size = np.linalg.norm(w, axis=1)
                    w = w[size > 0] / size[size > 0, None]
                rows.append((p, b, len(w), float(((w - book[nearest(w, book)]) ** 2).sum())))
            cols = list(zip(*rows))
            yield pa.RecordBatch.from_arrays([pa.array(v, t) for v, t in zip(cols, (pa.int32(), pa.int32(), pa.int64(), pa.float64()))], ["p", "b", "n", "err"])

    sums = _rows(df, spec.d, id_col, vec_col).mapInArrow(run, "p int, b int, n long, err double").groupBy("p", "b")
    return sums.agg(F.sum("n").alias("n"), (F.sum("err") / F.sum("n")).alias("mse"))


def codec_of(spec: QuantizerSpec) -> Codec:
    return codec(spec)
