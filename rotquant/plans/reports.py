"""Reports around the workloads: roll-ups, distributions, wide texts, learned blocks, numeric rows of tables."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions import theory
from ..model import normalize
from ..operators import metrics as M
from ..operators.quantize import encode
from ..operators.search import exact_topk, topk
from ..operators.trained import trained_books, trained_error
from ..sources.tables import read_table
from . import sql as S
from .tasks import _TEXT_VECTORS, TEXT_D, _texts, wide_specs
from .workloads import _ERR_ROWS, D, EVERY, _err_sql, _errors, _pairs_sql, _sums, all_specs, database, query, rounded, sketches, spec


@query("error_rollup", lambda: _err_sql(all_specs((1, 2)), "SELECT coalesce(method, 'all') AS method, coalesce(p, 0) AS p, coalesce(b, 0) AS b, count(*) AS n, round(avg(err), 6) AS mse, round(stddev_samp(err), 6) AS std FROM er WHERE rescale = 'best' GROUP BY ROLLUP (method, p, b)"))
def error_rollup(spark, sf_dir):
    e = _errors(spark, sf_dir, all_specs((1, 2))).where("rescale = 'best'").rollup("method", "p", "b").agg(F.count("*").alias("n"), F.avg("err").alias("mse"), F.stddev_samp("err").alias("std"))
    return rounded(e.select(F.coalesce("method", F.lit("all")).alias("method"), F.coalesce("p", F.lit(0)).alias("p"), F.coalesce("b", F.lit(0)).alias("b"), "n", "mse", "std"), "mse", "std")


#: Steps of the error that are counted apart; a window only ever sorts the vectors of one step.
STEPS = 4096


@query("error_cdf", lambda: _err_sql([spec("ball_block", 3, 2)], "SELECT vec_id, round(err, 6) AS err, round(cume_dist() OVER (ORDER BY round(err, 9)), 6) AS share, CAST(ntile(10) OVER (ORDER BY round(err, 9), vec_id) AS INTEGER) AS tenth FROM er WHERE rescale = 'best'"))
def error_cdf(spark, sf_dir):
    """The distribution function of the errors of one spec, by vector.

    Errors lie between 0 and 1. A histogram of STEPS steps tells how many vectors come before a
    step; ranks inside a step are added to it, so that no task reads all vectors.
    """
    e = _errors(spark, sf_dir, [spec("ball_block", 3, 2)]).where("rescale = 'best'").withColumn("e9", F.round("err", 9)).withColumn("step", F.floor(F.col("e9") * STEPS))
    counts = e.groupBy("step").agg(F.count("*").alias("k"))
    before = Window.orderBy("step").rowsBetween(Window.unboundedPreceding, -1)  # over STEPS rows at most
    counts = counts.select("step", F.coalesce(F.sum("k").over(before), F.lit(0)).alias("first"), F.sum("k").over(Window.partitionBy()).alias("n"))
    inside, upto = Window.partitionBy("step").orderBy("e9", "vec_id"), Window.partitionBy("step").orderBy("e9").rangeBetween(Window.unboundedPreceding, Window.currentRow)
    x = e.join(F.broadcast(counts), "step").withColumn("place", F.col("first") + F.row_number().over(inside) - 1).withColumn("reach", F.col("first") + F.count("*").over(upto))
    long, wide = F.pmod("n", F.lit(10)), F.floor(F.col("n") / 10)  # the first tenths hold one more
    tenth = F.when(F.col("place") < long * (wide + 1), F.floor(F.col("place") / (wide + 1))).otherwise(long + F.floor((F.col("place") - long * (wide + 1)) / F.greatest(wide, F.lit(1))))
    return x.select("vec_id", F.round("err", 6).alias("err"), F.round(F.col("reach") / F.col("n"), 6).alias("share"), (tenth + 1).cast("int").alias("tenth"))


@query("lost_neighbours", lambda: _pairs_sql([spec("ball_block", 3, 2, "unbiased")], """, a AS (SELECT query_id, vec_id FROM pr QUALIFY row_number() OVER (PARTITION BY query_id ORDER BY round(ip, 9) DESC, vec_id) <= 10),
c AS (SELECT query_id, vec_id FROM pr QUALIFY row_number() OVER (PARTITION BY query_id ORDER BY round(hat, 9) DESC, vec_id) <= 10) SELECT query_id, vec_id FROM a EXCEPT SELECT query_id, vec_id FROM c"""))
def lost_neighbours(spark, sf_dir):
    q, db = database(spark, sf_dir)
    s = spec("ball_block", 3, 2, "unbiased")
    return exact_topk(q, db, 10).select("query_id", "vec_id").exceptAll(topk(q, encode(db, s), s, 10).select("query_id", "vec_id"))


WIDE = [replace(s, rescale="raw", tail="error" if s.codebook == "ball_block" else "mixed") for s in wide_specs(TEXT_D, (1, 2, 3))] + [replace(s, rescale="raw") for s in wide_specs(TEXT_D, (4,), (("gauss_scalar", 1), ("sphere_scalar", 1), ("ball_block", 2)))]
WIDE_SQL = [s for s in WIDE if s.codebook != "grid_dir" and (s.p, s.b) != (3, 3)]


def _mse_rows(v, specs):
    e = M.errors(M.side_scalars(v, specs))
    return rounded(e.groupBy("method", "p", "b", "rescale").agg(F.count("*").alias("n"), F.avg("err").alias("mse")), "mse")


@query("mse_text192", lambda: f"""WITH {_TEXT_VECTORS},{S.base(WIDE_SQL[0], 'tv')},{S.scalars(WIDE_SQL)}, er AS ({_ERR_ROWS}) SELECT method, p, b, rescale, count(*) AS n, round(avg(err), 6) AS mse FROM er GROUP BY ALL""")
def mse_text192(spark, sf_dir):
    """Wide vectors that blocks of 2 and 3 divide; what SQL can code by brute force."""
    return _mse_rows(_texts(spark, sf_dir, TEXT_D), WIDE_SQL)


@query("mse_text192_all")
def mse_text192_all(spark, sf_dir):
    """All methods at 1 to 4 bits; grid directions by the exact sweep."""
    return _mse_rows(_texts(spark, sf_dir, TEXT_D), WIDE + wide_specs(TEXT_D, (4,), (("grid_dir", 1), ("ball_block", 3)), assign="top"))


@query("mse_text1536")
def mse_text1536(spark, sf_dir):
    """All methods at 1536 dimensions; blocks of 3 by candidate lists at 4 bits."""
    return _mse_rows(_texts(spark, sf_dir, 1536), wide_specs(1536, (1, 2, 3)) + wide_specs(1536, (4,), assign="top"))


CHEBYSHEV_EPS = (0.05, 0.1, 0.2)


@query("chebyshev", lambda: f"""WITH {S.base(sketches()[0])},{",".join(S.signbit_rows(s, EVERY, f"sb{s.b}") for s in sketches())}, pa AS ({" UNION ALL ".join(f"SELECT b, ip, hat FROM sb{s.b}" for s in sketches())})
SELECT pa.b, eps, round(least(1.0, v / 64 / (eps * eps)), 6) AS failure, round(least(1.0, avg(pow(hat - ip, 2)) / (eps * eps)), 6) AS bound, round(avg(CASE WHEN abs(hat - ip) > eps THEN 1.0 ELSE 0.0 END), 6) AS measured
 FROM pa JOIN (VALUES (1, 1.57e0), (2, 0.56e0), (3, 0.18e0), (4, 0.047e0)) t(b, v) ON pa.b = t.b, (VALUES (0.05e0), (0.1e0), (0.2e0)) e(eps) GROUP BY pa.b, v, eps""")
def chebyshev(spark, sf_dir):
    """The bound on failures that follows from the variance alone, published and of the table's pairs; measured failures are far below it."""
    sums = _sums(spark, sf_dir, sketches(), eps=CHEBYSHEV_EPS).select("b", "n", "ee", F.posexplode("beyond").alias("i", "k"))
    x = sums.groupBy("b", "i").agg((F.sum("ee") / F.sum("n")).alias("variance"), (F.sum("k") / F.sum("n")).alias("measured"))
    known = [(b, i, e, theory.chebyshev_failure(v / D, e)) for b, v in enumerate(theory.IP_LIMIT["sphere_scalar_signbit", 1], 1) for i, e in enumerate(CHEBYSHEV_EPS)]
    rows = x.join(F.broadcast(spark.createDataFrame(known, "b int, i int, eps double, failure double")), ["b", "i"])
    return rounded(rows.select("b", "eps", "failure", F.least(F.lit(1.0), F.col("variance") / (F.col("eps") * F.col("eps"))).alias("bound"), "measured"), "failure", "bound", "measured")


@query("learned_blocks")
def learned_blocks(spark, sf_dir):
    """Mean relative error of codebooks learned from the table, beside fixed ones of the same size (blocks of 2, 2 bits, all coordinates)."""
    _, db = database(spark, sf_dir)
    e = trained_error(db, trained_books(db, D, 2, 2), 2).withColumn("method", F.lit("learned"))
    fixed = _errors(spark, sf_dir, [spec("ball_block", 2, 2)]).where("rescale = 'raw'").select("vec_id", "err", F.lit("ball_block").alias("method"))
    size = db.select("vec_id", F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x * x).alias("sq"))
    x = e.join(size, "vec_id").select("method", (F.col("err") / F.col("sq")).alias("err")).unionByName(fixed.select("method", "err"))
    return rounded(x.groupBy("method").agg(F.count("*").alias("n"), F.avg("err").alias("relative_error")), "relative_error")


@query("order_vectors", """WITH o AS (SELECT l_orderkey, sum(l_quantity) AS a, sum(l_extendedprice) / 1000 AS b, sum(l_discount) AS c, sum(l_tax) AS d, CAST(count(*) AS DOUBLE) AS e, max(l_quantity) AS f FROM lineitem GROUP BY 1)
SELECT CAST(l_orderkey AS BIGINT) AS vec_id, round(sqrt(a * a + b * b + c * c + d * d + e * e + f * f), 4) AS norm FROM o""")
def order_vectors(spark, sf_dir):
    """Numeric rows of a table as vectors of any length; the norm is kept beside the code."""
    li = read_table(spark, sf_dir, "lineitem", "l_orderkey", "l_quantity", "l_extendedprice", "l_discount", "l_tax")
    o = li.groupBy("l_orderkey").agg(F.sum("l_quantity").alias("a"), (F.sum("l_extendedprice") / 1000).alias("b"), F.sum("l_discount").alias("c"), F.sum("l_tax").alias("d"), F.count("*").cast("double").alias("e"), F.max("l_quantity").alias("f"))
    v = o.select(F.col("l_orderkey").cast("long").alias("vec_id"), F.array("a", "b", "c", "d", "e", "f").alias("embedding"))
    return normalize(v).select("vec_id", F.round("norm", 4).alias("norm"))
