"""The experiments on the given tables, as queries with their SQL."""

from __future__ import annotations

from dataclasses import replace
from functools import partial

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import theory
from ..functions.codebooks import gauss_scalar, sphere_scalar
from ..model import QuantizerSpec, normalize
from ..operators import metrics as M
from ..operators import relational
from ..operators.quantize import decode, encode, pack_codes, unpack_codes
from ..operators.search import exact_topk, is_query, neighbour_overlap, pair_stats, ranks_of_best, split, topk
from ..sources.tables import read_table, read_vectors
from . import sql as S

D = 64
FAMILY = (("gauss_scalar", 1), ("sphere_scalar", 1), ("grid_dir", 1), ("ball_block", 2), ("ball_block", 3))
KS = (1, 2, 4, 8, 16, 32, 64)
EPS = (0.02, 0.05, 0.1)


def spec(family: str, p: int, b: int, rescale: str = "raw", seed: int = 0, **more) -> QuantizerSpec:
    return QuantizerSpec(family, rescale, D, p, b, seed, **more)


def all_specs(bits=(1, 2, 3, 4), rescale: str = "raw", seed: int = 0) -> list[QuantizerSpec]:
    return [spec(f, p, b, rescale, seed) for f, p in FAMILY for b in bits]


#: One vector in so many is a query, in every workload and its SQL.
EVERY = 10


def database(spark, sf_dir) -> tuple[DataFrame, DataFrame]:
    return split(read_vectors(spark, sf_dir), EVERY)


def rounded(df: DataFrame, *cols: str) -> DataFrame:
    return df.withColumns({c: F.round(c, 6) for c in cols})


QUERIES: dict = {}
SQL: dict = {}


def query(name: str, sql=None):
    """Registers a query; sql is text or a function that makes it when it is asked for."""

    def put(f):
        QUERIES[name] = f
        if sql is not None:
            SQL[name] = sql
        return f

    return put


# vectors ----------------------------------------------------------------------


@query(
    "normalize_vectors",
    """SELECT CAST(vec_id AS BIGINT) AS vec_id, round(sqrt(list_sum(list_transform(embedding, lambda v: CAST(v AS DOUBLE) * CAST(v AS DOUBLE)))), 6) AS norm,
  sqrt(list_sum(list_transform(embedding, lambda v: CAST(v AS DOUBLE) * CAST(v AS DOUBLE)))) = 0 AS is_zero FROM embeddings""",
)
def normalize_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rounded(normalize(read_vectors(spark, sf_dir)).select("vec_id", "norm", "is_zero"), "norm")


@query("split_queries", "SELECT CASE WHEN vec_id % 10 = 0 THEN 'query' ELSE 'database' END AS role, count(*) AS n FROM embeddings GROUP BY 1")
def split_queries(spark, sf_dir):
    return read_vectors(spark, sf_dir).groupBy(F.when(is_query(EVERY), "query").otherwise("database").alias("role")).agg(F.count("*").alias("n"))


_EXACT = """
WITH v AS (SELECT CAST(vec_id AS BIGINT) AS vec_id, list_transform(embedding, lambda v: CAST(v AS DOUBLE)) AS e FROM embeddings),
p AS (SELECT q.vec_id AS query_id, c.vec_id, list_dot_product(q.e, c.e) AS ip FROM v q JOIN v c ON q.vec_id % 10 = 0 AND c.vec_id % 10 <> 0)"""
_EXACT_TOP = (
    _EXACT
    + """, r AS (SELECT query_id, CAST(row_number() OVER (PARTITION BY query_id ORDER BY round(ip, 9) DESC, vec_id) AS INTEGER) AS rank, vec_id, round(ip, 6) AS score FROM p)
SELECT query_id, rank, vec_id, score FROM r WHERE rank <= {k}"""
)


def _exact(k, spark, sf_dir):
    return rounded(exact_topk(*database(spark, sf_dir), k), "score")


query("exact_top1", _EXACT_TOP.format(k=1))(partial(_exact, 1))
query("exact_topk", _EXACT_TOP.format(k=10))(partial(_exact, 10))


@query(
    "exact_ip_pairs_stats",
    _EXACT + " SELECT count(*) AS pairs, round(avg(ip), 6) AS mean, round(stddev_samp(ip), 6) AS std, round(min(ip), 6) AS low, round(max(ip), 6) AS high FROM p",
)
def exact_ip_pairs_stats(spark, sf_dir):
    return rounded(pair_stats(*database(spark, sf_dir)), "mean", "std", "low", "high")


# codes ------------------------------------------------------------------------


@query("rotate_relational", lambda: f"WITH {S.base(spec('sphere_scalar', 1, 2))} SELECT vec_id, round(list_sum(list_transform(y, lambda v: abs(v))), 6) AS l1, round(y[1], 6) AS first, round(y[{D}], 6) AS last FROM zt")
def rotate_relational(spark, sf_dir):
    z = relational.rotate_relational(read_vectors(spark, sf_dir), D, 0)
    l1 = F.aggregate("z", F.lit(0.0), lambda a, v: a + F.abs(v))
    return rounded(z.select("vec_id", l1.alias("l1"), F.col("z")[0].alias("first"), F.col("z")[D - 1].alias("last")), "l1", "first", "last")


def _codes(s: QuantizerSpec, spark, sf_dir):
    return encode(database(spark, sf_dir)[1], s).select("vec_id", F.array_join(F.transform("code", lambda c: c.cast("string")), ",").alias("code"), F.round("rho", 6).alias("rho"))


def _codes_sql(s: QuantizerSpec) -> str:
    return f"WITH {S.base(s, where='vec_id % 10 <> 0')},{S.coded(s, 'k')} SELECT vec_id, array_to_string(list_transform(code, lambda c: CAST(CAST(c AS BIGINT) AS VARCHAR)), ',') AS code, round(list_dot_product(z, zb), 6) AS rho FROM k"


for _name, _family, _p, _bits in (("gs", "gauss_scalar", 1, (1, 2, 3, 4)), ("ss", "sphere_scalar", 1, (1, 2, 3, 4)), ("bb2", "ball_block", 2, (1, 2, 3)), ("bb3", "ball_block", 3, (1, 2, 3)), ("gr_sweep", "grid_dir", 1, (1, 2, 3, 4))):
    for _b in _bits:
        query(f"{_name}_codes_b{_b}", partial(_codes_sql, spec(_family, _p, _b)))(partial(_codes, spec(_family, _p, _b)))


for _b in (2, 4):  # the approximation, beside the exact search
    query(f"gr_ladder_codes_b{_b}", partial(_codes_sql, spec("grid_dir", 1, _b, assign="ladder")))(partial(_codes, spec("grid_dir", 1, _b, assign="ladder")))
#: Blocks of one coordinate are the fitted scalars.
query("bb1_codes_b2", partial(_codes_sql, spec("sphere_scalar", 1, 2)))(partial(_codes, spec("ball_block", 1, 2)))


@query("codes_catalyst_b2", partial(_codes_sql, spec("sphere_scalar", 1, 2)))
def codes_catalyst_b2(spark, sf_dir):
    """The scalar codes without Python in the plan; alignment follows from the codes."""
    q = sphere_scalar(2, D).tolist()
    unit = normalize(database(spark, sf_dir)[1])
    z = relational.rotate_relational(unit, D, 0)
    c = relational.scalar_codes(z, "sphere_scalar", 2, D).join(z, "vec_id")
    rho = F.aggregate(F.zip_with("z", "code", lambda v, k: v * F.element_at(F.array(*map(F.lit, q)), k + 1)), F.lit(0.0), lambda a, v: a + v)
    return c.select("vec_id", F.array_join(F.transform("code", lambda k: k.cast("string")), ",").alias("code"), F.round(rho, 6).alias("rho"))


def _scales(rescale, spark, sf_dir):
    c = encode(database(spark, sf_dir)[1], spec("ball_block", 3, 2))
    s = {"raw": F.lit(1.0), "best": F.col("rho") / F.col("zbar_sq"), "unbiased": 1 / F.col("rho")}[rescale]
    return rounded(c.select("vec_id", "rho", s.alias("scale"), M.squared_error(rescale).alias("err")), "rho", "scale", "err")


def _scales_sql(rescale) -> str:
    s = spec("ball_block", 3, 2)
    return f"WITH {S.base(s, where='vec_id % 10 <> 0')},{S.scalars([s])} SELECT vec_id, round(rho, 6) AS rho, round({S.SCALE[rescale]}, 6) AS scale, round({S.ERROR[rescale]}, 6) AS err FROM sc"


for _r in ("raw", "best", "unbiased"):
    query(f"bb_scale_{_r}", partial(_scales_sql, _r))(partial(_scales, _r))


def decoded_sql(s: QuantizerSpec, table: str = "embeddings", where: str = f"vec_id % {EVERY} <> 0") -> str:
    """xd: rescale, vec_id, e, code and xhat under each rule."""
    back = S.literal(S.codec(s).rotation.T)
    parts = [f"SELECT '{r}' AS rescale, vec_id, e, code, norm * {x} AS f, zb FROM kd" for r, x in S.SCALE.items()]
    return f"""{S.base(s, table, where)},{S.coded(s, 'kc')}, kd AS (SELECT *, list_dot_product(z, zb) AS rho, list_dot_product(zb, zb) AS zsq FROM kc),
bk AS (SELECT {back} AS m), kf AS ({' UNION ALL '.join(parts)}),
xd AS (SELECT rescale, vec_id, e, code, list_transform(m, lambda r: f * list_dot_product(r, zb)) AS xhat FROM kf, bk)"""


_SEEN = "round(xhat[1], 6) + 0 AS first, round(list_sum(list_transform(xhat, lambda v: abs(v))), 6) AS l1, round(list_sum(list_transform(list_zip(e, xhat), lambda p: pow(p[1] - p[2], 2))), 6) AS err"


def decoded(vectors: DataFrame, s: QuantizerSpec, digits: int = 6) -> DataFrame:
    """rescale, vec_id, first, l1, err: reconstructions under each rule from the same codes, and their error by subtraction."""
    codes, out = encode(vectors, s), None
    for r in ("raw", "best", "unbiased"):
        hat = decode(codes, replace(s, rescale=r))
        own = hat.join(M.recon_error(vectors, hat), "vec_id").select(
            F.lit(r).alias("rescale"), "vec_id", (F.round(F.col("xhat")[0], 6) + 0).alias("first"), F.round(F.aggregate("xhat", F.lit(0.0), lambda a, v: a + F.abs(v)), 6).alias("l1"), F.round("err", digits).alias("err")
        )
        out = own if out is None else out.unionByName(own)
    return out


for _name, _family, _p, _b in (("decode_bb3", "ball_block", 3, 2), ("decode_gs", "gauss_scalar", 1, 2), ("decode_gr", "grid_dir", 1, 3)):
    query(_name, lambda s=spec(_family, _p, _b): f"WITH {decoded_sql(s)} SELECT rescale, vec_id, {_SEEN} FROM xd")(lambda spark, sf_dir, s=spec(_family, _p, _b): decoded(database(spark, sf_dir)[1], s))


@query("pack_unpack", lambda: _codes_sql(spec("ball_block", 3, 2)).replace("AS rho FROM", "AS rho, 16 AS bytes FROM"))
def pack_unpack(spark, sf_dir):
    """Codes through bytes and back; 128 bits a vector."""
    s = spec("ball_block", 3, 2)
    p = pack_codes(encode(database(spark, sf_dir)[1], s), s).withColumn("norm", F.octet_length("packed").cast("double"))
    u = unpack_codes(p, s)
    return u.select("vec_id", F.array_join(F.transform("code", lambda c: c.cast("string")), ",").alias("code"), F.round("rho", 6).alias("rho"), F.col("norm").cast("int").alias("bytes"))


# reconstruction ---------------------------------------------------------------

_ERR_ROWS = " UNION ALL ".join(f"SELECT method, p, b, '{r}' AS rescale, vec_id, {x} AS err FROM sc" for r, x in S.ERROR.items())


def _err_sql(specs, tail: str) -> str:
    return f"WITH {S.base(specs[0], where='vec_id % 10 <> 0')},{S.scalars(specs)}, er AS ({_ERR_ROWS}) {tail}"


def _errors(spark, sf_dir, specs):
    return M.errors(M.side_scalars(database(spark, sf_dir)[1], specs)).drop("seed")


@query("mse_by_method", lambda: _err_sql(all_specs(), "SELECT method, p, b, rescale, count(*) AS n, round(avg(err), 6) AS mse FROM er GROUP BY ALL"))
def mse_by_method(spark, sf_dir):
    e = _errors(spark, sf_dir, all_specs())
    return rounded(e.groupBy("method", "p", "b", "rescale").agg(F.count("*").alias("n"), F.avg("err").alias("mse")), "mse")


@query("mse_quantiles", lambda: _err_sql(all_specs(), "SELECT method, p, b, rescale, round(quantile_cont(err, 0.5), 6) AS q50, round(quantile_cont(err, 0.9), 6) AS q90 FROM er GROUP BY ALL"))
def mse_quantiles(spark, sf_dir):
    e = _errors(spark, sf_dir, all_specs())
    return rounded(e.groupBy("method", "p", "b", "rescale").agg(F.percentile("err", F.lit(0.5)).alias("q50"), F.percentile("err", F.lit(0.9)).alias("q90")), "q50", "q90")


@query("mse_hist", lambda: _err_sql(all_specs(), "SELECT method, p, b, rescale, CAST(CASE WHEN err < 0 THEN 0 WHEN err >= 0.2 THEN 41 ELSE floor(err / 0.2 * 40) + 1 END AS INTEGER) AS bin, count(*) AS n FROM er GROUP BY ALL"))
def mse_hist(spark, sf_dir):
    return M.error_histogram(_errors(spark, sf_dir, all_specs()), "err", 0.0, 0.2, 40, ("method", "p", "b", "rescale"))


@query(
    "error_cube",
    lambda: _err_sql(all_specs((1, 2)), "SELECT coalesce(method, 'all') AS method, coalesce(b, 0) AS b, CAST(grouping(method) * 2 + grouping(b) AS BIGINT) AS level, count(*) AS n, round(avg(err), 6) AS mse FROM er GROUP BY CUBE (method, b)"),
)
def error_cube(spark, sf_dir):
    e = _errors(spark, sf_dir, all_specs((1, 2))).cube("method", "b").agg(F.grouping_id().alias("level"), F.count("*").alias("n"), F.avg("err").alias("mse"))
    return rounded(e.select(F.coalesce("method", F.lit("all")).alias("method"), F.coalesce("b", F.lit(0)).alias("b"), "level", "n", "mse"), "mse")


@query("mse_pivot", lambda: _err_sql(all_specs((1, 2)), "SELECT method, p, round(avg(err) FILTER (b = 1), 6) AS b1, round(avg(err) FILTER (b = 2), 6) AS b2 FROM er WHERE rescale = 'best' GROUP BY ALL"))
def mse_pivot(spark, sf_dir):
    e = _errors(spark, sf_dir, all_specs((1, 2))).where("rescale = 'best'").groupBy("method", "p").pivot("b", [1, 2]).agg(F.avg("err"))
    return rounded(e.withColumnsRenamed({"1": "b1", "2": "b2"}), "b1", "b2")


SEEDS = range(5)


def _seed_sql() -> str:
    raw = [[spec(f, p, 2, seed=k) for f, p in FAMILY] for k in SEEDS]
    parts = ",".join(S.base(x[0], where=f"vec_id % {EVERY} <> 0", tag=f"_{k}") + "," + S.scalars(x, f"sc{k}", f"zt_{k}") for k, x in zip(SEEDS, raw))
    each = " UNION ALL ".join(f"SELECT method, p, b, seed, avg({S.ERROR['best']}) AS mse FROM sc{k} GROUP BY ALL" for k in SEEDS)
    return f"WITH {parts}, e AS ({each}) SELECT method, p, b, count(*) AS seeds, round(avg(mse), 6) AS mean, round(stddev_samp(mse), 6) AS std FROM e GROUP BY ALL"


@query("seed_summary", _seed_sql)
def seed_summary(spark, sf_dir):
    """Five rotations of every method, one scan."""
    e = M.errors(M.side_scalars(database(spark, sf_dir)[1], [spec(f, p, 2, seed=k) for k in SEEDS for f, p in FAMILY]), ("best",))
    by_seed = e.groupBy("method", "p", "b", "seed").agg(F.avg("err").alias("mse"))
    return rounded(M.seed_summary(by_seed, "mse", ("method", "p", "b")), "mean", "std")


# inner products ---------------------------------------------------------------


BITS = (1, 2, 3, 4)


def sketches(bits=BITS) -> list[QuantizerSpec]:
    return [spec("sphere_scalar_signbit", 1, b) for b in bits]


def ip_specs(bits=BITS) -> list[QuantizerSpec]:
    return [spec(f, p, b, r) for f, p in FAMILY for b in bits for r in ("best", "unbiased")]


def unbiased_specs(bits=BITS) -> list[QuantizerSpec]:
    return [spec(f, p, b, "unbiased") for f, p in FAMILY for b in bits]


def _pairs_sql(specs, tail: str, signs: list[QuantizerSpec] = ()) -> str:
    """pr: pairs of the specs, with the ratio law's prediction; pa: these and the pairs of the sign sketches."""
    raw = list({(s.codebook, s.p, s.b): spec(s.codebook, s.p, s.b) for s in specs}.values())
    more = "".join("," + S.signbit_rows(s, EVERY, f"sb{s.b}") for s in signs)
    every = " UNION ALL ".join(f"SELECT method, p, b, rescale, query_id, vec_id, ip, hat FROM {t}" for t in ["pr", *(f"sb{s.b}" for s in signs)])
    return f"WITH {S.base(raw[0])},{S.scalars(raw)},{S.pair_rows(specs, EVERY)}{more}, pa AS ({every}) {tail}"


def _sums(spark, sf_dir, specs, **more):
    q, db = database(spark, sf_dir)
    return M.pair_sums(q, db, specs, **more)


def _all_pairs(tail: str):
    return lambda: _pairs_sql(ip_specs(), tail, sketches())


@query("ip_error_stats", _all_pairs("SELECT method, p, b, rescale, count(*) AS pairs, round(avg(pow(hat - ip, 2)), 6) AS mse, round(avg(pow(hat - ip, 2)) * 63, 6) AS scaled FROM pa GROUP BY ALL"))
def ip_error_stats(spark, sf_dir):
    return rounded(M.ip_stats(_sums(spark, sf_dir, ip_specs() + sketches()), D), "mse", "scaled").select("method", "p", "b", "rescale", "pairs", "mse", "scaled")


@query("ip_bias", _all_pairs("SELECT method, p, b, rescale, round(avg(hat - ip), 6) + 0 AS bias, round(regr_slope(hat, ip), 6) AS slope FROM pa GROUP BY ALL"))
def ip_bias(spark, sf_dir):
    return rounded(M.ip_stats(_sums(spark, sf_dir, ip_specs() + sketches()), D), "bias", "slope").select("method", "p", "b", "rescale", (F.col("bias") + 0).alias("bias"), "slope")


@query("ip_error_hist", _all_pairs("SELECT method, p, b, rescale, CAST(CASE WHEN hat - ip < -0.5 THEN 0 WHEN hat - ip >= 0.5 THEN 21 ELSE floor((hat - ip + 0.5) * 20) + 1 END AS INTEGER) AS bin, count(*) AS n FROM pa GROUP BY ALL"))
def ip_error_hist(spark, sf_dir):
    return M.ip_bins(_sums(spark, sf_dir, ip_specs() + sketches())).drop("seed")


@query("ratio_law", lambda: _pairs_sql(unbiased_specs(), "SELECT method, p, b, rescale, round(avg(pow(hat - ip, 2)), 6) AS mse, round(avg(law), 6) AS law FROM pr GROUP BY ALL"))
def ratio_law(spark, sf_dir):
    """The ratio estimator's squared error beside what its law predicts."""
    return rounded(M.ip_stats(_sums(spark, sf_dir, unbiased_specs()), D), "mse", "law").select("method", "p", "b", "rescale", "mse", "law")


_FAIL = "SELECT method, p, b, rescale, eps, round(avg(CASE WHEN abs(hat - ip) > eps THEN 1.0 ELSE 0.0 END), 6) AS failure FROM pa, (VALUES (0.02e0), (0.05e0), (0.1e0)) t(eps) GROUP BY ALL"


@query("failure_rate", lambda: _pairs_sql(unbiased_specs(), _FAIL, sketches()))
def failure_rate(spark, sf_dir):
    return rounded(M.failure_rate(_sums(spark, sf_dir, unbiased_specs() + sketches(), eps=EPS), EPS).drop("seed"), "failure")


@query("bits_needed", lambda: _pairs_sql(unbiased_specs(), f", f AS ({_FAIL}) SELECT method, p, rescale, eps, min(b) FILTER (failure <= 0.1) AS bits FROM f GROUP BY ALL", sketches()))
def bits_needed(spark, sf_dir):
    return M.bits_needed(M.failure_rate(_sums(spark, sf_dir, unbiased_specs() + sketches(), eps=EPS), EPS), 0.1)


@query("signbit_estimate_stats", lambda: f"WITH {S.base(sketches((2,))[0])},{S.signbit_rows(sketches((2,))[0], EVERY, 'pr')} SELECT method, b, count(*) AS pairs, round(avg(pow(hat - ip, 2)), 6) AS mse, round(avg(hat - ip), 6) + 0 AS bias, round(regr_slope(hat, ip), 6) AS slope FROM pr GROUP BY ALL")
def signbit_estimate_stats(spark, sf_dir):
    x = rounded(M.ip_stats(_sums(spark, sf_dir, sketches((2,))), D), "mse", "bias", "slope")
    return x.select("method", "b", "pairs", "mse", (F.col("bias") + 0).alias("bias"), "slope")


# search -----------------------------------------------------------------------


def named(specs: list[QuantizerSpec]) -> dict[str, QuantizerSpec | None]:
    """Specs by name, and full precision; the names are unpacked again by unnamed()."""
    return {"exact": None} | {f"{s.codebook}:{s.p}:{s.b}:{s.seed}": s for s in specs}


def unnamed(df: DataFrame, *cols: str) -> DataFrame:
    part = F.split("method", ":")
    kinds = {"method": part[0], "p": part[1].cast("int"), "b": part[2].cast("int"), "seed": part[3].cast("int")}
    return df.select(*[kinds[c].alias(c) if c in kinds else c for c in cols])


def recall_rows(queries: DataFrame, db: DataFrame, specs: list[QuantizerSpec], ks=KS, **rows) -> DataFrame:
    """method, p, b, seed, k, recall: where each method puts the exact best row, counted in one scan for all methods."""
    by_name = {name: s for name, s in named(specs).items() if s}
    return unnamed(rounded(M.recall_of_ranks(ranks_of_best(queries, db, by_name, max(ks), **rows), ks), "recall"), "method", "p", "b", "seed", "k", "recall")


def _recall(b, spark, sf_dir):
    return recall_rows(*database(spark, sf_dir), unbiased_specs((b,))).drop("seed")


_FIRST = """, rt AS (SELECT query_id, arg_min(vec_id, rn) AS best FROM (SELECT query_id, vec_id, row_number() OVER (PARTITION BY query_id ORDER BY round(ip, 9) DESC, vec_id) AS rn
   FROM (SELECT DISTINCT query_id, vec_id, ip FROM {one})) GROUP BY query_id),
rf AS (SELECT method, p, b, query_id, vec_id, row_number() OVER (PARTITION BY method, p, b, query_id ORDER BY round(hat, 9) DESC, vec_id) AS r FROM pa),
rh AS (SELECT rf.method, rf.p, rf.b, rt.query_id, rf.r FROM rt JOIN rf ON rt.query_id = rf.query_id AND rt.best = rf.vec_id)
SELECT method, p, b, k, round(avg(CASE WHEN r <= k THEN 1.0 ELSE 0.0 END), 6) AS recall FROM rh, (VALUES {ks}) v(k) GROUP BY ALL"""


def recall_tail(one: str) -> str:
    return _FIRST.format(one=one, ks=", ".join(f"({k})" for k in KS))


def _recall_sql(b) -> str:
    return _pairs_sql(unbiased_specs((b,)), recall_tail("pr WHERE method = 'gauss_scalar'"))


query("recall_2bit", partial(_recall_sql, 2))(partial(_recall, 2))
query("recall_4bit", partial(_recall_sql, 4))(partial(_recall, 4))


def _recall_sign_sql() -> str:
    two = sketches((2, 4))
    more = ",".join(S.signbit_rows(s, EVERY, f"sb{s.b}") for s in two)
    return f"WITH {S.base(two[0])},{more}, pa AS (SELECT * FROM sb2 UNION ALL SELECT * FROM sb4) {recall_tail('sb2')}"


@query("recall_signbit", _recall_sign_sql)
def recall_signbit(spark, sf_dir):
    return recall_rows(*database(spark, sf_dir), sketches((2, 4))).drop("seed")


@query(
    "neighbour_overlap",
    lambda: _pairs_sql(
        [spec("ball_block", 3, 2, "unbiased")],
        """, a AS (SELECT query_id, vec_id FROM pr QUALIFY row_number() OVER (PARTITION BY query_id ORDER BY round(ip, 9) DESC, vec_id) <= 10),
c AS (SELECT query_id, vec_id FROM pr QUALIFY row_number() OVER (PARTITION BY query_id ORDER BY round(hat, 9) DESC, vec_id) <= 10)
SELECT a.query_id, round(count(c.vec_id) / 10.0, 6) AS overlap FROM a LEFT JOIN c ON a.query_id = c.query_id AND a.vec_id = c.vec_id GROUP BY 1""",
    ),
)
def neighbour_overlap_10(spark, sf_dir):
    q, db = database(spark, sf_dir)
    s = spec("ball_block", 3, 2, "unbiased")
    return neighbour_overlap(exact_topk(q, db, 10), topk(q, encode(db, s), s, 10))


def _lookup_sql(specs: list[QuantizerSpec]) -> str:
    """Blocks, agreement with the full search and excess error, from the cell lists as literals."""
    full = {s.b: replace(s, assign="exact") for s in specs}
    parts = [S.base(specs[0], where=f"vec_id % {EVERY} <> 0"), *(S.coded(s, f"fx{b}") for b, s in full.items()), *(S.looked_up(s, f"lk{i}") for i, s in enumerate(specs))]
    rows = []
    for i, s in enumerate(specs):
        books = ", ".join(f"{S.literal(b)} AS o{n}" for n, b in S.codec(s).books.items())
        at, back = 0, []
        for n, _, count in S.codec(s)._blocks():
            back.append(f"flatten(list_transform(list_slice(l.code, {at + 1}, {at + count}), lambda k: o{n}[k + 1]))")
            at += count
        err = lambda v: f"sum(list_sum(list_transform(list_zip(x.z, {v}), lambda p: pow(p[1] - p[2], 2))))"
        sizes = S.codec(s).tables[s.p].sizes.mean()
        rows.append(f"""SELECT '{s.assign}' AS assign, {s.p} AS p, {s.b} AS b, CAST(sum(len(x.code)) AS BIGINT) AS blocks,
 round(sum(len(list_filter(list_zip(x.code, l.code), lambda p: p[1] = p[2]))) / CAST(sum(len(x.code)) AS DOUBLE), 6) AS agreement,
 round({err(f"list_concat({', '.join(back)})" if len(back) > 1 else back[0])} / {err("x.zb")} - 1, 6) + 0 AS excess, round({float(sizes)!r}, 6) AS candidates, {float(len(S.codec(s).books[s.p]))} AS book
 FROM fx{s.b} x JOIN lk{i} l ON x.vec_id = l.vec_id, (SELECT {books})""")
    return f"WITH {','.join(parts)} {' UNION ALL '.join(rows)}"


#: Cells are few, so that the lists can be literals of the SQL.
COARSE = [spec("ball_block", 3, b, assign=a, cells=8, n_cand=8) for b in (2, 3) for a in ("safe", "top")]


@query("lookup_agreement", partial(_lookup_sql, COARSE))
def lookup_agreement(spark, sf_dir):
    """Lists of coarse cells against the full search: safe ones agree in every block, short ones in most."""
    x = rounded(M.lookup_quality(database(spark, sf_dir)[1], COARSE), "agreement", "excess", "candidates")
    return x.withColumn("excess", F.col("excess") + 0)


@query("lookup_ablation")
def lookup_ablation(spark, sf_dir):
    """The lists that the experiments use: 32 cells an axis, 16 candidates."""
    x = M.lookup_quality(database(spark, sf_dir)[1], [spec("ball_block", 3, b, assign="top") for b in (2, 3, 4)])
    return rounded(x, "agreement", "excess", "candidates")


# closed forms -----------------------------------------------------------------


def _values(rows: list[dict]) -> str:
    text = lambda v: "NULL" if v is None else f"'{v}'" if isinstance(v, str) else repr(v)
    return "SELECT * FROM (VALUES " + ", ".join("(" + ", ".join(map(text, r.values())) + ")" for r in rows) + f") t({', '.join(rows[0])})"


#: Families, block sizes and bits whose limits SQL integrates for itself.
COMPUTED = [(f, p, b) for f, p in (*FAMILY, ("sphere_scalar_signbit", 1)) for b in BITS if (p, b) != (3, 4)]


def _limits_sql() -> str:
    """lim: criterion, method, p, b, value by numerical integration over the law of a block in many dimensions, with the codebooks as literals."""
    normal = "g AS (SELECT t, exp(-t * t / 2) / sqrt(2 * pi()) * 0.0005 AS w FROM (SELECT -9 + 0.0005e0 * i AS t FROM range(0, 36001) r(i)))"
    sides = ", ".join(f"({b}, {S.literal(gauss_scalar(b, 1))})" for b in BITS)
    scalar = f"""sq AS (SELECT b, unnest(q) AS q FROM (VALUES {sides}) v(b, q)),
sw AS (SELECT b, q, (q + lag(q) OVER o) / 2 AS lo, (q + lead(q) OVER o) / 2 AS hi FROM sq WINDOW o AS (PARTITION BY b ORDER BY q)),
sm AS (SELECT b, sum(w * (t - q) * (t - q)) AS mse FROM sw JOIN g ON (lo IS NULL OR t > lo) AND (hi IS NULL OR t <= hi) GROUP BY b),
gs AS (SELECT b, s, sum(w * pow(abs(t) - s * (least(floor(abs(t) / s), pow(2, b - 1) - 1) + 0.5), 2)) AS mse
  FROM (VALUES (1), (2), (3), (4)) v(b), (SELECT 0.05 + 0.002 * i AS s FROM range(0, 900) r(i)), g WHERE CAST(round((t + 9) / 0.0005) AS BIGINT) % 20 = 0 GROUP BY b, s),
gm AS (SELECT b, min(mse) * 20 AS mse FROM gs GROUP BY b)"""
    blocks = []
    for p, bits in ((2, BITS), (3, (1, 2, 3))):
        n, d = theory.RADII, theory.MANY
        way = "[cos((k + 0.5) * 2 * pi() / {n}), sin((k + 0.5) * 2 * pi() / {n})]" if p == 2 else "[sqrt(1 - pow(1 - (2 * k + 1) / {n}e0, 2)) * cos(k * pi() * (3 - sqrt(5e0))), sqrt(1 - pow(1 - (2 * k + 1) / {n}e0, 2)) * sin(k * pi() * (3 - sqrt(5e0))), 1 - (2 * k + 1) / {n}e0]"
        blocks.append(f"""r{p} AS (SELECT (i + 0.5) * {9 / d**0.5!r} / {n} AS r FROM range(0, {n}) t(i)),
w{p} AS (SELECT r, pow(r, {p - 1}) * pow(1 - r * r, {(d - p - 2) / 2}) AS w FROM r{p}),
p{p} AS (SELECT {', '.join(f'r * a[{i + 1}] AS x{i}' for i in range(p))}, w / (sum(w) OVER ()) AS w, i FROM (SELECT r, w, k AS i, {way.format(n=n)} AS a FROM w{p}, range(0, {n}) t(k))),
b{p} AS (SELECT b, unnest(o) AS o FROM (VALUES {', '.join(f'({b}, {S.literal(theory.wide_book(p, b))})' for b in bits)}) v(b, o)),
n{p} AS (SELECT b, w, min({' + '.join(f'pow(x{i} - o[{i + 1}], 2)' for i in range(p))}) AS m FROM p{p}, b{p} GROUP BY b, w, {', '.join(f'x{i}' for i in range(p))}),
m{p} AS (SELECT b, sum(w * m) * {d} / {p} AS mse FROM n{p} GROUP BY b)""")
    rows = [f"SELECT '{f}' AS method, {p} AS p, b, mse FROM {t}" for f, p, t in (("gauss_scalar", 1, "sm"), ("sphere_scalar", 1, "sm"), ("grid_dir", 1, "gm"), ("ball_block", 2, "m2"), ("ball_block", 3, "m3"))]
    return f"""{normal},{scalar},{','.join(blocks)}, ms AS ({' UNION ALL '.join(rows)}),
lim AS (SELECT 'mse' AS criterion, method, p, b, mse AS value FROM ms UNION ALL SELECT 'ip', method, p, b, mse / (1 - mse) FROM ms WHERE method <> 'sphere_scalar'
  UNION ALL SELECT 'ip', 'sphere_scalar_signbit', 1, b, pi() / 2 * coalesce((SELECT mse FROM sm WHERE sm.b = v.b - 1), 1) FROM (VALUES (1), (2), (3), (4)) v(b))"""


def _beside_sql(tail: str) -> str:
    """me: criterion, method, p, b, measured on the table: errors of reconstruction, and of inner products times d - 1; lim: the limits."""
    return _pairs_sql(unbiased_specs(), f""", er AS ({_ERR_ROWS}), me AS (SELECT 'mse' AS criterion, method, p, b, avg(err) AS measured FROM er WHERE rescale = 'best' AND vec_id % {EVERY} <> 0 GROUP BY ALL
 UNION ALL SELECT 'ip', method, p, b, avg(pow(hat - ip, 2)) * {D - 1} FROM pa GROUP BY ALL), {_limits_sql()}{tail}""", sketches())


def _measured(spark, sf_dir) -> DataFrame:
    e = _errors(spark, sf_dir, all_specs()).where("rescale = 'best'").groupBy("method", "p", "b").agg(F.avg("err").alias("measured"))
    pairs = M.ip_stats(_sums(spark, sf_dir, unbiased_specs() + sketches()), D).select(F.lit("ip").alias("criterion"), "method", "p", "b", F.col("scaled").alias("measured"))
    return e.withColumn("criterion", F.lit("mse")).unionByName(pairs)


_ON = ["criterion", "method", "p", "b"]


@query("theory_computed", lambda: _beside_sql(" SELECT l.criterion, l.method, l.p, l.b, round(value, 4) AS value, round(measured, 6) AS measured FROM lim l LEFT JOIN me ON me.criterion = l.criterion AND me.method = l.method AND me.p = l.p AND me.b = l.b"))
def theory_computed(spark, sf_dir):
    """Limits of both criteria for many dimensions, computed from the codebooks, beside what the table's vectors measure."""
    rows = [("mse", f, p, b, theory.mse(f, p, b)) for f, p, b in COMPUTED if f != "sphere_scalar_signbit"]
    rows += [("ip", f, p, b, theory.ip(f, p, b, 2) * (2 if f == "sphere_scalar_signbit" else 1)) for f, p, b in COMPUTED if f != "sphere_scalar"]
    limits = spark.createDataFrame(rows, "criterion string, method string, p int, b int, value double").withColumn("value", F.round("value", 4))
    return rounded(limits.join(_measured(spark, sf_dir), _ON, "left"), "measured")


_PUBLISHED = """c(criterion, method, p, b1, b2, b3, b4) AS (VALUES ('mse', 'gauss_scalar', 1, 0.363, 0.117, 0.0345, 0.0095), ('mse', 'grid_dir', 1, 0.363, 0.119, 0.0374, 0.0115),
 ('mse', 'sphere_scalar', 1, 0.363, 0.117, 0.0345, 0.0095), ('mse', 'ball_block', 2, 0.363, 0.108, 0.0297, 0.0078), ('mse', 'ball_block', 3, 0.357, 0.101, 0.0271, 0.0071),
 ('ip', 'gauss_scalar', 1, 0.571, 0.133, 0.0358, 0.0096), ('ip', 'grid_dir', 1, 0.571, 0.135, 0.0389, 0.0117), ('ip', 'sphere_scalar_signbit', 1, 1.57, 0.56, 0.18, 0.047),
 ('ip', 'ball_block', 2, 0.571, 0.120, 0.0306, 0.0078), ('ip', 'ball_block', 3, 0.553, 0.113, 0.0279, 0.0071)),
l AS (SELECT criterion, method, p, unnest([1, 2, 3, 4]) AS b, CAST(unnest([b1, b2, b3, b4]) AS DOUBLE) AS value FROM c)"""


@query("theory_table", lambda: _beside_sql(f""", {_PUBLISHED},
cell(p, g) AS (VALUES (1, 1 / 12e0), (2, 5 / (36 * sqrt(3e0))), (3, 19 / (192 * pow(2e0, 1 / 3e0)))),
h AS (SELECT criterion || '_high_rate' AS criterion, c.method, c.p, CAST(NULL AS INTEGER) AS b, 2 * pi() * g * pow((c.p + 2) / CAST(c.p AS DOUBLE), (c.p + 2) / 2e0) * CASE WHEN method = 'sphere_scalar_signbit' THEN 2 * pi() ELSE 1 END AS value
 FROM c JOIN cell ON c.p = cell.p WHERE method <> 'grid_dir')
SELECT l.criterion, l.method, l.p, l.b, round(l.value, 6) AS value, abs(lim.value / l.value - 1) < 0.04 AS reached, round(measured, 6) AS measured FROM l LEFT JOIN me ON l.criterion = me.criterion AND l.method = me.method AND l.p = me.p AND l.b = me.b LEFT JOIN lim ON l.criterion = lim.criterion AND l.method = lim.method AND l.p = lim.p AND l.b = lim.b
UNION ALL SELECT criterion, method, p, b, round(value, 6), NULL, NULL FROM h"""))
def theory_table(spark, sf_dir):
    """Published constants; whether what is computed here comes within four hundredths of each (null where SQL does not compute it), and what the table's vectors measure."""
    close = {("mse", f, p, b): theory.mse(f, p, b) for f, p, b in COMPUTED if f != "sphere_scalar_signbit"} | {("ip", f, p, b): theory.ip(f, p, b, 2) * (2 if f == "sphere_scalar_signbit" else 1) for f, p, b in COMPUTED}
    rows = []
    for r in theory.table(D):
        own = close.get((r["criterion"], r["method"], r["p"], r["b"]))
        rows.append((*r.values(), None if own is None else abs(own / r["value"] - 1) < 0.04))
    known = spark.createDataFrame(rows, "criterion string, method string, p int, b int, value double, reached boolean")
    return rounded(known.join(_measured(spark, sf_dir), _ON, "left"), "value", "measured")


_GAP = [spec("ball_block", 3, b) for b in BITS]


@query("shannon_gap", lambda: _err_sql(_GAP, """, e AS (SELECT 64 AS d, b, avg(err) AS mse FROM er WHERE rescale = 'best' GROUP BY ALL),
a(d) AS (VALUES (64), (100), (1000)), f AS (SELECT d, exp(lgamma(1 + 2e0 / (d - 1)) + 2e0 / (d - 1) * (ln(2 * sqrt(pi())) + lgamma((d + 1) / 2e0) - lgamma(d / 2e0))) AS upper,
 -0.5772156649015329 - 2 * ln(2e0) AS psi_half,
 -0.5772156649015329 + list_sum(list_transform(range(1, CAST(d / 2 AS BIGINT)), lambda k: 1e0 / k)) AS psi FROM a),
s AS (SELECT d, upper, exp(ln((d - 1) / (2 * pi() * exp(1e0))) + 2e0 / (d - 1) * (d / 2e0 * ln(pi()) - lgamma(d / 2e0)) + (psi_half - psi) / (d - 1)) AS lower FROM f),
g AS (SELECT d, b, upper * pow(4e0, -b * d / (d - 1e0)) AS upper, lower * pow(4e0, -b * d / (d - 1e0)) AS lower FROM s, (VALUES (1), (2), (3), (4)) t(b))
SELECT g.d, g.b, round(upper, 6) AS upper, round(lower, 6) AS lower, round(mse, 6) AS measured, round(mse / lower, 6) AS gap FROM g LEFT JOIN e ON g.d = e.d AND g.b = e.b"""))
def shannon_gap(spark, sf_dir):
    """Both bounds, and how far above the lower one blocks of three are on the table's vectors (null for widths that it does not have)."""
    rows = [(d, b, theory.full_sphere_upper(b, d), theory.shannon_lower(b, d)) for d in (64, 100, 1000) for b in (1, 2, 3, 4)]
    e = _errors(spark, sf_dir, _GAP).where("rescale = 'best'").groupBy(F.lit(D).alias("d"), "b").agg(F.avg("err").alias("measured"))
    x = spark.createDataFrame(rows, "d int, b int, upper double, lower double").join(e, ["d", "b"], "left")
    return rounded(x.withColumn("gap", F.col("measured") / F.col("lower")), "upper", "lower", "measured", "gap")


@query("bit_curves", """WITH a AS (SELECT CAST(max(len(embedding)) AS INTEGER) AS d, count(embedding) AS n FROM embeddings UNION ALL SELECT 1536, count(text) FROM documents)
SELECT d, n, eps, delta, round(log2(greatest(1.0, ln(1 / delta) / (d * eps * eps)) + 1), 6) AS bits, round(log2(greatest(1.0, ln(greatest(n, 1) / delta) / (d * eps * eps)) + 1), 6) AS bits_all,
 ln(1 / delta) / eps <= d AS low_accuracy, d <= ln(1 / delta) / (eps * eps) AS high_accuracy FROM a, (VALUES (0.01e0), (0.05e0), (0.1e0)) b(eps), (VALUES (0.01e0), (0.001e0)) c(delta)""")
def bit_curves(spark, sf_dir):
    """Bits for one product with a query, and for those with all n vectors of a table: embeddings, and texts hashed to 1536 dimensions."""
    own = read_vectors(spark, sf_dir).agg(F.max(F.size("embedding")).alias("d"), F.count("embedding").alias("n"))
    texts = read_table(spark, sf_dir, "documents", "text").agg(F.lit(1536).alias("d"), F.count("text").alias("n"))
    eps, delta = (spark.createDataFrame([(x,) for x in xs], f"{name} double") for name, xs in (("eps", (0.01, 0.05, 0.1)), ("delta", (0.01, 0.001))))
    sure, d, e = F.log(1 / F.col("delta")), F.col("d"), F.col("eps")
    bits = lambda x: F.round(F.log2(F.greatest(F.lit(1.0), x / (d * e * e)) + 1), 6)
    rows = own.unionByName(texts).crossJoin(F.broadcast(eps.crossJoin(delta)))
    return rows.select("d", "n", "eps", "delta", bits(sure).alias("bits"), bits(F.log(F.greatest("n", F.lit(1)) / F.col("delta"))).alias("bits_all"), (sure / e <= d).alias("low_accuracy"), (d <= sure / (e * e)).alias("high_accuracy"))


@query("effective_bits", f"""WITH n AS (SELECT count(*) AS vectors, sum(len(embedding)) AS coordinates FROM embeddings WHERE vec_id % {EVERY} <> 0),
s AS (SELECT method, p, b, rescale, vectors, coordinates, CAST(coordinates * b + CASE WHEN rescale = 'raw' THEN 0 ELSE 32 * vectors END AS BIGINT) AS stored
 FROM n, (VALUES ('gauss_scalar', 1), ('sphere_scalar', 1), ('grid_dir', 1), ('ball_block', 2), ('ball_block', 3)) m(method, p), (VALUES (1), (2), (3), (4)) t(b), (VALUES ('raw'), ('best'), ('unbiased')) r(rescale))
SELECT method, p, b, rescale, vectors, stored, round(stored / CAST(coordinates AS DOUBLE), 6) AS bits, round(32 * coordinates / CAST(stored AS DOUBLE), 6) AS ratio FROM s""")
def effective_bits(spark, sf_dir):
    """Bits that the packed codes and scales of the database take, of all vectors and a coordinate, beside 32."""
    x = M.stored_bytes(database(spark, sf_dir)[1], all_specs()).crossJoin(F.broadcast(spark.createDataFrame([("raw", 0), ("best", 32), ("unbiased", 32)], "rescale string, side int")))
    x = x.withColumn("stored", F.col("bytes") * 8 + F.col("side") * F.col("vectors"))
    return rounded(x.select("method", "p", "b", "rescale", "vectors", "stored", (F.col("stored") / F.col("coordinates")).alias("bits"), (F.col("coordinates") * 32 / F.col("stored")).alias("ratio")), "bits", "ratio")


SPHERES = ((3, 2), (3, 3), (4, 2))

_BOUNDS = """a(d) AS (VALUES (3), (4)), f AS (SELECT d, exp(lgamma(1 + 2e0 / (d - 1)) + 2e0 / (d - 1) * (ln(2 * sqrt(pi())) + lgamma((d + 1) / 2e0) - lgamma(d / 2e0))) AS upper,
 exp(ln((d - 1) / (2 * pi() * exp(1e0))) + 2e0 / (d - 1) * (d / 2e0 * ln(pi()) - lgamma(d / 2e0)) + (-0.5772156649015329 - 2 * ln(2e0) - CASE d WHEN 3 THEN 2 - 0.5772156649015329 - 2 * ln(2e0) ELSE 1 - 0.5772156649015329 END) / (d - 1)) AS lower FROM a)"""


def _spheres_sql() -> str:
    from ..functions.codebooks import full_sphere

    away = lambda d: " + ".join(f"pow(w[{k + 1}] / r - o[{k + 1}], 2)" for k in range(d))
    parts = [f"""SELECT {d} AS d, {b} AS b, count(*) AS n, avg(m) AS mse FROM (SELECT list_min(list_transform(os, lambda o: {away(d)})) AS m
 FROM (SELECT w, sqrt(list_dot_product(w, w)) AS r FROM ({_blocks_sql(d)})), (SELECT {S.literal(full_sphere(d, b))} AS os) WHERE r > 0)""" for d, b in SPHERES]
    return f"""WITH {S.base(spec("sphere_scalar", 1, 1), where=f"vec_id % {EVERY} <> 0")}, {_BOUNDS}, m AS ({' UNION ALL '.join(parts)})
SELECT m.d, b, n, round(mse, 6) AS mse, round(upper * pow(4e0, -b * m.d / (m.d - 1e0)), 6) AS upper, round(lower * pow(4e0, -b * m.d / (m.d - 1e0)), 6) AS lower FROM m JOIN f ON m.d = f.d"""


@query("full_sphere_bounds", _spheres_sql)
def full_sphere_bounds(spark, sf_dir):
    """The sphere quantizer of tiny dimension between its bounds, on the directions of all blocks of the rotated database."""
    from ..functions.codebooks import full_sphere

    x = M.block_distortion(database(spark, sf_dir)[1], spec("sphere_scalar", 1, 1), {(d, b): full_sphere(d, b) for d, b in SPHERES}, unit=True).withColumnRenamed("p", "d")
    bounds = spark.createDataFrame([(d, b, theory.full_sphere_upper(b, d), theory.shannon_lower(b, d)) for d, b in SPHERES], "d int, b int, upper double, lower double")
    return rounded(x.join(F.broadcast(bounds), ["d", "b"]), "mse", "upper", "lower")


def _blocks_sql(p: int) -> str:
    """w: blocks of p coordinates of the rotated database."""
    return f"SELECT unnest(list_transform(range(0, {D // p}), lambda j: list_slice(z, {p} * j + 1, {p} * j + {p}))) AS w FROM zt"


@query("codebook_distortion", lambda: f"""WITH {S.base(spec("ball_block", 2, 2), where=f"vec_id % {EVERY} <> 0")}, o AS (SELECT {S.literal(S.codec(spec("ball_block", 2, 2)).books[2])} AS os)
SELECT 2 AS p, 2 AS b, count(*) AS n, round(avg(m), 6) AS mse FROM (SELECT list_min(list_transform(os, lambda c: pow(w[1] - c[1], 2) + pow(w[2] - c[2], 2))) AS m FROM ({_blocks_sql(2)}), o)""")
def codebook_distortion(spark, sf_dir):
    """The cost of a block codebook, which never saw data, on all blocks of the rotated database."""
    s = spec("ball_block", 2, 2)
    return rounded(M.block_distortion(database(spark, sf_dir)[1], s, {(2, 2): S.codec(s).books[2]}), "mse")


def ranked(df: DataFrame, by: str, order: str) -> DataFrame:
    return df.withColumn("rank", F.row_number().over(Window.partitionBy(by).orderBy(order)))


__all__ = ["QUERIES", "SQL", "read_table"]
