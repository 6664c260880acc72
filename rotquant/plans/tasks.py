"""Workloads on texts, caches and events."""

from __future__ import annotations

from dataclasses import replace
from functools import reduce

from pyspark import StorageLevel
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..model import QuantizerSpec
from ..operators import cache as C
from ..operators import metrics as M
from ..operators.quantize import encode
from ..operators.search import Asked, exact_topk, topk_by_method, topk_of_sets
from ..sources.tables import read_table, text_vectors
from ..streaming.windows import event_features, sessions, tumbling, user_vectors
from . import sql as S
from .workloads import EVERY, FAMILY, SEEDS, decoded, decoded_sql, query, recall_rows, recall_tail, rounded

TEXT_D = 192

_TEXT = f"""
t AS (SELECT CAST(doc_id AS BIGINT) AS doc_id, unnest(string_split(translate(lower(text), chr(9) || chr(10) || chr(12) || chr(13), '    '), ' ')) AS w FROM documents),
h AS (SELECT doc_id, md5(w) AS m FROM t WHERE w <> ''),
c AS (SELECT doc_id, CAST('0x' || substr(m, 1, 8) AS BIGINT) % {TEXT_D} AS i, sum(CASE WHEN CAST('0x' || substr(m, 9, 1) AS BIGINT) % 2 = 0 THEN 1 ELSE -1 END) AS v FROM h GROUP BY 1, 2),
n AS (SELECT doc_id, sqrt(CAST(sum(v * v) AS DOUBLE)) AS norm FROM c GROUP BY 1 HAVING sum(v * v) > 0)"""


@query("text_vectors_192", f"WITH {_TEXT} SELECT n.doc_id AS vec_id, count(*) FILTER (v <> 0) AS filled, round(CAST(sum(i * v) AS DOUBLE) / any_value(norm), 6) AS moment FROM n JOIN c ON n.doc_id = c.doc_id GROUP BY 1")
def text_vectors_192(spark, sf_dir) -> DataFrame:
    v = text_vectors(read_table(spark, sf_dir, "documents", "doc_id", "text"), TEXT_D)
    moment = F.aggregate(F.transform("embedding", lambda x, i: x * i), F.lit(0.0), lambda a, x: a + x)
    return v.select("vec_id", F.size(F.filter("embedding", lambda x: x != 0)).cast("long").alias("filled"), F.round(moment, 6).alias("moment"))


#: Dense unit vectors tv(vec_id, embedding) of the texts.
_TEXT_VECTORS = f"""{_TEXT},
sp AS (SELECT n.doc_id, list(i) AS i, list(v / norm) AS x FROM n JOIN c ON n.doc_id = c.doc_id GROUP BY 1),
tv AS (SELECT doc_id AS vec_id, list_transform(range(0, {TEXT_D}), lambda k: coalesce(x[list_position(i, k)], 0e0)) AS embedding FROM sp)"""


def wide_specs(d: int, bits, families=FAMILY, assign: str = "exact") -> list[QuantizerSpec]:
    return [QuantizerSpec(f, "unbiased", d, p, b, assign=assign if p > 1 else "exact") for f, p in families for b in bits]


def _texts(spark, sf_dir, d: int) -> DataFrame:
    return text_vectors(read_table(spark, sf_dir, "documents", "doc_id", "text"), d)


def _recall_text(d: int, specs: list[QuantizerSpec]):
    def run(spark, sf_dir):
        docs = read_table(spark, sf_dir, "documents", "doc_id", "text")
        texts = docs.select(F.col("doc_id").alias("vec_id"), F.col("text").alias("embedding"))  # hashed where they are scored
        return recall_rows(text_vectors(docs.where(F.col("doc_id") % EVERY == 0), d), texts.where(F.col("vec_id") % EVERY != 0), specs, text_width=d).drop("seed")

    return run


_SMALL = wide_specs(TEXT_D, (2,), [f for f in FAMILY if f != ("grid_dir", 1)])


def _recall_text_sql() -> str:
    """Codes of the texts by brute force; the best by the exact products of the same pairs."""
    more = S.signbit_rows(_SIGN, EVERY, "sb2")
    return f"""WITH {_TEXT_VECTORS},{S.base(_SMALL[0], 'tv')},{S.scalars(_SMALL)},{S.pair_rows(_SMALL, EVERY)},{more},
pa AS (SELECT method, p, b, query_id, vec_id, ip, hat FROM pr UNION ALL SELECT method, p, b, query_id, vec_id, ip, hat FROM sb2) {recall_tail("sb2")}"""


_SIGN = QuantizerSpec("sphere_scalar_signbit", "raw", TEXT_D, 1, 2)

query("recall_text192", _recall_text_sql)(_recall_text(TEXT_D, [*_SMALL, _SIGN]))
#: All methods; blocks of 3 are coded by their candidate lists, as books of 4096 words are long.
query("recall_text192_all")(_recall_text(TEXT_D, [*wide_specs(TEXT_D, (2, 4), assign="top"), *(QuantizerSpec("sphere_scalar_signbit", "raw", TEXT_D, 1, b) for b in (2, 4))]))
query("recall_text1536")(_recall_text(1536, [*wide_specs(1536, (2, 4), assign="top"), *(QuantizerSpec("sphere_scalar_signbit", "raw", 1536, 1, b) for b in (2, 4))]))
query("recall_text3072")(_recall_text(3072, wide_specs(3072, (2,), assign="top")))


# caches -------------------------------------------------------------------------

CACHES = {
    "ball_block": C.CacheSpec(), "gauss_scalar": C.CacheSpec("gauss_scalar", 1), "grid_dir": C.CacheSpec("grid_dir", 1),
    "sphere_scalar": C.CacheSpec("sphere_scalar", 1, "raw"), "sphere_scalar_signbit": C.CacheSpec("sphere_scalar_signbit", 1, "raw"),
}


def seeded(methods=tuple(CACHES)) -> dict[str, C.CacheSpec]:
    """Every method under five rotations, by name:seed."""
    return {f"{m}:{k}": replace(CACHES[m], seed=k) for m in methods for k in SEEDS}


def by_seed(df: DataFrame) -> DataFrame:
    part = F.split("method", ":")
    return df.withColumn("seed", F.coalesce(F.get(part, F.lit(1)).cast("int"), F.lit(0))).withColumn("method", part[0])


def mean_and_std(df: DataFrame, by: tuple[str, ...], *values: str) -> DataFrame:
    each = [x for v in values for x in (F.round(F.avg(v), 6).alias(v), F.round(F.stddev_samp(v), 6).alias(f"{v}_std"))]
    return df.groupBy(*by).agg(F.count("*").alias("seeds"), *each)


def _token_rows(spark, sf_dir) -> DataFrame:
    return C.token_rows(read_table(spark, sf_dir, "conversations", "conv_id", "turn", "text"))


def _state(kind: str) -> str:
    """128 components of a token's state as a list, from 32 digests."""
    scale = " * CASE WHEN (c * 37 + head * 11) % 128 < 32 THEN 4 + 0.25 * (c % 8) ELSE 1 END" if kind == "k" else ""
    return f"list_transform([list_transform(range(0, 32), lambda g: md5(token || ':{kind}' || head || ':' || g))], lambda m: list_transform(range(0, 128), lambda c: (CAST('0x' || substr(m[c // 4 + 1], 1 + 8 * (c % 4), 8) AS BIGINT) / 4294967296e0 - 0.5){scale}))[1]"


_TOKENS = """rw AS (SELECT conv_id, turn, unnest(string_split(translate(lower(text), chr(9) || chr(10) || chr(12) || chr(13), '    '), ' ')) AS token,
  generate_subscripts(string_split(translate(lower(text), chr(9) || chr(10) || chr(12) || chr(13), '    '), ' '), 1) AS i FROM conversations),
tk AS (SELECT conv_id, turn, i, token FROM rw WHERE token <> '')"""
_CHANNELS = f"""{_TOKENS},
hd(head) AS (VALUES (0), (1)), n AS (SELECT token, count(*) AS n FROM tk GROUP BY 1),
ks AS (SELECT token, head, n, {_state('k')} AS k FROM n, hd),
sq AS (SELECT head, c AS channel, sqrt(sum(n * k[c + 1] * k[c + 1])) AS norm FROM ks, range(0, 128) r(c) GROUP BY 1, 2),
oc AS (SELECT head, channel, norm, row_number() OVER (PARTITION BY head ORDER BY round(norm, 9) DESC, channel) AS rank FROM sq)"""


@query("cache_outliers", f"WITH {_CHANNELS} SELECT CAST(head AS INTEGER) AS head, CAST(channel AS INTEGER) AS channel, CAST(rank AS INTEGER) AS rank, round(norm, 6) AS norm FROM oc WHERE rank <= 32")
def cache_outliers(spark, sf_dir):
    return rounded(C.outlier_channels(_token_rows(spark, sf_dir)), "norm")


def _cache_sql(methods: list[str]) -> str:
    """Attention on the stored caches of scalar methods, by literals and sums over tokens."""
    half = lambda x: f"(round(({x}) / pow(2e0, floor(log2({x})) - 10)) * pow(2e0, floor(log2({x})) - 10))"
    parts, rows = [], []
    for m, name in enumerate(methods):
        s = CACHES[name]
        for part, d, bits, r in (("hi", 32, s.b_hi, s.rescale), ("lo", 96, s.b_lo, s.rescale), ("v", 128, s.b_value, "best")):
            q, t = s.part(d, bits, r), f"{part}{m}"
            parts.append(f"{t}r AS (SELECT {S.literal(S.codec(q).rotation)} AS m), {t}z AS (SELECT token, head, norm, list_transform(m, lambda r: list_dot_product(r, x) / norm) AS z FROM {part}x, {t}r)")
            parts.append(S.coded(q, f"{t}c", f"{t}z"))
            scale = {"raw": "1.0", "best": "list_dot_product(z, zb) / list_dot_product(zb, zb)", "unbiased": "1.0 / list_dot_product(z, zb)"}[q.rescale]
            parts.append(f"{t} AS (SELECT token, head, {half(f'{scale} * norm')} AS f, zb FROM {t}c)")
        turn = lambda part: f"list_transform({part}{m}r.m, lambda r: list_dot_product(r, a.{part}q))"
        rows.append(f"""l{m} AS (SELECT a.conv_id, a.head, (h.f * list_dot_product(h.zb, a.hr) + o.f * list_dot_product(o.zb, a.lr)) / sqrt(128e0) AS l, t.n, t.token
  FROM (SELECT a.*, {turn('hi')} AS hr, {turn('lo')} AS lr FROM ask a, hi{m}r, lo{m}r) a JOIN ct t ON t.conv_id = a.conv_id JOIN hi{m} h ON h.token = t.token AND h.head = a.head JOIN lo{m} o ON o.token = t.token AND o.head = a.head),
o{m} AS (SELECT l.conv_id, l.head, c, sum(n * exp(l) * v.f * v.zb[c + 1]) / sum(n * exp(l)) AS x FROM l{m} l JOIN v{m} v ON v.token = l.token AND v.head = l.head, range(0, 128) r(c) GROUP BY 1, 2, 3),
t{m} AS (SELECT conv_id, head, list(x ORDER BY c) AS x FROM e GROUP BY 1, 2), y{m} AS (SELECT conv_id, head, list_transform(m, lambda r: list_dot_product(r, x)) AS x FROM t{m}, v{m}r),
d{m} AS (SELECT o.conv_id, o.head, sqrt(sum(pow(o.x - y.x[o.c + 1], 2))) / sqrt(sum(pow(y.x[o.c + 1], 2))) AS rel FROM o{m} o JOIN y{m} y ON y.conv_id = o.conv_id AND y.head = o.head GROUP BY 1, 2),
g{m} AS (SELECT l.conv_id, l.head, sqrt(sum(l.n * pow(l.l - e.l, 2)) / sum(l.n)) AS le FROM l{m} l JOIN le e ON e.conv_id = l.conv_id AND e.head = l.head AND e.token = l.token GROUP BY 1, 2)""")
    out = " UNION ALL ".join(f"SELECT '{name}' AS method, count(*) AS n, round(avg(rel), 6) AS output_error, round(avg(le), 6) AS logit_error FROM d{m} d JOIN g{m} g ON g.conv_id = d.conv_id AND g.head = d.head" for m, name in enumerate(methods))
    pick = lambda inside, x: f"list_transform(list_filter(range(0, 128), lambda c: {'' if inside else 'NOT '}list_contains(cs, c)), lambda c: {x}[c + 1])"
    return f"""WITH {_CHANNELS},
ch AS (SELECT head, list(channel) AS cs FROM oc WHERE rank <= 32 GROUP BY 1),
hix AS (SELECT token, ks.head, {pick(True, 'k')} AS x, sqrt(list_dot_product(x, x)) AS norm FROM ks JOIN ch ON ch.head = ks.head),
lox AS (SELECT token, ks.head, {pick(False, 'k')} AS x, sqrt(list_dot_product(x, x)) AS norm FROM ks JOIN ch ON ch.head = ks.head),
vx AS (SELECT token, head, {_state('v')} AS x, sqrt(list_dot_product(x, x)) AS norm FROM n, hd),
la AS (SELECT conv_id, arg_max(token, turn * 1000000 + i) AS token FROM tk GROUP BY 1),
aq AS (SELECT conv_id, head, {_state('q')} AS q FROM la, hd),
ask AS (SELECT conv_id, aq.head, q, {pick(True, 'q')} AS hiq, {pick(False, 'q')} AS loq FROM aq JOIN ch ON ch.head = aq.head),
ct AS (SELECT conv_id, token, count(*) AS n FROM tk GROUP BY 1, 2),
le AS (SELECT a.conv_id, a.head, t.token, t.n, list_dot_product(a.q, k.k) / sqrt(128e0) AS l FROM ask a JOIN ct t ON t.conv_id = a.conv_id JOIN ks k ON k.token = t.token AND k.head = a.head),
e AS (SELECT l.conv_id, l.head, c, sum(n * exp(l) * v.x[c + 1]) / sum(n * exp(l)) AS x FROM le l JOIN vx v ON v.token = l.token AND v.head = l.head, range(0, 128) r(c) GROUP BY 1, 2, 3),
{','.join(parts)}, {','.join(rows)} {out}"""


@query("cache_scalar_error", lambda: _cache_sql(["gauss_scalar", "sphere_scalar"]))
def cache_scalar_error(spark, sf_dir):
    """Errors of logits and of attention outputs on caches of two scalar methods."""
    rows = _token_rows(spark, sf_dir)
    e = C.attention_error(C.attend(rows, C.outlier_channels(rows), {m: CACHES[m] for m in ("gauss_scalar", "sphere_scalar")}))
    return rounded(e, "output_error", "logit_error")


@query("cache_attention_error")
def cache_attention_error(spark, sf_dir):
    """All methods at one budget, five rotations each: mean and deviation of the errors."""
    rows = _token_rows(spark, sf_dir)
    e = C.attention_error_by_token(rows, C.outlier_channels(rows), seeded())
    return mean_and_std(by_seed(e), ("method", "n"), "output_error", "logit_error")


@query("cache_bits", f"""WITH {_TOKENS}, t AS (SELECT count(*) AS tokens FROM tk)
SELECT 'keys' AS part, tokens, tokens * {C.HEADS} * (32 * 4 + 96 * 3 + 2 * 16) AS stored, (32 * 4 + 96 * 3 + 2 * 16) / 128e0 AS bits FROM t
UNION ALL SELECT 'values', tokens, tokens * {C.HEADS} * (128 * 2 + 16), (128 * 2 + 16) / 128e0 FROM t""")
def cache_bits(spark, sf_dir):
    """Bits that the caches of all conversations take, and bits a channel."""
    s, n = C.CacheSpec(), F.col("tokens")
    parts = F.explode(F.array(*[F.struct(F.lit(p).alias("part"), F.lit(b).alias("bits")) for p, b in (("keys", s.key_bits), ("values", s.value_bits))])).alias("x")
    t = _token_rows(spark, sf_dir).agg(F.count("token").alias("tokens"))
    return t.select("tokens", parts).select("x.part", "tokens", (n * C.HEADS * C.WIDTH * F.col("x.bits")).cast("long").alias("stored"), "x.bits")


@query("needle_positions", "SELECT CAST(item_id AS BIGINT) AS item_id, CAST(doc_id AS BIGINT) AS doc_id, round((strpos(d.text, b.text) - 1) / CAST(length(d.text) AS DOUBLE), 6) AS depth FROM documents d, benchmark b WHERE contains(d.text, b.text)")
def needle_positions(spark, sf_dir):
    return rounded(C.needle_positions(read_table(spark, sf_dir, "documents", "doc_id", "text"), read_table(spark, sf_dir, "benchmark", "item_id", "text")), "depth")


@query("needle_grid")
def needle_grid(spark, sf_dir):
    """Hits by method, depth and context on caches at 3.5 bits a key channel, mean and deviation over five rotations."""
    docs, items = read_table(spark, sf_dir, "documents", "doc_id", "text"), read_table(spark, sf_dir, "benchmark", "item_id", "text")
    grid = C.needle_grid(by_seed(C.needle_hits(docs, items, seeded())), ("method", "seed"))
    return mean_and_std(grid, ("method", "depth", "context", "n"), "score")


@query("needle_scores")
def needle_scores(spark, sf_dir):
    """One score a method, with its deviation over five rotations."""
    docs, items = read_table(spark, sf_dir, "documents", "doc_id", "text"), read_table(spark, sf_dir, "benchmark", "item_id", "text")
    hits = by_seed(C.needle_hits(docs, items, seeded())).groupBy("method", "seed").agg(F.avg("hit").alias("score"))
    return mean_and_std(hits, ("method",), "score")


_WORDS = "list_filter(string_split(translate(lower({x}), chr(9) || chr(10) || chr(12) || chr(13), '    '), ' '), lambda w: w <> '')"
_SLOT = f"CAST('0x' || substr(md5(w), 1, 8) AS BIGINT) % {C.WIDTH} AS i, sum(CASE WHEN CAST('0x' || substr(md5(w), 9, 1) AS BIGINT) % 2 = 0 THEN 1 ELSE -1 END) AS v"


@query("needle_exact", f"""WITH j AS (SELECT CAST(doc_id AS BIGINT) AS doc_id, CAST(item_id AS BIGINT) AS item_id, {_WORDS.format(x="d.text")} AS ws, {_WORDS.format(x="b.text")} AS qs,
  len({_WORDS.format(x="substr(d.text, 1, strpos(d.text, b.text) - 1)")}) AS pos FROM documents d, benchmark b WHERE contains(d.text, b.text)),
ch AS (SELECT doc_id, item_id, ws, unnest(range(0, greatest(1, len(ws) - {C.CHUNK - C.STRIDE}), {C.STRIDE})) AS s FROM j),
ct AS (SELECT doc_id, item_id, s, unnest(list_slice(ws, s + 1, s + {C.CHUNK})) AS w FROM ch), cv AS (SELECT doc_id, item_id, s, {_SLOT} FROM ct GROUP BY 1, 2, 3, 4),
qt AS (SELECT doc_id, item_id, unnest(qs) AS w FROM j), qv AS (SELECT doc_id, item_id, {_SLOT} FROM qt GROUP BY 1, 2, 3), qn AS (SELECT doc_id, item_id, sqrt(CAST(sum(v * v) AS DOUBLE)) AS norm FROM qv GROUP BY 1, 2),
cn AS (SELECT cv.doc_id, cv.item_id, s, sum(cv.v * coalesce(qv.v, 0)) / sqrt(CAST(sum(cv.v * cv.v) AS DOUBLE)) AS ip FROM cv LEFT JOIN qv ON qv.doc_id = cv.doc_id AND qv.item_id = cv.item_id AND qv.i = cv.i GROUP BY 1, 2, 3 HAVING sum(cv.v * cv.v) > 0),
sc AS (SELECT ch.doc_id, ch.item_id, ch.s, coalesce(round(ip / norm, 9), 0e0) AS ip FROM ch JOIN qn ON qn.doc_id = ch.doc_id AND qn.item_id = ch.item_id LEFT JOIN cn ON cn.doc_id = ch.doc_id AND cn.item_id = ch.item_id AND cn.s = ch.s),
bs AS (SELECT doc_id, item_id, s FROM sc QUALIFY row_number() OVER (PARTITION BY doc_id, item_id ORDER BY ip DESC, s) = 1),
h AS (SELECT CAST(floor(pos / greatest(1, len(ws)) * 5) AS INTEGER) AS depth, CASE WHEN len(ws) < 200 THEN 'short' WHEN len(ws) < 800 THEN 'middle' ELSE 'long' END AS context,
  CASE WHEN s < pos + len(qs) AND pos < s + {C.CHUNK} THEN 1.0 ELSE 0.0 END AS hit FROM bs JOIN j ON j.doc_id = bs.doc_id AND j.item_id = bs.item_id)
SELECT 'exact' AS method, depth, context, count(*) AS n, round(avg(hit), 6) AS score FROM h GROUP BY ALL""")
def needle_exact(spark, sf_dir):
    """The grid of the full-precision keys."""
    docs, items = read_table(spark, sf_dir, "documents", "doc_id", "text"), read_table(spark, sf_dir, "benchmark", "item_id", "text")
    return rounded(C.needle_grid(C.needle_hits(docs, items, {})), "score")


# task groups --------------------------------------------------------------------

WEIGHTS = {"lang": 2.0, "quality": 2.0, "toxic": 2.0, "near_copy": 3.0, "passage": 2.0, "turn": 2.0}
NEAREST = 10


def turn_vectors(spark, sf_dir, d: int) -> DataFrame:
    """Vectors of all turns; ids leave room for as many turns as positions can name."""
    turns = read_table(spark, sf_dir, "conversations", "conv_id", "turn", "text").withColumn("id", F.col("conv_id") * C.TURN + F.col("turn"))
    return text_vectors(turns, d, "id")


def held(df: DataFrame) -> DataFrame:
    """df computed once, on the executors' disks until nothing refers to it."""
    return df.localCheckpoint(storageLevel=StorageLevel.DISK_ONLY)


def document_vectors(spark, sf_dir, d: int) -> DataFrame:
    """vec_id, embedding, known of the documents, hashed once for all scans; known: labels has the document."""
    known = read_table(spark, sf_dir, "labels", "doc_id").distinct().select(F.col("doc_id").cast("long").alias("vec_id"), F.lit(True).alias("known"))
    return held(_texts(spark, sf_dir, d).join(known, "vec_id", "left"))


def task_groups(spark, sf_dir, methods: dict, d: int, k: int = NEAREST, vectors: DataFrame | None = None) -> DataFrame:
    """method, task, score: six groups for all methods ('exact' among them); those of documents share their scans.

    lang, quality and toxic: whether the nearest text has the query's label (toxic balanced over its
    two values); near_copy: share of the neighbours of 0.8 and more that are found; passage: share of the
    benchmark's passages for which a text that holds them is found; turn: share of turns whose
    predecessor is found among all turns. vectors: document_vectors(), if they are there already.
    """
    docs, items = read_table(spark, sf_dir, "documents", "doc_id", "text", "lang"), read_table(spark, sf_dir, "benchmark", "item_id", "text")
    labels = read_table(spark, sf_dir, "labels", "doc_id", "quality", "toxic")
    v, ask = document_vectors(spark, sf_dir, d) if vectors is None else vectors, F.col("vec_id") % EVERY

    def with_labels(found: DataFrame, of: DataFrame, *cols: str) -> DataFrame:
        own, other = of.select(F.col("doc_id").alias("query_id"), *[F.col(c).alias(f"q_{c}") for c in cols]), of.select(F.col("doc_id").alias("vec_id"), *cols)
        return found.where("rank = 1").join(own, "query_id").join(other, "vec_id")

    def one(df: DataFrame, name: str, score) -> DataFrame:
        return df.groupBy("method").agg(F.avg(score).alias("score")).select("method", F.lit(name).alias("task"), "score")

    same = lambda c: (F.col(c) == F.col(f"q_{c}")).cast("double")
    sets = {"all": Asked(v.where(ask == 0), k, ask != 0), "known": Asked(v.where((ask == 0) & F.col("known")), 1, (ask != 0) & F.col("known")), "passage": Asked(text_vectors(items, d, "item_id"), k)}
    lists = held(topk_of_sets(sets, v, methods))  # several groups read them
    of = lambda name: lists.where(F.col("asked") == name).drop("asked")
    found, near = of("all"), with_labels(of("known"), labels, "quality", "toxic")
    balanced = near.groupBy("method", "q_toxic").agg(F.avg(same("toxic")).alias("r"))
    true = F.max(F.when((F.col("method") == "exact") & (F.col("score") >= 0.8), 1)).over(Window.partitionBy("query_id", "vec_id"))
    copies = found.withColumn("copy", true).where("copy = 1").groupBy("method").agg(F.count("*").alias("hits"))
    share = copies.withColumn("all", F.max(F.when(F.col("method") == "exact", F.col("hits"))).over(Window.partitionBy()))  # one row a method
    holds = held(C.needle_positions(docs, items).select(F.col("item_id").alias("query_id"), F.col("doc_id").alias("vec_id"), F.lit(1.0).alias("hit")))
    asked = of("passage").join(holds, ["query_id", "vec_id"], "left")
    got = asked.join(holds.select("query_id").distinct(), "query_id", "left_semi").groupBy("method", "query_id").agg(F.max(F.coalesce("hit", F.lit(0.0))).alias("hit"))
    tv = held(turn_vectors(spark, sf_dir, d))
    asks = tv.where((F.col("vec_id") % C.TURN > 0) & (F.floor(F.col("vec_id") / C.TURN) % EVERY == 0))
    before = topk_by_method(asks, tv, methods, k + 1).where("query_id <> vec_id").groupBy("method", "query_id").agg(F.max((F.col("vec_id") == F.col("query_id") - 1).cast("double")).alias("hit"))
    return reduce(DataFrame.unionByName, [
        one(with_labels(found, docs.select("doc_id", "lang"), "lang"), "lang", same("lang")), one(near, "quality", same("quality")), one(balanced, "toxic", F.col("r")),
        share.select("method", F.lit("near_copy").alias("task"), (F.col("hits") / F.col("all")).alias("score")), one(got, "passage", F.col("hit")), one(before, "turn", F.col("hit")),
    ])


def weighted(rows: DataFrame, by: tuple[str, ...]) -> DataFrame:
    """rows and their weighted means."""
    weight = F.element_at(F.create_map(*[F.lit(x) for kv in WEIGHTS.items() for x in kv]), F.col("task"))
    mean = rows.groupBy(*by).agg((F.sum(F.col("score") * weight) / F.sum(weight)).alias("score")).select(*by, F.lit("weighted").alias("task"), "score")
    return rows.select(*by, "task", "score").unionByName(mean)


def _vectors_sql(tag: str, table: str, name: str, d: int) -> str:
    """v{tag}(id, e): unit vectors of the texts of a table."""
    return f"""t{tag} AS (SELECT {name} AS id, unnest({_WORDS.format(x="text")}) AS w FROM {table}), c{tag} AS (SELECT id, {_SLOT} FROM t{tag} GROUP BY 1, 2),
n{tag} AS (SELECT id, sqrt(CAST(sum(v * v) AS DOUBLE)) AS norm FROM c{tag} GROUP BY 1 HAVING sum(v * v) > 0),
s{tag} AS (SELECT n.id, list(i) AS i, list(v / norm) AS x FROM n{tag} n JOIN c{tag} c ON n.id = c.id GROUP BY 1),
v{tag} AS (SELECT id, list_transform(range(0, {d}), lambda k: coalesce(x[list_position(i, k)], 0e0)) AS e FROM s{tag})"""


def _near_sql(out: str, asks: str, rows: str, k: int) -> str:
    return f"""{out} AS (SELECT q.id AS q, d.id AS d, round(list_dot_product(q.e, d.e), 9) AS ip, row_number() OVER (PARTITION BY q.id ORDER BY round(list_dot_product(q.e, d.e), 9) DESC, d.id) AS r
 FROM ({asks}) q, ({rows}) d QUALIFY r <= {k})"""


@query("task_exact", lambda: f"""WITH {_vectors_sql('d', 'documents', 'CAST(doc_id AS BIGINT)', C.WIDTH)},{_vectors_sql('i', 'benchmark', 'CAST(item_id AS BIGINT)', C.WIDTH)},
{_vectors_sql('u', 'conversations', f'CAST(conv_id AS BIGINT) * {C.TURN} + turn', C.WIDTH)},
{_near_sql('f', f'SELECT * FROM vd WHERE id % {EVERY} = 0', f'SELECT * FROM vd WHERE id % {EVERY} <> 0', NEAREST)},
{_near_sql('k', f'SELECT * FROM vd WHERE id % {EVERY} = 0 AND id IN (SELECT doc_id FROM labels)', f'SELECT * FROM vd WHERE id % {EVERY} <> 0 AND id IN (SELECT doc_id FROM labels)', 1)},
{_near_sql('p', 'SELECT * FROM vi', 'SELECT * FROM vd', NEAREST)},
{_near_sql('b', f'SELECT * FROM vu WHERE id % {C.TURN} > 0 AND id // {C.TURN} % {EVERY} = 0', 'SELECT * FROM vu', NEAREST + 1)},
l AS (SELECT a.toxic AS t0, CAST(a.quality = x.quality AS INTEGER) AS same_q, CAST(a.toxic = x.toxic AS INTEGER) AS same_t FROM k JOIN labels a ON a.doc_id = k.q JOIN labels x ON x.doc_id = k.d),
h AS (SELECT item_id, doc_id FROM benchmark i, documents d WHERE contains(d.text, i.text)),
s AS (SELECT 'lang' AS task, avg(CAST(a.lang = x.lang AS INTEGER)) AS score FROM f JOIN documents a ON a.doc_id = f.q JOIN documents x ON x.doc_id = f.d WHERE r = 1
 UNION ALL SELECT 'quality', avg(same_q) FROM l UNION ALL SELECT 'toxic', avg(m) FROM (SELECT avg(same_t) AS m FROM l GROUP BY t0)
 UNION ALL SELECT 'near_copy', count(*) FILTER (ip >= 0.8) / CAST(count(*) FILTER (ip >= 0.8) AS DOUBLE) FROM f
 UNION ALL SELECT 'passage', avg(m) FROM (SELECT q, max(CASE WHEN h.doc_id IS NULL THEN 0 ELSE 1 END) AS m FROM p LEFT JOIN h ON h.item_id = p.q AND h.doc_id = p.d WHERE q IN (SELECT item_id FROM h) GROUP BY q)
 UNION ALL SELECT 'turn', avg(m) FROM (SELECT q, max(CAST(d = q - 1 AS INTEGER)) AS m FROM b WHERE q <> d GROUP BY q))
SELECT 'exact' AS method, task, round(score, 6) AS score FROM s
UNION ALL SELECT 'exact', 'weighted', round(sum(score * CASE task WHEN 'near_copy' THEN 3 ELSE 2 END) / sum(CASE task WHEN 'near_copy' THEN 3 ELSE 2 END), 6) FROM s""")
def task_exact(spark, sf_dir):
    """The six groups at full precision."""
    rows = task_groups(spark, sf_dir, {"exact": None}, C.WIDTH)
    return rounded(weighted(rows, ("method",)), "score")


@query("task_scores")
def task_scores(spark, sf_dir):
    """Six task groups on keys at 3.5 bits a channel, by method, with their weighted mean: mean and deviation over five rotations."""
    v = document_vectors(spark, sf_dir, C.WIDTH)
    own = C.outlier_dimensions(v)
    caches = {"exact": None} | {name: C.KeyValueCache(s, own) for name, s in seeded().items()}
    rows = weighted(by_seed(task_groups(spark, sf_dir, caches, C.WIDTH, vectors=v)), ("method", "seed"))
    return mean_and_std(rows, ("method", "task"), "score")


@query("task_lang_exact", f"""WITH {_TEXT},
v AS (SELECT n.doc_id, list(i ORDER BY i) AS i, list(v / norm ORDER BY i) AS x FROM n JOIN c ON n.doc_id = c.doc_id GROUP BY 1),
f AS (SELECT doc_id, list_transform(range(0, {TEXT_D}), lambda k: coalesce(x[list_position(i, k)], 0e0)) AS x FROM v),
p AS (SELECT q.doc_id AS query_id, d.doc_id, row_number() OVER (PARTITION BY q.doc_id ORDER BY round(list_dot_product(q.x, d.x), 9) DESC, d.doc_id) AS r FROM f q JOIN f d ON q.doc_id % 10 = 0 AND d.doc_id % 10 <> 0)
SELECT count(*) AS n, round(avg(CASE WHEN a.lang = b.lang THEN 1.0 ELSE 0.0 END), 6) AS score FROM p JOIN documents a ON a.doc_id = query_id JOIN documents b ON b.doc_id = p.doc_id WHERE r = 1""")
def task_lang_exact(spark, sf_dir):
    docs, n = read_table(spark, sf_dir, "documents", "doc_id", "text", "lang"), EVERY
    first = exact_topk(text_vectors(docs.where(F.col("doc_id") % n == 0), TEXT_D), text_vectors(docs.where(F.col("doc_id") % n != 0), TEXT_D), 1)
    lang = docs.select("doc_id", "lang")
    a = first.join(lang.toDF("query_id", "ql"), "query_id").join(lang.toDF("vec_id", "vl"), "vec_id")
    return rounded(a.agg(F.count("*").alias("n"), F.avg((F.col("ql") == F.col("vl")).cast("double")).alias("score")), "score")


# events -------------------------------------------------------------------------


@query("event_windows", "SELECT date_trunc('day', ts) AS day, event_type, count(*) AS n, round(avg(value), 6) AS mean FROM events GROUP BY ALL")
def event_windows(spark, sf_dir):
    w = tumbling(read_table(spark, sf_dir, "events", "ts", "event_type", "value"), "1 day")
    return rounded(w.select(F.col("window.start").alias("day"), "event_type", "n", "mean"), "mean")


@query("event_sessions", """WITH g AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER w + INTERVAL 6 HOUR THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
s AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g), c AS (SELECT user_id, k, count(*) AS n FROM s GROUP BY 1, 2)
SELECT user_id, count(*) AS sessions, max(n) AS longest FROM c GROUP BY 1""")
def event_sessions(spark, sf_dir):
    s = sessions(read_table(spark, sf_dir, "events", "user_id", "ts"), "6 hours")
    return s.groupBy("user_id").agg(F.count("*").alias("sessions"), F.max("n").alias("longest"))


_USERS = """uc AS (SELECT user_id, event_type, CAST(count(*) AS DOUBLE) AS n FROM events GROUP BY 1, 2), ut AS (SELECT DISTINCT event_type FROM events),
uu AS (SELECT user_id, avg(value) AS v FROM events GROUP BY 1),
ul AS (SELECT uu.user_id, any_value(uu.v) AS v, list(coalesce(n, 0e0) ORDER BY ut.event_type) AS ns FROM uu CROSS JOIN ut LEFT JOIN uc ON uc.user_id = uu.user_id AND uc.event_type = ut.event_type GROUP BY 1),
uv AS (SELECT user_id AS vec_id, list_concat(ns, [v]) AS embedding FROM ul)"""


def _users_spec() -> QuantizerSpec:
    return QuantizerSpec("ball_block", "raw", 6, 3, 3)


@query("norm_roundtrip", lambda: f"""WITH {_USERS},{decoded_sql(_users_spec(), 'uv', 'TRUE')}
SELECT rescale, vec_id, round(sqrt(list_dot_product(e, e)), 6) AS norm, round(sqrt(list_sum(list_transform(list_zip(e, xhat), lambda p: pow(p[1] - p[2], 2))) / list_dot_product(e, e)), 6) AS away FROM xd""")
def norm_roundtrip(spark, sf_dir):
    """Vectors of any length through codes and back: norms are kept, and errors are relative to them."""
    v = user_vectors(event_features(read_table(spark, sf_dir, "events", "user_id", "event_type", "value"))).select("vec_id", "embedding")
    norms = encode(v, _users_spec()).select("vec_id", "norm")
    d = decoded(v, _users_spec(), 12).join(norms, "vec_id")
    return d.select("rescale", "vec_id", F.round("norm", 6).alias("norm"), F.round(F.sqrt("err") / F.col("norm"), 6).alias("away"))


@query("event_asof", """WITH c AS (SELECT event_id, user_id, ts FROM events WHERE event_type = 'click'), p AS (SELECT user_id, ts, value FROM events WHERE event_type = 'purchase')
SELECT event_id, round(value, 6) AS last_value FROM c ASOF LEFT JOIN (SELECT user_id, ts, max(value) AS value FROM p GROUP BY ALL) p ON c.user_id = p.user_id AND c.ts >= p.ts""")
def event_asof(spark, sf_dir):
    """Each click with its user's last purchase up to then: one window instead of a range join."""
    e = read_table(spark, sf_dir, "events", "event_id", "user_id", "ts", "event_type", "value").where("event_type IN ('click', 'purchase')")
    w = Window.partitionBy("user_id").orderBy("ts").rangeBetween(Window.unboundedPreceding, Window.currentRow)
    last = F.max(F.when(F.col("event_type") == "purchase", F.struct("ts", "value"))).over(w)
    return e.withColumn("last", last).where("event_type = 'click'").select("event_id", F.round("last.value", 6).alias("last_value"))
