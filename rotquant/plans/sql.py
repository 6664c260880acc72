"""SQL for a second engine: rotations and codebooks as literals, nearest codewords by brute force."""

from __future__ import annotations

import math

import numpy as np

from ..model import QuantizerSpec
from ..operators.codec import codec, ladder


def literal(x) -> str:
    if isinstance(x, np.ndarray):
        x = x.tolist()
    if isinstance(x, list):
        return "[" + ",".join(map(literal, x)) + "]"
    text = repr(float(x))
    return text if "e" in text else text + "e0"  # a double, not a decimal


def base(spec: QuantizerSpec, table: str = "embeddings", where: str = "TRUE", tag: str = "") -> str:
    """zt (and the tag): vec_id, norm, z (rotated direction) and y (rotated vector)."""
    c = codec(spec)
    return f"""
x{tag} AS (SELECT CAST(vec_id AS BIGINT) AS vec_id, list_transform(embedding, lambda v: CAST(v AS DOUBLE)) AS e FROM {table} WHERE {where}),
u{tag} AS (SELECT vec_id, e, sqrt(list_dot_product(e, e)) AS norm FROM x{tag}),
rot{tag} AS (SELECT {literal(c.rotation)} AS m),
y{tag} AS (SELECT vec_id, e, norm, list_transform(m, lambda r: list_dot_product(r, e)) AS y FROM u{tag}, rot{tag}),
zt{tag} AS (SELECT vec_id, e, norm, y, list_transform(y, lambda v: v / norm) AS z FROM y{tag})"""


def coded(spec: QuantizerSpec, name: str, source: str = "zt") -> str:
    """name: the columns of source with code and zb (raw reconstruction in the rotated domain)."""
    c = codec(spec)
    if spec.codebook in ("gauss_scalar", "sphere_scalar", "sphere_scalar_signbit"):
        return f"""
{name}_b AS (SELECT {literal(c.levels)} AS levels, CAST({literal(c.cuts)} AS DOUBLE[]) AS cuts),
{name}_c AS (SELECT t.*, list_transform(z, lambda v: len(list_filter(cuts, lambda k: k < v))) AS code FROM {source} t, {name}_b),
{name} AS (SELECT t.*, list_transform(code, lambda k: levels[k + 1]) AS zb FROM {name}_c t, {name}_b)"""
    if spec.codebook == "grid_dir":
        top, half = 2 ** (spec.b - 1) - 1, 2 ** (spec.b - 1)
        if spec.assign == "ladder":
            words = f"list_transform({literal(ladder(spec.b) / math.sqrt(spec.d))}, lambda s: list_transform(z, lambda v: least(floor(abs(v) / s), {top})))"
        else:  # a word for every scale at which some coordinate steps, taken just beyond it
            scales = f"list_concat([0e0], flatten(list_transform(range(1, {top + 1}), lambda k: list_transform(z, lambda v: k / abs(v)))))"
            words = f"list_transform({scales}, lambda s: list_transform(z, lambda v: least(floor(abs(v) * s * (1 + 1e-12)), {top})))"
        return f"""
{name}_w AS (SELECT t.*, {words} AS words FROM {source} t),
{name}_q AS (SELECT t.*, list_transform(words, lambda g: list_dot_product(list_transform(g, lambda k: k + 0.5), list_transform(z, lambda v: abs(v)))
  / sqrt(list_sum(list_transform(g, lambda k: (k + 0.5) * (k + 0.5))))) AS cos FROM {name}_w t),
{name}_c AS (SELECT * EXCLUDE (words, cos), list_transform(list_zip(z, words[list_position(cos, list_max(cos))]),
  lambda p: CAST(CASE WHEN p[1] >= 0 THEN p[2] + {half} ELSE {half - 1} - p[2] END AS BIGINT)) AS code FROM {name}_q),
{name}_g AS (SELECT t.*, list_transform(code, lambda k: k - {2.0 ** (spec.b - 1) - 0.5}) AS g FROM {name}_c t),
{name} AS (SELECT * EXCLUDE (g), list_transform(g, lambda v: v / sqrt(list_dot_product(g, g))) AS zb FROM {name}_g)"""
    books = ", ".join(f"{literal(b)} AS o{s}" for s, b in c.books.items())
    runs = []
    for s, a, n in c._blocks():
        away = " + ".join(f"(z[{a} + {s} * j + {i + 1}] - o[{i + 1}]) * (z[{a} + {s} * j + {i + 1}] - o[{i + 1}])" for i in range(s))
        runs.append((s, n, f"list_transform(range(0, {n}), lambda j: list_transform([list_transform(o{s}, lambda o: {away})], lambda q: list_position(q, list_min(q)) - 1)[1])"))
    at, parts = 0, []
    for s, n, _ in runs:
        parts.append(f"flatten(list_transform(list_slice(code, {at + 1}, {at + n}), lambda k: o{s}[k + 1]))")
        at += n
    join = lambda xs: xs[0] if len(xs) == 1 else f"list_concat({', '.join(xs)})"
    return f"""
{name}_b AS (SELECT {books}),
{name}_c AS (SELECT t.*, {join([r for *_, r in runs])} AS code FROM {source} t, {name}_b),
{name} AS (SELECT t.*, {join(parts)} AS zb FROM {name}_c t, {name}_b)"""


SCALE = {"raw": "1.0", "best": "rho / zsq", "unbiased": "1.0 / rho"}
ERROR = {"raw": "1 - 2 * rho + zsq", "best": "1 - rho * rho / zsq", "unbiased": "zsq / (rho * rho) - 1"}


def scalars(specs: list[QuantizerSpec], out: str = "sc", source: str = "zt") -> str:
    """out: method, p, b, seed, vec_id, norm, rho, zsq, zb of all specs (one rotation)."""
    parts = [coded(s, f"{out}k{i}", source) for i, s in enumerate(specs)]
    rows = [
        f"SELECT '{s.codebook}' AS method, {s.p} AS p, {s.b} AS b, {s.seed} AS seed, vec_id, norm, list_dot_product(z, zb) AS rho, list_dot_product(zb, zb) AS zsq, zb FROM {out}k{i}"
        for i, s in enumerate(specs)
    ]
    return ",".join([*parts, f"\n{out} AS ({' UNION ALL '.join(rows)})"])


def pair_rows(specs: list[QuantizerSpec], every: int, out: str = "pr") -> str:
    """out: method, p, b, rescale, query_id, vec_id, ip, hat, law of all pairs of queries and database."""
    scale = "CASE rescale " + " ".join(f"WHEN '{r}' THEN {x}" for r, x in SCALE.items()) + " END"
    names = ", ".join(f"('{s.codebook}', {s.p}, {s.b}, '{s.rescale}')" for s in specs)
    d = specs[0].d
    return f"""
wanted(method, p, b, rescale) AS (VALUES {names}),
{out} AS (SELECT sc.method, sc.p, sc.b, w.rescale, q.vec_id AS query_id, sc.vec_id, list_dot_product(q.e, x.e) AS ip,
  {scale} * sc.norm * list_dot_product(q.y, sc.zb) AS hat,
  (1 - pow(list_dot_product(q.e, x.e) / (q.norm * sc.norm), 2)) / {d - 1} * (zsq / (rho * rho) - 1) AS law
 FROM sc JOIN wanted w ON w.method = sc.method AND w.p = sc.p AND w.b = sc.b JOIN zt x ON x.vec_id = sc.vec_id
 JOIN zt q ON q.vec_id % {every} = 0 WHERE sc.vec_id % {every} <> 0)"""


def looked_up(spec: QuantizerSpec, name: str, source: str = "zt") -> str:
    """name: the columns of source with the codes of the blocks found by candidate lists of grid cells."""
    c, runs, tables = codec(spec), [], []
    for s, a, n in c._blocks():
        t = c.tables[s]
        rows = "[" + ",".join("[" + ",".join(map(str, r)) + "]" for r in t.lists.tolist()) + "]"
        tables.append(f"{literal(t.book)} AS o{s}, {rows} AS t{s}")
        axes = [f"floor((z[{a} + {s} * j + {i + 1}] + {t.half!r}) * {t.per_axis / (2 * t.half)!r})" for i in range(s)]
        inside = " AND ".join(f"{x} BETWEEN 0 AND {t.per_axis - 1}" for x in axes)
        cell = " + ".join(f"{x} * {t.per_axis ** (s - 1 - i)}" for i, x in enumerate(axes))
        away = " + ".join(f"(z[{a} + {s} * j + {i + 1}] - o{s}[o + 1][{i + 1}]) * (z[{a} + {s} * j + {i + 1}] - o{s}[o + 1][{i + 1}])" for i in range(s))
        cands = f"CASE WHEN {inside} THEN list_sort(t{s}[CAST({cell} AS BIGINT) + 1]) ELSE range(0, {len(t.book)}) END"
        runs.append(f"list_transform(range(0, {n}), lambda j: list_transform([{cands}], lambda cs: list_transform([list_transform(cs, lambda o: {away})], lambda q: cs[list_position(q, list_min(q))])[1])[1])")
    join = runs[0] if len(runs) == 1 else f"list_concat({', '.join(runs)})"
    return f"""
{name}_t AS (SELECT {', '.join(tables)}),
{name} AS (SELECT t.*, {join} AS code FROM {source} t, {name}_t)"""


def signbit_rows(spec: QuantizerSpec, every: int, out: str) -> str:
    """out: method, p, b, rescale, query_id, vec_id, ip, hat of the sign sketch for all pairs of queries and database."""
    c = codec(spec)
    return f"""{coded(spec, out + "k")},
{out}_g AS (SELECT {literal(c.projection)} AS g),
{out}_r AS (SELECT vec_id, e, norm, zb, list_transform(list_zip(z, zb), lambda p: p[1] - p[2]) AS r FROM {out}k WHERE vec_id % {every} <> 0),
{out}_s AS (SELECT vec_id, e, norm, zb, sqrt(list_dot_product(r, r)) AS rn, list_transform(g, lambda w: CASE WHEN list_dot_product(w, r) > 0 THEN 1.0 ELSE -1.0 END) AS sg FROM {out}_r, {out}_g),
{out}_q AS (SELECT vec_id AS query_id, e, y, list_transform(g, lambda w: list_dot_product(w, y)) AS gy FROM zt, {out}_g WHERE vec_id % {every} = 0),
{out} AS (SELECT 'sphere_scalar_signbit' AS method, 1 AS p, {spec.b} AS b, 'raw' AS rescale, query_id, s.vec_id, list_dot_product(q.e, s.e) AS ip,
  s.norm * (list_dot_product(q.y, s.zb) + sqrt(pi() / 2) / {spec.d} * rn * list_dot_product(gy, sg)) AS hat FROM {out}_s s, {out}_q q)"""
