"""Near-duplicate classes from bottom-k sketches of one hash function.

1. A text's shingles are hashed once; the k smallest hashes are its sketch. Texts with equal
   sets are one class, for which its smallest id stands from here on.
2. Inverted lists give candidates. At a threshold of 0.8 retained values are common to both
   sketches so often that some ``RUN`` of them follow each other in both: in sets that fit
   into the sketch always, in others but for a chance of about 1e-10. Lists are named by such
   runs, so a common word pair makes no list, and a common passage only where it fills much of a text.
3. In each list every member is paired with the member that leads it, and a random one, not
   with every other. The union sketch estimates a pair's resemblance, and full sets
   confirm it: links are exact.
4. Links are contracted to components. Where members under one leader are still in
   different components, they are compared in blocks by a wider sketch, one task a pair of
   blocks, out of which only pairs that pass come. Their confirmed links complete the
   components.

So copies are never expanded into all pairs, and a link between different texts is lost
only if the sketch estimate of a pair errs by more than ``DEVIATIONS`` standard deviations;
pairs whose sets fit into the sketch are exact.

Defined cases: null or empty texts, and texts of white space, have an empty set, link with
nothing and stay; equal rows are one class; a row without doc_id links with nothing and has
no component; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import Scratch, map_slices, table, written
from .components import components
from .shingles import shingle_set, working

SKETCH = 64
#: Values that follow each other in both sketches of a linked pair; sets up to SMALL may have one fewer.
RUN, SMALL = 3, 5
DEVIATIONS = 5.5
#: Retained values, and members of a block, where what is left is compared in blocks. Most sets fit whole.
WIDE = 1024
BLOCK = 256
#: Distinct values that are held as columns at once when two blocks are compared.
COLUMNS = 8192
#: Most ids of candidates that are broadcast to pick their texts; more are joined by a shuffle.
BROADCAST_IDS = 2_000_000
#: Most leaders whose parts are broadcast to their members; more are joined by a shuffle.
BROADCAST_LEADERS = 500_000


def needed(k: int, num: int, den: int) -> int:
    """Retained values that two linked sets have in common, at least, if both exceed k."""
    p = num / den
    return max(1, math.floor(k * p - DEVIATIONS * math.sqrt(k * p * (1 - p))))


def sketches(docs: DataFrame, n: int, k: int) -> DataFrame:
    """(doc_id, n_shingles, digest, sketch) of each row; digest is null for an empty set."""

    def start():
        working()

        def f(c):
            out = {"doc_id": c["doc_id"], "n_shingles": [], "digest": [], "sketch": []}
            for t in c["text"]:
                s = shingle_set(t, n)
                out["n_shingles"].append(len(s))
                out["digest"].append(xxhash.xxh128_digest(s.tobytes()) if len(s) else None)
                out["sketch"].append(s[:k])
            return out

        return f

    kinds = "doc_id long, n_shingles long, digest binary, sketch array<long>"
    return map_slices(docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")), kinds, start)


def listed(classes: DataFrame, num: int, den: int) -> DataFrame:
    """(value, cid, n, weight): the inverted lists of two members at least.

    A list is named by a run of retained values that follow each other in the sketch. weight
    tells how much a member's runs are shared.
    """
    run = max(1, min(RUN, num // (den - num) - 1)) if num < den else RUN

    def runs(length: int):
        last = F.greatest(F.lit(1), F.size("sketch") - (length - 1))
        return F.transform(F.sequence(F.lit(1), last), lambda i: F.xxhash64(F.slice("sketch", i, F.lit(length))))

    # in sets this small, linked ones may share a shorter run only
    keys = F.when(F.col("n") <= SMALL, F.concat(*[runs(r) for r in range(max(1, run - 1), run + 1)])).otherwise(runs(run))
    post = classes.select("cid", "n", F.explode(keys).alias("value"))
    often = post.groupBy("value").agg(F.count("*").alias("freq")).where("freq > 1")
    return post.join(often, "value").withColumn("weight", F.sum("freq").over(Window.partitionBy("cid"))).select("value", "cid", "n", "weight")


def _sizes_fit(num: int, den: int):
    a, b = F.col("na"), F.col("nb")
    return (F.least(a, b) * den >= F.greatest(a, b) * num)


def estimated(pairs: DataFrame, classes: DataFrame, k: int, num: int, den: int) -> DataFrame:
    """The pairs (a, b) whose union sketch does not rule the threshold out."""
    one = lambda x: classes.select(F.col("cid").alias(x), F.col("n").alias(f"n{x}"), F.col("sketch").alias(f"s{x}"))
    j = pairs.join(one("a"), "a").join(one("b"), "b").where(_sizes_fit(num, den))
    whole = (F.col("na") <= k) & (F.col("nb") <= k)
    union = F.array_sort(F.array_union("sa", "sb"))
    j = j.select("a", "b", whole.alias("whole"), F.when(whole, union).otherwise(F.slice(union, 1, k)).alias("u"), F.array_intersect("sa", "sb").alias("i"))
    both = F.size(F.array_intersect("u", "i"))
    return j.where(F.when(F.col("whole"), both * den >= F.size("u") * num).otherwise(both >= needed(k, num, den))).select("a", "b")


def _texts_of(docs: DataFrame, ids: DataFrame, scratch: Scratch) -> DataFrame:
    """(doc_id, text) of these documents. Ids are broadcast up to a bound, so that texts stay where they are."""
    ids = written(ids.distinct(), scratch)
    few = ids.count() <= BROADCAST_IDS
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return texts.join(F.broadcast(ids) if few else ids, "doc_id", "left_semi")


def confirmed(pairs: DataFrame, docs: DataFrame, n: int, num: int, den: int, scratch: Scratch) -> DataFrame:
    """The pairs whose full sets reach the threshold."""
    texts = _texts_of(docs, pairs.select(F.explode(F.array("a", "b")).alias("doc_id")), scratch)

    def sets():
        working()
        return lambda c: {"doc_id": c["doc_id"], "set": [shingle_set(t, n).tobytes() for t in c["text"]]}

    full = written(map_slices(texts, "doc_id long, set binary", sets), scratch)
    j = pairs.join(full.select(F.col("doc_id").alias("a"), F.col("set").alias("x")), "a").join(full.select(F.col("doc_id").alias("b"), F.col("set").alias("y")), "b")

    def compare():
        working()

        def f(c):
            keep = []
            for x, y in zip(c["x"], c["y"]):
                x, y = np.frombuffer(x, dtype=np.int64), np.frombuffer(y, dtype=np.int64)
                both = len(x) + len(y) - len(np.unique(np.concatenate((x, y))))
                keep.append(den * both >= num * (len(x) + len(y) - both))
            return {m: [v for v, ok in zip(c[m], keep) if ok] for m in ("a", "b")}

        return f

    return map_slices(j, "a long, b long", compare)


def led(lists: DataFrame) -> DataFrame:
    """lists with each list's leader, the member whose retained values are shared most, and a random member.

    The copy closest to what a group has in common leads it, so that most of the group is
    within the threshold of its leader. A member shares the list, and so the leader, with
    each of its candidates: leaders stand for lists from here on, and a member has few of them.
    """
    ends = lists.groupBy("value").agg(F.max(F.struct("weight", "cid")).alias("best"), F.min(F.struct(F.xxhash64("cid"), "cid")).alias("any"))
    return lists.join(ends.select("value", F.col("best.cid").alias("leader"), F.col("any.cid").alias("other")), "value").select("cid", "n", "leader", "other").distinct()


def to_leaders(members: DataFrame) -> DataFrame:
    j = members.select("cid", F.explode(F.array("leader", "other")).alias("o")).where("cid != o")
    return j.select(F.least("cid", "o").alias("a"), F.greatest("cid", "o").alias("b")).distinct()


def still_apart(members: DataFrame, comp: DataFrame, docs: DataFrame, words: int, num: int, den: int, scratch: Scratch, k: int = WIDE) -> DataFrame:
    """Pairs under one leader that no link has yet joined and a wider sketch allows.

    Members are dealt to blocks, and a pair of blocks is one group: its sketches are
    compared as products of 0/1 matrices. Members of the largest part meet the others only, so the
    work is the number outside it times the number of all; a leader with few members is one
    group. Sets that fit into the wide sketch are compared exactly, and
    of their links only those come out that join parts which are still apart.
    """
    x = members.select("leader", "cid", "n").distinct().join(comp, F.col("cid") == F.col("node"), "left").select("leader", "cid", "n", F.coalesce("component", "cid").alias("comp"))
    parts = x.groupBy("leader", "comp").agg(F.count("*").alias("k"))
    apart = parts.groupBy("leader").agg(F.sum("k").alias("size"), F.max(F.struct("k", "comp")).alias("most"), F.count("*").alias("parts")).where("parts > 1")
    apart = written(apart.select("leader", (F.col("size") - F.col("most.k")).alias("rest"), F.col("most.k").alias("main"), F.col("most.comp").alias("main_comp")), scratch)
    # one row a leader: broadcast up to a bound, so that the members of a leader do not gather; beyond it AQE splits a leader that is skewed
    x = written(x.join(F.broadcast(apart) if apart.count() <= BROADCAST_LEADERS else apart, "leader"), scratch)
    texts = _texts_of(docs, x.select(F.col("cid").alias("doc_id")), scratch)

    def wide():
        working()
        return lambda c: {"cid": c["doc_id"], "sketch": [shingle_set(t, words)[:k].tobytes() for t in c["text"]]}

    sketch = written(map_slices(texts, "cid long, sketch binary", wide), scratch)
    # blocks 0 to b - 1 hold what is outside the largest part, blocks from b on the largest part, whose members need not meet each other
    few = F.col("rest") + F.col("main") <= BLOCK
    b, a = F.when(few, 1).otherwise(F.ceil(F.col("rest") / BLOCK)).cast("int"), F.when(few, 0).otherwise(F.ceil(F.col("main") / BLOCK)).cast("int")
    inside, at = F.col("comp") == F.col("main_comp"), F.xxhash64("cid")
    x = x.withColumn("mine", F.when(few, 0).when(inside, b + F.pmod(at, a)).otherwise(F.pmod(at, b)).cast("int"))
    x = x.withColumn("theirs", F.explode(F.sequence(F.lit(0), F.when(inside, b - 1).otherwise(a + b - 1).cast("int"))))
    keyed = x.join(sketch, "cid").select("leader", "cid", "n", "comp", "sketch", "mine", F.least("mine", "theirs").alias("i"), F.greatest("mine", "theirs").alias("j"))
    need = needed(k, num, den)

    def run(t: pa.Table) -> pa.Table:
        cid, n, comp, mine = (t.column(m).to_numpy() for m in ("cid", "n", "comp", "mine"))
        left, right = np.flatnonzero(mine == t.column("i")[0].as_py()), np.flatnonzero(mine == t.column("j")[0].as_py())
        both = shared_values(t.column("sketch").to_pylist(), left, right)
        na, nb = n[left][:, None], n[right][None, :]
        whole = (na <= k) & (nb <= k)
        ok = np.where(whole, den * both >= num * (na + nb - both), both >= need)
        ok &= (comp[left][:, None] != comp[right][None, :]) & (np.minimum(na, nb) * den >= np.maximum(na, nb) * num)
        p, q = np.nonzero(ok)
        out, top = [], {}

        def root(c):
            while (up := top.get(c, c)) != c:
                c = up
            return c

        for p, q, sure in sorted(zip(p.tolist(), q.tolist(), whole[p, q].tolist()), key=lambda z: not z[2]):
            a, b = int(left[p]), int(right[q])
            u, v = root(int(comp[a])), root(int(comp[b]))
            if u != v:  # joined by links that are sure: nothing to add
                out.append((min(int(cid[a]), int(cid[b])), max(int(cid[a]), int(cid[b]))))
                if sure:
                    top[max(u, v)] = min(u, v)
        return pa.table({"a": pa.array([a for a, _ in out], type=pa.int64()), "b": pa.array([b for _, b in out], type=pa.int64())})

    return keyed.groupBy("leader", "i", "j").applyInArrow(run, "a long, b long").distinct()


def shared_values(sketches: list[bytes], left: np.ndarray, right: np.ndarray) -> np.ndarray:
    """How many values each sketch of left shares with each of right: a product of 0/1 matrices, some columns at a time.

    Only values that two sketches at least hold have a column, and no more than COLUMNS are held at once.
    """
    rows = np.array([len(s) // 8 for s in sketches])
    owner, values = np.repeat(np.arange(len(sketches)), rows), np.frombuffer(b"".join(sketches), dtype=np.int64)
    _, at, often = np.unique(values, return_inverse=True, return_counts=True)
    column = np.where(often > 1, np.cumsum(often > 1) - 1, -1)[at]
    owner, column = owner[column >= 0], column[column >= 0]
    order = np.argsort(column, kind="stable")
    owner, column = owner[order], column[order]
    both = np.zeros((len(left), len(right)), dtype=np.float32)
    for first in range(0, int(column[-1]) + 1 if len(column) else 0, COLUMNS):
        a, b = np.searchsorted(column, (first, first + COLUMNS))
        hot = np.zeros((len(sketches), int(column[b - 1]) - first + 1), dtype=np.float32)
        hot[owner[a:b], column[a:b] - first] = 1
        both += hot[left] @ hot[right].T
    return both.astype(np.int64)


def near_duplicates(docs: DataFrame, words: int = 5, num: int = 80, den: int = 100, k: int = SKETCH) -> DataFrame:
    """doc_id, n_shingles, component_id, kept of each row. Of what is written on the way only the result stays."""
    with Scratch(docs.sparkSession) as scratch:
        return written(_near_duplicates(docs, words, num, den, k, scratch))


def _near_duplicates(docs: DataFrame, words: int, num: int, den: int, k: int, scratch: Scratch) -> DataFrame:
    with Scratch(docs.sparkSession) as own:
        sketched = written(sketches(docs, words, k), own)
        some = sketched.where(F.col("digest").isNotNull() & F.col("doc_id").isNotNull())
        classes = written(
            some.groupBy("digest").agg(F.min("doc_id").alias("cid"), F.min_by(F.struct("n_shingles", "sketch"), "doc_id").alias("x"))
            .select("digest", "cid", F.col("x.n_shingles").alias("n"), F.col("x.sketch").alias("sketch")), own,
        )
        slim = written(sketched.select("doc_id", "n_shingles", "digest"), scratch)
        named = written(classes.select("digest", "cid"), scratch)
        members = written(led(listed(classes, num, den)), scratch)
        candidates = written(estimated(to_leaders(members), classes, k, num, den), scratch)
    comp = _contracted(candidates, docs, words, num, den, scratch)
    with Scratch(docs.sparkSession) as own:
        more = written(still_apart(members, comp, docs, words, num, den, own), scratch)
    # stars of the first components and the new links, contracted again
    comp = _contracted(more, docs, words, num, den, scratch, comp)
    named = named.join(comp, named["cid"] == comp["node"], "left").select("digest", F.coalesce("component", "cid").alias("component"))
    return (
        slim.join(named, "digest", "left")
        .select("doc_id", "n_shingles", F.when(F.col("doc_id").isNotNull(), F.coalesce("component", "doc_id")).alias("component_id"))
        .withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))
    )


def _contracted(pairs: DataFrame, docs: DataFrame, words: int, num: int, den: int, scratch: Scratch, known: DataFrame | None = None) -> DataFrame:
    """Components of the pairs that full sets confirm, and of the components known before."""
    with Scratch(docs.sparkSession) as own:
        links = confirmed(pairs, docs, words, num, den, own)
        if known is not None:
            links = known.select(F.col("component").alias("a"), F.col("node").alias("b")).unionByName(links)
        links = written(links, scratch)
    with Scratch(docs.sparkSession) as own:
        return written(components(links, scratch=own), scratch)


def one_of_each(docs: DataFrame, words: int = 5, num: int = 80, den: int = 100) -> DataFrame:
    """docs with the first document of each class, and all their columns, whatever their names.

    Null and empty texts and rows without doc_id stay; of rows that repeat an id one stays; an
    empty table stays empty.
    """
    name = "__id"
    while name in {c.lower() for c in docs.columns}:
        name += "_"
    seen = written(near_duplicates(docs, words, num, den).select("doc_id", "kept"))
    gone = written(seen.where(~F.col("kept")).select(F.col("doc_id").alias(name)).distinct())
    twice = written(seen.where("kept AND doc_id IS NOT NULL").groupBy(F.col("doc_id").alias(name)).agg(F.count("*").alias("k")).where("k > 1").select(name))
    few = lambda x: F.broadcast(x) if x.count() <= BROADCAST_IDS else x
    kept = docs.withColumn(name, F.col("doc_id").cast("long")).join(few(gone), name, "left_anti")
    if twice.limit(1).count():  # rows that repeat an id: one of them
        again = kept.join(few(twice), name, "left_semi").dropDuplicates([name])
        kept = kept.join(few(twice), name, "left_anti").unionByName(again)
    return kept.select(docs.columns)


def op6_near_duplicates(spark, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents", "doc_id", "text"), words=2)


OP6_SQL = """
WITH RECURSIVE w AS (
  SELECT CAST(doc_id AS BIGINT) AS doc_id, list_filter(string_split(translate(coalesce(text, ''),
    'ABCDEFGHIJKLMNOPQRSTUVWXYZ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13), 'abcdefghijklmnopqrstuvwxyz     '), ' '), lambda x: x <> '') AS ws
  FROM documents
), s AS (
  SELECT doc_id, list_sort(list_distinct(CASE WHEN len(ws) < 2 THEN ws ELSE list_transform(range(1, len(ws)), lambda i: ws[i] || ' ' || ws[i + 1]) END)) AS sh FROM w
), c AS (
  SELECT sh, min(doc_id) AS rep, len(sh) AS n FROM s WHERE len(sh) > 0 GROUP BY sh
), x AS (
  SELECT rep, n, unnest(sh) AS v FROM c
), p AS (
  SELECT a.rep AS a, b.rep AS b, a.n AS na, b.n AS nb, count(*) AS shared
  FROM x a JOIN x b ON a.v = b.v AND a.rep < b.rep AND least(a.n, b.n) * 100 >= greatest(a.n, b.n) * 80 GROUP BY 1, 2, 3, 4
), e AS (
  SELECT a, b FROM p WHERE 100 * shared >= 80 * (na + nb - shared)
), g AS (
  SELECT a, b FROM e UNION ALL SELECT b, a FROM e
), r(rep, comp) AS (
  SELECT rep, rep FROM c UNION SELECT g.b, r.comp FROM r JOIN g ON g.a = r.rep
), m AS (
  SELECT rep, min(comp) AS comp FROM r GROUP BY rep
)
SELECT s.doc_id, CAST(len(s.sh) AS BIGINT) AS n_shingles, coalesce(m.comp, s.doc_id) AS component_id, coalesce(m.comp, s.doc_id) = s.doc_id AS kept
FROM s LEFT JOIN c ON c.sh = s.sh AND len(s.sh) > 0 LEFT JOIN m ON m.rep = c.rep
"""
