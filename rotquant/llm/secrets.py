"""Secrets: fixed patterns, and random-looking tokens found by a battery of tests.

Everything here is DataFrame functions. Places of pattern matches come from the lengths of
the matches and of the gaps between them. Whole runs of letters, digits and signs that no
pattern covers are tested in four steps.

1. The encoding (letters, hexadecimal, base32 and base36 of either case, base64, base62) is
   inferred as the smallest alphabet that holds all characters, in which a random token of a
   larger one is uniform too, and each character becomes its value in that alphabet. Runs of
   digits alone are numbers and are not tested.
2. Three statistics are taken of the values: chi-squared of the counts, the number of runs of
   character classes (upper, lower, digit, sign; vowel and consonant among letters of one
   case), and the lag-one serial correlation. A token that any of them sets clearly apart from a uniform source
   is not random.
3. The same statistics give the p-value. A token of words has larger chi-squared and changes
   class as words do; a counting pattern is serially correlated and seldom changes class. The
   chance of statistics as near to uniform is taken under either, from two of the three each, and the larger one counts.
4. False discoveries are held below ``rate`` by the step-up rule over all tokens of the
   corpus, with weights that grow with length and average one. The rule needs the counts
   of tokens by length class and p-value bucket only, a table of bounded size.

Offsets are in code points, ends exclusive. Defined cases: a null text is empty; empty texts
have no span; repeated rows each give a row; very long texts are scanned whole; an empty
table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import table, written
from .spans import digests

KINDS = ("assign", "access", "hex", "random")
#: Fixed patterns. Failing assignments are consumed, so their length is tested afterwards.
ASSIGN = (
    "([pP][aA][sS][sS][wW][oO][rR][dD]|[pP][aA][sS][sS][wW][dD]|[sS][eE][cC][rR][eE][tT]|[tT][oO][kK][eE][nN]|[aA][pP][iI]_?[kK][eE][yY])"
    "[\"']?\\x20*[:=]\\x20*[\"']?([A-Za-z0-9+/_.=-]+)"
)
ACCESS = "AKIA[A-Z0-9]{16,}"  # as AKIA[A-Z0-9]+ of 20 characters and more: matches are whole runs
HEX = "[0-9a-f]{24,}"  # as [0-9a-f]+ of 24 characters and more, for the same reason
_SIGN = "A-Za-z0-9+/_=-"
#: Tokens that are tested: whole runs.
TOKEN = f"(?<![{_SIGN}])[{_SIGN}]{{20,}}+"
#: Upper ends of the length classes, and their raw weights.
CLASSES = ((24, 0.5), (32, 1.0), (48, 1.5), (64, 2.0), (1 << 30, 2.0))
BUCKETS = 2000  # of -100 log10 p
_SPAN = "array<struct<start: bigint, rank: int, kind: string, end: bigint>>"
_PLACE = "struct<start: bigint, end: bigint, token: string, value: string>"
#: Matches of one text that are placed together; a text with more has a list of such lists.
TOGETHER = 256


def _none(kind: str) -> Column:
    return F.array().cast(kind)


def _places(text: Column, pattern: str, value: int | None) -> Column:
    """array<struct<start, end, token, value>> of the leftmost matches of pattern."""
    hits = F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    values = hits if value is None else F.regexp_extract_all(text, F.lit(pattern), F.lit(value))
    zipped = F.arrays_zip(hits.alias("hit"), values.alias("value"), F.split(text, pattern, -1).alias("gap"))
    zero = lambda at, kind: F.struct(at.alias("at"), _none(kind).alias("out"))

    def step(acc, x):
        start = acc["at"] + F.length(x["gap"])
        end = start + F.coalesce(F.length(x["hit"]), F.lit(0))
        one = F.struct(start.alias("start"), end.alias("end"), x["hit"].alias("token"), x["value"].alias("value"))
        return F.struct(end.alias("at"), F.when(x["hit"].isNull(), acc["out"]).otherwise(F.concat(acc["out"], F.array(one))).alias("out"))

    def part(acc, x):  # arrays grow by copying, so that each is kept short
        own = F.aggregate(x, zero(acc["at"], f"array<{_PLACE}>"), step)
        return F.struct(own["at"].alias("at"), F.concat(acc["out"], F.array(own["out"])).alias("out"))

    parts = F.transform(F.sequence(F.lit(0), F.floor((F.size(hits) + F.lit(0)) / TOGETHER).cast("int")), lambda j: F.slice(zipped, j * TOGETHER + 1, F.lit(TOGETHER)))
    placed = F.flatten(F.aggregate(parts, zero(F.lit(0).cast("long"), f"array<array<{_PLACE}>>"), part)["out"])
    return F.when(text.rlike(pattern), placed).otherwise(_none(f"array<{_PLACE}>"))


def _text() -> Column:
    return F.coalesce(F.col("text").cast("string"), F.lit(""))


def touched(text: Column) -> Column:
    """Whether some pattern or token to test occurs at all."""
    return text.rlike(ASSIGN) | text.rlike(ACCESS) | text.rlike(HEX) | text.rlike(TOKEN)


def marked(text: Column) -> tuple[Column, Column]:
    """Pattern spans of a text, and its tokens to test."""

    def kind(k: str, found: Column) -> Column:
        return F.transform(found, lambda s: F.struct(s["start"].alias("start"), F.lit(KINDS.index(k)).alias("rank"), F.lit(k).alias("kind"), s["end"].alias("end")))

    assign = kind("assign", F.filter(_places(text, ASSIGN, 2), lambda s: F.length(s["value"]) >= 6))
    base = F.concat(assign, kind("access", _places(text, ACCESS, None)), kind("hex", _places(text, HEX, None)))
    cands = F.transform(_places(text, TOKEN, None), lambda s: F.struct(s["start"].alias("start"), s["end"].alias("end"), s["token"].alias("token")))
    return F.array_sort(base), cands


def _tail(z: Column) -> Column:
    """P(normal > z), by the usual rational approximation (fixed coefficients)."""
    a = F.abs(z)
    t = 1 / (1 + 0.2316419 * a)
    poly = t * (0.319381530 + t * (-0.356563782 + t * (1.781477937 + t * (-1.821255978 + t * 1.330274429))))
    upper = F.exp(-a * a / 2) / math.sqrt(2 * math.pi) * poly
    return F.when(z >= 0, upper).otherwise(1 - upper)


_UPPER, _LOWER, _DIGITS = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz", "0123456789"
#: Alphabets by encoding, the chance that two characters of a token of words agree, and that two neighbours
#: differ in class (names of capitalised words, and words between signs, change class twice a word).
ALPHABETS = {
    "letters": (_UPPER, 0.066, 0.6),
    "letters_lower": (_LOWER, 0.066, 0.6),
    "hex": ("0123456789abcdef", 0.10, 0.15),
    "base32": (_UPPER + "234567", 0.066, 0.15),
    "base32_lower": (_LOWER + "234567", 0.066, 0.15),
    "base36": (_UPPER + _DIGITS, 0.066, 0.15),
    "base36_lower": (_LOWER + _DIGITS, 0.066, 0.15),
    "base64": (_UPPER + _LOWER + _DIGITS + "+/", 0.066, 0.33),
    "base62": (_UPPER + _LOWER + _DIGITS, 0.066, 0.33),
}
#: Serial correlation, and the chance that neighbours differ in class, in counting patterns.
SERIAL, COUNTING_CHANGE = 0.5, 0.15
#: Deviations from uniform at which a token is no longer taken as random.
UNIFORM_Z = 4.0


def class_shares(encoding: str) -> list[float]:
    """Shares of the character classes in an alphabet."""
    alphabet = ALPHABETS[encoding][0]
    if encoding.startswith("letters"):
        return [5 / 26, 21 / 26]
    sizes = [sum(c in x for c in alphabet) for x in (_UPPER, _LOWER, _DIGITS, "+/")]
    return [n / len(alphabet) for n in sizes if n]


def uniform_runs(encoding: str) -> tuple[float, float]:
    """Of a uniform source: chance that neighbours differ in class, and the covariance of two such events in a row."""
    shares = class_shares(encoding)
    change = 1 - sum(p * p for p in shares)
    return change, sum(p * (1 - p) ** 2 for p in shares) - change**2


def tested(cands: DataFrame) -> DataFrame:
    """rid, start, end, token rows with encoding, statistics, p, length class and bucket."""
    tok = F.regexp_replace("token", "=+$", "")
    fits = {
        "letters": tok.rlike("^[A-Z]+$"),
        "letters_lower": tok.rlike("^[a-z]+$"),
        "hex": tok.rlike("^([0-9a-f]+|[0-9A-F]+)$") & tok.rlike("[A-Fa-f]"),
        "base32": tok.rlike("^[A-Z2-7]+$") & tok.rlike("[A-Z]"),
        "base32_lower": tok.rlike("^[a-z2-7]+$") & tok.rlike("[a-z]"),
        "base36": tok.rlike("^[A-Z0-9]+$") & tok.rlike("[A-Z]"),
        "base36_lower": tok.rlike("^[a-z0-9]+$") & tok.rlike("[a-z]"),
        "base64": tok.rlike("[+/_-]") & tok.rlike("[A-Za-z]"),
        "base62": tok.rlike("[A-Za-z]"),
    }
    values = lambda e: F.lower(tok) if e == "hex" else F.translate(tok, "-_=", "+/") if e == "base64" else F.translate(tok, "=", "")

    def one(e: str, ok: Column) -> Column:
        alphabet, same, change = ALPHABETS[e]
        own, cov = uniform_runs(e)
        facts = {"enc": e, "alphabet": alphabet, "same0": same, "change0": change, "change1": own, "cov1": cov}
        return F.struct(*[F.lit(v).alias(k) for k, v in facts.items()], values(e).alias("s"), ok.alias("ok"))

    # the first that fits, as a generator: it is found once a token, not again for every character
    x = cands.select("rid", "start", "end", F.inline(F.slice(F.filter(F.array(*[one(e, ok) for e, ok in fits.items()]), lambda f: f["ok"]), 1, 1)))
    x = x.withColumn("n", F.length("s").cast("double")).where("n >= 16").withColumn("size", F.length("alphabet").cast("double"))
    x = x.withColumn("chars", F.transform(F.sequence(F.lit(1), F.length("s")), lambda i: F.col("s").substr(i, F.lit(1))))
    x = x.withColumn("vals", F.transform("chars", lambda c: F.call_function("instr", F.col("alphabet"), c) - 1))
    squares = F.aggregate(F.array_distinct("chars"), F.lit(0.0), lambda a, c: a + F.pow(F.length("s") - F.length(F.replace(F.col("s"), c, F.lit(""))), F.lit(2)))
    mean = (F.col("size") - 1) / 2
    steps = F.arrays_zip(F.slice("vals", F.lit(1), (F.col("n") - 1).cast("int")).alias("u"), F.slice("vals", F.lit(2), (F.col("n") - 1).cast("int")).alias("v"))
    x = x.withColumn("squares", squares).withColumn("lag", F.aggregate(steps, F.lit(0.0), lambda a, p: a + (p["u"] - mean) * (p["v"] - mean)))
    kinds = F.regexp_replace(F.regexp_replace(F.regexp_replace(F.regexp_replace("s", "[a-z]+", "a"), "[A-Z]+", "A"), "[0-9]+", "0"), "[+/]+", "+")
    sounds = F.regexp_replace(F.regexp_replace(F.upper("s"), "[AEIOU]+", "0"), "[A-Z]+", "1")
    n, size, same, change0 = F.col("n"), F.col("size"), F.col("same0"), F.col("change0")
    x = x.withColumn("changes", F.length(F.when(F.col("enc").startswith("letters"), sounds).otherwise(kinds)).cast("double") - 1)
    r = F.least(F.lit(0.999), F.greatest(F.lit(-0.999), F.col("lag") / ((n - 1) * (size * size - 1) / 12)))
    chi = size / n * F.col("squares") - n
    spread = (n - 1) * F.col("change1") * (1 - F.col("change1")) + 2 * (n - 2) * F.col("cov1")
    x = x.withColumn("z_chi", (chi - (size - 1)) / F.sqrt(2 * (size - 1) * (1 - 1 / n)))
    x = x.withColumn("z_runs", (F.col("changes") - (n - 1) * F.col("change1")) / F.sqrt(spread)).withColumn("z_serial", r * F.sqrt(n - 1))
    # chi-squared counts pairs that agree; under words they are binomial
    pairs = n * (n - 1) / 2
    agree = (n * (chi + n) / size - n) / 2
    by_chi = (pairs * same - agree) / F.sqrt(pairs * same * (1 - same))
    apart = lambda p: (F.col("changes") - (n - 1) * p) / F.sqrt((n - 1) * p * (1 - p))
    by_runs = F.when(change0 > F.col("change1"), -apart(change0)).otherwise(apart(change0))
    by_serial = (math.atanh(SERIAL) - F.log((1 + r) / (1 - r)) / 2) * F.sqrt(n - 3)
    words = _tail((by_chi + by_runs) / math.sqrt(2))
    counting = _tail((by_serial + apart(F.lit(COUNTING_CHANGE))) / math.sqrt(2))
    uniform = (F.col("z_chi") <= UNIFORM_Z) & (F.abs("z_runs") <= UNIFORM_Z) & (F.abs("z_serial") <= UNIFORM_Z)
    x = x.withColumn("p", F.when(uniform, F.greatest(words, counting, F.lit(1e-19))).otherwise(1.0))
    length_class = F.lit(len(CLASSES) - 1)
    for i in range(len(CLASSES) - 2, -1, -1):
        length_class = F.when(n < CLASSES[i][0], F.lit(i)).otherwise(length_class)
    bucket = F.least(F.lit(BUCKETS), F.floor(-100 * F.log10("p"))).cast("int")
    return x.select("rid", "start", "end", "enc", "z_chi", "z_runs", "z_serial", "p", length_class.alias("length_class"), bucket.alias("bucket"))


def thresholds(tests: DataFrame, rate: float) -> list[int]:
    """The smallest bucket that counts as a discovery, for each length class."""
    rows = tests.groupBy("length_class", "bucket").agg(F.count("*").alias("n")).collect()  # at most len(CLASSES) * (BUCKETS + 1)
    m = sum(r["n"] for r in rows)
    mean = sum(CLASSES[r["length_class"]][1] * r["n"] for r in rows) / m if m else 1.0
    weight = [w / mean for _, w in CLASSES]
    # weighted p-values in rising order; the last that lies below its share of the rate counts
    steps = sorted((10 ** (-r["bucket"] / 100) / weight[r["length_class"]], r["n"]) for r in rows)
    seen, cut = 0, 0.0
    for p, n in steps:
        seen += n
        if p <= rate * seen / m:
            cut = p
    return [math.ceil(-100 * math.log10(cut * w) - 1e-9) if 0 < cut * w < 1 else BUCKETS + 1 for w in weight]


def with_spans(slim: DataFrame, rate: float) -> DataFrame:
    """slim (rid, base, cands, more) with spans: the pattern spans and the discoveries that overlap none of them."""
    tests = written(tested(slim.select("rid", F.inline("cands"))))
    least = F.lit(BUCKETS + 1)
    for i, b in enumerate(thresholds(tests, rate)):
        least = F.when(F.col("length_class") == i, F.lit(b)).otherwise(least)
    one = F.struct("start", F.lit(KINDS.index("random")).alias("rank"), F.lit("random").alias("kind"), "end")
    found = tests.where(F.col("bucket") >= least).groupBy("rid").agg(F.collect_list(one).alias("found"))
    free = F.filter(F.coalesce("found", _none(_SPAN)), lambda f: ~F.exists("base", lambda b: (b["start"] < f["end"]) & (f["start"] < b["end"])))
    return slim.join(found, "rid", "left").withColumn("spans", F.array_sort(F.concat("base", free))).drop("found", "cands")


def secret_spans(docs: DataFrame, rate: float = 0.01) -> DataFrame:
    """doc_id, base and spans (arrays of start, rank, kind, end) of each row."""
    base, cands = marked(_text())
    slim = docs.select(F.col("doc_id").cast("long").alias("doc_id"), base.alias("base"), cands.alias("cands"))
    return with_spans(written(slim.withColumn("rid", F.monotonically_increasing_id())), rate).drop("rid")


def redacted(docs: DataFrame, rate: float = 0.01, mask: str = "[SECRET]") -> DataFrame:
    """docs with every secret replaced by the mask, and n_chars, if there is one, brought up to date.

    Only texts in which some pattern or token occurs leave their task. Null and empty texts
    stay; repeated rows are each masked; columns of any name pass through.
    """
    some = touched(_text())
    base, cands = marked(_text())
    slim = written(docs.where(some).select(F.struct("*").alias("doc"), F.col("text").cast("string").alias("text"), base.alias("base"), cands.alias("cands")).withColumn("rid", F.monotonically_increasing_id()))
    zero = F.struct(F.lit(0).cast("long").alias("at"), _none("array<string>").alias("out"))

    def step(acc, s):
        gap = F.col("text").substr((acc["at"] + 1).cast("int"), F.greatest(F.lit(0), s["start"] - acc["at"]).cast("int"))
        more = F.concat(acc["out"], F.array(F.concat(gap, F.when(s["start"] >= acc["at"], F.lit(mask)).otherwise(F.lit("")))))
        return F.struct(F.greatest(acc["at"], s["end"]).alias("at"), more.alias("out"))

    done = F.aggregate("spans", zero, step, lambda a: F.concat(F.array_join(a["out"], ""), F.col("text").substr((a["at"] + 1).cast("int"), F.length("text"))))
    fixed = with_spans(slim, rate).withColumn("new", F.when(F.size("spans") > 0, done).otherwise(F.col("text")))
    now = {"text": F.col("new")} | ({"n_chars": F.length("new").cast(docs.schema["n_chars"].dataType)} if "n_chars" in docs.columns else {})
    return docs.where(~some).unionByName(fixed.select(*[now.get(c, F.col("doc")[c]).alias(c) for c in docs.columns]))


def op5_secrets(spark, sf_dir: str) -> DataFrame:
    return digests(secret_spans(table(spark, sf_dir, "documents", "doc_id", "text")), "base", "spans", KINDS[:3])
