"""Secrets in texts: fixed patterns, and strings that pass a battery of randomness tests."""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Workspace, id_text, table

KINDS = ("assign", "access", "hex", "random")
ASSIGN = r"""((?i:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
#: Runs are maximal, so that a least length in the pattern drops the same matches as a filter behind it.
ACCESS, HEX = "AKIA[A-Z0-9]{12,}", "[0-9a-f]{32,}"
#: Strings that the tests judge, if they have a digit: of 20 random characters in base 64 one in 28 has none, of 40 one in 900.
CANDIDATE = "[A-Za-z0-9+/_-]{20,}"
_D, _L, _U = "0123456789", "abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
#: Encodings by pattern, the narrowest first, with their alphabets.
ENCODINGS = (("^[0-9]+$", _D), ("^[0-9a-f]+$", _D + "abcdef"), ("^[0-9A-F]+$", _D + "ABCDEF"), ("^[A-Z2-7]+$", _U + "234567"), ("^[0-9a-z]+$", _D + _L), ("^[0-9A-Z]+$", _D + _U), ("^[0-9A-Za-z]+$", _U + _L + _D), ("^[0-9A-Za-z+/]+$", _U + _L + _D + "+/"), ("^[0-9A-Za-z_-]+$", _U + _L + _D + "-_"))
#: Least p-value of the three tests (times three) at which a string still counts as random.
UNIFORM_LEVEL = 0.01
#: What ordinary names, numbers and paths are taken for: text whose chi-squared value exceeds that of random text by
#: STRUCTURE for each character, and in which a share CHANGES of the neighbours differ in kind (lower case, upper case,
#: digit, mark; a capital and its word are of one kind). Random text in base 64 has 0 and 0.48.
STRUCTURE, CHANGES = 1.5, 0.25
#: Share of false ones that is tolerated among the strings found, in each class of lengths.
FALSE_DISCOVERIES, LENGTHS = 0.05, (32, 64)
_BINS_PER_E, _MOST_BIN = 20, 2000


#: Matches that are placed at once; more go by stretches, so that the work grows with their number and not its square.
STRETCH = 256


def _let(value: Column, use: Callable[[Column], Column]) -> Column:
    """``use`` of a value that is computed once, however often it stands in the result."""
    return F.element_at(F.transform(F.array(value), use), 1)


def _above(z: Column) -> Column:
    """The normal distribution's upper tail, at most 6 % too large and never too small above zero."""

    def tail(x: Column) -> Column:
        return F.exp(-x * x / 2) * (2 / math.sqrt(2 * math.pi)) / (x + F.sqrt(x * x + 8 / math.pi))

    return _let(z, lambda x: F.when(x >= 0, tail(x)).otherwise(1 - tail(-x)))


def _located(text: Column, pattern: str, group: int | None = None) -> Column:
    """array of (start, end, own): leftmost non-overlapping matches in code points; own: a group's length."""
    return F.arrays_zip(F.split(text, pattern, -1).alias("gap"), F.regexp_extract_all(text, F.lit(pattern), F.lit(0)).alias("hit"), F.regexp_extract_all(text, F.lit(pattern), F.lit(group or 0)).alias("own"))


_SPANS = "array<struct<kind:string,start:int,end:int,own:string>>"


def _placed(kind: str, located: Column) -> Column:
    """Spans with places, from the gaps between matches and the matches by running sums: within stretches first, then
    over stretches."""
    spans, none = f"struct<at:int,spans:{_SPANS}>", F.array().cast(_SPANS)

    def step(a: Column, x: Column) -> Column:
        start = (a["at"] + F.length(x["gap"])).cast("int")
        end = (start + F.coalesce(F.length(x["hit"]), F.lit(0))).cast("int")
        span = F.struct(F.lit(kind).alias("kind"), start.alias("start"), end.alias("end"), x["own"].alias("own"))
        return F.struct(end.alias("at"), F.when(x["hit"].isNull(), a["spans"]).otherwise(F.concat(a["spans"], F.array(span))).alias("spans"))

    def moved(part: Column, at: Column) -> Column:
        return F.transform(part["spans"], lambda x: F.struct(x["kind"].alias("kind"), (x["start"] + at).cast("int").alias("start"), (x["end"] + at).cast("int").alias("end"), x["own"].alias("own")))

    zero = F.struct(F.lit(0).alias("at"), none.alias("spans"))
    stretches = F.transform(F.sequence(F.lit(0), F.floor((F.size(located) - 1) / STRETCH).cast("int")), lambda k: F.reduce(F.slice(located, k * STRETCH + 1, F.lit(STRETCH)), zero, step))
    ends = lambda parts: F.reduce(parts, F.array(F.lit(0)), lambda a, x: F.concat(a, F.array((F.element_at(a, -1) + x["at"]).cast("int"))))
    whole = _let(stretches, lambda parts: F.flatten(F.zip_with(parts, F.slice(ends(parts), F.lit(1), F.size(parts)), moved)))
    return F.when(F.size(located) <= STRETCH, F.reduce(located, F.lit(None).cast(spans), lambda a, x: step(F.coalesce(a, zero), x))["spans"]).otherwise(whole)


def _battery(own: Column) -> Column:
    """(n, uniform, structured): the least corrected p-value of the three tests for randomness, and the p-value, by
    Fisher's rule, of a chi-squared value as low and of changes as many as these in structured text; it falls with the
    length of random strings."""
    alphabet = F.lit(None).cast("string")
    for pattern, letters in reversed(ENCODINGS):
        alphabet = F.when(own.rlike(pattern), F.lit(letters)).otherwise(alphabet)
    # One letter for each kind of character.
    kinds = F.regexp_replace(F.regexp_replace(F.regexp_replace(F.regexp_replace(own, "[+/_-]", "%"), "[0-9]", "0"), "[A-Z]", "A"), "[a-z]", "a")
    changes = _let(kinds, lambda x: F.size(F.filter(F.transform(F.sequence(F.lit(1), F.length(x) - 1), lambda i: F.substr(x, i, F.lit(2))), lambda two: ~two.isin("aa", "AA", "00", "%%", "Aa"))))
    base = F.struct(F.length(own).cast("double").alias("n"), alphabet.alias("alphabet"), changes.cast("double").alias("changes"))
    return _let(base, lambda x: _let(F.transform(F.split(own, ""), lambda c: F.instr(x["alphabet"], c)), lambda at: _let(_moments(at, x["n"]), lambda m: _tests(x, at, m))))


def _moments(at: Column, n: Column) -> Column:
    """Sums about the mean of the places in the alphabet: products of neighbours, squares, runs, and how many are above."""
    zero = F.struct(F.lit(None).cast("double").alias("last"), *(F.lit(0.0).alias(x) for x in ("both", "square", "runs", "high")))

    def step(a: Column, d: Column) -> Column:
        turned = a["last"].isNull() | ((a["last"] > 0) != (d > 0))
        return F.struct(
            d.alias("last"),
            (a["both"] + F.coalesce(a["last"] * d, F.lit(0.0))).alias("both"),
            (a["square"] + d * d).alias("square"),
            (a["runs"] + F.when(turned, 1.0).otherwise(0.0)).alias("runs"),
            (a["high"] + F.when(d > 0, 1.0).otherwise(0.0)).alias("high"),
        )

    mean = F.reduce(at, F.lit(0.0), lambda a, x: a + x) / n
    return _let(mean, lambda m: F.reduce(F.transform(at, lambda x: x - m), zero, step))


def _tests(x: Column, at: Column, m: Column) -> Column:
    n, k = x["n"], F.length(x["alphabet"]).cast("double")
    df = k - 1
    squares = F.reduce(F.array_distinct(at), F.lit(0.0), lambda a, v: a + F.pow(F.size(F.filter(at, lambda y: y == v)).cast("double"), F.lit(2.0)))
    high, low = m["high"], n - m["high"]
    expected = 2 * high * low / n + 1
    runs_z = (m["runs"] - expected) / F.sqrt(F.greatest((expected - 1) * (expected - 2) / (n - 1), F.lit(1e-9)))
    serial_z = (m["both"] / F.greatest(m["square"], F.lit(1e-9)) + 1 / n) * F.sqrt(n)
    many = _above((x["changes"] - 0.5 - (n - 1) * CHANGES) / F.sqrt((n - 1) * CHANGES * (1 - CHANGES)))
    rest = F.struct((2 * _above(F.abs(runs_z))).alias("runs"), (2 * _above(F.abs(serial_z))).alias("serial"), many.alias("many"))

    def judged(chi: Column, y: Column) -> Column:
        # Chi-squared values by the cube root that is nearly normal.
        uniform = _above((F.pow(F.greatest(chi, F.lit(0.0)) / df, F.lit(1 / 3)) - (1 - 2 / (9 * df))) / F.sqrt(2 / (9 * df)))
        few = _above((df + n * STRUCTURE - chi) / F.sqrt(2 * df + 4 * n * STRUCTURE))
        least = F.least(F.lit(1.0), 3 * F.least(uniform, y["runs"], y["serial"]))
        fisher = _let(F.greatest(few * y["many"], F.lit(1e-300)), lambda p: p * (1 - F.ln(p)))
        return F.struct(n.cast("int").alias("n"), least.alias("uniform"), fisher.alias("structured"))

    return _let(squares * k / n - n, lambda chi: _let(rest, lambda y: judged(chi, y)))


def _length_class(n: Column) -> Column:
    return sum((F.when(n >= x, 1).otherwise(0) for x in LENGTHS), F.lit(0))


def _discoveries(judged: DataFrame) -> dict[int, int]:
    """For each class of lengths the least bin of -log p that keeps false discoveries to their share.

    The step-up rule over binned p-values, each taken as the largest of its bin; at most 3 x 2001 counts are read.
    """
    counts: dict[int, dict[int, int]] = {}
    for cls, b, n in judged.groupBy("cls", "bin").agg(F.count(F.lit(1))).collect():
        counts.setdefault(cls, {})[b] = n
    least = {}
    for cls, of in counts.items():
        total, so_far = sum(of.values()), 0
        for b in sorted(of, reverse=True):
            so_far += of[b]
            if total * math.exp(-b / _BINS_PER_E) <= FALSE_DISCOVERIES * so_far:
                least[cls] = b
    return least


def scan(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per row of ``docs``: doc_id, base and found (arrays of kind, start, end in code points, end exclusive).

    base: the fixed patterns' spans by start, then kind. found: strings outside base that the tests call random:
    all three tests (chi-squared uniformity over the inferred alphabet, runs about the mean, serial correlation)
    leave them random, and their chi-squared value and changes of kind are not those of structured text of their length, under control
    of the false discoveries among all strings judged in the corpus. Strings without a digit or below 20 characters are
    not judged. Null and empty texts have no spans; repeated rows and null ids are rows like any other. The work for a
    text grows with its length and number of spans.
    """
    ws = Workspace(docs.sparkSession, "secrets")
    none = F.array().cast(_SPANS)
    texts = id_text(docs, id_col, text_col)
    at_least = ASSIGN[:-2] + "{8})"  # if it is not found, no match can have 8 characters
    out = texts
    for kind, pattern, first, group in (("assign", ASSIGN, at_least, 2), ("access", ACCESS, ACCESS, None), ("hex", HEX, HEX, None), ("random", CANDIDATE, CANDIDATE, None)):
        out = out.withColumn(f"__{kind}", F.when(F.col("text").rlike(first), _located(F.col("text"), pattern, group)))
    out = out.drop("text")
    for kind in KINDS:
        out = out.withColumn(kind, F.when(F.col(f"__{kind}").isNotNull(), _placed(kind, F.col(f"__{kind}"))).otherwise(none))
    rank = lambda k: sum((F.when(k == x, i).otherwise(0) for i, x in enumerate(KINDS)), F.lit(0))
    long_enough = F.filter("assign", lambda x: F.length(x["own"]) >= 8)
    ordered = F.array_sort(F.transform(F.concat(long_enough, "access", "hex"), lambda x: F.struct(x["start"].alias("start"), rank(x["kind"]).alias("rank"), x["end"].alias("end"), x["kind"].alias("kind"))))
    out = out.select("doc_id", F.transform(ordered, lambda x: F.struct(x["kind"].alias("kind"), x["start"].alias("start"), x["end"].alias("end"))).alias("base"), "random")
    free = F.filter("random", lambda x: x["own"].rlike("[0-9]") & ~F.exists("base", lambda b: (b["start"] < x["end"]) & (x["start"] < b["end"])))
    out = out.select("doc_id", "base", free.alias("random"))
    judged = F.transform("random", lambda x: F.struct(x["kind"].alias("kind"), x["start"].alias("start"), x["end"].alias("end"), _battery(x["own"]).alias("test")))
    out = ws.save(out.select("doc_id", "base", judged.alias("judged")), "judged")
    bin_of = lambda t: F.least(F.lit(_MOST_BIN), F.floor(-F.ln(F.greatest(t["structured"], F.lit(1e-300))) * _BINS_PER_E)).cast("int")
    rows = out.where(F.size("judged") > 0).select(F.explode("judged.test").alias("t"))
    least = _discoveries(rows.select(_length_class(F.col("t.n")).alias("cls"), bin_of(F.col("t")).alias("bin")))
    enough = lambda t: F.coalesce(*(F.when(_length_class(t["n"]) == c, bin_of(t) >= b) for c, b in least.items()), F.lit(False))
    kept = F.filter("judged", lambda x: (x["test"]["uniform"] >= UNIFORM_LEVEL) & enough(x["test"]))
    return out.select("doc_id", "base", F.transform(kept, lambda x: F.struct(x["kind"].alias("kind"), x["start"].alias("start"), x["end"].alias("end"))).alias("found"))


def op5_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """scan() of all ``documents``: counts and digests of the base spans, and all spans as text."""
    out = scan(table(spark, sf_dir, "documents"))
    n = lambda kind: F.size(F.filter("base", lambda x: x["kind"] == kind)).cast("long")
    said = lambda spans: F.array_join(F.transform(spans, lambda x: F.concat_ws(":", x["kind"], x["start"].cast("string"), x["end"].cast("string"))), ",")
    order = F.array_sort(F.concat("base", "found"), lambda a, b: F.when(a["start"] < b["start"], -1).when(a["start"] > b["start"], 1).otherwise(0))
    return out.select("doc_id", n("assign").alias("n_assign"), n("access").alias("n_access"), n("hex").alias("n_hex"), F.sha2(said(F.col("base")), 256).alias("base_sha256"), said(order).alias("spans"))
