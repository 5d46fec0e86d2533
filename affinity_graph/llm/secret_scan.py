"""Secret scans with DataFrame functions only: three patterns, and a randomness battery for what patterns cannot name.

Patterns (kinds assign, access, hex) give the base spans. Every other run of 20 or more characters of the usual encodings is a
candidate of kind ``random``. Its encoding is inferred (hex, base32, base36, letters, base64), and under the hypothesis that its symbols
are independent and uniform three tests are made: chi-squared over the alphabet, runs of the upper half of the alphabet, and
serial correlation of neighbours. The smallest p-value, times three, is the battery's; below ``LEVEL`` the candidate is
ordinary text. Those that pass are tested the other way round (``ordinary``), under the hypothesis that they are text, by the
statistics of chi-squared (pairs of equal symbols, fewer than text has) and of runs (changes between kinds of symbols); that
p-value, but not less than exp(-length * information per symbol), goes to the Benjamini-Hochberg step-up over the
candidates of its document at rate ``RATE``: short candidates need the company of longer ones. Rejected candidates count with 1.

Places are code points, from the lengths of what lies between matches; a text without matches costs a search alone. Work
on a document grows with its length and its matches, and nothing is shuffled.

Nulls and edges: a null text is empty and has no spans; repeated rows are scanned alike; overlapping spans of different
kinds are all reported, and ``redact`` covers them as one; other columns, of whatever name, pass through ``redact``; an
empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import load, packed, unpacked


def _either_case(word: str) -> str:
    return "".join(f"[{c.upper()}{c}]" if c.isalpha() else c for c in word)


#: Kinds in the order in which spans of one start are listed: (name, pattern, least length, group that has it) (fixed values).
ASSIGN = "(" + "|".join(map(_either_case, ("password", "passwd", "secret", "token", "api_?key"))) + ")[\"']?\\x20*[:=]\\x20*[\"']?([A-Za-z0-9+/_.=-]+)"
BASE = (("assign", ASSIGN, 6, 2), ("access", "AKIA[A-Z0-9]+", 20, 0), ("hex", "[0-9a-f]+", 24, 0))
#: What a search must find before matches are taken apart; equal in effect, as shorter matches are dropped.
SEARCH = {"assign": ASSIGN, "access": "AKIA[A-Z0-9]{16}", "hex": "[0-9a-f]{24}"}
CANDIDATE, LEAST = "[A-Za-z0-9+/_-]+", 20
LEVEL, RATE = 0.01, 0.01
#: Encodings: (name, test, alphabet, nats by which ordinary identifiers differ from uniform symbols) (fixed values).
ENCODINGS = (
    ("hex", "^(?=.*[0-9])(?=.*[a-f])[0-9a-f]+$", "0123456789abcdef", 0.25),
    ("hex", "^(?=.*[0-9])(?=.*[A-F])[0-9A-F]+$", "0123456789ABCDEF", 0.25),
    ("base32", "^(?=.*[2-7])(?=.*[A-Z])[A-Z2-7]+$", "ABCDEFGHIJKLMNOPQRSTUVWXYZ234567", 0.35),
    ("base64", "^(?=.*[0-9])(?=.*[a-z])(?=.*[A-Z])[A-Za-z0-9+/_-]+$", "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/", 0.45),
)
#: Looked at after those above, the last for every run that is left. Ordinary words are nearer to these, so the shares of kinds of symbols
#: must fit the alphabet (``KINDS``, ``FIT``), else the run is of no encoding. Dashes of hex groups are left out.
WIDER = (
    ("hex", "^(?=.*[0-9])(?=.*[a-f])(?=.*-)[0-9a-f][0-9a-f-]*$", "0123456789abcdef", 0.25),
    ("hex", "^(?=.*[0-9])(?=.*[A-F])(?=.*-)[0-9A-F][0-9A-F-]*$", "0123456789ABCDEF", 0.25),
    ("base32", "^(?=.*[2-7])(?=.*[a-z])[a-z2-7]+$", "abcdefghijklmnopqrstuvwxyz234567", 0.35),
    ("base36", "^(?=.*[0-9])(?=.*[a-z])[a-z0-9]+$", "abcdefghijklmnopqrstuvwxyz0123456789", 0.37),
    ("base36", "^(?=.*[0-9])(?=.*[A-Z])[A-Z0-9]+$", "ABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789", 0.37),
    ("base52", "^(?=.*[a-z])(?=.*[A-Z])[A-Za-z]+$", "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz", 0.42),
    ("base26", "^[a-z]+$", "abcdefghijklmnopqrstuvwxyz", 0.12),
    ("base26", "^[A-Z]+$", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", 0.12),
    ("base64", "^[A-Za-z0-9+/_-]+$", ENCODINGS[3][2], 0.45),
)
#: Ordinary identifiers: equal among pairs of symbols (in hex digits, else), changes of kind among neighbours (with letters of one
#: case, of both), changes between vowels and consonants (fixed values).
EQUAL, CHANGE, ALTERNATE = (0.12, 0.06), (0.12, 0.3), 0.6
KINDS, FIT = ("aeiou", "bcdfghjklmnpqrstvwxyz", "AEIOU", "BCDFGHJKLMNPQRSTVWXYZ", "0123456789", "+/"), 0.02
_SPAN = "array<struct<s:int,k:int,e:int,name:string,said:string>>"


def _matches(text: Column, pattern: str, search: str, number: int, name: str, least: int, group: int) -> Column:
    """Spans of one kind, leftmost and without overlap, short matches dropped after matching."""
    found = F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    parts = F.zip_with(F.slice(F.split(text, pattern, -1), 1, F.size(found)), found, lambda gap, m: F.struct(F.length(gap).alias("gap"), F.length(m).alias("size"), m.alias("said")))
    zero = F.struct(F.lit(0).alias("at"), F.array().cast(_SPAN).alias("out"))

    def step(acc: Column, p: Column) -> Column:
        start = acc["at"] + p["gap"]
        size = F.length(F.regexp_extract(p["said"], pattern, group)) if group else p["size"]
        span = F.struct(start.alias("s"), F.lit(number).alias("k"), (start + p["size"]).alias("e"), F.lit(name).alias("name"), p["said"].alias("said"))
        return F.struct((start + p["size"]).alias("at"), F.when(size >= least, F.array_append(acc["out"], span)).otherwise(acc["out"]).alias("out"))

    return F.when(text.rlike(search), F.aggregate(parts, zero, step, lambda acc: acc["out"])).otherwise(F.array().cast(_SPAN))


def _upper_tail(z: Column) -> Column:
    """P(Z > z) of a standard normal by a logistic curve (error under 2e-4)."""
    capped = F.greatest(F.lit(-8.0), F.least(F.lit(8.0), z))
    return F.lit(1.0) / (F.lit(1.0) + F.exp(F.lit(1.5976) * capped + F.lit(0.070565) * capped * capped * capped))


def battery(said: Column, alphabet: str) -> Column:
    """Three times the smallest p-value of the tests of uniform, independent symbols."""
    size = len(alphabet)
    n = F.length(said).cast("double")
    said = F.translate(said, "-_", "+/") if size == 64 else said
    df = float(size - 1)
    chi = (F.lit(2.0) * _collisions(said, alphabet) + n) * F.lit(float(size)) / n - n
    z_chi = (F.pow(F.greatest(chi, F.lit(0.0)) / df, F.lit(1 / 3)) - (1 - 2 / (9 * df))) / (2 / (9 * df)) ** 0.5
    halves = F.translate(said, alphabet, "0" * (size // 2) + "1" * (size // 2))
    ones = (n - F.length(F.replace(halves, F.lit("1"), F.lit("")))).cast("double")
    turns = (F.length(halves) * 2 - F.length(F.replace(halves, F.lit("01"), F.lit(""))) - F.length(F.replace(halves, F.lit("10"), F.lit("")))).cast("double") / 2
    mean = F.lit(2.0) * ones * (n - ones) / n + 1
    spread = F.sqrt(F.greatest((mean - 1) * (mean - 2) / (n - 1), F.lit(1e-9)))
    z_runs = F.abs(turns + 1 - mean) / spread
    values = F.transform(F.split(said, ""), lambda c: F.position(c, F.lit(alphabet)).cast("double") - (size + 1) / 2)
    m = F.length(said)
    product = F.aggregate(F.zip_with(F.slice(values, 1, m - 1), F.slice(values, 2, m - 1), lambda a, b: a * b), F.lit(0.0), lambda a, x: a + x)
    z_serial = F.abs(product) / (F.sqrt(n - 1) * ((size * size - 1) / 12))
    return F.least(F.lit(1.0), F.lit(3.0) * F.least(_upper_tail(z_chi), F.lit(2.0) * _upper_tail(z_runs), F.lit(2.0) * _upper_tail(z_serial)))


def _collisions(said: Column, alphabet: str) -> Column:
    """Pairs of equal symbols: chi-squared but for its scale, and with power where a symbol is expected less than once."""
    n = F.length(said).cast("double")
    squares = F.aggregate(F.transform(F.sequence(F.lit(1), F.lit(len(alphabet))), lambda i: F.pow((F.length(said) - F.length(F.replace(said, F.substr(F.lit(alphabet), i, F.lit(1)), F.lit("")))).cast("double"), F.lit(2.0))), F.lit(0.0), lambda a, x: a + x)
    return (squares - n) / 2


def ordinary(said: Column, alphabet: str) -> Column:
    """p-value of a run under the hypothesis of text, from a collision test and a test of changes between kinds (Stouffer's sum).

    Of pairs of symbols in text ``EQUAL`` are equal, and of neighbours ``CHANGE`` differ in kind (case, digit, sign); where
    the alphabet has letters of one case only, kinds are vowels and consonants, which alternate more in text.
    """
    n = F.length(said).cast("double")
    pairs = n * (n - 1) / 2
    z_equal = F.lit(2.0) * (F.sqrt(F.lit(EQUAL[len(alphabet) > 16]) * pairs + 0.375) - F.sqrt(_collisions(said, alphabet) + 0.375))
    letters_only = alphabet.isalpha() and (alphabet.islower() or alphabet.isupper())
    kinds = (KINDS[0] + KINDS[2], KINDS[1] + KINDS[3]) if letters_only else (KINDS[0] + KINDS[1], KINDS[2] + KINDS[3], KINDS[4], KINDS[5])
    kind_of = F.translate(said, "".join(kinds), "".join(str(i) * len(k) for i, k in enumerate(kinds)))
    turns = (F.length(F.regexp_replace(kind_of, r"(.)\1*", "x")) - 1).cast("double")
    both = any(c.islower() for c in alphabet) and any(c.isupper() for c in alphabet)
    share, sign = (ALTERNATE, -1.0) if letters_only else (CHANGE[both], 1.0)
    z_turns = F.lit(sign) * (turns - F.lit(share) * (n - 1)) / F.sqrt(F.lit(share * (1 - share)) * (n - 1))
    return _upper_tail((z_equal + z_turns) / F.lit(2**0.5))


def _fits(said: Column, alphabet: str) -> Column:
    """Whether vowels, consonants, digits and signs have about the shares of the alphabet (chi-squared)."""
    n = F.length(said).cast("double")
    kinds = [(k, sum(c in k for c in alphabet) / len(alphabet)) for k in KINDS]
    kinds = [(k, share) for k, share in kinds if share]
    chi = F.lit(0.0)
    for k, share in kinds:
        chi += F.pow(n - F.length(F.translate(said, k, "")) - n * share, F.lit(2.0)) / (n * share)
    df = float(len(kinds) - 1)
    return _upper_tail((F.pow(chi / df, F.lit(1 / 3)) - (1 - 2 / (9 * df))) / (2 / (9 * df)) ** 0.5) >= FIT


def _scored(candidates: Column) -> Column:
    """Candidates with the p-value of their being ordinary text; those that fit no encoding are left out."""

    def one(x: Column) -> Column:
        score = F.lit(None).cast("double")
        for name, test, alphabet, nats in reversed(WIDER):
            said = F.translate(x["said"], "-", "") if name == "hex" else F.translate(x["said"], "-_", "+/")
            odds = F.exp(F.length(said).cast("double") * -nats)
            passes = F.when(battery(said, alphabet) >= LEVEL, F.greatest(odds, ordinary(said, alphabet))).otherwise(F.lit(1.0))
            # too short to be told from text by any company: no part of the step-up
            score = F.when(x["said"].rlike(test), F.when((odds <= RATE) & _fits(said, alphabet), passes)).otherwise(score)
        for name, test, alphabet, nats in reversed(ENCODINGS):
            said = F.translate(x["said"], "-_", "+/") if name == "base64" else x["said"]
            odds = F.exp(F.length(said).cast("double") * -nats)
            passes = F.when(battery(said, alphabet) >= LEVEL, F.greatest(odds, ordinary(said, alphabet))).otherwise(F.lit(1.0))
            score = F.when(x["said"].rlike(test), passes).otherwise(score)
        return F.struct(score.alias("p"), x.alias("x"))

    return F.filter(F.transform(candidates, one), lambda y: y["p"].isNotNull())


def scan(docs: DataFrame) -> DataFrame:
    """(row, secrets): the columns of ``docs`` as a struct, and an array of (s, k, e, name, said) by start and kind."""
    t = F.coalesce(F.col("row.text"), F.lit(""))
    df = packed(docs).withColumn("x_text", t)
    t = F.col("x_text")
    for number, (name, pattern, least, group) in enumerate(BASE):
        df = df.withColumn(f"x_{name}", _matches(t, pattern, SEARCH[name], number, name, least, group))
    df = df.withColumn("x_run", _matches(t, CANDIDATE, f"{CANDIDATE[:-1]}{{{LEAST}}}", len(BASE), "random", LEAST, 0))
    df = df.withColumn("x_scored", F.when(F.size("x_run") > 0, _scored(F.col("x_run"))).otherwise(F.array().cast(f"array<struct<p:double,x:{_SPAN[6:-1]}>>")))
    ranked = F.transform(F.sort_array(F.transform("x_scored", lambda y: y["p"])), lambda p, i: F.when(p * F.size("x_scored") <= (i + 1) * F.lit(RATE), p))
    df = df.withColumn("x_limit", F.when(F.size("x_scored") > 0, F.array_max(ranked)))
    # The limit goes in by an array of its copies, so that it is worked out once a document even if projections are merged.
    paired = F.zip_with("x_scored", F.array_repeat("x_limit", F.size("x_scored")), lambda y, limit: F.when(y["p"] <= limit, y["x"]))
    random = F.filter(paired, lambda x: x.isNotNull())
    spans = F.sort_array(F.concat(*[f"x_{b[0]}" for b in BASE], random))
    # Filters on the spans are not pushed through a generator, which keeps them from working everything out again.
    return df.select("row", F.explode(F.array(spans)).alias("secrets"))


def listed(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda x: F.concat_ws(":", x["name"], x["s"].cast("string"), x["e"].cast("string"))), ",")


def redact(docs: DataFrame) -> DataFrame:
    """``docs`` with every secret replaced by ``[SECRET]``, n_chars following where it is there."""
    df = scan(docs)
    zero = F.struct(F.lit(0).alias("at"), F.array().cast("array<string>").alias("out"))

    def step(acc: Column, x: Column) -> Column:
        gap = F.substr(F.col("row.text"), acc["at"] + 1, x["s"] - acc["at"])
        out = F.when(x["s"] >= acc["at"], F.array_append(acc["out"], F.concat(gap, F.lit("[SECRET]")))).otherwise(acc["out"])
        return F.struct(F.greatest(acc["at"], x["e"]).alias("at"), out.alias("out"))

    left = F.aggregate("secrets", zero, step, lambda acc: F.concat(F.array_join(acc["out"], ""), F.substr(F.col("row.text"), acc["at"] + 1, F.length("row.text"))))
    df = df.withColumn("left", F.when(F.size("secrets") > 0, left).otherwise(F.col("row.text")))
    n_chars = F.when(F.size("secrets") > 0, F.length("left").cast("long")).otherwise(F.col("row.n_chars")) if "n_chars" in docs.columns else F.lit(None)
    return unpacked(df, docs.columns, text=F.col("left"), n_chars=n_chars)


def _of_kind(k: int):
    return lambda x: x["k"] == k


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = scan(load(spark, sf_dir, "documents").select("doc_id", "text"))
    base = F.filter("secrets", lambda x: x["k"] < len(BASE))
    counts = [F.size(F.filter("secrets", _of_kind(k))).cast("long").alias(f"n_{b[0]}") for k, b in enumerate(BASE)]
    return df.select("row.doc_id", *counts, F.sha2(listed(base), 256).alias("base_sha256"), listed(F.col("secrets")).alias("spans"))
