"""Line-first cleaning with DataFrame functions only.

Every line is judged by itself: navigation (menus of bars), symbols, shouting, missing punctuation and boilerplate. Failing
lines are removed, blank ones stay, and a document is rejected if it fails the base rules (too few words, too many words in
repeated windows) or loses more than ``max_loss`` percent of its word characters with its failing lines.

Repeated windows are counted per document: word hashes are paired three times to hash each 8-word window, and only
where two windows are equal are (hash, place) pairs sorted to find and cover the repeated places. All of it is linear or
n log n in the words of a document, and no row is shuffled.

Nulls and edges: a null or blank text has no words and fails; ``\\n`` alone parts lines; repeated rows are judged alike;
other columns, of whatever name, pass through ``clean`` unchanged; an empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import SPACES, load, packed, unpacked

MIN_WORDS, MAX_REPEAT_PERCENT, MAX_LOSS_PERCENT, WINDOW = 20, 30, 50, 8
SYMBOLS = "#*$%&|<>"
#: Phrases of lines that belong to a site or a licence and not to the text (fixed values).
BOILERPLATE = (
    "all rights reserved|licensed under|released under the|general public license|terms of use|terms of service|"
    "privacy policy|cookie policy|accept cookies|enable javascript|lorem ipsum|powered by wordpress|click here to|subscribe to our"
)
_BLANK = "[ \\t\\n\\x0b\\f\\r]"
_ENDS = "[.!?:;…。！？][\"')\\]»”’]*$"
_ANY_POINT = "[.,;:!?…。！？]"
_THREE_WORDS = "^[^ \\t\\r\\x0b\\f]+[ \\t\\r\\x0b\\f]+[^ \\t\\r\\x0b\\f]+[ \\t\\r\\x0b\\f]+[^ \\t\\r\\x0b\\f]"


def _dropped(column: Column | str, characters: str) -> Column:
    return F.translate(column, characters, "")


def line_fails(line: Column) -> Column:
    """Whether one line fails a rule; a blank line never does."""
    said = F.btrim(line, F.lit(SPACES))
    size = F.length(said)
    bars = size - F.length(_dropped(said, "|"))
    symbols = size - F.length(_dropped(said, SYMBOLS))
    shouts = size - F.length(F.replace(said, F.lit("!!"), F.lit("")))
    navigation = (bars >= 2) | said.endswith("|")
    odd = (symbols >= 3) & (symbols * 10 >= size)
    unpunctuated = ~said.rlike(_ENDS) & (~said.rlike(_THREE_WORDS) | ~said.rlike(_ANY_POINT))
    boilerplate = (size < 200) & F.lower(said).rlike(BOILERPLATE)
    return (size > 0) & (navigation | odd | (shouts >= 6) | unpunctuated | boilerplate)


def _pairs(a: str, gap: int, shorter: int) -> Column:
    """Hashes of the elements of array column ``a`` paired with those ``gap`` further on."""
    n = F.greatest(F.size(a) - shorter, F.lit(0))
    return F.zip_with(F.slice(a, 1, n), F.slice(a, 1 + gap, n), lambda x, y: F.xxhash64(x, y))


def measured(docs: DataFrame) -> DataFrame:
    """(row, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, q_lines, q_kept_lines); ``row`` has the columns of ``docs``."""
    none = F.array().cast("array<bigint>")
    t = F.coalesce(F.col("row.text"), F.lit(""))
    df = packed(docs).withColumn("q_words", F.array_remove(F.split(t, f"{_BLANK}+"), "")).withColumn("q_lines", F.split(t, "\\n"))
    df = df.withColumn("q_h1", F.transform("q_words", lambda w: F.xxhash64(w)))
    df = df.withColumn("q_h2", _pairs("q_h1", 1, 1)).withColumn("q_h4", _pairs("q_h2", 2, 2)).withColumn("q_h8", _pairs("q_h4", 4, 4))
    df = df.withColumn("q_again", F.size(F.array_distinct("q_h8")) < F.size("q_h8"))
    empty = F.array().cast("array<struct<h:bigint,i:int>>")
    df = df.withColumn("q_sorted", F.when(F.col("q_again"), F.sort_array(F.transform("q_h8", lambda h, i: F.struct(h.alias("h"), i.cast("int").alias("i"))))).otherwise(empty))
    hashes = F.transform("q_sorted", lambda x: x["h"])
    unknown = F.array(F.lit(None).cast("bigint"))
    df = df.withColumn("q_hashes", hashes)
    df = df.withColumn("q_near", F.zip_with(F.concat(unknown, F.slice("q_hashes", 1, F.greatest(F.size("q_hashes") - 1, F.lit(0)))), F.concat(F.slice("q_hashes", 2, F.greatest(F.size("q_hashes") - 1, F.lit(0))), unknown), lambda p, n: F.struct(p.alias("p"), n.alias("n"))))
    places = F.zip_with("q_sorted", "q_near", lambda x, y: F.when((x["h"] == y["p"]) | (x["h"] == y["n"]), x["i"].cast("bigint")))
    df = df.withColumn("q_places", F.when(F.col("q_again"), F.sort_array(F.filter(places, lambda p: p.isNotNull()))).otherwise(none))
    covered = F.aggregate(
        "q_places",
        F.struct(F.lit(0).cast("bigint").alias("upto"), F.lit(0).cast("bigint").alias("total")),
        lambda acc, p: F.struct((p + WINDOW).alias("upto"), (acc["total"] + p + WINDOW - F.greatest(acc["upto"], p)).alias("total")),
        lambda acc: acc["total"],
    )
    words = F.size("q_words").cast("long")
    said = F.filter("q_lines", lambda x: F.length(_dropped(x, SPACES)) > 0)
    df = df.withColumn("n_words", words).withColumn("word_chars", F.length(_dropped(t, SPACES)).cast("long")).withColumn("n_symbols", (F.length(t) - F.length(_dropped(t, SYMBOLS))).cast("long"))
    df = df.withColumn("q_said", said).withColumn("n_dup_lines", (F.size("q_said") - F.size(F.array_distinct("q_said"))).cast("long")).withColumn("n_repeat_words", covered)
    failed = (F.col("n_words") < MIN_WORDS) | (F.col("n_repeat_words") * 100 > F.col("n_words") * MAX_REPEAT_PERCENT)
    df = df.withColumn("base_failed", failed).withColumn("q_kept_lines", F.filter("q_lines", lambda x: ~line_fails(x)))
    return df.drop("q_words", "q_h1", "q_h2", "q_h4", "q_h8", "q_again", "q_sorted", "q_hashes", "q_near", "q_places", "q_said")


def judged(docs: DataFrame, max_loss: int = MAX_LOSS_PERCENT) -> DataFrame:
    """``measured`` with n_lines_removed, n_chars_lost and kept."""
    df = measured(docs)
    left = F.length(_dropped(F.array_join("q_kept_lines", ""), SPACES))
    df = df.withColumn("n_lines_removed", (F.size("q_lines") - F.size("q_kept_lines")).cast("long")).withColumn("n_chars_lost", F.col("word_chars") - left)
    return df.withColumn("kept", ~F.col("base_failed") & (F.col("n_chars_lost") * 100 <= F.col("word_chars") * max_loss))


def clean(docs: DataFrame, max_loss: int = MAX_LOSS_PERCENT) -> DataFrame:
    """The documents that are kept, without their failing lines, in the columns of ``docs``."""
    # A filter would be pushed through the projections and every measure worked out again inside it; one on the output of an
    # outer generator stays above them.
    one = F.explode_outer(F.when(F.col("kept"), F.array(F.lit(True))).otherwise(F.array().cast("array<boolean>")))
    kept = judged(docs, max_loss).select("row", "q_kept_lines", one.alias("q_one")).where("q_one IS NOT NULL").select("row", F.array_join("q_kept_lines", "\n").alias("said"))
    return unpacked(kept, docs.columns, text=F.col("said"), n_chars=F.length("said").cast("long"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents").select("doc_id", "text")
    return judged(docs).select("row.doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "n_lines_removed", "n_chars_lost", "kept")


_Q = {k: v.replace("'", "''") for k, v in {"ends": _ENDS.replace("$", "\\z"), "any": _ANY_POINT, "three": _THREE_WORDS, "boiler": BOILERPLATE}.items()}
_SP = "' ' || chr(9) || chr(10) || chr(11) || chr(12) || chr(13)"
ORACLE = f"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS t FROM documents),
a AS (SELECT doc_id, t, list_filter(string_split_regex(t, '[ \\t\\n\\x0b\\f\\r]+'), lambda x: x <> '') AS w, string_split(t, chr(10)) AS lines FROM d),
s AS (SELECT doc_id, unnest(range(1, len(w) - {WINDOW - 2})) AS i, w FROM a WHERE len(w) >= {WINDOW}),
g AS (SELECT doc_id, i, array_to_string(w[i:i + {WINDOW - 1}], ' ') AS win FROM s),
r AS (SELECT doc_id, i FROM g QUALIFY count(*) OVER (PARTITION BY doc_id, win) > 1),
c AS (SELECT doc_id, count(DISTINCT p) AS n FROM (SELECT doc_id, unnest(range(i, i + {WINDOW})) AS p FROM r) GROUP BY 1),
l AS (SELECT doc_id, t, w, lines, list_filter(lines, lambda x: length(regexp_replace(x, '[ \\t\\n\\x0b\\f\\r]', '', 'g')) > 0) AS said,
  list_filter(lines, lambda x: NOT (
    length(trim(x, {_SP})) > 0 AND (
      length(regexp_replace(x, '[^|]', '', 'g')) >= 2 OR ends_with(trim(x, {_SP}), '|')
      OR (length(regexp_replace(x, '[^{SYMBOLS}]', '', 'g')) >= 3 AND length(regexp_replace(x, '[^{SYMBOLS}]', '', 'g')) * 10 >= length(trim(x, {_SP})))
      OR length(x) - length(replace(x, '!!', '')) >= 6
      OR (NOT regexp_matches(trim(x, {_SP}), '{_Q["ends"]}') AND (NOT regexp_matches(trim(x, {_SP}), '{_Q["three"]}') OR NOT regexp_matches(x, '{_Q["any"]}')))
      OR (length(trim(x, {_SP})) < 200 AND regexp_matches(lower(trim(x, {_SP})), '{_Q["boiler"]}'))))) AS kl FROM a),
m AS (SELECT doc_id, len(w)::BIGINT AS n_words, length(array_to_string(w, ''))::BIGINT AS word_chars,
  length(regexp_replace(t, '[^{SYMBOLS}]', '', 'g'))::BIGINT AS n_symbols, (len(said) - len(list_distinct(said)))::BIGINT AS n_dup_lines,
  coalesce(c.n, 0)::BIGINT AS n_repeat_words, (len(lines) - len(kl))::BIGINT AS n_lines_removed,
  (length(array_to_string(w, '')) - length(regexp_replace(array_to_string(kl, ''), '[ \\t\\n\\x0b\\f\\r]', '', 'g')))::BIGINT AS n_chars_lost
  FROM l LEFT JOIN c USING (doc_id)),
b AS (SELECT *, (n_words < {MIN_WORDS} OR 100 * n_repeat_words > {MAX_REPEAT_PERCENT} * n_words) AS base_failed FROM m)
SELECT *, NOT base_failed AND 100 * n_chars_lost <= {MAX_LOSS_PERCENT} * word_chars AS kept FROM b
"""
