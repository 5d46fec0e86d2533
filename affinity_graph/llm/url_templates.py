"""URL filtering by rules and by a tree of path templates, with DataFrame functions only.

Per host, path segments make a tree, a level at a time and as deep as the paths; from level ``depth`` on, the rest of a path
is one segment. At each node (host and template so far):

1. Variable segments become the wildcard ``*``: those with digits or percent signs, very long ones, and rare ones (``RARE``
   pages at most) among many siblings (``WIDE`` or more).
2. Statistically similar branches merge: labelled siblings are put into ``RATES`` + 1 classes by their share of blocked labels, and
   neighbouring classes whose shares a two-proportion test cannot tell apart (``Z_SQUARED``) become one branch, named by its
   smallest member behind ``~``. Branches without labels are like nothing and stay by themselves.

A template is rejected if its labelled purity, (blocked + ``STRENGTH`` / 2) / (labelled + ``STRENGTH``), is over ``REJECT``: at least four
labels, nearly all of them blocked. A template without labels has 0.5 and is never rejected. Labels are the rules'
verdicts and, for pages without a rule, the boolean column a caller names.

Each level is a few aggregates over distinct templates, written to the shared folder, so that plans stay short; a node's siblings
are never in one group but as RATES + 1 sums. A host with a third of all pages is a few rows once aggregated before the
shuffle; the pages join their template on (host, segments), which adaptive execution can split.

Nulls and edges: a null url, or one without ``://``, has an empty host and path; empty segments are passed over; equal urls are
judged alike; of rules of equal length the one first in order of its text wins; a null label is none; columns other than
page_id, url and the labels are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window

from .common import load, stored

#: (verdict, host and path prefix) of the query (fixed values).
RULES = (("allow", "com/"), ("block", "example.com/en/"), ("allow", "www.example.com/en/"), ("block", "net/es/"), ("block", "net/fr/"))
DEPTH, WIDE, RARE, RATES = 8, 50, 2, 16
STRENGTH, REJECT, Z_SQUARED, LONG = 2.0, 0.8, 3.84, 24
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def host_and_path(url: Column | str) -> tuple[Column, Column]:
    host = F.translate(F.regexp_extract(url, "://([^/?#]*)", 1), _UPPER, _LOWER)
    return F.coalesce(host, F.lit("")), F.coalesce(F.regexp_extract(url, "://[^/?#]*([^?#]*)", 1), F.lit(""))


def rule_of(host: Column, path: Column, rules: tuple[tuple[str, str], ...]) -> tuple[Column, Column]:
    """The longest rule that fits, and its verdict. The list of rules is a parameter, hence one expression."""
    rule = verdict = F.lit(None).cast("string")
    for what, text in sorted(rules, key=lambda r: (len(r[1]), [-ord(c) for c in r[1]])):
        name, slash, rest = text.partition("/")
        fits = ((host == name) | host.endswith("." + name)) & path.startswith(slash + rest)
        rule, verdict = F.when(fits, F.lit(text)).otherwise(rule), F.when(fits, F.lit(what)).otherwise(verdict)
    return rule, verdict


def generalised(path: Column, depth: int = DEPTH) -> Column:
    """A path's segments, variable ones as ``*``, at most ``depth`` of them: the last one holds the rest of the path."""
    parts = F.transform(F.filter(F.split(path, "/"), lambda s: s != ""), lambda s: F.when(s.rlike("[0-9%]") | (F.length(s) > LONG), F.lit("*")).otherwise(s))
    rest = F.array_join(F.slice(parts, depth, F.greatest(F.size(parts) - depth + 1, F.lit(0))), "/")
    return F.when(F.size(parts) > depth, F.array_append(F.slice(parts, 1, depth - 1), rest)).otherwise(parts)


def _sums() -> list[Column]:
    return [F.sum(c).alias(c) for c in ("n", "labelled", "bad")]


def _merged(branch: DataFrame) -> DataFrame:
    """(host, above, class, branch): classes of labelled siblings by share of blocked, similar neighbours under one name."""
    at = ["host", "above"]
    classes = branch.where("labelled > 0").groupBy(*at, "class").agg(F.sum("labelled").alias("l"), F.sum("bad").alias("b"), F.min("name").alias("least"), F.count(F.lit(1)).alias("members"))
    order = Window.partitionBy(*at).orderBy("class")  # RATES + 1 rows at most
    classes = classes.withColumn("l0", F.lag("l").over(order)).withColumn("b0", F.lag("b").over(order))
    pooled = (F.col("b") + F.col("b0")) / (F.col("l") + F.col("l0"))
    gap = F.col("b") / F.col("l") - F.col("b0") / F.col("l0")
    apart = F.coalesce(gap * gap > F.lit(Z_SQUARED) * pooled * (F.lit(1.0) - pooled) * (F.lit(1.0) / F.col("l") + F.lit(1.0) / F.col("l0")), F.lit(True))
    classes = classes.withColumn("part", F.sum(apart.cast("int")).over(order))
    part = Window.partitionBy(*at, "part")
    least, members = F.min("least").over(part), F.sum("members").over(part)
    return classes.select(*at, "class", F.when(members > 1, F.concat(F.lit("~"), least)).otherwise(least).alias("branch"))


def grown(tree: DataFrame, level: int) -> DataFrame:
    """``tree`` (host, segments, above, n, labelled, bad) with the template ``above`` longer by the branch of segment ``level``."""
    at = ["host", "above"]
    child = tree.where(F.size("segments") > level).groupBy(*at, F.get("segments", F.lit(level)).alias("segment")).agg(*_sums())
    brothers = child.groupBy(*at).agg(F.count(F.lit(1)).alias("brothers"))
    rare = (F.col("brothers") >= WIDE) & (F.col("n") <= RARE)
    child = child.join(brothers, at).withColumn("name", F.when(rare, F.lit("*")).otherwise(F.col("segment")))
    branch = child.groupBy(*at, "name").agg(*_sums()).withColumn("class", F.floor(F.try_divide(F.col("bad") * RATES, F.col("labelled"))))
    names = branch.select(*at, "name", "class").join(_merged(branch), [*at, "class"], "left").select(*at, "name", F.coalesce("branch", "name").alias("branch"))
    of = child.select(*at, "segment", "name").join(names, [*at, "name"]).select(*at, "segment", "branch")
    out = tree.withColumn("segment", F.get("segments", F.lit(level))).join(of, [*at, "segment"], "left")
    above = F.when(F.col("branch").isNotNull(), F.array_append("above", F.col("branch"))).otherwise(F.col("above"))
    return out.select("host", "segments", above.alias("above"), "n", "labelled", "bad")


def template_tree(pages: DataFrame) -> DataFrame:
    """Per (host, segments) of ``pages`` (host, segments, blocked): its template, that template's counts and its purity."""
    one, bad = F.col("blocked").isNotNull().cast("long"), F.coalesce(F.col("blocked"), F.lit(False)).cast("long")
    tree = pages.groupBy("host", "segments").agg(F.count(F.lit(1)).alias("n"), F.sum(one).alias("labelled"), F.sum(bad).alias("bad"))
    tree = stored(tree.withColumn("above", F.array().cast("array<string>")), "templates")
    for level in range(tree.agg(F.max(F.size("segments"))).head()[0] or 0):  # ``depth`` levels at most
        tree = stored(grown(tree, level), "templates")
    template = tree.groupBy("host", "above").agg(F.sum("n").alias("t_n"), F.sum("labelled").alias("t_labelled"), F.sum("bad").alias("t_bad"))
    purity = (F.col("t_bad") + F.lit(STRENGTH / 2)) / (F.col("t_labelled") + F.lit(STRENGTH))
    name = F.concat_ws("/", F.array("host"), "above")
    return tree.select("host", "segments", "above").join(template, ["host", "above"]).select("host", "segments", name.alias("template"), "t_n", "t_labelled", F.round(purity, 9).alias("purity"))


def judge(pages: DataFrame, rules: tuple[tuple[str, str], ...] = RULES, labels: str | None = None, depth: int = DEPTH) -> DataFrame:
    """(page_id, host, path, rule, verdict, template, t_labelled, purity) of ``pages`` (page_id, url).

    ``labels`` names a boolean column of ``pages``, true where a page is known to be bad.
    """
    host, path = host_and_path("url")
    known = F.col(f"`{labels}`").cast("boolean") if labels else F.lit(None).cast("boolean")
    df = pages.select("page_id", host.alias("host"), path.alias("path"), known.alias("known"))
    rule, said = rule_of(F.col("host"), F.col("path"), rules)
    df = df.select("page_id", "host", "path", rule.alias("rule"), said.alias("said"), "known", generalised(F.col("path"), depth).alias("segments"))
    tree = template_tree(df.withColumn("blocked", F.coalesce(F.col("said") == "block", "known")))
    verdict = F.coalesce("said", F.when(F.col("purity") > REJECT, F.lit("block")).otherwise(F.lit("allow")))
    return df.join(tree, ["host", "segments"]).select("page_id", "host", "path", "rule", verdict.alias("verdict"), "template", "t_labelled", "purity")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge(load(spark, sf_dir, "pages"))


def _oracle() -> str:
    cases = []
    for what, text in sorted(RULES, key=lambda r: (-len(r[1]), r[1])):
        name, _, rest = text.partition("/")
        cases.append((f"(host = '{name}' OR ends_with(host, '.{name}')) AND starts_with(path, '/{rest}')", text, what))
    rule = "CASE " + " ".join(f"WHEN {c} THEN '{t}'" for c, t, _ in cases) + " END"
    said = "CASE " + " ".join(f"WHEN {c} THEN '{w}'" for c, _, w in cases) + " END"
    sums = "sum(n) AS n, sum(labelled) AS labelled, sum(bad) AS bad"
    pooled = "((b + b0)::DOUBLE / (l + l0))"
    steps = ""
    for k in range(DEPTH):
        steps += f"""
c{k} AS MATERIALIZED (SELECT host, above, segments[{k + 1}] AS segment, {sums} FROM t{k} WHERE len(segments) > {k} GROUP BY ALL),
v{k} AS MATERIALIZED (SELECT *, CASE WHEN count(*) OVER (PARTITION BY host, above) >= {WIDE} AND n <= {RARE} THEN '*' ELSE segment END AS name FROM c{k}),
b{k} AS MATERIALIZED (SELECT host, above, name, floor(sum(bad) * {RATES}::DOUBLE / nullif(sum(labelled), 0)) AS class, sum(labelled) AS labelled, sum(bad) AS bad FROM v{k} GROUP BY host, above, name),
r{k} AS (SELECT host, above, class, sum(labelled) AS l, sum(bad) AS b, min(name) AS least, count(*) AS members FROM b{k} WHERE labelled > 0 GROUP BY host, above, class),
a{k} AS (SELECT *, lag(l) OVER w AS l0, lag(b) OVER w AS b0 FROM r{k} WINDOW w AS (PARTITION BY host, above ORDER BY class)),
d{k} AS (SELECT *, sum(coalesce((b::DOUBLE / l - b0::DOUBLE / l0) * (b::DOUBLE / l - b0::DOUBLE / l0) > {Z_SQUARED}::DOUBLE * {pooled} * (1.0::DOUBLE - {pooled}) * (1.0::DOUBLE / l + 1.0::DOUBLE / l0), true)::INT)
  OVER (PARTITION BY host, above ORDER BY class) AS part FROM a{k}),
m{k} AS (SELECT host, above, class, CASE WHEN sum(members) OVER w > 1 THEN '~' ELSE '' END || min(least) OVER w AS branch FROM d{k} WINDOW w AS (PARTITION BY host, above, part)),
t{k + 1} AS MATERIALIZED (SELECT t.host, t.segments, CASE WHEN v.name IS NULL THEN t.above ELSE list_append(t.above, coalesce(m.branch, v.name)) END AS above, t.n, t.labelled, t.bad FROM t{k} t
  LEFT JOIN v{k} v ON v.host = t.host AND v.above = t.above AND v.segment = t.segments[{k + 1}]
  LEFT JOIN b{k} b ON b.host = t.host AND b.above = t.above AND b.name = v.name LEFT JOIN m{k} m ON m.host = t.host AND m.above = t.above AND m.class = b.class),"""
    return f"""
WITH u AS (SELECT page_id, coalesce(regexp_extract(url, '://([^/?#]*)', 1), '') AS h, coalesce(regexp_extract(url, '://[^/?#]*([^?#]*)', 1), '') AS path FROM pages),
h AS (SELECT page_id, translate(h, '{_UPPER}', '{_LOWER}') AS host, path, list_transform(list_filter(string_split(path, '/'), lambda s: s <> ''), lambda s: CASE WHEN regexp_matches(s, '[0-9%]') OR length(s) > {LONG} THEN '*' ELSE s END) AS parts FROM u),
r AS MATERIALIZED (SELECT page_id, host, path, {rule} AS rule, {said} AS said, CASE WHEN len(parts) > {DEPTH} THEN list_append(parts[1:{DEPTH - 1}], array_to_string(parts[{DEPTH}:], '/')) ELSE parts END AS segments FROM h),
t0 AS MATERIALIZED (SELECT host, segments, CAST([] AS VARCHAR[]) AS above, count(*) AS n, count(said) AS labelled, count(*) FILTER (said = 'block') AS bad FROM r GROUP BY ALL),{steps}
tm AS (SELECT host, above, sum(bad) AS t_bad, sum(labelled)::BIGINT AS t_labelled FROM t{DEPTH} GROUP BY ALL),
tree AS (SELECT host, segments, array_to_string(list_prepend(host, above), '/') AS template, t_labelled, round((t_bad + {STRENGTH / 2}::DOUBLE) / (t_labelled + {STRENGTH}::DOUBLE), 9) AS purity FROM t{DEPTH} JOIN tm USING (host, above))
SELECT page_id, host, path, rule, coalesce(said, CASE WHEN purity > {REJECT} THEN 'block' ELSE 'allow' END) AS verdict, template, t_labelled, purity
FROM r JOIN tree USING (host, segments)
"""


ORACLE = _oracle()
