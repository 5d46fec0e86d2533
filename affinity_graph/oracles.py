"""DuckDB SQL of the graphs and measures, composed from the same rules in another engine's words."""

from __future__ import annotations

import math


def _simple(raw: str) -> str:
    return f"SELECT DISTINCT least(src, dst)::BIGINT AS lo, greatest(src, dst)::BIGINT AS hi FROM ({raw}) WHERE src IS NOT NULL AND dst IS NOT NULL AND src <> dst"


def _together(members: str) -> str:
    return _simple(f"WITH m AS (SELECT DISTINCT k, v FROM ({members})) SELECT x.v AS src, y.v AS dst FROM m x JOIN m y ON x.k = y.k AND x.v < y.v")


def _hashed(c: str, side: int) -> str:
    return f"CAST('0x' || substr(md5({c}), 1, 12) AS BIGINT) * 2 + {side}"


_HREF = "unnest(regexp_extract_all(html, 'href=\"([^\"]+)\"', 1))"

EDGES = {
    "doc_line": _together("""SELECT k, v FROM (SELECT *, count(*) OVER (PARTITION BY k) AS c FROM (SELECT DISTINCT doc_id AS v, md5(line) AS k FROM (SELECT doc_id, trim(unnest(string_split(text, chr(10)))) AS line FROM documents) WHERE length(line) > 15)) WHERE c BETWEEN 2 AND 60"""),
    "part_basket": _together("SELECT l_orderkey AS k, l_partkey AS v FROM lineitem"),
    "supp_basket": _together("SELECT l_orderkey AS k, l_suppkey AS v FROM lineitem"),
    "cust_day": _together("SELECT o_orderdate::DATE AS k, o_custkey AS v FROM orders"),
    "user_next": _simple("SELECT lag(user_id) OVER (ORDER BY ts, event_id) AS src, user_id AS dst FROM events"),
    "user_props": _together("SELECT hash(event_type, props, date_trunc('hour', ts)) AS k, user_id AS v FROM events"),
    "users_within": _simple("SELECT a.user_id AS src, b.user_id AS dst FROM events a JOIN events b ON a.event_type = b.event_type AND a.props = b.props AND a.ts >= b.ts AND a.ts <= b.ts + INTERVAL 1 HOUR"),
    "user_window": _together("SELECT time_bucket(INTERVAL 5 MINUTE, ts) AS k, user_id AS v FROM events"),
    "page_href": _simple(f"SELECT page_id * 2 AS src, {_hashed('href', 1)} AS dst FROM (SELECT page_id, {_HREF} AS href FROM pages)"),
    "host_href": _simple(f"SELECT {_hashed('host', 0)} AS src, {_hashed('href', 1)} AS dst FROM (SELECT regexp_extract(url, '^[a-z]+://([^/?#]+)', 1) AS host, {_HREF} AS href FROM pages)"),
    "cust_order": _simple("SELECT o_custkey * 2 AS src, o_orderkey * 2 + 1 AS dst FROM orders"),
    "order_part": _simple("SELECT l_orderkey * 2 AS src, l_partkey * 2 + 1 AS dst FROM lineitem"),
    "turn_chain": _simple("SELECT lag(conv_id * 1000 + turn) OVER (PARTITION BY conv_id ORDER BY turn) AS src, conv_id * 1000 + turn AS dst FROM conversations"),
    "vec_knn": _simple("""WITH e AS (SELECT vec_id, list_transform(embedding, lambda x: x::DOUBLE) AS v FROM embeddings), p AS (SELECT a.vec_id AS src, b.vec_id AS dst, round(list_cosine_similarity(a.v, b.v), 9) AS sim FROM e a JOIN e b ON a.vec_id <> b.vec_id) SELECT src, dst FROM p QUALIFY row_number() OVER (PARTITION BY src ORDER BY sim DESC, dst) <= 10"""),
}


# --- measures ----------------------------------------------------------------------------------------------------


def _base(g: str) -> str:
    return f"""e AS ({EDGES[g]}),
nd AS (SELECT v, count(*)::BIGINT AS degree FROM (SELECT lo AS v FROM e UNION ALL SELECT hi FROM e) GROUP BY v),
h AS (SELECT degree, count(*)::BIGINT AS n FROM nd GROUP BY degree)"""


def _clustered(g: str) -> str:
    return _base(g) + """,
tri AS (SELECT a.lo AS x, a.hi AS y, b.hi AS z FROM e a JOIN e b ON a.hi = b.lo JOIN e c ON c.lo = a.lo AND c.hi = b.hi),
cl AS (SELECT v, count(*)::BIGINT AS closed FROM (SELECT x AS v FROM tri UNION ALL SELECT y FROM tri UNION ALL SELECT z FROM tri) GROUP BY v),
lc AS (SELECT nd.v, degree, coalesce(closed, 0)::BIGINT AS closed, CASE WHEN degree > 1 THEN coalesce(closed, 0)::DOUBLE / (degree * (degree - 1) / 2) ELSE 0 END AS c FROM nd LEFT JOIN cl USING (v)),
cd AS (SELECT degree, count(*)::BIGINT AS n, sum(closed)::BIGINT AS closed, (count(*) * (degree * (degree - 1) // 2))::BIGINT AS wedges, avg(c) AS c_mean FROM lc GROUP BY degree),
prof AS (SELECT degree, n, CASE WHEN wedges > 0 THEN closed::DOUBLE / wedges ELSE 0 END AS c FROM cd)"""


def degrees(g: str) -> str:
    return f"WITH {_base(g)} SELECT v, degree FROM nd"


def degree_hist(g: str) -> str:
    return f"WITH {_base(g)} SELECT degree, n FROM h"


def size_from_hist(g: str) -> str:
    return f"WITH {_base(g)} SELECT sum(n)::BIGINT AS nodes, (sum(degree * n) // 2)::BIGINT AS edges, max(degree) AS dmax, round(sum(degree * n)::DOUBLE / sum(n), 6) AS davg FROM h"


def wedge_counts(g: str) -> str:
    return f"WITH {_base(g)} SELECT degree, n, (n * (degree * (degree - 1) // 2))::BIGINT AS wedges FROM h"


_SUMMARY = """SELECT '{g}' AS graph, '{model}' AS model, coalesce(sum(n), 0)::BIGINT AS nodes, coalesce(sum(degree * n) // 2, 0)::BIGINT AS edges, coalesce(max(degree), 0)::BIGINT AS dmax, round(coalesce(sum(degree * n)::DOUBLE / sum(n), 0), 6) AS davg,
coalesce(sum(wedges), 0)::BIGINT AS wedges, coalesce(sum(closed) // 3, 0)::BIGINT AS triangles, round(coalesce(sum(closed)::DOUBLE / nullif(sum(wedges), 0), 0), 6) AS gcc FROM cd"""


def summary(g: str, model: str = "original") -> str:
    return f"WITH {_clustered(g)} {_SUMMARY.format(g=g, model=model)}"


def clustering(g: str) -> str:
    return f"WITH {_clustered(g)} SELECT degree, n, closed, wedges, round(CASE WHEN wedges > 0 THEN closed::DOUBLE / wedges ELSE 0 END, 6) AS c, round(c_mean, 6) AS c_mean FROM cd"


def local(g: str) -> str:
    return f"WITH {_clustered(g)} SELECT v, degree, closed, round(c, 6) AS c FROM lc"


def triangle_rows(g: str) -> str:
    return f"WITH {_clustered(g)} SELECT x AS a, y AS b, z AS c FROM tri"


def gcc(g: str) -> str:
    return f"WITH {_clustered(g)} SELECT '{g}' AS graph, round(coalesce(sum(c * n * (degree * (degree - 1) // 2)) / nullif(sum(n * (degree * (degree - 1) // 2)), 0), 0), 6) AS gcc FROM prof"


def order(g: str) -> str:
    return f"WITH {_base(g)} SELECT v, degree, row_number() OVER (ORDER BY CASE WHEN degree = 1 THEN 4611686018427387904 ELSE degree END, v)::BIGINT AS position FROM nd"


def cumulative(g: str) -> str:
    return f"WITH {_base(g)} SELECT degree, (sum(n) OVER (ORDER BY degree))::BIGINT AS cum_le, (sum(n) OVER (ORDER BY degree ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING))::BIGINT AS cum_ge FROM h"


def cumulative_shares(g: str) -> str:
    return f"WITH {_base(g)} SELECT degree, round(sum(n) OVER (ORDER BY degree) / sum(n) OVER (), 6) AS cum_le, round(sum(n) OVER (ORDER BY degree ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) / sum(n) OVER (), 6) AS cum_ge FROM h"


#: Bin k begins at ceil((w^(k-1) - 1) / (w - 1)) + 1; repeated starts are one bin.
_BINS = """bs AS (SELECT DISTINCT ceil(round((pow(1.5, k - 1) - 1) / 0.5, 9))::BIGINT + 1 AS lo FROM range(1, 41) r(k)),
bn AS (SELECT row_number() OVER (ORDER BY lo)::INTEGER AS k, lo, lead(lo) OVER (ORDER BY lo) - 1 AS hi FROM bs)"""


def binned(g: str) -> str:
    return f"WITH {_clustered(g)}, {_BINS} SELECT k, lo, hi, sum(n)::BIGINT AS n, round(avg(c), 6) AS c FROM prof JOIN bn ON degree BETWEEN lo AND hi GROUP BY k, lo, hi"


def bins() -> str:
    return f"WITH {_BINS} SELECT k, lo, hi FROM bn WHERE lo <= 3000"


def roughness(g: str) -> str:
    return f"WITH {_base(g)} SELECT * FROM (SELECT degree, round(lag(ln(n)) OVER w - 2 * ln(n) + lead(ln(n)) OVER w, 6) AS second_difference FROM h WINDOW w AS (ORDER BY degree)) WHERE second_difference IS NOT NULL"


# --- plan --------------------------------------------------------------------------------------------------------

FIXTURE = "prof AS (SELECT degree::BIGINT AS degree, n::BIGINT AS n, CASE WHEN degree > 1 THEN 0.9::DOUBLE * exp(-0.1::DOUBLE * (degree - 1)) ELSE 0 END AS c FROM (VALUES (1,26),(2,20),(3,10),(4,6),(5,4),(6,3),(7,2),(8,1),(9,1)) t(degree, n))"


def _harmonic(n: str) -> str:
    return f"CASE WHEN {n} < 256 THEN coalesce(list_sum(list_transform(range(1, least({n}, 256) + 1), lambda k: 1::DOUBLE / k)), 0) ELSE ln({n}::DOUBLE) + 0.5772156649015329::DOUBLE + 1 / (2 * {n})::DOUBLE - 1 / (12 * ({n})::DOUBLE ** 2) + 1 / (120 * ({n})::DOUBLE ** 4) END"


_PAIRS = "(block_size * (block_size - 1) // 2)"
_SEEN = f"round_even({_PAIRS} * rho, 0)::BIGINT"
WEIGHTS = {"log": f"-blocks * {_PAIRS} * ln(1 - rho)", "plain": f"blocks * {_PAIRS} * rho", "harmonic": f"blocks * ({_PAIRS} * (({_harmonic(_PAIRS)}) - ({_harmonic(f'({_PAIRS} - {_SEEN})')})))"}


def planned(head: str, beta: float = 1.0, weight: str = "log") -> str:
    """CTEs up to pd (degrees) and pg (groups): the scan as a recursive query over distinct degrees."""

    def rho(c: str, size: str) -> str:
        return f"CASE WHEN {size} < 2 THEN 0::DOUBLE WHEN sqrt(least(1, greatest(0, {c}))) >= 1 THEN 1 - 1 / ({size} * ({size} - 1))::DOUBLE ELSE sqrt(least(1, greatest(0, {c}))) END"

    return f"""{head},
ir AS (SELECT degree, n, c, (1 + coalesce(sum(n) OVER (ORDER BY CASE WHEN degree = 1 THEN 4611686018427387904 ELSE degree END ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))::BIGINT AS first_node,
  coalesce(sum(n) OVER (ORDER BY degree ROWS BETWEEN 1 FOLLOWING AND UNBOUNDED FOLLOWING), 0)::BIGINT AS n_above FROM prof),
iq AS (SELECT *, row_number() OVER (ORDER BY degree) AS rn FROM ir WHERE degree > 1),
sc AS (
  SELECT 0::BIGINT AS rn, 0::BIGINT AS slots, 0::DOUBLE AS local, 0::BIGINT AS g, 0::BIGINT AS degree, 0::BIGINT AS first_node, 0::BIGINT AS n, 0::BIGINT AS fill, 0::DOUBLE AS w_fill, 0::DOUBLE AS w_bulk,
    0::BIGINT AS m1, 0::BIGINT AS b1, 0::BIGINT AS s1, 0::DOUBLE AS r1, 0::BIGINT AS m2, 0::BIGINT AS s2, 0::DOUBLE AS r2
  UNION ALL
  SELECT rn, CASE WHEN bulk = 0 THEN slots0 - fill WHEN m2 > 0 THEN s2 - m2 ELSE b1 * s1 - m1 END, CASE WHEN bulk = 0 THEN local0 WHEN m2 > 0 THEN (s2 - 1) * r2 ELSE (s1 - 1) * r1 END,
    g0 + (m1 > 0)::BIGINT + (m2 > 0)::BIGINT, degree, first_node, n, fill, fill * (degree - local0) / 2, m1 * (degree - (s1 - 1) * r1) / 2 + CASE WHEN m2 > 0 THEN m2 * (degree - (s2 - 1) * r2) / 2 ELSE 0 END, m1, b1, s1, r1, m2, s2, r2
  FROM (SELECT *, {rho("c", "s1")} AS r1, {rho("c", "s2")} AS r2
    FROM (SELECT *, CASE WHEN bulk = 0 THEN 0 WHEN whole_fits OR blocks = 1 THEN bulk ELSE bulk // size * size END AS m1, CASE WHEN bulk = 0 THEN 0 WHEN whole_fits OR blocks = 1 THEN blocks ELSE bulk // size END AS b1,
        CASE WHEN bulk = 0 THEN 0 WHEN whole_fits OR blocks > 1 THEN size ELSE remain END AS s1, CASE WHEN bulk = 0 OR whole_fits OR blocks = 1 THEN 0 ELSE bulk - bulk // size * size END AS m2,
        CASE WHEN bulk = 0 OR whole_fits OR blocks = 1 THEN 0 ELSE remain - bulk // size * size END AS s2
      FROM (SELECT *, blocks * size <= remain AS whole_fits
        FROM (SELECT q.rn, q.degree, q.first_node, q.n, q.c, least(s.slots, q.n) AS fill, q.n - least(s.slots, q.n) AS bulk, q.n - least(s.slots, q.n) + q.n_above AS remain, q.degree + 1 AS size,
            (q.n - least(s.slots, q.n) + q.degree) // (q.degree + 1) AS blocks, s.slots AS slots0, s.local AS local0, s.g AS g0 FROM sc s JOIN iq q ON q.rn = s.rn + 1)))))
,
pd0 AS (SELECT degree, first_node, n, fill AS n_fill, w_fill, w_bulk FROM sc WHERE rn > 0 UNION ALL SELECT degree, first_node, n, floor({beta} * n + 0.5)::BIGINT, n / 2::DOUBLE, 0 FROM ir WHERE degree = 1),
pd AS (SELECT *, w_fill + w_bulk AS w, CASE WHEN w_fill + w_bulk > 0 THEN w_fill / (w_fill + w_bulk) ELSE 0 END AS r FROM pd0),
pg0 AS (SELECT g - (m2 > 0)::BIGINT AS g, degree, first_node + fill AS first_node, b1 AS blocks, s1 AS block_size, r1 AS rho FROM sc WHERE m1 > 0
  UNION ALL SELECT g, degree, first_node + fill + b1 * s1, 1, s2, r2 FROM sc WHERE m2 > 0),
pg AS (SELECT *, CASE WHEN block_size > 1 THEN {WEIGHTS[weight]} ELSE 0 END AS w FROM pg0)"""


def plan_degree(g: str) -> str:
    head = FIXTURE if g == "fixture73" else _clustered(g)
    return f"WITH RECURSIVE {planned(head)} SELECT '{g}' AS graph, degree, first_node, n, n_fill, round(w_fill, 6) AS w_fill, round(w_bulk, 6) AS w_bulk, round(w, 6) AS w, round(r, 6) AS r FROM pd"


def plan_group(g: str, weight: str = "log", head: str | None = None) -> str:
    head = head or (FIXTURE if g == "fixture73" else _clustered(g))
    return f"WITH RECURSIVE {planned(head, weight=weight)} SELECT '{g}' AS graph, g::INTEGER AS g, degree, first_node, blocks, block_size, round(rho, 6) AS rho, round(w, 6) AS w FROM pg"


def plan_by_degree(g: str, top: float, fall: float) -> str:
    """Densities by a formula of the degree."""
    rho = f"{top}::DOUBLE * exp(-{fall}::DOUBLE * degree)"
    return plan_group(g, head=f"{_base(g)}, prof AS (SELECT degree, n, ({rho}) * ({rho}) AS c FROM h)")


def plan_ranges(g: str) -> str:
    return f"WITH RECURSIVE {planned(_clustered(g))} SELECT degree, n, first_node, n_above FROM ir"


def expected_edges(g: str) -> str:
    return f"WITH RECURSIVE {planned(_clustered(g))} SELECT round((SELECT sum(blocks * block_size * (block_size - 1) / 2 * rho) FROM pg), 6) AS local, round((SELECT sum(w) FROM pd), 6) AS global, round((SELECT sum(blocks * block_size * (block_size - 1) / 2 * rho) FROM pg) + (SELECT sum(w) FROM pd), 6) AS edges"


def plan_cells(g: str) -> str:
    return f"WITH RECURSIVE {planned(_clustered(g))} SELECT (SELECT count(*) * 5 FROM pd)::BIGINT AS degree_cells, (SELECT count(*) * 4 FROM pg)::BIGINT AS group_cells, (SELECT max(degree) * 10 FROM pd)::BIGINT AS bound"


def expanded_nodes() -> str:
    return f"WITH RECURSIVE {planned(FIXTURE)} SELECT 'fixture73' AS graph, v, degree, v < first_node + n_fill AS filler FROM (SELECT *, unnest(range(first_node, first_node + n)) AS v FROM pd)"


def expanded_blocks(g: str = "fixture73") -> str:
    return f"WITH RECURSIVE {planned(FIXTURE if g == 'fixture73' else _clustered(g))} SELECT '{g}' AS graph, g::INTEGER AS g, k AS block, (first_node + k * block_size)::BIGINT AS first_node, (first_node + (k + 1) * block_size - 1)::BIGINT AS last_node, degree FROM (SELECT *, unnest(range(0, blocks)) AS k FROM pg)"


# --- draws and generated edges through the portable uniforms --------------------------------------------------------


def _cumulated(source: str, key: str, keep: str) -> str:
    return f"""(SELECT bin, {keep}, (run - q)::DOUBLE / total::DOUBLE AS lo, run::DOUBLE / total::DOUBLE AS hi FROM (SELECT *, sum(q) OVER (ORDER BY bin) AS run, sum(q) OVER () AS total FROM (SELECT {key} AS bin, {keep}, greatest(w, 0)::DECIMAL(28,9) AS q FROM {source}) WHERE q > 0))"""


def _u(seed: int, stream: int | str, id_: str = "edge_id") -> str:
    from .functions.rng import duckdb_uniform

    return duckdb_uniform(seed, id_, stream)


def _below(u: str, n: str) -> str:
    return f"least(floor({u} * ({n})::DOUBLE)::BIGINT, ({n})::BIGINT - 1)"


def _unranked(source: str) -> str:
    """(a, b) of pair codes: the block, then the pair j < i with i (i - 1) / 2 + j."""
    return f"""SELECT first_node + blk * block_size + q - i * (i - 1) // 2 AS a, first_node + blk * block_size + i AS b
  FROM (SELECT *, CASE WHEN i0 * (i0 - 1) // 2 > q THEN i0 - 1 WHEN (i0 + 1) * i0 // 2 <= q THEN i0 + 1 ELSE i0 END AS i
    FROM (SELECT *, floor((sqrt(8::DOUBLE * q + 1) + 1) / 2)::BIGINT AS i0 FROM (SELECT *, code // pairs AS blk, code % pairs AS q FROM {source})))"""


def _gap(u: str, rho: str) -> str:
    return f"floor(ln(1 - {u}) / ln(1 - {rho}))::BIGINT + 1"


def _skipped(seed: int) -> str:
    """CTEs up to loc (a, b): pairs of dense groups by coins, of the others by gaps in tiles of 64 expected hits."""
    return f"""tg AS (SELECT *, {_PAIRS} AS pairs, blocks * {_PAIRS} AS codes FROM pg WHERE block_size > 1),
dense AS (SELECT g, first_node, block_size, pairs, rho, unnest(range(0, codes)) AS code FROM tg WHERE rho > 0.1),
tiles AS (SELECT *, unnest(range(0, (codes - 1) // span + 1)) AS tile FROM (SELECT *, ceil(64::DOUBLE / rho)::BIGINT AS span FROM tg WHERE rho > 0 AND rho <= 0.1)),
sparse AS (SELECT g, first_node, block_size, pairs, tile * span - 1 + sum({_gap(_u(seed, 13, "g || '-' || tile || '-' || s"), "rho")}) OVER (PARTITION BY g, tile ORDER BY s) AS code, least(codes, (tile + 1) * span) AS hi FROM tiles, range(1, 161) q(s)),
kept AS (SELECT first_node, block_size, pairs, code FROM dense WHERE {_u(seed, 13, "g || '-' || code")} < rho UNION ALL SELECT first_node, block_size, pairs, code::BIGINT FROM sparse WHERE code < hi),
loc AS ({_unranked("kept")})"""


def _poissoned(seed: int) -> str:
    """CTEs up to loc (a, b): a Poisson number of draws a tile of about 4096, by inversion below a mean of 30."""
    return f"""tg AS (SELECT *, {_PAIRS} AS pairs, blocks * {_PAIRS} AS codes FROM pg WHERE block_size > 1 AND w > 0),
tiles AS (SELECT *, tile * span AS lo, least(codes, (tile + 1) * span) AS hi FROM (SELECT *, unnest(range(0, (codes - 1) // span + 1)) AS tile FROM (SELECT *, greatest(1, ceil(4096::DOUBLE * codes / w)::BIGINT) AS span FROM tg))),
means AS (SELECT *, w * (hi - lo) / codes AS mean, {_u(seed, 11, "g || '-' || tile")} AS u1, {_u(seed, 12, "g || '-' || tile")} AS u2 FROM tiles),
steps AS (SELECT g, tile, u1, sum(exp(-mean + CASE WHEN k > 0 THEN k * ln(mean) - lgamma(k + 1) ELSE 0 END)) OVER (PARTITION BY g, tile ORDER BY k) AS cdf FROM means, range(0, 120) q(k) WHERE mean < 30),
numbers AS (SELECT g, tile, count(*) FILTER (cdf <= u1) AS number FROM steps GROUP BY g, tile UNION ALL
  SELECT g, tile, greatest(0, round(mean + sqrt(mean) * sqrt(-2 * ln(1 - u1)) * cos({2 * 3.141592653589793!r}::DOUBLE * u2))::BIGINT) FROM means WHERE mean >= 30),
drawn AS (SELECT m.*, unnest(range(1, number + 1)) AS s FROM means m JOIN numbers USING (g, tile)),
kept AS (SELECT first_node, block_size, pairs, lo + {_below(_u(seed, 3, "g || '-' || tile || '-' || s"), "hi - lo")} AS code FROM drawn),
loc AS ({_unranked("kept")})"""


def _realised(seed: int) -> str:
    """CTEs up to far (edge_id, a, b): both ends in proportion to what the local edges left of each node's degree."""

    def end(name: str, s: int) -> str:
        return f"{name} AS (SELECT edge_id, rk.v FROM (SELECT edge_id, start + {_below('mu', 'members')} AS position FROM (SELECT i AS edge_id, {_u(seed, s, 'i')} AS u, {_u(seed, s + 2, 'i')} AS mu FROM range((SELECT floor(sum(w) / 2 + 0.5)::BIGINT FROM lc2)) t(i)) x JOIN ld ON u >= lo AND u < hi) JOIN rk USING (position))"

    return f"""le AS (SELECT DISTINCT least(a, b) AS lo, greatest(a, b) AS hi FROM loc),
hv AS (SELECT v, count(*) AS has FROM (SELECT lo AS v FROM le UNION ALL SELECT hi FROM le) GROUP BY v),
wanted AS (SELECT degree, unnest(range(first_node, first_node + n)) AS v FROM pd),
rk AS (SELECT v, lft, row_number() OVER (ORDER BY lft, v) AS position FROM (SELECT v, degree - coalesce(has, 0) AS lft FROM wanted LEFT JOIN hv USING (v)) WHERE lft > 0),
lc2 AS (SELECT lft, count(*) AS members, min(position) AS start, lft * count(*) AS w FROM rk GROUP BY lft),
ld AS {_cumulated("lc2", "lft", "members, start")}, {end("ra", 5)}, {end("rb", 8)},
far AS (SELECT ra.edge_id, ra.v AS a, rb.v AS b FROM ra JOIN rb USING (edge_id))"""


def generated(g: str, beta: float, seed: int, mode: str = "independent") -> str:
    """CTEs up to gen (edge_id, phase, a, b); edge_id is null for local edges that are not drawn from ids."""
    head = planned(_clustered(g), beta)
    if mode == "independent":
        ids = f"""ids AS (SELECT i AS edge_id, {_u(seed, 0, "i")} < (SELECT w1 / (w1 + w2) FROM tot) AS is_local FROM range((SELECT floor(w1 + w2 + 0.5)::BIGINT FROM tot)) t(i))"""
    else:
        ids = """ids AS (SELECT i AS edge_id, i < (SELECT floor(w1 + 0.5) FROM tot) AS is_local FROM range((SELECT (floor(w1 + 0.5) + floor(w2 + 0.5))::BIGINT FROM tot)) t(i))"""

    def end(name: str, s: int) -> str:
        return f"{name} AS (SELECT edge_id, first_node + CASE WHEN fu < r THEN {_below('mu', 'n_fill')} ELSE n_fill + {_below('mu', 'n_bulk')} END AS v FROM (SELECT edge_id, {_u(seed, s)} AS u, {_u(seed, s + 1)} AS fu, {_u(seed, s + 2)} AS mu FROM ids WHERE NOT is_local) x JOIN dd ON u >= lo AND u < hi)"

    drawn = f"""lo1 AS (SELECT edge_id, first_node + {_below("bu", "blocks")} * block_size AS base, {_below("iu", "block_size")} AS i, {_below("ju", "block_size - 1")} AS j
  FROM (SELECT edge_id, {_u(seed, 1)} AS u, {_u(seed, 2)} AS bu, {_u(seed, 3)} AS iu, {_u(seed, 4)} AS ju FROM ids WHERE is_local) x JOIN gd ON u >= lo AND u < hi),
loc AS (SELECT edge_id, base + i AS a, base + j + (j >= i)::BIGINT AS b FROM lo1)"""
    local = {"skip": _skipped, "realised": _skipped, "poisson": _poissoned}.get(mode, lambda _: drawn)(seed)
    own_id = "edge_id" if local == drawn else "NULL::BIGINT AS edge_id"
    far = _realised(seed) if mode == "realised" else f'{end("ea", 5)}, {end("eb", 8)},\nfar AS (SELECT ea.edge_id, ea.v AS a, eb.v AS b FROM ea JOIN eb USING (edge_id))'
    return f"""{head},
tot AS (SELECT (SELECT coalesce(sum(w), 0) FROM pg) AS w1, (SELECT coalesce(sum(w), 0) FROM pd) AS w2),
gd AS {_cumulated("pg", "g", "first_node, blocks, block_size")},
dd AS {_cumulated("(SELECT *, greatest(n - n_fill, 0) AS n_bulk FROM pd)", "degree", "first_node, n_fill, n_bulk, r")},
{ids},
{local},
{far},
gen AS (SELECT {own_id}, 1 AS phase, a, b FROM loc UNION ALL SELECT edge_id, 2, a, b FROM far)"""


_UNIQUE = "SELECT DISTINCT least(a, b)::BIGINT AS lo, greatest(a, b)::BIGINT AS hi FROM gen WHERE a <> b"


def gen_rows(g: str, beta: float, seed: int, phase: int) -> str:
    return f"WITH RECURSIVE {generated(g, beta, seed)} SELECT edge_id::BIGINT AS edge_id, phase::TINYINT AS phase, a::BIGINT AS a, b::BIGINT AS b FROM gen WHERE phase = {phase}"


def gen_edges(g: str, beta: float, seed: int, mode: str = "independent") -> str:
    return f"WITH RECURSIVE {generated(g, beta, seed, mode)} {_UNIQUE}"


def gen_count(g: str, beta: float, seed: int) -> str:
    return f"WITH RECURSIVE {generated(g, beta, seed)} SELECT least(a, b)::BIGINT AS lo, greatest(a, b)::BIGINT AS hi, count(*)::BIGINT AS times FROM gen WHERE a <> b GROUP BY 1, 2"


def _of_edges(inner: str, tail: str) -> str:
    """Measures on generated edges: the graph CTEs with ``e`` replaced."""
    body = _clustered("turn_chain").split("nd AS", 1)[1]
    return f"WITH e AS ({inner}),\nnd AS{body} {tail}"


def clone_summary(g: str, beta: float, seed: int) -> str:
    return _of_edges(gen_edges(g, beta, seed), _SUMMARY.format(g=g, model="model"))


def clone_profile(g: str, beta: float, seed: int) -> str:
    return _of_edges(gen_edges(g, beta, seed), f"SELECT '{g}' AS graph, degree, n, round(c, 6) AS c FROM prof")


def repeat_ratio(g: str, beta: float, seed: int) -> str:
    one = "SELECT phase::INTEGER AS phase, count(*)::BIGINT AS generated, count(DISTINCT CASE WHEN a <> b THEN least(a, b)::VARCHAR || '-' || greatest(a, b)::VARCHAR END)::BIGINT AS u FROM gen GROUP BY phase"
    return f"WITH RECURSIVE {generated(g, beta, seed)}, x AS ({one} UNION ALL SELECT 0, count(*), count(DISTINCT CASE WHEN a <> b THEN least(a, b)::VARCHAR || '-' || greatest(a, b)::VARCHAR END) FROM gen) SELECT phase::INTEGER AS phase, generated::BIGINT AS generated, u::BIGINT AS \"unique\", round(generated::DOUBLE / nullif(u, 0), 6) AS ratio FROM x"


def blowup(g: str, beta: float, seed: int) -> str:
    return f"""WITH RECURSIVE {generated(g, beta, seed)}, ue AS ({_UNIQUE}), dg AS (SELECT v, count(*) AS degree FROM (SELECT lo AS v FROM ue UNION ALL SELECT hi FROM ue) GROUP BY v),
one AS (SELECT first_node, n_fill FROM pd WHERE degree = 1), hit AS (SELECT dg.degree FROM dg JOIN one ON v >= first_node AND v < first_node + n_fill)
SELECT n_fill::BIGINT AS pool, (n_fill - (SELECT count(*) FROM hit))::BIGINT AS unused, (SELECT count(*) FROM hit WHERE degree = 1)::BIGINT AS once, (SELECT count(*) FROM hit WHERE degree > 1)::BIGINT AS more FROM one"""


def draw_rows(g: str, seed: int, rows: int) -> str:
    return f"""WITH {_base(g)}, dist AS {_cumulated("(SELECT degree, n, degree * n::DOUBLE AS w FROM h)", "degree", "n")}
SELECT i::BIGINT AS edge_id, bin FROM (SELECT i, {_u(seed, 5, "i")} AS u FROM range({rows}) t(i)) JOIN dist ON u >= lo AND u < hi"""


def coin_rows(share: float, seed: int, rows: int) -> str:
    return f"SELECT i::BIGINT AS edge_id, {_u(seed, 0, 'i')} < {share} AS local FROM range({rows}) t(i)"


def chung_lu(g: str, beta: float, seed: int, tail: str = _UNIQUE) -> str:
    def end(name: str, s: int, t: int) -> str:
        return f"{name} AS (SELECT edge_id, first_node + {_below('mu', 'pool')} AS v FROM (SELECT i AS edge_id, {_u(seed, s, 'i')} AS u, {_u(seed, t, 'i')} AS mu FROM range((SELECT floor(sum(w) / 2 + 0.5)::BIGINT FROM cls)) r(i)) x JOIN dist ON u >= lo AND u < hi)"

    return f"""WITH {_base(g)}, cls AS (SELECT degree, pool, w, 1 + coalesce(sum(pool) OVER (ORDER BY CASE WHEN degree = 1 THEN 4611686018427387904 ELSE degree END ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS first_node
  FROM (SELECT degree, CASE WHEN degree = 1 THEN floor({beta} * n + 0.5) ELSE n END::BIGINT AS pool, degree::DOUBLE * n AS w FROM h)),
dist AS {_cumulated("cls", "degree", "first_node, pool")}, {end("ea", 5, 7)}, {end("eb", 8, 10)},
gen AS (SELECT ea.v AS a, eb.v AS b FROM ea JOIN eb USING (edge_id)) {tail}"""


def degree_dispersion(g: str, seeds: int) -> str:
    """Moments over seeds of the degrees that nodes of a class get, repeats kept."""
    of = "SELECT degree, pool, count(*) AS got FROM (SELECT a AS v FROM gen UNION ALL SELECT b FROM gen) JOIN cls ON v >= first_node AND v < first_node + pool GROUP BY degree, pool, v"
    runs = " UNION ALL ".join(f"({chung_lu(g, 1.0, seed, of)})" for seed in range(seeds))
    return f"SELECT degree, round(sum(got) / (pool * {seeds})::DOUBLE, 6) AS mean, round(sum(got * got) / (pool * {seeds})::DOUBLE - (sum(got) / (pool * {seeds})::DOUBLE) * (sum(got) / (pool * {seeds})::DOUBLE), 6) AS variance FROM ({runs}) GROUP BY degree, pool"


def chung_lu_expected(g: str) -> str:
    return f"WITH {_base(g)}, s AS (SELECT sum(degree * n)::DOUBLE AS stubs FROM h) SELECT a.degree AS degree_a, b.degree AS degree_b, round(CASE WHEN a.degree = b.degree THEN 1 ELSE 2 END * (a.degree * a.n * b.degree * b.n) / stubs / 2, 6) AS expected FROM h a JOIN h b ON a.degree <= b.degree, s"


def chung_lu_pairs(g: str, seed: int) -> str:
    from .functions.rng import duckdb_uniform

    return f"WITH {_base(g)}, s AS (SELECT sum(degree)::DOUBLE AS stubs FROM nd) SELECT x.v AS lo, y.v AS hi FROM nd x JOIN nd y ON x.v < y.v, s WHERE {duckdb_uniform(seed, 'x.v || chr(45) || y.v', 14)} < least(1, x.degree * y.degree / stubs)"


_DAYS = "z AS (SELECT count(DISTINCT o_orderdate::DATE)::BIGINT AS n FROM orders), v AS (SELECT unnest(range(0, n)) AS i FROM z)"


def erdos_renyi_pairs(rho: float, seed: int) -> str:
    """A node per day of orders."""
    return f"WITH {_DAYS} SELECT x.i + 1 AS lo, y.i + 1 AS hi FROM v x JOIN v y ON x.i < y.i WHERE {_u(seed, 14, '(y.i * (y.i - 1) // 2 + x.i)')} < {rho}"


def erdos_renyi_skip(rho: float, seed: int) -> str:
    """A node per day of orders."""
    span = math.ceil(64 / rho)
    gaps = f"SELECT n, total, t * {span} - 1 + sum({_gap(_u(seed, 13, chr(39).join(['t || ', '-', ' || s'])), f'{rho}::DOUBLE')}) OVER (PARTITION BY t ORDER BY s) AS code, (t + 1) * {span} AS upto FROM (SELECT n, total, unnest(range(0, (total + {span} - 1) // {span})) AS t FROM w), range(1, 161) y(s)"
    kept = f"(SELECT 1 AS first_node, n AS block_size, total AS pairs, code::BIGINT AS code FROM ({gaps}) WHERE code < upto AND code < total)"
    return f"WITH {_DAYS}, w AS (SELECT n, n * (n - 1) // 2 AS total FROM z) SELECT a::BIGINT AS lo, b::BIGINT AS hi FROM ({_unranked(kept)})"


def kronecker_profile(seed: int, initiator: tuple[float, ...]) -> str:
    """Unique edges of as many levels and draws as the profile ``prof`` has nodes (in powers of two) and edges."""
    p = [x / sum(initiator) for x in initiator]
    u = _u(seed, "(100 + level)", "i")
    return f"""(WITH z AS (SELECT greatest(1, floor(log2(sum(n) - 1) + 1e-9)::BIGINT + 1) AS levels, (sum(n * degree) // 2)::BIGINT AS m FROM prof),
d AS (SELECT i, level, levels, {u} AS u FROM z, LATERAL (SELECT unnest(range(0, m)) AS i), LATERAL (SELECT unnest(range(0, levels)) AS level)),
gen AS (SELECT i, sum((u >= {p[0] + p[1]!r}::DOUBLE)::BIGINT << (levels - 1 - level)) AS a, sum(((u >= {p[0]!r}::DOUBLE AND u < {p[0] + p[1]!r}::DOUBLE) OR u >= {p[0] + p[1] + p[2]!r}::DOUBLE)::BIGINT << (levels - 1 - level)) AS b FROM d GROUP BY i)
{_UNIQUE})"""


def kronecker(levels: int, edges: int, initiator: tuple[float, ...], seed: int, noise: float = 0.0) -> str:
    from .operators.baselines import quadrants

    a, b = [], []
    for level in range(levels):
        p = quadrants(initiator, noise, seed, level)
        cuts = (repr(p[0]), repr(p[0] + p[1]), repr(p[0] + p[1] + p[2]))
        u = _u(seed, 100 + level, "i")
        a.append(f"({u} >= {cuts[1]}::DOUBLE)::BIGINT * {1 << (levels - 1 - level)}")
        b.append(f"(({u} >= {cuts[0]}::DOUBLE AND {u} < {cuts[1]}::DOUBLE) OR {u} >= {cuts[2]}::DOUBLE)::BIGINT * {1 << (levels - 1 - level)}")
    return f"WITH gen AS (SELECT {' + '.join(a)} AS a, {' + '.join(b)} AS b FROM range({edges}) t(i)) {_UNIQUE}"


# --- idealized profiles -----------------------------------------------------------------------------------------------


def _law(kind: str, p: tuple[float, ...], d: str = "degree") -> str:
    return f"pow({d}::DOUBLE, -{p[0]}::DOUBLE)" if kind == "dpl" else f"exp(-pow(ln({d}::DOUBLE) / {p[0]}::DOUBLE, {p[1]}::DOUBLE))"


def ideal(kind: str, p: tuple[float, ...], dmax: int) -> str:
    return f"WITH r AS (SELECT degree::BIGINT AS degree, {_law(kind, p)} AS f FROM range(1, {dmax + 1}) t(degree)) SELECT degree, round(f / (SELECT sum(f) FROM r), 9) AS p FROM r"


def ideal_moments(kind: str, p: tuple[float, ...], dmax: int) -> str:
    return f"WITH r AS (SELECT degree, {_law(kind, p)} AS f FROM range(1, {dmax + 1}) t(degree)) SELECT round(sum(degree * f) / sum(f), 6) AS davg, round(ln(max_by(f, degree) / sum(f)), 6) AS log_p_top FROM r"


def fit_grid(kind: str, names: list[str], rows: list[tuple[float, ...]], g: str, dmax: int) -> str:
    values = ", ".join("(" + ", ".join(f"{x}::DOUBLE" for x in r) + ")" for r in rows)
    law = "pow(d::DOUBLE, -gamma)" if kind == "dpl" else "exp(-pow(ln(d::DOUBLE) / alpha, delta))"
    return f"WITH {_base(g)}, c({', '.join(names)}) AS (VALUES {values}), x AS (SELECT {', '.join(names)}, sum({law} * d) / sum({law}) AS m FROM c, range(1, {dmax + 1}) t(d) GROUP BY ALL) SELECT {', '.join(names)}, round(m, 6) AS davg, round(abs(ln(m / (SELECT sum(degree * n)::DOUBLE / sum(n) FROM h))), 6) AS loss FROM x"


def ideal_clustering(g: str, c_max: float, xi: float) -> str:
    return f"WITH {_base(g)} SELECT degree, n, round(CASE WHEN degree >= 2 THEN {c_max}::DOUBLE * exp(-(degree - 1) * {xi}::DOUBLE) ELSE 0 END, 6) AS c FROM h"


def ideal_gcc(g: str, c_max: float, xi: float) -> str:
    return f"WITH {_base(g)}, p AS (SELECT n * (degree * (degree - 1) // 2) AS w, CASE WHEN degree >= 2 THEN {c_max}::DOUBLE * exp(-(degree - 1) * {xi}::DOUBLE) ELSE 0 END AS c FROM h) SELECT 'ideal' AS graph, round(sum(c * w) / sum(w), 6) AS gcc FROM p"


def ideal_noisy(g: str, c_max: float, xi: float, seed: int) -> str:
    mean = f"{c_max}::DOUBLE * exp(-(degree - 1) * {xi}::DOUBLE)"
    normal = f"sqrt(-2 * ln(1 - {_u(seed, 11, 'degree')})) * cos({2 * 3.141592653589793!r}::DOUBLE * {_u(seed, 12, 'degree')})"
    return f"WITH {_base(g)} SELECT degree, n, round(CASE WHEN degree >= 2 THEN least(1, greatest(0, {mean} + least(0.01, {mean} / 2) * {normal})) ELSE 0 END, 6) AS c FROM h"


def dgln_study(g: str, dmax: int) -> str:
    return f"WITH {_base(g)}, c(alpha, delta) AS (VALUES (1.5::DOUBLE, 2::DOUBLE), (2, 1.5), (2, 2), (2, 2.5), (2.5, 2)), r AS (SELECT alpha, delta, d, exp(-pow(ln(d::DOUBLE) / alpha, delta)) AS f FROM c, range(1, {dmax + 1}) t(d)), s AS (SELECT alpha, delta, sum(f) AS total FROM r GROUP BY ALL) SELECT alpha, delta, d::BIGINT AS degree, round(f / total * (SELECT sum(n) FROM h), 6) AS n FROM r JOIN s USING (alpha, delta) WHERE (d & (d - 1)) = 0"


def coupon_fixed(trials: str, seed: int) -> str:
    return f"WITH t AS (SELECT i AS trial, {_below(_u(seed, 3, '(i * 1000 + s)'), '45')} AS code FROM {trials} r(i), range(1, 32) q(s)), u AS (SELECT trial, count(DISTINCT code) AS k FROM t GROUP BY trial) SELECT k::BIGINT AS \"unique\", count(*)::BIGINT AS trials FROM u GROUP BY k"


def compared(g: str, beta: float, seed: int) -> str:
    """Distance of the clone's degree distribution from the original's."""
    clone = gen_edges(g, beta, seed)
    return f"""WITH {_base(g)}, ce AS ({clone}), ch AS (SELECT degree, count(*) AS n FROM (SELECT v, count(*) AS degree FROM (SELECT lo AS v FROM ce UNION ALL SELECT hi FROM ce) GROUP BY v) GROUP BY degree),
s AS (SELECT degree, sum(x) AS x, sum(y) AS y FROM (SELECT degree, n AS x, 0 AS y FROM h UNION ALL SELECT degree, 0, n FROM ch) GROUP BY degree)
SELECT round(max(gap), 6) AS ks FROM (SELECT abs(sum(x) OVER (ORDER BY degree)::DOUBLE / sum(x) OVER () - sum(y) OVER (ORDER BY degree)::DOUBLE / sum(y) OVER ()) AS gap FROM s)"""


# --- sampled wedges, comparisons, reports ------------------------------------------------------------------------


def _sampled(g: str, k: int, seed: int, exact_below: int = 0) -> str:
    """CTEs up to sp (degree, n, c): k wedges a degree drawn by rank of the centre and of two of its neighbours."""
    id_ = "(degree * 1048576 + k)"
    return f"""{_clustered(g)},
sd AS (SELECT degree, n, {_below(_u(seed, 15, id_), "n")} AS rank, {_below(_u(seed, 16, id_), "degree")} AS i, {_below(_u(seed, 17, id_), "degree - 1")} AS j0 FROM h, range({k}) t(k) WHERE degree >= 2 AND n * (degree * (degree - 1) // 2) > {exact_below}),
sr AS (SELECT v, degree, row_number() OVER (PARTITION BY degree ORDER BY v) - 1 AS rank FROM nd),
sn AS (SELECT v, w, row_number() OVER (PARTITION BY v ORDER BY w) - 1 AS at FROM (SELECT lo AS v, hi AS w FROM e UNION ALL SELECT hi, lo FROM e)),
sw AS (SELECT sd.degree, n, x.w AS a, y.w AS b FROM sd JOIN sr ON sr.degree = sd.degree AND sr.rank = sd.rank JOIN sn x ON x.v = sr.v AND x.at = i JOIN sn y ON y.v = sr.v AND y.at = j0 + (j0 >= i)::BIGINT),
sp AS (SELECT degree, n, count(lo)::DOUBLE / count(*) AS c FROM sw LEFT JOIN e ON lo = least(a, b) AND hi = greatest(a, b) GROUP BY degree, n
  UNION ALL SELECT degree, n, c FROM prof WHERE degree < 2 OR n * (degree * (degree - 1) // 2) <= {exact_below})"""


def sampled_clustering(g: str, k: int, seed: int, exact_below: int = 0) -> str:
    return f"WITH {_sampled(g, k, seed, exact_below)} SELECT degree, n, round(c, 6) AS c FROM sp"


def sampled_gcc(g: str, k: int, seed: int) -> str:
    return f"WITH {_sampled(g, k, seed)} SELECT 'sampled' AS graph, round(coalesce(sum(c * n * (degree * (degree - 1) // 2)) / nullif(sum(n * (degree * (degree - 1) // 2)), 0), 0), 6) AS gcc FROM sp"


def sampling_error(g: str, k: int, seed: int) -> str:
    return f"WITH {_sampled(g, k, seed)} SELECT degree, round(prof.c, 6) AS exact, round(sp.c, 6) AS sampled, round(abs(prof.c - sp.c), 6) AS gap FROM prof JOIN sp USING (degree)"


def profile_series(g: str, beta: float, seed: int) -> str:
    return f"WITH {_clustered(g)}, y AS ({_of_edges(gen_edges(g, beta, seed), 'SELECT degree, n, c FROM prof')}) SELECT degree, coalesce(prof.n, 0)::BIGINT AS n_a, coalesce(y.n, 0)::BIGINT AS n_b, round(coalesce(prof.c, 0), 6) AS c_a, round(coalesce(y.c, 0), 6) AS c_b FROM prof FULL JOIN y USING (degree)"


def pivoted(g: str, beta: float, seed: int) -> str:
    return f"SELECT a.graph, a.nodes AS original_nodes, a.edges AS original_edges, b.nodes AS model_nodes, b.edges AS model_edges FROM ({summary(g)}) a JOIN ({clone_summary(g, beta, seed)}) b ON a.graph = b.graph"


def flagship(g: str, beta: float, seed: int) -> str:
    return f"SELECT * FROM ({summary(g)}) UNION ALL SELECT * FROM ({clone_summary(g, beta, seed)})"


def phase_rollup(g: str, beta: float, seed: int) -> str:
    return f"""WITH RECURSIVE {generated(g, beta, seed)},
bl AS (SELECT g, k, first_node + k * block_size AS f0, first_node + (k + 1) * block_size AS f1 FROM (SELECT *, unnest(range(0, blocks)) AS k FROM pg)),
x AS (SELECT phase, coalesce(p.f0 = q.f0, false) AS same_block FROM gen LEFT JOIN bl p ON a >= p.f0 AND a < p.f1 LEFT JOIN bl q ON b >= q.f0 AND b < q.f1)
SELECT phase::INTEGER AS phase, same_block, count(*)::BIGINT AS edges, grouping(phase, same_block)::BIGINT AS level FROM x GROUP BY ROLLUP (phase, same_block)"""


def triangle_provenance(g: str, beta: float, seed: int) -> str:
    return f"""WITH RECURSIVE {generated(g, beta, seed)}, te AS (SELECT least(a, b) AS lo, greatest(a, b) AS hi, (min(phase) = 1)::INTEGER AS p FROM gen WHERE a <> b GROUP BY 1, 2)
SELECT (x.p + y.p + z.p)::INTEGER AS local_edges, count(*)::BIGINT AS triangles FROM te x JOIN te y ON x.hi = y.lo JOIN te z ON z.lo = x.lo AND z.hi = y.hi GROUP BY 1"""


def compare_models(g: str, betas: tuple[float, ...], beta: float, initiator: tuple[float, ...], seed: int) -> str:
    """Distances of the original's and every model's profile from the original's."""
    parts = [f"SELECT 'model_{b:g}' AS model, * FROM ({_of_edges(gen_edges(g, b, seed), 'SELECT degree, n, c FROM prof')})" for b in betas]
    parts.append(f"SELECT 'chung_lu' AS model, * FROM ({_of_edges(chung_lu(g, beta, seed), 'SELECT degree, n, c FROM prof')})")
    inner = f"WITH {_clustered(g)} SELECT * FROM {kronecker_profile(seed, initiator)}"
    parts.append(f"SELECT 'kronecker' AS model, * FROM ({_of_edges(inner, 'SELECT degree, n, c FROM prof')})")
    w = "(degree * (degree - 1) // 2)"
    return f"""WITH {_clustered(g)}, {_BINS},
own AS MATERIALIZED (SELECT degree, n, c FROM prof),
md AS MATERIALIZED (SELECT 'original' AS model, * FROM own UNION ALL {" UNION ALL ".join(parts)}),
by0 AS (SELECT model, degree, sum(x) AS x, sum(y) AS y, sum(cx) AS cx, sum(cy) AS cy FROM (SELECT model, own.degree, own.n AS x, 0 AS y, own.c AS cx, 0 AS cy FROM own, (SELECT DISTINCT model FROM md) UNION ALL SELECT model, degree, 0, n, 0, c FROM md) GROUP BY model, degree),
by1 AS (SELECT *, abs(sum(x) OVER r::DOUBLE / sum(x) OVER e - sum(y) OVER r::DOUBLE / sum(y) OVER e) AS far FROM by0 WINDOW r AS (PARTITION BY model ORDER BY degree), e AS (PARTITION BY model)),
m AS (SELECT model, max(far) AS ks, sum(abs(cx - cy) * x) FILTER (degree >= 2 AND x > 0) / sum(x) FILTER (degree >= 2) AS gap_n, sum(abs(cx - cy) * x * {w}) FILTER (degree >= 2 AND x > 0) / sum(x * {w}) FILTER (degree >= 2) AS gap_wedge,
  sum(cx * x * {w}) / sum(x * {w}) AS gx, sum(cy * y * {w}) / sum(y * {w}) AS gy FROM by1 GROUP BY model),
b AS (SELECT model, avg(abs(x - y)::DOUBLE / greatest(x, y)) AS gap_binned FROM (SELECT model, k, sum(x) AS x, sum(y) AS y FROM by0 JOIN bn ON degree BETWEEN lo AND hi GROUP BY model, k) GROUP BY model)
SELECT model, round(ks, 6) AS ks, round(gap_n, 6) AS gap_n, round(gap_wedge, 6) AS gap_wedge, round(gap_binned, 6) AS gap_binned, round(coalesce(abs(gx - gy) / gx, 0), 6) AS gcc_rel FROM m JOIN b USING (model)"""


def coupon_poisson(trials: str, seed: int, cdf: list[float]) -> str:
    return f"WITH t AS (SELECT i AS trial, len(list_filter([{', '.join(f'{x!r}::DOUBLE' for x in cdf)}], lambda x: x <= {_u(seed, 14, 'i')})) AS number FROM {trials} r(i)), d AS (SELECT trial, {_below(_u(seed, 3, '(trial * 1000 + s)'), '45')} AS code FROM (SELECT trial, unnest(range(1, number + 1)) AS s FROM t)), u AS (SELECT trial, count(DISTINCT code) AS k FROM t LEFT JOIN d USING (trial) GROUP BY trial) SELECT k::BIGINT AS \"unique\", count(*)::BIGINT AS trials FROM u GROUP BY k"


def _realised_counts(kind: str, p: tuple[float, ...], dmax: int) -> str:
    return f"r AS (SELECT degree::BIGINT AS degree, {_law(kind, p)} AS f FROM range(1, {dmax + 1}) t(degree)), p AS (SELECT degree, f / (SELECT sum(f) FROM r) AS p FROM r)"


def realised_rounded(kind: str, p: tuple[float, ...], dmax: int, nodes: int) -> str:
    return f"""WITH {_realised_counts(kind, p, dmax)}, x AS (SELECT degree, p * {nodes} AS x, floor(p * {nodes})::BIGINT AS base FROM p), o AS (SELECT *, row_number() OVER (ORDER BY round(x - base, 9) DESC, degree) AS place FROM x)
SELECT degree, n::BIGINT AS n FROM (SELECT degree, base + (place <= {nodes} - (SELECT sum(base) FROM x))::BIGINT AS n FROM o) WHERE n > 0"""


def realised_multinomial(kind: str, p: tuple[float, ...], dmax: int, nodes: int, seed: int) -> str:
    dist = _cumulated("(SELECT degree, 0 AS zero, p * 1000000000000::DOUBLE AS w FROM p)", "degree", "zero")
    return f"WITH {_realised_counts(kind, p, dmax)}, dist AS {dist} SELECT bin AS degree, count(*)::BIGINT AS n FROM (SELECT {_u(seed, 14, 'i')} AS u FROM range({nodes}) t(i)) JOIN dist ON u >= lo AND u < hi GROUP BY bin"


def ideal_check(kind: str, p: tuple[float, ...], dmax: int, g: str) -> str:
    return f"WITH {_base(g)}, o AS (SELECT sum(n) AS nodes, sum(degree * n)::DOUBLE / sum(n) AS own FROM h), {_realised_counts(kind, p, dmax)}, m AS (SELECT sum(degree * p) AS davg, max_by(p, degree) AS p_top FROM p) SELECT round(davg, 4) AS davg, round(p_top, 4) AS p_top, abs(davg - own) <= 0.01::DOUBLE * own AS mean_fits, p_top * nodes < 1 AS tail_fits FROM m, o"


def clustering_gap(g: str, beta: float, seed: int) -> str:
    w = "(degree * (degree - 1) // 2)"
    return f"WITH {_clustered(g)}, y AS ({_of_edges(gen_edges(g, beta, seed), 'SELECT degree, c FROM prof')}), s AS (SELECT degree, n, abs(prof.c - coalesce(y.c, 0)) AS gap FROM prof LEFT JOIN y USING (degree) WHERE degree >= 2) SELECT round(sum(gap * n) / sum(n), 6) AS gap_n, round(sum(gap * n * {w}) / sum(n * {w}), 6) AS gap_wedge FROM s"


def xi_grid(g: str, c_max: float, gcc: float, xis: list[float]) -> str:
    values = ", ".join(f"({x}::DOUBLE)" for x in xis)
    w = "(n * (degree * (degree - 1) // 2))"
    return f"WITH {_base(g)}, x(xi) AS (VALUES {values}), s AS (SELECT xi, {c_max}::DOUBLE * sum({w} * exp(-(degree - 1) * xi)) / sum({w}) AS gcc FROM h, x WHERE degree >= 2 GROUP BY xi) SELECT xi, round(gcc, 6) AS gcc, round(abs(gcc - {gcc}), 6) AS loss FROM s"


SESSIONS = """WITH e AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) <= INTERVAL 10 MINUTE THEN 0 ELSE 1 END AS fresh FROM events),
s AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS k FROM e)
SELECT min(ts) AS start, max(ts) + INTERVAL 10 MINUTE AS "end", user_id, count(*)::BIGINT AS events FROM s GROUP BY user_id, k"""
