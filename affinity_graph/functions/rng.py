"""Counter-based uniforms: a pure function of (seed, id, stream), so that results do not depend on partitioning.

``fast`` hashes with xxhash64 and stays in generated code; ``portable`` takes 52 bits of an md5 and can be said in any SQL
engine, which is how generated edges are compared with an oracle.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Streams, one for each independent draw of an edge.
PHASE, GROUP, BLOCK, FIRST, SECOND = range(5)
DEGREE_A, FILL_A, MEMBER_A, DEGREE_B, FILL_B, MEMBER_B = range(5, 11)
NOISE_1, NOISE_2, SKIP, TRIAL, CENTER, NEIGHBOUR_1, NEIGHBOUR_2 = range(11, 18)
LEVEL = 100


def uniform(seed: int, id_: Column | str, stream: int | Column, kind: str = "fast") -> Column:
    """A double in [0, 1)."""
    id_ = F.col(id_) if isinstance(id_, str) else id_
    stream = F.lit(stream) if isinstance(stream, int) else stream
    if kind == "fast":
        return F.shiftrightunsigned(F.xxhash64(F.lit(seed), id_, stream), 11).cast("double") * F.lit(2.0**-53)
    if kind == "portable":
        digits = F.substring(F.md5(F.concat_ws("|", F.lit(str(seed)), id_.cast("string"), stream.cast("string")).cast("binary")), 1, 13)
        return F.conv(digits, 16, 10).cast("double") / F.lit(2.0**52)
    raise ValueError(f"unknown kind of uniform: {kind}")


def below(u: Column, n: Column) -> Column:
    """floor(u * n) as bigint, never n itself."""
    return F.least(F.floor(u * n.cast("double")).cast("bigint"), n.cast("bigint") - 1)


def duckdb_uniform(seed: int, id_: str, stream: int | str) -> str:
    """The portable uniform in DuckDB's SQL."""
    return f"(CAST('0x' || substr(md5('{seed}|' || {id_} || '|' || {stream}), 1, 13) AS BIGINT)::DOUBLE / 4503599627370496.0::DOUBLE)"
