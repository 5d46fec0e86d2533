"""Helpers shared by the training-data operators."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Word separators of every operator here: space and U+0009..U+000D (fixed values).
SPACES = " \t\n\x0b\x0c\r"


def load(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share: spark.checkpoint.dir. Where that is unset one of our own serves a local master only."""
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        base = tempfile.mkdtemp(prefix="affinity-shared-")
        spark.sparkContext.setCheckpointDir(base)
    return base.rstrip("/")


def new_path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


def stored(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` to the shared folder and read it back: cuts the lineage and survives lost executors."""
    spark = df.sparkSession
    path = new_path(spark, name)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def quoted(name: str) -> str:
    return "`" + name.replace("`", "``") + "`"


def packed(docs: DataFrame) -> DataFrame:
    """All columns of ``docs`` as the one column ``row``, so that none can clash with an operator's own."""
    return docs.select(F.struct(*[F.col(quoted(c)) for c in docs.columns]).alias("row"))


def unpacked(df: DataFrame, columns: list[str], **changed: Column) -> DataFrame:
    """The columns that ``packed`` put into ``row``, those in ``changed`` as given there."""
    return df.select(*[changed.get(c, F.col(f"row.{quoted(c)}")).alias(c) for c in columns])


def shuffle_width(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def public_path(name: str) -> str:
    """Path of a public vocabulary file; only the default of a parameter."""
    import public_tokenizers

    return public_tokenizers.path(name)


def text_pieces(batches: Iterator[pa.RecordBatch], column: str = "text", limit: int = 8 << 20) -> Iterator[pa.RecordBatch]:
    """Cut record batches so that each has about ``limit`` bytes of text; a longer single row stays whole."""
    for batch in batches:
        if not batch.num_rows:
            continue
        sizes = pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False)
        group = np.cumsum(sizes) // limit
        cuts = np.flatnonzero(np.diff(group)) + 1
        for lo, hi in zip([0, *cuts.tolist()], [*cuts.tolist(), batch.num_rows], strict=True):
            yield batch.slice(lo, hi - lo)
    release()


# --- vectorised word hashing -------------------------------------------------------------------------------------

_GEN = np.random.Generator(np.random.PCG64(20240607))
_BYTE = _GEN.integers(1, 2**63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_BYTE_LOWER = _BYTE.copy()
_BYTE_LOWER[65:91] = _BYTE[97:123]
_SEP = np.zeros(256, bool)
_SEP[[0x20, 9, 10, 11, 12, 13]] = True
_BASE = 0x9E3779B97F4A7C13
_INVERSE = pow(_BASE, -1, 1 << 64)
_BLOCK = 1 << 20


def _powers(base: int, n: int) -> np.ndarray:
    p = np.full(n, base, np.uint64)
    p[0] = 1
    return np.multiply.accumulate(p)


_tables: list[np.ndarray] = []


def _power_tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of the base and of its inverse; only those of ordinary blocks are kept."""
    if n > _BLOCK + 4096:
        return _powers(_BASE, n), _powers(_INVERSE, n)
    if not _tables:
        _tables.extend((_powers(_BASE, _BLOCK + 4096), _powers(_INVERSE, _BLOCK + 4096)))
    return _tables[0], _tables[1]


def release() -> None:
    """Give freed memory back to the system: Python workers outlive their tasks."""
    import ctypes

    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):
        return  # another C library


def mix64(h: np.ndarray) -> np.ndarray:
    """A bijective 64-bit finaliser."""
    h = h ^ (h >> np.uint64(33))
    h *= np.uint64(0xFF51AFD7ED558CCD)
    h ^= h >> np.uint64(33)
    h *= np.uint64(0xC4CEB9FE1A85EC53)
    h ^= h >> np.uint64(33)
    return h


def text_buffer(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes of a string column laid end to end, and each row's start (nulls are empty)."""
    column = pc.fill_null(column, "").cast(pa.large_string())
    if column.offset:
        column = pa.concat_arrays([column])
    n = len(column)
    offsets = np.frombuffer(column.buffers()[1], np.int64, n + 1, offset=column.offset * 8)
    data = column.buffers()[2]
    raw = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return raw[offsets[0] : offsets[-1]], offsets - offsets[0]


def word_spans(raw: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Byte start and end of every word, and the number of words before each row."""
    n = len(raw)
    if not n:
        z = np.zeros(0, np.int64)
        return z, z, np.zeros(len(offsets), np.int64)
    sep = _SEP[raw]
    first = np.zeros(n + 1, bool)
    first[offsets] = True
    first = first[:n]
    begin = ~sep
    begin[1:] &= sep[:-1] | first[1:]
    starts = np.flatnonzero(begin)
    end = ~sep
    end[:-1] &= sep[1:] | first[1:]
    ends = np.flatnonzero(end) + 1
    return starts, ends, np.searchsorted(starts, offsets)


def span_hashes(raw: np.ndarray, starts: np.ndarray, ends: np.ndarray, lower: bool = False) -> np.ndarray:
    """64-bit hashes of disjoint ascending byte spans: differences of a running polynomial over random byte values.

    The polynomial runs over a block of spans at a time, which bounds the arrays; a span's hash does not depend on its block.
    """
    out, lo = np.empty(len(starts), np.uint64), 0
    while lo < len(starts):
        base = int(starts[lo])
        hi = max(lo + 1, int(np.searchsorted(starts, base + _BLOCK)))
        s, e = starts[lo:hi] - base, ends[lo:hi] - base
        part = raw[base : int(ends[hi - 1])]
        power, inverse = _power_tables(len(part) + 1)
        values = (_BYTE_LOWER if lower else _BYTE)[part]
        values *= power[: len(part)]
        run = np.empty(len(part) + 1, np.uint64)
        run[0] = 0
        np.cumsum(values, out=run[1:])
        out[lo:hi] = mix64((run[e] - run[s]) * inverse[s] + (e - s).astype(np.uint64))
        lo = hi
    return out


_LANES = _GEN.integers(1, 2**63, 64, dtype=np.uint64) * np.uint64(2) + np.uint64(1)


def window_hashes(words: np.ndarray, width: int) -> np.ndarray:
    """Hash of each run of ``width`` consecutive word hashes (rows are not kept apart here)."""
    n = len(words) - width + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    out = words[:n] * _LANES[0]
    for j in range(1, width):
        out += words[j : j + n] * _LANES[j]
    return mix64(out)


def pack_ints(values: np.ndarray) -> bytes:
    """Small binary form of an ascending int64 array: zstd over its differences, one byte plane after another."""
    import zstandard

    v = np.asarray(values, np.int64)
    d = np.diff(v, prepend=np.int64(0))
    return zstandard.ZstdCompressor(level=1).compress(np.ascontiguousarray(d.view(np.uint8).reshape(-1, 8).T).tobytes())


def unpack_ints(blob: bytes) -> np.ndarray:
    import zstandard

    raw = np.frombuffer(zstandard.ZstdDecompressor().decompress(blob), np.uint8)
    return np.cumsum(np.ascontiguousarray(raw.reshape(8, -1).T).reshape(-1).view(np.int64))
