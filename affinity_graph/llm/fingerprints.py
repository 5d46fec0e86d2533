"""Document fingerprints by content-defined chunking.

A gear hash (each byte's random value, shifted left once a byte, so that it sees the last 32 bytes) runs over a text's UTF-8
bytes. Chunk boundaries are normalised: up to ``NORMAL`` bytes a harder mask must be zero, beyond it an easier one, with
``SMALLEST`` and ``LARGEST`` as bounds. Boundaries hang on content alone, so an insertion shifts them and changes only the
chunks it touches. The fingerprint is the sorted set of (chunk digest, chunk length); the likeness of one text to another is
the share of its fingerprint's length whose chunks are in the other's too: containment.

The next document is found without a global sort in one task: ids are cut into ranges by quantiles, every document goes to its
range, and the first document of each range goes to the range before it as well (one copy per range).

Nulls and edges: a null text is empty; an empty text has an empty fingerprint, likeness 1 to an empty one and 0 to others; of
equal or null doc_ids, nulls come last and ties go by the hash of the text; a table of one row is its own next; an empty
table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import bisect
import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import load, shuffle_width, span_hashes, text_pieces

SMALLEST, NORMAL, LARGEST = 8, 32, 128
HARD, EASY = np.uint64(0x3F << 25), np.uint64(0x07 << 25)
_GEAR = np.random.Generator(np.random.PCG64(77)).integers(0, 2**63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)


def gear(raw: np.ndarray) -> np.ndarray:
    """The gear hash after each byte, over at most the last 32 bytes, in five doubling steps."""
    h = _GEAR[raw]
    for step in (1, 2, 4, 8, 16):
        if len(h) > step:
            h[step:] += h[:-step] << np.uint64(step)
    return h


def cuts(raw: np.ndarray) -> list[int]:
    """Ends of the chunks of one text."""
    n = len(raw)
    h = gear(raw)
    easy = np.flatnonzero((h & EASY) == 0) + 1
    hard = easy[(h[easy - 1] & HARD) == 0].tolist()
    easy = easy.tolist()
    out, at = [], 0
    while n - at > SMALLEST:
        k = bisect.bisect_left(hard, at + SMALLEST)
        end = hard[k] if k < len(hard) and hard[k] <= at + NORMAL else 0
        if not end:
            k = bisect.bisect_left(easy, at + NORMAL)
            end = easy[k] if k < len(easy) and easy[k] <= at + LARGEST else min(n, at + LARGEST)
        out.append(end)
        at = end
    if at < n:
        out.append(n)
    return out


def chunk_set(text: bytes) -> dict[int, int]:
    """Digest -> length of the distinct chunks of a text."""
    if not text:
        return {}
    raw = np.frombuffer(text, np.uint8)
    ends = np.array(cuts(raw), np.int64)
    starts = np.concatenate([[0], ends[:-1]])
    # 40 bits: only the sets of two documents are compared at a time
    return dict(zip((span_hashes(raw, starts, ends) >> np.uint64(24)).tolist(), (ends - starts).tolist(), strict=True))


def written(chunks: dict[int, int]) -> str:
    """The fingerprint as text: twelve hex digits a chunk, ten of digest and two of length, in order."""
    return np.sort(np.fromiter((d << 8 | n for d, n in chunks.items()), np.uint64, len(chunks))).astype(">u8").view(np.uint8).reshape(-1, 8)[:, 2:].tobytes().hex()


def likeness(one: dict[int, int], other: dict[int, int]) -> float:
    if not one or not other:
        return float(one.keys() == other.keys())
    return sum(one[d] for d in one.keys() & other.keys()) / sum(one.values())


def fingerprints(docs: DataFrame) -> DataFrame:
    """(doc_id, n_chars, fingerprint) of every text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for piece in text_pieces(batches):
            texts = [t or "" for t in piece.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([piece.column("doc_id"), pa.array([len(t) for t in texts], pa.int64()), pa.array([written(chunk_set(t.encode())) for t in texts])], ["doc_id", "n_chars", "fingerprint"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, n_chars long, fingerprint string")


def with_next(docs: DataFrame) -> DataFrame:
    """Documents dealt to ranges of descending doc_id (``slot``), each range followed by the next one's first document (``halo``)."""
    spark = docs.sparkSession
    width = shuffle_width(spark)
    docs = docs.select("doc_id", "text")
    # Three counters a range come to the driver, and nothing of any text.
    edges = docs.stat.approxQuantile("doc_id", [k / width for k in range(1, width)], max(0.2 / width, 1e-5)) if width > 1 else []
    bounds = sorted({int(x) for x in edges}, reverse=True)
    ascending = np.array(bounds[::-1], np.int64)
    lowest = -(1 << 63)

    def slots(ids: np.ndarray) -> np.ndarray:
        """0 for the highest ids; a bound belongs to the lower range."""
        return (len(ascending) - np.searchsorted(ascending, ids, side="left")).astype(np.int32)

    def places(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        top: dict[int, int] = {}
        for b in batches:
            ids = b.column("doc_id").fill_null(lowest).to_numpy(zero_copy_only=False)
            s = slots(ids)
            for k in np.unique(s).tolist():
                top[k] = max(top.get(k, lowest), int(ids[s == k].max()))
        yield pa.RecordBatch.from_arrays([pa.array(list(top), pa.int32()), pa.array(list(top.values()), pa.int64())], ["slot", "top"])

    tops = sorted((r["slot"], r["top"]) for r in docs.select("doc_id").mapInArrow(places, "slot int, top long").groupBy("slot").agg(F.max("top").alias("top")).collect())
    before = {top: tops[k - 1][0] for k, (_, top) in enumerate(tops)}  # the first range's goes behind the last

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ids = b.column("doc_id").fill_null(lowest).to_numpy(zero_copy_only=False)
            s = slots(ids)
            yield pa.RecordBatch.from_arrays([pa.array(s), pa.array(np.zeros(len(s), np.int32)), *b.columns], ["slot", "halo", "doc_id", "text"])
            first = [i for i, x in enumerate(ids.tolist()) if x in before]
            if first:
                part = b.take(pa.array(first))
                yield pa.RecordBatch.from_arrays([pa.array([before[int(ids[i])] for i in first], pa.int32()), pa.array(np.ones(len(first), np.int32)), *part.columns], ["slot", "halo", "doc_id", "text"])

    dealt = docs.mapInArrow(deal, "slot int, halo int, doc_id long, text string").repartitionById(max(1, len(bounds) + 1), F.col("slot"))
    return dealt.sortWithinPartitions("halo", F.col("doc_id").desc_nulls_last(), F.xxhash64("text"))


def compared(docs: DataFrame) -> DataFrame:
    """Fingerprints of every text and of its edited text, and their likenesses."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows: list[tuple] = []

        def done(doc_id: int | None, text: str, own: dict[int, int], following: str, after: dict[int, int]) -> tuple:
            n = len(text)
            edited = (text[: n - n // 2] + following[: n // 2]).encode()
            other = chunk_set(edited)
            return doc_id, n, hashlib.sha256(edited).hexdigest(), written(own), written(other), likeness(own, other), likeness(own, after)

        def flush() -> pa.RecordBatch:
            kinds = [pa.int64(), pa.int64(), pa.string(), pa.string(), pa.string(), pa.float64(), pa.float64()]
            out = pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], COLUMNS)
            rows.clear()
            return out

        held: tuple | None = None
        ended = False
        for piece in text_pieces(batches, limit=2 << 20):
            for halo, doc_id, text in zip(*(piece.column(c).to_pylist() for c in ("halo", "doc_id", "text")), strict=True):
                if ended:  # only the first halo row follows the range
                    break
                text = text or ""
                own = chunk_set(text.encode())
                if held is not None:
                    rows.append(done(*held, text, own))
                held, ended = (doc_id, text, own), bool(halo)
            if rows:
                yield flush()

    return with_next(docs).mapInArrow(run, "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double")


COLUMNS = ["doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next"]


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return compared(load(spark, sf_dir, "documents"))


def brute_force(rows: list[tuple[int, str | None]]) -> list[tuple[int, int, str]]:
    """(doc_id, n_chars, edited_sha256) from a sort of all rows in one place."""
    rows = sorted(((d, t or "") for d, t in rows), reverse=True)
    return [(d, len(t), hashlib.sha256((t[: len(t) - len(t) // 2] + rows[(k + 1) % len(rows)][1][: len(t) // 2]).encode()).hexdigest()) for k, (d, t) in enumerate(rows)]
