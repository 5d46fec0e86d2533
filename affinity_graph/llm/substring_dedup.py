"""Repeated passages by prefix-partitioned suffix trees over words.

A suffix is a word position followed by at least ``width`` words of its document. Suffixes are split by variable-length
prefixes into groups that fit in memory: counts of prefixes of 1, 2, 4 and ``width`` words (hashed to bins by the shuffle's width) over
the whole corpus give the plan; a prefix too frequent for a group is taken apart by its longer ones. Each group's suffixes
are sorted by the digest of their first ``width`` words, which lays the leaves under one inner node at depth ``width`` side by
side. Such a node with leaves in two documents is a repeat; its leaves in other documents than the smallest are starts of
repeated windows, and neighbouring windows of a document join into maximal repeats, whose words are removed.

Before the shuffle each task sorts its own suffixes: below a node only those of its smallest document go on, the others are
known to be repeats already. A passage that a third of all documents share thus sends one entry a task. A suffix costs about
nine bytes of shuffle (64-bit digest and a packed place); texts follow compressed, dealt by document together with
their repeats. The digest and the prefix group (a separate hash) must both agree, so that false repeats stay below one
in 10^10 words at 10^13 words. No group, bucket or document is cut short.

Nulls and edges: a null text has no words; a document of fewer than ``width`` words has no suffix; a null doc_id is neither
smaller nor larger than any other and keeps its words; rows that repeat a doc_id are one document, none the other's repeat,
and a place that is repeated in one is removed in all that reach to it; all other columns, of whatever name, pass through; an
empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
import heapq
import re
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import load, mix64, pack_ints, quoted, shuffle_width, span_hashes, text_buffer, text_pieces, unpack_ints, window_hashes, word_spans

WIDTH = 13
PREFIXES = (1, 2, 4)
GROUP_SUFFIXES = 1_500_000
PACKED = "slot int, grp int, docs binary, counts binary, places binary, digests binary"
_PACKED_TYPES = [pa.int32(), pa.int32(), pa.binary(), pa.binary(), pa.binary(), pa.binary()]
_WORD_AND_GAP = re.compile(rb"[^\x20\x09-\x0D]+[\x20\x09-\x0D]*")


class _Suffixes:
    """Suffixes of a batch of documents in ascending order of doc_id."""

    def __init__(self, batch: pa.RecordBatch, width: int):
        ids = batch.column("doc_id")
        batch = pa.Table.from_batches([batch]).filter(ids.is_valid()).sort_by("doc_id").combine_chunks()
        self.ids = batch.column("doc_id").to_numpy()
        text = batch.column("text").combine_chunks() if batch.num_rows else pa.array([], pa.string())
        raw, offsets = text_buffer(text)
        starts, ends, self.first = word_spans(raw, offsets)
        self.words = span_hashes(raw, starts, ends)
        doc = np.repeat(np.arange(len(self.ids)), np.diff(self.first))
        at = np.arange(len(self.words))
        self.at = at[at + width <= self.first[doc + 1]] if len(at) else at
        self.doc = doc[self.at]
        self.width = width

    def prefix(self, length: int) -> np.ndarray:
        """Hash of each suffix's first ``length`` words, other than its digest even at full length."""
        h = window_hashes(self.words, length)[self.at] if length > 1 else self.words[self.at]
        return mix64(h ^ np.uint64(0xA5A5A5A55A5A5A5A)) if length == self.width else h

    def digest(self) -> np.ndarray:
        return window_hashes(self.words, self.width)[self.at] if len(self.at) else np.zeros(0, np.uint64)


def bins_log2(slots: int) -> int:
    """Bins a prefix length is hashed to: 16 a shuffle partition, from 2^12 up to 2^20 (a few MB of counts on the driver)."""
    return min(20, max(12, (16 * slots - 1).bit_length()))


def count_prefixes(docs: DataFrame, width: int, log2: int) -> dict[int, np.ndarray]:
    """Suffixes per prefix bin, for each prefix length; lengths x bins counts come to the driver, as Arrow columns."""
    lengths = [*(p for p in PREFIXES if p < width), width]
    shift = np.uint64(64 - log2)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts = np.zeros((len(lengths), 1 << log2), np.int64)
        for piece in text_pieces(batches, limit=4 << 20):
            s = _Suffixes(piece, width)
            for k, length in enumerate(lengths):
                counts[k] += np.bincount((s.prefix(length) >> shift).astype(np.int64), minlength=1 << log2)
        level, where = np.nonzero(counts)
        yield pa.RecordBatch.from_arrays([pa.array(level.astype(np.int32)), pa.array(where.astype(np.int32)), pa.array(counts[level, where])], ["level", "bin", "n"])

    rows = docs.select("doc_id", "text").mapInArrow(run, "level int, bin int, n long").groupBy("level", "bin").agg(F.sum("n").alias("n")).toArrow()
    level, where, n = (rows[c].to_numpy() for c in ("level", "bin", "n"))
    out = {length: np.zeros(1 << log2, np.int64) for length in lengths}
    for k, length in enumerate(lengths):
        out[length][where[level == k]] = n[level == k]
    return out


def plan_groups(counts: dict[int, np.ndarray], slots: int, group_suffixes: int = GROUP_SUFFIXES) -> tuple[list[tuple[int, np.ndarray]], int]:
    """For each prefix length the group of each bin (-1: look at the next length), and the number of groups.

    Groups are filled largest bin first, each bin into the emptiest group, and group g belongs to slot g modulo ``slots``.
    """
    lengths = sorted(counts)
    total = int(counts[lengths[0]].sum())
    groups = slots * max(1, -(-total // (group_suffixes * slots)))
    most = max(1, total // (4 * groups))
    tables = [(length, np.full(len(counts[length]), -1, np.int32)) for length in lengths]
    units, share = [], 1.0
    for (length, _), last in zip(tables, [False] * (len(tables) - 1) + [True], strict=True):
        n = counts[length]
        takes = n <= most if not last else np.ones(len(n), bool)
        units += [(int(n[b] * share) + 1, length, int(b)) for b in np.flatnonzero(takes)]
        share *= float(n[~takes].sum()) / max(1, int(n.sum()))  # longer prefixes only see what shorter ones left
    load_of = [(0, g) for g in range(groups)]
    by_length = dict(tables)
    for n, length, b in sorted(units, key=lambda u: (-u[0], u[1:])):
        held, g = load_of[0]
        by_length[length][b] = g
        heapq.heapreplace(load_of, (held + n, g))
    return tables, groups


def _row(slot: int, grp: int, docs: np.ndarray, counts: np.ndarray, places: np.ndarray, digests: bytes) -> list:
    return [slot, grp, pack_ints(docs), pack_ints(counts), pack_ints(places), digests]


def _batch(rows: list[list]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), _PACKED_TYPES, strict=True)], [c.split()[0] for c in PACKED.split(", ")])


def _bucket(ids: np.ndarray, buckets: int) -> np.ndarray:
    return (mix64(ids.astype(np.int64).view(np.uint64)) % np.uint64(buckets)).astype(np.int64)


def _repeat_rows(ids: np.ndarray, starts: np.ndarray, buckets: int) -> Iterator[list]:
    """Starts of repeated windows (doc ids and word places) packed into one row per bucket of documents."""
    bucket = _bucket(ids, buckets)
    order = np.lexsort((starts, ids, bucket))
    ids, starts, bucket = ids[order], starts[order], bucket[order]
    for part in np.split(np.arange(len(ids)), np.flatnonzero(np.diff(bucket)) + 1):
        if len(part):
            docs, counts = np.unique(ids[part], return_counts=True)
            yield _row(int(bucket[part[0]]), -1, docs, counts, starts[part], b"")


def subtree_repeats(digests: np.ndarray, docs: np.ndarray) -> np.ndarray:
    """Which leaves of a group lie below a deep node whose smallest document is another than theirs."""
    order = np.argsort(digests, kind="stable")
    d = digests[order]
    node = np.concatenate([[True], d[1:] != d[:-1]])
    begins = np.flatnonzero(node)
    least = np.minimum.reduceat(docs[order], begins)[np.cumsum(node) - 1]
    out = np.zeros(len(digests), bool)
    out[order] = docs[order] > least
    return out


def repeated_windows(docs: DataFrame, width: int = WIDTH) -> DataFrame:
    """Packed starts of repeated windows, dealt by bucket of documents (column ``slot``)."""
    slots = shuffle_width(docs.sparkSession)
    log2 = bins_log2(slots)
    tables, _ = plan_groups(count_prefixes(docs, width, log2), slots)
    shift = np.uint64(64 - log2)

    def split(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for piece in text_pieces(batches, limit=6 << 20):
            s = _Suffixes(piece, width)
            if not len(s.at):
                continue
            digest = s.digest()
            grp = np.full(len(s.at), -1, np.int32)
            for length, table in tables:
                open_ = grp < 0
                if open_.any():
                    grp[open_] = table[(s.prefix(length)[open_] >> shift).astype(np.int64)]
            ids = s.ids[s.doc]
            place = s.at - s.first[s.doc]
            known = subtree_repeats(digest, ids)
            if known.any():
                for row in _repeat_rows(ids[known], place[known], slots):
                    yield _batch([row])
            on = np.flatnonzero(~known)
            on = on[np.argsort(grp[on], kind="stable")]
            for part in np.split(on, np.flatnonzero(np.diff(grp[on])) + 1):
                docs_, counts = np.unique(ids[part], return_counts=True)
                g = int(grp[part[0]])
                yield _batch([_row(g % slots, g, docs_, counts, place[part], digest[part].tobytes())])

    def gather(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        now = None

        def close() -> Iterator[pa.RecordBatch]:
            digests, ids, places = (np.concatenate(x) for x in zip(*held, strict=True))
            found = subtree_repeats(digests, ids)
            if found.any():
                for row in _repeat_rows(ids[found], places[found], slots):
                    yield _batch([row])

        for batch in batches:
            for k in range(batch.num_rows):
                r = {n: batch.column(n)[k].as_py() for n in ("grp", "docs", "counts", "places", "digests", "slot")}
                if r["grp"] < 0:
                    yield batch.slice(k, 1)
                    continue
                if r["grp"] != now and held:
                    yield from close()
                    held.clear()
                now = r["grp"]
                held.append((np.frombuffer(r["digests"], np.uint64), np.repeat(unpack_ints(r["docs"]), unpack_ints(r["counts"])), unpack_ints(r["places"])))
        if held:
            yield from close()

    dealt = docs.select("doc_id", "text").mapInArrow(split, PACKED).repartitionById(slots, F.col("slot")).sortWithinPartitions("grp")
    return dealt.mapInArrow(gather, PACKED)


def covered(starts: np.ndarray, width: int, words: int) -> np.ndarray:
    """Which of ``words`` words a window at one of ``starts`` covers: the union is the document's maximal repeats."""
    edge = np.zeros(words + width + 1, np.int32)
    np.add.at(edge, starts, 1)
    np.add.at(edge, starts + width, -1)
    return np.cumsum(edge)[:words] > 0


def _shape(ddl: str, more: list[T.StructField] | tuple = ()) -> T.StructType:
    return T.StructType([*T.StructType.fromDDL(ddl).fields, *more])


def without_repeats(docs: DataFrame, width: int = WIDTH, texts: bool = True) -> DataFrame:
    """``docs`` with n_words, n_removed and kept_sha256 and, if ``texts``, its text without the removed words.

    Removed words go with the space after them; kept_sha256 is over the kept words joined by single spaces.
    """
    slots = shuffle_width(docs.sparkSession)
    found = repeated_windows(docs, width)
    other = [c for c in docs.columns if c not in ("doc_id", "text")]

    def shrink(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import zstandard

        squeeze = zstandard.ZstdCompressor(level=3).compress
        for piece in text_pieces(batches):
            ids = piece.column("doc_id")
            body = [None if t is None else squeeze(t.encode()) for t in piece.column("text").to_pylist()]
            spread = np.fromiter((zlib.crc32(x or b"") for x in body), np.int64, len(body)) % slots  # rows without an id have no marks to meet
            slot = np.where(ids.is_valid().to_numpy(zero_copy_only=False), _bucket(ids.fill_null(0).to_numpy(zero_copy_only=False), slots), spread).astype(np.int32)
            yield pa.RecordBatch.from_arrays([pa.array(slot), pa.array(np.ones(len(slot), np.int32)), ids, pa.array(body, pa.binary()), *([piece.column("rest")] if other else [])], ["slot", "kind", "doc_id", "body", *["rest"] * bool(other)])

    rest = [F.struct(*[F.col(quoted(c)) for c in other]).alias("rest")] if other else []
    carried = docs.select(*rest).schema.fields if other else []
    packed = docs.select("doc_id", "text", *rest).mapInArrow(shrink, _shape("slot int, kind int, doc_id long, body binary", carried))
    marks = found.select("slot", F.lit(0).alias("kind"), "docs", "counts", "places")
    both = packed.unionByName(marks, allowMissingColumns=True).repartitionById(slots, F.col("slot")).sortWithinPartitions("kind")

    def apply(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import zstandard

        expand = zstandard.ZstdDecompressor().decompress
        starts: dict[int, list[np.ndarray]] = {}
        for batch in batches:
            kinds = batch.column("kind").to_numpy()
            for k in np.flatnonzero(kinds == 0).tolist():
                ids, counts, places = (unpack_ints(batch.column(n)[k].as_py()) for n in ("docs", "counts", "places"))
                for doc_id, p in zip(ids.tolist(), np.split(places.astype(np.int32), np.cumsum(counts)[:-1]), strict=True):
                    starts.setdefault(doc_id, []).append(p)
            at = np.flatnonzero(kinds == 1)
            if not len(at):
                continue
            batch = batch.slice(int(at[0]), len(at))  # sorted by kind
            n_words, n_removed, digests, kept_texts = [], [], [], []
            for doc_id, body in zip(batch.column("doc_id").to_pylist(), batch.column("body").to_pylist(), strict=True):
                raw = b"" if body is None else expand(body)
                words = raw.split()
                own = starts.get(doc_id) if doc_id is not None else None
                own = np.concatenate(own) if own else np.zeros(0, np.int32)
                own = own[own + width <= len(words)]  # a place of another text under the same id
                gone = covered(own, width, len(words)) if len(own) else None
                left = words if gone is None else [w for w, g in zip(words, gone.tolist(), strict=True) if not g]
                n_words.append(len(words))
                n_removed.append(len(words) - len(left))
                digests.append(hashlib.sha256(b" ".join(left)).hexdigest())
                if texts:
                    if gone is not None:
                        lead = raw[: len(raw) - len(raw.lstrip())]
                        raw = lead + b"".join(w for w, g in zip(_WORD_AND_GAP.findall(raw), gone.tolist(), strict=True) if not g)
                    kept_texts.append(None if body is None else raw.decode())
            columns = [batch.column("doc_id"), *([batch.column("rest")] if other else []), pa.array(n_words, pa.int64()), pa.array(n_removed, pa.int64()), pa.array(digests, pa.string())]
            names = ["doc_id", *["rest"] * bool(other), "n_words", "n_removed", "kept_sha256"]
            if texts:
                columns.append(pa.array(kept_texts, pa.string()))
                names.append("text")
            yield pa.RecordBatch.from_arrays(columns, names)

    said = "n_words long, n_removed long, kept_sha256 string" + (", text string" if texts else "")
    return both.mapInArrow(apply, T.StructType([*_shape("doc_id long", carried).fields, *_shape(said).fields]))


def deduplicated(docs: DataFrame, width: int = WIDTH) -> DataFrame:
    """``docs`` in its own columns, texts without repeated passages, n_chars following where it is there."""
    out = without_repeats(docs, width)
    columns = []
    for c in docs.columns:
        if c == "n_chars":
            columns.append(F.when(F.col("n_removed") > 0, F.length("text").cast(docs.schema["n_chars"].dataType)).otherwise(F.col("rest.n_chars")).alias(c))
        else:
            columns.append(F.col(c) if c in ("doc_id", "text") else F.col(f"rest.{quoted(c)}").alias(c))
    return out.select(*columns)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return without_repeats(load(spark, sf_dir, "documents").select("doc_id", "text"), texts=False)


ORACLE = f"""
WITH d AS (SELECT doc_id, list_filter(string_split_regex(coalesce(text, ''), '[ \\t\\n\\x0b\\f\\r]+'), lambda x: x <> '') AS w FROM documents),
s AS (SELECT doc_id, w, unnest(range(1, len(w) - {WIDTH - 2})) AS i FROM d WHERE len(w) >= {WIDTH}),
g AS (SELECT doc_id, i, array_to_string(w[i:i + {WIDTH - 1}], ' ') AS win FROM s),
m AS (SELECT win, min(doc_id) AS least FROM g GROUP BY win),
r AS (SELECT g.doc_id, unnest(range(i, i + {WIDTH})) AS p FROM g JOIN m USING (win) WHERE g.doc_id > least),
c AS (SELECT doc_id, list(DISTINCT p) AS gone FROM r GROUP BY doc_id),
x AS (SELECT doc_id, unnest(w) AS word, generate_subscripts(w, 1) AS p FROM d),
k AS (SELECT x.doc_id, string_agg(word, ' ' ORDER BY p) AS kept, count(*) AS n FROM x WHERE NOT EXISTS (SELECT 1 FROM (SELECT DISTINCT doc_id, p FROM r) q WHERE q.doc_id = x.doc_id AND q.p = x.p) GROUP BY 1)
SELECT d.doc_id, len(w)::BIGINT AS n_words, (len(w) - coalesce(k.n, 0))::BIGINT AS n_removed, sha256(coalesce(kept, '')) AS kept_sha256
FROM d LEFT JOIN k ON k.doc_id = d.doc_id
"""
