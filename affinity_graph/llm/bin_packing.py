"""Hierarchical residual packing of token pieces into sequences.

Level 0 packs in the task that tokenizes: every text is cut into pieces of at most ``capacity`` tokens, pieces of full
length are sequences at once, and the others are packed best-fit, largest first. Bins whose residual is at most
``slack`` leave; underfull bins go on as single items with their members inside, are dealt by a hash to groups of
bounded size, and are packed again, with the number of groups falling as bins close, until one group has been packed or
a round no longer helps (it closes or merges less than one bin in a hundred). Then all bins leave. Nothing is dropped,
and no task gets more than about ``group_items`` items, however many cannot be paired.

Nulls and edges: a null text is empty and has its end id only; a null doc_id is kept; a document's last piece may be
shorter; repeated rows are separate pieces; an empty table gives an empty result.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import load, public_path, shuffle_width, stored, text_pieces
from .token_output import END_ID, TOKENIZER, encoder

CAPACITY, SLACK, GROUP_ITEMS = 4096, 8, 40_000

MEMBER = "doc_id: bigint, piece: int, start: bigint, length: bigint, ids_crc32: bigint, offset: bigint"
BINS = f"closed boolean, sequence_id bigint, fill int, members array<struct<{MEMBER}>>"
_MEMBER_TYPE = pa.struct([("doc_id", pa.int64()), ("piece", pa.int32()), ("start", pa.int64()), ("length", pa.int64()), ("ids_crc32", pa.int64()), ("offset", pa.int64())])


def best_fit(sizes: list[int], capacity: int) -> list[list[int]]:
    """Best-fit over sizes in the given order: bins as lists of places in ``sizes``.

    Open bins are kept by residual, and the smallest residual that fits is the lowest set bit of a mask.
    """
    by_residual: dict[int, list[int]] = {}
    mask, bins = 0, []
    for i, size in enumerate(sizes):
        fit = mask >> size
        if fit:
            residual = size + (fit & -fit).bit_length() - 1
            stack = by_residual[residual]
            k = stack.pop()
            if not stack:
                mask ^= 1 << residual
            bins[k].append(i)
        else:
            residual, k = capacity, len(bins)
            bins.append([i])
        residual -= size
        if residual:
            by_residual.setdefault(residual, []).append(k)
            mask |= 1 << residual
    return bins


def _emit(bins: list[tuple[bool, int, int, list[tuple]]]) -> Iterator[pa.RecordBatch]:
    for lo in range(0, len(bins), 4096):
        part = bins[lo : lo + 4096]
        flat = [m for b in part for m in b[3]]
        cuts = np.cumsum([0, *(len(b[3]) for b in part)]).astype(np.int32)
        columns = [pa.array(c, k.type) for c, k in zip(zip(*flat, strict=True), _MEMBER_TYPE, strict=True)]
        members = pa.ListArray.from_arrays(pa.array(cuts), pa.StructArray.from_arrays(columns, fields=list(_MEMBER_TYPE)))
        yield pa.RecordBatch.from_arrays([pa.array([b[0] for b in part]), pa.array([b[1] for b in part], pa.int64()), pa.array([b[2] for b in part], pa.int32()), members], ["closed", "sequence_id", "fill", "members"])


def _pack(items: list[tuple[int, list[tuple]]], capacity: int, slack: int, numbers: Iterator[int]) -> list[tuple[bool, int, int, list[tuple]]]:
    """Items (fill, members) to bins (closed, number, fill, members), members placed without gaps."""
    items.sort(key=lambda x: (-x[0], x[1][0][0] is not None, x[1][0][:2]))
    out = []
    for chosen in best_fit([f for f, _ in items], capacity):
        members, at = [], 0
        for i in chosen:
            members += [(*m[:5], m[5] + at) for m in items[i][1]]
            at += items[i][0]
        out.append((capacity - at <= slack, next(numbers), at, members))
    return out


def _numbers(level: int, part: int) -> Iterator[int]:
    at = (level << 58) + (part << 34)
    while True:
        yield at
        at += 1


def cut_and_pack(docs: DataFrame, tokenizer_path: str, capacity: int, slack: int, end_id: int = END_ID, group_items: int = GROUP_ITEMS) -> DataFrame:
    """Level 0: tokenize, cut, and pack in the scan's own tasks."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        encode, numbers, items = encoder(tokenizer_path, end_id).encode_all, _numbers(0, TaskContext.get().partitionId()), []
        for piece in text_pieces(batches, limit=1 << 20):
            full = []
            for doc_id, body in zip(piece.column("doc_id").to_pylist(), encode(piece.column("text")), strict=True):
                n = len(body) // 4
                for k, start in enumerate(range(0, n, capacity)):
                    length = min(capacity, n - start)
                    member = (doc_id, k, start, length, zlib.crc32(body[4 * start : 4 * (start + length)]), 0)
                    if length == capacity:
                        full.append((True, next(numbers), capacity, [member]))
                    else:
                        items.append((length, [member]))
            yield from _emit(full)
            if len(items) >= group_items:
                yield from _emit(_pack(items, capacity, slack, numbers))
                items = []
        if items:
            yield from _emit(_pack(items, capacity, slack, numbers))

    return docs.select("doc_id", "text").mapInArrow(run, BINS)


def repack(bins: DataFrame, groups: int, level: int, capacity: int, slack: int) -> DataFrame:
    """One round over underfull bins, dealt to ``groups`` groups by a hash of their number."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        items = [(f, [tuple(m.values()) for m in ms]) for b in batches for f, ms in zip(b.column("fill").to_pylist(), b.column("members").to_pylist(), strict=True)]
        if items:
            yield from _emit(_pack(items, capacity, slack, _numbers(level, TaskContext.get().partitionId())))

    dealt = bins.repartitionById(groups, F.pmod(F.xxhash64("sequence_id", F.lit(level)), F.lit(groups)).cast("int"))
    return dealt.mapInArrow(run, BINS)


def pack(docs: DataFrame, tokenizer_path: str, capacity: int = CAPACITY, slack: int = SLACK, group_items: int = GROUP_ITEMS) -> DataFrame:
    """Sequences as one row per piece: doc_id, piece, start, length, ids_crc32, sequence_id, offset."""
    spark = docs.sparkSession
    table = stored(cut_and_pack(docs, tokenizer_path, capacity, slack, group_items=group_items), "bins-0")
    done = [table.where("closed")]
    table = table.where("NOT closed")
    left, level = table.count(), 0
    groups = max(1, min(shuffle_width(spark), left // 2_000), -(-left // group_items)) if left else 0
    while groups and level < 30:
        level += 1
        packed = stored(repack(table.select("sequence_id", "fill", "members"), groups, level, capacity, slack), f"bins-{level}")
        counts = {r[0]: r[1] for r in packed.groupBy("closed").count().collect()}
        after, before, last = counts.get(False, 0), left, groups == 1
        groups = max(1, min(groups // 4, after // 2_000), -(-after // group_items))
        if last or not after or sum(counts.values()) > 0.99 * before and counts.get(True, 0) < 0.01 * before:
            done.append(packed)
            break
        done.append(packed.where("closed"))
        table, left = packed.where("NOT closed"), after
    else:
        done.append(table)
    out = done[0]
    for d in done[1:]:
        out = out.unionByName(d)
    return out.select("sequence_id", F.explode("members").alias("m")).select("m.doc_id", "m.piece", "m.start", "m.length", "m.ids_crc32", "sequence_id", "m.offset")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(load(spark, sf_dir, "documents"), public_path(TOKENIZER))
