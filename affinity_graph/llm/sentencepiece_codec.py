"""SentencePiece encoding and decoding through a table of distinct marked words.

Where no piece of the vocabulary has a whitespace marker after another character, segmentation never crosses from a
word into the next marker run, so a text's ids are those of its marked words end to end:

1. Documents are taken in blocks of about ``BLOCK_BYTES`` of text, named by a digest of their contents. A block numbers its
   distinct marked words; a document becomes the numbers of its words in their places. Documents are read twice, once for
   the words and once for the places, which costs less than writing either; what is not a plain scan of files is
   written first, and a block whose words were not found in the first reading is an error.
2. The words of all blocks meet in slots by their hash. There each distinct word of the corpus is segmented once, and its ids go
   back to every block that has it. A slot's table holds that slot's words only; there are ``SLOTS`` slots a shuffle partition.
3. Each block meets its ids and joins them back by place, document by document.

What is shuffled grows with the distinct words of a block and with packed places, not with the words in full. A word that is
in all texts is one entry a block. Vocabularies with crossing pieces, or a normaliser that is not the identity, are
encoded whole, text by text.

Nulls and edges: a null text is empty and has the end id only; texts of blanks only, marker characters in the text,
repeated rows, null ids and very long texts (a block of their own) are ordinary; other columns are ignored; an empty table
gives an empty result.
"""

from __future__ import annotations

import hashlib
import re
import zlib
from array import array
from collections.abc import Callable, Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import load, pack_ints, public_path, release, shuffle_width, stored, text_pieces, unpack_ints

MODEL = "piece_bpe_32k.model"
MARK = "▁"
BLOCK_BYTES, SLOTS = 16 << 20, 4
_MARKED = re.compile(f"{MARK}+[^{MARK}]*")


class MarkedWordTable:
    """Encodes texts by looking up their marked words; ``ids`` and ``digits`` are the table's columns. ``limit``: entries held, None: all."""

    def __init__(self, path: str, end_id: bool = True, limit: int | None = 250_000):
        import sentencepiece

        self.model = sentencepiece.SentencePieceProcessor(model_file=path)
        self.limit = limit
        self.end = [self.model.eos_id()] if end_id else []
        pieces = [self.model.id_to_piece(i) for i in range(self.model.get_piece_size())]
        probe = "a   ﬁ　 A"
        same = self.model.decode(self.model.encode(probe)) == probe and self.model.encode_as_pieces("a")[0].startswith(MARK)
        self.separable = same and not any(MARK in p.lstrip(MARK) for p in pieces)
        self.clear()

    _of: dict[str, MarkedWordTable] = {}

    @classmethod
    def of(cls, path: str) -> MarkedWordTable:
        """One table a Python worker, for what needs no ids."""
        if path not in cls._of:
            cls._of[path] = cls(path)
        return cls._of[path]

    def clear(self) -> None:
        lone = [self.model.piece_to_id(MARK)]
        self.ids: dict[str, list[int]] = {"": lone}
        self.digits: dict[str, str] = {"": str(lone[0])}

    def words(self, text: str) -> list[str]:
        """Marked words of a text, each without its first marker."""
        if MARK not in text and "  " not in text and text[0] != " " and text[-1] != " ":
            return text.split(" ")
        marked = MARK + text.replace(" ", MARK)
        return [w[1:].replace(MARK, " ") for w in _MARKED.findall(marked)]

    def look_up(self, words: list[str]) -> None:
        fresh = [w for w in dict.fromkeys(words) if w not in self.ids]
        if self.limit and len(self.ids) + len(fresh) > self.limit and len(self.ids) > 1:
            self.clear()
            fresh = [w for w in dict.fromkeys(words) if w]
        for w, ids in zip(fresh, self.model.encode(fresh, num_threads=1), strict=True):
            self.ids[w] = ids
            self.digits[w] = " ".join(map(str, ids))

    def encode(self, text: str | None) -> tuple[list[int], str]:
        """Ids of the whole text with the end id, and the same as decimals joined by a space."""
        if not text:
            return self.end, " ".join(map(str, self.end))
        if not self.separable:
            ids = self.model.encode(text) + self.end
            return ids, " ".join(map(str, ids))
        words = self.words(text)
        if not all(map(self.ids.__contains__, words)):
            self.look_up(words)
        ids = list(chain.from_iterable(map(self.ids.__getitem__, words)))
        ids += self.end
        return ids, " ".join([*map(self.digits.__getitem__, words), *map(str, self.end)])


class _Numbering(dict):
    """Words to numbers in order of first sight."""

    def __missing__(self, word: str) -> int:
        self[word] = number = len(self)
        return number


def _pack(values: np.ndarray) -> bytes:
    """int32 values, one byte plane after another, compressed."""
    return zstandard.ZstdCompressor(level=1).compress(np.ascontiguousarray(np.asarray(values, "<i4").view(np.uint8).reshape(-1, 4).T).tobytes())


def _unpack(blob: bytes) -> np.ndarray:
    raw = np.frombuffer(zstandard.ZstdDecompressor().decompress(blob), np.uint8)
    return np.ascontiguousarray(raw.reshape(4, -1).T).reshape(-1).view("<i4").astype(np.int64)


_WORDS = "block long, slot int, numbers binary, words binary"
_IDS = "block long, doc_ids array<long>, counts binary, places binary, numbers binary, sizes binary, ids binary"


def _rows(ddl: str, rows: list[dict]) -> pa.RecordBatch:
    types = {"long": pa.int64(), "int": pa.int32(), "array<long>": pa.list_(pa.int64()), "binary": pa.binary()}
    fields = [f.split() for f in ddl.split(", ")]
    return pa.RecordBatch.from_arrays([pa.array([r.get(n) for r in rows], types[t]) for n, t in fields], [n for n, _ in fields])


def _blocks(docs: DataFrame, run: Callable, schema: str) -> DataFrame:
    """``run`` over (block, doc_ids, texts) of blocks of whole documents."""

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for piece in text_pieces(batches, limit=BLOCK_BYTES):
            doc_ids, texts = piece.column("doc_id").to_pylist(), piece.column("text").to_pylist()
            digest = hashlib.blake2b(repr(doc_ids).encode(), digest_size=8)
            for text in texts:
                digest.update((text or "").encode() + b"\xff")
            yield from run(int.from_bytes(digest.digest(), "little", signed=True), doc_ids, texts)

    return docs.select("doc_id", "text").mapInArrow(each, schema)


def _words(docs: DataFrame, model_path: str, slots: int) -> DataFrame:
    """Each block's distinct words by slot; a word's number is its place among them in order of first sight."""

    def run(block: int, doc_ids: list, texts: list) -> Iterator[pa.RecordBatch]:
        table, seen = MarkedWordTable.of(model_path), {}
        for text in texts:
            if text:
                seen.update(dict.fromkeys(table.words(text)))
        words = list(seen)
        slot = np.fromiter(map(zlib.crc32, map(str.encode, words)), np.int64, len(words)) % slots
        order = np.argsort(slot, kind="stable")
        for part in np.split(order, np.flatnonzero(np.diff(slot[order])) + 1):
            if len(part):
                said = MARK.join(map(words.__getitem__, part.tolist())).encode()
                yield _rows(_WORDS, [{"block": block, "slot": int(slot[part[0]]), "numbers": pack_ints(part), "words": zstandard.ZstdCompressor(level=3).compress(said)}])

    return _blocks(docs, run, _WORDS)


def _places(docs: DataFrame, model_path: str) -> DataFrame:
    """Each block's documents as numbers of words, in the columns of ``_IDS``."""

    def run(block: int, doc_ids: list, texts: list) -> Iterator[pa.RecordBatch]:
        table, numbers, counts, places = MarkedWordTable.of(model_path), _Numbering(), [], array("i")
        for text in texts:
            before = len(places)
            if text:
                places.extend(map(numbers.__getitem__, table.words(text)))
            counts.append(len(places) - before)
        yield _rows(_IDS, [{"block": block, "doc_ids": doc_ids, "counts": _pack(counts), "places": _pack(np.frombuffer(places, np.int32) if places else [])}])

    return _blocks(docs, run, _IDS)


def _segmented(words: DataFrame, model_path: str) -> DataFrame:
    """The ids of each block's words; rows come sorted by slot, and a slot's table serves all of its blocks."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table, now = MarkedWordTable(model_path, limit=None), None
        for batch in batches:
            for r in batch.to_pylist():
                if r["slot"] != now:
                    table.clear()
                    now = r["slot"]
                said = zstandard.ZstdDecompressor().decompress(r["words"]).decode().split(MARK)
                if not all(map(table.ids.__contains__, said)):
                    table.look_up(said)
                ids = list(map(table.ids.__getitem__, said))
                yield _rows(_IDS, [{"block": r["block"], "numbers": r["numbers"], "sizes": _pack(list(map(len, ids))), "ids": _pack(list(chain.from_iterable(ids)))}])

    return words.mapInArrow(run, _IDS)


def _joined(rows: Iterator[dict], end: list[int]) -> Iterator[tuple[int | None, np.ndarray, str]]:
    """(doc_id, ids with the end id, the same as decimals) of the documents of blocks; a block's ids come before its documents."""
    said_end, now, parts, table = list(map(str, end)), None, [], None
    for r in rows:
        if r["block"] != now:
            now, parts, table = r["block"], [], None
        if r["ids"] is not None:
            parts.append((unpack_ints(r["numbers"]), _unpack(r["sizes"]), _unpack(r["ids"])))
            continue
        if table is None:  # equal blocks share a digest and what was found for it
            numbers, sizes, ids = (np.concatenate(x) if parts else np.zeros(0, np.int64) for x in (zip(*parts, strict=True) if parts else ((), (), ())))
            begins = np.cumsum(sizes) - sizes
            many = int(numbers.max()) + 1 if len(numbers) else 0
            digits, texts = [""] * many, list(map(str, ids.tolist()))
            for number, a, n in zip(numbers.tolist(), begins.tolist(), sizes.tolist(), strict=True):
                digits[number] = texts[a] if n == 1 else " ".join(texts[a : a + n])
            size_of, begin_of = np.zeros(many, np.int64), np.zeros(many, np.int64)
            size_of[numbers], begin_of[numbers] = sizes, begins
            table, texts = True, []
        places, upto = _unpack(r["places"]), 0
        if len(places) and (places.max() >= many or not size_of[places].all()):
            raise ValueError("documents changed between two readings: write them first")
        for doc_id, count in zip(r["doc_ids"], _unpack(r["counts"]).tolist(), strict=True):
            own = places[upto : upto + count]
            upto += count
            n = size_of[own]
            at = np.repeat(begin_of[own] - (np.cumsum(n) - n), n) + np.arange(int(n.sum()))
            yield doc_id, np.concatenate([ids[at], np.array(end, np.int64)]), " ".join([*map(digits.__getitem__, own.tolist()), *said_end])


def _each(docs: DataFrame, model_path: str, finish: Callable, schema: str, scan: bool) -> DataFrame:
    """``finish`` over (doc_id, ids, decimals) of every document, in lists of about a thousand. ``scan``: read twice, it is the same."""
    if not MarkedWordTable(model_path).separable:

        def whole(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            table = MarkedWordTable(model_path)
            for piece in text_pieces(batches, limit=4 << 20):
                encoded = [table.encode(t) for t in piece.column("text").to_pylist()]
                yield finish(table, [(d, np.array(ids, np.int64), said) for d, (ids, said) in zip(piece.column("doc_id").to_pylist(), encoded, strict=True)])

        return docs.select("doc_id", "text").mapInArrow(whole, schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = MarkedWordTable(model_path)
        rows = (r for batch in batches for k in range(batch.num_rows) for r in batch.slice(k, 1).to_pylist())
        held, size = [], 0
        for item in _joined(rows, table.end):
            held.append(item)
            size += len(item[1])
            if len(held) >= 1000 or size > 1 << 20:
                yield finish(table, held)
                held, size = [], 0
        if held:
            yield finish(table, held)
        release()

    width = shuffle_width(docs.sparkSession)
    docs = docs.select("doc_id", "text") if scan else stored(docs.select("doc_id", "text"), "texts")
    words = _words(docs, model_path, SLOTS * width).repartition(width, "slot").sortWithinPartitions("slot")
    both = _segmented(words, model_path).unionByName(_places(docs, model_path)).withColumn("last", F.col("ids").isNull())
    return both.repartition(width, "block").sortWithinPartitions("block", "last").mapInArrow(run, schema)


def encode(docs: DataFrame, model_path: str, scan: bool = False) -> DataFrame:
    """(doc_id, ids array<int>) of whole texts. ``scan``: ``docs`` is a plain scan of files, which need not be written first."""

    def finish(table: MarkedWordTable, items: list) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array([d for d, _, _ in items], pa.int64()), pa.array([ids.astype(np.int32) for _, ids, _ in items], pa.list_(pa.int32()))], ["doc_id", "ids"])

    return _each(docs, model_path, finish, "doc_id long, ids array<int>", scan)


def decode(ids: DataFrame, model_path: str) -> DataFrame:
    """(doc_id, text) of id arrays; a null array is an empty text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import sentencepiece

        model = sentencepiece.SentencePieceProcessor(model_file=model_path)
        for batch in batches:
            texts = [model.decode(list(x)) if x else "" for x in batch.column("ids").to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(texts, pa.string())], ["doc_id", "text"])

    return ids.select("doc_id", "ids").mapInArrow(run, "doc_id long, text string")


def round_trip(docs: DataFrame, model_path: str, scan: bool = False) -> DataFrame:
    """Encode and decode each text and return digests of both, so that ids never leave their task. ``scan`` as for ``encode``."""

    def finish(table: MarkedWordTable, items: list) -> pa.RecordBatch:
        columns = zip(*((d, len(ids), hashlib.sha256(said.encode()).hexdigest(), hashlib.sha256(table.model.decode(ids.tolist()).encode()).hexdigest()) for d, ids, said in items), strict=True)
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, (pa.int64(), pa.int64(), pa.string(), pa.string()), strict=True)], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return _each(docs, model_path, finish, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string", scan)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return round_trip(load(spark, sf_dir, "documents"), public_path(MODEL), scan=True)


def brute_force(rows: list[tuple[int, str | None]], model_path: str) -> list[tuple[int, int, str, str]]:
    import sentencepiece

    m, out = sentencepiece.SentencePieceProcessor(model_file=model_path), []
    for doc_id, text in rows:
        ids = m.encode(text or "", add_eos=True)
        out.append((doc_id, len(ids), hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256(m.decode(ids).encode()).hexdigest()))
    return out
