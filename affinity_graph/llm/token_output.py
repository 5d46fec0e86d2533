"""Token ids in binary shards: one shared zstandard dictionary, every document a frame of its own.

File format (a Parquet table, written and read by Spark so that any file system does):
``blocks``  one row per block of consecutive documents: shard, block, dict_hash, first_id, last_id, start (tokens
            of the shard before the block) and, as little-endian int64 arrays, doc_ids, n_tokens and offsets; payload
            has the frames end to end, frame i at offsets[i]..offsets[i+1].
``dictionary``  one row: dict_hash, content.
Shards are ranges of doc_id in ascending order, so (shard, block, place in block) is the global order.

Nulls and edges: a null text is an empty document (its end id only); a null doc_id comes first and is kept; repeated
rows are kept, in an order fixed by the text's hash; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import os
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import load, new_path, public_path, shuffle_width, text_buffer, text_pieces, word_spans

TOKENIZER = "word_bpe_49k.json"
END_ID = 1
BLOCK_BYTES = 1 << 20
#: The dictionary is trained on so many documents (lowest hash of doc_id) and so many characters of each.
SAMPLE_DOCS, SAMPLE_CHARS, DICTIONARY_BYTES = 1000, 16384, 112_640
NULL_ID = -(1 << 63)

BLOCKS = "shard int, block int, dict_hash string, first_id long, last_id long, start long, tokens long, doc_ids binary, n_tokens binary, offsets binary, payload binary"


#: Longest chunk, in bytes, that a key of two 64-bit integers holds whole: the last byte has the length.
_SHORT = 15
#: Chunks looked up at a time.
_BLOCK_CHUNKS = 1 << 17
_LOWER = bytes(range(65)) + bytes(range(97, 123)) + bytes(range(91, 256))
_HEAD = np.array([(1 << 8 * k) - 1 for k in range(9)], np.uint64)
_TOP = np.uint64(0x8080808080808080)
#: Second bytes of the letters of Latin-1 beyond ASCII, after 0xC3; those of capitals.
_LATIN = np.array([0x80 <= c < 0xC0 and c not in (0x97, 0xB7) for c in range(256)])
_CAPITAL = _LATIN & (np.arange(256) < 0x9F)
_ALNUM, _PUNCT = (np.array([0x20 < c < 0x7F and chr(c).isalnum() == alnum for c in range(256)]) for alnum in (True, False))


class _KeyTable:
    """Open-addressed table from a chunk's two-integer key to the place and number of its ids; looked up and filled in bulk.

    Keys are the chunks themselves and compared whole, so that no hash decides what is equal.
    """

    def __init__(self, words: int):
        self.bits = max(10, (2 * words - 1).bit_length())
        #: Two integers of the key (the second is 0 in a free slot), place << 8 | number of ids, and one to fill 32 bytes.
        self.slots = np.zeros((1 << self.bits, 4), np.uint64)
        self.arena, self.words, self.used = np.zeros(4096, np.uint32), 0, 0

    def _first(self, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
        h = lo * np.uint64(0x9E3779B97F4A7C15) ^ hi * np.uint64(0xC2B2AE3D27D4EB4F)
        h ^= h >> np.uint64(32)
        h *= np.uint64(0xD6E8FEB86659FD93)
        return (h >> np.uint64(64 - self.bits)).astype(np.int64)

    def find(self, lo: np.ndarray, hi: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The third integer of each key's slot, and which keys have one."""
        at = self._first(lo, hi)
        rows = self.slots.take(at, axis=0)
        out, known = rows[:, 2].copy(), (rows[:, 0] == lo) & (rows[:, 1] == hi)
        left = np.flatnonzero(~known & (rows[:, 1] != 0))
        while len(left):
            at[left] = at[left] + 1 & (1 << self.bits) - 1
            rows = self.slots.take(at[left], axis=0)
            hit = (rows[:, 0] == lo[left]) & (rows[:, 1] == hi[left])
            out[left[hit]], known[left[hit]] = rows[hit, 2], True
            left = left[~hit & (rows[:, 1] != 0)]
        return out, known

    def reserve(self, n: int) -> None:
        """Room for ``n`` ids beyond those in use."""
        if self.used + n > len(self.arena):
            self.arena = np.concatenate([self.arena[: self.used], np.zeros(max(n, self.used) + 4096, np.uint32)])

    def add(self, lo: np.ndarray, hi: np.ndarray, counts: np.ndarray, ids: np.ndarray) -> None:
        """Keys that differ from each other and from the table's, with their ids end to end."""
        self.reserve(len(ids))
        self.arena[self.used : self.used + len(ids)] = ids
        value = (self.used + np.cumsum(counts) - counts << 8 | counts).astype(np.uint64)
        self.used, self.words = self.used + len(ids), self.words + len(lo)
        at, left = self._first(lo, hi), np.arange(len(lo))
        while len(left):
            free = self.slots[at[left], 1] == 0
            _, first = np.unique(at[left[free]], return_index=True)
            won = left[free][first]
            self.slots[at[won], 0], self.slots[at[won], 1], self.slots[at[won], 2] = lo[won], hi[won], value[won]
            # A key whose free slot another one took sees it taken in the next turn.
            at[left[~free]] = at[left[~free]] + 1 & (1 << self.bits) - 1
            left = np.setdiff1d(left, won, assume_unique=True)


def _gathered(arena: np.ndarray, places: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """``counts[i]`` values of ``arena`` from ``places[i]`` on, end to end."""
    ends = np.cumsum(counts)
    return arena[np.repeat(places - ends + counts, counts) + np.arange(int(ends[-1]) if len(ends) else 0)]


class ChunkEncoder:
    """Ids of whole texts by a fast tokenizer that drops white space: each distinct white-space-free chunk is encoded once.

    Splitting at the six ASCII separators is exact here, as normalisation never joins across them and the pre-tokenizer
    drops them. Punctuation at the end of a chunk that follows a letter of Latin-1 or a digit is a chunk of its own, as it is a
    pre-token, and chunks in Latin-1 are lower-cased, as the tokenizer does, so that fewer are distinct. Chunks of up to 15 bytes
    are found many at a time in a table of keys, longer ones and those with a mark of special tokens in a dict. New chunks of
    letters only are encoded many at a time: each is one pre-token, and ends where a piece with the word-end suffix does.

    Both tables have two generations of at most ``limit`` chunks (the dict: an eighth of it), or of one block's if it has more:
    when the young one is full the old one is dropped.
    """

    def __init__(self, path: str, end_id: int = END_ID, limit: int = 1 << 19):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.limit, self.end = limit, np.array([end_id], "<u4").tobytes()
        self.keys, self.old_keys, self.long, self.old_long = _KeyTable(limit), None, {}, {}
        suffix = getattr(self.tokenizer.model, "end_of_word_suffix", None)
        vocabulary = self.tokenizer.get_vocab(with_added_tokens=True)
        self.closes = np.zeros(max(vocabulary.values()) + 1, bool)
        if suffix:
            self.closes[[i for piece, i in vocabulary.items() if piece.endswith(suffix)]] = True

    def _learn(self, fresh: list[str]) -> list[np.ndarray]:
        """The tokenizer's ids of each chunk."""
        out: list[np.ndarray] = [None] * len(fresh)
        letters, rest = [], []
        for k, c in enumerate(fresh):
            (letters if c.isalpha() and len(c) < 200 else rest).append(k)
        for lo in range(0, len(letters), 256):
            part = letters[lo : lo + 256]
            ids = np.array(self.tokenizer.encode_batch_fast([" ".join([fresh[k] for k in part])], add_special_tokens=False)[0].ids, "<u4")
            cuts = np.flatnonzero(self.closes[ids]) + 1
            if len(cuts) != len(part) or cuts[-1] != len(ids):
                rest += part
                continue
            at = 0
            for k, to in zip(part, cuts.tolist(), strict=True):
                out[k] = ids[at:to]
                at = to
        for k, e in zip(rest, self.tokenizer.encode_batch_fast([fresh[k] for k in rest], add_special_tokens=False), strict=True):
            out[k] = np.array(e.ids, "<u4")
        return out

    def _long(self, chunks: list[bytes]) -> list[np.ndarray]:
        """Ids of chunks that no key holds."""
        if len(self.long) > self.limit // 8:
            self.old_long, self.long = self.long, {}
        table, old = self.long, self.old_long
        fresh = [c for c in dict.fromkeys(chunks) if c not in table and c not in old]
        table.update(zip(fresh, self._learn([c.decode() for c in fresh]), strict=True))
        for c in chunks:
            if c not in table:
                table[c] = old[c]
        return [table[c] for c in chunks]

    def _short(self, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
        """Place and number of each key's ids in the young table, which learns those it lacks."""
        value, known = self.keys.find(lo, hi)
        if known.all():
            return value
        lack = np.flatnonzero(~known)
        lack = lack[np.lexsort((lo[lack], hi[lack]))]
        first = np.ones(len(lack), bool)
        first[1:] = (lo[lack[1:]] != lo[lack[:-1]]) | (hi[lack[1:]] != hi[lack[:-1]])
        new = lack[first]
        if self.keys.words and self.keys.words + len(new) > self.limit:
            # All keys again, as those found were found in the table that is the old one now.
            self.old_keys, self.keys = self.keys, _KeyTable(self.limit)
            return self._short(lo, hi)
        if len(new) > self.limit:
            self.keys = _KeyTable(len(new))
        if self.old_keys is not None:
            kept, old = self.old_keys.find(lo[new], hi[new])
            places, counts = (kept[old] >> np.uint64(8)).astype(np.int64), (kept[old] & np.uint64(255)).astype(np.int64)
            self.keys.add(lo[new[old]], hi[new[old]], counts, _gathered(self.old_keys.arena, places, counts))
            new = new[~old]
        raw = np.column_stack([lo[new], hi[new]]).astype("<u8").tobytes()
        learnt = self._learn([raw[at : at + raw[at + _SHORT]].decode() for at in range(0, len(raw), 16)])
        if learnt:
            self.keys.add(lo[new], hi[new], np.array([*map(len, learnt)], np.int64), np.concatenate(learnt))
        value[lack] = self.keys.find(lo[lack], hi[lack])[0]
        return value

    def _block(self, body: bytes, lower: bytearray, starts: np.ndarray, ends: np.ndarray, special: np.ndarray, wide: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids of the chunks end to end, and how many each has; ``body`` and ``lower`` go on for 16 bytes after the last one.

        ``special`` chunks have a mark of special tokens, ``wide`` ones characters beyond Latin-1.
        """
        raw = np.frombuffer(body, np.uint8)
        cut, tail = ends.copy(), np.flatnonzero(~special)
        for _ in range(3):
            tail = tail[_PUNCT[raw[cut[tail] - 1]]]
            cut[tail] -= 1
            tail = tail[cut[tail] > starts[tail]]
        parted = (cut < ends) & (cut > starts)
        parted &= _ALNUM[raw[cut - 1]] | _LATIN[raw[cut - 1]] & (raw[cut - 2] == 0xC3)
        # The place of each chunk's first part among all parts.
        head = np.arange(len(starts)) + np.cumsum(parted) - parted
        s, e = np.empty(len(starts) + int(parted.sum()), np.int64), np.empty(len(starts) + int(parted.sum()), np.int64)
        s[head], e[head] = starts, np.where(parted, cut, ends)
        s[head[parted] + 1], e[head[parted] + 1] = cut[parted], ends[parted]

        size = e - s
        long = size > _SHORT
        long[head[special]] = True
        masks, tops = _HEAD[np.minimum(size, 8)], _HEAD[np.clip(size - 8, 0, 7)]
        words = np.ndarray(len(lower) - 7, "<u8", lower, 0, (1,))
        lo, hi = words[s] & masks, words[s + 8] & tops
        other = np.flatnonzero((lo | hi) & _TOP) if wide.any() else wide[:0]
        if len(other):
            other = other[wide[np.searchsorted(head, other, "right") - 1]]
            # Beyond Latin-1 a letter can be composed with what follows, so case is left to the tokenizer.
            words = np.ndarray(len(body) - 7, "<u8", body, 0, (1,))
            lo[other], hi[other] = words[s[other]] & masks[other], words[s[other] + 8] & tops[other]
        hi |= size.astype(np.uint64) << np.uint64(56)
        if not long.any():
            value = self._short(lo, hi)
            places, counts = (value >> np.uint64(8)).astype(np.int64), (value & np.uint64(255)).astype(np.int64)
        else:
            places, counts = np.empty(len(s), np.int64), np.empty(len(s), np.int64)
            value = self._short(lo[~long], hi[~long])
            places[~long], counts[~long] = (value >> np.uint64(8)).astype(np.int64), (value & np.uint64(255)).astype(np.int64)
            ids = self._long([body[a:b] for a, b in zip(s[long].tolist(), e[long].tolist(), strict=True)])
            n = np.array([*map(len, ids)], np.int64)
            # Behind the table's own ids, for this block only.
            self.keys.reserve(int(n.sum()))
            self.keys.arena[self.keys.used : self.keys.used + int(n.sum())] = np.concatenate(ids)
            places[long], counts[long] = self.keys.used + np.cumsum(n) - n, n
        return _gathered(self.keys.arena, places, counts), np.add.reduceat(counts, head)

    def encode(self, text: str | None) -> bytes:
        """All ids of the text and the end id, as little-endian unsigned 32-bit integers."""
        return self.encode_all([text])[0]

    def encode_all(self, texts: list[str | None] | pa.Array) -> list[bytes]:
        raw, offsets = text_buffer(texts if isinstance(texts, pa.Array) else pa.array(texts, pa.large_string()))
        starts, ends, before = word_spans(raw, offsets)
        body = raw.tobytes() + bytes(16)
        lower = bytearray(body.translate(_LOWER))
        latin = np.flatnonzero(raw == 0xC3) + 1
        latin = latin[_CAPITAL[np.frombuffer(body, np.uint8)[latin]]]
        np.frombuffer(lower, np.uint8)[latin] += 0x20
        special, wide, at = np.zeros(len(starts), bool), np.zeros(len(starts), bool), body.find(b"<|")
        wide[np.searchsorted(starts, np.flatnonzero(raw >= 0xC4), "right") - 1] = True
        while at >= 0:
            special[np.searchsorted(starts, at, "right") - 1] = True
            at = body.find(b"<|", at + 1)
        ids, counts = [], []
        for lo in range(0, len(starts), _BLOCK_CHUNKS):
            part = slice(lo, lo + _BLOCK_CHUNKS)
            found = self._block(body, lower, starts[part], ends[part], special[part], wide[part])
            ids.append(found[0])
            counts.append(found[1])
        if not ids:
            return [self.end] * (len(offsets) - 1)
        flat = np.concatenate(ids).astype("<u4", copy=False).data.cast("B")
        cuts = (4 * np.cumsum(np.concatenate([[0], *counts]))[before]).tolist()
        return [b"".join((flat[a:b], self.end)) for a, b in zip(cuts, cuts[1:], strict=False)]


_encoders: dict[tuple[str, int], ChunkEncoder] = {}


def encoder(path: str, end_id: int = END_ID) -> ChunkEncoder:
    """This process's encoder, so that a reused Python worker keeps its table from task to task."""
    if (path, end_id) not in _encoders:
        _encoders[path, end_id] = ChunkEncoder(path, end_id)
    return _encoders[path, end_id]


def train_dictionary(samples: list[bytes], size: int = DICTIONARY_BYTES) -> bytes:
    """A zstandard dictionary; where samples are too few to train on, their own bytes."""
    import zstandard

    total = sum(map(len, samples))
    try:
        return zstandard.train_dictionary(min(size, max(1024, total // 8)), samples).as_bytes()
    except zstandard.ZstdError:
        return b"".join(samples)[:size]


def _dictionary(content: bytes):
    import zstandard

    return zstandard.ZstdCompressionDict(content) if content else None


def write_shards(docs: DataFrame, path: str, tokenizer_path: str, end_id: int = END_ID, sample_docs: int = SAMPLE_DOCS, sample_chars: int = SAMPLE_CHARS) -> None:
    """Encode ``docs`` (doc_id, text) and write the shards and their dictionary under ``path``.

    The dictionary is trained on ``sample_docs`` documents, ``sample_chars`` characters of each; every document is encoded whole.
    """
    spark = docs.sparkSession
    docs = docs.select("doc_id", "text")
    # Only ids meet in the top-k; texts of the chosen ones are fetched by a pushed-down filter.
    ids = [r[0] for r in docs.select("doc_id").where("doc_id IS NOT NULL").orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample_docs).collect()]
    sample = docs.where(F.col("doc_id").isin(ids)).select(F.substring("text", 1, sample_chars).alias("text")).limit(sample_docs) if ids else None
    content = train_dictionary(sorted(encoder(tokenizer_path, end_id).encode_all([r[0] for r in sample.collect()]))) if sample is not None else b""
    dict_hash = hashlib.sha256(content).hexdigest()
    spark.createDataFrame([(dict_hash, bytearray(content))], "dict_hash string, content binary").coalesce(1).write.parquet(f"{path}/dictionary")

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import zstandard
        from pyspark import TaskContext

        encode = encoder(tokenizer_path, end_id).encode_all
        squeeze = zstandard.ZstdCompressor(level=1, dict_data=_dictionary(content)).compress
        shard, block, start = TaskContext.get().partitionId(), 0, 0
        ids, counts, frames, held = [], [], [], 0

        def row() -> pa.RecordBatch:
            sizes = np.cumsum([0, *map(len, frames)])
            known = [i for i in ids if i != NULL_ID]
            values = [shard, block, dict_hash, min(known, default=None), max(known, default=None), start, sum(counts), np.array(ids, "<i8").tobytes(), np.array(counts, "<i8").tobytes(), sizes.astype("<i8").tobytes(), b"".join(frames)]
            kinds = [pa.int32(), pa.int32(), pa.string(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), *[pa.binary()] * 4]
            names = [c.split()[0] for c in BLOCKS.split(", ")]
            return pa.RecordBatch.from_arrays([pa.array([v], k) for v, k in zip(values, kinds, strict=True)], names)

        for piece in text_pieces(batches, limit=1 << 20):
            for doc_id, body in zip(piece.column("doc_id").to_pylist(), encode(piece.column("text")), strict=True):
                frames.append(squeeze(body))
                ids.append(NULL_ID if doc_id is None else doc_id)
                counts.append(len(body) // 4)
                held += len(frames[-1])
                if held >= BLOCK_BYTES or len(ids) >= 8192:
                    yield row()
                    block, start = block + 1, start + sum(counts)
                    ids, counts, frames, held = [], [], [], 0
        if ids:
            yield row()

    # By the text's hash too, so that rows of one id, or of none, are not one task's.
    order = F.col("doc_id").asc_nulls_first(), F.xxhash64("text").asc()
    ordered = docs.repartitionByRange(shuffle_width(spark), *order).sortWithinPartitions(*order)
    ordered.mapInArrow(pack, BLOCKS).write.option("compression", "none").parquet(f"{path}/blocks")


def _content(spark: SparkSession, path: str) -> tuple[str, bytes]:
    row = spark.read.parquet(f"{path}/dictionary").head()
    content = bytes(row["content"])
    if hashlib.sha256(content).hexdigest() != row["dict_hash"]:
        raise ValueError("the dictionary does not match its hash")
    return row["dict_hash"], content


def read_shards(spark: SparkSession, path: str, doc_ids: list[int] | None = None) -> DataFrame:
    """Documents of the shards as (doc_id, start, n_tokens, ids binary); with ``doc_ids`` only their frames are opened.

    Blocks without a wanted id are pruned by first_id and last_id in the Parquet scan.
    """
    dict_hash, content = _content(spark, path)
    blocks = spark.read.schema(BLOCKS).parquet(f"{path}/blocks")
    # One row per shard (their number is the number of written partitions), so the running sum and the broadcast are small.
    before = Window.orderBy("shard").rowsBetween(Window.unboundedPreceding, -1)
    bases = blocks.groupBy("shard").agg(F.sum("tokens").alias("tokens")).select("shard", F.coalesce(F.sum("tokens").over(before), F.lit(0)).alias("base"))
    if doc_ids is not None:
        wanted = F.lit(False)
        for i in doc_ids:
            wanted = wanted | ((F.col("first_id") <= i) & (F.col("last_id") >= i))
        blocks = blocks.where(wanted)
    chosen = None if doc_ids is None else set(doc_ids)

    def unpack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import zstandard

        expand = zstandard.ZstdDecompressor(dict_data=_dictionary(content)).decompress
        for batch in batches:
            for r in batch.to_pylist():
                if r["dict_hash"] != dict_hash:
                    raise ValueError("a block was written with another dictionary")
                ids, counts, offsets = (np.frombuffer(r[k], "<i8") for k in ("doc_ids", "n_tokens", "offsets"))
                starts = r["base"] + r["start"] + np.cumsum(counts) - counts
                rows, held = [], 0
                for i, doc_id in enumerate(ids.tolist()):
                    if chosen is None or doc_id in chosen:
                        body = expand(r["payload"][offsets[i] : offsets[i + 1]])
                        rows.append((None if doc_id == NULL_ID else doc_id, int(starts[i]), int(counts[i]), body))
                        held += len(body)
                    if rows and (held > 8 << 20 or i == len(ids) - 1):
                        yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), (pa.int64(), pa.int64(), pa.int64(), pa.binary()), strict=True)], ["doc_id", "start", "n_tokens", "ids"])
                        rows, held = [], 0

    joined = blocks.join(F.broadcast(bases), "shard").select("dict_hash", "base", "start", "doc_ids", "n_tokens", "offsets", "payload")
    return joined.mapInArrow(unpack, "doc_id long, start long, n_tokens long, ids binary")


def checksums(ids: DataFrame) -> DataFrame:
    """The unsigned crc32 of each document's id bytes, JVM-side."""
    return ids.select("doc_id", "start", "n_tokens", F.crc32("ids").alias("ids_crc32"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = new_path(spark, "token-shards")
    write_shards(load(spark, sf_dir, "documents"), path, public_path(TOKENIZER))
    return checksums(read_shards(spark, path))


def brute_force(rows: list[tuple[int, str | None]], tokenizer_path: str) -> list[tuple[int, int, int, int]]:
    """What the query returns, by one whole-text call per document."""
    from tokenizers import Tokenizer

    t, start, out = Tokenizer.from_file(tokenizer_path), 0, []
    for doc_id, text in sorted(rows):
        ids = [*t.encode(text or "", add_special_tokens=False).ids, END_ID]
        out.append((doc_id, start, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes())))
        start += len(ids)
    return out
