"""Near-duplicate groups by b-bit MinHash, with every link confirmed on full shingle sets.

1. Each text's set of word shingles is hashed (64 bits); minima make band keys (``Scheme``: 40 bands of 5 at 80 percent), and two
   bits of each of ``HASHES`` minima, mixed anew, the packed signature. Texts with equal sets (a 128-bit digest) are one representative from here on.
2. First round: in each band bucket every representative is paired with the bucket's smallest. Pairs whose sizes allow the
   threshold and whose bit counts, corrected for chance collisions, come within five deviations of it are confirmed on full
   sets; connected components of the confirmed links follow. This folds a large group of copies with one pair a member.
3. Second round: a bucket that still holds several components gives the forest of its best estimated pairs between them, one
   pair a member at most, which finds the text that others were copied from wherever it is. Confirmed links join components.
4. Third round: all pairs of different components that are left in a bucket are looked at, each in the first bucket it shares;
   full sets go to the buckets where a pair passes the filter, and only links come out. Nothing is capped: only pairs
   already in one component are passed over.

Buckets are worked on in pairs of blocks of ``BLOCK`` members, each a unit of its own. Members of a bucket's largest component
are never paired with each other, so that a bucket of one large group and a few others costs in proportion to its size. Bands
and the least bit count follow from the threshold: a link at it shares no band with probability ``MISS`` at most and fails the
bit count with 3e-7.

Nulls and edges: a text without words, or null, has an empty set and is linked with nothing; one with fewer words than a shingle
has its whole sequence as one; a null doc_id is linked with nothing and kept; rows that repeat a doc_id are one document with
the links of all its texts, kept or dropped together; other columns are ignored by ``groups`` and pass ``deduplicated``; an
empty table gives an empty result; a percentage outside 30 to 100 is refused.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import load, mix64, pack_ints, quoted, shuffle_width, span_hashes, stored, text_buffer, text_pieces, unpack_ints, window_hashes, word_spans

PERCENT, HASHES, MISS, MOST_ROWS = 80, 1024, 1.4e-7, 25
PER_LONG, LOW_BITS = 32, 0x5555555555555555
BLOCK = 256
_RNG = np.random.Generator(np.random.PCG64(4242))
_ODD = _RNG.integers(0, 2**31, HASHES, dtype=np.uint32) * np.uint32(2) + np.uint32(1)
_MIX = _RNG.integers(0, 2**63, MOST_ROWS, dtype=np.uint64) * np.uint64(2) + np.uint64(1)


@dataclass(frozen=True)
class Scheme:
    """What follows from a threshold in percent: rows a band, bands, and the equal entries that a link has at least.

    Rows are as many as leave a pair at the threshold a chance of a third to share a band; then bands for ``MISS``. Equal
    two-bit entries are binomial with mean 1/4 + 3/4 of the similarity; five deviations below that are allowed.
    """

    percent: int = PERCENT

    def __post_init__(self) -> None:
        if not 30 <= self.percent <= 100:
            raise ValueError("percent is from 30 to 100")

    @property
    def rows(self) -> int:
        s = self.percent / 100
        return MOST_ROWS if s == 1 else min(MOST_ROWS, max(2, int(math.log(0.326) / math.log(s))))

    @property
    def bands(self) -> int:
        s = self.percent / 100
        return 1 if s == 1 else math.ceil(math.log(MISS) / math.log1p(-(s**self.rows)))

    @property
    def least_equal(self) -> int:
        p = 1 / 4 + 3 / 4 * self.percent / 100
        return math.floor(HASHES * p - 5 * math.sqrt(HASHES * p * (1 - p)))

    @property
    def least_similarity(self) -> float:
        return (self.least_equal / HASHES - 1 / 4) / (3 / 4)


def shingle_sets(batch: pa.RecordBatch, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct shingle hashes of each row, end to end, and where each row's begin (one more than rows)."""
    raw, offsets = text_buffer(batch.column("text"))
    starts, ends, first = word_spans(raw, offsets)
    words = span_hashes(raw, starts, ends, lower=True)
    windows = window_hashes(words, width)
    sets = []
    for a, b in zip(first[:-1].tolist(), first[1:].tolist(), strict=True):
        if b - a >= width:
            s = np.sort(windows[a : b - width + 1])
            sets.append(s[np.concatenate([[True], s[1:] != s[:-1]])])
        elif b > a:
            sets.append(mix64(np.array([window_hashes(words[a:b], b - a)[0] ^ np.uint64(b - a)], np.uint64)))
        else:
            sets.append(np.zeros(0, np.uint64))
    return (np.concatenate(sets) if sets else np.zeros(0, np.uint64)), np.cumsum([0, *map(len, sets)])


def two_bits(least: np.ndarray, k: int) -> np.ndarray:
    """The signature's entries for the minima of hash ``k``. An odd factor leaves agreement modulo 4 as it is, so that bits of a
    minimum itself would collide by chance in all hashes or in none: they are taken after mixing, with the hash's number."""
    return mix64(least | np.uint64(k << 32)) & np.uint64(3)


def signatures(docs: DataFrame, width: int, scheme: Scheme) -> DataFrame:
    """(doc_id, n, d1, d2, bands, signature) of every text; arrays are empty for empty sets."""
    n_bands, n_rows = scheme.bands, scheme.rows

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for piece in text_pieces(batches, limit=4 << 20):
            values, cuts = shingle_sets(piece, width)
            sizes = np.diff(cuts)
            has = np.flatnonzero(sizes)
            d = np.zeros((2, len(sizes)), np.uint64)
            bands = np.zeros((len(has), n_bands), np.uint64)
            packed = np.zeros((len(has), HASHES // PER_LONG), np.uint64)
            if len(has):
                begins = cuts[:-1][has]
                d[0, has] = np.add.reduceat(mix64(values ^ np.uint64(0x51ED270B)), begins)
                d[1, has] = np.add.reduceat(mix64(values ^ np.uint64(0xC3A5C85C97CB3127)), begins)
                short = (values >> np.uint64(32)).astype(np.uint32)
                turned = np.empty_like(short)
                for k in range(HASHES):
                    np.multiply(short, _ODD[k], out=turned)
                    least = np.minimum.reduceat(turned, begins).astype(np.uint64)
                    if k < n_bands * n_rows:
                        bands[:, k // n_rows] += least * _MIX[k % n_rows]
                    packed[:, k // PER_LONG] |= two_bits(least, k) << np.uint64(2 * (k % PER_LONG))
                bands = mix64(bands + np.arange(n_bands, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15))

            def arrays(x: np.ndarray, per: int, sizes: np.ndarray = sizes) -> pa.Array:
                ends = np.cumsum(np.concatenate([[0], np.where(sizes > 0, per, 0)])).astype(np.int32)
                return pa.ListArray.from_arrays(pa.array(ends), pa.array(x.reshape(-1).view(np.int64)))

            yield pa.RecordBatch.from_arrays([piece.column("doc_id"), pa.array(sizes.astype(np.int64)), pa.array(d[0].view(np.int64)), pa.array(d[1].view(np.int64)), arrays(bands, n_bands), arrays(packed, HASHES // PER_LONG)], ["doc_id", "n", "d1", "d2", "bands", "signature"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, n long, d1 long, d2 long, bands array<long>, signature array<long>")


def equal_entries(a: str, b: str) -> F.Column:
    """Number of equal two-bit entries of two packed signatures, by bit counts."""

    def differing(x: F.Column, y: F.Column) -> F.Column:
        z = x.bitwiseXOR(y)
        return F.bit_count(z.bitwiseOR(F.shiftrightunsigned(z, 1)).bitwiseAND(F.lit(LOW_BITS)))

    return F.lit(HASHES) - F.aggregate(F.zip_with(a, b, differing), F.lit(0), lambda acc, x: acc + x)


def similarity(equal: F.Column) -> F.Column:
    """Jaccard similarity estimated from equal two-bit entries, corrected for chance collisions."""
    return F.greatest(F.lit(0.0), (equal / F.lit(float(HASHES)) - 1 / 4) / (1 - 1 / 4))


def components(links: DataFrame) -> DataFrame:
    """(node, component): the smallest node that each end of a link reaches. ``links``: a, b.

    Large-star and small-star steps in turn; every step is a grouped minimum and a join, so that a hub is combined
    before it is shuffled and split after, and is written to the shared folder.
    """

    def least(pairs: DataFrame) -> DataFrame:
        return pairs.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))

    def state(edges: DataFrame) -> tuple:
        return tuple(edges.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(20,0)"))).head())

    edges = stored(links.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u <> v").distinct(), "stars")
    seen = state(edges)
    while seen[0]:
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        large = both.join(least(both), "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        small = large.join(least(large), "u").select(F.explode(F.array(F.struct(F.col("v").alias("u"), F.col("m").alias("v")), F.struct("u", F.col("m").alias("v")))).alias("e")).select("e.u", "e.v").where("u <> v").distinct()
        edges = stored(small, "stars")
        now = state(edges)
        if now == seen:
            break
        seen = now
    nodes = edges.select(F.col("u").alias("node"), F.col("v").alias("component"))
    return nodes.unionByName(edges.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct())


def full_sets(docs: DataFrame, ids: DataFrame, width: int) -> DataFrame:
    """(rep, shingles) of the documents with these ids: 48-bit hashes, packed. Texts go through the join compressed."""

    def shrink(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import zstandard

        squeeze = zstandard.ZstdCompressor(level=3).compress
        for piece in text_pieces(batches):
            yield pa.RecordBatch.from_arrays([piece.column("doc_id"), pa.array([squeeze((t or "").encode()) for t in piece.column("text").to_pylist()], pa.binary())], ["doc_id", "body"])

    def expand(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import zstandard

        whole = zstandard.ZstdDecompressor().decompress
        for batch in batches:
            for lo in range(0, batch.num_rows, 512):
                part = batch.slice(lo, 512)
                texts = pa.array([whole(x).decode() for x in part.column("body").to_pylist()], pa.large_string())
                values, cuts = shingle_sets(pa.RecordBatch.from_arrays([texts], ["text"]), width)
                short = (values >> np.uint64(16)).view(np.int64)
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.array([pack_ints(short[a:b]) for a, b in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True)], pa.binary())], ["rep", "shingles"])

    packed = docs.select("doc_id", "text").where("doc_id IS NOT NULL").mapInArrow(shrink, "doc_id long, body binary")
    return packed.join(ids.select(F.col("rep").alias("doc_id")), "doc_id", "left_semi").mapInArrow(expand, "rep long, shingles binary")


def confirmed(pairs: DataFrame, sets: DataFrame, percent: int = PERCENT) -> DataFrame:
    """The pairs (a, b) whose full sets have the similarity."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        opened: dict[bytes, np.ndarray] = {}  # by the packed set itself: an id may come with several
        for batch in batches:
            keep = []
            for a, b, x, y in zip(*(batch.column(c).to_pylist() for c in ("a", "b", "sa", "sb")), strict=True):
                if len(opened) > 256:
                    opened.clear()
                s, t = (opened.setdefault(z, unpack_ints(z)) if z not in opened else opened[z] for z in (x, y))
                both = len(np.intersect1d(s, t, assume_unique=True))
                keep.append(100 * both >= percent * (len(s) + len(t) - both))
            yield batch.select(["a", "b"]).filter(pa.array(keep, pa.bool_()))

    j = pairs.select("a", "b").join(sets.select(F.col("rep").alias("a"), F.col("shingles").alias("sa")), "a").join(sets.select(F.col("rep").alias("b"), F.col("shingles").alias("sb")), "b")
    return j.select("a", "b", "sa", "sb").mapInArrow(run, "a long, b long")


def _promising(scheme: Scheme) -> F.Column:
    """Pairs whose sizes allow the threshold and whose estimated similarity is not too far below it."""
    sizes = F.least("na", "nb") * 100 >= F.greatest("na", "nb") * scheme.percent
    return sizes & (similarity(equal_entries("sa", "sb")) >= scheme.least_similarity - 1e-9)


def _forest(a: np.ndarray, b: np.ndarray, equal: np.ndarray, component: dict[int, int]) -> list[int]:
    """Places of the pairs, best estimate first, that join parts not joined before."""
    above: dict[int, int] = {}

    def top(x: int) -> int:
        while above.get(x, x) != x:
            above[x] = x = above.get(above[x], above[x])
        return x

    out = []
    for k in np.lexsort((b, a, -equal)).tolist():
        x, y = top(component[int(a[k])]), top(component[int(b[k])])
        if x != y:
            above[x] = y
            out.append(k)
    return out


UNIT = "key bigint, i int, j int, own int, least_rep bigint, rep bigint, component bigint, n bigint, signature array<bigint>, bands array<bigint>"


def _units(rows: DataFrame) -> DataFrame:
    """Bucket rows (key, members, largest, of_largest, least_rep, rep, component, n, signature, bands) dealt to units (key, i, j).

    A unit has two blocks of members at most. Blocks 0 to ``first`` - 1 are of the largest component and meet other blocks only.
    """
    most = F.lit(float(BLOCK))
    rows = rows.withColumn("first", F.ceil(F.col("of_largest") / most).cast("int")).withColumn("blocks", F.col("first") + F.ceil((F.col("members") - F.col("of_largest")) / most).cast("int"))
    inside = F.col("component") == F.col("largest")
    own = F.when(inside, F.pmod(F.xxhash64("rep"), F.col("first"))).otherwise(F.col("first") + F.pmod(F.xxhash64("rep"), F.col("blocks") - F.col("first"))).cast("int")
    rows = rows.withColumn("own", own).withColumn("start", F.when(inside, F.col("first")).otherwise(F.lit(0)))
    rows = rows.withColumn("unit", F.explode(F.transform(F.sequence(F.col("start"), F.col("blocks") - 1), lambda j: F.struct(F.least(j, F.col("own")).alias("i"), F.greatest(j, F.col("own")).alias("j")))))
    return _dealt(rows.select("key", "unit.i", "unit.j", "own", "least_rep", "rep", "component", "n", "signature", "bands"))


def _dealt(rows: DataFrame) -> DataFrame:
    return rows.repartition(shuffle_width(rows.sparkSession), "key", "i", "j").sortWithinPartitions("key", "i", "j")


def _each_unit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.Table]:
    held: list[pa.RecordBatch] = []
    now = None
    for batch in batches:
        unit = np.stack([batch.column(c).to_numpy(zero_copy_only=False).astype(np.int64) for c in ("key", "i", "j")])
        cut = [0, *(np.flatnonzero((unit[:, 1:] != unit[:, :-1]).any(axis=0)) + 1).tolist(), batch.num_rows]
        for lo, hi in zip(cut, cut[1:], strict=False):
            if hi == lo:
                continue
            this = tuple(unit[:, lo].tolist())
            if this != now and held:
                yield pa.Table.from_batches(held)
                held = []
            now = this
            held.append(batch.slice(lo, hi - lo))
    if held:
        yield pa.Table.from_batches(held)


def _candidates(t: pa.Table, scheme: Scheme) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Pairs of a unit's rows, as places, of different components that pass the filter and share no earlier band; equal entries."""
    key, i, j = (t[c][0].as_py() for c in ("key", "i", "j"))
    own, least, rep, comp, n = (t[c].to_numpy() for c in ("own", "least_rep", "rep", "component", "n"))
    sig, bands = (t[c].combine_chunks().flatten().to_numpy(zero_copy_only=False).view(np.uint64).reshape(len(rep), -1) for c in ("signature", "bands"))
    out = [np.zeros((3, 0), np.int64)]
    for k in range(len(rep)):
        others = np.flatnonzero((comp != comp[k]) & (rep > rep[k]) & ((own != own[k]) if i != j else True) & (100 * np.minimum(n, n[k]) >= scheme.percent * np.maximum(n, n[k])))
        if rep[k] == least[k] or not len(others):
            continue  # the smallest has been paired with all others in the first round
        z = sig[others] ^ sig[k]
        equal = HASHES - np.bitwise_count((z | (z >> np.uint64(1))) & np.uint64(LOW_BITS)).sum(axis=1, dtype=np.int64)
        near = equal >= scheme.least_equal
        others, equal = others[near], equal[near]
        if len(others):
            same = bands[others] == bands[k]
            first = bands[k][same.argmax(axis=1)].view(np.int64) == key
            out.append(np.stack([np.full(int(first.sum()), k), others[first], equal[first]]))
    a, b, equal = np.concatenate(out, axis=1)
    return a, b, equal


def _best_left(units: DataFrame, scheme: Scheme) -> DataFrame:
    """The best candidate pairs (a, b) that would leave no unit in parts."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in _each_unit(batches):
            a, b, equal = _candidates(t, scheme)
            if len(a):
                rep, comp = t["rep"].to_numpy(), t["component"].to_numpy()
                chosen = _forest(rep[a], rep[b], equal, dict(zip(rep.tolist(), comp.tolist(), strict=True)))
                yield pa.RecordBatch.from_arrays([pa.array(rep[a[chosen]]), pa.array(rep[b[chosen]])], ["a", "b"])

    return units.mapInArrow(run, "a long, b long").distinct()


def _links_left(units: DataFrame, sets: DataFrame, scheme: Scheme) -> DataFrame:
    """Links (a, b) among all candidate pairs of the units, tested on full sets inside each unit."""

    def those_with_pairs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in _each_unit(batches):
            a, b, _ = _candidates(t, scheme)
            if len(a):
                yield from t.take(pa.array(np.unique(np.concatenate([a, b])))).combine_chunks().to_batches()

    def test(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for t in _each_unit(batches):
            a, b, _ = _candidates(t, scheme)
            rep, packed, opened, out = t["rep"].to_numpy(), t["shingles"], {}, []
            for x, y in zip(a.tolist(), b.tolist(), strict=True):
                for k in (x, y):
                    if k not in opened:
                        opened[k] = unpack_ints(packed[k].as_py())
                both = len(np.intersect1d(opened[x], opened[y], assume_unique=True))
                if 100 * both >= scheme.percent * (len(opened[x]) + len(opened[y]) - both):
                    out.append((rep[x], rep[y]))
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*out, strict=True)], ["a", "b"])

    some = units.mapInArrow(those_with_pairs, UNIT)
    return _dealt(some.join(sets, "rep").select(*some.columns, "shingles")).mapInArrow(test, "a long, b long")


def _one_id(full: DataFrame, reps: DataFrame) -> DataFrame:
    """Links (a, b) between the sets of rows that repeat a doc_id with other texts; none where doc_id is a key."""
    sets = F.struct("d1", "d2", "n")
    twice = full.groupBy("doc_id").agg(F.min(sets).alias("s0"), F.max(sets).alias("s1")).where("s0 <> s1").select("doc_id")
    own = full.select("doc_id", "d1", "d2", "n").join(twice, "doc_id").join(reps.select("d1", "d2", "n", "rep"), ["d1", "d2", "n"])
    return own.select(F.col("doc_id").alias("a"), F.col("rep").alias("b"))


def groups(docs: DataFrame, width: int = 5, percent: int = PERCENT) -> DataFrame:
    """(doc_id, n_shingles, component_id, kept) of every row of ``docs`` (doc_id, text)."""
    scheme = Scheme(percent)
    light = stored(signatures(docs, width, scheme), "signatures")
    full = light.where("n > 0 AND doc_id IS NOT NULL")
    reps = stored(full.groupBy("d1", "d2", "n").agg(F.min("doc_id").alias("rep"), F.count(F.lit(1)).alias("copies"), F.any_value("bands").alias("bands"), F.any_value("signature").alias("signature")), "representatives")
    rows = reps.select("rep", F.explode("bands").alias("key"))
    keys = rows.groupBy("key").agg(F.min("rep").alias("least_rep"), F.count(F.lit(1)).alias("members")).where("members > 1")
    shared = stored(rows.join(keys, "key"), "buckets")
    facts = reps.select("rep", "n", "signature", "bands")

    def side(x: str) -> DataFrame:
        return reps.select(F.col("rep").alias(x), F.col("n").alias(f"n{x}"), F.col("signature").alias(f"s{x}"))

    stars = shared.where("rep <> least_rep").select(F.col("least_rep").alias("a"), F.col("rep").alias("b")).distinct()
    first = stored(stars.join(side("a"), "a").join(side("b"), "b").where(_promising(scheme)).select("a", "b"), "pairs")
    sets = stored(full_sets(docs, shared.select("rep").distinct(), width), "shingle-sets")
    links = stored(confirmed(first, sets, percent).unionByName(_one_id(full, reps)), "links-1")
    found = stored(components(links), "components-1")

    for last in (False, True):
        labelled = shared.select("key", "least_rep", "rep").join(found.select(F.col("node").alias("rep"), "component"), "rep", "left").withColumn("component", F.coalesce("component", "rep"))
        parts = labelled.groupBy("key", "component").agg(F.count(F.lit(1)).alias("k")).groupBy("key").agg(F.max(F.struct("k", "component")).alias("top"), F.sum("k").alias("members"), F.count(F.lit(1)).alias("parts"))
        open_ = parts.where("parts > 1").select("key", F.col("top.component").alias("largest"), F.col("top.k").alias("of_largest"), "members")
        units = _units(labelled.join(open_, "key").join(facts, "rep"))
        links = stored(_links_left(units, sets, scheme) if last else confirmed(_best_left(units, scheme), sets, percent), "links")
        if links.head(1):
            found = stored(components(found.select(F.col("node").alias("a"), F.col("component").alias("b")).unionByName(links)), "components")

    # A set's component, for sets that have copies or links; all other documents are their own.
    of_set = reps.join(found.select(F.col("node").alias("rep"), "component"), "rep", "left").where("copies > 1 OR component IS NOT NULL").select("d1", "d2", F.col("n").alias("m"), F.coalesce("component", "rep").alias("component_id"))
    out = light.select("doc_id", "n", "d1", "d2").join(of_set, (light["d1"] == of_set["d1"]) & (light["d2"] == of_set["d2"]) & (light["n"] == of_set["m"]) & (light["n"] > 0) & light["doc_id"].isNotNull(), "left")
    component = F.coalesce("component_id", "doc_id")
    return out.select("doc_id", F.col("n").alias("n_shingles"), component.alias("component_id"), F.coalesce(component == F.col("doc_id"), F.lit(True)).alias("kept"))


def deduplicated(docs: DataFrame, width: int = 5, percent: int = PERCENT) -> DataFrame:
    """One document of each group, the one with the smallest doc_id, in the columns of ``docs``."""
    gone = groups(docs, width, percent).where("NOT kept").select("doc_id").distinct()
    return docs.join(gone, "doc_id", "left_anti").select(*map(quoted, docs.columns))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return groups(load(spark, sf_dir, "documents").select("doc_id", "text"), width=2)


ORACLE = """
WITH RECURSIVE d AS (SELECT doc_id, list_filter(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[ \\t\\n\\x0b\\f\\r]+'), lambda x: x <> '') AS w FROM documents),
g AS (SELECT doc_id, CASE WHEN len(w) = 0 THEN [] WHEN len(w) = 1 THEN [w[1]] ELSE list_distinct(list_transform(range(1, len(w)), lambda i: w[i] || ' ' || w[i + 1])) END AS s FROM d),
e AS (SELECT doc_id, len(s) AS n, unnest(s) AS x FROM g),
p AS (SELECT a.doc_id AS a, b.doc_id AS b FROM e a JOIN e b ON a.x = b.x AND a.doc_id <> b.doc_id GROUP BY a.doc_id, b.doc_id, a.n, b.n HAVING 100 * count(*) >= 80 * (a.n + b.n - count(*))),
r AS (SELECT doc_id AS node, doc_id AS seen FROM d UNION SELECT r.node, p.b FROM r JOIN p ON p.a = r.seen),
c AS (SELECT node, min(seen) AS component_id FROM r GROUP BY node)
SELECT g.doc_id, len(s)::BIGINT AS n_shingles, component_id, component_id = g.doc_id AS kept FROM g JOIN c ON c.node = g.doc_id
"""
