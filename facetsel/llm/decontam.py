"""Benchmark decontamination by spaced seeds.

A mask names positions of a short window of words that count; the others are ignored, so a hit survives substitutions
there. Hashes of all masked windows of the benchmark are looked up for every window of every document; around a hit the
two texts are laid side by side, and the overlap counts if some stretch of WINDOW words (the whole item where it is
shorter) agrees in at least AGREE of its words.

The masks are chosen so that every stretch that counts holds a seed, wherever its changed words are: a test enumerates
the patterns.

The benchmark is a query set. Up to BLOCK_ITEMS items, by a count, their seeds are broadcast and looked up where the
documents lie. Beyond that the seeds of both sides are joined by hash in one pass over the documents; each seed carries the
words around it, by which chance meetings are turned away before a text moves, and the pairs left are verified on their
whole texts. Both ways give the same rows.

Defined results: words are runs without white space, in lower case, without ASCII punctuation; null and empty texts and
items of fewer than SHORTEST words match nothing; a null id stays null. Repeated
rows give repeated results; other columns are ignored.
"""

from __future__ import annotations

import string
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from facetsel.llm.common import given_id, ship, small, staged, table, whole_id

#: Of thirteen words two may differ: wherever they lie, one of these masks fits beside them.
MASKS = ("1111011", "111010011")
#: For items of fewer than WINDOW words, of which one in five may differ.
SHORT_MASKS = ("1101", "1011")
WINDOW, AGREE, SHORTEST = 13, 0.8, 4
BLOCK_ITEMS = 20_000
#: The bitmap of a large benchmark's seeds has at most so many address bits: 64 MB as the workers hold it.
MOST_BITS = 26
#: Rows of an Arrow batch of seeds.
FLUSH = 10_000
_DROP = string.punctuation.encode()
_STEP = np.array([(0x9E3779B97F4A7C15 * (2 * i + 1)) & (2**64 - 1) for i in range(64)], np.uint64)


class _WordIds(dict):
    def __missing__(self, word: bytes) -> int:
        if len(self) > 1_000_000:
            self.clear()
        out = self[word] = xxhash.xxh3_64_intdigest(word) | 1
        return out


_IDS = _WordIds()


def word_ids(text: str | None) -> np.ndarray:
    words = (text or "").encode("utf-8", "surrogatepass").lower().translate(None, _DROP).split()
    return np.fromiter(map(_IDS.__getitem__, words), np.uint64, len(words))


def _offsets(mask: str) -> list[int]:
    return [i for i, c in enumerate(mask) if c == "1"]


def seeds(ids: np.ndarray, offsets: list[int], salt: int) -> np.ndarray:
    """A hash for each window; windows start at each word at which a whole window fits."""
    n = len(ids) - offsets[-1]
    if n <= 0:
        return np.zeros(0, np.uint64)
    h = np.full(n, salt + 1, np.uint64)
    for k, o in enumerate(offsets):
        h += ids[o : o + n] * _STEP[k]
    h ^= h >> np.uint64(29)
    h *= np.uint64(0xBF58476D1CE4E5B9)
    return h ^ (h >> np.uint64(32))


@dataclass
class SeedIndex:
    """Sorted seed hashes of a block of items, with the item and place of each; a bitmap of them turns most windows away."""

    items: list[tuple[int, np.ndarray]]
    shapes: list[list[int]] = field(default_factory=list)
    hashes: list[np.ndarray] = field(default_factory=list)
    owners: list[np.ndarray] = field(default_factory=list)
    bits: int = 20

    def __post_init__(self):
        self.shapes = [_offsets(m) for m in (*MASKS, *SHORT_MASKS)]
        for salt, offsets in enumerate(self.shapes):
            h, own = [], []
            for i, (_, x) in enumerate(self.items):
                if len(x) >= WINDOW if salt < len(MASKS) else SHORTEST <= len(x) < WINDOW:
                    got = seeds(x, offsets, salt)
                    h.append(got)
                    own.append(np.stack([np.full(len(got), i), np.arange(len(got))], 1))
            h = np.concatenate(h) if h else np.zeros(0, np.uint64)
            own = np.concatenate(own) if own else np.zeros((0, 2), np.int64)
            order = np.argsort(h, kind="stable")
            self.hashes.append(h[order])
            self.owners.append(own[order])
        total = sum(map(len, self.hashes))
        self.bits = max(16, min(26, int(total * 16).bit_length()))
        self.bitmap = np.zeros(1 << self.bits, bool)
        for h in self.hashes:
            self.bitmap[h >> np.uint64(64 - self.bits)] = True

    def diagonals(self, ids: np.ndarray) -> set[tuple[int, int]]:
        """(item, document position of the item's first word) of every seed hit."""
        found = set()
        for salt, offsets in enumerate(self.shapes):
            h = seeds(ids, offsets, salt) if len(self.hashes[salt]) else ()
            at = np.flatnonzero(self.bitmap[h >> np.uint64(64 - self.bits)]) if len(self.hashes[salt]) else ()
            if len(at):
                lo = np.searchsorted(self.hashes[salt], h[at], "left")
                hi = np.searchsorted(self.hashes[salt], h[at], "right")
                for p, a, b in zip(at[hi > lo], lo[hi > lo], hi[hi > lo], strict=True):
                    for i, q in self.owners[salt][a:b]:
                        found.add((int(i), int(p) - int(q)))
        return found

    def overlaps(self, text: str | None) -> list[tuple[int, int, int, int]]:
        """(item_id, first word in the document, words compared, words equal) of the best stretch with each item."""
        ids, best = word_ids(text), {}
        for i, d in self.diagonals(ids):
            item_id, item = self.items[i]
            got = stretch(ids, item, d)
            if got and (item_id not in best or (got[2], -got[0]) > (best[item_id][2], -best[item_id][0])):
                best[item_id] = got
        return [(k, *best[k]) for k in sorted(best)]


def stretch(ids: np.ndarray, item: np.ndarray, d: int) -> tuple[int, int, int] | None:
    """(first word in the document, words compared, words equal) of what agrees where the item's first word lies at d."""
    lo, hi = max(0, -d), min(len(item), len(ids) - d)
    w = min(WINDOW, len(item))
    if hi - lo < w:
        return None
    equal = item[lo:hi] == ids[lo + d : hi + d]
    sums = np.cumsum(np.concatenate([[0], equal]))
    good = np.flatnonzero(sums[w:] - sums[:-w] >= AGREE * w)
    if not len(good):
        return None
    a, b = int(good[0]), int(good[-1]) + w
    a, b = (x := np.flatnonzero(equal[a:b]))[0] + a, x[-1] + a + 1
    return int(lo + d + a), int(b - a), int(sums[b] - sums[a])


def item_blocks(benchmark: DataFrame, key: str, text: str, block: int) -> Iterator[SeedIndex]:
    """Blocks of items, streamed to the driver one at a time."""
    held: list[tuple[int, np.ndarray]] = []
    for r in benchmark.select(key, text).where(F.col(key).isNotNull()).toLocalIterator():
        held.append((r[0], word_ids(r[1])))
        if len(held) == block:
            yield SeedIndex(held)
            held = []
    if held:
        yield SeedIndex(held)


HITS = "doc_id long, item_id long, first_word long, n_words long, n_equal long"
SEEDS = "id long, seed long, at int, around array<long>"


def _seeded(rows: DataFrame, items: bool, bits: int = 0, bitmap=None) -> DataFrame:
    """(id, seed, at, around) of rows (k, t): each seed with the place of its window and the words of the WINDOW - 1 places
    before it and of those from it on, zeros beyond the text; of documents only seeds that the bitmap knows."""

    def batch(held: list[tuple[int, np.ndarray, np.ndarray, np.ndarray]]) -> pa.RecordBatch:
        around = np.concatenate([x[3] for x in held])
        ends = np.arange(0, around.size + 1, around.shape[1], dtype=np.int32)
        lists = pa.ListArray.from_arrays(pa.array(ends), pa.array(around.ravel().view(np.int64)))
        at, seed = np.concatenate([x[2] for x in held]), np.concatenate([x[1] for x in held])
        ids = np.concatenate([np.full(len(x[2]), x[0], np.int64) for x in held])
        return pa.RecordBatch.from_arrays([pa.array(ids), pa.array(seed.view(np.int64)), pa.array(at.astype(np.int32)), lists], ["id", "seed", "at", "around"])

    def told(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shapes, reach = [_offsets(m) for m in (*MASKS, *SHORT_MASKS)], WINDOW - 1
        held, n = [], 0
        for b in batches:
            for k, t in zip(b["k"], b["t"], strict=True):
                ids = word_ids(t.as_py())
                views = np.lib.stride_tricks.sliding_window_view(np.pad(ids, (reach, WINDOW)), reach + WINDOW)
                for salt, offsets in enumerate(shapes):
                    if items and not (len(ids) >= WINDOW if salt < len(MASKS) else SHORTEST <= len(ids) < WINDOW):
                        continue
                    h = seeds(ids, offsets, salt)
                    at = np.arange(len(h)) if items else np.flatnonzero(bitmap.value[h >> np.uint64(64 - bits)])
                    for part in np.split(at, range(FLUSH, len(at), FLUSH)):
                        held.append((k.as_py(), h[part], part, views[part]))
                        n += len(part)
                        if n >= FLUSH:
                            yield batch(held)
                            held, n = [], 0
        if n:
            yield batch(held)

    return rows.mapInArrow(told, SEEDS)


def _promising(a: pd.Series, b: pd.Series) -> pd.Series:
    """Whether the words around two equal seeds agree enough in some window that holds the seed's first word. Zeros are
    beyond an end and equal nothing; items shorter than a window have fewer words to agree in."""
    x, y = np.stack(a.to_numpy()), np.stack(b.to_numpy())
    sums = np.cumsum(np.pad((x == y) & (x != 0), ((0, 0), (1, 0))), axis=1)
    best = (sums[:, WINDOW:] - sums[:, :-WINDOW]).max(axis=1)
    return pd.Series(best >= AGREE * np.minimum(WINDOW, (y != 0).sum(axis=1)))


def _bitmap_of(seeded: DataFrame, bits: int) -> np.ndarray:
    """One bit in 2^bits for each seed; at most 2^bits / 64 words come to the driver, whatever the number of seeds."""
    top = F.shiftrightunsigned("seed", 64 - bits)
    words = seeded.select(F.shiftright(top, 6).alias("w"), F.expr("shiftleft(1L, cast(shiftrightunsigned(seed, %d) & 63 as int))" % (64 - bits)).alias("v"))
    out = np.zeros(1 << (bits - 6), np.uint64)
    for r in words.groupBy("w").agg(F.bit_or("v").alias("v")).toLocalIterator():
        out[r.w] = np.uint64(r.v & (2**64 - 1))
    return np.unpackbits(out.view(np.uint8), bitorder="little").astype(bool)


def _by_join(docs: DataFrame, items: DataFrame) -> DataFrame:
    """HITS of documents and items (k, t), by a join of their seeds."""
    spark = docs.sparkSession
    known = staged(_seeded(items, True), "benchmark-seeds")
    bits = max(16, min(MOST_BITS, int(known.count() * 16).bit_length()))
    sent = spark.sparkContext.broadcast(_bitmap_of(known, bits))
    found = _seeded(docs, False, bits, sent).join(known.select(F.col("id").alias("item_id"), "seed", F.col("at").alias("q"), F.col("around").alias("other")), "seed")
    promising = F.pandas_udf(_promising, "boolean")
    pairs = found.where(promising("around", "other")).select(F.col("id").alias("doc_id"), "item_id", (F.col("at") - F.col("q")).alias("d")).distinct()
    pairs = staged(pairs.groupBy("doc_id", "item_id").agg(F.collect_set("d").alias("ds")), "benchmark-pairs")

    def verified(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            rows = []
            for k, i, ds, t, u in zip(b["doc_id"], b["item_id"], b["ds"], b["t"], b["u"], strict=True):
                ids, item = word_ids(t), word_ids(u)
                got = [x for x in (stretch(ids, item, int(d)) for d in ds) if x]
                if got:
                    rows.append((k, i, *max(got, key=lambda x: (x[2], -x[0]))))
            yield pd.DataFrame(rows, columns=["doc_id", "item_id", "first_word", "n_words", "n_equal"])

    texts = pairs.join(items.select(F.col("k").alias("item_id"), F.col("t").alias("u")), "item_id")
    return docs.select(F.col("k").alias("doc_id"), "t").join(texts, "doc_id").mapInPandas(verified, HITS)


def leaks(docs: DataFrame, benchmark: DataFrame, text: str = "text", key: str = "doc_id", item_key: str = "item_id", item_text: str = "text", block: int = BLOCK_ITEMS) -> DataFrame:
    """(doc_id, item_id, first_word, n_words, n_equal) for every document and item that overlap. Items beyond the number
    block are met by a join, for which the ids of documents and of items must each tell their rows apart, but for nulls:
    rows without an id, and those of an id that repeats, are numbered first."""
    spark = docs.sparkSession
    ship(spark)
    rows = docs.select(whole_id(key).alias("k"), F.col(text).alias("t"))
    items = benchmark.where(F.col(item_key).isNotNull())
    if len(items.select(item_key).take(block + 1)) > block:
        numbered = staged(rows.select("k", F.monotonically_increasing_id().alias("n"), "t"), "numbered-documents")
        asked = staged(items.select(F.col(item_key).alias("i"), F.monotonically_increasing_id().alias("n"), F.col(item_text).alias("t")), "numbered-items")
        found = _by_join(numbered.select(F.col("n").alias("k"), "t"), asked.select(F.col("n").alias("k"), "t"))
        found = found.join(asked.select(F.col("n").alias("item_id"), "i"), "item_id").drop("item_id").join(numbered.select(F.col("n").alias("doc_id"), "k"), "doc_id")
        best = found.groupBy(F.col("doc_id").alias("n"), "k", "i").agg(F.max_by(F.struct("first_word", "n_words", "n_equal"), F.struct("n_equal", -F.col("first_word"))).alias("x"))
        return best.select(given_id("k").alias("doc_id"), F.col("i").cast("long").alias("item_id"), "x.first_word", "x.n_words", "x.n_equal")
    out = None
    for index in item_blocks(benchmark, item_key, item_text, block):
        sent = spark.sparkContext.broadcast(index)

        def scan(batches: Iterator[pd.DataFrame], sent=sent) -> Iterator[pd.DataFrame]:
            for b in batches:
                rows = [(k, *x) for k, t in zip(b["k"], b["t"], strict=True) for x in sent.value.overlaps(t)]
                yield pd.DataFrame(rows, columns=["doc_id", "item_id", "first_word", "n_words", "n_equal"])

        out = rows.mapInPandas(scan, HITS).withColumn("doc_id", given_id("doc_id"))
    return out if out is not None else spark.createDataFrame([], HITS)


def op5_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def _clean(index: SeedIndex, spark: SparkSession):
    sent = spark.sparkContext.broadcast(index)

    @F.arrow_udf("boolean")
    def clean(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for texts in batches:
            yield pa.array([not sent.value.overlaps(t.as_py()) for t in texts], pa.bool_())

    return clean


def decontaminate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The documents that overlap no benchmark item; each is judged where it lies, without a join, unless the items are
    more than BLOCK_ITEMS: then rows are numbered, and those of a leak are taken out by their number."""
    ship(spark)
    benchmark = table(spark, sf_dir, "benchmark")
    if len(benchmark.where("item_id is not null").take(BLOCK_ITEMS + 1)) > BLOCK_ITEMS:
        numbered = staged(docs.select(F.struct(*docs.columns).alias("row"), F.monotonically_increasing_id().alias("n")), "numbered-documents")
        gone = staged(leaks(numbered.select("n", F.col("row.text").alias("text")), benchmark, key="n").select(F.col("doc_id").alias("n")).distinct(), "leaks")
        return numbered.join(small(gone), "n", "left_anti").select("row.*")
    for index in item_blocks(benchmark, "item_id", "text", BLOCK_ITEMS):
        docs = docs.where(_clean(index, spark)("text"))
    return docs
