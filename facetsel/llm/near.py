"""MinHash near-dedup with sequential Bayesian verification.

Texts become sets of hashed word shingles and MinHash signatures. Equal sets are one node. Bands of the signatures give
buckets. Each member is compared with its buckets' leaders first, and the verified links give components; then, inside
buckets whose members lie in several components, all pairs over two components are compared, in blocks of signatures.
Signatures are compared in batches; after each, the posterior of the similarity, from a uniform prior, drops the pair if
it reaches the threshold with less than the chosen miss probability. Survivors form clusters; in blocks of a cluster's
texts, the surviving pairs over two components are verified on the full sets of shingles, most similar first, but for
pairs that verified links have joined meanwhile. Blocks tell spanning trees and not pairs, so that a large group costs
comparisons in memory and not rows; a cluster's largest component is not compared with itself.

Misses: a pair at the threshold shares no band with probability (1 - t^ROWS)^bands, at most MISS, and is pruned wrongly
with about MISS. Sets are compared by 64-bit shingle hashes.

Defined results: words are runs without ASCII white space, A-Z in lower case; with fewer words than a shingle the whole
sequence is the one shingle; null and empty texts have the empty set and are linked with nothing. Rows with equal ids are
one node with one component; a null id is never linked and its row is kept. Other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from math import ceil, comb, log

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from facetsel.llm.buckets import led, stars, unsettled
from facetsel.llm.common import components, given_id, n_words, ship, small, staged, table, whole_id

SHINGLE, PERCENT = 5, 85
ROWS = 5
#: Positions of a signature, of which the low byte is kept; those after which a pair may be pruned; miss probability.
WIDTH, STEPS, MISS = 512, (32, 64, 128, 256, 512), 1e-5
#: Members of a bucket that are compared with each other in one piece; candidates of a member that are verified first.
BLOCK, FIRST = 512, 2
_RNG = np.random.default_rng(11)
_A = (_RNG.integers(0, 2**32, WIDTH, dtype=np.uint64) | np.uint64(1)).astype(np.uint32)
_B = _RNG.integers(0, 2**32, WIDTH, dtype=np.uint64).astype(np.uint32)
_STEP = np.array([0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93, 0xA0761D6478BD642F], np.uint64)


class _WordHashes(dict):
    def __missing__(self, word: bytes) -> int:
        if len(self) > 1_000_000:
            self.clear()
        out = self[word] = xxhash.xxh3_64_intdigest(word)
        return out


_HASHES = _WordHashes()


def shingles(text: str | None, k: int = SHINGLE) -> np.ndarray:
    """The sorted set of hashed shingles."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return np.zeros(0, np.uint64)
    h = np.fromiter(map(_HASHES.__getitem__, words), np.uint64, len(words))
    m, n = min(k, len(h)), max(1, len(h) - k + 1)
    out = np.full(n, m, np.uint64)
    for i in range(m):
        out = (out ^ (out >> np.uint64(31))) * _STEP[i % 5] + h[i : i + n]
    out ^= out >> np.uint64(29)
    out *= np.uint64(0xBF58476D1CE4E5B9)
    return np.unique(out ^ (out >> np.uint64(32)))


def signature(hashes: np.ndarray, block: int = 2048) -> np.ndarray:
    x = (hashes >> np.uint64(32)).astype(np.uint32)
    out = np.full(len(_A), 2**32 - 1, np.uint32)
    for i in range(0, len(x), block):
        part = x[i : i + block, None] * _A
        part += _B
        np.minimum(out, part.min(axis=0), out=out)
    return out


def least_matches(n: int, threshold: float, miss: float) -> int:
    """The fewest equal positions of n with which the similarity may still reach the threshold: under a uniform prior
    its posterior is a beta distribution, whose tail is a binomial sum."""
    tail = 0.0
    for m in range(n + 1):
        tail += comb(n + 1, m) * threshold**m * (1 - threshold) ** (n + 1 - m)
        if tail >= miss:
            return m
    return n


def bands_of(percent: int) -> int:
    """The fewest bands of which a pair at the threshold shares none with a probability of MISS at most: 20 at 85, 29 at 80."""
    return ceil(log(MISS) / log(1 - (percent / 100) ** ROWS)) if percent < 100 else 1


def sketch(docs: DataFrame, text: str, key: str, n_bands: int) -> DataFrame:
    """(doc_id, n_shingles, h1, h2, bands, sig): 128 bits that name the set, 64 bits for each band, a byte a position."""
    ship(docs.sparkSession)
    bits64 = (1 << 64) - 1

    def sketched(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            sets = [shingles(t) for t in b["t"]]
            digests = [xxhash.xxh3_128_intdigest(s.tobytes()) for s in sets]
            bands, sigs = [], []
            for s in sets:
                sig = signature(s)
                raw = sig[: n_bands * ROWS].tobytes()
                bands.append(b"".join(xxhash.xxh3_64_digest(raw[4 * ROWS * i : 4 * ROWS * (i + 1)], seed=i) for i in range(n_bands)))
                sigs.append(sig.astype(np.uint8).tobytes())
            yield pd.DataFrame({"doc_id": b["k"], "n_shingles": [len(s) for s in sets], "h1": np.array([d >> 64 for d in digests], np.uint64).view(np.int64), "h2": np.array([d & bits64 for d in digests], np.uint64).view(np.int64), "bands": bands, "sig": sigs})

    out = docs.select(whole_id(key).alias("k"), F.col(text).alias("t")).mapInPandas(sketched, "doc_id long, n_shingles long, h1 long, h2 long, bands binary, sig binary")
    return out.withColumn("doc_id", given_id("doc_id"))


def steps_of(percent: int) -> list[tuple[int, int]]:
    """(positions read, fewest equal). Two different minima have equal low bytes once in 256 times."""
    t = percent / 100
    return [(n, least_matches(n, t + (1 - t) / 256, MISS)) for n in STEPS]


def promising(left: np.ndarray, right: np.ndarray, steps: list[tuple[int, int]]) -> tuple[np.ndarray, np.ndarray]:
    """Indices of the pairs (rows of left and right) that no step prunes, and their numbers of equal positions."""
    live, equal, at = np.arange(len(left)), np.zeros(len(left), np.int64), 0
    for n, least in steps:
        equal[live] += (left[live, at:n] == right[live, at:n]).sum(axis=1)
        live, at = live[equal[live] >= least], n
    return live, equal[live]


def _matrix(column, width: int, kind=np.uint8) -> np.ndarray:
    return np.frombuffer(b"".join(column), kind).reshape(len(column), width)


def _first_look(percent: int):
    """Pairs (a, b, equal) of members and leaders that the Bayesian comparison leaves."""
    steps = steps_of(percent)

    def compared(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            if len(b):
                live, equal = promising(_matrix(b["sa"], WIDTH), _matrix(b["sb"], WIDTH), steps)
                yield b[["a", "b"]].iloc[live].assign(equal=equal)

    return compared


def block_pairs(comp, block, size, sig, steps, percent) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(x, y, equal) of the pairs over two components, of sizes that allow the similarity, that no step prunes; where the
    rows are of two blocks, only pairs over both."""
    n, out = len(comp), [(np.zeros(0, np.int64),) * 3]
    two = block.min() < block.max()
    parts = [np.ascontiguousarray(sig[:, a:b]) for a, b in zip((0, *STEPS), STEPS, strict=False)]
    for i in range(0, n, 128):
        rows = slice(i, min(n, i + 128))
        ok = (comp[rows, None] != comp[None, :]) & (np.arange(n)[rows, None] < np.arange(n)[None, :])
        ok &= 100 * np.minimum(size[rows, None], size[None, :]) >= percent * np.maximum(size[rows, None], size[None, :])
        if two:
            ok &= block[rows, None] != block[None, :]
        x, y = np.nonzero(ok)
        x = x + i
        equal = np.zeros(len(x), np.int64)
        for part, (_, least) in zip(parts, steps, strict=True):
            for j in range(0, len(x), 1 << 16):
                equal[j : j + (1 << 16)] += (part[x[j : j + (1 << 16)]] == part[y[j : j + (1 << 16)]]).sum(axis=1)
            live = equal >= least
            x, y, equal = x[live], y[live], equal[live]
        out.append((x, y, equal))
    return tuple(np.concatenate(z) for z in zip(*out, strict=True))


class Joined:
    """Which components have been joined."""

    def __init__(self):
        self.root: dict[int, int] = {}

    def find(self, x: int) -> int:
        while (y := self.root.get(x, x)) != x:
            self.root[x] = self.root.get(y, y)
            x = y
        return x

    def join(self, x: int, y: int) -> bool:
        """False where they were joined already."""
        x, y = self.find(x), self.find(y)
        self.root[max(x, y)] = min(x, y)
        return x != y


def _runs(names: list[str], found):
    """mapInPandas over sorted rows: found(rows) for the whole runs of equal names, which may span batches. A run has two
    blocks' rows at most."""

    def each(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        held = None
        for rows in batches:
            rows = rows if held is None else pd.concat([held, rows], ignore_index=True)
            last = (rows[names] == rows[names].iloc[-1]).all(axis=1).to_numpy() if len(rows) else np.zeros(0, bool)
            held = rows[last].reset_index(drop=True)
            if not last.all():
                yield found(rows[~last].reset_index(drop=True))
        if held is not None and len(held):
            yield found(held)

    return each


def _spans(rows: pd.DataFrame, names: list[str]) -> tuple[np.ndarray, np.ndarray]:
    key = rows[names].to_numpy()
    starts = np.flatnonzero(np.r_[True, (key[1:] != key[:-1]).any(axis=1)])
    return starts, np.r_[starts[1:], len(rows)]


CELL = ["bucket", "bi", "bj"]


def _across(percent: int):
    """A spanning forest of the surviving pairs of each cell."""
    steps = steps_of(percent)

    def forest(rows: pd.DataFrame) -> pd.DataFrame:
        starts, ends = _spans(rows, CELL)
        ids, comp, block, size = (rows[c].to_numpy() for c in ("id", "component", "block", "n_shingles"))
        sig = _matrix(rows["sig"], WIDTH)
        a, b = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
        twos = starts[ends - starts == 2]
        twos = twos[(comp[twos] != comp[twos + 1]) & (100 * np.minimum(size[twos], size[twos + 1]) >= percent * np.maximum(size[twos], size[twos + 1]))]
        if len(twos):
            x = twos[promising(sig[twos], sig[twos + 1], steps)[0]]
            a.append(ids[x]), b.append(ids[x + 1])
        for s, e in zip(starts, ends, strict=True):
            if e - s > 2:
                x, y, _ = block_pairs(comp[s:e], block[s:e], size[s:e], sig[s:e], steps, percent)
                seen = Joined()
                tree = np.fromiter((seen.join(p, q) for p, q in zip(x.tolist(), y.tolist(), strict=True)), bool, len(x))
                a.append(ids[s + x[tree]]), b.append(ids[s + y[tree]])
        a, b = np.concatenate(a), np.concatenate(b)
        return pd.DataFrame({"a": np.minimum(a, b), "b": np.maximum(a, b)})

    return _runs(CELL, forest)


def _in_cells(percent: int):
    """Verified links of each cell, as far as they join components."""
    steps = steps_of(percent)

    def linked(rows: pd.DataFrame) -> pd.DataFrame:
        out = []
        for s, e in zip(*_spans(rows, CELL), strict=True):
            own = rows.iloc[s:e]
            ids, comp = own["id"].tolist(), own["component"].to_numpy()
            x, y, equal = block_pairs(comp, own["block"].to_numpy(), own["n_shingles"].to_numpy(), _matrix(own["sig"], WIDTH), steps, percent)
            joined, sets, texts, of = Joined(), {}, own["t"].tolist(), comp.tolist()
            for k in np.argsort(-equal, kind="stable"):
                p, q = int(x[k]), int(y[k])
                if joined.find(of[p]) != joined.find(of[q]):
                    u = sets[p] if p in sets else sets.setdefault(p, shingles(texts[p]))
                    v = sets[q] if q in sets else sets.setdefault(q, shingles(texts[q]))
                    inter = len(np.intersect1d(u, v, assume_unique=True))
                    if inter and 100 * inter >= percent * (len(u) + len(v) - inter):
                        joined.join(of[p], of[q])
                        out.append((ids[p], ids[q]))
        return pd.DataFrame(out, columns=["a", "b"]).astype("int64")

    return _runs(CELL, linked)


def _verified(percent: int):
    """Pairs whose full sets are similar; a text that comes again in a batch is cut once."""

    def checked(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            kept: dict[int, np.ndarray] = {}
            good = []
            for a, c, ta, tc in zip(b["a"], b["b"], b["ta"], b["tb"], strict=True):
                x = kept[a] if a in kept else kept.setdefault(a, shingles(ta))
                y = kept[c] if c in kept else kept.setdefault(c, shingles(tc))
                inter = len(np.intersect1d(x, y, assume_unique=True))
                good.append(inter > 0 and 100 * inter >= percent * (len(x) + len(y) - inter))
                if len(kept) > 500:
                    kept.clear()
            yield b[["a", "b"]][np.array(good, bool)]

    return checked


def _links(pairs: DataFrame, docs: DataFrame, text: str, key: str, percent: int) -> DataFrame:
    """The pairs whose full sets are similar. pairs is staged."""
    named = small(staged(pairs.select(F.explode(F.array("a", "b")).alias("id")).distinct(), "named"))
    texts = docs.select(F.col(key).alias("id"), F.col(text).alias("t")).join(named, "id").groupBy("id").agg(F.min("t").alias("t"))
    texts = staged(texts, "texts")
    pairs = pairs.join(texts.select(F.col("id").alias("a"), F.col("t").alias("ta")), "a").join(texts.select(F.col("id").alias("b"), F.col("t").alias("tb")), "b")
    return staged(pairs.select("a", "b", "ta", "tb").mapInPandas(_verified(percent), "a long, b long"), "near-links")


def _cluster_links(clusters: DataFrame, found: DataFrame, reps: DataFrame, docs: DataFrame, text: str, key: str, percent: int) -> DataFrame:
    """Links inside clusters (node, component: the cluster) between different components of found. Of each cluster the
    largest component has blocks of its own, which are compared with all others' blocks but not with each other."""
    rows = clusters.select(F.col("node").alias("id"), F.col("component").alias("bucket")).join(found.withColumnRenamed("node", "id"), "id", "left").withColumn("component", F.coalesce("component", "id"))
    rows = staged(rows, "clustered")
    sizes = rows.groupBy("bucket", "component").agg(F.count("*").alias("n")).groupBy("bucket").agg(F.max_by("component", "n").alias("main"), F.max("n").alias("n_main"), F.sum("n").alias("n"))
    texts = docs.select(F.col(key).alias("id"), F.col(text).alias("t")).join(small(rows.select("id")), "id", "left_semi").groupBy("id").agg(F.min("t").alias("t"))
    rows = rows.join(reps.select("id", "n_shingles", "sig"), "id").join(texts, "id").join(sizes, "bucket")
    rest, main = (F.greatest(F.lit(1), F.ceil(x / BLOCK)).cast("int") for x in (F.col("n") - F.col("n_main"), F.col("n_main")))
    own = F.pmod(F.xxhash64("id"), F.when(F.col("component") == F.col("main"), main).otherwise(rest)).cast("int")
    rows = rows.withColumn("is_main", F.col("component") == F.col("main")).withColumn("block", F.when(F.col("is_main"), rest + own).otherwise(own))
    others = F.when(F.col("is_main"), F.sequence(F.lit(0), rest - 1)).otherwise(F.sequence(F.lit(0), rest + main - 1))
    rows = rows.withColumn("other", F.explode(others))
    rows = rows.select("bucket", F.least("block", "other").alias("bi"), F.greatest("block", "other").alias("bj"), "id", "component", "block", "n_shingles", "sig", "t")
    return staged(rows.repartition(*CELL).sortWithinPartitions(*CELL).mapInPandas(_in_cells(percent), "a long, b long"), "cluster-links")


def near_components(docs: DataFrame, text: str = "text", key: str = "doc_id", percent: int = PERCENT) -> tuple[DataFrame, DataFrame]:
    """(rows, groups): rows (doc_id, n_shingles) of every row of docs; groups (doc_id, component) of every id with a set."""
    rows = staged(sketch(docs, text, key, bands_of(percent)), "sketches")
    full = rows.where("n_shingles > 0 and doc_id is not null")
    first = staged(full.groupBy("h1", "h2").agg(F.min("doc_id").alias("rep")), "first")  # joins of staged sides may split hot keys
    mine = lambda c: F.when(F.col("doc_id") == F.col("rep"), F.col(c)).alias(c)
    owned = staged(full.join(first, ["h1", "h2"]).select("doc_id", "rep", "n_shingles", mine("bands"), mine("sig")), "owned")
    reps = staged(owned.where("doc_id = rep").dropDuplicates(["doc_id", "bands"]).select(F.col("doc_id").alias("id"), "n_shingles", "bands", "sig"), "reps")
    cut = F.array(*[F.xxhash64(F.lit(i), F.expr(f"substring(bands, {8 * i + 1}, 8)")) for i in range(bands_of(percent))])
    entries = staged(led(reps.select("id", F.explode(cut).alias("bucket"))), "buckets")

    side = lambda x, s: reps.select(F.col("id").alias(x), F.col("sig").alias(s), F.col("n_shingles").alias(f"n{x}"))
    looked = stars(entries).join(side("a", "sa"), "a").join(side("b", "sb"), "b").where(f"100 * least(na, nb) >= {percent} * greatest(na, nb)")
    looked = looked.select("a", "b", "sa", "sb").mapInPandas(_first_look(percent), "a long, b long, equal long")
    best = looked.withColumn("nth", F.row_number().over(W.partitionBy("a").orderBy(F.desc("equal"), "b"))).where(F.col("nth") <= FIRST)
    links = _links(staged(best.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), "pairs"), docs, text, key, percent)
    found = components(links)

    left = unsettled(entries.select("id", "bucket"), found).join(reps.select("id", "n_shingles", "sig"), "id")
    blocks = F.ceil(F.col("n") / BLOCK).cast("int")
    left = left.withColumn("block", F.pmod(F.xxhash64("id"), blocks).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), blocks - 1)))
    left = left.select("bucket", F.least("block", "other").alias("bi"), F.greatest("block", "other").alias("bj"), "id", "component", "block", "n_shingles", "sig")
    forest = staged(left.repartition(*CELL).sortWithinPartitions(*CELL).mapInPandas(_across(percent), "a long, b long"), "across")
    if not forest.isEmpty():
        found = components(links.unionByName(_cluster_links(components(forest), found, reps, docs, text, key, percent)))
    by_set = owned.select("doc_id", "rep").distinct().join(found.withColumnRenamed("node", "rep"), "rep", "left")
    return rows.select("doc_id", "n_shingles"), by_set.select("doc_id", F.coalesce("component", "rep").alias("component"))


def near_duplicates(docs: DataFrame, text: str = "text", key: str = "doc_id", percent: int = PERCENT) -> DataFrame:
    """(doc_id, n_shingles, component_id, kept) for every row."""
    rows, groups = near_components(docs, text, key, percent)
    groups = groups.where("doc_id <> component").groupBy("doc_id").agg(F.min("component").alias("component"))
    out = rows.join(groups, "doc_id", "left")
    out = out.select("doc_id", "n_shingles", F.coalesce("component", "doc_id").alias("component_id"))
    return out.withColumn("kept", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)))


def op7_near(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents"))


def near_stage(spark: SparkSession, docs: DataFrame, sf_dir: str, percent: int = PERCENT) -> DataFrame:
    """One document of each group: the one with the least id (of rows with that same id, one)."""
    rows, groups = near_components(docs, percent=percent)
    kept = docs.join(groups.where("doc_id <> component").select("doc_id").distinct(), "doc_id", "left_anti").select(*docs.columns)
    again = rows.where("n_shingles > 0 and doc_id is not null").groupBy("doc_id").agg(F.count("*").alias("n")).where("n > 1")
    again = staged(again.select("doc_id"), "repeated-ids")
    if again.isEmpty():
        return kept
    repeated = kept.join(small(again), "doc_id", "left_semi").withColumn("has_set", n_words(F.col("text")) > 0)
    one = repeated.where("has_set").groupBy("doc_id").agg(F.min_by(F.struct(*docs.columns), "text").alias("row")).select("row.*")
    return kept.join(small(again), "doc_id", "left_anti").unionByName(repeated.where("not has_set").drop("has_set")).unionByName(one).select(*docs.columns)


#: All pairs that share a shingle, and everything reachable from each text; no signature or bucket in here.
OP7_SQL = r"""
WITH RECURSIVE w AS (
  SELECT doc_id, coalesce(regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+'), []) AS w FROM documents),
s AS (
  SELECT doc_id, CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 5 THEN [array_to_string(w, ' ')]
    ELSE list_distinct(list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' '))) END AS s FROM w),
k AS (SELECT doc_id, s, len(s) AS n, md5(array_to_string(list_sort(s), chr(10))) AS h FROM s),
r AS (SELECT h, min(doc_id) AS rep, any_value(n) AS n, any_value(s) AS s FROM k WHERE n > 0 GROUP BY h),
u AS (SELECT rep, n, unnest(s) AS x FROM r),
p AS (SELECT a.rep AS a, b.rep AS b FROM u a JOIN u b ON a.x = b.x AND a.rep < b.rep GROUP BY a.rep, b.rep, a.n, b.n HAVING 100 * count(*) >= 85 * (a.n + b.n - count(*))),
e AS (SELECT a, b FROM p UNION SELECT b, a FROM p),
t AS (SELECT rep AS a, rep AS b FROM r UNION SELECT t.a, e.b FROM t JOIN e ON t.b = e.a),
c AS (SELECT a AS rep, min(b) AS component FROM t GROUP BY a)
SELECT k.doc_id, CAST(k.n AS BIGINT) AS n_shingles, coalesce(c.component, k.doc_id) AS component_id, coalesce(c.component, k.doc_id) = k.doc_id AS kept
FROM k LEFT JOIN r ON r.h = k.h AND k.n > 0 LEFT JOIN c ON c.rep = r.rep
"""
