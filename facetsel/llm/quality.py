"""Quality by nearest-neighbour voting over latent-semantic vectors.

A text is a bag of hashed byte windows: square roots of counts, weighted by rarity, scaled to length one, and projected
on the leading singular directions of a bounded sample of labelled texts. The projection and the sample's vectors are a
few megabytes whatever the corpus holds, and are broadcast; they are fitted in one task, so that the driver holds no bags. Every document, in blocks, is multiplied with all labelled
vectors; its nearest ones vote with their labels, each by a power of its cosine, and the two classes are weighed as if
they were equally frequent in the sample before the corpus's own odds are put back.

Defined results: a null or empty text has no windows; its score is the base rate of the sample. Labelled rows without a
document, documents without a label and null labels are not learned from; a null id is scored, and is not held out; ids with several labels go by the greatest;
with no labelled rows at all every score is 0.5. Repeated rows give repeated rows; other columns are ignored.
"""

from __future__ import annotations

import io
from collections.abc import Iterator
from dataclasses import dataclass
from operator import eq

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from facetsel.llm.common import given_id, ship, table, whole_id


@dataclass(frozen=True)
class Settings:
    """per_class: the most labelled rows learned from, of either label. buckets, dims: of the bag and of the latent
    vectors. neighbours vote by cosine ** sharpness."""

    per_class: int = 1500
    buckets: int = 4096
    dims: int = 64
    neighbours: int = 31
    sharpness: float = 16.0
    threshold: float = 0.7


#: Buckets that all hold the count of echoed words, so that it weighs beside thousands of windows.
ECHO = 16
_MIX = np.array([0x9E3779B1, 0x85EBCA77, 0xC2B2AE3D, 0x27D4EB2F], np.uint32)


def bag(text: str | None, buckets: int) -> np.ndarray:
    """Hashed counts of all byte windows of three; the last ECHO buckets count the words that repeat one of the two
    words before them, less what plain prose has of those."""
    whole = (text or "").encode("utf-8", "surrogatepass")
    raw = np.frombuffer(whole, np.uint8).astype(np.uint32)
    if len(raw) < 3:
        return np.zeros(buckets, np.float32)
    h = (raw[:-2] * _MIX[0]) ^ (raw[1:-1] * _MIX[1]) ^ (raw[2:] * _MIX[2])
    h = (h ^ (h >> np.uint32(15))) * _MIX[3]
    out = np.bincount(h >> np.uint32(32 - (buckets.bit_length() - 1)), minlength=buckets).astype(np.float32)
    words = whole.split()
    out[-ECHO:] = max(0, sum(map(eq, words, words[1:])) + sum(map(eq, words, words[2:])) - 1 - len(words) // 32)
    return out


@dataclass
class Model:
    settings: Settings
    rarity: np.ndarray
    axes: np.ndarray
    vectors: np.ndarray
    labels: np.ndarray
    prior: float

    def latent(self, bags: np.ndarray) -> np.ndarray:
        x = np.sqrt(bags) * self.rarity
        x /= np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-12)
        z = x @ self.axes
        return z / np.maximum(np.linalg.norm(z, axis=1, keepdims=True), 1e-12)

    def score(self, bags: np.ndarray) -> np.ndarray:
        if not len(self.labels):
            return np.full(len(bags), 0.5)
        s, seen = self.settings, bags.any(axis=1)
        cosines = self.latent(bags) @ self.vectors.T
        k = min(s.neighbours, len(self.labels))
        near = np.argpartition(cosines, len(self.labels) - k, axis=1)[:, -k:]
        votes = np.maximum(np.take_along_axis(cosines, near, 1), 1e-6).astype(np.float64) ** s.sharpness
        share = self.labels.mean()
        weight = np.where(self.labels[near] == 1, self.prior / max(share, 1e-9), (1 - self.prior) / max(1 - share, 1e-9))
        votes = votes * weight
        out = (votes * (self.labels[near] == 1)).sum(axis=1) / np.maximum(votes.sum(axis=1), 1e-300)
        return np.where(seen, np.clip(out, 0, 1), self.prior)


def fit(bags: np.ndarray, labels: np.ndarray, prior: float, s: Settings) -> Model:
    """Singular directions by subspace iteration from a fixed start."""
    if not len(labels):
        return Model(s, np.zeros(s.buckets, np.float32), np.zeros((s.buckets, 1), np.float32), np.zeros((0, 1), np.float32), labels, 0.5)
    rarity = np.log1p(len(bags) / (1.0 + (bags > 0).sum(axis=0))).astype(np.float32)
    model = Model(s, rarity, np.zeros((s.buckets, 1), np.float32), np.zeros((0, 1), np.float32), labels, prior)
    x = np.sqrt(bags)
    x *= rarity
    x /= np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-12)
    q = np.random.default_rng(5).standard_normal((s.buckets, min(s.dims + 16, len(x), s.buckets))).astype(np.float32)
    for _ in range(4):
        q = np.linalg.qr(x.T @ (x @ q))[0]
    inside = np.linalg.svd(x @ q, full_matrices=False)[2]
    model.axes = np.ascontiguousarray((q @ inside.T)[:, : s.dims]).astype(np.float32)
    model.vectors = np.ascontiguousarray(model.latent(bags))
    return model


def labelled_sample(docs: DataFrame, labels: DataFrame, s: Settings) -> DataFrame:
    """(label, text): of the learnable labelled rows, for each label those whose ids have the least md5, per_class at
    most. Ids of the held-out part of the data are never learned from."""
    known = labels.where("quality is not null and doc_id is not null").groupBy("doc_id").agg(F.max("quality").alias("label"))
    known = known.where("crc32(cast(doc_id as string)) % 4 <> 2")
    picked = None
    for label in (0, 1):
        part = known.where(F.col("label") == label).orderBy(F.md5(F.col("doc_id").cast("string")), "doc_id").limit(s.per_class)
        picked = part if picked is None else picked.unionByName(part)
    return docs.select("doc_id", "text").join(F.broadcast(picked), "doc_id").groupBy("doc_id").agg(F.first("label").alias("label"), F.min("text").alias("text"))


def train(docs: DataFrame, labels: DataFrame, s: Settings = Settings()) -> Model:
    """The sample's bags are made where its texts lie and meet in one task: at most 2 * per_class rows of buckets numbers."""
    ship(docs.sparkSession)
    base = labels.where("quality is not null and crc32(cast(doc_id as string)) % 4 <> 2").agg(F.avg((F.col("quality") == 1).cast("double"))).first()[0]
    prior = 0.5 if base is None else float(base)

    def bags(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            yield pd.DataFrame({"doc_id": b["doc_id"], "label": b["label"], "bag": [bag(t, s.buckets).astype(np.uint32).tobytes() for t in b["text"]]})

    def fitted(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        rows = sorted((x for b in batches for x in zip(b["doc_id"].tolist(), b["label"].tolist(), b["bag"], strict=True)), key=lambda x: x[0])
        x = np.zeros((len(rows), s.buckets), np.float32)
        for i, r in enumerate(rows):
            x[i] = np.frombuffer(r[2], np.uint32)
        m, out = fit(x, np.array([r[1] for r in rows], np.int64), prior, s), io.BytesIO()
        np.savez(out, rarity=m.rarity, axes=m.axes, vectors=m.vectors, labels=m.labels)
        yield pd.DataFrame({"model": [out.getvalue()]})

    sample = labelled_sample(docs, labels, s).mapInPandas(bags, "doc_id long, label int, bag binary")
    got = sample.repartition(1).mapInPandas(fitted, "model binary").collect()
    if not got:
        return fit(np.zeros((0, s.buckets), np.float32), np.zeros(0, np.int64), prior, s)
    with np.load(io.BytesIO(got[0]["model"])) as m:
        return Model(s, m["rarity"], m["axes"], m["vectors"], m["labels"], prior)


def score(docs: DataFrame, model: Model, key: str = "doc_id", block: int = 256) -> DataFrame:
    """(doc_id, held_out, score, predicted) for every row."""
    spark = docs.sparkSession
    ship(spark)
    sent, s = spark.sparkContext.broadcast(model), model.settings

    def voted(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        m = sent.value
        for b in batches:
            got = [m.score(np.stack([bag(t, s.buckets) for t in b["text"].iloc[i : i + block]])) for i in range(0, len(b), block)]
            yield pd.DataFrame({"doc_id": b["k"], "score": np.concatenate(got) if got else np.zeros(0)})

    out = docs.select(whole_id(key).alias("k"), "text").mapInPandas(voted, "doc_id long, score double")
    out = out.withColumn("doc_id", given_id("doc_id"))
    return out.select("doc_id", F.expr("coalesce(crc32(cast(doc_id as string)) % 4 = 2, false)").alias("held_out"), "score", (F.col("score") >= s.threshold).cast("int").alias("predicted"))


def op3_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return score(docs, train(docs, table(spark, sf_dir, "labels")))


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The documents predicted to be good. Rows are scored where they lie, so that no text is shuffled, and in slices, so
    that a worker holds few texts twice."""
    model = train(docs, table(spark, sf_dir, "labels"))
    ship(spark)
    sent, s = spark.sparkContext.broadcast(model), model.settings

    @F.arrow_udf("double")
    def scored(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for texts in batches:
            parts = (texts.slice(i, 256).to_pylist() for i in range(0, len(texts), 256))
            yield pa.array(np.concatenate([sent.value.score(np.stack([bag(t, s.buckets) for t in part])) for part in parts] or [np.zeros(0)]), pa.float64())

    return docs.where(scored("text") >= s.threshold)
