"""Token counts of whole texts.

Texts of up to LONG characters are counted where they lie, in one pass without a shuffle. Longer ones are cut into chunks
of CHUNK characters, which any tasks read; each gives the map that the transducer makes of it, and a text's maps, a few
numbers each, are composed pairwise.

Defined results: a null or empty text has 0 bytes and 0 tokens; a null id stays null; repeated rows give repeated rows;
other columns are ignored."""

from __future__ import annotations

import json
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from facetsel.llm.common import given_id, ship, table, whole_id

MODEL, LIMIT = "piece_bpe_32k.model", 4096
LONG, CHUNK = 1 << 20, 1 << 17


def model_path(name: str = MODEL) -> str:
    """Where the public vocabulary files lie, on each machine."""
    import public_tokenizers

    return public_tokenizers.path(name)


def count_tokens(docs: DataFrame, text: str = "text", model: str = MODEL):
    """A column expression over docs: tokens of the text."""
    ship(docs.sparkSession)

    @F.pandas_udf("long")
    def counted(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        from facetsel.llm.fst import piece_counter

        counter = piece_counter(model_path(model))
        for texts in batches:
            yield pd.Series(counter.all(texts), dtype="int64")

    return counted(F.col(text))


def _by_chunks(long: DataFrame, model: str, chunk: int) -> DataFrame:
    """(doc_id, n_bytes, n_tokens) of rows (k, part, n_bytes, t); rows equal in id and text are composed together."""
    ship(long.sparkSession)

    def cut(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for b in batches:
            for k, part, n, t in zip(b["k"].tolist(), b["part"].tolist(), b["n_bytes"].tolist(), b["t"], strict=True):
                for i in range(0, len(t), chunk):
                    yield pd.DataFrame({"k": [k], "part": [part], "n_bytes": [n], "i": [i], "t": [t[i : i + chunk]]})

    def mapped(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        from facetsel.llm.fst import piece_counter

        counter = piece_counter(model_path(model))
        for b in batches:
            maps = [counter.chunk(t, i == 0) for i, t in zip(b["i"].tolist(), b["t"], strict=True)]
            yield b[["k", "part", "n_bytes", "i"]].assign(map=[json.dumps([m.head, m.closed, m.count, m.state]) for m in maps])

    def composed(rows: pd.DataFrame) -> pd.DataFrame:
        from facetsel.llm.fst import ChunkMap, piece_counter

        one = rows.drop_duplicates("i").sort_values("i")
        maps = [ChunkMap(h, c, n, tuple(map(tuple, s))) for h, c, n, s in map(json.loads, one["map"])]
        total = piece_counter(model_path(model)).joined(maps)
        return pd.DataFrame({"doc_id": rows["k"], "n_bytes": rows["n_bytes"], "n_tokens": total})[rows["i"] == 0]

    parts = long.mapInPandas(cut, "k long, part long, n_bytes long, i long, t string").repartition("k", "part", "i")
    maps = parts.mapInPandas(mapped, "k long, part long, n_bytes long, i long, map string")
    out = maps.groupBy("k", "part").applyInPandas(composed, "doc_id long, n_bytes long, n_tokens long")
    return out.withColumn("doc_id", given_id("doc_id"))


def token_counts(docs: DataFrame, text: str = "text", key: str = "doc_id", limit: int = LIMIT, model: str = MODEL, long: int = LONG, chunk: int = CHUNK) -> DataFrame:
    """(doc_id, n_bytes, n_tokens, over_limit) for every row."""
    size = F.coalesce(F.octet_length(text), F.lit(0)).cast("long").alias("n_bytes")
    is_long = F.coalesce(F.length(text) > long, F.lit(False))
    out = docs.where(~is_long).select(F.col(key).cast("long").alias("doc_id"), size, count_tokens(docs, text, model).alias("n_tokens"))
    rest = docs.where(is_long).select(whole_id(key).alias("k"), F.xxhash64(text).alias("part"), size, F.col(text).alias("t"))
    return out.unionByName(_by_chunks(rest, model, chunk)).withColumn("over_limit", F.col("n_tokens") > limit)


def op6_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts(table(spark, sf_dir, "documents"))
