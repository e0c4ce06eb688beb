"""The store of judgements: what students or teachers said of a pool, kept for other budgets and other facets.

Scores are long, (pool, instance_id, source, lang, facet, score), in folders by pool and facet; flags likewise by pool and
style. A draw over some facets reads only their folders, a facet that is added later writes only its own, and no text is
read again. Scores of 0 and flags of 0 are not written: what is missing reads as 0."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from facetsel.catalog import DEFAULT_FACETS, STYLES

_KEYS = ("instance_id", "source", "lang")


def _long(judged: DataFrame, prefix: str, names: Sequence[str], name: str, value: str) -> DataFrame:
    stack = f"stack({len(names)}, " + ", ".join(f"'{n}', {prefix}_{n}" for n in names) + f") as ({name}, {value})"
    return judged.selectExpr(*_KEYS, stack).where(f"{value} > 0")


def materialize_scores(judged: DataFrame, path: str, pool: str, facets: Sequence[str] = (), styles: Sequence[str] = ()) -> None:
    """Write judgements (instance_id, source, lang, r_<facet>, g_<style>) of the pool; folders of the same pool and facet
    or style are replaced, others stay. One pass without a shuffle; every row of the pool is listed once besides."""
    keyed = judged.select(F.lit(pool).alias("pool"), *_KEYS)
    how = {"partitionOverwriteMode": "dynamic", "compression": "zstd"}
    keyed.write.mode("overwrite").options(**how).partitionBy("pool").parquet(f"{path}/rows")
    for kind, prefix, names, name, value in (("scores", "r", facets, "facet", "score"), ("flags", "g", styles, "style", "flag")):
        if names:
            long = _long(judged, prefix, names, name, value).select(F.lit(pool).alias("pool"), name, "instance_id", F.col(value).cast("tinyint").alias(value))
            long.write.mode("overwrite").options(**how).partitionBy("pool", name).parquet(f"{path}/{kind}")


def stored_scores(spark: SparkSession, path: str, pool: str, facets: Sequence[str] = DEFAULT_FACETS) -> DataFrame:
    """(instance_id, facet, score) above 0 of the facets; other folders are not listed in the scan."""
    return spark.read.parquet(f"{path}/scores").where((F.col("pool") == pool) & F.col("facet").isin(*facets)).select("instance_id", "facet", "score")


def stored_judgements(spark: SparkSession, path: str, pool: str, facets: Sequence[str] = DEFAULT_FACETS, styles: Sequence[str] = STYLES) -> DataFrame:
    """(instance_id, source, lang, r_<facet>, g_<style>) as a draw wants them: one shuffle of numbers by id."""
    rows = spark.read.parquet(f"{path}/rows").where(F.col("pool") == pool).select(*_KEYS)
    scores = stored_scores(spark, path, pool, facets).groupBy("instance_id").pivot("facet", list(facets)).agg(F.max("score"))
    flags = spark.read.parquet(f"{path}/flags").where((F.col("pool") == pool) & F.col("style").isin(*styles))
    flags = flags.groupBy("instance_id").pivot("style", list(styles)).agg(F.max("flag"))
    out = rows.join(scores, "instance_id", "left").join(flags, "instance_id", "left")
    zero = lambda c, name: F.coalesce(F.col(c), F.lit(0)).cast("int").alias(name)
    return out.select(*_KEYS, *[zero(f, f"r_{f}") for f in facets], *[zero(s, f"g_{s}") for s in styles])


def export_subset(pool: DataFrame, selected: DataFrame, path: str, key: str = "instance_id") -> DataFrame:
    """Write the selected instances of a pool as JSON lines with what they were chosen for, and a manifest of how many
    each cell gave; returns the manifest (cell_id, facet, style, n, least_score)."""
    chosen = selected.select(F.col("instance_id").alias(key), "cell_id", "facet", "style", "score", "pick_round", "pick_rank")
    pool.join(chosen, key).write.mode("overwrite").option("compression", "gzip").json(f"{path}/subset")
    manifest = selected.groupBy("cell_id", "facet", "style").agg(F.count("*").alias("n"), F.min("score").alias("least_score"))
    manifest.write.mode("overwrite").parquet(f"{path}/manifest")
    return selected.sparkSession.read.schema(manifest.schema).parquet(f"{path}/manifest")
