"""Measures over results (setting, budget, method, bench, score), and how balanced a selection is."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from facetsel.catalog import BENCHES, FULL, PUBLISHED


def published(spark) -> DataFrame:
    """The published scores in long form; the full pool is a method at budget 100."""
    rows = [(s, b, m, bench, x) for s, b, m, scores, _, _ in PUBLISHED for bench, x in zip(BENCHES, scores, strict=True)]
    rows += [("main", 100, "full", bench, x) for bench, x in zip(BENCHES, FULL, strict=True)]
    return spark.createDataFrame(rows, "setting string, budget int, method string, bench string, score double")


def relative_to_full(results: DataFrame) -> DataFrame:
    """Mean over the benches of score / full score, in per cent; benches without a full score are left out."""
    full = results.where("method = 'full'").select("bench", F.col("score").alias("whole"))
    return results.join(F.broadcast(full), "bench").where("whole <> 0").groupBy("setting", "budget", "method").agg(F.round(100 * F.avg(F.col("score") / F.col("whole")), 4).alias("relative"))


def wins_over(results: DataFrame, reference: str = "random") -> DataFrame:
    """Benches strictly above the reference at the same budget, out of how many."""
    ref = results.where(F.col("method") == reference).select("budget", "bench", F.col("score").alias("ref"))
    return results.where("method <> 'full'").join(ref, ["budget", "bench"]).groupBy("setting", "budget", "method").agg(F.sum((F.col("score") > F.col("ref")).cast("int")).alias("wins"), F.count("*").alias("benches"))


def marks(results: DataFrame, reference: str = "random") -> DataFrame:
    """Rank within budget and bench, best flag, and whether the reference is beaten."""
    ref = results.where(F.col("method") == reference).select("budget", "bench", F.col("score").alias("ref"))
    ranked = results.where("method <> 'full'").withColumn("place", F.rank().over(W.partitionBy("budget", "bench").orderBy(F.desc("score"))))
    return ranked.join(ref, ["budget", "bench"]).select("setting", "budget", "method", "bench", "score", "place", (F.col("place") == 1).alias("best"), (F.col("score") > F.col("ref")).alias("beats_reference"))


def report(results: DataFrame, benches: list[str] | None = None) -> DataFrame:
    """A row for each setting, budget and method, a column for each bench, with wins and relative score."""
    benches = benches or sorted(r[0] for r in results.select("bench").distinct().collect())
    wide = results.groupBy("setting", "budget", "method").pivot("bench", benches).agg(F.max("score"))
    return wide.join(wins_over(results).select("setting", "budget", "method", "wins"), ["setting", "budget", "method"], "left").join(relative_to_full(results), ["setting", "budget", "method"], "left")


def entropy(selected: DataFrame, column: str) -> DataFrame:
    """Entropy in bits of a column's values, and of how many."""
    n = selected.groupBy(column).agg(F.count("*").alias("n"))
    p = F.col("n") / F.sum("n").over(W.partitionBy())
    return n.select(F.lit(column).alias("what"), (-p * F.log2(p)).alias("h")).groupBy("what").agg(F.round(F.sum("h"), 6).alias("entropy"), F.count("*").alias("values"))


def jaccard(a: DataFrame, b: DataFrame, key: str = "instance_id") -> DataFrame:
    x = a.select(key).distinct().withColumn("a", F.lit(1)).join(b.select(key).distinct().withColumn("b", F.lit(1)), key, "full")
    return x.agg(F.sum(F.coalesce(F.col("a") * F.col("b"), F.lit(0))).alias("both"), F.count("*").alias("either")).select("both", "either", F.round(F.col("both") / F.greatest(F.col("either"), F.lit(1)), 6).alias("jaccard"))


def agreement(student: DataFrame, teacher: DataFrame, by: str = "facet", value: str = "score") -> DataFrame:
    """By facet: mean absolute error, share of equal levels, correlation (null where one side never varies). Both sides have
    a row for each instance and facet, of a few bytes in files and many in memory: they are never broadcast."""
    j = student.select("instance_id", by, F.col(value).alias("p")).hint("merge").join(teacher.select("instance_id", by, F.col(value).alias("t")), ["instance_id", by])
    return j.groupBy(by).agg(F.count("*").alias("n"), F.round(F.avg(F.abs(F.col("p") - F.col("t"))), 6).alias("mae"), F.round(F.avg((F.col("p") == F.col("t")).cast("int")), 6).alias("exact"), F.round(F.try_divide(F.covar_pop(F.col("p").cast("double"), F.col("t").cast("double")), F.stddev_pop("p") * F.stddev_pop("t")), 4).alias("corr"))
