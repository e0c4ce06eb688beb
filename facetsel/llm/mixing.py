"""Mixing sources to target weights.

Every document gets a hash-random key. Within its source the keys are cut into equal ranges (coarse and fine, so
that no window is ever long); sums of the ranges give a distributed prefix sum of token counts, and each source is
cut at its exact budget in key order, after as many whole epochs as the budget holds. Only ids, sizes and keys move.

Defined results: a null or empty text has size 0 and takes 0; a null source is a source of its own, last; a null id stays null, its random key is that of an empty one; repeated
rows count one by one; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from facetsel.llm.common import HASH60_SQL, hash60, n_words, small, staged, table, whole_id

#: Rows that a finest key range holds on average, and the most bits of a level of ranges.
RANGE_ROWS, LEVEL_BITS = 256, 12
#: Sources are planned on the driver, a few numbers each; more than so many is refused.
MOST_SOURCES = 1_000_000


def budgets(sizes: Sequence[tuple[str | None, int]], weights: Sequence[float], most_epochs: float) -> list[float]:
    """Targets by source that add up to all sizes: in proportion to the weights, but none above most_epochs times
    its source's size; what is above goes to the others by weight, until none is above.

    The sources that stop at their limit are those whose limit per weight is least, so one ordered pass finds the
    common level."""
    order = sorted(range(len(sizes)), key=lambda i: (most_epochs * sizes[i][1] / weights[i], i))
    left, weight = sum(n for _, n in sizes), sum(weights)
    out = [0.0] * len(sizes)
    for k, i in enumerate(order):
        limit = most_epochs * sizes[i][1]
        if left / weight * weights[i] <= limit:
            for j in order[k:]:
                out[j] = left / weight * weights[j]
            break
        out[i] = float(limit)
        left, weight = left - limit, weight - weights[i]
    return out


def mix(docs: DataFrame, size: Column, weights: Sequence[float] = (5, 2, 1), most_epochs: int = 3, seed: int = 17, source: str = "source", key: str = "doc_id") -> DataFrame:
    """(key, size, source_size, target, taken) for every row of docs.

    weights repeat over the sources in code-point order, null last. taken adds up to the rounded target of each
    source: whole epochs of all its documents, then the documents of least random key; the last one is cut."""
    spark = docs.sparkSession
    rows = staged(docs.select(F.col(key).alias("doc_id"), F.col(source).alias("source"), size.alias("size"), hash60(seed, F.col(key)).alias("rnd")), "mix")
    per = rows.groupBy("source").agg(F.sum("size").alias("n"), F.count("*").alias("rows"))
    if per.count() > MOST_SOURCES:
        raise ValueError(f"more than {MOST_SOURCES} sources")
    found = sorted(per.collect(), key=lambda r: (r.source is None, (r.source or "").encode("utf-32-be")))
    sizes = [(r.source, int(r.n)) for r in found]
    targets = budgets(sizes, [weights[i % len(weights)] for i in range(len(sizes))], most_epochs)
    plan = [(i, s, n, t, math.floor(t + 0.5)) for i, ((s, n), t) in enumerate(zip(sizes, targets, strict=True))]
    plan = spark.createDataFrame(plan, "sid int, source string, source_size long, target double, budget long")
    plan = plan.withColumn("epochs", F.expr("if(source_size > 0, budget div source_size, 0L)")).withColumn("rest", F.expr("budget - epochs * source_size"))

    most = max((r.rows for r in found), default=0)
    bits = max(0, math.ceil(math.log2(max(1, most / RANGE_ROWS))))
    coarse, fine = min(LEVEL_BITS, (bits + 1) // 2), min(LEVEL_BITS, bits // 2)
    rows = rows.join(F.broadcast(plan.select(F.col("source").alias("source_"), "sid")), F.col("source").eqNullSafe(F.col("source_")))
    rows = rows.select("doc_id", "sid", "size", "rnd", F.shiftright("rnd", 60 - coarse).cast("int").alias("c"), F.shiftright("rnd", 60 - coarse - fine).cast("int").alias("f"))
    by_fine = rows.groupBy("sid", "c", "f").agg(F.sum("size").alias("n"))
    by_coarse = by_fine.groupBy("sid", "c").agg(F.sum("n").alias("n"))
    earlier = lambda w: F.coalesce(F.sum("n").over(w.rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    by_coarse = by_coarse.select("sid", "c", earlier(W.partitionBy("sid").orderBy("c")).alias("before_c"))
    by_fine = by_fine.select("sid", "c", "f", earlier(W.partitionBy("sid", "c").orderBy("f")).alias("before_f"))
    starts = by_fine.join(by_coarse, ["sid", "c"]).select("sid", "c", "f", (F.col("before_c") + F.col("before_f")).alias("start"))
    in_range = W.partitionBy("sid", "c", "f").orderBy("rnd", "doc_id", "size").rowsBetween(W.unboundedPreceding, 0)
    rows = rows.withColumn("prefix", F.sum("size").over(in_range) - F.col("size")).join(starts, ["sid", "c", "f"])
    rows = rows.join(F.broadcast(plan.drop("source")), "sid")
    cut = F.greatest(F.lit(0).cast("long"), F.least(F.col("size"), F.col("rest") - F.col("start") - F.col("prefix")))
    return rows.select("doc_id", "size", "source_size", "target", (F.col("epochs") * F.col("size") + cut).alias("taken"))


def op1_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return mix(docs, n_words(docs["text"]))


def mix_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The documents of the mix with size, source_size, target and taken, in place of columns of such names that docs has;
    those of which it takes nothing go.

    Only ids, sources, hashes and sizes of texts are numbered, sorted and summed; texts move once, to meet their shares.
    Rows equal in id, source and text are numbered, so that each keeps its own share."""
    row = ["k", "s", "h"]
    own = [whole_id("doc_id").alias("k"), F.coalesce("source", F.lit("")).alias("s"), F.xxhash64("text", "source").alias("h")]
    slim = staged(docs.select(*own, "source", n_words(docs["text"]).alias("size")), "mix-rows")
    twice = staged(slim.groupBy(*row).agg(F.count("*").alias("n")).where("n > 1").select(*row), "mix-repeats")
    rows, slim = docs.select(F.struct(*docs.columns).alias("row"), *own).withColumn("nth", F.lit(1)), slim.withColumn("nth", F.lit(1))
    if not twice.isEmpty():
        numbered = lambda df: df.join(small(twice), row, "left_semi").withColumn("nth", F.row_number().over(W.partitionBy(*row).orderBy(F.lit(0))))
        rows = rows.join(small(twice), row, "left_anti").unionByName(numbered(rows))
        slim = slim.join(small(twice), row, "left_anti").unionByName(numbered(slim))
    named = slim.select(F.concat_ws("#", "k", "h", "nth").alias("name"), "source", "size")
    shares = mix(named, F.col("size"), key="name")
    told = shares.where("taken > 0").select(F.split_part("doc_id", F.lit("#"), F.lit(1)).cast("long").alias("k"), F.split_part("doc_id", F.lit("#"), F.lit(2)).cast("long").alias("h"), F.split_part("doc_id", F.lit("#"), F.lit(3)).cast("int").alias("nth"), "size", "source_size", "target", "taken")
    added = ["size", "source_size", "target", "taken"]
    kept = rows.join(small(staged(told, "mix-shares")), ["k", "h", "nth"])
    return kept.select(*[F.col(f"row.{c}") for c in docs.columns if c not in added], *added)


OP1_SQL = rf"""
WITH sized AS (
  SELECT doc_id, source, {HASH60_SQL.format(seed=17, key="doc_id")} AS rnd,
         CAST(coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0) AS BIGINT) AS size
  FROM documents),
per AS (
  SELECT source, CAST(sum(size) AS BIGINT) AS n,
         [5, 2, 1][1 + (row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3] AS w
  FROM sized GROUP BY source),
ranked AS (
  SELECT *, row_number() OVER (ORDER BY 3.0 * n / w, source NULLS LAST) AS k FROM per),
levels AS (
  SELECT *, (SELECT sum(n) FROM per) - coalesce(sum(3 * n) OVER (ORDER BY k ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS rest_n,
         sum(w) OVER (ORDER BY k ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS rest_w
  FROM ranked),
stop AS (SELECT min(k) AS k FROM levels WHERE CAST(rest_n AS DOUBLE) / rest_w * w <= 3 * n),
level AS (SELECT CAST(rest_n AS DOUBLE) / rest_w AS height, k FROM levels WHERE k = (SELECT k FROM stop)),
plan AS (
  SELECT source, n AS source_size, CASE WHEN r.k < l.k THEN 3.0 * n ELSE l.height * w END AS target
  FROM ranked r, level l),
whole AS (
  SELECT *, CAST(floor(target + 0.5) AS BIGINT) AS budget,
         CASE WHEN source_size > 0 THEN CAST(floor(target + 0.5) AS BIGINT) // source_size ELSE 0 END AS epochs FROM plan),
run AS (
  SELECT s.doc_id, s.size, p.source_size, CAST(p.target AS DOUBLE) AS target, p.epochs, p.budget - p.epochs * p.source_size AS rest,
         sum(s.size) OVER (PARTITION BY s.source ORDER BY s.rnd, s.doc_id, s.size ROWS UNBOUNDED PRECEDING) - s.size AS before
  FROM sized s JOIN whole p ON s.source IS NOT DISTINCT FROM p.source)
SELECT doc_id, size, source_size, target, CAST(epochs * size + greatest(0, least(size, rest - before)) AS BIGINT) AS taken FROM run
"""
