"""Budgets are met exactly, whatever repeats or is missing; the store gives back what was judged; shortfalls are told."""

from pyspark.sql import functions as F

from facetsel.functions.keys import ranked_between, smallest
from facetsel.functions.session import shared_dir
from facetsel.operators.baselines import pick_kmeans_greedy, pick_random
from facetsel.operators.draw import balanced_draw
from facetsel.operators.store import materialize_scores, stored_judgements
from facetsel.plans.subset import filled, select_subset, shortfall
from facetsel.sources import pools

FACETS, STYLES = ("stem", "ocr"), ("terse", "numeric")


def judged(spark, n=60, repeats=1):
    rows = spark.range(n).withColumn("instance_id", F.col("id") % (n // repeats))
    return rows.select("instance_id", F.concat(F.lit("s"), F.col("id") % 3).alias("source"), F.lit("en").alias("lang"), (F.col("id") % 6).cast("int").alias("r_stem"), F.when(F.col("id") % 7 > 0, F.col("id") % 4).cast("int").alias("r_ocr"), (F.col("id") % 2).cast("int").alias("g_terse"), F.lit(1).alias("g_numeric"))


def test_exact_budgets(spark):
    pool = judged(spark, 60, 4)
    for b in (0, 1, 15, 59, 60, 99):
        assert pick_random(pool, b, 1).count() == min(b, 60)
    rows = spark.range(100).select((F.col("id") % 5).alias("k"), "id")
    for lo, hi in ((0, 30), (10, 35), (20, 40), (95, 200)):
        got = ranked_between(rows, "k", lo, hi)
        assert got.count() == min(hi, 100) - lo and smallest(rows, "k", hi).count() == min(hi, 100)
        assert got.select("id").distinct().count() == got.count()
    for engine in ("serial", "cutoff", "rounds"):
        drawn = balanced_draw(pool, 12, FACETS, STYLES, engine=engine)
        assert drawn.count() == drawn.select("instance_id").distinct().count() == 12


def test_missing_scores_are_zero(spark):
    pool = judged(spark)
    zero = pool.fillna(0, ["r_ocr"])
    draws = [sorted(tuple(r) for r in balanced_draw(p, 20, FACETS, STYLES, engine=e).collect()) for p in (pool, zero) for e in ("serial", "cutoff")]
    assert all(d == draws[0] for d in draws)


def test_kmeans_greedy_gives_its_budget(spark):
    vectors = spark.range(100).select(F.col("id").alias("vec_id"), F.array(F.when(F.col("id") < 3, 100.0).otherwise(0.0) + F.col("id") / 1000, F.lit(0.0)).alias("embedding"))
    for b in (1, 4, 40, 97, 100, 150):
        got = pick_kmeans_greedy(vectors, "embedding", "vec_id", b, 2)
        assert got.count() == got.select("vec_id").distinct().count() == min(b, 100)


def test_store(spark):
    path = f"{shared_dir(spark)}/store-test"
    pool = judged(spark)
    materialize_scores(pool, path, "a", ("stem",), STYLES)
    materialize_scores(pool, path, "a", ("ocr",))
    materialize_scores(pool.limit(5), path, "b", FACETS, STYLES)
    again = stored_judgements(spark, path, "a", FACETS, STYLES)
    assert sorted(again.collect()) == sorted(pool.fillna(0, ["r_ocr"]).select(again.columns).collect())
    plan = stored_judgements(spark, path, "a", ("stem",), ("terse",))._jdf.queryExecution().executedPlan().toString()
    assert "PartitionFilters" in plan and "facet#" in plan
    assert stored_judgements(spark, path, "b", FACETS, STYLES).count() == 5


def test_select_subset_reads_the_store(spark, sf_dir):
    flat, path = pools.docs_flat(spark, sf_dir), f"{shared_dir(spark)}/store-subset"
    first = select_subset(flat, "10 %", store=path, pool="docs")
    again = select_subset(flat, "10 %", store=path, pool="docs")
    assert sorted(first.collect()) == sorted(again.collect()) and first.count() == 20


def test_shortfall_and_fallback(spark):
    pool = judged(spark)
    drawn = balanced_draw(pool, 50, FACETS, STYLES)
    told = shortfall(pool, drawn, 50, FACETS, STYLES).collect()
    assert sum(r.quota for r in told) == 50 and all(r.short == r.quota - r.picked >= 0 and r.picked <= r.members for r in told)
    all_of_it = balanced_draw(pool, 60, FACETS, STYLES)
    assert all_of_it.count() < 60
    got = filled(pool, all_of_it, 60)
    assert got.count() == got.select("instance_id").distinct().count() == 60 and got.where("cell_id is null").count() == 60 - all_of_it.count()
