"""End-to-end selection: judge a sample, fit students, score and tag the whole pool, store that, draw. Its queries."""

from __future__ import annotations

import uuid
from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from facetsel.catalog import DEFAULT_FACETS, FACET_NAMES, STYLES, TEACHER_FRACTION
from facetsel.functions import rubric
from facetsel.functions.keys import smallest, tie_key
from facetsel.functions.session import kept, shared_dir
from facetsel.operators.cells import Layout, allot_quotas, cell_sizes, pack, resolve_budget
from facetsel.operators.draw import balanced_draw
from facetsel.operators.store import export_subset, materialize_scores, stored_judgements
from facetsel.operators.student import CELL, CellMeanStudent
from facetsel.operators.teacher import RubricTeacher, teacher_sample
from facetsel.plans import sqltext
from facetsel.plans.comparison import cellmean_ctes
from facetsel.plans.selection import of_pool
from facetsel.sources import pools


def distilled(flat: DataFrame, teacher=None, fraction: float = TEACHER_FRACTION, seed: int = 42) -> DataFrame:
    """(instance_id, source, lang, r_<facet>, g_<style>) of the whole pool by cell-mean students, which are fitted on the
    teacher's judgements of a sample. The teacher reads the sample only; the students read features."""
    sample = teacher_sample(flat, fraction, seed)
    taught = kept((teacher or RubricTeacher()).judge(sample), "taught")
    features = kept(rubric.featurize(flat), "features")
    cells = features.select("instance_id", "source", "lang", *[F.expr(e).cast("int").alias(k) for k, e in CELL.items()])
    return CellMeanStudent().fit_wide(cells, taught).score_wide(cells)


def select_subset(flat: DataFrame, budget: int | float | str, teacher=None, fraction: float = TEACHER_FRACTION, store: str | None = None, pool: str = "pool", facets: Sequence[str] = DEFAULT_FACETS, styles: Sequence[str] = STYLES, fallback: bool = False, **how) -> DataFrame:
    """The whole method over a flat pool (see sources.pools). store: a folder for judgements, which are read back from
    there if it holds the pool's already. fallback: rows in no cell fill what the cells cannot."""
    spark = flat.sparkSession
    path = store or f"{shared_dir(spark).rstrip('/')}/store-{uuid.uuid4().hex}"
    if store is None or not stored(spark, path, pool):
        materialize_scores(kept(distilled(flat, teacher, fraction), "distilled"), path, pool, FACET_NAMES, STYLES)
    judged = kept(stored_judgements(spark, path, pool, facets, styles), "stored")
    b = resolve_budget(judged.count(), budget)
    picked = balanced_draw(judged, b, facets, styles, **how)
    return filled(judged, picked, b) if fallback else picked


def stored(spark: SparkSession, path: str, pool: str) -> bool:
    jvm = spark._jvm
    at = jvm.org.apache.hadoop.fs.Path(f"{path}/rows/pool={pool}")
    return at.getFileSystem(spark._jsc.hadoopConfiguration()).exists(at)


def filled(judged: DataFrame, picked: DataFrame, b: int, seed: int = 42) -> DataFrame:
    """picked and, where it has fewer than b rows, others of the pool by hash; those have no cell."""
    picked = kept(picked, "picked")
    short = b - picked.count()
    if short <= 0:
        return picked
    rest = judged.select("instance_id", "source").join(picked.select("instance_id"), "instance_id", "left_anti").withColumn("tie", tie_key(seed, "instance_id"))
    more = smallest(rest, "tie", short).drop("tie")
    return picked.unionByName(more, allowMissingColumns=True)


def shortfall(judged: DataFrame, picked: DataFrame, b: int, facets: Sequence[str] = DEFAULT_FACETS, styles: Sequence[str] = STYLES) -> DataFrame:
    """(cell_id, facet, style, quota, members, picked, short): what each cell was to give, held and gave in the first
    sweep; short is what later sweeps had to find elsewhere."""
    layout = Layout(tuple(facets), tuple(styles))
    sizes, quotas = cell_sizes(pack(judged, facets, styles), layout), allot_quotas(b, layout)
    told = judged.sparkSession.createDataFrame([(i, *layout.cell(i)[:2], int(quotas[i]), int(sizes.get(i, 0))) for i in range(layout.n)], "cell_id int, facet string, style string, quota long, members long")
    got = picked.where("pick_round = 1").groupBy("cell_id").agg(F.count("*").alias("picked"))
    out = told.join(F.broadcast(got), "cell_id", "left").fillna(0, ["picked"])
    return out.withColumn("short", F.col("quota") - F.col("picked"))


def q_select(percent: int):
    def run(spark, sf_dir):
        return select_subset(pools.docs_flat(spark, sf_dir), f"{percent} %", pool="docs")

    return run


def _store(spark, sf_dir) -> str:
    path = f"{shared_dir(spark).rstrip('/')}/store-{uuid.uuid4().hex}"
    judged = kept(RubricTeacher().judge(pools.docs_flat(spark, sf_dir)), "judged")
    materialize_scores(judged, path, "docs", DEFAULT_FACETS, STYLES)
    materialize_scores(judged, path, "docs", ("ocr",))  # a facet that is added later
    return path


def q_store(spark, sf_dir):
    """What the store holds, by facet."""
    scores = spark.read.parquet(f"{_store(spark, sf_dir)}/scores")
    return scores.groupBy("pool", "facet").agg(F.count("*").alias("n"), F.sum("score").alias("total"))


def q_from_store(spark, sf_dir):
    j = kept(stored_judgements(spark, _store(spark, sf_dir), "docs", ("stem", "ocr")), "stored")
    return balanced_draw(j, resolve_budget(j.count(), "5 %"), ("stem", "ocr"))


def q_shortfall(spark, sf_dir):
    j = kept(RubricTeacher().judge(pools.docs_flat(spark, sf_dir)), "judged")
    b = resolve_budget(j.count(), "30 %")
    return shortfall(j, balanced_draw(j, b), b)


def q_fallback(spark, sf_dir):
    """A draw over one narrow cell asks for more than it holds; the rest of the budget is filled by hash."""
    j = kept(RubricTeacher().judge(pools.docs_flat(spark, sf_dir)), "judged")
    b = resolve_budget(j.count(), "50 %")
    return filled(j, balanced_draw(j, b, ("datareading",), ("tabular",)), b).select("instance_id", "source", "facet")


def q_export(spark, sf_dir):
    j = kept(RubricTeacher().judge(pools.docs_flat(spark, sf_dir)), "judged")
    picked = balanced_draw(j, resolve_budget(j.count(), "10 %"))
    docs = pools.table(spark, sf_dir, "documents").withColumnRenamed("doc_id", "instance_id").drop("source")
    return export_subset(docs, picked, f"{shared_dir(spark).rstrip('/')}/export-{uuid.uuid4().hex}")


def q_redraw(spark, sf_dir):
    """A pool that grows by two sub-domains in batches: each is judged as it comes and added to the store; after the last,
    what was drawn first stays and its share of the grown pool is drawn from what is new."""
    flat = pools.docs_flat(spark, sf_dir)
    path = f"{shared_dir(spark).rstrip('/')}/store-{uuid.uuid4().hex}"
    late = F.pmod(tie_key(5, "source"), F.lit(3)) == 0
    for name, rows in (("first", flat.where(~late)), ("late", flat.where(late))):
        materialize_scores(kept(RubricTeacher().judge(rows), "judged"), path, name, DEFAULT_FACETS, STYLES)
    first, new = (kept(stored_judgements(spark, path, p), "stored") for p in ("first", "late"))
    b = resolve_budget(first.count() + new.count(), "10 %")
    before = balanced_draw(first, resolve_budget(first.count(), "10 %"))
    before = kept(before, "drawn")
    after = balanced_draw(new, b - before.count())
    return before.withColumn("step", F.lit("first")).unionByName(after.withColumn("step", F.lit("late")))


def queries():
    out = {f"select_cellmean_{p:02d}": q_select(p) for p in (5, 10, 30)}
    return out | {"score_store": q_store, "draw_from_store": q_from_store, "draw_shortfall": q_shortfall, "draw_fallback": q_fallback, "export_manifest": q_export, "stream_redraw": q_redraw}


def select_sql(percent: int) -> str:
    flags = ", ".join(f"g_{s} AS {s}" for s in STYLES)
    wide = ", ".join([f"CAST(max(CASE WHEN facet = '{f}' THEN score END) AS INT) AS r_{f}" for f in FACET_NAMES] + [f"CAST(max(CASE WHEN facet = '{s}' THEN score END) AS INT) AS g_{s}" for s in STYLES])
    return f"""WITH RECURSIVE {cellmean_ctes()},
marks AS (SELECT instance_id, facet, score FROM (SELECT instance_id, {flags} FROM judged) UNPIVOT (score FOR facet IN ({", ".join(STYLES)}))),
fit_g AS (SELECT facet, b1, b2, b3, count(*) AS n, CAST(sum(score) AS BIGINT) AS total FROM marks JOIN sampled USING (instance_id) JOIN cells USING (instance_id) GROUP BY ALL),
whole_g AS (SELECT facet, sum(n) AS n0, sum(total) AS total0 FROM fit_g GROUP BY facet),
predicted_g AS (SELECT c.instance_id, w.facet, CAST(coalesce((2 * total + n) // (2 * n), (2 * total0 + n0) // (2 * n0)) AS INT) AS score FROM cells c CROSS JOIN whole_g w LEFT JOIN fit_g f ON f.facet = w.facet AND f.b1 = c.b1 AND f.b2 = c.b2 AND f.b3 = c.b3),
students AS (SELECT instance_id, source, {wide} FROM (SELECT * FROM predicted UNION ALL SELECT * FROM predicted_g) JOIN (SELECT instance_id, source FROM judged) USING (instance_id) GROUP BY ALL),
{sqltext.draw_ctes(of_pool(percent), source="students")}
SELECT {sqltext.DRAWN} FROM drawn"""


def oracle_sql():
    head = f"WITH RECURSIVE {sqltext.judged()}"
    stored = " UNION ALL ".join(f"SELECT '{f}' AS facet, r_{f} AS score FROM judged" for f in (*DEFAULT_FACETS, "ocr"))
    s = len(STYLES)
    pairs = ", ".join(f"{{'i': {i * s + k}, 'f': '{f}', 't': '{t}', 'm': r_{f} > 0 AND g_{t} = 1}}" for i, f in enumerate(DEFAULT_FACETS) for k, t in enumerate(STYLES))
    late = "CAST('0x' || substr(md5('5|' || source), 1, 15) AS BIGINT) % 3 = 0"
    b_first = "(SELECT count(*) * 10 // 100 FROM old)"
    return {f"select_cellmean_{p:02d}": select_sql(p) for p in (5, 10, 30)} | {
        "score_store": f"{head} SELECT 'docs' AS pool, facet, count(*) AS n, CAST(sum(score) AS BIGINT) AS total FROM ({stored}) WHERE score > 0 GROUP BY facet",
        "draw_from_store": sqltext.draw_sql(of_pool(5), facets=("stem", "ocr")),
        "draw_shortfall": f"""{head}, {sqltext.draw_ctes(of_pool(30))},
m AS (SELECT unnest([{pairs}]) AS c FROM judged),
n AS (SELECT CAST(c.i AS INT) AS cell_id, c.f AS facet, c.t AS style, count(*) FILTER (c.m) AS members FROM m GROUP BY ALL),
p AS (SELECT cell_id, count(*) AS picked FROM drawn WHERE pick_round = 1 GROUP BY cell_id)
SELECT n.cell_id, n.facet, n.style, CAST(q.q AS BIGINT) AS quota, n.members, coalesce(p.picked, 0) AS picked, CAST(q.q AS BIGINT) - coalesce(p.picked, 0) AS short FROM n JOIN drawn_q q ON q.j = n.cell_id LEFT JOIN p USING (cell_id)""",
        "draw_fallback": f"""{head}, {sqltext.draw_ctes(of_pool(50), facets=("datareading",), styles=("tabular",))},
r AS (SELECT instance_id, source, row_number() OVER (ORDER BY {sqltext.TIE}) AS n FROM judged WHERE instance_id NOT IN (SELECT instance_id FROM drawn))
SELECT instance_id, source, facet FROM drawn UNION ALL SELECT instance_id, source, NULL FROM r WHERE n <= {of_pool(50)} - (SELECT count(*) FROM drawn)""",
        "export_manifest": f"{head}, {sqltext.draw_ctes(of_pool(10))} SELECT cell_id, facet, style, count(*) AS n, min(score) AS least_score FROM drawn GROUP BY ALL",
        "stream_redraw": f"""{head}, old AS (SELECT * FROM judged WHERE NOT ({late})), late AS (SELECT * FROM judged WHERE {late}),
{sqltext.draw_ctes(b_first, source="old", name="a")},
{sqltext.draw_ctes(f"{of_pool(10)} - (SELECT count(*) FROM a)", source="late", name="b")}
SELECT {sqltext.DRAWN}, 'first' AS step FROM a UNION ALL SELECT {sqltext.DRAWN}, 'late' FROM b""",
    }
