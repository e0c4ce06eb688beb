"""End-to-end selection over the given pools, and its registered queries."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from facetsel.catalog import BUDGETS, DEFAULT_FACETS, FACET_NAMES, FACETS, STYLES, TEACHER_FRACTION
from facetsel.functions import rubric
from facetsel.functions.dialect import DUCK
from facetsel.functions.session import kept
from facetsel.operators.cells import Layout, allot_quotas, cell_sizes, pack, resolve_budget
from facetsel.operators.draw import balanced_draw, coverable, extend_selection
from facetsel.plans import sqltext
from facetsel.sources import pools


def judged(spark: SparkSession, sf_dir: str, pool: str = "docs", levels=(1, 2, 3, 4, 5)) -> DataFrame:
    """The rubric teacher over a whole pool, kept: text is read once, whatever is drawn afterwards."""
    return kept(rubric.judge_wide(rubric.featurize(pools.FLAT[pool](spark, sf_dir)), levels), "judged")


def draw(budget: str, pool: str = "docs", **how):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        j = judged(spark, sf_dir, pool)
        return balanced_draw(j, resolve_budget(j.count(), budget), **how)

    return run


def of_pool(percent: int, relation: str = "judged") -> str:
    return f"(SELECT count(*) * {percent} // 100 FROM {relation})"


def score_stack() -> str:
    return f"stack({len(FACETS)}, " + ", ".join(f"'{f}', r_{f}" for f in FACET_NAMES) + ") as (facet, score)"


def q_wide(spark, sf_dir):
    return judged(spark, sf_dir).select("instance_id", *[F.col(f"r_{f}").alias(f) for f in FACET_NAMES])


def q_long(spark, sf_dir):
    return judged(spark, sf_dir).selectExpr("instance_id", score_stack())


def q_flags(spark, sf_dir):
    return judged(spark, sf_dir).select("instance_id", *[F.col(f"g_{s}").alias(s) for s in STYLES])


def q_rationale(spark, sf_dir):
    return q_long(spark, sf_dir).select("instance_id", "facet", "score", F.expr(rubric.rationale_column()).alias("rationale"))


def q_packed(spark, sf_dir):
    return pack(judged(spark, sf_dir), FACET_NAMES, STYLES).select("instance_id", "source", "sig", "tie")


def q_sizes(spark, sf_dir):
    j = judged(spark, sf_dir)
    layout = Layout(DEFAULT_FACETS, STYLES)
    sizes = cell_sizes(pack(j, DEFAULT_FACETS, STYLES), layout)
    return spark.createDataFrame([(i, *layout.cell(i)[:2], sizes.get(i, 0)) for i in range(layout.n)], "cell_id int, facet string, style string, n long")


def q_matrix(spark, sf_dir):
    j = judged(spark, sf_dir)
    cells = j.selectExpr("*", score_stack()).where("score > 0")
    return cells.groupBy("facet").agg(*[F.sum(f"g_{s}").alias(s) for s in STYLES])


def q_quotas(remainder: str, by_source: str = "none"):
    def run(spark, sf_dir):
        j = judged(spark, sf_dir)
        sources = tuple(sorted(r[0] for r in j.select("source").distinct().collect())) if by_source == "flat" else ()
        layout = Layout(DEFAULT_FACETS, STYLES, sources)
        b = resolve_budget(j.count(), "10 %")
        q = allot_quotas(b, layout, remainder, cell_sizes(pack(j, DEFAULT_FACETS, STYLES), layout))
        return spark.createDataFrame([(i, int(x)) for i, x in enumerate(q)], "cell_id int, quota long")

    return run


def quotas_sql(remainder: str, by_source: str = "none") -> str:
    return f"WITH RECURSIVE {sqltext.judged()},\n{sqltext.draw_ctes(of_pool(10), remainder=remainder, by_source=by_source)}\nSELECT CAST(j AS INT) AS cell_id, CAST(q AS BIGINT) AS quota FROM drawn_q"


def q_budgets(spark, sf_dir):
    n = pools.table(spark, sf_dir, "documents").count()
    return spark.createDataFrame([(p, resolve_budget(n, f"{p} %")) for p in BUDGETS], "percent int, budget long")


def q_extend(spark, sf_dir):
    """A facet added to a finished selection: its old picks and the new ones."""
    j = judged(spark, sf_dir)
    first = balanced_draw(j, resolve_budget(j.count(), "10 %"))
    extra = extend_selection(first, j, "ocr", resolve_budget(j.count(), "2 %"))
    return first.withColumn("step", F.lit("first")).unionByName(extra.withColumn("step", F.lit("added")))


EXTEND_SQL = f"""WITH RECURSIVE {sqltext.judged()},
{sqltext.draw_ctes(of_pool(10))},
rest AS (SELECT * FROM judged WHERE instance_id NOT IN (SELECT instance_id FROM drawn)),
{sqltext.draw_ctes(of_pool(2), facets=("ocr",), source="rest", name="added")}
SELECT {sqltext.DRAWN}, 'first' AS step FROM drawn UNION ALL SELECT {sqltext.DRAWN}, 'added' FROM added"""


def q_instances(build, vec: bool):
    def run(spark, sf_dir):
        i = build(spark, sf_dir)
        shown = F.round(F.element_at("context.vec", 1).cast("double"), 5) if vec else F.length("context.body")
        return i.select("pool", "instance_id", F.col("context.kind").alias("kind"), shown.alias("context_sign"), "prompt", "answer", "source", "lang", "n_chars")

    return run


def instances_sql(pool: str) -> str:
    flat = pools.FLAT_SQL[pool]
    if pool == "docs":
        sign, joined = "round(CAST(e.embedding[1] AS DOUBLE), 5)", "LEFT JOIN embeddings e ON e.vec_id = i.instance_id % (SELECT count(*) FROM embeddings)"
        kind = "vec"
    elif pool == "web":
        sign, joined, kind = "length(i.html)", "", "html"
    else:
        kind = "history"
        joined = "LEFT JOIN (SELECT conv_id * 1000 + turn AS id, coalesce(string_agg(text, chr(10)) OVER (PARTITION BY conv_id ORDER BY turn ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), '') AS h FROM conversations) h ON h.id = i.instance_id"
        sign = "length(h.h)"
    return f"SELECT '{pool}' AS pool, i.instance_id, '{kind}' AS kind, {sign} AS context_sign, i.prompt, i.answer, i.source, i.lang, CAST(length(i.body) AS BIGINT) AS n_chars FROM ({flat}) i {joined}"


def q_coverage(dim):
    """How a draw, a random subset and the pool spread over source and style: rollup, cube and grouping sets."""

    def run(spark, sf_dir):
        j = judged(spark, sf_dir)
        d = balanced_draw(j, resolve_budget(j.count(), "10 %"))
        agg = [F.count("*").alias("n"), F.sum("score").alias("total")]
        if dim == "rollup":
            return d.rollup("source", "style").agg(*agg)
        if dim == "cube":
            return d.join(j.select("instance_id", "lang"), "instance_id").cube("lang", "style").agg(*agg)
        d.createOrReplaceTempView("drawn_for_sets")
        return spark.sql("SELECT facet, style, source, count(*) AS n, sum(score) AS total FROM drawn_for_sets GROUP BY GROUPING SETS ((facet), (style), (source))")

    return run


def coverage_sql(dim: str) -> str:
    head = f"WITH RECURSIVE {sqltext.judged()},\n{sqltext.draw_ctes(of_pool(10))}\n"
    agg = "count(*) AS n, CAST(sum(score) AS BIGINT) AS total"
    if dim == "rollup":
        return head + f"SELECT source, style, {agg} FROM drawn GROUP BY ROLLUP (source, style)"
    if dim == "cube":
        return head + f"SELECT j.lang, style, {agg} FROM drawn JOIN judged j USING (instance_id) GROUP BY CUBE (j.lang, style)"
    return head + f"SELECT facet, style, source, {agg} FROM drawn GROUP BY GROUPING SETS ((facet), (style), (source))"


def q_uncovered(spark, sf_dir):
    c = coverable(judged(spark, sf_dir), DEFAULT_FACETS, STYLES)
    return c.groupBy("source").agg(F.count("*").alias("n"), F.sum((F.col("in_cells") == 0).cast("int")).alias("in_no_cell"), F.sum("in_cells").alias("memberships"))


UNCOVERED_SQL = f"""WITH {sqltext.judged()}, c AS (SELECT source, ({" + ".join(f"CAST(r_{f} > 0 AS INT)" for f in DEFAULT_FACETS)}) * ({" + ".join(f"g_{s}" for s in STYLES)}) AS m FROM judged)
SELECT source, count(*) AS n, CAST(sum(CASE WHEN m = 0 THEN 1 ELSE 0 END) AS BIGINT) AS in_no_cell, CAST(sum(m) AS BIGINT) AS memberships FROM c GROUP BY source"""


def q_sample(spark, sf_dir):
    from facetsel.operators.teacher import teacher_sample

    return teacher_sample(pools.docs_flat(spark, sf_dir), TEACHER_FRACTION, 42).select("instance_id", "source")


SAMPLE_SQL = f"SELECT instance_id, source FROM (SELECT doc_id AS instance_id, source, row_number() OVER (ORDER BY {DUCK.tie(42, 'doc_id')}) AS n, count(*) OVER () AS total FROM documents) WHERE n <= total * 15 // 100"


def queries():
    out = {
        "instances_docs": q_instances(pools.docs, True),
        "instances_web": q_instances(pools.web, False),
        "instances_chat": q_instances(pools.chat, False),
        "resolve_budgets": q_budgets,
        "teacher_sample": q_sample,
        "facet_scores_wide": q_wide,
        "facet_scores_long": q_long,
        "rationale": q_rationale,
        "style_flags": q_flags,
        "packed_signature": q_packed,
        "cell_sizes": q_sizes,
        "cell_matrix": q_matrix,
        "quotas_first": q_quotas("first"),
        "quotas_rotating": q_quotas("rotating", "flat"),
        "quotas_largest": q_quotas("largest"),
        "draw_sweep_05": draw("5 %"),
        "draw_sweep_10": draw("10 %"),
        "draw_sweep_30": draw("30 %"),
        "draw_cutoff_10": draw("10 %", engine="cutoff"),
        "draw_rounds_05": draw("5 %", engine="rounds"),
        "draw_interleave_10": draw("10 %", order="interleave"),
        "draw_flat_10": draw("10 %", by_source="flat", remainder="rotating"),
        "draw_nested_10": draw("10 %", by_source="nested"),
        "draw_custom": draw("5 %", facets=("stem", "datareading")),
        "draw_extend_ocr": q_extend,
        "draw_web": draw("10 %", pool="web"),
        "draw_chat": draw("10 %", pool="chat"),
        "coverage_rollup": q_coverage("rollup"),
        "coverage_cube": q_coverage("cube"),
        "coverage_sets": q_coverage("sets"),
        "coverage_cells": q_uncovered,
    }
    for p in (1, 40, 50):
        out[f"draw_scale_{p:02d}"] = draw(f"{p} %")
    return out


def oracle_sql():
    wide = ", ".join(f"r_{f} AS {f}" for f in FACET_NAMES)
    flags = ", ".join(f"g_{s} AS {s}" for s in STYLES)
    unpivot = "SELECT instance_id, facet, score FROM (SELECT instance_id, " + wide + " FROM judged) UNPIVOT (score FOR facet IN (" + ", ".join(FACET_NAMES) + "))"
    head = f"WITH {sqltext.judged()} "
    reached = " ".join(f"WHEN facet = '{f.name}' THEN '{{\"score\":' || score || ',\"reached\":' || [0,{','.join(map(str, f.levels))}][score + 1] || ',\"next\":' || coalesce(CAST([{','.join(map(str, f.levels))},NULL][score + 1] AS VARCHAR), 'null') || '}}'" for f in FACETS)
    sig = " | ".join([f"(CAST(r_{f} AS BIGINT) << {3 * i})" for i, f in enumerate(FACET_NAMES)] + [f"(CAST(g_{s} AS BIGINT) << {3 * len(FACET_NAMES) + i})" for i, s in enumerate(STYLES)])
    s = len(STYLES)
    cells = ", ".join(f"{{'cell_id': {i * s + k}, 'facet': '{f}', 'style': '{t}', 'r': r_{f}, 'g': g_{t}}}" for i, f in enumerate(DEFAULT_FACETS) for k, t in enumerate(STYLES))
    matrix = ", ".join(f"CAST(sum(g_{t}) AS BIGINT) AS {t}" for t in STYLES)
    out = {
        "instances_docs": instances_sql("docs"),
        "instances_web": instances_sql("web"),
        "instances_chat": instances_sql("chat"),
        "resolve_budgets": "SELECT CAST(p AS INT) AS percent, (SELECT count(*) FROM documents) * p // 100 AS budget FROM (VALUES " + ", ".join(f"({p})" for p in BUDGETS) + ") v(p)",
        "teacher_sample": SAMPLE_SQL,
        "facet_scores_wide": head + f"SELECT instance_id, {wide} FROM judged",
        "facet_scores_long": head + unpivot,
        "rationale": head + f"SELECT instance_id, facet, score, CASE {reached} END AS rationale FROM ({unpivot})",
        "style_flags": head + f"SELECT instance_id, {flags} FROM judged",
        "packed_signature": head + f"SELECT instance_id, source, {sig} AS sig, {sqltext.TIE} AS tie FROM judged",
        "cell_sizes": head + f", m AS (SELECT unnest([{cells}]) AS c FROM judged) SELECT CAST(c.cell_id AS INT) AS cell_id, c.facet AS facet, c.style AS style, CAST(sum(CASE WHEN c.r > 0 AND c.g = 1 THEN 1 ELSE 0 END) AS BIGINT) AS n FROM m GROUP BY ALL",
        "cell_matrix": head + f", l AS ({unpivot}) SELECT facet, {matrix} FROM l JOIN judged USING (instance_id) WHERE score > 0 GROUP BY facet",
        "quotas_first": quotas_sql("first"),
        "quotas_rotating": quotas_sql("rotating", "flat"),
        "quotas_largest": quotas_sql("largest"),
        "draw_sweep_05": sqltext.draw_sql(of_pool(5)),
        "draw_sweep_10": sqltext.draw_sql(of_pool(10)),
        "draw_sweep_30": sqltext.draw_sql(of_pool(30)),
        "draw_cutoff_10": sqltext.draw_sql(of_pool(10)),
        "draw_rounds_05": sqltext.draw_sql(of_pool(5)),
        "draw_interleave_10": sqltext.draw_sql(of_pool(10), order="interleave"),
        "draw_flat_10": sqltext.draw_sql(of_pool(10), by_source="flat", remainder="rotating"),
        "draw_nested_10": sqltext.draw_sql(of_pool(10), by_source="nested"),
        "draw_custom": sqltext.draw_sql(of_pool(5), facets=("stem", "datareading")),
        "draw_extend_ocr": EXTEND_SQL,
        "draw_web": sqltext.draw_sql(of_pool(10), pool="web"),
        "draw_chat": sqltext.draw_sql(of_pool(10), pool="chat"),
        "coverage_rollup": coverage_sql("rollup"),
        "coverage_cube": coverage_sql("cube"),
        "coverage_sets": coverage_sql("sets"),
        "coverage_cells": UNCOVERED_SQL,
    }
    for p in (1, 40, 50):
        out[f"draw_scale_{p:02d}"] = sqltext.draw_sql(of_pool(p))
    return out
