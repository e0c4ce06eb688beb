"""Cleaning of the pool, the SQL surface and the outside judge as registered queries."""

from __future__ import annotations

from pyspark.sql import functions as F

from facetsel.catalog import FACET_NAMES, STYLES
from facetsel.functions.dialect import DUCK
from facetsel.functions.surface import register
from facetsel.operators import hygiene as H
from facetsel.operators.cells import pack
from facetsel.operators.teacher import BatchTeacher
from facetsel.plans import sqltext
from facetsel.plans.selection import judged
from facetsel.sources import pools


def q_near(spark, sf_dir):
    return H.near_duplicates(pools.docs_flat(spark, sf_dir))


def q_contaminated(spark, sf_dir):
    return H.contaminated(pools.docs_flat(spark, sf_dir), pools.table(spark, sf_dir, "benchmark"))


def q_surface(spark, sf_dir):
    """Through the SQL surface alone: by facet and style, how many members there are and the first in order of the draw."""
    j = judged(spark, sf_dir)
    register(spark, j, "pool_")
    pack(j, FACET_NAMES, STYLES).createOrReplaceTempView("pool_packed")
    return spark.sql("""
        select s.facet, f.style, count(*) as n, min_by(s.instance_id, struct(-s.score, tie_key(42, s.instance_id))) as first_id,
               sum(facet_score('scene', s.score * 20)) as levels
        from pool_facet_scores s
        join pool_packed p on p.instance_id = s.instance_id
        join pool_style_flags f on f.instance_id = s.instance_id and style_flag(p.sig, f.style) = 1
        where s.score > 0
        group by s.facet, f.style""")


def asked(texts: list[str]) -> list[dict[str, int]]:
    """A stand-in for an outside judge: scores by length, one flag."""
    return [{"scene": len(t) // 500, "langgen": len(t) % 6, "terse": len(t) < 200} for t in texts]


def q_batch_teacher(spark, sf_dir):
    j = BatchTeacher(asked, 32).judge(pools.docs_flat(spark, sf_dir))
    return j.select("instance_id", "source", F.col("r_scene").alias("scene"), F.col("r_langgen").alias("langgen"), F.col("g_terse").alias("terse"), F.col("r_stem").alias("stem"))


def queries():
    return {"near_dup": q_near, "decontaminate": q_contaminated, "sql_surface": q_surface, "batch_teacher": q_batch_teacher}


def _near_sql() -> str:
    return f"""WITH RECURSIVE w AS (SELECT doc_id AS id, {DUCK.tokens("text")} AS t FROM documents),
s AS (SELECT id, CASE WHEN len(t) < {H.SHINGLE} THEN [array_to_string(t, ' ')] ELSE list_distinct(list_transform(range(1, len(t) - {H.SHINGLE - 2}), lambda i: array_to_string(t[i:i + {H.SHINGLE - 1}], ' '))) END AS s FROM w WHERE len(t) > 0),
k AS (SELECT id, len(s) AS n, md5(array_to_string(list_sort(s), chr(10))) AS d, s FROM s),
r AS (SELECT d, min(id) AS rep, any_value(n) AS n, any_value(s) AS s FROM k GROUP BY d),
u AS (SELECT rep, n, unnest(s) AS x FROM r),
p AS (SELECT a.rep AS a, b.rep AS b FROM u a JOIN u b ON a.x = b.x AND a.rep < b.rep GROUP BY a.rep, b.rep, a.n, b.n HAVING 10 * count(*) >= 8 * (a.n + b.n - count(*))),
e AS (SELECT a, b FROM p UNION SELECT b, a FROM p),
t AS (SELECT rep AS a, rep AS b FROM r UNION SELECT t.a, e.b FROM t JOIN e ON t.b = e.a),
c AS (SELECT a AS rep, min(b) AS component FROM t GROUP BY a)
SELECT k.id, c.component, k.id = c.component AS stays FROM k JOIN r USING (d) JOIN c ON c.rep = r.rep"""


def _runs(relation: str, key: str) -> str:
    n = H.SHARED
    return f"SELECT {key} AS id, unnest(list_transform(range(1, len(t) - {n - 2}), lambda i: array_to_string(t[i:i + {n - 1}], ' '))) AS run FROM (SELECT {key}, {DUCK.tokens('text')} AS t FROM {relation}) WHERE len(t) >= {n}"


def oracle_sql():
    cells = ", ".join(f"{{'facet': '{f}', 'style': '{s}', 'r': r_{f}, 'g': g_{s}}}" for f in FACET_NAMES for s in STYLES)
    from facetsel.catalog import FACETS

    scene = next(f.levels for f in FACETS if f.name == "scene")
    level = " + ".join(f"CAST(c.r * 20 >= {x} AS INT)" for x in scene)
    return {
        "near_dup": _near_sql(),
        "decontaminate": f"SELECT DISTINCT id FROM ({_runs('documents', 'doc_id')}) WHERE run IN (SELECT run FROM ({_runs('benchmark', 'item_id')}))",
        "sql_surface": f"WITH {sqltext.judged()}, m AS (SELECT instance_id, {sqltext.TIE} AS tie, unnest([{cells}]) AS c FROM judged) SELECT c.facet AS facet, c.style AS style, count(*) AS n, min_by(instance_id, (-c.r, tie)) AS first_id, CAST(sum({level}) AS BIGINT) AS levels FROM m WHERE c.r > 0 AND c.g = 1 GROUP BY ALL",
        "batch_teacher": "SELECT doc_id AS instance_id, source, CAST(least(5, length(text) // 500) AS INT) AS scene, CAST(length(text) % 6 AS INT) AS langgen, CAST(length(text) < 200 AS INT) AS terse, 0 AS stem FROM documents",
    }
