"""The SQL surface: views of a pool's judgements and functions over them, for use from spark.sql. The functions are SQL
expressions that Catalyst inlines; none runs Python."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from facetsel.catalog import FACET_NAMES, FACETS, STYLES


def register(spark: SparkSession, judged: DataFrame, prefix: str = "") -> None:
    """Views <prefix>judged (a row each), <prefix>facet_scores and <prefix>style_flags (long), and the functions
    facet_score(facet, measure): the level 0..5 that a measure reaches; style_flag(sig, style): a packed signature's flag;
    tie_key(seed, id): the order of equal scores."""
    judged.createOrReplaceTempView(f"{prefix}judged")
    stack = lambda names, p, what: f"stack({len(names)}, " + ", ".join(f"'{n}', {p}_{n}" for n in names) + f") as ({what})"
    judged.selectExpr("instance_id", "source", stack(FACET_NAMES, "r", "facet, score")).createOrReplaceTempView(f"{prefix}facet_scores")
    judged.selectExpr("instance_id", "source", stack(STYLES, "g", "style, flag")).createOrReplaceTempView(f"{prefix}style_flags")
    level = " ".join(f"when facet = '{f.name}' then " + " + ".join(f"cast(measure >= {x} as int)" for x in f.levels) for f in FACETS)
    place = " ".join(f"when style = '{s}' then {i}" for i, s in enumerate(STYLES))
    spark.sql(f"create or replace temporary function facet_score(facet string, measure bigint) returns int return case {level} end")
    spark.sql(f"create or replace temporary function style_flag(sig bigint, style string) returns int return cast(shiftright(sig, {3 * len(FACET_NAMES)} + case {place} end) & 1 as int)")
    spark.sql("create or replace temporary function tie_key(seed int, id bigint) returns bigint return cast(conv(substring(md5(concat(seed, '|', id)), 1, 15), 16, 10) as bigint)")
