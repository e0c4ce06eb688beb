"""Surrounding relational operators on the given tables: scans, joins, windows, set operations, aggregates, functions,
user-defined functions. Each has the same statement in SQL."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from facetsel.catalog import DEFAULT_FACETS, FACET_NAMES, STYLES
from facetsel.functions.dialect import DUCK
from facetsel.functions.keys import tie_key
from facetsel.functions.session import ship
from facetsel.plans import sqltext
from facetsel.plans.comparison import q_random, random_sql
from facetsel.plans.selection import judged
from facetsel.sources.pools import table

Q, SQL = {}, {}


def query(name: str, sql: str | None = None):
    def take(f):
        Q[name] = f
        if sql:
            SQL[name] = sql
        return f

    return take


# Joins ---------------------------------------------------------------------------------------------------------------

@query("semi_labelled", "SELECT doc_id, source FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)")
def _(spark, d):
    return table(spark, d, "documents").select("doc_id", "source").join(table(spark, d, "labels"), "doc_id", "left_semi")


@query("anti_unlabelled", "SELECT doc_id, source FROM documents x WHERE NOT EXISTS (SELECT 1 FROM labels y WHERE y.doc_id = x.doc_id)")
def _(spark, d):
    return table(spark, d, "documents").select("doc_id", "source").join(table(spark, d, "labels"), "doc_id", "left_anti")


@query("full_outer_labels", "SELECT coalesce(x.doc_id, y.doc_id) AS doc_id, x.source, y.quality, y.toxic FROM (SELECT * FROM documents WHERE doc_id % 3 <> 0) x FULL JOIN labels y ON x.doc_id = y.doc_id")
def _(spark, d):
    x = table(spark, d, "documents").where("doc_id % 3 <> 0").select("doc_id", "source")
    return x.join(table(spark, d, "labels"), "doc_id", "full").select("doc_id", "source", "quality", "toxic")


_LEVELS = ((1, 16), (2, 91), (3, 193), (4, 404), (5, 800))


@query("theta_levels", "SELECT doc_id, count(k) AS level FROM documents LEFT JOIN (VALUES " + ", ".join(f"({k}, {t})" for k, t in _LEVELS) + ") v(k, t) ON n_chars >= t * 6 GROUP BY doc_id")
def _(spark, d):
    levels = spark.createDataFrame(_LEVELS, "k int, t int")
    x = table(spark, d, "documents").select("doc_id", "n_chars").join(F.broadcast(levels), F.col("n_chars") >= F.col("t") * 6, "left")
    return x.groupBy("doc_id").agg(F.count("k").alias("level"))


@query("band_range", "SELECT band, count(*) AS n, sum(n_chars)::BIGINT AS chars FROM documents JOIN (VALUES ('short', 0, 500), ('middle', 500, 3000), ('long', 3000, 1000000)) v(band, lo, hi) ON n_chars >= lo AND n_chars < hi GROUP BY band")
def _(spark, d):
    """Bands meet rows in bins of 500 characters, so that the range join is an equi-join whatever the number of bands."""
    bands = spark.createDataFrame([("short", 0, 500), ("middle", 500, 3000), ("long", 3000, 1_000_000)], "band string, lo long, hi long")
    bins = bands.withColumn("bin", F.explode(F.sequence(F.floor(F.col("lo") / 500), F.floor((F.col("hi") - 1) / 500))))
    x = table(spark, d, "documents").select("n_chars", F.floor(F.col("n_chars") / 500).alias("bin"))
    return x.join(bins, "bin").where("n_chars >= lo and n_chars < hi").groupBy("band").agg(F.count("*").alias("n"), F.sum("n_chars").alias("chars"))


@query("asof_event", """SELECT e.event_id, max_by(p.event_id, (p.ts, p.event_id)) AS last_view FROM events e LEFT JOIN events p ON p.user_id = e.user_id AND p.event_type = 'view' AND (p.ts, p.event_id) < (e.ts, e.event_id)
  WHERE e.event_type = 'purchase' GROUP BY e.event_id""")
def _(spark, d):
    """The last view before each purchase of the same user: one window over the union, no join."""
    e = table(spark, d, "events").where("event_type in ('view', 'purchase')")
    w = W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(W.unboundedPreceding, -1)
    seen = e.withColumn("last_view", F.last(F.when(F.col("event_type") == "view", F.col("event_id")), True).over(w))
    return seen.where("event_type = 'purchase'").select("event_id", "last_view")


@query("interval_purchase", "SELECT c.event_id AS click_id, p.event_id AS purchase_id FROM events c JOIN events p ON p.user_id = c.user_id AND p.ts > c.ts AND p.ts <= c.ts + INTERVAL 1 HOUR WHERE c.event_type = 'click' AND p.event_type = 'purchase'")
def _(spark, d):
    e = table(spark, d, "events").select("event_id", "ts", "user_id", "event_type")
    c, p = e.where("event_type = 'click'").alias("c"), e.where("event_type = 'purchase'").alias("p")
    on = (F.col("p.user_id") == F.col("c.user_id")) & (F.col("p.ts") > F.col("c.ts")) & (F.col("p.ts") <= F.col("c.ts") + F.expr("interval 1 hour"))
    return c.join(p, on).select(F.col("c.event_id").alias("click_id"), F.col("p.event_id").alias("purchase_id"))


@query("join_star", "SELECT r_name, c_mktsegment, p_brand, count(*) AS n, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey JOIN part ON l_partkey = p_partkey WHERE l_quantity < 10 GROUP BY ALL")
def _(spark, d):
    """Small dimensions are left to Spark to broadcast by their size."""
    t = lambda n: table(spark, d, n)
    x = t("lineitem").where("l_quantity < 10").join(t("orders"), F.col("l_orderkey") == F.col("o_orderkey")).join(t("customer"), F.col("o_custkey") == F.col("c_custkey"))
    x = x.join(t("nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(t("region"), F.col("n_regionkey") == F.col("r_regionkey")).join(t("part"), F.col("l_partkey") == F.col("p_partkey"))
    return x.groupBy("r_name", "c_mktsegment", "p_brand").agg(F.count("*").alias("n"), F.round(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))), 2).alias("revenue"))


@query("revenue_by_nation", "SELECT n_name, year(l_shipdate) AS year, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN nation ON s_nationkey = n_nationkey GROUP BY ALL")
def _(spark, d):
    x = table(spark, d, "lineitem").join(table(spark, d, "supplier"), F.col("l_suppkey") == F.col("s_suppkey")).join(table(spark, d, "nation"), F.col("s_nationkey") == F.col("n_nationkey"))
    return x.groupBy("n_name", F.year("l_shipdate").cast("long").alias("year")).agg(F.round(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))), 2).alias("revenue"))


# Windows, top-k, sets ------------------------------------------------------------------------------------------------

@query("win_rank_family", "SELECT doc_id, row_number() OVER w AS rn, rank() OVER v AS rk, dense_rank() OVER v AS dr, ntile(4) OVER w AS quarter, round(percent_rank() OVER v, 6) AS pr, round(cume_dist() OVER v, 6) AS cd, lag(doc_id) OVER w AS before, lead(doc_id) OVER w AS after FROM documents WINDOW w AS (PARTITION BY source ORDER BY n_chars, doc_id), v AS (PARTITION BY source ORDER BY n_chars)")
def _(spark, d):
    w, v = W.partitionBy("source").orderBy("n_chars", "doc_id"), W.partitionBy("source").orderBy("n_chars")
    return table(spark, d, "documents").select("doc_id", F.row_number().over(w).alias("rn"), F.rank().over(v).alias("rk"), F.dense_rank().over(v).alias("dr"), F.ntile(4).over(w).alias("quarter"), F.round(F.percent_rank().over(v), 6).alias("pr"), F.round(F.cume_dist().over(v), 6).alias("cd"), F.lag("doc_id").over(w).alias("before"), F.lead("doc_id").over(w).alias("after"))


@query("win_running", "SELECT doc_id, sum(n_chars) OVER (PARTITION BY source ORDER BY doc_id ROWS UNBOUNDED PRECEDING)::BIGINT AS running, first_value(n_chars) OVER (PARTITION BY source ORDER BY doc_id) AS first, last_value(n_chars) OVER (PARTITION BY source ORDER BY doc_id ROWS BETWEEN 2 PRECEDING AND 1 FOLLOWING) AS near_last FROM documents")
def _(spark, d):
    w = W.partitionBy("source").orderBy("doc_id")
    return table(spark, d, "documents").select("doc_id", F.sum("n_chars").over(w.rowsBetween(W.unboundedPreceding, 0)).alias("running"), F.first("n_chars").over(w).alias("first"), F.last("n_chars").over(w.rowsBetween(-2, 1)).alias("near_last"))


@query("win_range_frame", "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY o_orderdate RANGE BETWEEN INTERVAL 90 DAY PRECEDING AND CURRENT ROW) AS in_quarter FROM orders")
def _(spark, d):
    seconds = F.expr("timestampdiff(SECOND, timestamp_ntz'1970-01-01', o_orderdate)")
    w = W.partitionBy("o_custkey").orderBy(seconds).rangeBetween(-90 * 86400, 0)
    return table(spark, d, "orders").select("o_orderkey", F.count("*").over(w).alias("in_quarter"))


@query("topk_per_source", "SELECT source, doc_id, n_chars FROM (SELECT *, row_number() OVER (PARTITION BY source ORDER BY n_chars DESC, doc_id) AS n FROM documents) WHERE n <= 3")
def _(spark, d):
    w = W.partitionBy("source").orderBy(F.desc("n_chars"), "doc_id")
    return table(spark, d, "documents").select("source", "doc_id", "n_chars", F.row_number().over(w).alias("n")).where("n <= 3").drop("n")


@query("global_topk", "SELECT doc_id, n_chars FROM documents ORDER BY n_chars DESC, doc_id LIMIT 20")
def _(spark, d):
    return table(spark, d, "documents").select("doc_id", "n_chars").orderBy(F.desc("n_chars"), "doc_id").limit(20)


for _name, _op, _sql in (("union_all", "unionAll", "UNION ALL"), ("union_distinct", "union", "UNION"), ("intersect", "intersect", "INTERSECT"), ("except", "subtract", "EXCEPT")):

    @query(_name, f"({random_sql(1)}) {_sql} ({random_sql(2)})")
    def _(spark, d, op=_op, distinct=_name == "union_distinct"):
        out = getattr(q_random(1)(spark, d), op)(q_random(2)(spark, d))
        return out.distinct() if distinct else out


@query("dedup_exact", "SELECT min(doc_id) AS doc_id, count(*) AS copies FROM documents GROUP BY md5(trim(lower(text)))")
def _(spark, d):
    x = table(spark, d, "documents").select("doc_id", F.md5(F.trim(F.lower("text"))).alias("h"))
    return x.groupBy("h").agg(F.min("doc_id").alias("doc_id"), F.count("*").alias("copies")).drop("h")


@query("stratified_sample", f"SELECT doc_id, source FROM (SELECT doc_id, source, row_number() OVER (PARTITION BY source ORDER BY {DUCK.tie(5, 'doc_id')}) AS n, count(*) OVER (PARTITION BY source) AS total FROM documents) WHERE n <= (total + 9) // 10")
def _(spark, d):
    """A tenth of each source, rounded up, at least one: cut by hash counts and not by a window over a source."""
    from facetsel.functions.keys import nth_key_cutoff

    x = table(spark, d, "documents").select("doc_id", "source", tie_key(5, "doc_id").alias("k"))
    per = x.groupBy("source").count().orderBy("source").collect()
    index = spark.createDataFrame([(r["source"], i) for i, r in enumerate(per)], "s string, g int")
    x = x.join(F.broadcast(index), F.col("source").eqNullSafe(F.col("s"))).drop("s")
    cut = nth_key_cutoff(x.select("g", "k"), "g", "k", {i: (r["count"] + 9) // 10 for i, r in enumerate(per)})
    told = spark.createDataFrame([(g, c) for g, c in cut.items()], "g int, cut long")
    return x.join(F.broadcast(told), "g").where("k <= cut").select("doc_id", "source")


# Aggregates ----------------------------------------------------------------------------------------------------------

@query("agg_basic", "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS quantity, round(avg(l_discount), 6) AS discount, min(l_tax) AS lo, max(l_tax) AS hi, round(stddev_samp(l_quantity), 4) AS sd, count(*) FILTER (l_quantity > 25) AS large FROM lineitem GROUP BY ALL")
def _(spark, d):
    return table(spark, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("quantity"), F.round(F.avg("l_discount"), 6).alias("discount"), F.min("l_tax").alias("lo"), F.max("l_tax").alias("hi"), F.round(F.stddev_samp("l_quantity"), 4).alias("sd"), F.count_if(F.col("l_quantity") > 25).alias("large"))


@query("agg_distinct", "SELECT o_orderpriority, count(DISTINCT o_custkey) AS customers, count(DISTINCT date_trunc('month', o_orderdate)) AS months FROM orders GROUP BY ALL")
def _(spark, d):
    return table(spark, d, "orders").groupBy("o_orderpriority").agg(F.countDistinct("o_custkey").alias("customers"), F.countDistinct(F.trunc("o_orderdate", "month")).alias("months"))


@query("agg_percentile", "SELECT source, round(quantile_cont(n_chars, 0.5), 4) AS median, round(quantile_cont(n_chars, 0.9), 4) AS p90 FROM documents GROUP BY source")
def _(spark, d):
    return table(spark, d, "documents").groupBy("source").agg(F.round(F.percentile("n_chars", F.lit(0.5)), 4).alias("median"), F.round(F.percentile("n_chars", F.lit(0.9)), 4).alias("p90"))


@query("agg_pivot", "SELECT source, count(*) FILTER (lang = 'de') AS de, count(*) FILTER (lang = 'en') AS en, count(*) FILTER (lang = 'es') AS es, count(*) FILTER (lang = 'fr') AS fr FROM documents GROUP BY source")
def _(spark, d):
    return table(spark, d, "documents").groupBy("source").pivot("lang", ["de", "en", "es", "fr"]).count().fillna(0)


@query("approx_distinct")
def _(spark, d):
    return table(spark, d, "lineitem").agg(F.approx_count_distinct("l_partkey", 0.02).alias("parts"), F.percentile_approx("l_extendedprice", 0.5, 10_000).alias("median"))


# Functions -----------------------------------------------------------------------------------------------------------

@query("fn_string", "SELECT doc_id, upper(substr(source, 1, 8)) AS head, length(text) AS n, trim(lower(source)) AS s, md5(text) AS h, concat_ws('-', lang, source) AS tag, replace(lang, 'e', 'E') AS r, levenshtein(lang, source) AS lev, sha256(source) AS sha FROM documents")
def _(spark, d):
    return table(spark, d, "documents").select("doc_id", F.upper(F.substring("source", 1, 8)).alias("head"), F.length("text").alias("n"), F.trim(F.lower("source")).alias("s"), F.md5("text").alias("h"), F.concat_ws("-", "lang", "source").alias("tag"), F.replace("lang", F.lit("e"), F.lit("E")).alias("r"), F.levenshtein("lang", "source").alias("lev"), F.sha2("source", 256).alias("sha"))


@query("fn_regex", r"SELECT doc_id, len(regexp_extract_all(text, '[0-9]+')) AS numbers, regexp_extract(text, '[A-Za-z]+') AS first_word, length(regexp_replace(text, '[^a-z]', '', 'g')) AS letters, regexp_matches(text, '[|]') AS bars FROM documents")
def _(spark, d):
    return table(spark, d, "documents").select("doc_id", F.size(F.regexp_extract_all("text", F.lit("([0-9]+)"))).alias("numbers"), F.regexp_extract("text", "[A-Za-z]+", 0).alias("first_word"), F.length(F.regexp_replace("text", "[^a-z]", "")).alias("letters"), F.col("text").rlike("[|]").alias("bars"))


@query("fn_date", "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, CAST(date_trunc('month', o_orderdate) AS DATE) AS month_start, date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS days, CAST(CAST(o_orderdate AS DATE) + INTERVAL 2 MONTH AS DATE) AS later FROM orders")
def _(spark, d):
    return table(spark, d, "orders").select("o_orderkey", F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"), F.trunc("o_orderdate", "month").alias("month_start"), F.datediff("o_orderdate", F.lit("1995-01-01").cast("date")).alias("days"), F.add_months(F.to_date("o_orderdate"), 2).alias("later"))


@query("fn_math", "SELECT o_orderkey, round(ln(o_totalprice + 1), 6) AS a, round(sqrt(abs(o_totalprice)), 6) AS b, floor(o_totalprice / 7)::BIGINT AS c, ceil(o_totalprice / 7)::BIGINT AS d, greatest(o_custkey, o_orderkey) AS g, least(o_custkey, o_orderkey) AS l, o_orderkey % 7 AS m, round(pow(o_custkey, 0.5), 6) AS p FROM orders")
def _(spark, d):
    t = F.col("o_totalprice")
    return table(spark, d, "orders").select("o_orderkey", F.round(F.log(t + 1), 6).alias("a"), F.round(F.sqrt(F.abs(t)), 6).alias("b"), F.floor(t / 7).alias("c"), F.ceil(t / 7).alias("d"), F.greatest("o_custkey", "o_orderkey").alias("g"), F.least("o_custkey", "o_orderkey").alias("l"), F.pmod("o_orderkey", F.lit(7)).alias("m"), F.round(F.pow("o_custkey", F.lit(0.5)), 6).alias("p"))


@query("fn_array", "SELECT vec_id, len(embedding) AS n, round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE))), 4) AS norm2, len(list_filter(embedding, lambda x: x > 0)) AS positive, round(CAST(embedding[1] AS DOUBLE), 5) AS first FROM embeddings")
def _(spark, d):
    return table(spark, d, "embeddings").select("vec_id", F.size("embedding").alias("n"), F.round(F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double")), 4).alias("norm2"), F.size(F.filter("embedding", lambda x: x > 0)).alias("positive"), F.round(F.element_at("embedding", 1).cast("double"), 5).alias("first"))


@query("fn_map", f"WITH {sqltext.judged()} SELECT instance_id, r_stem AS stem, {' + '.join(f'CAST(r_{f} >= 4 AS INT)' for f in FACET_NAMES)} AS strong FROM judged")
def _(spark, d):
    """The score vector as a map from facet to score."""
    m = F.map_from_arrays(F.array(*map(F.lit, FACET_NAMES)), F.array(*[F.col(f"r_{f}") for f in FACET_NAMES]))
    return judged(spark, d).select("instance_id", m.alias("m")).select("instance_id", F.element_at("m", "stem").alias("stem"), F.size(F.map_filter("m", lambda k, v: v >= 4)).alias("strong"))


@query("fn_json", "SELECT event_type, CAST(sum(CAST(json_extract(props, '$.k') AS BIGINT)) AS BIGINT) AS k, count(*) AS n FROM events GROUP BY event_type")
def _(spark, d):
    return table(spark, d, "events").select("event_type", F.from_json("props", "k long").alias("p")).groupBy("event_type").agg(F.sum("p.k").alias("k"), F.count("*").alias("n"))


# User-defined functions ----------------------------------------------------------------------------------------------

@query("udf_facet", f"WITH {sqltext.judged()} SELECT instance_id, r_datareading AS score FROM judged")
def _(spark, d):
    """A facet as a vectorised Python function, registered for SQL: what an external judge would be."""
    ship(spark)

    @F.pandas_udf("int")
    def facet_datareading(text: pd.Series) -> pd.Series:
        n = text.str.count(r"\|")
        return sum((n >= t).astype("int32") for t in (1, 4, 12, 40, 140)).astype("int32")

    spark.udf.register("facet_datareading", facet_datareading)
    table(spark, d, "documents").createOrReplaceTempView("documents_for_udf")
    return spark.sql("SELECT doc_id AS instance_id, facet_datareading(text) AS score FROM documents_for_udf")


@query("udaf_entropy", "SELECT source, round(-sum(p * log2(p)), 6) AS entropy FROM (SELECT source, n / sum(n) OVER (PARTITION BY source) AS p FROM (SELECT source, lang, count(*) AS n FROM documents GROUP BY source, lang)) GROUP BY source")
def _(spark, d):
    """A grouped aggregate in Python over pre-aggregated counts, so that a group is as long as it has values."""
    ship(spark)

    @F.pandas_udf("double")
    def entropy_of(n: pd.Series) -> float:
        import numpy as np

        p = n.to_numpy() / n.sum()
        return float(-(p * np.log2(p)).sum())

    counts = table(spark, d, "documents").groupBy("source", "lang").count()
    return counts.groupBy("source").agg(F.round(entropy_of("count"), 6).alias("entropy"))


@query("udtf_cells", f"WITH {sqltext.judged()}, m AS (SELECT instance_id, unnest([" + ", ".join(f"{{'f': '{f}', 's': '{s}', 'r': r_{f}, 'g': g_{s}}}" for f in DEFAULT_FACETS for s in STYLES) + "]) AS c FROM judged) SELECT c.f AS facet, c.s AS style, count(*) AS n FROM m WHERE c.r > 0 AND c.g = 1 GROUP BY ALL")
def _(spark, d):
    """A row for each cell of an instance, by a table function in SQL's FROM clause."""

    class CellsOf:
        def eval(self, scores: list, styles: list):
            for f, r in scores:
                if r > 0:
                    for s, g in styles:
                        if g:
                            yield f, s

    spark.udtf.register("cells_of", F.udtf(CellsOf, returnType="facet string, style string"))
    pair = lambda k, c: F.struct(F.lit(k).alias("k"), F.col(c).alias("v"))
    j = judged(spark, d).select("instance_id", F.array(*[pair(f, f"r_{f}") for f in DEFAULT_FACETS]).alias("scores"), F.array(*[pair(s, f"g_{s}") for s in STYLES]).alias("styles"))
    j.createOrReplaceTempView("judged_for_cells")
    return spark.sql("SELECT c.facet, c.style, count(*) AS n FROM judged_for_cells, LATERAL cells_of(scores, styles) AS c GROUP BY c.facet, c.style")


def queries():
    return dict(Q)


def oracle_sql():
    return dict(SQL)
