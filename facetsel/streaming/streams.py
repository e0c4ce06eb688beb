"""Growing pools: incremental tagging, running best of a cell, windows, deduplication and joins over streams.

Each stream reads the table's files as they come (availableNow in tests), and its result is written to the shared folder
with its checkpoint and read back. Stateful operators are bounded: windows by their number, the running best by q rows a
cell, stream joins by their watermarks."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from facetsel.catalog import FACET_NAMES
from facetsel.functions import rubric
from facetsel.functions.keys import rank_key, tie_key
from facetsel.functions.session import shared_dir, ship
from facetsel.plans import sqltext
from facetsel.plans.selection import score_stack


def arriving(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """The table's files as a stream, with the schema of those already there. A table is a folder of files, whatever their
    names, or one file beside others of its name; listing asks the path's own file system, which may be a remote one."""
    path = f"{sf_dir.rstrip('/')}/{name}.parquet"
    schema = spark.read.parquet(path).schema
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    stream = spark.readStream.schema(schema)
    if at.getFileSystem(spark._jsparkSession.sessionState().newHadoopConf()).getFileStatus(at).isDirectory():
        return stream.parquet(path)
    return stream.option("pathGlobFilter", f"{name}*.parquet").parquet(sf_dir)


def settled(stream: DataFrame, mode: str) -> DataFrame:
    """Run to the end of what is there. append: all rows written; complete: the last result; update: rows in the order of
    their batches, with batch_id."""
    spark = stream.sparkSession
    top = f"{shared_dir(spark).rstrip('/')}/stream-{uuid.uuid4().hex}"
    out, schema = f"{top}/out", stream.schema

    def put(rows: DataFrame, batch: int) -> None:
        rows = rows.withColumn("batch_id", F.lit(batch)) if mode == "update" else rows
        rows.write.mode("overwrite").parquet(out if mode == "complete" else f"{out}/batch={batch}")  # a batch that is tried again replaces itself

    stream.writeStream.foreachBatch(put).outputMode(mode).option("checkpointLocation", f"{top}/checkpoint").trigger(availableNow=True).start().awaitTermination()
    read = spark.read.parquet(out)
    return read.select(*schema.names, *(["batch_id"] if mode == "update" else []))


def flat(docs: DataFrame) -> DataFrame:
    from facetsel.sources.pools import _SPLIT

    return docs.select(F.col("doc_id").alias("instance_id"), "source", "lang", F.col("text").alias("body"), F.expr(_SPLIT["prompt"]).alias("prompt"), F.expr(_SPLIT["answer"]).alias("answer"), F.lit(False).alias("has_context"))


def tag(spark, sf_dir):
    """New documents are judged as they come and appended to the store; the draw then reads the store."""
    j = settled(rubric.judge_wide(rubric.featurize(flat(arriving(spark, sf_dir, "documents")))), "append")
    return j.select("instance_id", *[F.col(f"r_{f}").alias(f) for f in FACET_NAMES])


TOP = 5


def top_of_facet(spark, sf_dir):
    """The running TOP best of every facet; state holds TOP keys and ids a facet."""
    ship(spark)
    judged = rubric.judge_wide(rubric.featurize(flat(arriving(spark, sf_dir, "documents"))))
    keyed = judged.selectExpr("instance_id", score_stack()).where("score > 0").select("facet", "instance_id", rank_key(F.col("score"), tie_key(42, "instance_id")).alias("key"))
    q = TOP

    def best(key: tuple, rows: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        held = list(zip(*state.get, strict=True)) if state.exists else []
        for r in rows:
            held = sorted({*held, *zip(r["key"].tolist(), r["instance_id"].tolist(), strict=True)})[:q]
        state.update(([k for k, _ in held], [i for _, i in held]))
        yield pd.DataFrame({"facet": key[0], "place": range(1, len(held) + 1), "instance_id": [i for _, i in held]})

    from pyspark.sql.streaming.state import GroupStateTimeout

    out = keyed.groupBy("facet").applyInPandasWithState(best, "facet string, place int, instance_id long", "keys array<long>, ids array<long>", "update", GroupStateTimeout.NoTimeout)
    rows = settled(out, "update")
    return rows.groupBy("facet", "place").agg(F.max_by("instance_id", "batch_id").alias("instance_id"))


def events(spark, sf_dir):
    return arriving(spark, sf_dir, "events").withColumn("at", F.col("ts").cast("timestamp"))


def _named(windowed: DataFrame, *keys: str) -> DataFrame:
    return windowed.select(F.date_format("w.start", "yyyy-MM-dd HH:mm:ss").alias("start"), *keys, "n")


def tumbling(spark, sf_dir):
    e = events(spark, sf_dir).withWatermark("at", "1 hour")
    return _named(settled(e.groupBy(F.window("at", "1 hour").alias("w"), "event_type").agg(F.count("*").alias("n")), "complete"), "event_type")


def sliding(spark, sf_dir):
    e = events(spark, sf_dir).withWatermark("at", "1 hour")
    return _named(settled(e.groupBy(F.window("at", "2 hours", "1 hour").alias("w"), "event_type").agg(F.count("*").alias("n")), "complete"), "event_type")


def sessions(spark, sf_dir):
    e = events(spark, sf_dir).withWatermark("at", "1 hour")
    return _named(settled(e.groupBy(F.session_window("at", "30 minutes").alias("w"), "user_id").agg(F.count("*").alias("n")), "complete"), "user_id")


def dedup(spark, sf_dir):
    """Texts seen for the first time within a day of arrivals, by digest; older digests leave the state."""
    d = arriving(spark, sf_dir, "documents").select(F.md5("text").alias("h"), F.current_timestamp().alias("seen"))
    d = d.withWatermark("seen", "1 day").dropDuplicatesWithinWatermark(["h"]).select("h")
    return settled(d, "append")


def join_static(spark, sf_dir):
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    return settled(arriving(spark, sf_dir, "documents").select("doc_id", "source").join(labels, "doc_id"), "append")


def join_streams(spark, sf_dir):
    """Purchases within an hour after a click of the same user; state goes with the watermarks."""
    e = events(spark, sf_dir)
    c = e.where("event_type = 'click'").select(F.col("event_id").alias("click_id"), F.col("user_id").alias("u"), F.col("at").alias("clicked")).withWatermark("clicked", "1 hour")
    p = e.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), F.col("user_id").alias("v"), F.col("at").alias("bought")).withWatermark("bought", "1 hour")
    on = F.expr("u = v and bought > clicked and bought <= clicked + interval 1 hour")
    return settled(c.join(p, on), "append").select("click_id", "purchase_id")


def queries():
    return {"stream_tag": tag, "stream_topq": top_of_facet, "stream_tumbling": tumbling, "stream_sliding": sliding, "stream_session": sessions, "stream_dedup": dedup, "stream_join_static": join_static, "stream_join_stream": join_streams}


def oracle_sql():
    wide = ", ".join(f"r_{f} AS {f}" for f in FACET_NAMES)
    fmt = "strftime({}, '%Y-%m-%d %H:%M:%S')"
    return {
        "stream_tag": f"WITH {sqltext.judged()} SELECT instance_id, {wide} FROM judged",
        "stream_topq": f"WITH {sqltext.judged()}, l AS (SELECT instance_id, facet, score FROM (SELECT instance_id, {wide} FROM judged) UNPIVOT (score FOR facet IN ({', '.join(FACET_NAMES)}))), k AS (SELECT facet, instance_id, row_number() OVER (PARTITION BY facet ORDER BY score DESC, {sqltext.TIE}) AS place FROM l WHERE score > 0) SELECT facet, CAST(place AS INT) AS place, instance_id FROM k WHERE place <= {TOP}",
        "stream_tumbling": f"SELECT {fmt.format('date_trunc($$hour$$, ts)')} AS start, event_type, count(*) AS n FROM events GROUP BY ALL",
        "stream_sliding": f"SELECT {fmt.format('date_trunc($$hour$$, ts) - to_hours(CAST(k AS INT))')} AS start, event_type, count(*) AS n FROM events, (VALUES (0), (1)) v(k) GROUP BY ALL",
        "stream_session": f"WITH g AS (SELECT *, CASE WHEN ts < lag(ts) OVER w + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT {fmt.format('min(ts)')} AS start, user_id, count(*) AS n FROM s GROUP BY user_id, k",
        "stream_dedup": "SELECT DISTINCT md5(text) AS h FROM documents",
        "stream_join_static": "SELECT doc_id, source, quality, toxic FROM documents JOIN labels USING (doc_id)",
        "stream_join_stream": "SELECT c.event_id AS click_id, p.event_id AS purchase_id FROM events c JOIN events p ON p.user_id = c.user_id AND p.ts > c.ts AND p.ts <= c.ts + INTERVAL 1 HOUR WHERE c.event_type = 'click' AND p.event_type = 'purchase'",
    }
