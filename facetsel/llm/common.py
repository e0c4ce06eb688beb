"""What the operators share: tables, staged results, code shipping, components of a graph."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from facetsel.functions.session import kept as staged
from facetsel.functions.session import released, shared_dir, ship

__all__ = ["HASH60_SQL", "WORD", "components", "given_id", "hash60", "n_words", "released", "shared_dir", "ship", "small", "staged", "table", "whole_id"]

#: A word: a run of anything but the six ASCII white-space characters.
WORD = r"[^\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


#: Rows of a few numbers each that may be broadcast; more go by a shuffled join.
BROADCAST_ROWS = 1_000_000


def small(df: DataFrame, most: int = BROADCAST_ROWS) -> DataFrame:
    """df marked for broadcasting if a count shows that it has few rows. For staged tables of numbers: counting reads
    their footers, and the rows' size is known."""
    return F.broadcast(df) if df.count() <= most else df


_NO_ID = -(1 << 63)


def whole_id(key: str | Column) -> Column:
    """A bigint id without nulls, as Python workers want it: a column of theirs with nulls is one of doubles, which hold
    no id above 2^53. given_id() gives the nulls back; the least bigint is no id."""
    return F.coalesce((F.col(key) if isinstance(key, str) else key).cast("long"), F.lit(_NO_ID).cast("long"))


def given_id(name: str) -> Column:
    return F.when(F.col(name) > _NO_ID, F.col(name)).alias(name)


def n_words(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def hash60(seed: int, key: Column) -> Column:
    """60 bits of md5 of 'seed|key' as a bigint; DuckDB gives the same, see HASH60_SQL."""
    return F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}|"), F.coalesce(key.cast("string"), F.lit("")))), 1, 15), 16, 10).cast("long")


HASH60_SQL = "CAST('0x' || substr(md5('{seed}|' || coalesce(CAST({key} AS VARCHAR), '')), 1, 15) AS BIGINT)"


def components(edges: DataFrame, a: str = "a", b: str = "b", most_rounds: int = 60) -> DataFrame:
    """Connected components of an undirected graph of bigint nodes: (node, component), the component named by its
    smallest node, for every node that has an edge.

    Alternating stars: each node hands its larger neighbours to the smallest one it knows, then its smaller ones.
    The number of rounds grows with the logarithm of the longest path. A round is two aggregations with map-side
    combining and two equi-joins whose skewed partitions adaptive execution may split; its result is staged, so
    that lineage does not grow. It ends when every node has one parent and no parent has one."""
    links = edges.select(F.col(a).cast("long").alias("u"), F.col(b).cast("long").alias("v")).where("u is not null and v is not null and u <> v")
    links = staged(links.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")), "links")
    for _ in range(most_rounds):
        both = links.select(F.explode(F.array(F.struct("u", "v"), F.struct(F.col("v").alias("u"), F.col("u").alias("v")))).alias("e")).select("e.u", "e.v")
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        small_least = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(small_least, "u").select(F.explode(F.array(F.struct(F.col("u"), F.col("m").alias("v")), F.struct(F.col("v").alias("u"), F.col("m").alias("v")))).alias("e"))
        before, links = links, staged(small.select("e.u", "e.v").where("u <> v").distinct(), "links")
        released(before)
        roles = links.select(F.explode(F.array(F.struct(F.col("u").alias("n"), F.lit(1).alias("child")), F.struct(F.col("v").alias("n"), F.lit(0).alias("child")))).alias("r")).select("r.n", "r.child")
        roles = roles.groupBy("n").agg(F.sum("child").alias("parents"), F.min("child").alias("leaf"))
        if roles.where("parents > 1 or (parents = 1 and leaf = 0)").isEmpty():
            break
    else:
        raise RuntimeError("components did not settle")
    nodes = links.select(F.col("u").alias("node"), F.col("v").alias("component"))
    return nodes.unionByName(nodes.select(F.col("component").alias("node"), "component").distinct())
