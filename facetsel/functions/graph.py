"""Groups of linked rows: buckets of rows that may be linked, and connected components of links."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from facetsel.functions.session import kept, released


#: Parts of the buckets, or of pairs, that move one after another; of two, the low bits.
SLICES = 8


def bucket_pairs(entries: DataFrame, groups: DataFrame | None = None, marks: DataFrame | None = None, near: Column | None = None) -> DataFrame:
    """Distinct (a, b), a < b, of entries (id, bucket), kept. Without groups, every member with its bucket's least id: as
    many pairs as members. With groups (node, component), members of one bucket that lie in different ones, which is what
    the first pairs left open; of these, with marks (id, ...), the ones for which near, a condition on l.* and r.* columns,
    holds: it is asked inside the join, so that a large bucket of unlike members makes no rows. Buckets are hashes and go in slices, all of them; what a slice moves goes before the next
    one moves."""
    parts = []
    for k in range(SLICES):
        own = entries.where(F.col("bucket").bitwiseAND(F.lit(SLICES - 1)) == k)
        parts.append(kept(_pairs(own, groups, marks, near), "pairs-part"))
    out = kept(reduce(DataFrame.unionByName, parts).distinct(), "pairs")
    released(*parts)
    return out


def _pairs(entries: DataFrame, groups: DataFrame | None, marks: DataFrame | None, near: Column | None) -> DataFrame:
    if groups is None:
        least = kept(entries.groupBy("bucket").agg(F.min("id").alias("a"), F.max("id").alias("z")).where("a < z").select("bucket", "a"), "leaders")
        pairs = entries.join(least, "bucket").where("id > a").select("a", F.col("id").alias("b"))
    else:
        told = entries.join(groups.withColumnRenamed("node", "id"), "id", "left").withColumn("c", F.coalesce("component", "id")).drop("component")
        mixed = told.groupBy("bucket").agg(F.min("c").alias("lo"), F.max("c").alias("hi")).where("lo < hi").select("bucket")
        told = told.join(mixed, "bucket")
        told = told if marks is None else told.join(marks, "id")
        on = (F.col("l.bucket") == F.col("r.bucket")) & (F.col("l.c") < F.col("r.c"))
        pairs = told.alias("l").join(told.alias("r"), on if near is None else on & near).select(F.least("l.id", "r.id").alias("a"), F.greatest("l.id", "r.id").alias("b"))
    return pairs.distinct()


def components(links: DataFrame, most_rounds: int = 60) -> DataFrame:
    """(node, component) of every node that has a link (a, b), the component named by its least node. In a round every node
    points at the least node that it or its neighbours point at, then at what that one points at; each is an aggregation
    with map-side combining and an equi-join, and its result is staged."""
    both = kept(links.select(F.explode(F.array(F.struct(F.col("a").alias("u"), F.col("b").alias("v")), F.struct(F.col("b").alias("u"), F.col("a").alias("v")))).alias("e")).select("e.u", "e.v").distinct(), "links")
    at = kept(both.groupBy("u").agg(F.least("u", F.min("v")).alias("p")).select(F.col("u").alias("node"), F.col("p").alias("component")), "component")
    for _ in range(most_rounds):
        seen = both.join(at, F.col("v") == F.col("node")).groupBy("u").agg(F.min("component").alias("m"))
        near = at.join(seen, F.col("node") == F.col("u")).select("node", F.least("component", "m").alias("p"), F.col("component").alias("was"))
        above = at.select(F.col("node").alias("p"), F.col("component").alias("pp"))
        now = kept(near.join(above, "p", "left").select("node", "was", F.least("p", F.coalesce("pp", "p")).alias("component")), "component")
        if now.where("component <> was").isEmpty():
            return now.select("node", "component")
        at = now.select("node", "component")
    raise RuntimeError("components did not settle")
