"""Candidate pairs from hashed buckets, linear in the number of bucket entries.

A bucket's members are not paired with each other. First each is paired with one leader of its bucket (a star). When the
links among those pairs are known, a bucket whose members lie in one component has no more to tell; of the others, only
pairs over two components are left, and those are all taken. So no link is lost that a bucket could show, and a large
group of near copies costs as many pairs as it has members."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from facetsel.llm.common import staged


def led(entries: DataFrame) -> DataFrame:
    """entries (bucket, id, ...) of buckets with several ids, and each bucket's leader: the id that comes first when the
    bucket's own number is mixed into all, so that a member in several buckets meets several leaders."""
    mixed = F.col("id").bitwiseXOR(F.col("bucket"))
    leaders = entries.groupBy("bucket").agg(F.min(mixed).alias("lo"), F.max(mixed).alias("hi")).where("lo < hi")
    leaders = staged(leaders.select("bucket", F.col("lo").bitwiseXOR(F.col("bucket")).alias("leader")), "leaders")
    return entries.join(leaders, "bucket")


def stars(with_leader: DataFrame) -> DataFrame:
    """Distinct (a, b): each member a with its buckets' leaders b."""
    return with_leader.where("id <> leader").select(F.col("id").alias("a"), F.col("leader").alias("b")).distinct()


def unsettled(entries: DataFrame, component: DataFrame) -> DataFrame:
    """The entries of buckets whose members lie in several components, with component and the bucket's size n.
    component: (node, component); ids that it lacks are their own."""
    known = entries.join(component.withColumnRenamed("node", "id"), "id", "left").withColumn("component", F.coalesce("component", "id"))
    mixed = known.groupBy("bucket").agg(F.min("component").alias("c_lo"), F.max("component").alias("c_hi"), F.count("*").alias("n")).where("c_lo < c_hi")
    return known.join(mixed.select("bucket", "n"), "bucket")


def across(entries: DataFrame, component: DataFrame, near: Column | None = None) -> DataFrame:
    """Distinct (a, b), a < b: members of one bucket that lie in different components. near: a condition on l.* and r.*
    columns of entries, under which they are told."""
    left = unsettled(entries, component)
    on = (F.col("l.bucket") == F.col("r.bucket")) & (F.col("l.component") < F.col("r.component"))
    pairs = left.alias("l").join(left.alias("r"), on if near is None else on & near)
    return pairs.select(F.least("l.id", "r.id").alias("a"), F.greatest("l.id", "r.id").alias("b")).distinct()
