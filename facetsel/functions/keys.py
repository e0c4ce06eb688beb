"""Order keys that Spark and DuckDB compute alike, and a distributed n-th smallest key."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F
from pyspark.sql import types as T

TIE_BITS = 60
#: The most bins that a pass of nth_key_cutoff tells to the driver; the bits it settles follow from the number of groups.
MOST_BINS = 1_000_000


def tie_key(seed: int, key: str | Column) -> Column:
    """The first 15 hex digits of md5('seed|key') as a bigint of 60 bits."""
    key = F.col(key) if isinstance(key, str) else key
    return F.conv(F.substring(F.md5(F.concat(F.lit(f"{seed}|"), key.cast("string"))), 1, 15), 16, 10).cast("long")


def rank_key(score: Column, tie: Column, best: int = 5) -> Column:
    """Small for good scores, then for small ties."""
    return (F.lit(best) - score).cast("long") * F.lit(1 << TIE_BITS) + tie


def nth_key_cutoff(df: DataFrame, by: str, key: str, wanted: dict[int, int]) -> dict[int, int]:
    """For each group the n-th smallest of its non-negative bigint keys: keys up to the returned value are n, or all of
    the group where it has fewer (then the value is 2^63 - 1); n = 0 gives -1.

    Digit by digit from the top: counts of the next bits by group, of keys that share the digits settled so far. A pass
    is one aggregation with map-side combining; the pool is never sorted nor shuffled. Ends early for a group whose
    bin holds exactly what is still wanted."""
    spark = df.sparkSession
    bits = max(4, min(14, (MOST_BINS // max(1, len(wanted))).bit_length() - 1))
    out = {g: -1 for g, n in wanted.items() if n <= 0}
    live = {g: (0, n) for g, n in wanted.items() if n > 0}
    shift = 63
    schema = T.StructType([T.StructField("g_", T.IntegerType()), T.StructField("p_", T.LongType())])
    while live:
        above, shift = shift, max(0, shift - bits)
        seen = spark.createDataFrame([(int(g), int(p)) for g, (p, _) in live.items()], schema)
        rows = df.join(F.broadcast(seen), F.col(by) == F.col("g_"))
        if above < 63:
            rows = rows.where(F.shiftright(key, above) == F.col("p_"))
        bins = rows.groupBy("g_", F.shiftright(key, shift).alias("bin")).agg(F.count("*").alias("n"))
        by_group: dict[int, list[tuple[int, int]]] = {}
        for r in bins.collect():
            by_group.setdefault(r["g_"], []).append((r["bin"], r["n"]))
        following = {}
        for g, (_, n) in live.items():
            left = n
            for b, c in sorted(by_group.get(g, [])):
                if c >= left:
                    if c == left or shift == 0:
                        out[g] = ((b + 1) << shift) - 1
                    else:
                        following[g] = (b, left)
                    break
                left -= c
            else:
                out[g] = (1 << 63) - 1
        live = following
    return out


def ranked_between(df: DataFrame, key: str, lo: int, hi: int) -> DataFrame:
    """The rows of ranks lo + 1 to hi by key, exactly hi - lo of them or all there are: two cuts and a filter, not a sort.
    Rows of one key at a cut, as repeated rows have, are told apart by a digest of all their columns."""
    keyed = df.withColumn("__g", F.lit(0)).select("__g", F.col(key).alias("__k"))
    low, high = (nth_key_cutoff(keyed, "__g", "__k", {0: n})[0] for n in (lo, hi))
    below = lambda c: F.count(F.when(F.col("__k") < F.lit(c), 1))
    upto = lambda c: F.count(F.when(F.col("__k") <= F.lit(c), 1))
    n = keyed.agg(below(low).alias("bl"), upto(low).alias("ul"), below(high).alias("bh"), upto(high).alias("uh")).first()
    if n["ul"] <= lo and n["uh"] <= hi:
        return df.where((F.col(key) > F.lit(low)) & (F.col(key) <= F.lit(high)))
    middle = df.where((F.col(key) > F.lit(low)) & (F.col(key) < F.lit(high)))
    edges = df.where(F.col(key).isin(low, high))
    digest = F.xxhash64(*[F.to_json(F.col(c)) if isinstance(t.dataType, (T.MapType, T.VariantType)) else F.col(c) for c, t in zip(df.columns, df.schema, strict=True)])
    before = F.when(F.col(key) == F.lit(low), F.lit(n["bl"])).otherwise(F.lit(n["bh"]))
    ranked = edges.withColumn("__rank", before + F.row_number().over(W.partitionBy(key).orderBy(digest)))
    return middle.unionByName(ranked.where((F.col("__rank") > lo) & (F.col("__rank") <= hi)).drop("__rank"))


def smallest(df: DataFrame, key: str, n: int) -> DataFrame:
    """The n rows of least key."""
    return ranked_between(df, key, 0, n)
