"""What is taken out of a pool before the teacher's sample is drawn: near copies, and instances that hold a benchmark's
text. Built-in functions only; words are the rubric's tokens."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from facetsel.functions.graph import SLICES, bucket_pairs, components
from facetsel.functions.session import kept, released
from facetsel.operators.baselines import tokens

SHINGLE, SIMILAR, SHARED = 5, 0.8, 8
#: Numbers of 64 bits that tell by parities which sets may be similar; a power of two.
PARITIES = 8


def shingles(texts: DataFrame, key: str, text: str, size: int) -> DataFrame:
    """(id, h): distinct hashes of the runs of size tokens; a text of fewer has itself as the one run."""
    cut = texts.select(F.col(key).alias("id"), F.explode(F.array(tokens(F.col(text)))).alias("t")).where(F.size("t") > 0)
    at = cut.select("id", "t", F.posexplode("t").alias("i", "w"))
    # of a text shorter than a run, what lies behind its end is null, and only its first place counts
    run = F.xxhash64(*[F.get("t", F.col("i") + k) for k in range(size)])
    return at.where((F.col("i") + size <= F.size("t")) | (F.col("i") == 0)).select("id", run.alias("h")).distinct()


def sets_of(pool: DataFrame, key: str, text: str, size: int) -> DataFrame:
    """(id, s): the sorted distinct hashes of shingles(), built where the text lies; only rows of an id that repeats are
    brought together."""
    cut = pool.select(F.col(key).alias("id"), F.explode(F.array(tokens(F.col(text)))).alias("t")).where(F.size("t") > 0)
    run = lambda i: F.xxhash64(*[F.get("t", i + k) for k in range(size)])
    starts = F.sequence(F.lit(0), F.greatest(F.size("t") - size, F.lit(0)))
    rows = kept(cut.select("id", F.sort_array(F.array_distinct(F.transform(starts, run))).alias("s")), "sets")
    again = rows.groupBy("id").agg(F.count("*").alias("n")).where("n > 1").select("id")
    if again.isEmpty():
        return rows
    again = kept(again, "again")
    one = rows.join(again, "id").groupBy("id").agg(F.sort_array(F.array_distinct(F.flatten(F.collect_list("s")))).alias("s"))
    out = kept(rows.join(again, "id", "left_anti").unionByName(one), "sets")
    released(rows, again)
    return out


def _of_sets(pairs: DataFrame, sets: DataFrame, part: Column) -> DataFrame:
    """pairs (a, b, ...) with that part of their sets, sa and sb. Only sets of the pairs move."""
    needed = pairs.select(F.explode(F.array("a", "b")).alias("id")).distinct()
    own = sets.select("id", part.alias("s")).join(needed, "id", "left_semi")
    side = lambda c: own.select(F.col("id").alias(c), F.col("s").alias(f"s{c}"))
    return pairs.join(side("a"), "a").join(side("b"), "b")


def marks(sets: DataFrame) -> DataFrame:
    """(id, n, p0, p1, ...), kept: the size of each set, and which of 64 * PARITIES bits an odd number of its hashes has."""
    rows = sets.select("id", F.size("s").alias("n"), F.explode("s").alias("h"))
    odd = [F.expr(f"bit_xor(if((shiftright(h, 6) & {PARITIES - 1}) = {k}, shiftleft(1L, cast(h & 63 as int)), 0L))").alias(f"p{k}") for k in range(PARITIES)]
    return kept(rows.groupBy("id").agg(F.max("n").alias("n"), *odd), "marks")


def alike(similar: float) -> Column:
    """Whether sizes and parities of l and r allow the similarity, which loses no link: a hash of one set only turns one bit,
    and of so many at most a link may have."""
    size = F.expr(f"least(l.n, r.n) >= {similar} * greatest(l.n, r.n) - 1e-9")
    turned = " + ".join(f"bit_count(l.p{k} ^ r.p{k})" for k in range(PARITIES))
    return size & (F.expr(turned) <= (F.col("l.n") + F.col("r.n")) * ((1 - similar) / (1 + similar)) + 1e-6)


def may_link(similar: float) -> Column:
    """Whether the least hashes sa and sb of two sets of na and nb allow the similarity, which loses no link: up to the last
    hash that both show, what only one of them has is of one set only, and of so many at most a link may have."""
    last = F.least(F.element_at("sa", -1), F.element_at("sb", -1))
    upto = lambda c: F.size(F.filter(c, lambda x: x <= last))
    apart = upto("sa") + upto("sb") - 2 * F.size(F.array_intersect("sa", "sb"))
    return apart <= (F.col("na") + F.col("nb")) * ((1 - similar) / (1 + similar)) + 1e-6


def near_duplicates(pool: DataFrame, key: str = "instance_id", text: str = "body", similar: float = SIMILAR) -> DataFrame:
    """(id, component, stays) of every row with tokens: sets of runs of five tokens whose Jaccard similarity is reached are
    linked; of each connected group the least id stays.

    No link is lost: of two sets that are similar enough, the first n - ceil(similar * n) + 1 runs by hash hold a common
    one, so only these are keys, a fifth of all. Equal sets are one node. Pairs of different groups
    are told apart by parities of their sets inside the join, all by their first runs, as far as these show how many runs are
    of one set only, and what is left is verified on the full sets, in slices."""
    sets = sets_of(pool, key, text, SHINGLE)
    told = kept(sets.select("id", F.size("s").alias("n"), F.xxhash64("s").alias("d1"), F.xxhash64(F.lit(7), F.col("s")).alias("d2")), "digests")
    same = kept(told.groupBy("d1", "d2").agg(F.min("id").alias("rep")), "same")
    owned = kept(told.join(same, ["d1", "d2"]).select("id", "rep", "n"), "owned")
    released(told, same)
    head = F.slice("s", F.lit(1), (F.size("s") - F.ceil(F.size("s") * similar - 1e-9) + 1).cast("int"))
    heads = sets.select("id", head.alias("head")).join(owned.where("id = rep").select("id"), "id", "left_semi")
    entries = kept(heads.select("id", F.explode("head").alias("bucket")), "heads")

    def verified(pairs: DataFrame) -> DataFrame:
        """Sizes that exclude a link are told before first runs are fetched, and those that do before sets are fetched; of
        a slice of the pairs the sets go before the next one's move."""
        size = lambda c: owned.select(F.col("id").alias(c), F.col("n").alias(f"n{c}"))
        close = pairs.join(size("a"), "a").join(size("b"), "b").where(F.expr(f"least(na, nb) >= {similar} * greatest(na, nb) - 1e-9"))
        close, found = kept(close, "close"), []
        for k in range(SLICES):
            own = close.where(F.pmod(F.xxhash64("a"), F.lit(SLICES)) == k)
            near = kept(_of_sets(own, sets, head).where(may_link(similar)).select("a", "b"), "may-link")
            common = F.size(F.array_intersect("sa", "sb"))
            both = _of_sets(near, sets, F.col("s"))
            found.append(kept(both.where(common >= similar * (F.size("sa") + F.size("sb") - common) - 1e-9).select("a", "b"), "near"))
            released(near)
        released(close)
        return reduce(DataFrame.unionByName, found)

    tried = bucket_pairs(entries)
    links = verified(tried)
    groups = components(links)
    marked = marks(sets)
    open_pairs = bucket_pairs(entries, groups, marked, alike(similar))
    left = kept(open_pairs.join(tried, ["a", "b"], "left_anti"), "pairs-left")
    released(tried, open_pairs, entries, marked)
    more = verified(left)
    released(left)
    groups = groups if more.isEmpty() else components(links.unionByName(more))
    out = owned.join(groups, F.col("rep") == F.col("node"), "left").select("id", F.coalesce("component", "rep").alias("component"))
    return out.withColumn("stays", F.col("id") == F.col("component"))


def contaminated(pool: DataFrame, benchmark: DataFrame, key: str = "instance_id", text: str = "body", item_text: str = "text", shared: int = SHARED) -> DataFrame:
    """(id) of rows that share a run of so many tokens with a benchmark item. The benchmark's runs are broadcast only if
    Spark finds them small; the pool is cut once and never joined with itself."""
    items = benchmark.select(F.monotonically_increasing_id().alias("item"), F.col(item_text).alias("t")).where(F.size(tokens(F.col("t"))) >= shared)
    held = kept(shingles(items, "item", "t", shared).select("h").distinct(), "benchmark-runs")
    return shingles(pool, key, text, shared).join(held, "h", "left_semi").select("id").distinct()


def clean_pool(pool: DataFrame, benchmark: DataFrame, key: str = "instance_id", text: str = "body") -> DataFrame:
    """pool without later near copies and without rows that share text with the benchmark."""
    gone = near_duplicates(pool, key, text).where("not stays").select("id").unionByName(contaminated(pool, benchmark, key, text))
    return pool.join(kept(gone.distinct(), "gone").withColumnRenamed("id", key), key, "left_anti")
