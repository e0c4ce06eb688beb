"""Cells, quotas and the compact draw table."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from facetsel.functions.keys import rank_key, tie_key


def resolve_budget(n: int, budget: int | float | str) -> int:
    """A count, or a share given as '5 %' or a float below 1, of n rows; 0 <= b <= n."""
    if isinstance(budget, str):
        b = int(n * float(budget.strip().rstrip("%")) / 100)
    elif isinstance(budget, float) and budget < 1:
        b = int(n * budget)
    else:
        b = int(budget)
    if not 0 <= b <= n:
        raise ValueError(f"budget {b} is not between 0 and {n}")
    return b


@dataclass(frozen=True)
class Layout:
    """Which cells there are: facets by styles, each cut by the sources if there are any."""

    facets: tuple[str, ...]
    styles: tuple[str, ...]
    sources: tuple[str | None, ...] = ()

    @property
    def pairs(self) -> int:
        return len(self.facets) * len(self.styles)

    @property
    def n(self) -> int:
        return self.pairs * max(1, len(self.sources))

    def cell(self, j: int) -> tuple[str, str, str | None]:
        r = max(1, len(self.sources))
        pair, s = divmod(j, r)
        return self.facets[pair // len(self.styles)], self.styles[pair % len(self.styles)], self.sources[s] if self.sources else None


def pack(judged: DataFrame, facets: Sequence[str], styles: Sequence[str], seed: int = 42) -> DataFrame:
    """(instance_id, source, sig, tie): three bits a score and one bit a flag in one bigint, about 28 bytes a row. All
    that follows reads this and no text. A missing score or flag is 0."""
    sig: Column = F.lit(0).cast("long")
    for i, f in enumerate(facets):
        sig = sig.bitwiseOR(F.shiftleft(F.coalesce(F.col(f"r_{f}").cast("long"), F.lit(0)), 3 * i))
    for i, s in enumerate(styles):
        sig = sig.bitwiseOR(F.shiftleft(F.coalesce(F.col(f"g_{s}").cast("long"), F.lit(0)), 3 * len(facets) + i))
    return judged.select("instance_id", "source", sig.alias("sig"), tie_key(seed, "instance_id").alias("tie"))


def score_of(i: int) -> Column:
    return F.shiftright("sig", 3 * i).bitwiseAND(F.lit(7))


def flag_of(i: int, n_facets: int) -> Column:
    return F.shiftright("sig", 3 * n_facets + i).bitwiseAND(F.lit(1))


def member_keys(layout: Layout) -> list[Column]:
    """For each (facet, style) in order: the row's order key there, null where it is no member."""
    c = len(layout.facets)
    return [F.when((score_of(i) > 0) & (flag_of(k, c) == 1), rank_key(score_of(i), F.col("tie"))) for i in range(c) for k in range(len(layout.styles))]


def source_index(table: DataFrame, layout: Layout) -> DataFrame:
    """table with src, the place of its source in the layout (0 where sources do not cut cells)."""
    if not layout.sources:
        return table.withColumn("src", F.lit(0))
    known = table.sparkSession.createDataFrame([(s, i) for i, s in enumerate(layout.sources)], "s_ string, src int")
    return table.join(F.broadcast(known), F.col("source").eqNullSafe(F.col("s_"))).drop("s_")


def cell_sizes(table: DataFrame, layout: Layout) -> dict[int, int]:
    """Members of every cell that has some: one aggregation of conditional counts, nothing is exploded."""
    r = max(1, len(layout.sources))
    counts = [F.count(k).alias(f"k{j}") for j, k in enumerate(member_keys(layout))]
    rows = source_index(table, layout).groupBy("src").agg(*counts).collect()
    return {j * r + row["src"]: row[f"k{j}"] for row in rows for j in range(layout.pairs) if row[f"k{j}"]}


def allot_quotas(b: int, layout: Layout, remainder: str = "first", sizes: dict[int, int] | None = None) -> list[int]:
    """The equal share of every cell, and the remainder one each: to the first cells in order, to cells that rotate over
    facets, styles and sources, or to the largest."""
    base, over = divmod(b, layout.n)
    r, s, c = max(1, len(layout.sources)), len(layout.styles), len(layout.facets)
    if remainder == "first":
        order = range(layout.n)
    elif remainder == "rotating":
        at = lambda j: (j // r // s, j // r % s, j % r)
        order = sorted(range(layout.n), key=lambda j: ((at(j)[2] - at(j)[0] - at(j)[1]) % r, (at(j)[1] - at(j)[0]) % s, at(j)[0]))
    elif remainder == "largest":
        order = sorted(range(layout.n), key=lambda j: (-(sizes or {}).get(j, 0), j))
    else:
        raise ValueError(f"remainder {remainder!r}")
    out = [base] * layout.n
    for j in list(order)[:over]:
        out[j] += 1
    return out


def long_cells(table: DataFrame, layout: Layout) -> DataFrame:
    """(cell, instance_id, source, key, score): a row for each membership; about thirty times the pool, for inspection and
    for the engine of moderate sizes only."""
    r = max(1, len(layout.sources))
    keyed = source_index(table, layout).select("instance_id", "source", "src", F.posexplode(F.array(*member_keys(layout))).alias("j", "key")).where("key is not null")
    return keyed.select((F.col("j") * r + F.col("src")).alias("cell"), "instance_id", "source", "key", (5 - F.shiftright("key", 60)).cast("int").alias("score"))
