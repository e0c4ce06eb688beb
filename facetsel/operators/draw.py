"""The balanced draw: an equal share of the budget to every cell, best scores first, nothing twice.

sweep: the cells are gone through in order, each takes its quota of its best members that are still free; what is left
of the budget starts further sweeps over the cells that still have free members. interleave: each cell in turn takes
one.

Engines for the sweep, equal in result:
serial   one task holds the compact rows; for up to SERIAL_ROWS of them.
rounds   deferred acceptance over exploded memberships: every cell proposes to its best members that have not refused
         it, a member keeps its first cell and refuses the others, until none is refused.
cutoff   a cell's outcome is one number, the worst key it accepts. The driver holds one bound for each cell; a round
         scans the compact rows and moves each bound to where the cell has its quota of members that no earlier cell's
         bound takes. No row is shuffled; for any size. Different ids with equal 60 bits of md5 would be taken together.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F
from pyspark.sql import types as T

from facetsel.catalog import DEFAULT_FACETS, STYLES
from facetsel.functions.keys import nth_key_cutoff
from facetsel.functions.session import kept, ship
from facetsel.operators.cells import Layout, allot_quotas, cell_sizes, long_cells, member_keys, pack, source_index

SERIAL_ROWS = 20_000_000
MOST_ROUNDS = 5_000
SELECTED = T.StructType([T.StructField("instance_id", T.LongType()), T.StructField("source", T.StringType()), T.StructField("cell_id", T.IntegerType()), T.StructField("score", T.IntegerType()), T.StructField("pick_round", T.IntegerType()), T.StructField("pick_rank", T.IntegerType())])


class Pool:
    """The compact rows as arrays, with each facet's order; the serial statement of the draw."""

    def __init__(self, ids, source, sig, tie, layout: Layout, nested: bool = False):
        order = np.lexsort((ids, tie))
        self.ids, self.sig, self.tie = (np.asarray(x)[order] for x in (ids, sig, tie))
        self.source, self.layout, self.nested = np.asarray(source, object)[order], layout, nested
        index = {s: i for i, s in enumerate(layout.sources)}
        self.src = np.array([index.get(s, -1) for s in self.source]) if layout.sources else np.zeros(len(ids), int)
        names = {s: i for i, s in enumerate(sorted({x for x in self.source if x is not None}))}
        self.turn_of = np.array([names.get(s, -1) for s in self.source])
        c = len(layout.facets)
        self.scores = [(self.sig >> (3 * i)) & 7 for i in range(c)]
        flags = [((self.sig >> (3 * c + k)) & 1).astype(bool) for k in range(len(layout.styles))]
        by_source = [np.flatnonzero(self.src == s) for s in range(max(1, len(layout.sources)))]
        self.members = []
        for i in range(c):
            ranked = {s: rows[np.argsort(-self.scores[i][rows], kind="stable")] for s, rows in enumerate(by_source)}
            for k in range(len(layout.styles)):
                for s in range(len(by_source)):
                    m = ranked[s][(self.scores[i][ranked[s]] > 0) & flags[k][ranked[s]]]
                    self.members.append(self._take_turns(m, i) if nested else m)

    def _take_turns(self, m: np.ndarray, i: int) -> np.ndarray:
        """Sources take turns in a cell: first the best of every source, then the second best."""
        seen: dict[int, int] = {}
        rank = np.array([seen.__setitem__(s, (n := seen.get(s, -1) + 1)) or n for s in self.turn_of[m]], int)
        return m[np.lexsort((self.ids[m], self.tie[m], -self.scores[i][m], rank))] if len(m) else m

    def free_cells(self, free: np.ndarray) -> list[int]:
        return [j for j, m in enumerate(self.members) if free[m].any()]

    def draw(self, b: int, quotas: Sequence[int], order: str) -> list[tuple]:
        free, out, sweep = np.ones(len(self.ids), bool), [], 0
        live, left = list(range(len(self.members))), b
        while left > 0 and live:
            sweep += 1
            if order == "interleave":
                quotas = [1] * len(live)
            elif sweep > 1:
                base, over = divmod(left, len(live))
                quotas = [base + (k < over) for k in range(len(live))]
            for j, q in zip(live, quotas, strict=True):
                m = self.members[j]
                got = m[free[m]][: min(q, left)]
                free[got] = False
                left -= len(got)
                out += [(int(self.ids[x]), self.source[x], j, int(self.scores[j // max(1, len(self.layout.sources)) // len(self.layout.styles)][x]), sweep, n + 1) for n, x in enumerate(got)]
            live = self.free_cells(free)
        return out


def _serial(table: DataFrame, layout: Layout, b: int, quotas: list[int], order: str, nested: bool) -> DataFrame:
    ship(table.sparkSession)

    def drawn(rows: pd.DataFrame) -> pd.DataFrame:
        pool = Pool(rows["instance_id"].to_numpy(), rows["source"].to_numpy(), rows["sig"].to_numpy(), rows["tie"].to_numpy(), layout, nested)
        return pd.DataFrame(pool.draw(b, quotas, order), columns=SELECTED.names)

    return table.groupBy(F.lit(0).alias("all_")).applyInPandas(drawn, SELECTED)


def _cutoff_sweep(table: DataFrame, layout: Layout, quotas: dict[int, int]) -> DataFrame:
    """One sweep: table with owner (cell or null) and key there."""
    spark, r, pairs = table.sparkSession, max(1, len(layout.sources)), layout.pairs
    rows = table.withColumn("keys", F.array(*member_keys(layout)))
    bounds = {j: -1 for j in range(layout.n)}
    schema = T.StructType([T.StructField("src_", T.IntegerType()), T.StructField("bounds", T.ArrayType(T.LongType()))])

    def owned() -> DataFrame:
        told = spark.createDataFrame([(s, [bounds[j * r + s] for j in range(pairs)]) for s in range(r)], schema)
        with_bounds = rows.join(F.broadcast(told), F.col("src") == F.col("src_")).drop("src_")
        return with_bounds.withColumn("o", F.array_position(F.zip_with("keys", "bounds", lambda k, x: F.coalesce(k <= x, F.lit(False))), True).cast("int"))

    for _ in range(MOST_ROUNDS):
        now = owned()
        reach = F.slice("keys", F.lit(1), F.when(F.col("o") == 0, F.lit(pairs)).otherwise(F.col("o")))
        free = now.select("src", F.posexplode(reach).alias("j", "key")).where("key is not null").select((F.col("j") * r + F.col("src")).cast("int").alias("cell"), "key")
        moved = nth_key_cutoff(free, "cell", "key", quotas)
        if all(moved[j] <= bounds[j] for j in quotas):
            return now.select(*table.columns, F.when(F.col("o") > 0, (F.col("o") - 1) * r + F.col("src")).alias("owner"), F.when(F.col("o") > 0, F.element_at("keys", F.when(F.col("o") > 0, F.col("o")).otherwise(1))).alias("key"))
        bounds |= {j: max(bounds[j], moved[j]) for j in quotas}
    raise RuntimeError("bounds did not settle")


def _rounds_sweep(table: DataFrame, layout: Layout, quotas: dict[int, int]) -> DataFrame:
    spark = table.sparkSession
    cells = kept(long_cells(table.drop("src"), layout).select("cell", "instance_id", "key"), "cells")
    told = F.broadcast(spark.createDataFrame([(int(j), int(q)) for j, q in quotas.items()], "cell int, quota int"))
    cells = cells.join(told, "cell").where("quota > 0")
    by_cell = W.partitionBy("cell").orderBy("key", "instance_id")
    for _ in range(MOST_ROUNDS):
        proposed = cells.withColumn("n", F.row_number().over(by_cell)).where("n <= quota")
        chosen = kept(proposed.withColumn("first", F.min("cell").over(W.partitionBy("instance_id"))).select("cell", "instance_id", "key", "first"), "proposals")
        refused = chosen.where("cell > first").select("cell", "instance_id")
        if refused.isEmpty():
            won = chosen.select("instance_id", F.col("cell").alias("owner"), "key")
            return table.join(won, "instance_id", "left")
        cells = kept(cells.join(refused, ["cell", "instance_id"], "left_anti"), "cells")
    raise RuntimeError("rounds did not settle")


def _sweeps(table: DataFrame, layout: Layout, b: int, quotas: list[int], engine: str) -> DataFrame:
    one = {"cutoff": _cutoff_sweep, "rounds": _rounds_sweep}[engine]
    rest, out, left, n = kept(source_index(table, layout), "draw"), None, b, 0
    todo = dict(enumerate(quotas))
    while left > 0 and todo:
        n += 1
        swept = kept(one(rest, layout, todo), "sweep")
        got = swept.where("owner is not null").withColumn("pick_round", F.lit(n))
        out = got if out is None else out.unionByName(got)
        left -= got.count()
        rest = swept.where("owner is null").drop("owner", "key")
        live = sorted(cell_sizes(rest.drop("src"), layout)) if left > 0 else []
        todo = {j: left // len(live) + (k < left % len(live)) for k, j in enumerate(live)}
    if out is None:
        return table.sparkSession.createDataFrame([], SELECTED)
    rank = F.row_number().over(W.partitionBy("pick_round", "owner").orderBy("key", "instance_id"))
    return out.select("instance_id", "source", F.col("owner").cast("int").alias("cell_id"), (5 - F.shiftright("key", 60)).cast("int").alias("score"), "pick_round", rank.cast("int").alias("pick_rank"))


def balanced_draw(judged: DataFrame, b: int, facets: Sequence[str] = DEFAULT_FACETS, styles: Sequence[str] = STYLES, order: str = "sweep", engine: str = "auto", by_source: str = "none", remainder: str = "first", seed: int = 42, named: bool = True) -> DataFrame:
    """(instance_id, source, cell_id, facet, style, score, pick_round, pick_rank) of b rows of judged, or of all that lie in
    some cell if those are fewer. Rows of one id are one instance, of the greatest scores; missing scores and flags are 0.

    judged: instance_id, source, r_<facet> 0..5, g_<style> 0/1. by_source: none; flat cuts cells by source; nested lets
    sources take turns inside a cell (serial engine)."""
    facets, styles = tuple(facets), tuple(styles)
    table = kept(pack(judged, facets, styles, seed), "packed")
    twice = kept(table.groupBy("instance_id").agg(F.count("*").alias("n")).where("n > 1").select("instance_id"), "repeated")
    if not twice.isEmpty():  # an instance is drawn once, however many rows it has
        one = table.join(twice, "instance_id", "left_semi").groupBy("instance_id").agg(F.max(F.struct("sig", "source", "tie")).alias("x"))
        table = kept(table.join(twice, "instance_id", "left_anti").unionByName(one.select("instance_id", "x.source", "x.sig", "x.tie")), "packed")
    sources = tuple(sorted((r[0] for r in table.select("source").distinct().collect()), key=lambda s: (s is None, s))) if by_source == "flat" else ()
    layout = Layout(facets, styles, sources)
    quotas = allot_quotas(b, layout, remainder, cell_sizes(table, layout) if remainder == "largest" else None)
    if engine == "auto":
        engine = "serial" if order == "interleave" or by_source == "nested" or table.count() <= SERIAL_ROWS else "cutoff"
    if engine == "serial":
        out = _serial(table, layout, b, quotas, order, by_source == "nested")
    elif order == "interleave" or by_source == "nested":
        raise ValueError("interleave and nested need the serial engine")
    else:
        out = _sweeps(table, layout, b, quotas, engine)
    if not named:
        return out
    r, s = max(1, len(sources)), len(styles)
    pair = F.floor(F.col("cell_id") / r)
    name = lambda xs, at: F.element_at(F.array(*map(F.lit, xs)), (at + 1).cast("int"))
    return out.select("instance_id", "source", "cell_id", name(facets, F.floor(pair / s)).alias("facet"), name(styles, pair % s).alias("style"), "score", "pick_round", "pick_rank")


def extend_selection(selected: DataFrame, judged: DataFrame, facet: str, extra: int, styles: Sequence[str] = STYLES, seed: int = 42, **how) -> DataFrame:
    """extra further rows for one more facet; what is selected stays as it is."""
    rest = judged.join(selected.select("instance_id"), "instance_id", "left_anti")
    return balanced_draw(rest, extra, (facet,), styles, seed=seed, **how)


def coverable(judged: DataFrame, facets: Sequence[str], styles: Sequence[str]) -> DataFrame:
    """judged with in_cells: in how many cells a row lies; rows in none can never be drawn."""
    f = sum(((F.col(f"r_{x}") > 0).cast("int") for x in facets), F.lit(0))
    s = sum((F.col(f"g_{x}") for x in styles), F.lit(0))
    return judged.withColumn("in_cells", f * s)


def reference_draw(rows: Iterator[tuple], layout: Layout, b: int, quotas: Sequence[int], order: str = "sweep") -> list[tuple]:
    """The same by plain loops over (id, source, scores, flags, tie), for tests and worked examples: (id, cell, round)."""
    rows = list(rows)
    r = max(1, len(layout.sources))
    cells = []
    for j in range(layout.n):
        c, s = divmod(j // r, len(layout.styles))
        own = [x for x in rows if x[2][c] > 0 and x[3][s] and (not layout.sources or x[1] == layout.sources[j % r])]
        cells.append([x[0] for x in sorted(own, key=lambda x: (-x[2][c], x[4], x[0]))])
    taken, out, sweep, live = set(), [], 0, list(range(layout.n))
    while len(taken) < b and live:
        sweep += 1
        left = b - len(taken)
        share = list(quotas) if sweep == 1 else [left // len(live) + (k < left % len(live)) for k in range(len(live))]
        if order == "interleave":
            share = [1] * len(live)
        for j, q in zip(live, share, strict=True):
            for x in [i for i in cells[j] if i not in taken][: min(q, b - len(taken))]:
                taken.add(x)
                out.append((x, j, sweep))
        live = [j for j in range(layout.n) if any(i not in taken for i in cells[j])]
    return out
