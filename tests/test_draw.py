import random

import pytest
from pyspark.sql import functions as F

from facetsel.functions.keys import nth_key_cutoff, smallest, tie_key
from facetsel.operators.cells import Layout, allot_quotas, cell_sizes, pack, resolve_budget
from facetsel.operators.draw import Pool, balanced_draw, extend_selection, reference_draw

SIX = [(1, "s", (5, 0), (1, 0), 0), (2, "s", (4, 5), (1, 1), 0), (3, "s", (4, 3), (0, 1), 0), (4, "s", (1, 4), (1, 0), 0), (5, "s", (0, 0), (1, 1), 0), (6, "s", (2, 2), (0, 0), 0)]


def frame(spark, rows, facets="ab", styles="st"):
    schema = "instance_id long, source string, " + ", ".join([*(f"r_{f} int" for f in facets), *(f"g_{s} int" for s in styles)])
    return spark.createDataFrame([(i, src, *r, *g) for i, src, r, g, _ in rows], schema)


@pytest.mark.parametrize("b, chosen", [(0, []), (1, [1]), (2, [1, 2]), (3, [1, 2, 4]), (4, [1, 2, 3, 4]), (5, [1, 2, 3, 4])])
def test_worked_example(b, chosen):
    layout = Layout(("a", "b"), ("s", "t"))
    assert sorted(x[0] for x in reference_draw(SIX, layout, b, allot_quotas(b, layout))) == chosen


def test_second_sweep():
    rows = [(10, "s", (3,), (1, 0), 0), (11, "s", (2,), (1, 0), 0), (12, "s", (1,), (1, 0), 0)]
    layout = Layout(("a",), ("s", "t"))
    assert reference_draw(rows, layout, 2, allot_quotas(2, layout)) == [(10, 0, 1), (11, 0, 2)]


@pytest.mark.parametrize("b", [0, 1, 11, 12, 13, 100])
@pytest.mark.parametrize("remainder", ["first", "rotating", "largest"])
def test_quotas_add_up(b, remainder):
    layout = Layout(("a", "b"), ("s", "t"), ("x", "y", "z"))
    q = allot_quotas(b, layout, remainder, {3: 9, 5: 10})
    assert sum(q) == b and max(q) - min(q) <= 1
    if b == 1:
        assert q.index(1) == {"first": 0, "rotating": 0, "largest": 5}[remainder]


def test_rotating_touches_every_pair():
    layout = Layout(("a", "b", "c"), ("s", "t"), ("x", "y", "z", "u"))
    q = allot_quotas(6, layout, "rotating")
    assert len({layout.cell(j)[:2] for j in range(layout.n) if q[j]}) == 6


def test_budget():
    assert resolve_budget(1000, "5 %") == 50 and resolve_budget(1000, 0.3) == 300 and resolve_budget(10, 10) == 10
    with pytest.raises(ValueError):
        resolve_budget(10, 11)


def random_rows(n, seed, sources=("p", "q", "r")):
    r = random.Random(seed)
    return [(i, r.choice(sources), tuple(r.choice((0, 0, 1, 2, 3, 5)) for _ in range(3)), tuple(int(r.random() < 0.4) for _ in range(3)), 0) for i in range(n)]


def with_ties(spark, rows, seed=42):
    ids = spark.createDataFrame([(x[0],) for x in rows], "instance_id long")
    tie = {r[0]: r[1] for r in ids.select("instance_id", tie_key(seed, "instance_id")).collect()}
    return [(*x[:4], tie[x[0]]) for x in rows]


@pytest.mark.parametrize("by_source", ["none", "flat"])
@pytest.mark.parametrize("b", [7, 60, 170])
def test_engines_agree(spark, b, by_source):
    rows = with_ties(spark, random_rows(220, b))
    df = frame(spark, rows, "abc", "stu")
    layout = Layout(tuple("abc"), tuple("stu"), ("p", "q", "r") if by_source == "flat" else ())
    want = sorted(reference_draw(rows, layout, b, allot_quotas(b, layout)))
    for engine in ("serial", "cutoff") + (("rounds",) if b == 60 else ()):
        got = balanced_draw(df, b, tuple("abc"), tuple("stu"), engine=engine, by_source=by_source)
        assert sorted((r.instance_id, r.cell_id, r.pick_round) for r in got.collect()) == want, engine


def test_interleave_and_nested(spark):
    rows = with_ties(spark, random_rows(150, 3))
    df, layout = frame(spark, rows, "abc", "stu"), Layout(tuple("abc"), tuple("stu"))
    got = balanced_draw(df, 40, tuple("abc"), tuple("stu"), order="interleave")
    assert sorted((r.instance_id, r.cell_id, r.pick_round) for r in got.collect()) == sorted(reference_draw(rows, layout, 40, [1] * 9, "interleave"))
    nested = balanced_draw(df, 40, tuple("abc"), tuple("stu"), by_source="nested").collect()
    assert len({r.instance_id for r in nested}) == 40


def test_stable_and_complete(spark):
    rows = with_ties(spark, random_rows(200, 9))
    df = frame(spark, rows, "abc", "stu")
    got = balanced_draw(df, 200, tuple("abc"), tuple("stu")).collect()
    inside = {x[0] for x in rows if max(x[2]) > 0 and any(x[3])}
    assert {r.instance_id for r in got} == inside
    by = {x[0]: x for x in rows}
    assert all(by[r.instance_id][2]["abc".index(r.facet)] == r.score > 0 and by[r.instance_id][3]["stu".index(r.style)] for r in got)


def test_extension_leaves_old_picks(spark):
    rows = with_ties(spark, random_rows(150, 5))
    df = frame(spark, rows, "abc", "stu")
    first = balanced_draw(df, 30, ("a", "b"), tuple("stu"))
    more = extend_selection(first, df, "c", 10, tuple("stu")).collect()
    assert len(more) == 10 and {r.facet for r in more} == {"c"}
    assert not {r.instance_id for r in more} & {r.instance_id for r in first.collect()}


def test_nth_key(spark):
    df = spark.range(1000).select((F.col("id") % 3).cast("int").alias("g"), tie_key(1, "id").alias("k"))
    keys = {g: sorted(r.k for r in df.where(F.col("g") == g).collect()) for g in range(3)}
    cut = nth_key_cutoff(df, "g", "k", {0: 5, 1: 0, 2: 10_000, 9: 3})
    assert sum(k <= cut[0] for k in keys[0]) == 5 and cut[1] == -1 and cut[2] == cut[9] == 2**63 - 1
    assert smallest(df, "k", 17).count() == 17


def test_sizes(spark):
    df = frame(spark, SIX)
    assert cell_sizes(pack(df, "ab", "st"), Layout(("a", "b"), ("s", "t"))) == {0: 3, 1: 2, 2: 2, 3: 2}
    assert Pool([1], ["s"], __import__("numpy").array([0]), __import__("numpy").array([0]), Layout(("a",), ("s",))).draw(1, [1], "sweep") == []
