"""Every registered query of the library runs on the smallest tables, and equals its SQL where it has some."""

import math
import os

import duckdb
import pytest

import __spark_entry__ as entry
from facetsel.registry import oracle_sql, queries

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
#: Student fits and whole workloads take minutes; they run in the round's checks.
SLOW = {"student_ordinal", "w1_main", "w2_ablation", "w3_transfer", "w4_small_model", "w5_scaling", "w6_growth", "w7_overview", "draw_rounds_05", "draw_cutoff_10", "transfer_chat_to_docs", "style_student"}


@pytest.fixture(scope="module")
def duck(sf_dir):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"create view {t} as select * from '{sf_dir}/{t}.parquet'")
    return con


def shown(v):
    if isinstance(v, float):
        return "nan" if math.isnan(v) else repr(round(v, 9) + 0.0)
    return str(v)


@pytest.mark.parametrize("name", sorted(set(queries()) - (SLOW if not os.environ.get("ALL_QUERIES") else set())))
def test_query(spark, sf_dir, duck, name):
    df = queries()[name](spark, sf_dir)
    columns = sorted(df.columns)
    rows = sorted(tuple(map(shown, r)) for r in df.select(*[f"`{c}`" for c in columns]).collect())
    sql = oracle_sql().get(name)
    if sql:
        got = duck.execute(sql)
        names = [x[0] for x in got.description]
        assert sorted(names) == columns
        at = [names.index(c) for c in columns]
        assert rows == sorted(tuple(shown(r[i]) for i in at) for r in got.fetchall())


def test_entry(spark):
    assert entry.entry(spark).count() == 20


def test_selection_reads_no_text_twice(spark, sf_dir):
    """What is drawn from is compact: no plan after judging reads the text, and the cutoff engine has no window or Python
    over the pool."""
    from facetsel.operators.cells import Layout, pack
    from facetsel.operators.draw import _cutoff_sweep, source_index
    from facetsel.plans.selection import judged

    layout = Layout(("stem", "langgen"), ("terse", "longform"))
    table = source_index(pack(judged(spark, sf_dir), layout.facets, layout.styles), layout)
    plan = _cutoff_sweep(table, layout, {0: 3, 1: 3, 2: 2, 3: 2})._jdf.queryExecution().executedPlan().toString()
    assert "text" not in plan and "Window" not in plan and "Python" not in plan and "Pandas" not in plan
