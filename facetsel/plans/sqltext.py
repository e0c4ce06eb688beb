"""DuckDB SQL of the draws, for the oracle: cells as ordered lists, the sweep as a recursion over cells."""

from __future__ import annotations

from facetsel.catalog import DEFAULT_FACETS, STYLES
from facetsel.functions import rubric
from facetsel.functions.dialect import DUCK
from facetsel.sources.pools import FLAT_SQL

TIE = DUCK.tie(42, "instance_id")


def judged(pool: str = "docs", levels=(1, 2, 3, 4, 5)) -> str:
    return rubric.sql(FLAT_SQL[pool], levels)


def draw_ctes(b: str, facets=DEFAULT_FACETS, styles=STYLES, source: str = "judged", by_source: str = "none", remainder: str = "first", order: str = "sweep", name: str = "drawn") -> str:
    """CTEs that end in name(instance_id, source, cell_id, facet, style, score, pick_round, pick_rank). b: an SQL
    expression. source: a relation with instance_id, source, r_*, g_*."""
    s = len(styles)
    pairs = ", ".join(f"{{'p': {i * s + k}, 'r': r_{f}, 'g': g_{t}}}" for i, f in enumerate(facets) for k, t in enumerate(styles))
    flat = by_source == "flat"
    n_src = f"(SELECT count(DISTINCT source) FROM {source})" if flat else "1"
    src = f"(SELECT count(DISTINCT y.source) FROM {source} y WHERE y.source < x.source)" if flat else "0"
    src_of = f"{name}_src AS (SELECT x.source, {src} AS src FROM (SELECT DISTINCT source FROM {source}) x),"
    key = "score DESC, tie, instance_id"
    if by_source == "nested":
        key = "turn, " + key
    if remainder == "rotating":
        place = f"row_number() OVER (ORDER BY ((j % {name}_k.r - j // {name}_k.r // {s} - j // {name}_k.r % {s}) % {name}_k.r + {name}_k.r) % {name}_k.r, ((j // {name}_k.r % {s} - j // {name}_k.r // {s}) % {s} + {s}) % {s}, j // {name}_k.r // {s})"
    elif remainder == "largest":
        place = "row_number() OVER (ORDER BY len(m) DESC, j)"
    else:
        place = "j + 1"
    quota = f"{name}_k.b // {name}_k.n + CASE WHEN {place} <= {name}_k.b % {name}_k.n THEN 1 ELSE 0 END"
    first = "1" if order == "interleave" else "q"
    taken = "list_filter(c.cells[d.live[d.j + 1] + 1], lambda x: NOT list_contains(d.used, x))[1:least(d.quotas[d.j + 1], k.b - len(d.used))]"
    live = "list_filter(range(k.n), lambda z: len(list_filter(c.cells[z + 1], lambda x: NOT list_contains(d.used, x))) > 0)"
    left = "(k.b - len(d.used))"
    again = "1" if order == "interleave" else f"{left} // len(live) + CASE WHEN z < {left} % len(live) THEN 1 ELSE 0 END"
    return f"""{src_of}
{name}_k AS (SELECT CAST({b} AS BIGINT) AS b, CAST({len(facets) * s} * {n_src} AS BIGINT) AS n, CAST({n_src} AS BIGINT) AS r),
{name}_m AS (SELECT instance_id, source, {TIE} AS tie, unnest([{pairs}]) AS c FROM {source}),
{name}_l AS (SELECT c.p * (SELECT r FROM {name}_k) + s.src AS j, instance_id, c.r AS score, tie, m.source,
  row_number() OVER (PARTITION BY c.p, m.source ORDER BY c.r DESC, tie, instance_id) AS turn
  FROM {name}_m m JOIN {name}_src s ON s.source IS NOT DISTINCT FROM m.source WHERE c.r > 0 AND c.g = 1),
{name}_c AS (SELECT z.j, coalesce(list(instance_id ORDER BY {key}) FILTER (instance_id IS NOT NULL), []) AS m
  FROM (SELECT unnest(range((SELECT n FROM {name}_k))) AS j) z LEFT JOIN {name}_l l ON l.j = z.j GROUP BY z.j),
{name}_q AS (SELECT j, m, {quota} AS q FROM {name}_c, {name}_k),
{name}_a AS (SELECT list(m ORDER BY j) AS cells, list(CAST({first} AS BIGINT) ORDER BY j) AS quotas FROM {name}_q),
{name}_r AS (
  SELECT 1 AS sweep, 0 AS j, CAST(NULL AS BIGINT) AS cell, CAST([] AS BIGINT[]) AS used, CAST([] AS BIGINT[]) AS picked, c.quotas AS quotas,
         CAST(range(k.n) AS BIGINT[]) AS live FROM {name}_a c, {name}_k k
  UNION ALL (
  SELECT sweep, j, cell, list_concat(used, picked), picked, quotas, live FROM (
    SELECT d.sweep, d.j + 1 AS j, d.live[d.j + 1] AS cell, d.used, {taken} AS picked, d.quotas, d.live
    FROM {name}_r d, {name}_a c, {name}_k k WHERE d.j < len(d.live) AND len(d.used) < k.b)
  UNION ALL
  SELECT sweep, 0, NULL, used, CAST([] AS BIGINT[]), list_transform(range(len(live)), lambda z: CAST({again.replace(left, 'rest')} AS BIGINT)), live FROM (
    SELECT d.sweep + 1 AS sweep, d.used, k.b - len(d.used) AS rest, CAST({live} AS BIGINT[]) AS live
    FROM {name}_r d, {name}_a c, {name}_k k WHERE d.j = len(d.live) AND len(d.used) < k.b AND len(d.live) > 0))),
{name}_p AS (SELECT sweep, cell, unnest(picked) AS instance_id, generate_subscripts(picked, 1) AS pick_rank FROM {name}_r WHERE len(picked) > 0),
{name} AS (SELECT p.instance_id, l.source, CAST(p.cell AS INT) AS cell_id, [{", ".join(repr(f) for f in facets)}][CAST(p.cell // k.r // {s} + 1 AS INT)] AS facet,
  [{", ".join(repr(t) for t in styles)}][CAST(p.cell // k.r % {s} + 1 AS INT)] AS style, l.score, CAST(p.sweep AS INT) AS pick_round, CAST(p.pick_rank AS INT) AS pick_rank
  FROM {name}_p p JOIN {name}_l l ON l.j = p.cell AND l.instance_id = p.instance_id, {name}_k k)"""


DRAWN = "instance_id, source, cell_id, facet, style, score, pick_round, pick_rank"


def draw_sql(b: str, pool: str = "docs", levels=(1, 2, 3, 4, 5), **how) -> str:
    return f"WITH RECURSIVE {judged(pool, levels)},\n{draw_ctes(b, **how)}\nSELECT {DRAWN} FROM drawn"
