"""Teachers: who judges the small sample."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from facetsel.catalog import FACET_NAMES, FACETS, STYLES
from facetsel.functions import rubric
from facetsel.functions.keys import nth_key_cutoff, tie_key
from facetsel.functions.session import ship


def teacher_sample(pool: DataFrame, fraction: float, seed: int = 42, exact: bool = True, key: str = "instance_id") -> DataFrame:
    """A uniform share of the pool by hash. exact: as many rows as the share of the count, found by counting digits of the
    hash; else every row whose hash lies below the share, in one narrow filter."""
    tie = tie_key(seed, key)
    if not exact:
        return pool.where(tie < F.lit(int(fraction * (1 << 60))))
    n = int(round(pool.count() * 100 * fraction)) // 100
    cut = nth_key_cutoff(pool.select(F.lit(0).alias("__g"), tie.alias("__k")), "__g", "__k", {0: n})[0]
    return pool.where(tie <= F.lit(cut))


class RubricTeacher:
    """Levels by thresholds over lexical measures; coarse knows only some of the levels."""

    def __init__(self, levels: tuple[int, ...] = (1, 2, 3, 4, 5)):
        self.levels = levels

    def judge(self, instances: DataFrame) -> DataFrame:
        return rubric.judge_wide(rubric.featurize(instances), self.levels)


class NoisyTeacher(RubricTeacher):
    """The rubric with seeded noise: scores move by one either way in 15 per cent each, flags flip in 5 per cent."""

    def __init__(self, seed: int = 7):
        super().__init__()
        self.seed = seed

    def judge(self, instances: DataFrame) -> DataFrame:
        j = super().judge(instances)
        roll = lambda name: F.pmod(tie_key(self.seed, F.concat_ws("|", F.col("instance_id").cast("string"), F.lit(name))), F.lit(100))
        out = {}
        for f in FACET_NAMES:
            moved = F.col(f"r_{f}") + F.when(roll(f) < 15, -1).when(roll(f) >= 85, 1).otherwise(0)
            out[f"r_{f}"] = F.greatest(F.lit(0), F.least(F.lit(5), moved)).cast("int")
        for s in STYLES:
            out[f"g_{s}"] = F.when(roll(s) < 5, 1 - F.col(f"g_{s}")).otherwise(F.col(f"g_{s}")).cast("int")
        return j.select("instance_id", "source", "lang", *[c.alias(k) for k, c in out.items()])


class TableTeacher:
    """Judgements made elsewhere: a table with instance_id, facet, score (and instance_id, style, flag)."""

    def __init__(self, scores: DataFrame, flags: DataFrame):
        self.scores, self.flags = scores, flags

    def judge(self, instances: DataFrame) -> DataFrame:
        r = self.scores.groupBy("instance_id").pivot("facet", list(FACET_NAMES)).agg(F.max("score"))
        g = self.flags.groupBy("instance_id").pivot("style", list(STYLES)).agg(F.max("flag"))
        j = instances.select("instance_id", "source", "lang").join(r, "instance_id").join(g, "instance_id", "left")
        return j.select("instance_id", "source", "lang", *[F.coalesce(F.col(f), F.lit(0)).cast("int").alias(f"r_{f}") for f in FACET_NAMES], *[F.coalesce(F.col(s), F.lit(0)).cast("int").alias(f"g_{s}") for s in STYLES])


class BatchTeacher:
    """An outside judge that is asked in batches: ask(texts) gives for each text a dict of facet scores and style flags.
    Batches come by Arrow; one that fails is asked again, tries times; missing answers are 0, scores are held to 0..5."""

    def __init__(self, ask: Callable[[list[str]], list[dict[str, int]]], batch: int = 64, tries: int = 3):
        self.ask, self.batch, self.tries = ask, batch, tries

    def judge(self, instances: DataFrame) -> DataFrame:
        ship(instances.sparkSession)
        ask, size, tries = self.ask, self.batch, self.tries
        columns = {f"r_{f}": (f, 5) for f in FACET_NAMES} | {f"g_{s}": (s, 1) for s in STYLES}

        def patiently(texts: list[str]) -> list[dict[str, int]]:
            for left in range(tries - 1, -1, -1):
                try:
                    return ask(texts)
                except OSError:
                    if not left:
                        raise
            return []

        def judged(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for whole in batches:
                for i in range(0, whole.num_rows, size):
                    b = whole.slice(i, size)
                    said = patiently([t or "" for t in b.column("body").to_pylist()])
                    more = [pa.array([max(0, min(most, int(x.get(name) or 0))) for x in said], pa.int32()) for name, most in columns.values()]
                    yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), b.column(2), *more], names=["instance_id", "source", "lang", *columns])

        schema = "instance_id long, source string, lang string, " + ", ".join(f"{c} int" for c in columns)
        return instances.select("instance_id", "source", "lang", "body").mapInArrow(judged, schema)


def quality_judgement(instances: DataFrame) -> DataFrame:
    """One abstract criterion in place of the facets, and the one style 'any': 5 less a level each for junk symbols,
    shouting and repeated lines (two levels where they are many), 0 for texts without words."""
    f = instances.select("instance_id", "source", "lang", F.expr("cast(regexp_count(body, '[^ \\n]+') as bigint)").alias("n"), F.expr("cast(regexp_count(body, '[#$%&*|]') as bigint)").alias("junk"), F.expr("cast(regexp_count(body, '[A-Z]{4,}') as bigint)").alias("shout"), F.expr("cast(size(split(body, '\\n')) - size(array_distinct(split(body, '\\n'))) as bigint)").alias("rep"))
    return f.select("instance_id", "source", "lang", F.expr(QUALITY_LEVEL).cast("int").alias("r_quality"), F.lit(1).alias("g_any"))


QUALITY_LEVEL = "case when n = 0 then 0 else 5 - (case when junk * 10 >= n then 2 when junk * 50 >= n then 1 else 0 end) - (case when shout * 10 >= n then 2 when shout * 50 >= n then 1 else 0 end) - (case when rep >= 1 then 1 else 0 end) end"
QUALITY_SQL = rf"""SELECT instance_id, source, lang, CAST({QUALITY_LEVEL} AS INT) AS r_quality, 1 AS g_any, n FROM (
  SELECT instance_id, source, lang, len(regexp_extract_all(body, '[^ \n]+')) AS n, len(regexp_extract_all(body, '[#$%&*|]')) AS junk, len(regexp_extract_all(body, '[A-Z]{{4,}}')) AS shout,
         len(string_split(body, chr(10))) - len(list_distinct(string_split(body, chr(10)))) AS rep FROM (FLAT))"""


def judgement_cost(n_sample: int, n_facets: int = len(FACETS), n_styles: int = len(STYLES)) -> int:
    return n_sample * (n_facets + n_styles)
