"""The rubric teacher: features of an instance, levels of each facet, flags of each style, as SQL expressions.

Instances have the columns instance_id, body (what is judged), prompt, answer, lang, source, has_context. Features are
computed once, in a projection of their own; levels and flags read only them."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from facetsel.catalog import ENDINGS, FACETS, STYLES, WORDS
from facetsel.functions.dialect import SPARK, Spark


def _in(words: list[str]) -> str:
    return "x in (" + ", ".join(f"'{w}'" for w in words) + ")"


def _ends(endings: list[str]) -> str:
    by_length: dict[int, list[str]] = {}
    for e in endings:
        by_length.setdefault(len(e), []).append(e)
    return " or ".join(f"right(x, {n}) in (" + ", ".join(f"'{e}'" for e in es) + ")" for n, es in sorted(by_length.items()))


def token_columns(d: Spark) -> dict[str, str]:
    return {"t": d.tokens("body"), "prompt_t": d.distinct(d.tokens("prompt")), "answer_t": d.tokens("answer")}


def listed_column(d: Spark) -> str:
    """The tokens that are in some word list; the lists are then counted in this shorter array."""
    return d.kept("t", _in(sorted({w for ws in WORDS.values() for w in ws})))


def feature_columns(d: Spark) -> dict[str, str]:
    """Counts over the tokens t, distinct prompt tokens, answer tokens, and the texts themselves."""
    out = {f"n_{k}": d.where("listed", _in(w)) for k, w in WORDS.items()}
    out |= {f"n_{k}": d.where("t", _ends(e)) for k, e in ENDINGS.items()}
    out |= {
        "n_tokens": d.size("t"),
        "n_distinct": d.size(d.distinct("t")),
        "n_long": d.where("t", "length(x) >= 8"),
        "n_answer": d.size("answer_t"),
        "n_prompt": d.size("prompt_t"),
        "n_reused": d.size(d.common("prompt_t", d.distinct("answer_t"))),
        "n_commas": d.count("body", ","),
        "n_sentences": d.count("body", "[.!?]+"),
        "n_accents": d.count("body", r"[^\x00-\x7F]"),
        "n_capitals": d.count("body", "[a-z,] [A-Z]"),
        "n_signs": d.count("body", "[0-9+*/=%^]"),
        "n_digits": d.count("body", "[0-9]"),
        "n_bars": d.count("body", r"\|"),
        "n_caps_runs": d.count("body", "[A-Z]{4,}"),
        "n_long_caps_runs": d.count("body", "[A-Z]{6,}"),
        "n_symbol_runs": d.count("body", "[#$%&*!]{2,}"),
        "n_shouts": d.count("body", "!!"),
        "n_breaks": d.count("body", r"\n"),
    }
    return out


def measure_columns(d: Spark) -> dict[str, str]:
    per = lambda n, k, whole: d.div(f"{n} * {k}", f"greatest({whole}, 1)")
    return {
        "spatial": per("n_spatial", 1000, "n_tokens"),
        "attributes": per("n_attributes", 100, "n_tokens"),
        "deduction": per("(n_deduction + n_commas)", 10, "n_sentences"),
        "scene": "n_distinct",
        "finegrained": per("n_long", 100, "n_tokens"),
        "langgen": "n_answer",
        "incontext": per("n_reused", 100, "n_prompt"),
        "comparison": per("n_comparison", 1000, "n_tokens"),
        "activity": per("n_activity", 100, "n_tokens"),
        "causality": per("n_causality", 10, "n_sentences"),
        "humanities": "n_accents + n_capitals",
        "stem": "n_signs",
        "datareading": "n_bars",
        "ocr": "n_caps_runs + n_symbol_runs",
    }


def level_columns(d: Spark, levels: tuple[int, ...] = (1, 2, 3, 4, 5)) -> dict[str, str]:
    """Scores 0..5: thresholds reached. A judge that knows only some levels gives the highest of those."""
    out = {}
    for f in FACETS:
        m = measure_columns(d)[f.name]
        cases = " ".join(f"when {m} >= {f.levels[k - 1]} then {k}" for k in sorted(levels, reverse=True))
        out[f.name] = f"case {cases} else 0 end"
    return out


def flag_columns(d: Spark) -> dict[str, str]:
    tests = {
        "terse": "n_answer <= 20",
        "longform": "n_answer >= 200",
        "explanatory": "n_sentences >= 5",
        "itemised": "n_breaks >= 3",
        "tabular": "n_bars >= 6",
        "numeric": "n_digits >= 3",
        "emphatic": "n_shouts > 0 or n_long_caps_runs > 0",
        "nonenglish": "lang <> 'en'",
        "passage": "n_breaks between 1 and 3 or has_context",
    }
    return {s: f"case when {tests[s]} then 1 else 0 end" for s in STYLES}


KEYS = ("instance_id", "source", "lang")


def _sel(df: DataFrame, columns: dict[str, str], kept: tuple[str, ...]) -> DataFrame:
    return df.select(*kept, *[F.expr(e).alias(k) for k, e in columns.items()])


def featurize(instances: DataFrame) -> DataFrame:
    """One row of numbers for each instance; the only step that reads text."""
    with_tokens = _sel(instances, token_columns(SPARK), (*KEYS, "body", "has_context"))
    with_tokens = with_tokens.withColumn("listed", F.expr(listed_column(SPARK)))
    return _sel(with_tokens, feature_columns(SPARK), (*KEYS, "has_context"))


def judge_wide(features: DataFrame, levels: tuple[int, ...] = (1, 2, 3, 4, 5)) -> DataFrame:
    """(instance_id, source, lang, r_<facet>..., g_<style>...): the teacher's judgements."""
    scores = {f"r_{k}": f"cast({e} as int)" for k, e in level_columns(SPARK, levels).items()}
    flags = {f"g_{k}": f"cast({e} as int)" for k, e in flag_columns(SPARK).items()}
    return _sel(features, scores | flags, KEYS)


def rationale_column() -> str:
    """Which thresholds a score met and missed, as JSON."""
    parts = []
    for f in FACETS:
        parts.append(f"when facet = '{f.name}' then concat('{{\"score\":', score, ',\"reached\":', " + f"element_at(array(0,{','.join(map(str, f.levels))}), score + 1), ',\"next\":', coalesce(cast(element_at(array({','.join(map(str, f.levels))},null), score + 1) as string), 'null'), '}}')")
    return "case " + " ".join(parts) + " end"


def sql(instances_sql: str, levels: tuple[int, ...] = (1, 2, 3, 4, 5), name: str = "judged", d: Spark | None = None) -> str:
    """The same, as common table expressions of the other dialect, for the oracle."""
    from facetsel.functions.dialect import DUCK

    d = d or DUCK
    line = lambda cols: ", ".join(f"{e} AS {k}" for k, e in cols.items())
    keys = ", ".join(KEYS)
    scores = {f"r_{k}": f"CAST({e} AS INT)" for k, e in level_columns(d, levels).items()}
    flags = {f"g_{k}": f"CAST({e} AS INT)" for k, e in flag_columns(d).items()}
    return f"""{name}_i AS ({instances_sql}),
{name}_t AS (SELECT {keys}, body, has_context, {line(token_columns(d))} FROM {name}_i),
{name}_w AS (SELECT *, {listed_column(d)} AS listed FROM {name}_t),
{name}_f AS (SELECT {keys}, has_context, {line(feature_columns(d))} FROM {name}_w),
{name} AS (SELECT {keys}, {line(scores)}, {line(flags)} FROM {name}_f)"""
