"""All registered queries of the engine, but those of the llm subpackage."""

from facetsel.plans import cleaning, comparison, relational, selection, subset, workloads
from facetsel.streaming import streams

_PARTS = (selection, subset, cleaning, comparison, relational, workloads, streams)


def queries():
    out = {}
    for part in _PARTS:
        out |= part.queries()
    return out


def oracle_sql():
    out = {}
    for part in _PARTS:
        out |= part.oracle_sql()
    return out
