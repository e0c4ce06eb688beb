"""A corpus pipeline: quality classifier, line dedup, near dedup, decontamination, mixing.

Each stage takes (spark, docs, sf_dir) and works on all that the one before it kept; its result is written as Parquet in
the shared folder and read again."""

from functools import partial

from facetsel.llm.common import staged, table
from facetsel.llm.decontam import decontaminate_stage
from facetsel.llm.lines import line_stage
from facetsel.llm.mixing import mix_stage
from facetsel.llm.near import near_stage
from facetsel.llm.quality import quality_stage

#: Of documents with this share of their five-word shingles in common, in per cent, one stays; op7_near's contract is 85.
NEAR = 80

STAGES = [
    ("quality classifier", quality_stage),
    ("line dedup", line_stage),
    ("near dedup", partial(near_stage, percent=NEAR)),
    ("decontamination", decontaminate_stage),
    ("mixing", mix_stage),
]

#: Nearest-neighbour voting has no SQL; tests hold each stage against a brute-force version.
ORACLE_SQL = None


def run(spark, sf_dir):
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = staged(stage(spark, docs, sf_dir), name.replace(" ", "-"))
    return docs
