"""Substring dedup by unit hashing.

Texts are cut into lines, and lines behind every mark that ends a sentence or clause, so that a passage put anywhere into a
text has the same units but for its first and last. Units are normalised (lower case, white space as one space) and
digested with 128 bits. Digests are grouped over the whole corpus; the occurrence ranked first, by document and place,
stays. Of the other occurrences, adjoining ones form runs, which blank lines and other units without words do not end;
runs whose different units have LEAST_WORDS words or more together are removed, with the offsets (in characters of the
original text) retained. A unit said again and again counts once, so that stuttering is no passage.

Hot units are pre-aggregated before they are shuffled, and the join that tells a unit its first occurrence is an
equi-join that adaptive execution may split. Texts are not shuffled, only digests.

Defined results: null and empty texts have no units; units without words are never repeated. Rows are told apart by id and
text: rows of one id and different texts are documents of their own, of which any may be the first; of rows equal in
both the first stays and each other one is a removed span as a whole (copy 2, 3, ...). A null id ranks first. Other
columns are ignored.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from facetsel.llm.common import given_id, n_words, ship, small, staged, table, whole_id

#: A unit: what ends in marks of a sentence or clause, with the blanks behind them, or what is left of a line.
UNIT = re.compile(r"[^\n.!?,;:]*[.!?,;:]+[ \t]*|[^\n.!?,;:]*\n|[^\n.!?,;:]+")
LEAST_WORDS = 25


def units(text: str | None) -> list[tuple[int, int, int, int]]:
    """(start, end, words, digest) of each unit; the units of a text join to the text."""
    out = []
    for m in UNIT.finditer(text or ""):
        words = m[0].lower().split()
        out.append((m.start(), m.end(), len(words), xxhash.xxh3_128_intdigest(" ".join(words).encode("utf-8", "surrogatepass")) if words else 0))
    return out


def _cut(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    """Units with words; reach is the end of the wordless units that follow, fresh whether the row has it for the first
    time."""
    low = (1 << 64) - 1
    for b in batches:
        ids, parts, got = [], [], []
        for k, part, t in zip(b["k"].tolist(), b["part"].tolist(), b["t"], strict=True):
            x, seen = [], set()
            for start, end, words, digest in units(t):
                if words:
                    x.append([start, end, words, digest, end, digest not in seen])
                    seen.add(digest)
                elif x:
                    x[-1][4] = end
            got += x
            ids += [k] * len(x)
            parts += [part] * len(x)
        d = [x[3] for x in got]
        yield pd.DataFrame({"doc_id": np.array(ids, np.int64), "part": np.array(parts, np.int64), "start": np.array([x[0] for x in got], np.int64), "end": np.array([x[1] for x in got], np.int64), "reach": np.array([x[4] for x in got], np.int64), "fresh": np.array([x[5] for x in got], bool), "words": np.array([x[2] for x in got], np.int32), "h1": np.array([x >> 64 for x in d], np.uint64).view(np.int64), "h2": np.array([x & low for x in d], np.uint64).view(np.int64)})


ROW = ["doc_id", "part"]


def _told(docs: DataFrame, text: str, key: str) -> DataFrame:
    """(k, part, t): id, hash of the text and text."""
    return docs.select(whole_id(key).alias("k"), F.xxhash64(text).alias("part"), F.col(text).alias("t"))


def _repeated_rows(docs: DataFrame, text: str, key: str) -> DataFrame:
    """(k, part, n) of the rows equal in id and text, staged."""
    return staged(_told(docs, text, key).where("t <> ''").groupBy("k", "part").agg(F.count("*").alias("n")).where("n > 1"), "repeated-rows")


def removed_spans(docs: DataFrame, text: str = "text", key: str = "doc_id", least_words: int = LEAST_WORDS) -> DataFrame:
    """(doc_id, part, copy, start, end, n_units, n_words, first_doc_id): what to cut from each row, and where the first copy
    of the span's first unit stays. part: the text's hash; copy: which of the rows equal in id and text."""
    ship(docs.sparkSession)
    twice = _repeated_rows(docs, text, key)
    rows, more = _told(docs, text, key), None
    if not twice.isEmpty():
        of_twice = rows.join(small(twice), ["k", "part"]).groupBy("k", "part", "n").agg(F.min("t").alias("t"))
        rows = rows.join(small(twice), ["k", "part"], "left_anti").unionByName(of_twice.drop("n"))
        size = F.length("t").cast("long")
        more = of_twice.select(F.col("k").alias("doc_id"), "part", F.explode(F.sequence(F.lit(2).cast("long"), "n")).alias("copy"), F.lit(0).cast("long").alias("start"), size.alias("end"), F.lit(1).cast("long").alias("n_units"), n_words(F.col("t")).alias("n_words"), F.col("k").alias("first_doc_id"))
    cut = staged(rows.mapInPandas(_cut, "doc_id long, part long, start long, end long, reach long, fresh boolean, words int, h1 long, h2 long"), "units")
    first = cut.groupBy("h1", "h2").agg(F.min("doc_id").alias("first_doc_id"), F.min_by("part", "doc_id").alias("first_part"), F.count("*").alias("n")).where("n > 1").drop("n")
    first = staged(first, "first")  # so that the join's skewed partitions are not bound to an aggregation's, and may be split
    again = cut.join(first, ["h1", "h2"]).where("not (fresh and doc_id = first_doc_id and part = first_part)").repartition(*ROW)
    in_row = W.partitionBy(*ROW).orderBy("start")
    opens = F.when(F.lag("reach").over(in_row) >= F.col("start"), 0).otherwise(1)
    again = again.withColumn("opens", opens).withColumn("run", F.sum("opens").over(in_row.rowsBetween(W.unboundedPreceding, 0)))
    once = again.groupBy(*ROW, "run", "h1", "h2").agg(F.min("start").alias("start"), F.max("end").alias("end"), F.count("*").alias("n_units"), F.sum("words").alias("n_words"), F.max("words").alias("once"), F.min_by("first_doc_id", "start").alias("first_doc_id"))
    runs = once.groupBy(*ROW, "run").agg(F.sum("once").alias("once"), F.min_by("first_doc_id", "start").alias("first_doc_id"), F.min("start").alias("start"), F.max("end").alias("end"), F.sum("n_units").alias("n_units"), F.sum("n_words").alias("n_words"))
    runs = runs.where(F.col("once") >= least_words).withColumn("copy", F.lit(1).cast("long"))
    names = ["doc_id", "part", "copy", "start", "end", "n_units", "n_words", "first_doc_id"]
    runs = runs.select(names) if more is None else runs.select(names).unionByName(more)
    return runs.select(given_id("doc_id"), "part", "copy", "start", "end", "n_units", "n_words", given_id("first_doc_id"))


def without_spans(docs: DataFrame, spans: DataFrame, text: str = "text", key: str = "doc_id") -> DataFrame:
    """docs with the spans cut out of their texts and listed in removed_spans."""
    ship(docs.sparkSession)
    listed = spans.select(whole_id("doc_id").alias("k"), "part", "copy", "start", "end").groupBy("k", "part", "copy").agg(F.sort_array(F.collect_list(F.struct("start", "end"))).alias("removed_spans"))
    columns = [c for c in docs.columns if c != "removed_spans"]
    rows = docs.select(F.struct(*columns).alias("row"), whole_id(key).alias("k"), F.xxhash64(text).alias("part"), F.lit(1).cast("long").alias("copy"))
    twice = _repeated_rows(docs, text, key)
    if not twice.isEmpty():
        again = rows.join(small(twice.drop("n")), ["k", "part"], "left_semi").withColumn("copy", F.row_number().over(W.partitionBy("k", "part").orderBy(F.xxhash64("row"))).cast("long"))
        rows = rows.join(small(twice.drop("n")), ["k", "part"], "left_anti").unionByName(again)
    joined = rows.join(listed, ["k", "part", "copy"], "left")

    @F.pandas_udf("string")
    def cut(texts: pd.Series, spans: pd.Series) -> pd.Series:
        def one(t, s):
            if t is None or s is None:
                return t
            out, at = [], 0
            for x in s:
                out.append(t[at : x["start"]])
                at = x["end"]
            return "".join(out) + t[at:]

        return pd.Series([one(t, s) for t, s in zip(texts, spans, strict=True)], dtype=object)

    left = F.when(F.col("removed_spans").isNull(), F.col(f"row.{text}")).otherwise(cut(F.col(f"row.{text}"), "removed_spans"))
    return joined.select(*[left.alias(c) if c == text else F.col(f"row.{c}") for c in columns], "removed_spans")


def op2_substrings(spark: SparkSession, sf_dir: str) -> DataFrame:
    return removed_spans(table(spark, sf_dir, "documents")).drop("part", "copy")


#: The same units and ranks, compared as text.
OP2_SQL = rf"""
WITH u AS (
  SELECT doc_id, generate_subscripts(us, 1) AS i, unnest(us) AS unit FROM (
    SELECT doc_id, regexp_extract_all(text, '[^\n.!?,;:]*[.!?,;:]+[ \t]*|[^\n.!?,;:]*\n|[^\n.!?,;:]+') AS us FROM documents)),
o AS (
  SELECT doc_id, i, sum(length(unit)) OVER (PARTITION BY doc_id ORDER BY i ROWS UNBOUNDED PRECEDING) AS e, length(unit) AS n,
         list_filter(regexp_split_to_array(lower(unit), '\s+'), lambda x: x <> '') AS w FROM u),
k AS (
  SELECT doc_id, CAST(e - n AS BIGINT) AS s, CAST(e AS BIGINT) AS e, len(w) AS words, array_to_string(w, ' ') AS t,
         row_number() OVER (PARTITION BY doc_id ORDER BY i) AS place FROM o WHERE len(w) > 0),
f AS (
  SELECT *, min(doc_id) OVER (PARTITION BY t) AS first_doc_id, row_number() OVER (PARTITION BY t ORDER BY doc_id, s) AS nth FROM k),
g AS (SELECT *, place - row_number() OVER (PARTITION BY doc_id ORDER BY s) AS run FROM f WHERE nth > 1),
r AS (SELECT *, row_number() OVER (PARTITION BY doc_id, run, t) AS said FROM g)
SELECT doc_id, min(s) AS start, max(e) AS "end", count(*) AS n_units, CAST(sum(words) AS BIGINT) AS n_words, min_by(first_doc_id, s) AS first_doc_id
FROM r GROUP BY doc_id, run HAVING sum(words) FILTER (said = 1) >= {LEAST_WORDS}
"""
