"""Ids above 2^53 beside nulls come through every operator as they are."""

import pytest

from facetsel.llm import chat, decontam, licences, lines, near, quality, rules, substrings, tokens

BIG = 2**60 + 1
TEXT = " ".join(f"word{i}" for i in range(60)) + "."


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(BIG, TEXT, "en", "a"), (None, TEXT + " more", "en", None), (BIG + 2, TEXT, None, "a"), (BIG + 4, None, "en", "b")]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string").selectExpr("*", "1 as k", "2 as t", "3 as row", "4 as id")


def ids(df, name="doc_id"):
    return {r[name] for r in df.collect()}


def test_row_operators(spark, docs):
    every = {BIG, None, BIG + 2, BIG + 4}
    labels = spark.createDataFrame([(BIG, 1, 0), (BIG + 2, 0, 0)], "doc_id long, quality int, toxic int")
    scored = quality.score(docs, quality.train(docs, labels))
    assert ids(scored) == every and scored.where("held_out is null or score is null").count() == 0
    assert ids(tokens.token_counts(docs)) == every
    assert ids(rules.quality_rules(docs)) == every
    assert ids(near.near_duplicates(docs)) == every


def test_finders(spark, docs):
    items = spark.createDataFrame([(7, " ".join(f"word{i}" for i in range(20, 40)))], "item_id long, text string")
    assert ids(decontam.leaks(docs, items)) == {BIG, None, BIG + 2}
    got = {(r.doc_id, r.first_doc_id) for r in substrings.removed_spans(docs).collect()}
    assert got == {(BIG, None), (BIG + 2, None)}
    assert {(r.doc_id, r.kept_doc_id) for r in lines.duplicate_lines(docs, hamming=None).collect()} == {(BIG, None), (BIG + 2, None)}
    said = spark.createDataFrame([(BIG, "Released under the MIT License."), (None, "Released under the MIT License.")], "doc_id long, text string")
    assert ids(licences.scan(said)) == {BIG, None}


def test_chat(spark):
    turns = spark.createDataFrame([(BIG, 0, "user", "a"), (None, 0, "user", "b"), (BIG, 1, "assistant", "c")], "conv_id long, turn long, role string, text string")
    parts = turns.withColumn("parts", chat.text_parts(turns["text"]))
    got = chat.conversation_digests(chat.read_back(chat.format_turns(parts)))
    assert {(r.conv_id, r.n_turns) for r in got.collect()} == {(BIG, 2), (None, 1)}
