import random

import pytest

from facetsel.llm.fst import CountTransducer, PieceCounter, WordCounts
from facetsel.llm.tokens import model_path, token_counts

sentencepiece = pytest.importorskip("sentencepiece")


@pytest.fixture(scope="module")
def pair():
    return PieceCounter(model_path()), sentencepiece.SentencePieceProcessor(model_file=model_path())


def texts(n=6000, seed=0):
    r = random.Random(seed)
    alphabet = [*" ▁\n\tabcde<>s/[]INST0x.,'é日本語😀ß１", "  ", "   ", "the ", "ing", "<s>", "</s>", "<0x0A>", "<unk>", " " * 20, "\x00", "\xa0"]
    return ["".join(r.choice(alphabet) for _ in range(r.randint(0, 40))) for _ in range(n)]


def test_against_the_library(pair):
    mine, theirs = pair
    for t in texts():
        assert mine(t) == len(theirs.encode(t)), repr(t)


def test_chunks_compose(pair):
    mine, theirs = pair
    r = random.Random(3)
    for alphabet in ("abcdeginth日本é", "ab", "the ing\n ", "日"):
        t = "".join(r.choice(alphabet) for _ in range(20_000))
        want = len(theirs.encode(t))
        whole = "▁" + t.replace(" ", "▁")
        assert mine(t) == want
        assert all(mine.machine.count(whole, chunk) == want for chunk in (1, 7, 997) if chunk > 1 or len(t) < 30_000)


def test_composition_is_associative(pair):
    m = pair[0].machine
    r = random.Random(4)
    for _ in range(200):
        a, b, c = (m.chunk("".join(r.choice("ab▁\n日the") for _ in range(r.randint(1, 8)))) for _ in range(3))
        left, right = m.compose(m.compose(a, b), c), m.compose(a, m.compose(b, c))
        total = lambda x: m.walk(m.start, x.head)[1] + x.count
        assert total(left) == total(right)


def test_few_states_are_made_again(pair):
    mine, theirs = pair
    small = CountTransducer(mine.machine.scores, most_states=50)
    for t in texts(300, 9):
        if t:
            assert small.count("▁" + t.replace(" ", "▁"), chunk=5) == len(theirs.encode(t)), repr(t)
    assert len(WordCounts(mine.machine, most=3)) == 0


def test_query_over_a_table(spark, pair):
    rows = [(i, t) for i, t in enumerate(texts(200, 5))] + [(1000, None), (1001, ""), (1002, "word " * 5000), (None, "x"), (1002, "word " * 5000)]
    docs = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("*", "1 as n_tokens")
    got = sorted(((r.doc_id is None, r.doc_id, r.n_bytes, r.n_tokens, r.over_limit) for r in token_counts(docs).collect()), key=str)
    want = sorted(((i is None, i, len((t or "").encode()), n := len(pair[1].encode(t or "")), n > 4096) for i, t in rows), key=str)
    assert got == want and token_counts(docs.limit(0)).count() == 0


def test_long_texts_by_chunks(spark, pair):
    """Chunks of any size, read by different tasks, compose to what the library counts; equal rows each have a row."""
    r = random.Random(8)
    rows = [(2**60 + i, "".join(r.choice(("the ", "ing", " ", "日本", "x", "\n", "  ", "straße ")) for _ in range(400))) for i in range(12)]
    rows += [rows[0], (None, rows[1][1]), (5, "short"), (6, "x" * 700)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    for chunk in (7, 64, 500):
        got = sorted(((r.doc_id, r.n_bytes, r.n_tokens) for r in token_counts(df, long=100, chunk=chunk).collect()), key=str)
        assert got == sorted(((i, len(t.encode()), len(pair[1].encode(t))) for i, t in rows), key=str)
