import random

from pyspark.sql import functions as F

from facetsel.llm.substrings import LEAST_WORDS, removed_spans, units, without_spans

R = random.Random(12)


def prose(n_sentences):
    words = lambda: " ".join("".join(R.choice("abcdefghij") for _ in range(R.randint(2, 8))) for _ in range(R.randint(3, 14)))
    return "".join(words().capitalize() + R.choice((". ", ". ", "? ", ".\n")) for _ in range(n_sentences))


def brute(docs):
    """Units with words in order of (id, place); what came before goes, in runs of neighbours with enough different words."""
    seen, runs = {}, []
    for i, t in sorted(docs):
        last = None
        for place, (s, e, n, d) in enumerate(u for u in units(t) if u[2]):
            if d not in seen:
                seen[d] = i
                continue
            if last != place - 1 or not runs or runs[-1][0] != i:
                runs.append([i, s, e, 0, 0, seen[d], {}])
            last = place
            r = runs[-1]
            r[2], r[3], r[4] = e, r[3] + 1, r[4] + n
            r[6][d] = n
    return sorted(tuple(r[:6]) for r in runs if sum(r[6].values()) >= LEAST_WORDS)


def some_docs():
    passages = [prose(9) for _ in range(4)]
    docs = []
    for i in range(80):
        t = prose(R.randint(0, 12))
        if R.random() < 0.6:
            k = R.randint(0, len(t))
            t = t[:k] + R.choice((" ", "")) + R.choice(passages) + t[k:]
        docs.append((i, t))
    return [*docs, (80, ""), (81, None), (82, docs[3][1]), (83, "\n\n \n"), (84, passages[0] + passages[0])]


def test_units_join_to_the_text():
    for _, t in some_docs():
        assert "".join((t or "")[a:b] for a, b, *_ in units(t)) == (t or "")


def test_against_brute_force(spark):
    docs = some_docs()
    df = spark.createDataFrame(docs, "doc_id long, text string").withColumn("start", F.lit(1)).withColumn("h1", F.lit("x"))
    got = sorted(tuple(r) for r in removed_spans(df).drop("part", "copy").collect())
    assert got == brute(docs)
    texts = dict(docs)
    cut = {r.doc_id: r.text for r in without_spans(df, removed_spans(df)).collect()}
    for i, t in docs:
        want = t
        for d, s, e, *_ in sorted(got, reverse=True):
            if d == i:
                want = want[:s] + want[e:]
        assert cut[i] == want
    assert removed_spans(df.limit(0)).count() == 0 and set(cut) == set(texts)


def test_planted_passages(spark):
    """Passages of over 50 words, put anywhere into unlike documents: all but the first are caught, clean texts are not."""
    planted, clean = [], []
    for p in range(20):
        passage = prose(8)
        while len(passage.split()) <= 50:
            passage += prose(1)
        for k in range(3):
            t = prose(10)
            at = R.choice([i for i, c in enumerate(t) if c == " "])
            planted.append((p * 10 + k, t[:at] + " " + passage + " " + t[at:]))
        clean.append((1000 + p, prose(12)))
    got = {r.doc_id for r in removed_spans(spark.createDataFrame([*planted, *clean], "doc_id long, text string")).collect()}
    assert got == {i for i, _ in planted if i % 10}


def test_repeated_rows_and_null_ids(spark):
    """Of equal rows the first stays whole, also beside nulls and ids that no double holds; rows of one id and other texts
    are documents of their own."""
    t, other, big = prose(10), prose(10), 2**60 + 1
    rows = [(None, t), (1, t), (big, other), (big, other), (big, prose(8)), (2, None), (2, None)]
    df = spark.createDataFrame(rows, "doc_id long, text string").withColumns({"k": F.lit(1), "copy": F.lit(2), "row": F.lit(3), "removed_spans": F.lit("x")})
    spans = removed_spans(df)
    got = sorted(((r.doc_id, r.copy, r.first_doc_id) for r in spans.collect()), key=str)
    assert got == [(1, 1, None), (big, 2, big)]
    cut = without_spans(df, spans)
    assert cut.columns == ["doc_id", "text", "k", "copy", "row", "removed_spans"]
    assert sorted(((r.doc_id, r.text) for r in cut.collect()), key=str) == sorted([(None, t), (1, ""), (big, other), (big, ""), rows[4], (2, None), (2, None)], key=str)


def test_runs_over_line_ends(spark):
    """Passages of short lines, or of short paragraphs, are one run: wordless units do not end it."""
    line = lambda: prose(1).strip().rstrip(".?") + "."
    for gap in ("\n", "\n\n", "\n \n"):
        lines = []
        while sum(len(x.split()) for x in lines) <= 50:
            if len(x := line()) and len(x.split()) < 20:
                lines.append(x)
        passage = gap.join(lines)
        df = spark.createDataFrame([(1, passage), (2, "Something else stands here before all.\n" + passage + gap)], "doc_id long, text string")
        (got,) = removed_spans(df).collect()
        assert (got.doc_id, got.start, got.end, got.n_words) == (2, 39, 39 + len(passage), len(passage.split()))


def test_stuttering_is_no_passage(spark):
    df = spark.createDataFrame([(1, "the, " * 100), (2, "ha! " * 60)], "doc_id long, text string")
    assert removed_spans(df).count() == 0
