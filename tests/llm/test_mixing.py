import random
from collections import defaultdict

from facetsel.llm.common import n_words
from facetsel.llm.mixing import budgets, mix, mix_stage


def test_budgets():
    assert budgets([("a", 100), ("b", 100), ("c", 100)], [5, 2, 1], 3) == [187.5, 75.0, 37.5]
    got = budgets([("a", 10), ("b", 500), ("c", 100)], [5, 2, 1], 3)
    assert got[0] == 30 and abs(sum(got) - 610) < 1e-9 and abs(got[1] / got[2] - 2) < 1e-9
    assert budgets([("a", 0), ("b", 0)], [5, 2], 3) == [0.0, 0.0] and budgets([], [], 3) == []
    got = budgets([("a", 1), ("b", 1), ("c", 1000)], [5, 2, 1], 3)
    assert got[:2] == [3, 3] and abs(got[2] - 996) < 1e-9


def some(spark, n=900, seed=1):
    r = random.Random(seed)
    rows = [(i, " ".join("w" * r.randint(0, 30)) if r.random() > 0.05 else None, "en", r.choices(["b", "a", "é", None], [6, 1, 2, 1])[0], 7) for i in range(n)]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")


def test_exact_budgets(spark):
    docs = some(spark)
    rows = mix(docs, n_words(docs["text"])).collect()
    source = {r.doc_id: r.source for r in docs.select("doc_id", "source").collect()}
    per = defaultdict(lambda: [0, 0, 0, 0.0])
    for r in rows:
        assert 0 <= r.taken <= 3 * r.size
        p = per[source[r.doc_id]]
        p[0] += r.size
        p[1] += r.taken
        p[2], p[3] = r.source_size, r.target
    assert len(rows) == 900 and all(p[0] == p[2] and abs(p[1] - p[3]) <= 0.5 for p in per.values())
    total = sum(p[0] for p in per.values())
    assert abs(sum(p[3] for p in per.values()) - total) < 1e-6
    assert per["a"][3] == 3 * per["a"][0] and abs(per["b"][3] / per["é"][3] - 2) < 1e-9
    again = mix(docs.repartition(5), n_words(docs["text"])).collect()
    assert sorted(map(tuple, rows)) == sorted(map(tuple, again))


def test_edges(spark):
    docs = some(spark, 0)
    assert mix(docs, n_words(docs["text"])).count() == 0
    docs = spark.createDataFrame([(1, "a b"), (1, "a b"), (None, "")], "doc_id long, text string").selectExpr("*", "'s' as source", "5 as size", "6 as taken")
    assert sorted((r.size, r.taken) for r in mix(docs, n_words(docs["text"])).collect()) == [(0, 0), (2, 2), (2, 2)]
    out = mix_stage(spark, docs, "")
    assert out.columns == ["doc_id", "text", "source", "size", "source_size", "target", "taken"][0:3] + ["size", "source_size", "target", "taken"] and out.count() == 2


def test_stage(spark):
    """Repeated rows and rows without id or source keep their own shares; columns of the stage's names give way."""
    rows = [(i % 7 if i % 5 else None, f"w{i % 3} " * (i % 9), "abc"[i % 3] if i % 4 else None, "en", 9.0) for i in range(60)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string, lang string, target double").selectExpr("*", "1 as k", "2 as row", "3 as h")
    got = mix_stage(spark, docs, "")
    assert got.columns == ["doc_id", "text", "source", "lang", "k", "row", "h", "size", "source_size", "target", "taken"]
    out = got.collect()
    assert all(0 < r.taken <= 3 * r.size and r.size == len(r.text.split()) for r in out)
    for source in ("a", "b", "c", None):
        own = [r for r in out if r.source == source]
        assert abs(sum(r.taken for r in own) - own[0].target) <= 0.5
    assert mix_stage(spark, docs.limit(0), "").count() == 0
