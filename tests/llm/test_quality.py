import random
import zlib

import numpy as np

from facetsel.llm.quality import Model, Settings, bag, fit, labelled_sample, op3_quality, quality_stage, score, train


def test_vote_by_brute_force():
    """Exact cosines to every labelled vector, the nearest vote with their similarity."""
    r = random.Random(1)
    texts = ["".join(r.choice("abcdef ") for _ in range(200)) for _ in range(40)] + ["XYZ!! " * r.randint(5, 40) for _ in range(20)]
    labels = np.array([1] * 40 + [0] * 20)
    s = Settings(buckets=256, dims=16, neighbours=7)
    m = fit(np.stack([bag(t, 256) for t in texts]), labels, 0.8, s)
    test = ["XYZ!! XYZ!! WXY!! XYZ!!", "abc def fed cab " * 9, "", "q"]
    bags = np.stack([bag(t, 256) for t in test])
    got = m.score(bags)
    z = m.latent(bags)
    for i, t in enumerate(test):
        if not bags[i].any():
            assert got[i] == 0.8
            continue
        cos = [(float(z[i] @ v), k) for k, v in enumerate(m.vectors)]
        near = sorted(cos, reverse=True)[:7]
        w = [(max(c, 1e-6) ** 16 * (0.8 / labels.mean() if labels[k] else 0.2 / (1 - labels.mean())), labels[k]) for c, k in near]
        want = sum(x for x, y in w if y) / sum(x for x, _ in w)
        assert abs(got[i] - want) < 1e-3
    assert got[0] < 0.5 < got[1]


def test_no_labels(spark):
    docs = spark.createDataFrame([(1, "a b c"), (2, None)], "doc_id long, text string")
    labels = spark.createDataFrame([(1, None, 0), (None, 1, 0)], "doc_id long, quality int, toxic int")
    m = train(docs, labels)
    assert isinstance(m, Model) and {r.score for r in score(docs, m).collect()} == {0.5}
    assert score(docs.limit(0), m).count() == 0


def test_learns_from_the_right_rows(spark):
    docs = spark.range(400).selectExpr("id as doc_id", "concat('text ', id) as text")
    labels = spark.range(500).selectExpr("id as doc_id", "cast(id % 2 as int) as quality", "0 as toxic")
    rows = labelled_sample(docs, labels, Settings(per_class=60)).collect()
    assert 0 < len(rows) <= 120 and all(zlib.crc32(str(r.doc_id).encode()) % 4 != 2 and r.label == r.doc_id % 2 for r in rows)


def test_held_out_accuracy(spark):
    sf = "/root/testdata/sf0.01"
    got = op3_quality(spark, sf)
    assert got.where("score < 0 or score > 1 or score is null").count() == 0 and got.count() == spark.read.parquet(f"{sf}/documents.parquet").count()
    rows = got.where("held_out").join(spark.read.parquet(f"{sf}/labels.parquet"), "doc_id").collect()
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 4 == 2) for r in rows)
    good, bad = [r for r in rows if r.quality == 1], [r for r in rows if r.quality == 0]
    assert sum(r.predicted for r in good) >= 0.97 * len(good) and sum(1 - r.predicted for r in bad) >= 0.8 * len(bad)


def test_stage_takes_effect(spark):
    sf = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    kept = quality_stage(spark, docs, sf)
    want = {r.doc_id for r in op3_quality(spark, sf).where("predicted = 1").collect()}
    assert kept.columns == docs.columns and {r.doc_id for r in kept.collect()} == want
