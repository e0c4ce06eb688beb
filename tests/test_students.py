from pyspark.sql import functions as F

from facetsel.catalog import FACET_NAMES, FACETS, STYLES
from facetsel.functions import rubric
from facetsel.operators import measures as M
from facetsel.operators.cells import Layout, pack
from facetsel.operators.student import LinearStudent, OrdinalStudent, StyleStudent, tag_report
from facetsel.operators.teacher import NoisyTeacher, RubricTeacher, TableTeacher, judgement_cost, quality_judgement, teacher_sample
from facetsel.plans.selection import score_stack
from facetsel.sources import pools


def test_rubric_by_hand(spark):
    text = "Where on in at.\nGoing walked, that this | 12 + 3 !! WALKED."
    df = spark.createDataFrame([(1, "s", "en", text, text.split("\n")[0], text.split("\n")[1], False), (2, None, "fr", "", "", "", True)], "instance_id long, source string, lang string, body string, prompt string, answer string, has_context boolean")
    f = {r.instance_id: r for r in rubric.featurize(df).collect()}
    assert (f[1].n_tokens, f[1].n_spatial, f[1].n_activity, f[1].n_commas, f[1].n_bars, f[1].n_digits, f[1].n_shouts, f[1].n_breaks) == (12, 3, 3, 1, 1, 3, 1, 1)
    assert f[2].n_tokens == 0 and f[2].n_sentences == 0
    j = {r.instance_id: r for r in rubric.judge_wide(rubric.featurize(df)).collect()}
    assert j[1].r_spatial == 5 and j[1].r_stem == 2 and j[1].g_terse == 1 and j[1].g_emphatic == 1 and j[1].g_numeric == 1
    assert all(j[2][f"r_{k}"] == 0 for k in FACET_NAMES) and j[2].g_nonenglish == 1 and j[2].g_passage == 1


def test_packing_round_trip(spark, sf_dir):
    j = RubricTeacher().judge(pools.docs_flat(spark, sf_dir)).limit(60)
    packed = pack(j, FACET_NAMES, STYLES).join(j.drop("source"), "instance_id").collect()
    for r in packed:
        assert [(r.sig >> (3 * i)) & 7 for i in range(14)] == [r[f"r_{f}"] for f in FACET_NAMES]
        assert [(r.sig >> (42 + i)) & 1 for i in range(9)] == [r[f"g_{s}"] for s in STYLES]
    assert Layout(FACET_NAMES, STYLES).n == 126


def test_sample_sizes(spark):
    pool = spark.range(1000).withColumnRenamed("id", "instance_id")
    assert teacher_sample(pool, 0.15).count() == 150 and 90 < teacher_sample(pool, 0.15, exact=False).count() < 210
    assert judgement_cost(150) == 150 * 23


def test_levels_only_coarsen(spark, sf_dir):
    flat = pools.docs_flat(spark, sf_dir)
    fine, coarse = RubricTeacher().judge(flat), RubricTeacher((1, 3, 5)).judge(flat)
    for f in ("langgen", "finegrained"):
        pairs = fine.select("instance_id", F.col(f"r_{f}").alias("a")).join(coarse.select("instance_id", F.col(f"r_{f}").alias("b")), "instance_id").select("a", "b").distinct().collect()
        assert all(r.b == {0: 0, 1: 1, 2: 1, 3: 3, 4: 3, 5: 5}[r.a] for r in pairs)


def test_noise_and_tables(spark, sf_dir):
    flat = pools.docs_flat(spark, sf_dir)
    clean, noisy = RubricTeacher().judge(flat), NoisyTeacher().judge(flat)
    a = M.agreement(noisy.selectExpr("instance_id", score_stack()), clean.selectExpr("instance_id", score_stack())).collect()
    assert all(0.5 < r.exact < 0.98 and r.mae < 0.5 for r in a)
    flags = clean.selectExpr("instance_id", f"stack({len(STYLES)}, " + ", ".join(f"'{s}', g_{s}" for s in STYLES) + ") as (style, flag)")
    back = TableTeacher(clean.selectExpr("instance_id", score_stack()), flags).judge(flat)
    assert back.exceptAll(clean.select(back.columns)).count() == 0


def test_quality_levels(spark):
    rows = [(1, "good words here\nmore words"), (2, ""), (3, "a#b $ % & * |\na"), (4, "LOUD LOUD\nLOUD LOUD")]
    df = spark.createDataFrame([(i, "s", "en", t) for i, t in rows], "instance_id long, source string, lang string, body string")
    assert {r.instance_id: r.r_quality for r in quality_judgement(df).collect()} == {1: 5, 2: 0, 3: 3, 4: 2}


def test_students_beat_the_mean(spark):
    sf = "/root/testdata/sf0.01"
    flat = pools.docs_flat(spark, sf)
    truth = RubricTeacher().judge(flat)
    sample = teacher_sample(flat, 0.3)
    sample = RubricTeacher().judge(sample).join(sample.select("instance_id", "body"), "instance_id")
    facets = ("langgen", "scene")
    stack = "stack(2, 'langgen', r_langgen, 'scene', r_scene) as (facet, score)"
    flat_truth = truth.selectExpr("instance_id", stack)
    for student in (LinearStudent(facets), OrdinalStudent(("langgen",))):
        said = student.fit(sample).score(flat)
        said = said.selectExpr("instance_id", stack if len(student.facets) == 2 else "'langgen' as facet", *(["r_langgen as score"] if len(student.facets) == 1 else []))
        got = {r.facet: r for r in M.agreement(said, flat_truth).collect()}
        assert got["langgen"].mae < 1.4
    report = {r.style: r for r in tag_report(StyleStudent(("longform", "nonenglish")).fit(sample).tag(flat), truth, ("longform", "nonenglish")).collect()}
    assert report["nonenglish"].f1 > 0.8


def test_thresholds_rise():
    assert all(list(f.levels) == sorted(f.levels) for f in FACETS) and len(FACETS) == 14 and len(STYLES) == 9
