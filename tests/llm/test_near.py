import random

import numpy as np
from pyspark.sql import functions as F

from facetsel.llm import near
from facetsel.llm.common import components
from facetsel.llm.near import block_pairs, least_matches, near_duplicates, near_stage, shingles, steps_of


def brute(texts, percent=85):
    sets = {}
    for i, t in texts.items():
        w = (t or "").encode().lower().split()
        sets[i] = {tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))} if w else set()
    root = {i: i for i in texts}

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    ids = sorted(texts)
    for n, a in enumerate(ids):
        for b in ids[n + 1 :]:
            x, y = sets[a], sets[b]
            if x and y and 100 * len(x & y) >= percent * len(x | y):
                p, q = sorted((find(a), find(b)))
                root[q] = p
    return {i: (len(sets[i]), find(i)) for i in ids}


def near_texts(n=260, seed=4):
    r = random.Random(seed)
    vocabulary = ["".join(r.choice("abcdefgh") for _ in range(r.randint(2, 6))) for _ in range(400)]
    out, bases = {}, [[r.choice(vocabulary) for _ in range(r.choice((3, 5, 8, 60, 150)))] for _ in range(12)]
    for i in range(n):
        w = list(bases[min(11, int(r.expovariate(0.5)))]) if r.random() < 0.8 else [r.choice(vocabulary) for _ in range(40)]
        for _ in range(r.choice((0, 0, 1, 1, 2, 4, 9))):
            w[r.randrange(len(w))] = r.choice(vocabulary)
        out[i] = " ".join(w).title() if r.random() < 0.3 else "\n".join(w)
    out |= {n: "", n + 1: None, n + 2: " \t\n", n + 3: "", n + 4: "One two", n + 5: "one  TWO", n + 6: "É é", n + 7: "é É"}
    return out


def test_against_all_pairs(spark):
    texts = near_texts()
    docs = spark.createDataFrame(list(texts.items()), "doc_id long, text string").withColumn("sig", F.lit("clash")).withColumn("component", F.lit(1))
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in near_duplicates(docs).collect()}
    assert got == brute(texts)


def test_stage_keeps_one_of_each_group(spark):
    texts = near_texts(120, 8)
    docs = spark.createDataFrame([(i, t, "en", "s", len(t or "")) for i, t in texts.items()], "doc_id long, text string, lang string, source string, n_chars long")
    kept = near_stage(spark, docs, "")
    assert kept.columns == docs.columns
    assert {r.doc_id for r in kept.collect()} == {c for _, c in brute(texts).values()}


def test_null_ids_and_empty_tables(spark):
    docs = spark.createDataFrame([(None, "a b c d e f"), (1, "a b c d e f"), (1, "a b c d e f"), (2, "a b c d e f")], "doc_id long, text string")
    got = sorted(((r.doc_id is None, r.doc_id, r.component_id, r.kept) for r in near_duplicates(docs).collect()), key=str)
    assert got == [(False, 1, 1, True), (False, 1, 1, True), (False, 2, 1, False), (True, None, None, True)]
    assert near_duplicates(docs.limit(0)).count() == 0


def test_posterior_bound():
    for n, least in steps_of(85):
        assert 0 < least < 0.86 * n and least_matches(n, 0.85, 0.5) > least


def test_blocks_find_what_lies_across():
    r = np.random.default_rng(0)
    base = r.integers(0, 256, (1, 512), dtype=np.uint8)
    sig = np.repeat(base, 40, 0)
    sig[30:] = r.integers(0, 256, (10, 512))
    comp, size, block = np.arange(40) // 10, np.full(40, 100), np.zeros(40, int)
    x, y, equal = block_pairs(comp, block, size, sig, steps_of(85), 85)
    assert len(x) == 3 * 100 and (equal == 512).all()
    block[10:] = 1
    assert len(block_pairs(comp, block, size, sig, steps_of(85), 85)[0]) == 2 * 100


def test_large_groups_in_blocks(spark, monkeypatch):
    """Blocks of few rows, so that cells over two blocks and the main component's blocks are used."""
    monkeypatch.setattr(near, "BLOCK", 4)
    monkeypatch.setattr(near, "FIRST", 1)
    texts = near_texts(150, 21)
    docs = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    assert {r.doc_id: (r.n_shingles, r.component_id) for r in near_duplicates(docs).collect()} == brute(texts)


def test_shingles():
    assert len(shingles("a b c d e f a b c d e f")) == 6 and len(shingles("a b")) == 1 and not len(shingles(None))
    assert (shingles("A b  c\td e") == shingles("a B c d e")).all()


def test_components_of_a_long_path(spark):
    n = 300
    edges = spark.range(n).select(F.col("id").alias("a"), (F.col("id") + 1).alias("b"))
    edges = edges.unionByName(spark.createDataFrame([(1000, 1001), (1001, 1000), (5, 5)], "a long, b long"))
    got = {r.node: r.component for r in components(edges).collect()}
    assert got == {**dict.fromkeys(range(n + 1), 0), 1000: 1000, 1001: 1000}


def test_pipeline_stage_of_eighty_per_cent(spark):
    """The pipeline's stage has its own threshold, and bands enough for it."""
    import corpus_pipeline

    assert near.bands_of(85) == 20 and (1 - 0.8**near.ROWS) ** near.bands_of(80) <= near.MISS
    texts = near_texts(120, 8)
    docs = spark.createDataFrame(list(texts.items()), "doc_id long, text string")
    want = {c for _, c in brute(texts, 80).values()}
    assert {r.doc_id for r in dict(corpus_pipeline.STAGES)["near dedup"](spark, docs, "").collect()} == want
    assert len(want) < len({c for _, c in brute(texts).values()})


def test_stage_keeps_one_of_repeated_rows(spark):
    """Rows of one id and one text, with copies of other ids and without; rows without an id or a word stay."""
    rows = [(1, "a b c d e f"), (1, "a b c d e f"), (2, "A b c d e f"), (3, "g h i j k l"), (3, "g h i j k l"), (4, ""), (4, ""), (None, "a b c d e f"), (None, "a b c d e f"), (5, "m")]
    got = near_stage(spark, spark.createDataFrame(rows, "doc_id long, text string"), "").collect()
    assert sorted(map(str, map(tuple, got))) == sorted(map(str, [rows[0], rows[3], (4, ""), (4, ""), rows[7], rows[7], (5, "m")]))
