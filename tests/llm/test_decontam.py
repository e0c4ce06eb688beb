import math
import random
import string
from itertools import combinations

import numpy as np

from facetsel.llm import decontam
from facetsel.llm.decontam import MASKS, SeedIndex, decontaminate_stage, leaks, word_ids

R = random.Random(6)
VOCABULARY = ["".join(R.choice(string.ascii_lowercase) for _ in range(R.randint(2, 7))) for _ in range(500)]


def sentence(n):
    return [R.choice(VOCABULARY) for _ in range(n)]


def brute(doc, item):
    """Best stretch over all diagonals: some window of 13 words (or the item) with 80 per cent equal."""
    clean = lambda t: t.lower().translate(str.maketrans("", "", string.punctuation)).split()
    a, b = clean(doc), clean(item)
    if len(b) < 4:
        return False
    w = min(13, len(b))
    for d in range(-len(b), len(a)):
        lo, hi = max(0, -d), min(len(b), len(a) - d)
        eq = [a[i + d] == b[i] for i in range(lo, hi)]
        if any(sum(eq[i : i + w]) >= 0.8 * w for i in range(len(eq) - w + 1)):
            return True
    return False


def cases():
    items = [sentence(n) for n in (3, 4, 6, 8, 12, 15, 30, 60)]
    docs = []
    for _ in range(150):
        d = sentence(R.choice((0, 5, 60)))
        it = list(R.choice(items))
        if R.random() < 0.7:
            a = R.randrange(len(it)) if R.random() < 0.3 else 0
            part = it[a:]
            for _ in range(R.choice((0, 0, 1, 2, 4))):
                part[R.randrange(len(part))] = R.choice(VOCABULARY)
            d[len(d) // 2 : len(d) // 2] = part
        docs.append(" ".join(w.title() + R.choice(("", ",", ".", "\n")) for w in d))
    return docs, [" ".join(x) for x in items]


def test_against_all_alignments(spark, monkeypatch):
    docs, items = cases()
    want = {(i, j) for i, d in enumerate(docs) for j, t in enumerate(items) if brute(d, t)}
    df = spark.createDataFrame([*enumerate(docs), (900, None), (901, "")], "doc_id long, text string").selectExpr("*", "1 as item_id")
    bench = spark.createDataFrame([*enumerate(items), (50, None), (51, ""), (None, items[-1])], "item_id long, text string")
    looked_up, joined = (sorted(map(tuple, leaks(df, bench, block=block).collect())) for block in (20_000, 3))
    assert {x[:2] for x in looked_up} == want and joined == looked_up
    assert leaks(df, bench.limit(0)).count() == 0 and leaks(df.limit(0), bench).count() == 0


def test_substitutions_are_found():
    item = " ".join(sentence(26))
    index = SeedIndex([(7, word_ids(item))])
    words = item.split()
    for _ in range(200):
        w = list(words)
        for k in R.sample(range(26), 2):
            w[k] = "zzz"
        doc = " ".join(sentence(20) + w + sentence(20))
        (got,) = index.overlaps(doc)
        assert got[0] == 7 and 20 <= got[1] <= 23 and got[3] == 24
    assert index.overlaps(" ".join(sentence(2000))) == [] and index.overlaps(None) == []


def fits(masks, n, changed):
    """Whether some mask lies in n words beside those changed."""
    return any(all(s + o not in changed for o in decontam._offsets(m)) for m in masks for s in range(n - len(m) + 1))


def test_every_pattern_of_changes_leaves_a_seed():
    for n in range(decontam.SHORTEST, decontam.WINDOW + 1):
        masks = MASKS if n == decontam.WINDOW else decontam.SHORT_MASKS
        most = n - math.ceil(decontam.AGREE * n - 1e-9)
        assert all(fits(masks, n, x) for k in range(most + 1) for x in combinations(range(n), k)), n


def test_masks():
    every = (*MASKS, *decontam.SHORT_MASKS)
    assert all(m[0] == m[-1] == "1" for m in every) and all("0" in m for m in every)
    assert len(np.unique([decontam.seeds(word_ids("a b c d e f g h i j k l"), decontam._offsets(m), k)[0] for k, m in enumerate(every)])) == 4


def test_stage_and_given_tables(spark, sf_dir, monkeypatch):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    hit = {r.doc_id for r in leaks(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet")).collect()}
    kept = decontaminate_stage(spark, docs, sf_dir)
    monkeypatch.setattr(decontam, "BLOCK_ITEMS", 3)
    joined = decontaminate_stage(spark, docs, sf_dir)
    assert joined.columns == docs.columns and sorted(r.doc_id for r in joined.collect()) == sorted(r.doc_id for r in kept.collect())
    assert kept.columns == docs.columns and {r.doc_id for r in kept.collect()} == {r.doc_id for r in docs.select("doc_id").collect()} - hit
