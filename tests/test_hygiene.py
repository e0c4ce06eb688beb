"""Sets of shingles built where the text lies."""

from pyspark.sql import functions as F

from facetsel.operators.hygiene import near_duplicates, sets_of, shingles


def test_sets_are_those_of_the_shingles(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    more = spark.createDataFrame([(0, "another text of the same id in six or seven words"), (-1, "two words"), (-2, ""), (-3, None), (-4, " . ")], "doc_id long, text string")
    rows = docs.unionByName(more)
    want = shingles(rows, "doc_id", "text", 5).groupBy("id").agg(F.sort_array(F.collect_set("h")).alias("s"))
    got = sets_of(rows, "doc_id", "text", 5)
    assert got.count() == want.count() == got.join(want, ["id", "s"]).count()


def test_no_word_is_shuffled_to_build_sets(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    import os

    from facetsel.functions.session import shared_dir

    before = set(os.listdir(shared_dir(spark)))
    near_duplicates(docs, "doc_id", "text").count()
    made = [x.split("-")[0] for x in set(os.listdir(shared_dir(spark))) - before]
    assert made.count("sets") == 1 and "reps" not in made


def test_first_runs_tell_pairs_apart_and_lose_no_link(spark):
    """Sets of the similarity are never told apart by their first hashes; unlike sets that share a passage are, so that
    their full sets do not move."""
    import random

    from facetsel.operators.hygiene import SIMILAR, may_link

    r, rows = random.Random(4), []
    for i in range(600):
        n = r.randint(1, 120)
        held = n - r.randint(0, n // 4) if i % 2 else n // 8
        a = r.sample(range(10**9), n)
        a, b = set(a), set(a[:held]) | set(r.sample(range(10**9), r.randint(0, n // 4) if i % 2 else n - held))
        if b:
            first = lambda s: sorted(s)[: len(s) - -(-8 * len(s) // 10) + 1]
            rows.append((len(a), len(b), first(a), first(b), 10 * len(a & b) >= 8 * len(a | b)))
    told = spark.createDataFrame(rows, "na int, nb int, sa array<long>, sb array<long>, link boolean").withColumn("may", may_link(SIMILAR))
    n = {(x["link"], x["may"]): x["count"] for x in told.groupBy("link", "may").count().collect()}
    assert (True, False) not in n and n[True, True] > 50 and n[False, False] > 50


def test_buckets_move_in_slices(spark, monkeypatch):
    """Pairs are those of all buckets, whatever their slice, and no more than a slice's rows move at once."""
    from facetsel.functions import graph

    made, kept = [], graph.kept
    monkeypatch.setattr(graph, "kept", lambda df, name="stage": made.append(name) or kept(df, name))
    entries = spark.createDataFrame([(i, b) for b in range(-20, 20) for i in (abs(b), abs(b) + 50, 200)], "id long, bucket long")
    assert {tuple(x) for x in graph.bucket_pairs(entries).collect()} == {(b, c) for b in range(21) for c in (b + 50, 200)}
    assert made.count("pairs-part") == graph.SLICES  # none before


def test_unlike_sets_of_a_common_run_make_no_pairs(spark):
    """Members of one large bucket are paired as far as their sets may be similar, and every link is among the pairs."""
    import random

    from facetsel.functions.graph import bucket_pairs
    from facetsel.operators.hygiene import SIMILAR, alike, marks

    r, sets = random.Random(6), []
    for _ in range(60):
        a = r.sample(range(10**12), r.randint(5, 400))
        sets += [a, a[len(a) // 10 :] + r.sample(range(10**12), len(a) // 10)]
    own = [set(x) for x in sets]
    links = {(i, j) for i in range(120) for j in range(i + 1, 120) if 10 * len(own[i] & own[j]) >= 8 * len(own[i] | own[j])}
    entries = spark.createDataFrame([(i, b) for i in range(120) for b in (3, 4)], "id long, bucket long")
    none = spark.createDataFrame([], "node long, component long")
    told = marks(spark.createDataFrame(list(enumerate(map(sorted, sets))), "id long, s array<long>"))
    got = {tuple(x) for x in bucket_pairs(entries, none, told, alike(SIMILAR)).collect()}
    assert links <= got and len(links) > 50 and len(got) < 200  # 7,140 before
