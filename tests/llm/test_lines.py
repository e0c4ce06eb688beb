import random
import re

from pyspark.sql import functions as F

from facetsel.llm.lines import HAMMING, coded, digested, duplicate_lines, line_stage, selections, words_of


def words(line):
    return re.findall(r"[^\W_]+", line.lower())


def edit(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        last, row[0] = row[0], i
        for j, y in enumerate(b, 1):
            last, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, last + (x != y))
    return row[-1]


def some_docs(n=60, seed=2):
    r = random.Random(seed)
    vocabulary = ["".join(r.choice("abcdefghé") for _ in range(r.randint(2, 7))) for _ in range(300)]
    lines = [[r.choice(vocabulary) for _ in range(r.choice((2, 5, 8, 30, 90)))] for _ in range(25)]
    out = []
    for i in range(n):
        own = []
        for _ in range(r.randint(1, 6)):
            w = list(r.choice(lines)) if r.random() < 0.7 else [r.choice(vocabulary) for _ in range(20)]
            if r.random() < 0.4:
                w[r.randrange(len(w))] = r.choice(vocabulary)
            own.append((" ".join(w)).capitalize() + r.choice((".", "!", "", "\t")))
        out.append((i, "\n".join(own)))
    return [*out, (n, ""), (n + 1, None), (n + 2, "\n\n"), (n + 3, out[0][1])]


def brute(docs, sims):
    """Links: hamming distance and word edit similarity, over all pairs of distinct lines."""
    places = {}
    for i, t in docs:
        for k, line in enumerate((t or "").split("\n")):
            if len(w := tuple(words(line))) >= 5:
                places.setdefault(w, []).append((i, k))
    keys = sorted(places)
    root = {k: k for k in keys}

    def find(k):
        while root[k] != k:
            k = root[k]
        return k

    for n, a in enumerate(keys):
        for b in keys[n + 1 :]:
            if bin((sims[a] ^ sims[b]) & (2**64 - 1)).count("1") <= HAMMING and edit(a, b) <= 0.2 * max(len(a), len(b)) + 1e-9:
                root[find(b)] = find(a)
    gone = []
    groups = {}
    for k in keys:
        groups.setdefault(find(k), []).extend(places[k])
    for own in groups.values():
        own.sort()
        gone += [(*x, *own[0]) for x in own[1:]]
    return sorted(gone)


def test_against_all_pairs(spark):
    docs = some_docs()
    df = spark.createDataFrame(docs, "doc_id long, text string").withColumn("bucket", F.lit(0)).withColumn("pos", F.lit(1))
    by_place = {(r.doc_id, r.pos): r.sim for r in digested(df, "text", "doc_id").collect()}
    sims = {tuple(words(t.split("\n")[k])): s for (i, k), s in by_place.items() for t in [docs[i][1]]}
    assert sorted(tuple(r) for r in duplicate_lines(df).collect()) == brute(docs, sims)


def test_hamming_is_small_for_small_changes(spark):
    a = " ".join(f"w{i}" for i in range(200))
    df = spark.createDataFrame([(1, a), (2, a.replace("w7 ", "x7 ")), (3, " ".join(f"v{i}" for i in range(200)))], "doc_id long, text string")
    s = {r.doc_id: r.sim & (2**64 - 1) for r in digested(df, "text", "doc_id").collect()}
    assert bin(s[1] ^ s[2]).count("1") < 10 < bin(s[1] ^ s[3]).count("1")


def test_selections_meet():
    r = random.Random(1)
    for n in (10, 10_000, 10_000_000, 10**11):
        masks = selections(n)
        for _ in range(200):
            x = r.getrandbits(64)
            y = x
            for b in r.sample(range(64), HAMMING):
                y ^= 1 << b
            assert any(x & m == y & m for m in masks)


def test_codes(spark):
    df = spark.createDataFrame([("a b c",), ("a x c d",)], "t string").select(coded(words_of(F.col("t"))).alias("c"))
    x, y = (r.c for r in df.collect())
    assert len(x) == 3 and len(y) == 4 and edit(x, y) == 2


def test_stage(spark):
    docs = spark.createDataFrame([(2, "one two three four five\nshort", "en", "s", 1), (1, "One two, three four five!\nnew", "en", "s", 1), (3, None, "en", None, 0)], "doc_id long, text string, lang string, source string, n_chars long")
    got = {r.doc_id: (r.text, r.n_chars) for r in line_stage(spark, docs, "").collect()}
    assert got == {1: ("One two, three four five!\nnew", 29), 2: ("short", 5), 3: (None, None)}
    assert duplicate_lines(docs.limit(0)).count() == 0


def test_every_link_of_the_edit_similarity(spark):
    """Against a brute force without SimHash: links by word edit similarity alone."""
    docs = some_docs(70, 5)
    lines = {tuple(words(line)) for _, t in docs for line in (t or "").split("\n")}
    want = brute(docs, dict.fromkeys(lines, 0))
    df = spark.createDataFrame(docs, "doc_id long, text string")
    texts = dict(docs)
    got = sorted(tuple(r) for r in duplicate_lines(df, hamming=None).collect() if len(words(texts[r.doc_id].split("\n")[r.line])) >= 5)
    assert got == want and len(want) > duplicate_lines(df).count()


def test_short_and_very_long_lines(spark):
    """Equal lines of few words, or of words that no space parts, are repeats; so are near copies of over 8,191 words."""
    long = [f"w{i}" for i in range(9000)]
    docs = [(1, "Chapter one\n---\n\n你好世界再见"), (2, "new\nchapter ONE.\n---\n\n你好世界再见。"), (3, " ".join(long)), (4, " ".join(["x", *long[1:]]))]
    got = duplicate_lines(spark.createDataFrame(docs, "doc_id long, text string"), hamming=None).collect()
    assert sorted(tuple(r) for r in got) == [(2, 1, 1, 0), (2, 4, 1, 3), (4, 0, 3, 0)]


def test_short_lines_of_a_common_run_make_no_pairs(spark):
    """Unlike lines that share a run of words lie in one bucket; odd words tell them apart before pairs are made."""
    from facetsel.llm.lines import EDIT, _across, _hints

    r = random.Random(5)
    lines = [(i, " ".join([f"w{r.randrange(9000)}" for _ in range(9)] + ["one", "common", "run"])) for i in range(200)]
    texts = spark.createDataFrame(lines, "id long, line string")
    entries = texts.select("id", F.lit(12).alias("m"), F.lit(1).cast("long").alias("bucket")).join(_hints(texts, EDIT), "id", "left")
    none = spark.createDataFrame([], "node long, component long")
    assert _across(entries, none, EDIT).count() < 200  # 19,900 before


def test_odd_words_lose_no_link(spark):
    """Lines of any length within the edit similarity are never told apart, whatever the changes are."""
    from facetsel.llm.lines import EDIT, WIDE, WIDE_FROM, _hints, _near

    r = random.Random(6)
    rows = []
    for i in range(400):
        n = r.randint(5, 40)
        a = [f"w{r.randrange(50)}" for _ in range(n)]
        b = list(a)
        for _ in range(n // 5):
            at = r.randrange(len(b))
            b[at : at + 1] = r.choice(([f"w{r.randrange(50)}"], [], [b[at], "more"]))
        if edit(a, b) <= 0.2 * max(len(a), len(b)) + 1e-9 and min(len(a), len(b)) < WIDE_FROM:
            rows.append((2 * i, 2 * i + 1, len(a), len(b), " ".join(a), " ".join(b)))
    assert len(rows) > 200
    pairs = spark.createDataFrame(rows, "a long, b long, m_a int, m_b int, la string, lb string")
    hints = _hints(pairs.selectExpr("stack(2, a, la, b, lb) as (id, line)"), EDIT)
    side = lambda c: hints.select(F.col("id").alias(c), F.col("sim").alias(f"sim_{c}"), F.col("odd").alias(f"odd_{c}"))
    both = pairs.join(side("a"), "a", "left").join(side("b"), "b", "left")
    assert both.where("odd_a is null and m_a < 30 or odd_b is null and m_b < 30").isEmpty()
    assert both.where(_near(("m_a", "m_b"), ("sim_a", "sim_b"), ("odd_a", "odd_b"), WIDE, EDIT)).count() == len(rows)


def test_staged_tables_go_with_their_use(spark):
    """Of the tables staged on the way only those stay that the result reads."""
    import os

    from facetsel.functions.session import shared_dir

    before = set(os.listdir(shared_dir(spark)))
    duplicate_lines(spark.createDataFrame(some_docs(), "doc_id long, text string"), hamming=None).count()
    made = {x.rsplit("-", 1)[0] if len(x.rsplit("-", 1)[1]) == 32 else x for x in set(os.listdir(shared_dir(spark))) - before}
    assert not made & {"line-keys", "line-buckets", "line-others", "line-stars", "line-holders", "line-texts", "line-codes", "line-across"}


def test_long_lines_across_groups_lose_no_link(spark):
    """Lines of one common passage in many common buckets: every pair within the edit similarity is told, as far as its
    SimHashes may lie apart, and few others; lengths that differ allow fewer turned parities."""
    from facetsel.llm.lines import EDIT, _across, _parities

    r = random.Random(8)
    passage = [f"p{i}" for i in range(20)]
    lines = []
    for _ in range(60):
        a = passage + [f"w{r.randrange(9000)}" for _ in range(r.randint(40, 100))]
        b = list(a)
        for _ in range(len(a) // 5):
            at = r.randrange(len(b))
            b[at : at + 1] = r.choice(([f"w{r.randrange(9000)}"], [], [b[at], "more"]))
        lines += [a, b]
    links = {(i, j) for i in range(len(lines)) for j in range(i) if 0.8 * max(len(lines[i]), len(lines[j])) <= min(len(lines[i]), len(lines[j])) and edit(lines[i], lines[j]) <= 0.2 * max(len(lines[i]), len(lines[j])) + 1e-9}
    links = {(b, a) for a, b in links}
    texts = spark.createDataFrame([(i, " ".join(w)) for i, w in enumerate(lines)], "id long, line string")
    entries = spark.createDataFrame([(i, len(w), k) for i, w in enumerate(lines) for k in range(5)], "id long, m int, bucket long")
    got = _across(entries, spark.createDataFrame([], "node long, component long"), EDIT, texts)
    found = {(x.a, x.b) for x in got.collect()}
    assert links <= found and len(links) >= 55 and len(found) < 2 * len(links)
    assert len(_parities(texts).columns) == 9


def test_changed_long_words_lose_no_link(spark):
    """Lines of mostly short words, on whose few long ones a SimHash stands, are near copies when only those differ."""
    r = random.Random(9)
    docs = []
    for i in range(12):
        a = [f"{r.choice('abcdefgh')}{r.randrange(10, 99)}" for _ in range(40)]
        for k in range(2):
            docs.append((2 * i + k, " ".join([*a[:20], *[f"long{i}x{k}y{j}" for j in range(7)], *a[20:]])))
    got = duplicate_lines(spark.createDataFrame(docs, "doc_id long, text string"), hamming=None).collect()
    assert sorted(tuple(x) for x in got) == [(2 * i + 1, 0, 2 * i, 0) for i in range(12)]  # 2 of 12 before


def test_a_large_group_makes_few_pairs(spark, monkeypatch):
    """Near copies meet one leader each, and others only where that left them in several groups."""
    from facetsel.llm import lines

    r, made = random.Random(10), []
    a = [f"w{i}" for i in range(60)]
    docs = [(i, " ".join(f"x{i}" if r.random() < 0.05 else w for w in a)) for i in range(80)]
    similar = lines._similar
    monkeypatch.setattr(lines, "_similar", lambda pairs, *more: made.append(pairs.count()) or similar(pairs, *more))
    got = duplicate_lines(spark.createDataFrame(docs, "doc_id long, text string"), hamming=None).count()
    assert got == 79 and 70 <= sum(made) < 120


def test_keys_of_repeated_lines_are_put_together(spark):
    """Keys of a line that repeats often are told once a line, others as they are."""
    from facetsel.llm.lines import _rarer

    keys = spark.createDataFrame([(1, 7, 5)] * 20 + [(2, 7, 5)] * 20 + [(1, 8, 5)] * 2, "bucket long, id long, m int")
    repeats = spark.createDataFrame([(7, 0, 20), (8, 0, 2)], "d1 long, d2 long, n long")
    assert sorted(tuple(x) for x in _rarer(keys, repeats, 10).select("bucket", "id", "m").collect()) == [(1, 7, 5), (1, 8, 5), (1, 8, 5), (2, 7, 5)]


def test_pairs_are_told_apart_before_their_codes_move(spark):
    """Very long lines, on which few parities tell nothing, are told apart by many; similar ones stay."""
    from facetsel.llm.lines import EDIT, _told_alike

    a = [f"w{i}" for i in range(200)]
    lines = [(1, " ".join(a)), (2, " ".join([*a[:170], *[f"x{i}" for i in range(30)]])), (3, " ".join(f"v{i}" for i in range(200)))]
    pairs = spark.createDataFrame([(1, 2), (1, 3), (2, 3)], "a long, b long")
    got = _told_alike(pairs, spark.createDataFrame([*lines, lines[0]], "id long, line string"), EDIT)
    assert [tuple(x) for x in got.collect()] == [(1, 2)]


def test_lines_meet_by_simhash_too(spark, monkeypatch):
    """The operator's SimHash step adds links that the runs chosen as keys do not show: with no key at all, lines of one
    SimHash are still linked, and a third, unlike line is not."""
    from facetsel.llm import lines

    a = [f"word{i}" for i in range(30)]
    docs = [(1, " ".join(a)), (2, " ".join([*a, "word3"])), (3, " ".join(f"other{i}" for i in range(30)))]
    df = spark.createDataFrame(docs, "doc_id long, text string")
    monkeypatch.setattr(lines, "RUNS", 0)
    assert [tuple(x) for x in duplicate_lines(df, hamming=None).collect()] == [(2, 0, 1, 0)]  # none before


def test_stage_meets_by_simhash_too(spark, monkeypatch):
    """The pipeline's stage has the SimHash step as the operator has it."""
    from facetsel.llm import lines

    a = " ".join(f"word{i}" for i in range(30))
    docs = [(1, a), (2, f"{a} word3"), (3, " ".join(f"other{i}" for i in range(30)))]
    monkeypatch.setattr(lines, "RUNS", 0)
    got = line_stage(spark, spark.createDataFrame(docs, "doc_id long, text string"), "").collect()
    assert sorted(tuple(x) for x in got) == [docs[0], docs[2]]  # all three before
