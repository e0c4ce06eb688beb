import math
import random
import re
from collections import Counter

import pytest

from facetsel.llm.rules import BANDS, band_rates, base_counts, fertility, quality_rules
from facetsel.llm.tokens import model_path

sentencepiece = pytest.importorskip("sentencepiece")


def brute(text):
    words = re.findall(r"[^\x20\x09-\x0D]+", text or "")
    lines, seen, dup = (text or "").split("\n"), set(), 0
    for x in lines:
        if re.search(r"[^\x20\x09-\x0D]", x):
            dup += x in seen
            seen.add(x)
    windows = Counter(tuple(words[i : i + 3]) for i in range(len(words) - 2))
    covered = {i + k for i in range(len(words) - 2) if windows[tuple(words[i : i + 3])] > 1 for k in range(3)}
    return len(words), sum(map(len, words)), len(re.findall(r"[#*$%&|<>]", text or "")), dup, len(covered)


def texts(n=1500, seed=0):
    r = random.Random(seed)
    alphabet = ["a", "b", "bé", "#", "|", " ", " ", " ", "\n", "\t", "\x1c", "\xa0", "\x0b", "the", "日", "😀"]
    return ["".join(r.choice(alphabet) for _ in range(r.choice((0, 1, 3, 20, 120)))) for _ in range(n)]


def test_base_counts():
    for t in [*texts(), None, "", "\n\n", "a b c a b c", "x x x x"]:
        assert base_counts(t) == brute(t), repr(t)


def test_whole_query(spark):
    rows = [(i, t, ("en", "fr", None, "xx")[i % 4]) for i, t in enumerate(texts(150, 2))] + [(900, None, None), (901, "plain words of a text " * 40, "en"), (None, "é " * 60, "de")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string").selectExpr("*", "true as kept")
    sp = sentencepiece.SentencePieceProcessor(model_file=model_path())
    got = {(r.doc_id): r for r in quality_rules(docs).collect()}
    for i, t, lang in rows:
        g, n = got[i], brute(t)
        assert (g.n_words, g.word_chars, g.n_symbols, g.n_dup_lines, g.n_repeat_words) == n
        assert g.base_failed == (n[0] < 50 or 100 * n[4] > 50 * n[0])
        ids = sp.encode(t or "")
        assert g.n_tokens == len(ids)
        if ids:
            assert g.byte_share == pytest.approx(sum(map(sp.is_byte, ids)) / len(ids)) and g.chars_per_token == pytest.approx(len(t) / len(ids))
        low, high, most, least = BANDS[g.band]
        assert g.fence is None and not g.fenced  # too few texts
        assert g.kept == (not g.base_failed and low <= g.chars_per_token <= high and g.byte_share <= most and g.entropy >= least)
        assert g.band == (lang if lang in BANDS else g.band)


def test_entropy():
    class Two:
        bytes = [False] * 4

        def ids(self, text):
            return [0, 1, 0, 1]

    two = Two()
    two.bytes = __import__("numpy").zeros(4, bool)
    n, per, byte, entropy = fertility("abcd", two)
    assert (n, per, byte) == (4, 1.0, 0.0) and entropy == pytest.approx(1 / math.log2(4))


def test_clean_documents_are_kept(spark, sf_dir):
    docs, labels = (spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in ("documents", "labels"))
    rows = quality_rules(docs).where("n_words >= 50").join(labels.where("quality = 1"), "doc_id").collect()
    assert sum(r.kept for r in rows) >= 0.95 * len(rows)


def fence_of(values):
    """Quartiles by linear interpolation, and three ranges beyond."""
    values = sorted(round(v, 3) for v in values)
    at = lambda p: values[int(p)] + (p - int(p)) * (values[min(int(p) + 1, len(values) - 1)] - values[int(p)])
    a, b = at(0.25 * (len(values) - 1)), at(0.75 * (len(values) - 1))
    return a - 3 * (b - a), b + 3 * (b - a)


def spoiled(r, texts):
    """Texts that pass the base rules and are none: wrongly decoded, consonants, digits, signs. Shuffled letters are not
    seen in the given tables, whose words are invented; see test_shuffled_letters."""
    out = []
    for t in texts:
        words = t.split()
        out.append(("mojibake", " ".join(w + r.choice(["Ã©", "â€™", "Ã¼"]) for w in words)))
        out.append(("keys", " ".join("".join(r.choice("bcdfghjklmnpqrstvwxz") for _ in w) for w in words)))
        out.append(("codes", " ".join("".join(r.choice("0123456789abcdef") for _ in range(9)) for w in words)))
        out.append(("signs", " ".join(w + r.choice("☃♞⌘⚙") for w in words)))
    return out


def test_fences_and_planted_texts(spark, sf_dir):
    docs, labels = (spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in ("documents", "labels"))
    docs = docs.select("doc_id", "text", "lang")
    clean = [r.text for r in docs.where("lang = 'en'").join(labels.where("quality = 1"), "doc_id").orderBy("doc_id").limit(12).collect()]
    bad = spoiled(random.Random(3), [t for t in clean if len(t.split()) >= 80])
    planted = spark.createDataFrame([(10**9 + i, t, "en") for i, (_, t) in enumerate(bad)], docs.schema)
    rules = quality_rules(docs.unionByName(planted), least=20)
    got = {r.doc_id: r for r in rules.collect()}
    kind = {}
    for i, (k, _) in enumerate(bad):
        kind.setdefault(k, []).append(got[10**9 + i].kept)
    assert all(sum(v) <= 0.1 * len(v) for v in kind.values()), {k: sum(v) / len(v) for k, v in kind.items()}
    for band in ("en", "fr"):
        rows = [r for r in got.values() if r.band == band and not r.base_failed]
        if len(rows) < 20:
            continue
        for c, lo, hi in (("chars_per_token", "low", "high"), ("byte_share", None, "most_bytes"), ("entropy", "least_entropy", None)):
            a, b = fence_of([r[c] for r in rows])
            assert lo is None or rows[0].fence[lo] == pytest.approx(a)
            assert hi is None or rows[0].fence[hi] == pytest.approx(b)
    rates = {r.band: r for r in band_rates(rules).collect()}
    assert sum(r.n for r in rates.values()) == len(got) and sum(r.kept for r in rates.values()) == sum(r.kept for r in got.values())
    assert all(r.n == r.base_failed + r.outside_band + r.outside_fence + r.kept for r in rates.values())
    assert rates["en"].outside_band > 0


def test_empty_table(spark):
    none = spark.createDataFrame([], "doc_id long, text string, lang string, fence string")
    assert quality_rules(none).count() == 0


def test_shuffled_letters(spark):
    r = random.Random(5)
    english = "people often walk through the market before breakfast because morning light makes every colour brighter and children laugh while their parents choose fresh vegetables from wooden tables near old stone houses under green trees where birds sing about another summer that will surely return after long winter nights without much snow or rain".split()
    english += "the of and to a in is it he was on as at by we be an so up if".split() * 2
    good = [" ".join(r.choice(english) for _ in range(120)) for _ in range(300)]
    bad = [" ".join("".join(r.sample(w, len(w))) for w in t.split()) for t in good[:20]]
    got = {x.doc_id: x for x in quality_rules(spark.createDataFrame([(i, t, "en") for i, t in enumerate(good + bad)], "doc_id long, text string, lang string")).collect()}
    assert not any(got[300 + i].base_failed or got[300 + i].kept for i in range(20)) and sum(got[i].kept for i in range(300)) >= 297
