import re

import pytest

from facetsel.llm.licences import DICE, TEMPLATES, scan, telling_words, template_bigrams


def brute(text):
    out = {}
    units = text.split("\n") + (re.split(r"\n\s*\n", text) if "\n\n" in text else []) + ([text] if "\n" in text else [])
    for u in units:
        w = re.findall(r"[^\W_]+", u.lower())
        b = {f"{x} {y}" for x, y in zip(w, w[1:], strict=False)}
        for name, t in TEMPLATES.items():
            tb = set(template_bigrams(t))
            if b and (d := 2 * len(b & tb) / (len(b) + len(tb))) >= DICE:
                best, n = out.get(name, (0, 0))
                out[name] = (max(best, d), n + 1)
    return {**windows(text), **out}


def windows(text):
    """All windows of the running words, up to the size bound."""
    w, out = re.findall(r"[^\W_]+", text.lower()), {}
    g = [f"{x} {y}" for x, y in zip(w, w[1:], strict=False)]
    for name, t in TEMPLATES.items():
        tb, best, n, last = set(template_bigrams(t)), 0, 0, None
        for i in range(len(g)) if len(tb & set(g)) > 0.6 * len(tb) else ():
            if g[i] in tb:
                seen, top = set(), 0
                for x in g[i : i + int((2 - DICE) / DICE * len(tb) + 1e-9)]:
                    seen.add(x)
                    top = max(top, 2 * len(seen & tb) / (len(seen) + len(tb)))
                if top >= DICE:
                    best = max(best, top)
                    if last is None or i - last >= len(tb):
                        n, last = n + 1, i
        if n:
            out[name] = (best, n)
    return out


def docs():
    out = [(i, t) for i, t in enumerate(TEMPLATES.values())]
    mit = TEMPLATES["mit"]
    out += [(100, f"Copyright 2020 Some One\n\n{mit}\n\nmore"), (101, mit.replace("Software", "Program")), (102, mit[: len(mit) // 3]), (103, "Released under the MIT license\nReleased under the MIT License!"), (104, "We were released under the stars."), (105, ""), (106, "license"), (107, "x " * 5000 + "license")]
    out += [(108, "\n".join(TEMPLATES["isc"].split(". "))), (109, TEMPLATES["apache-2.0 header"].upper())]
    prose = " ".join(f"word{i}" for i in range(300))
    out += [(110, f"{prose}. Released under the MIT License. {prose} and released under the M.I.T. or MIT license (which is no such notice) {prose}"), (111, f"{prose} {mit} {prose}\n{prose}")]
    out += [(112, f"{prose} {' '.join(mit.split()[20:-30])} {prose}"), (113, f"{prose} Released under the {prose} MIT License"), (114, "All rights reserved. Do not copy or distribute. " * 3 + prose)]
    return out


def test_against_all_templates(spark):
    df = spark.createDataFrame([*docs(), (200, None), (0, docs()[0][1])], "doc_id long, text string").selectExpr("*", "'x' as licence", "1 as dice")
    got = {}
    for r in scan(df).collect():
        got.setdefault(r.doc_id, {})[r.licence] = (r.dice, r.n_units)
    want = {i: b for i, t in docs() if (b := brute(t))}
    want[0] = {k: (d, 2 * n) for k, (d, n) in want[0].items()}
    assert got == want and scan(df.limit(0)).count() == 0


def test_each_template_finds_itself(spark):
    df = spark.createDataFrame(list(enumerate(TEMPLATES.values())), "doc_id long, text string")
    best = {(r.doc_id, r.licence) for r in scan(df).where("dice = 1").collect()}
    assert best >= {(i, k) for i, k in enumerate(TEMPLATES)}


def test_bound_loses_nothing():
    for t in TEMPLATES.values():
        b = template_bigrams(t)
        words = telling_words(b, DICE)
        without = [x for x in b if not words & set(x.split())]
        assert 2 * len(without) / (len(without) + len(b)) < DICE


def test_empty_templates(spark):
    with pytest.raises(ValueError):
        scan(spark.createDataFrame([(1, "a")], "doc_id long, text string"), {"none": "word"})


def test_licences_of_several_lines_in_longer_texts(spark):
    """Laid out in paragraphs or wrapped, with any line ends, before and after other words."""
    other = "\n".join(" ".join(f"word{i}x{j}" for i in range(20)) for j in range(10))
    longer = {k: v for k, v in TEMPLATES.items() if len(v) > 200}
    want, docs = {}, []
    for k, v in longer.items():
        w = v.split()
        thirds = [" ".join(w[len(w) * a // 3 : len(w) * (a + 1) // 3]) for a in range(3)]
        wrapped = [" ".join(w[i : i + 12]) for i in range(0, len(w), 12)]
        for body in ("\n\n".join(thirds), "\r\n\r\n".join(thirds), "\n \n".join(thirds), "\r\n".join(wrapped), "\n".join(wrapped)):
            want[len(docs)] = k
            docs.append((len(docs), f"{other}\n\n{body}\n\n{other}"))
    docs.append((len(docs), f"{other}\n\n{other}"))
    got = {(r.doc_id, r.licence): r.dice for r in scan(spark.createDataFrame(docs, "doc_id long, text string")).collect()}
    assert {(i, k) for i, k in want.items()} <= set(got) and all(got[x] == 1 for x in want.items()) and len(docs) - 1 not in {i for i, _ in got}


def test_long_units_of_few_bigrams(spark):
    """A notice again and again in one line has the bigrams of one, whatever its length."""
    t = " ".join(["Released under the MIT License."] * 700)
    assert {r.licence: (r.dice, r.n_units) for r in scan(spark.createDataFrame([(1, t)], "doc_id long, text string")).collect()} == brute(t)


def test_licences_in_running_text(spark):
    """Wrapped between prose lines, or inside one line: found as what they are, and counted by place."""
    got = {}
    for r in scan(spark.createDataFrame([x for x in docs() if x[0] >= 110], "doc_id long, text string")).collect():
        got.setdefault(r.doc_id, {})[r.licence] = (r.dice, r.n_units)
    assert got[110]["mit notice"] == (1, 1) and got[111] == {"mit": (1, 1)} and 113 not in got
    assert 0.8 <= got[112]["mit"][0] < 1 and got[114]["proprietary notice"] == (1, 3)
