"""Quality rules with tokeniser fertility.

Base rules count words, characters, symbols, repeated lines and repeated three-word windows. The fertility rule measures,
under a public vocabulary, characters per token, the share of byte-fallback tokens and the entropy of the tokens, and
rejects a text outside the bands of its language, or of its main script where the language has none. There are two bands:
a wide one of fixed values, and one that the table itself gives, fences FENCE interquartile ranges beyond the quartiles of
all texts that pass the base rules. A language needs LEAST_ROWS such texts for fences, or else goes by its script's; where
these are too few as well, the wide band decides alone. Quartiles are exact, of measures rounded to thousandths.

Defined results: a null text has no words, fails the base rules and has zero measures; null or unknown languages go by
script; a null id stays null; repeated rows give repeated rows, and count as often for the quartiles; other columns are
ignored. Whole texts, read once; what is measured of them, a few numbers a row, is staged."""

from __future__ import annotations

import math
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from facetsel.llm.common import given_id, ship, small, staged, table, whole_id
from facetsel.llm.tokens import MODEL, model_path

SYMBOLS, SPACES = b"#*$%&|<>", b" \t\n\v\f\r"
LEAST_WORDS, MOST_REPEATED_PERCENT = 50, 50
#: Far outliers, as box plots have them; texts that quartiles are taken of.
FENCE, LEAST_ROWS = 3.0, 200

# Bands by language, then by script; least and most characters per token, most share of byte-fallback
# tokens, least entropy in bits a token relative to the most that so many tokens can have.
BANDS = {
    "en": (2.10, 6.00, 0.08, 0.48),
    "fr": (1.95, 6.00, 0.08, 0.48),
    "de": (2.20, 6.00, 0.08, 0.48),
    "es": (2.00, 6.00, 0.08, 0.48),
    "latin": (1.90, 6.50, 0.10, 0.45),
    "other": (0.30, 4.00, 0.60, 0.35),
}


class _Pieces(dict):
    """Words, each after one space, with the ids of their tokens; bounded."""

    def __init__(self, model: str, most: int = 300_000):
        import sentencepiece

        self.processor, self.most = sentencepiece.SentencePieceProcessor(model_file=model_path(model)), most
        p = self.processor
        self.bytes = np.fromiter((p.is_byte(i) for i in range(p.get_piece_size())), bool)

    def __missing__(self, word: str) -> tuple[int, ...]:
        ids = tuple(self.processor.encode(word))
        if len(word) <= 40:
            if len(self) >= self.most:
                self.clear()
            self[word] = ids
        return ids

    def ids(self, text: str) -> list[int]:
        """No piece goes over the start of a word, so words that one space parts can be encoded one by one."""
        if "▁" in text or "  " in text or text[0] == " " or text[-1] == " ":
            return self.processor.encode(text)
        return list(chain.from_iterable(map(self.__getitem__, text.split(" "))))


_KEPT: dict[str, _Pieces] = {}


def fertility(text: str, pieces: _Pieces) -> tuple[int, float, float, float]:
    """Tokens, characters per token, byte-fallback share, entropy relative to its maximum (1.0 for one token)."""
    if not text:
        return 0, 0.0, 0.0, 0.0
    ids = np.array(pieces.ids(text), np.int64)
    n = len(ids)
    counts = np.bincount(ids)
    counts = counts[counts > 0]
    most = math.log2(min(n, len(pieces.bytes)))
    entropy = float(math.log2(n) - (counts * np.log2(counts)).sum() / n)
    return n, len(text) / n, float(pieces.bytes[ids].mean()), entropy / most if most else 1.0


def base_counts(text: str | None) -> tuple[int, int, int, int, int]:
    """n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words."""
    text = text or ""
    raw = text.encode("utf-8", "surrogatepass")
    words = raw.split()
    n = len(words)
    chars = len(text) - (len(raw) - len(raw.translate(None, SPACES)))
    symbols = len(raw) - len(raw.translate(None, SYMBOLS))
    lines = [x for x in raw.split(b"\n") if x.strip()]
    repeated = 0
    if n >= 4:
        ids = {w: i for i, w in enumerate(set(words))}
        a = np.fromiter(map(ids.__getitem__, words), np.int64, n)
        pairs = np.unique(a[:-1] * len(ids) + a[1:], return_inverse=True)[1]
        windows = pairs[:-1] * len(ids) + a[2:]
        _, back, counts = np.unique(windows, return_inverse=True, return_counts=True)
        twice = counts[back] > 1
        cover = np.zeros(n, bool)
        for k in range(3):
            cover[k : n - 2 + k] |= twice
        repeated = int(cover.sum())
    return n, chars, symbols, len(lines) - len(set(lines)), repeated


def _main_script(text: str) -> str:
    letters = sum(map(str.isalpha, text))
    return "latin" if sum(c < "ɐ" for c in text if c.isalpha()) * 2 >= letters else "other"


def judge(text: str | None, lang: str | None, pieces: _Pieces, bands: dict = BANDS) -> tuple:
    n, chars, symbols, dup, rep = base_counts(text)
    failed = n < LEAST_WORDS or 100 * rep > MOST_REPEATED_PERCENT * n
    tokens, per, byte, entropy = fertility(text or "", pieces)
    script = _main_script(text or "")
    band = lang if lang in bands else script
    low, high, most_bytes, least_entropy = bands[band]
    kept = not failed and low <= per <= high and byte <= most_bytes and entropy >= least_entropy
    return n, chars, symbols, dup, rep, failed, kept, tokens, per, byte, entropy, band, lang, script


SCHEMA = "doc_id long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, kept boolean, n_tokens long, chars_per_token double, byte_share double, entropy double, band string, lang string, script string"


def _fences(measured: DataFrame, by: str, fence: float, least: int) -> DataFrame:
    """(by, fence_<by>): the least and most characters per token, the most byte share and the least entropy, of each
    language or script with so many texts that pass the base rules."""
    quartiles = lambda c: F.percentile(F.round(c, 3), F.array(F.lit(0.25), F.lit(0.75)))
    of = measured.where(~F.col("base_failed") & F.col(by).isNotNull()).groupBy(by)
    got = of.agg(F.count("*").alias("n"), *[quartiles(c).alias(c) for c in ("chars_per_token", "byte_share", "entropy")]).where(F.col("n") >= least)
    low = lambda c: F.col(c)[0] - fence * (F.col(c)[1] - F.col(c)[0])
    high = lambda c: F.col(c)[1] + fence * (F.col(c)[1] - F.col(c)[0])
    told = F.struct(low("chars_per_token").alias("low"), high("chars_per_token").alias("high"), high("byte_share").alias("most_bytes"), low("entropy").alias("least_entropy"))
    return staged(got.select(by, told.alias(f"fence_{by}")), f"fences-{by}")


def quality_rules(docs: DataFrame, text: str = "text", key: str = "doc_id", lang: str = "lang", model: str = MODEL, bands: dict = BANDS, fence: float = FENCE, least: int = LEAST_ROWS) -> DataFrame:
    """Base counts, fertility measures, the fences that held and the verdict of every row. fenced is true where a text
    that passes the base rules and the wide band lies beyond the fences."""
    ship(docs.sparkSession)

    def measured(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        from facetsel.llm import rules

        pieces = rules._KEPT.get(model) or rules._KEPT.setdefault(model, rules._Pieces(model))
        names = [x.split()[0] for x in SCHEMA.split(", ")]
        for b in batches:
            rows = [(k, *rules.judge(t, g, pieces, bands)) for k, t, g in zip(b["k"], b["t"], b["g"], strict=True)]
            yield pd.DataFrame(rows, columns=names)

    rows = staged(docs.select(whole_id(key).alias("k"), F.col(text).alias("t"), F.col(lang).alias("g")).mapInPandas(measured, SCHEMA), "fertility")
    out = rows
    for by in ("lang", "script"):
        out = out.join(small(_fences(rows, by, fence, least)), by, "left")
    held = F.coalesce("fence_lang", "fence_script")
    within = F.col("chars_per_token").between(held["low"], held["high"]) & (F.col("byte_share") <= held["most_bytes"]) & (F.col("entropy") >= held["least_entropy"])
    out = out.withColumn("fenced", F.col("kept") & ~F.coalesce(within, F.lit(True))).withColumn("kept", F.col("kept") & ~F.col("fenced"))
    names = [x.split()[0] for x in SCHEMA.split(", ") if x.split()[0] not in ("doc_id", "lang", "script")]
    return out.select(given_id("doc_id").alias("doc_id"), *names, "script", held.alias("fence"), "fenced")


def band_rates(rules: DataFrame) -> DataFrame:
    """(band, n, base_failed, outside_band, outside_fence, kept): how many texts of a band each rule turns away."""
    one = lambda c: F.sum(c.cast("long"))
    wide = ~F.col("base_failed") & ~F.col("kept") & ~F.col("fenced")
    return rules.groupBy("band").agg(F.count("*").alias("n"), one(F.col("base_failed")).alias("base_failed"), one(wide).alias("outside_band"), one(F.col("fenced")).alias("outside_fence"), one(F.col("kept")).alias("kept"))


def op9_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_rules(table(spark, sf_dir, "documents"))
