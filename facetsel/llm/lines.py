"""Fuzzy line dedup, with DataFrame functions only.

Lines are normalised (lower case, words of letters and digits) and digested; equal digests are one line. Different lines
of at least LEAST_WORDS words are linked by edit similarity, one less the share of words to change, and of each connected
group the first occurrence stays.

Which lines are compared follows from the pigeonhole principle, over words: so few words may differ that some block of a
line is left whole. Lines of up to DROP words, of which one may differ, meet by what is left of them without one word;
longer ones by their runs of RUN neighbouring words, of which each changed word spoils RUN at most. Of the runs of a line
those are keys whose hash lies under a bound that leaves RUNS of them on average, the same ones in any line. In a bucket
of equal keys all lines meet the leader, then those of different groups meet (see buckets.py), as far as their numbers of
words allow the similarity. Lines are told apart by which words they hold an odd number of times, which loses nothing. What
is left is verified by edit distance.

Then lines of different groups meet by their SimHashes: two lines within HAMMING bits of each other agree in so many of
their blocks of bits that they meet in a bucket of some selection of blocks, whichever runs they have as keys. These pairs
are verified alike, and add links to those of the words. SimHash: 64 bits, each the weighted majority of that bit over the
hashes of a line's distinct words, longer words weighing more; sums are kept in 15-bit lanes of 16 numbers, which plain
sums add up. hamming=HAMMING gives the narrower operator of SimHashes alone. It links few lines, as few changed words move
a SimHash by far more bits.

Defined results: null and empty texts have no lines; lines of fewer than LEAST_WORDS words are compared by digest only, and
lines without words always stay; lines of more than 8,191 distinct words meet by words only; with hamming=HAMMING shorter
lines stay, and those longer ones are compared by digest only; repeated rows (equal ids) count as one occurrence
of their lines; null ids come first. Other columns are ignored.
"""

from __future__ import annotations

import math
from itertools import combinations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from facetsel.llm.buckets import across, stars, unsettled
from facetsel.llm.common import components, released, small, staged, table

LEAST_WORDS, HAMMING, EDIT = 5, 3, 0.8
#: The most words of lines that meet without one word; words of a run, and how many runs of a line are keys on average.
DROP, RUN, RUNS = 9, 3, 8
#: Bits of 64 in which the SimHashes of lines of WIDE_FROM words or more may differ from a leader's.
WIDE, WIDE_FROM = 26, 30
#: Numbers of 64 bits that tell by parities of words which lines of different groups may be similar.
PARITIES = 8
#: Numbers of 64 bits of parities that every line has from the first pass on; a power of two.
ODDS = 2
#: Entries of a bucket from which on those of equal lines are put together before they move.
HOT_LINE = 10_000
#: Rows of ids or of lists of places that the driver may hold for a broadcast, beside what the session takes of its memory.
HELD_ROWS = 200_000
#: Longer words than this weigh more than short ones, mostly function words that all lines share: else unlike lines of one
#: language would agree in many bits, and meet in buckets, by those words alone.
SHORT, LONG_WEIGHT = 3, 4
#: Codes of words.
CODES = 1_000_000
#: A lane holds so many words of the greater weight.
LANE_WORDS = 8_191
_NO_ID = -(1 << 63)
#: What parts words: Latin-1 signs one by one, which are looked up faster than ranges, general and CJK punctuation.
_GAPS = "".join(f"\\x{c:02X}" for c in range(256) if not chr(c).isalnum() and c not in (10, 32)) + r"\u2000-\u206F\u2E00-\u2E7F\u3000-\u303F"


#: Ones at the lowest bits of the four lanes of a number.
_LANES = 1 | 1 << 15 | 1 << 30 | 1 << 45


def _lane(hashed: str, k: int) -> str:
    """Four bits of a hash, from bit 4k, as zeros and ones at bits 0, 15, 30 and 45: the factor puts copies of the four
    at distances of 14, and the mask takes another bit from each."""
    return f"((shiftrightunsigned({hashed}, {4 * k}) & 15L) * {1 | 1 << 14 | 1 << 28 | 1 << 42}L) & {_LANES}L"


def _majority(sums: DataFrame, lanes: list[str], n: str, kept: list[str]) -> DataFrame:
    """kept and sim, the 64 bits from the lanes' sums: what is added to a lane carries into its top bit where more than
    half of n were ones, and shifts bring the four top bits together."""
    carried = sums.select(*kept, n, *lanes, F.expr(f"(16383L - shiftright({n}, 1)) * {_LANES}L").alias("half"))
    tops = carried.select(*kept, n, *[F.expr(f"shiftrightunsigned({s} + half, 14) & {_LANES}L").alias(s) for s in lanes])
    four = [f"shiftleft(({s} | shiftrightunsigned({s}, 14) | shiftrightunsigned({s}, 28) | shiftrightunsigned({s}, 42)) & 15L, {4 * k})" for k, s in enumerate(lanes)]
    quarters = tops.select(*kept, n, *[F.expr(" | ".join(four[k : k + 4])).alias(f"q{k}") for k in range(0, 16, 4)])
    return quarters.select(*kept, F.expr(f"if({n} > 0, q0 | q4 | q8 | q12, null)").alias("sim"))


def _simhashed(words: DataFrame, kept: list[str], short: bool = True) -> DataFrame:
    """kept and sim of rows (kept, u: distinct words or a null in place of them), by kept; of equal rows one is told.
    short: whether short words count at all."""
    rows = words.select(*kept, F.explode("u").alias("word"))
    rows = rows if short else rows.where(F.length("word") > SHORT)
    weight = F.when(F.length("word") > SHORT, LONG_WEIGHT).otherwise(1).cast("long")
    rows = rows.select(*kept, F.xxhash64("word").alias("h"), F.when(F.col("word").isNotNull(), weight).otherwise(0).alias("weight"))
    lanes = [f"s{k}" for k in range(16)]
    sums = rows.groupBy(*kept).agg(F.sum("weight").alias("n"), *[F.expr(f"sum(({_lane('h', k)}) * weight)").alias(s) for k, s in enumerate(lanes)])
    return _majority(sums, lanes, "n", kept)


def words_of(line: Column) -> Column:
    return _spaced(F.regexp_replace(F.lower(line), f"[\\n{_GAPS}]+", " "))


def _spaced(line: Column) -> Column:
    """The words of a line whose gaps are spaces. A split by one plain character compiles no pattern for each line."""
    return F.array_remove(F.split(line, " "), "")


def placed(docs: DataFrame, text: str, key: str) -> DataFrame:
    """One pass over the texts: of every line with words a row (doc_id, pos, d1, d2, m, o0, o1, bucket), its digests, its
    number of words and its parities; of every block of a line of enough words a row (d1, m, bucket), the rest null. A
    line's own row has a bucket too where shorter or longer lines by a word may meet it.

    Parities: which of 64 * ODDS bits an odd number of words has by its hash. What is left of a line without a word has the
    digest that a line of just those words has. Of lines of n words, n / 5 may differ; runs of three that are spoiled are
    at most three times as many, so that lines of ten words and more always have two runs in common, and lines of nine and
    fewer differ in one word at most. Arrays of one element are exploded so that what a line needs once is computed once."""
    cut = docs.select(F.coalesce(F.col(key), F.lit(_NO_ID).cast("long")).alias("doc_id"), F.posexplode(F.split(F.regexp_replace(F.lower(F.col(text)), f"[{_GAPS}]+", " "), "\n")).alias("pos", "line"))
    cut = cut.select("doc_id", "pos", F.explode(F.array(_spaced(F.col("line")))).alias("w")).where(F.size("w") > 0)
    cut = cut.select("doc_id", "pos", "w", F.explode(F.array(F.transform("w", lambda x: F.xxhash64(x)))).alias("h"))
    odd = [F.expr(f"aggregate(h, 0L, (a, x) -> if((shiftright(x, 6) & {ODDS - 1}) = {k}, a ^ shiftleft(1L, cast(x & 63 as int)), a))").alias(f"o{k}") for k in range(ODDS)]
    told = F.struct("doc_id", "pos", F.xxhash64("h").alias("d1"), F.xxhash64(F.lit(7), F.col("w")).alias("d2"), F.size("h").alias("m"), *odd, F.col("h").alias("h"))
    at = cut.select(F.explode(F.array(told)).alias("x")).select("x", F.posexplode(F.when(F.col("x.m") >= LEAST_WORDS, F.col("x.h")).otherwise(F.slice("x.h", 1, 1))).alias("i", "first"))
    run = F.xxhash64(F.lit(RUN), "first", *[F.get("x.h", F.col("i") + k) for k in range(1, RUN)])
    whole = F.col("i") + RUN <= F.col("x.m")
    chosen = (F.col("x.m") > DROP) & whole & (run.bitwiseAND(F.lit((1 << 20) - 1)) * (F.col("x.m") - RUN + 1) < RUNS << 20)
    less = F.xxhash64(F.slice("x.h", F.lit(1), F.col("i")), F.slice("x.h", F.col("i") + 2, F.col("x.m")))
    short = F.col("x.m").between(LEAST_WORDS, DROP)
    head = F.col("i") == 0
    at = at.where(head | short | chosen)
    own = F.when((F.col("x.m") >= LEAST_WORDS) & (F.col("x.m") < DROP), F.col("x.d1"))
    none = F.array().cast("array<bigint>")
    found = F.when(chosen, F.array(run)).when(short & whole & (F.col("x.m") >= DROP - 1), F.array(run, less)).when(short, F.array(less)).otherwise(none)
    rows = at.select("x", "i", F.posexplode(F.concat(F.when(head, F.array(own)).otherwise(none), found)).alias("j", "bucket"))
    line = lambda c: F.when((F.col("i") == 0) & (F.col("j") == 0), F.col(f"x.{c}")).alias(c)
    return rows.select(line("doc_id"), line("pos"), F.col("x.d1").alias("d1"), line("d2"), F.col("x.m").alias("m"), *[line(f"o{k}") for k in range(ODDS)], "bucket")


def digested(docs: DataFrame, text: str, key: str, least: int = LEAST_WORDS) -> DataFrame:
    """(doc_id, pos, d1, d2, sim) of every line of enough words, digests as placed() has them; sim is null where it has too
    many, or too few for links."""
    cut = docs.select(F.coalesce(F.col(key), F.lit(_NO_ID).cast("long")).alias("doc_id"), F.posexplode(F.split(text, "\n")).alias("pos", "line"))
    cut = cut.select("doc_id", "pos", F.explode(F.array(words_of(F.col("line")))).alias("w"))
    told = F.struct(F.xxhash64(F.transform("w", lambda x: F.xxhash64(x))).alias("d1"), F.xxhash64(F.lit(7), F.col("w")).alias("d2"), F.array_distinct("w").alias("u"))
    cut = cut.where(F.size("w") >= least).select("doc_id", "pos", F.size("w").alias("m"), F.explode(F.array(told)).alias("x"))
    few = F.when((F.size("x.u") <= LANE_WORDS) & (F.col("m") >= LEAST_WORDS), F.col("x.u")).otherwise(F.array(F.lit(None).cast("string")))
    return _simhashed(cut.select("doc_id", "pos", "x.d1", "x.d2", few.alias("u")), ["doc_id", "pos", "d1", "d2"])


def selections(n: int, hamming: int = HAMMING, spare_bits: int = 4, bits: int = 64) -> list[int]:
    """Masks of bits. Of hamming + m blocks, two values within hamming bits agree in m at least; all selections of m are
    taken, with the least m whose buckets are expected to hold few of n values."""
    m = 1
    while bits * m // (hamming + m) < math.log2(max(2, n)) + spare_bits and m < 5:
        m += 1
    edges = [bits * i // (hamming + m) for i in range(hamming + m + 1)]
    blocks = [(1 << b) - (1 << a) for a, b in zip(edges, edges[1:], strict=False)]
    return [sum(x) for x in combinations(blocks, m)]


def _signed(x: int) -> int:
    return x - (1 << 64) if x >= 1 << 63 else x


def coded(words: Column) -> Column:
    """The words as one string, a code point for each: a million codes by hash, so that two different words of a pair of
    lines are taken for the same about once in a million comparisons. Edit distances over it count words."""
    codes = F.transform(words, lambda x: F.lpad(F.hex(F.pmod(F.xxhash64(x), F.lit(CODES)) + 65_536), 8, "0"))
    return F.decode(F.unhex(F.array_join(codes, "")), "UTF-32")


def _lines_at(docs: DataFrame, places: DataFrame, text: str, key: str) -> DataFrame:
    """(id, line) of places (id, doc_id, pos), read again from the documents that hold them, each of which is cut once;
    staged. places are staged too."""
    listed = staged(places.groupBy("doc_id").agg(F.collect_list(F.struct("pos", "id")).alias("held")), "line-holders")
    told = F.broadcast(listed) if places.count() <= HELD_ROWS else listed.hint("shuffle_hash")
    texts = docs.select(F.coalesce(F.col(key), F.lit(_NO_ID).cast("long")).alias("doc_id"), F.col(text).alias("t")).join(told, "doc_id")
    cut = texts.select("held", F.explode(F.array(F.split("t", "\n"))).alias("lines")).select("lines", F.explode("held").alias("x"))
    out = staged(cut.select("x.id", F.get("lines", F.col("x.pos")).alias("line")), "line-texts")
    released(listed)
    return out


def _codes(lines: DataFrame) -> DataFrame:
    """(id, line) with the words as codes, staged; ids that repeated rows hold more than once have one text."""
    texts = lines.select("id", coded(words_of(F.col("line"))).alias("line"))
    return staged(texts.groupBy("id").agg(F.max("line").alias("line")), "line-codes")


def _similar(pairs: DataFrame, codes: DataFrame, edit: float) -> DataFrame:
    """Pairs (a, b) whose lines, as _codes() has them, have the edit similarity, staged."""
    both = pairs.join(codes.select(F.col("id").alias("a"), F.col("line").alias("la")), "a").join(codes.select(F.col("id").alias("b"), F.col("line").alias("lb")), "b")
    longest = "greatest(length(la), length(lb))"
    near = both.where(f"least(length(la), length(lb)) >= {edit} * {longest}").where(f"levenshtein(la, lb, int(floor({1 - edit:.6f} * {longest} + 1e-9))) >= 0")
    return staged(near.select("a", "b"), "line-links")


def _verified(pairs: DataFrame, lines: DataFrame, edit: float) -> DataFrame:
    """Pairs (a, b) of line digests whose lines (id, line) have the edit similarity. Both are staged."""
    named = staged(pairs.select(F.explode(F.array("a", "b")).alias("id")).distinct(), "line-ids")
    codes = _codes(lines.join(small(named, HELD_ROWS), "id"))
    out = _similar(pairs, codes, edit)
    released(named, codes)
    return out


def _led(entries: DataFrame, hamming: int) -> DataFrame:
    """(id, bucket, leader) of the buckets that hold several lines, as buckets.led() has it; but a bucket of two or three
    lines none of which is near another, as most chance meetings are, goes at once: the least, the greatest and the sum
    without carry of their SimHashes tell all three."""
    mixed = F.col("id").bitwiseXOR(F.col("bucket"))
    sums = entries.groupBy("bucket").agg(F.min(mixed).alias("lo"), F.count("*").alias("n"), F.min("sim").alias("p"), F.max("sim").alias("q"), F.bit_xor("sim").alias("x"))
    near = " or ".join(f"bit_count({d}) <= {hamming}" for d in ("p ^ q", "x ^ p", "x ^ q"))  # x ^ p is q ^ r, x ^ q is p ^ r
    leaders = sums.where(f"n > 3 or (n = 2 and bit_count(p ^ q) <= {hamming}) or (n = 3 and ({near}))")
    leaders = staged(leaders.select("bucket", F.col("lo").bitwiseXOR(F.col("bucket")).alias("leader")), "line-leaders")
    return entries.select("id", "bucket").join(leaders, "bucket")


def _places(lines: DataFrame, ids: DataFrame) -> DataFrame:
    """(id, doc_id, pos): the first place of each of the ids, staged."""
    held = lines.select(F.col("d1").alias("id"), "doc_id", "pos").join(ids, "id")
    first = held.groupBy("id").agg(F.min(F.struct("doc_id", "pos")).alias("p"))
    return staged(first.select("id", "p.doc_id", "p.pos"), "line-places")


def _lengths(a: str, b: str, edit: float) -> str:
    return f"1000000L * least({a}, {b}) >= {round(1e6 * edit)}L * greatest({a}, {b})"


def _turned(a: str, b: str, edit: float) -> str:
    """How many bits of parities may differ between similar lines of a and b words: two for a changed word, one for each
    word that comes or goes, and as many come or go as the lengths differ by."""
    return f"2 * floor({1 - edit:.6f} * greatest({a}, {b}) + 1e-9) - abs({a} - {b})"


def _alike(a: str, b: str, odds: list[tuple[str, str]], edit: float) -> str:
    """Whether parities of lines of a and b words allow the similarity."""
    return f"{' + '.join(f'bit_count({x} ^ {y})' for x, y in odds)} <= {_turned(a, b, edit)}"


def _near(m: tuple[str, str], sim: tuple[str, str], odd: tuple[str, str], bits: int, edit: float) -> str:
    """Whether SimHashes of long lines and odd words of short ones allow it; a line without one of them is compared with
    all. By _turned() this loses no link of short lines."""
    close = f"(least({m[0]}, {m[1]}) < {WIDE_FROM} or coalesce(bit_count({sim[0]} ^ {sim[1]}) <= {bits}, true))"
    return f"{close} and coalesce(bit_count({odd[0]} ^ {odd[1]}) <= {_turned(*m, edit)}, true)"


def _hints(texts: DataFrame, edit: float) -> DataFrame:
    """(id, sim, odd) of lines (id, line), staged: SimHashes of lines of WIDE_FROM words or more, and of lines that may be
    similar to shorter ones, which of 64 bits an odd number of words has by its code, as coded() gives it."""
    cut = texts.select("id", F.explode(F.array(words_of(F.col("line")))).alias("w"))
    words = cut.where(F.size("w") >= WIDE_FROM).select("id", F.explode(F.array(F.array_distinct("w"))).alias("u")).where(F.size("u") <= LANE_WORDS)
    sims = _simhashed(words, ["id"], short=False).select("id", "sim", F.lit(None).cast("long").alias("odd"))
    odd = F.expr(f"aggregate(w, 0L, (a, x) -> a ^ shiftleft(1L, cast(pmod(xxhash64(x), {CODES}) % 64 as int)))")
    odds = cut.where(F.size("w") * edit < WIDE_FROM).select("id", F.lit(None).cast("long").alias("sim"), odd.alias("odd"))
    return staged(sims.unionByName(odds).groupBy("id").agg(F.max("sim").alias("sim"), F.max("odd").alias("odd")), "line-hints")


def _parities(texts: DataFrame) -> DataFrame:
    """(id, p0, p1, ...) of lines (id, line), staged: which of 64 * PARITIES bits an odd number of words has by its code."""
    codes = F.transform(words_of(F.col("line")), lambda x: F.pmod(F.xxhash64(x), F.lit(CODES)) % (64 * PARITIES))
    cut = texts.select("id", F.explode(F.array(codes)).alias("w"))
    bits = [F.expr(f"aggregate(w, 0L, (a, x) -> if(shiftright(x, 6) = {k}, a ^ shiftleft(1L, cast(x & 63 as int)), a))") for k in range(PARITIES)]
    told = cut.select("id", *[x.alias(f"p{k}") for k, x in enumerate(bits)])
    return staged(told.groupBy("id").agg(*[F.max(f"p{k}").alias(f"p{k}") for k in range(PARITIES)]), "line-parities")


def _across(entries: DataFrame, groups: DataFrame, edit: float, texts: DataFrame | None = None) -> DataFrame:
    """Distinct (a, b): lines (id, m) of one bucket that lie in different groups and may be similar. Only lines of the same
    class of lengths, or of the next, are laid side by side, and lines that share several buckets in the least of them.
    Parities of many bits, of the entries or of texts (id, line), tell unlike lines apart, which loses no link, and the
    result is staged; without both, entries have sim and odd."""
    left, made, ready = unsettled(entries, groups), [], "o0" in entries.columns
    if texts is None and not ready:
        near = F.expr(_near(("l.m", "r.m"), ("l.sim", "r.sim"), ("l.odd", "r.odd"), WIDE, edit))
    else:
        odds = [f"o{k}" for k in range(ODDS)] if ready else []
        rows = staged(left.select("id", "bucket", "m", "component", *odds), "line-unsettled")
        ids = staged(rows.groupBy("id").agg(F.sort_array(F.collect_set("bucket")).alias("buckets")), "line-ids")
        made, left = [rows, ids], rows.join(ids, "id")
        if not ready:
            told = _parities(texts.join(small(ids.select("id"), HELD_ROWS), "id"))
            odds, made, left = [f"p{k}" for k in range(PARITIES)], [*made, told], left.join(told, "id")
        near = F.expr(_alike("l.m", "r.m", [(f"l.{x}", f"r.{x}") for x in odds], edit)) & F.expr("l.bucket = array_min(array_intersect(l.buckets, r.buckets))")
    left = left.withColumn("c", F.floor(F.log("m") / -math.log(edit)))
    other = left.withColumn("own", F.col("c")).withColumn("c", F.explode(F.array(F.col("c"), F.col("c") + 1)))
    once = (F.col("l.component") < F.col("r.component")) | ((F.col("r.own") < F.col("l.c")) & (F.col("l.component") != F.col("r.component")))
    on = (F.col("l.bucket") == F.col("r.bucket")) & (F.col("l.c") == F.col("r.c")) & once
    pairs = left.alias("l").join(other.alias("r"), on & F.expr(_lengths("l.m", "r.m", edit)) & near)
    pairs = pairs.select(F.least("l.id", "r.id").alias("a"), F.greatest("l.id", "r.id").alias("b")).distinct()
    if made:
        pairs = staged(pairs, "line-met")
        released(*made)
    return pairs


def _rarer(keys: DataFrame, repeats: DataFrame, often: int = HOT_LINE) -> DataFrame:
    """keys (bucket, id, m), those of lines that repeats (d1, d2, n) has over often times once a line: they are aggregated
    where they lie, so that no task gets all rows of one line. As many lines as a broadcast may hold are so many."""
    hot = staged(repeats.where(F.col("n") > often).select(F.col("d1").alias("id")).distinct(), "line-hot")
    found = hot.count()
    if found > HELD_ROWS // 2:
        released(hot)
        return _rarer(keys, repeats, 10 * often)
    if not found:
        return keys
    return keys.join(F.broadcast(hot), "id", "left_anti").unionByName(keys.join(F.broadcast(hot), "id", "left_semi").distinct())


def _met(keys: DataFrame, lines: DataFrame, edit: float) -> DataFrame:
    """(bucket, id, m, o0, ..., leader, near, k) of buckets of several lines, staged: whether a line may be similar to its
    bucket's leader, and how many lines the bucket holds. The leader comes first when the bucket's own number is mixed into
    all ids. Keys move once; the buckets of one line, and of two of unlike lengths, end there."""
    dealt = keys.repartition(int(keys.sparkSession.conf.get("spark.sql.shuffle.partitions")), "bucket")
    sums = dealt.groupBy("bucket").agg(F.min("id").alias("lo"), F.max("id").alias("hi"), F.count("*").alias("n"), F.min("m").alias("s"), F.max("m").alias("l"))
    several = sums.where(f"lo < hi and (n > 2 or {_lengths('s', 'l', edit)})").select("bucket")
    # a left semi join would be moved before the exchange, which then would not be the aggregation's
    met = staged(dealt.join(several.hint("shuffle_hash"), "bucket").distinct(), "line-buckets")
    odds = [f"o{k}" for k in range(ODDS)]
    told = lines.where(F.col("m") >= LEAST_WORDS).groupBy(F.col("d1").alias("id")).agg(*[F.max(x).alias(x) for x in odds])
    whole = Window.partitionBy("bucket")
    first = F.min_by(F.struct("id", "m", *odds), F.col("id").bitwiseXOR(F.col("bucket"))).over(whole)
    rows = met.join(told, "id").select("*", first.alias("first"), F.count("*").over(whole).alias("k")).withColumn("leader", F.col("first.id"))
    near = F.expr(f"{_lengths('m', 'first.m', edit)} and {_alike('m', 'first.m', [(x, f'first.{x}') for x in odds], edit)}")
    out = staged(rows.select("bucket", "id", "m", *odds, "leader", near.alias("near"), "k"), "line-met")
    released(met)
    return out


def _by_keys(rows: DataFrame, repeats: DataFrame, docs: DataFrame, text: str, key: str, edit: float) -> tuple[DataFrame, DataFrame]:
    """Links (a, b) and their groups (node, component) of the lines that meet by keys and have the edit similarity; rows as placed() has them, and the
    digests (d1, d2, n) that repeat, both staged. A line meets the leader of its largest bucket first; then those other leaders that are not of its group."""
    lines = rows.where("pos is not null")
    met = _met(_rarer(rows.where("bucket is not null").select("bucket", F.col("d1").alias("id"), "m"), repeats), lines, edit)
    members = met.where("id <> leader")
    # a bucket's only other member has met it when it has met the leader
    others = members.where("k > 2").select("bucket", "id", "m", *[f"o{k}" for k in range(ODDS)])
    pairs = members.where("near").groupBy(F.col("id").alias("a"), F.col("leader").alias("b")).agg(F.max("k").alias("k"))
    pairs = staged(pairs, "line-pairs")
    ids = staged(pairs.select(F.explode(F.array("a", "b")).alias("id")).distinct(), "line-ids")
    places = _places(lines, small(ids, HELD_ROWS))
    texts = _lines_at(docs, places, text, key)
    codes = _codes(texts)
    released(ids, places, texts)
    firsts = staged(pairs.groupBy("a").agg(F.max_by("b", "k").alias("b")), "line-firsts")
    links = _similar(firsts, codes, edit)
    groups = components(links)
    rest = staged(_apart(pairs.select("a", "b").join(firsts, ["a", "b"], "left_anti"), groups), "line-seconds")
    more = _similar(rest, codes, edit)
    released(firsts, rest, codes)
    links = links.unionByName(more)
    groups = groups if more.isEmpty() else components(links)
    across_groups = _across(others, groups, edit)
    tried = pairs.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))
    rest = staged(across_groups.join(tried, ["a", "b"], "left_anti"), "line-across")
    released(met, pairs, across_groups)
    more = None
    if not rest.isEmpty():
        ids = staged(rest.select(F.explode(F.array("a", "b")).alias("id")).distinct(), "line-ids")
        places = _places(lines, small(ids, HELD_ROWS))
        texts = _lines_at(docs, places, text, key)
        close = staged(_told_alike(rest, texts, edit), "line-close")
        more = _verified(close, texts, edit)
        released(ids, places, texts, close)
    released(rest)
    if more is None or more.isEmpty():
        return links, groups
    links = links.unionByName(more)
    return links, components(links)


def _told_alike(pairs: DataFrame, texts: DataFrame, edit: float) -> DataFrame:
    """Pairs (a, b) that parities of many bits of their lines (id, line) do not tell apart, before codes of long lines move."""
    counted = texts.select("id", F.size(words_of(F.col("line"))).alias("m")).distinct()
    told = _parities(texts).join(counted, "id")
    side = lambda i: told.select(*[F.col(c).alias(i if c == "id" else f"{c}_{i}") for c in told.columns])
    near = _alike("m_a", "m_b", [(f"p{k}_a", f"p{k}_b") for k in range(PARITIES)], edit)
    return pairs.join(side("a"), "a").join(side("b"), "b").where(near).select("a", "b")


def _apart(pairs: DataFrame, groups: DataFrame) -> DataFrame:
    """Pairs (a, b) of different groups (node, component)."""
    side = lambda i: groups.select(F.col("node").alias(i), F.col("component").alias(f"c_{i}"))
    told = pairs.join(side("a"), "a", "left").join(side("b"), "b", "left")
    return told.where("not coalesce(c_a = c_b, false)").select("a", "b")


def _by_bits(hashed: DataFrame, lines: DataFrame, docs: DataFrame, text: str, key: str, edit: float, hamming: int, known: tuple[DataFrame, DataFrame] | None = None) -> DataFrame:
    """(node, component) of the lines whose SimHashes, hashed (d1, sim), are within hamming bits and that have the edit
    similarity. known: links (a, b) and their groups to which these are added; only lines of different groups are read."""
    fuzzy = staged(hashed.where("sim is not null").groupBy("d1").agg(F.max("sim").alias("sim")), "fuzzy-lines")
    masks = selections(fuzzy.count(), hamming)
    bits = F.array(*[F.xxhash64(F.lit(i), F.col("sim").bitwiseAND(F.lit(_signed(x)))) for i, x in enumerate(masks)])
    entries = staged(_led(fuzzy.select(F.col("d1").alias("id"), "sim", F.explode(bits).alias("bucket")), hamming), "line-meetings")
    side = lambda s: fuzzy.select(F.col("d1").alias(s), F.col("sim").alias(f"sim_{s}"))
    close = f"bit_count(sim_a ^ sim_b) <= {hamming}"
    pairs = staged(stars(entries).join(side("a"), "a").join(side("b"), "b").where(close).select("a", "b"), "line-pairs")

    def linked(pairs: DataFrame) -> DataFrame:
        ids = staged(pairs.select(F.explode(F.array("a", "b")).alias("id")).distinct(), "line-ids")
        places = _places(lines, small(ids, HELD_ROWS))
        texts = _lines_at(docs, places, text, key)
        out = _verified(pairs, texts, edit)
        released(ids, places, texts)
        return out

    if known is None:
        links = linked(pairs)
        groups = components(links)
    else:
        links, groups = known
        rest = staged(_apart(pairs, groups), "line-seconds")
        if not rest.isEmpty():
            links = links.unionByName(linked(rest))
            groups = components(links)
        released(rest)
    named = entries.select("id", "bucket").join(fuzzy.select(F.col("d1").alias("id"), "sim"), "id")
    tried = pairs.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))
    rest = staged(across(named, groups, F.expr(f"bit_count(l.sim ^ r.sim) <= {hamming}")).join(tried, ["a", "b"], "left_anti"), "line-across")
    released(fuzzy, entries, pairs)
    out = groups if rest.isEmpty() else components(links.unionByName(linked(rest)))
    released(rest)
    return out


def duplicate_lines(docs: DataFrame, text: str = "text", key: str = "doc_id", edit: float = EDIT, hamming: int | None = HAMMING) -> DataFrame:
    """(doc_id, line, kept_doc_id, kept_line): each line to remove, and the occurrence that stays; lines count from 0.
    hamming: HAMMING, links within so many bits only; None, links of the edit similarity by words and by SimHashes
    within HAMMING bits, and shorter lines that are equal."""
    repeated = lambda x: staged(x.groupBy("d1", "d2").agg(F.count("*").alias("n")).where("n > 1"), "line-counts")
    if hamming is not None:
        lines = staged(digested(docs, text, key), "lines")
        repeats, groups = repeated(lines), _by_bits(lines, lines, docs, text, key, edit, hamming)
    else:
        rows = staged(placed(docs, text, key), "lines")
        lines = rows.where("pos is not null")
        repeats = repeated(lines)
        known = _by_keys(rows, repeats, docs, text, key, edit)
        groups = _by_bits(digested(docs, text, key), lines, docs, text, key, edit, HAMMING, known)
    groups = staged(groups.withColumnRenamed("node", "d1"), "line-groups")
    # of the rest, digests that repeat; the two kinds of groups are staged, so that the joins' skewed partitions may be split
    again = repeats.join(small(groups.select("d1"), HELD_ROWS), "d1", "left_anti").select("d1", "d2")
    again = lines.select("doc_id", "pos", "d1", "d2").join(staged(again, "line-repeats"), ["d1", "d2"])
    near = lines.select("doc_id", "pos", "d1").join(groups, "d1")
    real = lambda c: F.when(F.col(c) > _NO_ID, F.col(c))
    out = None
    for rows, by in ((again, ["d1", "d2"]), (near, ["component"])):
        rows = staged(rows.distinct(), "line-members")
        kept = staged(rows.groupBy(*by).agg(F.min(F.struct("doc_id", "pos")).alias("kept")), "line-keepers")
        gone = rows.join(kept, by).where("doc_id <> kept.doc_id or pos <> kept.pos")
        gone = gone.select(real("doc_id").alias("doc_id"), F.col("pos").alias("line"), real("kept.doc_id").alias("kept_doc_id"), F.col("kept.pos").alias("kept_line"))
        out = gone if out is None else out.unionByName(gone)
    return out


def without_lines(docs: DataFrame, gone: DataFrame, text: str = "text", key: str = "doc_id", emptied: bool = True) -> DataFrame:
    """docs without those lines; without emptied, those that lose their last line with words go."""
    listed = gone.groupBy(F.col(key).alias("id")).agg(F.collect_set("line").alias("gone"))
    joined = docs.select(F.struct(*docs.columns).alias("row"), F.col(key).alias("own")).join(listed, F.col("own").eqNullSafe(F.col("id")), "left")
    left = F.array_join(F.filter(F.split(F.col(f"row.{text}"), "\n"), lambda x, i: ~F.array_contains(F.col("gone"), i)), "\n")
    cut = joined.select("row", "gone", F.when(F.col("gone").isNull(), F.col(f"row.{text}")).otherwise(left).alias("left"))
    if not emptied:
        cut = cut.where(F.col("gone").isNull() | (F.size(words_of(F.col("left"))) > 0))
    return cut.select(*[F.col("left").alias(c) if c == text else F.col(f"row.{c}") for c in docs.columns])


def op10_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    return duplicate_lines(table(spark, sf_dir, "documents"), hamming=None)


def line_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The documents without their repeated lines; n_chars follows the text. A document of whose lines none with words is
    left is held elsewhere, and goes; one without words stays as it is."""
    left = without_lines(docs, duplicate_lines(docs, hamming=None), emptied=False)
    return left.withColumn("n_chars", F.length("text").cast("long")) if "n_chars" in docs.columns else left
