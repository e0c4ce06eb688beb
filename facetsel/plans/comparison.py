"""Baselines, students, the evaluation harness and the measures as registered queries."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from facetsel.catalog import DEFAULT_FACETS, FACET_NAMES, STYLES, TEACHER_FRACTION
from facetsel.functions import rubric
from facetsel.functions.dialect import DUCK
from facetsel.functions.keys import tie_key
from facetsel.functions.session import kept, spread
from facetsel.operators import baselines as B
from facetsel.operators import evalkit as E
from facetsel.operators import measures as M
from facetsel.operators.cells import resolve_budget
from facetsel.operators.draw import balanced_draw
from facetsel.operators.student import CELL, CellMeanStudent, LinearStudent, OrdinalStudent, StyleStudent, cell_features, tag_report
from facetsel.operators.teacher import QUALITY_SQL, NoisyTeacher, RubricTeacher, judgement_cost, quality_judgement, teacher_sample
from facetsel.plans import sqltext
from facetsel.plans.selection import judged, of_pool, score_stack
from facetsel.sources import pools

TOK = lambda text: DUCK.tokens(text)


# Random ------------------------------------------------------------------------------------------------------------

def q_random(seed: int, percent: int = 10):
    def run(spark, sf_dir):
        d = pools.table(spark, sf_dir, "documents").select(F.col("doc_id").alias("instance_id"), "source")
        return B.pick_random(d, resolve_budget(d.count(), f"{percent} %"), seed).select("instance_id", "source")

    return run


def random_sql(seed: int, percent: int = 10) -> str:
    return f"SELECT doc_id AS instance_id, source FROM (SELECT doc_id, source, row_number() OVER (ORDER BY {DUCK.tie(seed, 'doc_id')}) AS n, count(*) OVER () AS total FROM documents) WHERE n <= total * {percent} // 100"


# Perplexity --------------------------------------------------------------------------------------------------------

def outside_texts(spark, sf_dir) -> DataFrame:
    """Texts of the other corpora: what a model has read that has not seen the pool."""
    p = pools.web_flat(spark, sf_dir).select((F.col("instance_id") * 2).alias("id"), F.col("body").alias("text"))
    b = pools.table(spark, sf_dir, "benchmark").select((F.col("item_id") * 2 + 1).alias("id"), "text")
    return p.unionByName(b)


OUTSIDE_SQL = f"outside AS (SELECT instance_id * 2 AS id, body AS text FROM ({pools.WEB_FLAT_SQL}) UNION ALL SELECT item_id * 2 + 1, text FROM benchmark)"


def pairs_sql(relation: str, key: str) -> str:
    return f"(SELECT {key}, t[i] AS v, t[i + 1] AS w FROM (SELECT {key}, t, unnest(range(1, len(t))) AS i FROM (SELECT {key}, {TOK('text')} AS t FROM {relation})))"


def q_unigram(spark, sf_dir):
    return B.unigrams(outside_texts(spark, sf_dir))


def q_bigram(spark, sf_dir):
    return B.fit_lm(outside_texts(spark, sf_dir), "id")


def scored_perplexity(spark, sf_dir, before: bool) -> DataFrame:
    d = spread(pools.table(spark, sf_dir, "documents").select("doc_id", "text"))
    lm = B.fit_lm(outside_texts(spark, sf_dir), "id") if before else B.fit_lm(d, "doc_id")
    return B.perplexity(d, lm, "doc_id")


def perplexity_sql(before: bool) -> str:
    corpus, key = ("outside", "id") if before else ("documents", "doc_id")
    return f"""{OUTSIDE_SQL}, lm AS (SELECT v, w, count(*) AS c FROM {pairs_sql(corpus, key)} GROUP BY v, w),
cv AS (SELECT v, sum(c) AS cv FROM lm GROUP BY v), size AS (SELECT count(DISTINCT w) AS k FROM lm),
scored AS (SELECT doc_id, round(exp(-avg(ln((coalesce(c, 0) + 1) / (coalesce(cv, 0) + k)))), 4) AS ppl
  FROM {pairs_sql('documents', 'doc_id')} p LEFT JOIN lm USING (v, w) LEFT JOIN cv USING (v), size GROUP BY doc_id)"""


def q_pick_perplexity(before: bool, keep: str):
    def run(spark, sf_dir):
        s = kept(scored_perplexity(spark, sf_dir, before), "ppl")
        return B.pick_perplexity(s, s.count() // 10, keep).select("doc_id")

    return run


# Quality and complexity --------------------------------------------------------------------------------------------

def quality_complexity(spark, sf_dir) -> DataFrame:
    flat = pools.docs_flat(spark, sf_dir)
    q = quality_judgement(flat).select("instance_id", F.col("r_quality").alias("quality"))
    c = rubric.featurize(flat).select("instance_id", B.complexity_level().cast("int").alias("complexity"))
    return q.join(c, "instance_id")


def q_quality_complexity(spark, sf_dir):
    j = kept(quality_complexity(spark, sf_dir), "qc")
    return B.pick_quality_complexity(j, resolve_budget(j.count(), "10 %")).select("instance_id", "quality", "complexity", "product")


def quality_complexity_sql() -> str:
    level = " + ".join(f"CAST(n_distinct * (n_tokens // greatest(n_sentences, 1)) >= {t} AS INT)" for t in B.COMPLEXITY_LEVELS)
    return f"""WITH {sqltext.judged()}, q AS ({QUALITY_SQL.replace('FLAT', pools.DOCS_FLAT_SQL)}),
j AS (SELECT instance_id, r_quality AS quality, CAST({level} AS INT) AS complexity FROM judged_f JOIN q USING (instance_id)),
k AS (SELECT *, quality * complexity AS product, row_number() OVER (ORDER BY quality * complexity DESC, {sqltext.TIE} >> 3) AS n, count(*) OVER () AS total FROM j)
SELECT instance_id, quality, complexity, product FROM k WHERE n <= total * 10 // 100"""


def q_quality_diverse(spark, sf_dir):
    j = kept(quality_complexity(spark, sf_dir), "qc")
    e = pools.table(spark, sf_dir, "embeddings")
    v = j.withColumn("vec_id", F.pmod("instance_id", F.lit(e.count()))).join(e.select("vec_id", "embedding"), "vec_id")
    rank = (25 - F.col("quality") * F.col("complexity")).cast("long") * F.lit(1 << 57) + F.shiftright(tie_key(42, "instance_id"), 3)
    return B.pick_quality_diverse(v.select(F.col("instance_id").alias("id"), rank.alias("rank"), F.col("embedding").alias("vec")), resolve_budget(j.count(), "10 %"))


# Alignment ---------------------------------------------------------------------------------------------------------

def alignment(spark, sf_dir, window: int | None) -> DataFrame:
    d, e = pools.table(spark, sf_dir, "documents"), pools.table(spark, sf_dir, "embeddings")
    n = max(1, e.count())
    v = d.select("doc_id", F.pmod("doc_id", F.lit(n)).alias("vec_id")).join(e, "vec_id").select("doc_id", F.col("embedding").alias("vec"))
    return B.alignment(spread(d.select("doc_id", "text")), "doc_id", F.col("text"), v, window)


def alignment_sql(window: int | None) -> str:
    cut = f"[1:{window}]" if window else ""
    h = DUCK.tie(0, "token")
    return f"""WITH t AS (SELECT doc_id, unnest(({TOK('text')}){cut}) AS token FROM documents),
h AS (SELECT doc_id, CAST({h} % 64 AS INT) AS b, CASE WHEN ({h} >> 10) & 1 = 1 THEN 1 ELSE -1 END AS s FROM t),
v AS (SELECT doc_id, b, sum(s) AS x FROM h GROUP BY doc_id, b),
e AS (SELECT doc_id, embedding FROM documents d JOIN embeddings e ON e.vec_id = d.doc_id % (SELECT count(*) FROM embeddings)),
n AS (SELECT doc_id, embedding, sqrt(list_sum(list_transform(embedding, lambda y: CAST(y AS DOUBLE) * CAST(y AS DOUBLE)))) AS norm FROM e)
SELECT doc_id, round(sum(x * CAST(embedding[b + 1] AS DOUBLE)) / (sqrt(CAST(sum(x * x) AS DOUBLE)) * max(norm)), 5) AS cosine FROM v JOIN n USING (doc_id) GROUP BY doc_id"""


# Clusters ----------------------------------------------------------------------------------------------------------

def q_cluster_shares(spark, sf_dir):
    s = B.cluster_shares(pools.table(spark, sf_dir, "embeddings"), "label", "embedding", 0.1)
    return s.select("label", "n", F.round("similarity", 5).alias("similarity"), F.round("spread", 5).alias("spread"), F.round("share", 5).alias("share"))


CENTROID_SQL = """p AS (SELECT label, i, avg(CAST(embedding[i] AS DOUBLE)) AS m, count(*) AS n FROM (SELECT label, embedding, unnest(range(1, len(embedding) + 1)) AS i FROM embeddings) GROUP BY label, i),
c AS (SELECT label, max(n) AS n, list(m ORDER BY i) AS centroid FROM p GROUP BY label),
s AS (SELECT a.label AS i, b.label AS j, list_cosine_similarity(a.centroid, b.centroid) AS cosine FROM c a JOIN c b ON a.label <> b.label)"""
SHARES_SQL = f"""WITH {CENTROID_SQL},
q AS (SELECT i AS label, avg(cosine) AS similarity FROM s GROUP BY i),
d AS (SELECT label, avg(dist) AS spread FROM (SELECT e.label, list_sum(list_transform(range(1, 65), lambda k: (CAST(embedding[k] AS DOUBLE) - centroid[k]) * (CAST(embedding[k] AS DOUBLE) - centroid[k]))) AS dist FROM embeddings e JOIN c USING (label)) GROUP BY label),
w AS (SELECT label, n, similarity, spread, exp(similarity / (0.1 * spread)) AS weight FROM c JOIN q USING (label) JOIN d USING (label))
SELECT label, n, round(similarity, 5) AS similarity, round(spread, 5) AS spread, round(weight / sum(weight) OVER (), 5) AS share FROM w"""


def q_centroid_similarity(spark, sf_dir):
    c = kept(B.centroids(pools.table(spark, sf_dir, "embeddings"), "label", "embedding"), "centroids")
    pairs = c.select(F.col("label").alias("i"), F.col("centroid").alias("a")).crossJoin(F.broadcast(c.select(F.col("label").alias("j"), F.col("centroid").alias("b")))).where("i <> j")
    return pairs.select("i", "j", F.round(B.cosine("a", "b"), 5).alias("cosine"))


def q_kcenter(spark, sf_dir):
    return B.pick_kcenter(pools.table(spark, sf_dir, "embeddings"), "embedding", "vec_id", 10)


KCENTER_SQL = """WITH RECURSIVE v AS (SELECT list(vec_id ORDER BY vec_id) AS ids, list(CAST(embedding AS DOUBLE[]) ORDER BY vec_id) AS vs FROM embeddings),
r AS (SELECT 0 AS step, CAST(1 AS BIGINT) AS spot, list_transform(ids, lambda x: CAST('inf' AS DOUBLE)) AS d FROM v
  UNION ALL SELECT step, list_position(d, list_max(d)), d FROM (
    SELECT r.step + 1 AS step, list_transform(range(1, len(v.ids) + 1), lambda i: least(r.d[i], list_sum(list_transform(range(1, 65), lambda k: (v.vs[i][k] - v.vs[r.spot][k]) * (v.vs[i][k] - v.vs[r.spot][k]))))) AS d FROM r, v WHERE r.step < 9))
SELECT CAST(step AS INT) AS step, v.ids[spot] AS vec_id FROM r, v"""


def q_kmeans_greedy(spark, sf_dir):
    e = pools.table(spark, sf_dir, "embeddings")
    return B.pick_kmeans_greedy(e, "embedding", "vec_id", e.count() // 10, 10).select("vec_id", "cluster", "n")


def q_kmeans_cluster(spark, sf_dir):
    e = pools.table(spark, sf_dir, "embeddings")
    return B.pick_clustered(e, "embedding", "vec_id", e.count() // 10, 10)


# Direct judges and the abstract criterion ------------------------------------------------------------------------------

def direct_judgements(spark, sf_dir, kind: str) -> DataFrame:
    teacher = RubricTeacher((1, 3, 5)) if kind == "coarse" else NoisyTeacher()
    return kept(teacher.judge(pools.docs_flat(spark, sf_dir)), "direct")


def q_direct(kind: str):
    def run(spark, sf_dir):
        j = direct_judgements(spark, sf_dir, kind)
        return balanced_draw(j, resolve_budget(j.count(), "10 %"))

    return run


def noisy_sql() -> str:
    roll = lambda name: f"({DUCK.tie(7, 'instance_id || ' + repr('|' + name))} % 100)"
    r = ", ".join(f"greatest(0, least(5, r_{f} + CASE WHEN {roll(f)} < 15 THEN -1 WHEN {roll(f)} >= 85 THEN 1 ELSE 0 END)) AS r_{f}" for f in FACET_NAMES)
    g = ", ".join(f"CASE WHEN {roll(s)} < 5 THEN 1 - g_{s} ELSE g_{s} END AS g_{s}" for s in STYLES)
    return f"WITH RECURSIVE {sqltext.judged()}, noisy AS (SELECT instance_id, source, lang, {r}, {g} FROM judged),\n{sqltext.draw_ctes(of_pool(10), source='noisy')}\nSELECT {sqltext.DRAWN} FROM drawn"


def q_abstract(spark, sf_dir):
    j = kept(quality_judgement(pools.docs_flat(spark, sf_dir)), "abstract")
    return balanced_draw(j, resolve_budget(j.count(), "10 %"), ("quality",), ("any",), by_source="flat")


ABSTRACT_SQL = f"""WITH RECURSIVE q AS ({QUALITY_SQL.replace('FLAT', pools.DOCS_FLAT_SQL)}),
{sqltext.draw_ctes(of_pool(10, 'q'), facets=('quality',), styles=('any',), source='q', by_source='flat')}
SELECT {sqltext.DRAWN} FROM drawn"""


# Students ----------------------------------------------------------------------------------------------------------

def taught(spark, sf_dir, pool: str = "docs", fraction: float = TEACHER_FRACTION) -> DataFrame:
    """The judged teacher sample, with the text it was judged on."""
    flat = teacher_sample(pools.FLAT[pool](spark, sf_dir), fraction)
    return kept(RubricTeacher().judge(flat).join(flat.select("instance_id", "body"), "instance_id"), "taught")


def cell_mean(spark, sf_dir) -> tuple[CellMeanStudent, DataFrame]:
    cells = kept(cell_features(rubric.featurize(pools.docs_flat(spark, sf_dir))), "cell-features")
    return CellMeanStudent().fit(cells, taught(spark, sf_dir).selectExpr("instance_id", score_stack())), cells


def q_cellmean_fit(spark, sf_dir):
    return cell_mean(spark, sf_dir)[0].means


def q_cellmean_predict(spark, sf_dir):
    student, cells = cell_mean(spark, sf_dir)
    return student.score(cells)


def q_agreement(spark, sf_dir):
    return M.agreement(q_cellmean_predict(spark, sf_dir), judged(spark, sf_dir).selectExpr("instance_id", score_stack()))


def cellmean_ctes() -> str:
    wide = ", ".join(f"r_{f} AS {f}" for f in FACET_NAMES)
    cells = ", ".join(f"CAST({e.replace(' div ', ' // ')} AS INT) AS {k}" for k, e in CELL.items())
    return f"""{sqltext.judged()},
long AS (SELECT instance_id, facet, score FROM (SELECT instance_id, {wide} FROM judged) UNPIVOT (score FOR facet IN ({", ".join(FACET_NAMES)}))),
cells AS (SELECT instance_id, {cells} FROM judged_f),
sampled AS (SELECT instance_id FROM (SELECT instance_id, row_number() OVER (ORDER BY {sqltext.TIE}) AS n, count(*) OVER () AS total FROM judged) WHERE n <= total * 15 // 100),
fit AS (SELECT facet, b1, b2, b3, count(*) AS n, CAST(sum(score) AS BIGINT) AS total FROM long JOIN sampled USING (instance_id) JOIN cells USING (instance_id) GROUP BY ALL),
whole AS (SELECT facet, sum(n) AS n0, sum(total) AS total0 FROM fit GROUP BY facet),
predicted AS (SELECT c.instance_id, w.facet, CAST(coalesce((2 * total + n) // (2 * n), (2 * total0 + n0) // (2 * n0)) AS INT) AS score FROM cells c CROSS JOIN whole w LEFT JOIN fit f ON f.facet = w.facet AND f.b1 = c.b1 AND f.b2 = c.b2 AND f.b3 = c.b3)"""


def q_student(kind):
    """Agreement of a learned student with the teacher over the whole pool."""

    def run(spark, sf_dir):
        facets = FACET_NAMES if kind is LinearStudent else ("langgen", "stem", "finegrained")
        sample = taught(spark, sf_dir)
        student = kind(facets).fit(sample)
        stack = f"stack({len(facets)}, " + ", ".join(f"'{f}', r_{f}" for f in facets) + ") as (facet, score)"
        said = student.score(pools.docs_flat(spark, sf_dir)).selectExpr("instance_id", stack)
        return M.agreement(said, judged(spark, sf_dir).selectExpr("instance_id", stack))

    return run


def q_style_student(spark, sf_dir):
    return tag_report(StyleStudent().fit(taught(spark, sf_dir)).tag(pools.docs_flat(spark, sf_dir)), judged(spark, sf_dir))


def q_transfer(spark, sf_dir):
    """Students fitted on 30 per cent of the chats score and tag all documents, which are then drawn from."""
    sample = taught(spark, sf_dir, "chat", 0.30)
    flat = pools.docs_flat(spark, sf_dir)
    scores, tags = LinearStudent(DEFAULT_FACETS).fit(sample).score(flat), StyleStudent().fit(sample).tag(flat)
    j = kept(scores.join(tags, "instance_id"), "transferred")
    return balanced_draw(j, resolve_budget(j.count(), "10 %"))


# Evaluation ----------------------------------------------------------------------------------------------------------

def train_ids(spark, sf_dir) -> DataFrame:
    return pools.table(spark, sf_dir, "documents").select("doc_id").where(~E.held_out())


def evaluated(spark, sf_dir, selected: DataFrame, size: int = E.BIG) -> DataFrame:
    """Bench scores (setting, bench, n, accuracy, balanced) of selections (setting, doc_id): both targets."""
    docs, labels = pools.table(spark, sf_dir, "documents"), pools.table(spark, sf_dir, "labels")
    buckets = kept(E.token_buckets(spread(docs.select("doc_id", "text")), size), "buckets")
    test, out = docs.where(E.held_out()).join(labels.select("doc_id"), "doc_id").select("doc_id"), None
    selected = kept(selected.join(train_ids(spark, sf_dir), "doc_id"), "selected")
    for target in ("quality", "toxic"):
        counts, priors = E.train_nb(selected, labels.select("doc_id", F.col(target).alias("label")), buckets)
        counts, priors = kept(counts, "nb"), kept(priors, "nb-priors")
        part = E.bench_scores(E.predict_nb(counts, priors, test, buckets, size), docs, labels, target)
        out = part if out is None else out.unionByName(part)
    return out


def everything(spark, sf_dir, name: str = "full") -> DataFrame:
    return pools.table(spark, sf_dir, "documents").select(F.lit(name).alias("setting"), "doc_id")


def q_nb_counts(spark, sf_dir):
    docs, labels = pools.table(spark, sf_dir, "documents"), pools.table(spark, sf_dir, "labels")
    sel = everything(spark, sf_dir).join(train_ids(spark, sf_dir), "doc_id")
    return E.train_nb(sel, labels.select("doc_id", F.col("quality").alias("label")), E.token_buckets(docs, E.BIG))[0].select("label", "bucket", "n")


def q_nb_predict(spark, sf_dir):
    docs, labels = pools.table(spark, sf_dir, "documents"), pools.table(spark, sf_dir, "labels")
    buckets = kept(E.token_buckets(docs, E.BIG), "buckets")
    counts, priors = E.train_nb(everything(spark, sf_dir).join(train_ids(spark, sf_dir), "doc_id"), labels.select("doc_id", F.col("quality").alias("label")), buckets)
    test = docs.where(E.held_out()).join(labels.select("doc_id"), "doc_id").select("doc_id")
    return E.predict_nb(counts, priors, test, buckets, E.BIG).select("doc_id", "predicted")


def nb_ctes(target: str = "quality", size: int = E.BIG) -> str:
    return f"""tok AS (SELECT doc_id, unnest({TOK('text')}) AS token FROM documents),
buckets AS (SELECT doc_id, CAST({DUCK.tie(0, 'token')} % {size} AS INT) AS bucket, count(*) AS n FROM tok GROUP BY ALL),
train AS (SELECT doc_id, {target} AS label FROM labels WHERE {DUCK.tie(E.HELD_OUT_SEED, 'doc_id')} % {E.HELD_OUT_OF} <> 0),
counts AS (SELECT label, bucket, CAST(sum(n) AS BIGINT) AS n FROM train JOIN buckets USING (doc_id) GROUP BY ALL),
priors AS (SELECT label, count(*) AS docs, (SELECT count(*) FROM train) AS all_docs, (SELECT sum(n) FROM counts c WHERE c.label = t.label) AS total FROM train t GROUP BY label),
test AS (SELECT doc_id FROM labels WHERE {DUCK.tie(E.HELD_OUT_SEED, 'doc_id')} % {E.HELD_OUT_OF} = 0),
logp AS (SELECT b.doc_id, p.label, round(sum(b.n * ln((coalesce(c.n, 0) + 1) / (p.total + {size}))) + max(ln(p.docs / p.all_docs)), 6) AS logp
  FROM test JOIN buckets b USING (doc_id) CROSS JOIN priors p LEFT JOIN counts c ON c.label = p.label AND c.bucket = b.bucket GROUP BY b.doc_id, p.label),
predicted AS (SELECT doc_id, CAST(max_by(label, (logp, label)) AS INT) AS predicted FROM logp GROUP BY doc_id)"""


def q_bench_full(spark, sf_dir):
    return evaluated(spark, sf_dir, everything(spark, sf_dir)).where("bench like 'quality%'").select("bench", "n", "accuracy", "balanced")


def bench_full_sql() -> str:
    cases = ", ".join(f"CASE WHEN {c.replace(' rlike ', ' ~ ')} THEN '{b}' END" if "rlike" not in c else f"CASE WHEN regexp_matches(text, {c.split(' rlike ')[1]}) THEN '{b}' END" for b, c, t in E.BENCHES if t == "quality")
    return f"""WITH {nb_ctes()}, r AS (SELECT unnest([{cases}]) AS bench, quality AS actual, CAST(predicted = quality AS INT) AS ok FROM predicted JOIN labels USING (doc_id) JOIN documents USING (doc_id)),
p AS (SELECT bench, actual, count(*) AS n, sum(ok) AS ok FROM r WHERE bench IS NOT NULL GROUP BY ALL)
SELECT bench, CAST(sum(n) AS BIGINT) AS n, round(100 * sum(ok) / sum(n), 4) AS accuracy, round(100 * avg(ok / n), 4) AS balanced FROM p GROUP BY bench"""


def q_centroid_eval(spark, sf_dir):
    e = pools.table(spark, sf_dir, "embeddings")
    p = E.nearest_centroid(e.where(~E.held_out("vec_id")), e.where(E.held_out("vec_id")))
    bench = F.when(F.col("label") < 5, "vectors_0_4").otherwise("vectors_5_9")
    return p.groupBy(bench.alias("bench")).agg(F.count("*").alias("n"), F.round(100 * F.avg((F.col("label") == F.col("predicted")).cast("int")), 4).alias("accuracy"))


CENTROID_EVAL_SQL = f"""WITH tr AS (SELECT * FROM embeddings WHERE {DUCK.tie(E.HELD_OUT_SEED, 'vec_id')} % {E.HELD_OUT_OF} <> 0),
te AS (SELECT vec_id, label, CAST(embedding AS DOUBLE[]) AS v FROM embeddings WHERE {DUCK.tie(E.HELD_OUT_SEED, 'vec_id')} % {E.HELD_OUT_OF} = 0),
p AS (SELECT label, i, avg(CAST(embedding[i] AS DOUBLE)) AS m FROM (SELECT label, embedding, unnest(range(1, len(embedding) + 1)) AS i FROM tr) GROUP BY label, i),
c AS (SELECT label AS class, list(m ORDER BY i) AS centroid FROM p GROUP BY label),
s AS (SELECT vec_id, label, max_by(class, (round(list_cosine_similarity(v, centroid), 9), class)) AS predicted FROM te, c GROUP BY vec_id, label)
SELECT CASE WHEN label < 5 THEN 'vectors_0_4' ELSE 'vectors_5_9' END AS bench, count(*) AS n, round(100 * avg(CAST(label = predicted AS INT)), 4) AS accuracy FROM s GROUP BY 1"""


# Measures ------------------------------------------------------------------------------------------------------------

#: Budgets in per cent, and the order keys of the methods whose selections are scored on the given tables.
SCORED_BUDGETS = (5, 10, 30)
SCORED_LANGS = ("de", "en", "es", "fr")
SCORED_BENCHES = [f"{b}_{g}" for b in ("clean", "good") for g in SCORED_LANGS]
_MOST = (1 << 20) - 1


def scored_selections(spark, sf_dir) -> DataFrame:
    """(setting, budget, method, bench, score): of the labelled documents of a language that a method selects, the share
    in per cent that is of good quality, and that is not toxic. A method takes the documents up to its n-th order key, at
    random or the longest or shortest first; full is the whole table. The cuts are found by counts of key digits."""
    from facetsel.functions.keys import nth_key_cutoff

    docs, labels = pools.table(spark, sf_dir, "documents"), pools.table(spark, sf_dir, "labels")
    size, low = F.least(F.coalesce("n_chars", F.lit(0)).cast("long"), F.lit(_MOST)), F.shiftright(tie_key(1, "doc_id"), 20)
    order = {"random": tie_key(1, "doc_id"), "longest": F.shiftleft(F.lit(_MOST) - size, 40) + low, "shortest": F.shiftleft(size, 40) + low}
    d = kept(docs.select("doc_id", "lang", *[k.alias(m) for m, k in order.items()]), "order-keys")
    n, cells = d.count(), [(m, b) for m in order for b in SCORED_BUDGETS]
    long = d.select(F.explode(F.array(*[F.struct(F.lit(g).alias("g"), F.col(m).alias("k")) for g, (m, _) in enumerate(cells)])).alias("x")).select("x.g", "x.k")
    cut = nth_key_cutoff(long, "g", "k", {g: n * b // 100 for g, (_, b) in enumerate(cells)})
    picks = [F.when(F.col(m) <= F.lit(cut[g]), F.struct(F.lit(m).alias("method"), F.lit(b).alias("budget"))) for g, (m, b) in enumerate(cells)]
    picks.append(F.struct(F.lit("full").alias("method"), F.lit(100).alias("budget")))
    rows = d.where(F.col("lang").isin(*SCORED_LANGS)).hint("merge").join(labels, "doc_id").select("lang", "quality", "toxic", F.explode(F.array_compact(F.array(*picks))).alias("p"))
    rows = rows.groupBy("p.method", "p.budget", "lang").agg(F.avg(1 - F.col("toxic")).alias("clean"), F.avg("quality").alias("good"))
    told = F.array(*[F.struct(F.concat(F.lit(f"{b}_"), "lang").alias("bench"), F.round(100 * F.col(b), 4).alias("score")) for b in ("clean", "good")])
    return kept(rows.select(F.lit("main").alias("setting"), "budget", "method", F.explode(told).alias("x")).select("setting", "budget", "method", "x.*"), "scored")


def scored_sql() -> str:
    size, low = f"least(CAST(coalesce(n_chars, 0) AS BIGINT), {_MOST})", f"({DUCK.tie(1, 'doc_id')} >> 20)"
    order = {"random": DUCK.tie(1, "doc_id"), "longest": f"(({_MOST} - {size}) << 40) + {low}", "shortest": f"({size} << 40) + {low}"}
    keys = " UNION ALL ".join(f"SELECT doc_id, lang, '{m}' AS method, {k} AS k FROM documents" for m, k in order.items())
    langs = ", ".join(f"'{g}'" for g in SCORED_LANGS)
    return f"""u AS ({keys}),
nth AS (SELECT method, k, row_number() OVER (PARTITION BY method ORDER BY k) AS n, count(*) OVER (PARTITION BY method) AS total FROM u),
cut AS (SELECT method, budget, max(k) AS cut FROM nth, (VALUES {", ".join(f"({b})" for b in SCORED_BUDGETS)}) v(budget) WHERE n <= total * budget // 100 GROUP BY method, budget),
picked AS (SELECT method, budget, doc_id, lang FROM u JOIN cut USING (method) WHERE k <= cut UNION ALL SELECT 'full', 100, doc_id, lang FROM documents),
told AS (SELECT method, budget, lang, unnest([{{'b': 'clean', 'x': 1 - toxic}}, {{'b': 'good', 'x': quality}}]) AS t FROM picked JOIN labels USING (doc_id) WHERE lang IN ({langs})),
pub AS (SELECT 'main' AS setting, CAST(budget AS INT) AS budget, method, t.b || '_' || lang AS bench, round(100 * avg(t.x), 4) AS score FROM told GROUP BY ALL)"""


def queries():
    scored = lambda f: lambda spark, sf_dir: f(scored_selections(spark, sf_dir))
    out = {f"random_s{s}": q_random(s) for s in (1, 2, 3)}
    out |= {
        "lm_unigram": q_unigram,
        "lm_bigram": q_bigram,
        "ppl_before": lambda spark, sf_dir: scored_perplexity(spark, sf_dir, True),
        "ppl_after": lambda spark, sf_dir: scored_perplexity(spark, sf_dir, False),
        "pick_ppl_before": q_pick_perplexity(True, "middle"),
        "pick_ppl_after_low": q_pick_perplexity(False, "low"),
        "pick_ppl_after_high": q_pick_perplexity(False, "high"),
        "quality_complexity": q_quality_complexity,
        "quality_diverse": q_quality_diverse,
        "align_short": lambda spark, sf_dir: alignment(spark, sf_dir, B.SHORT_WINDOW),
        "align_long": lambda spark, sf_dir: alignment(spark, sf_dir, None),
        "cluster_shares": q_cluster_shares,
        "centroid_similarity": q_centroid_similarity,
        "kcenter": q_kcenter,
        "kmeans_greedy": q_kmeans_greedy,
        "kmeans_cluster": q_kmeans_cluster,
        "draw_direct_a": q_direct("coarse"),
        "draw_direct_b": q_direct("noisy"),
        "draw_abstract": q_abstract,
        "cellmean_fit": q_cellmean_fit,
        "cellmean_predict": q_cellmean_predict,
        "agreement": q_agreement,
        "student_linear": q_student(LinearStudent),
        "student_ordinal": q_student(OrdinalStudent),
        "style_student": q_style_student,
        "transfer_chat_to_docs": q_transfer,
        "nb_counts": q_nb_counts,
        "nb_predict": q_nb_predict,
        "bench_scores": q_bench_full,
        "centroid_eval": q_centroid_eval,
        "published_relative": scored(M.relative_to_full),
        "published_wins": scored(M.wins_over),
        "published_rank": scored(M.marks),
        "results_pivot": scored(lambda r: M.report(r, SCORED_BENCHES)),
        "entropy": lambda spark, sf_dir: M.entropy(judged_draw(spark, sf_dir), "facet").unionByName(M.entropy(judged_draw(spark, sf_dir), "style")),
        "jaccard": lambda spark, sf_dir: M.jaccard(judged_draw(spark, sf_dir), q_random(1)(spark, sf_dir)),
        "teacher_cost": q_teacher_cost,
        "selection_cost": q_selection_cost,
    }
    return out


def judged_draw(spark, sf_dir):
    j = judged(spark, sf_dir)
    return balanced_draw(j, resolve_budget(j.count(), "10 %"))


def q_teacher_cost(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = []
    for pool, build in pools.FLAT.items():
        n = build(spark, sf_dir).count()
        for percent in (5, 15, 30):
            rows.append((pool, percent, n * percent // 100, judgement_cost(n * percent // 100)))
    return spark.createDataFrame(rows, "pool string, percent int, sample long, judgements long")


TEACHER_COST_SQL = "SELECT pool, CAST(p AS INT) AS percent, n * p // 100 AS sample, n * p // 100 * 23 AS judgements FROM (" + " UNION ALL ".join(f"SELECT '{k}' AS pool, count(*) AS n FROM ({v})" for k, v in pools.FLAT_SQL.items()) + ") CROSS JOIN (VALUES (5), (15), (30)) v(p)"


def q_selection_cost(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = pools.table(spark, sf_dir, "embeddings").count()
    rows = [("tagging", 0), ("kcenter_10", B.distance_evaluations(n, 10, 1)), ("kmeans_10", B.distance_evaluations(n, 10)), ("kmeans_10000", B.distance_evaluations(n, 10_000)), ("pairwise", B.distance_evaluations(n, pairwise=True))]
    return spark.createDataFrame(rows, "method string, evaluations long")


SELECTION_COST_SQL = "WITH n AS (SELECT count(*) AS n FROM embeddings) SELECT method, CAST(e AS BIGINT) AS evaluations FROM (SELECT 'tagging' AS method, 0 AS e UNION ALL SELECT 'kcenter_10', n * 10 FROM n UNION ALL SELECT 'kmeans_10', n * 100 FROM n UNION ALL SELECT 'kmeans_10000', n * 100000 FROM n UNION ALL SELECT 'pairwise', n * (n - 1) // 2 FROM n)"


def oracle_sql():
    pub = f"WITH {scored_sql()}"
    rel = "SELECT p.setting, p.budget, p.method, round(100 * avg(p.score / f.score), 4) AS relative FROM pub p JOIN pub f ON f.method = 'full' AND f.bench = p.bench WHERE f.score <> 0 GROUP BY ALL"
    wins = "SELECT p.setting, p.budget, p.method, CAST(sum(CAST(p.score > r.score AS INT)) AS BIGINT) AS wins, count(*) AS benches FROM pub p JOIN pub r ON r.method = 'random' AND r.budget = p.budget AND r.bench = p.bench WHERE p.method <> 'full' GROUP BY ALL"
    head = f"WITH RECURSIVE {sqltext.judged()},\n{sqltext.draw_ctes(of_pool(10))}\n"
    ent = lambda c: f"SELECT '{c}' AS what, round(-sum(p * log2(p)), 6) AS entropy, count(*) AS values FROM (SELECT {c}, count(*) / sum(count(*)) OVER () AS p FROM drawn GROUP BY {c})"
    pick = lambda before, first: f"WITH {perplexity_sql(before)}, k AS (SELECT doc_id, row_number() OVER (ORDER BY (CAST(floor(ppl * 10000) AS BIGINT) << 20) | ({DUCK.tie(0, 'doc_id')} >> 40)) AS n, count(*) OVER () AS total FROM scored) SELECT doc_id FROM k WHERE n > {first} AND n <= {first} + total // 10"
    out = {f"random_s{s}": random_sql(s) for s in (1, 2, 3)}
    return out | {
        "lm_unigram": f"WITH {OUTSIDE_SQL} SELECT token, count(*) AS n FROM (SELECT unnest({TOK('text')}) AS token FROM outside) GROUP BY token",
        "lm_bigram": f"WITH {OUTSIDE_SQL} SELECT v, w, count(*) AS n FROM {pairs_sql('outside', 'id')} GROUP BY v, w",
        "ppl_before": f"WITH {perplexity_sql(True)} SELECT doc_id, ppl FROM scored",
        "ppl_after": f"WITH {perplexity_sql(False)} SELECT doc_id, ppl FROM scored",
        "pick_ppl_before": pick(True, "(total - total // 10) // 2"),
        "pick_ppl_after_low": pick(False, "0"),
        "pick_ppl_after_high": pick(False, "total - total // 10"),
        "quality_complexity": quality_complexity_sql(),
        "align_short": alignment_sql(B.SHORT_WINDOW),
        "align_long": alignment_sql(None),
        "cluster_shares": SHARES_SQL,
        "centroid_similarity": f"WITH {CENTROID_SQL} SELECT i, j, round(cosine, 5) AS cosine FROM s",
        "kcenter": KCENTER_SQL,
        "draw_direct_a": sqltext.draw_sql(of_pool(10), levels=(1, 3, 5)),
        "draw_direct_b": noisy_sql(),
        "draw_abstract": ABSTRACT_SQL,
        "cellmean_fit": f"WITH {cellmean_ctes()} SELECT * FROM fit",
        "cellmean_predict": f"WITH {cellmean_ctes()} SELECT * FROM predicted",
        "agreement": f"WITH {cellmean_ctes()} SELECT facet, count(*) AS n, round(avg(abs(p.score - l.score)), 6) AS mae, round(avg(CAST(p.score = l.score AS INT)), 6) AS exact, CASE WHEN stddev_pop(p.score) * stddev_pop(l.score) > 0 THEN round(covar_pop(p.score, l.score) / (stddev_pop(p.score) * stddev_pop(l.score)), 4) END AS corr FROM predicted p JOIN long l USING (instance_id, facet) GROUP BY facet",
        "nb_counts": f"WITH {nb_ctes()} SELECT label, bucket, n FROM counts",
        "nb_predict": f"WITH {nb_ctes()} SELECT doc_id, predicted FROM predicted",
        "bench_scores": bench_full_sql(),
        "centroid_eval": CENTROID_EVAL_SQL,
        "published_relative": f"{pub} {rel}",
        "published_wins": f"{pub} {wins}",
        "published_rank": f"{pub} SELECT p.setting, p.budget, p.method, p.bench, p.score, CAST(p.place AS INT) AS place, p.place = 1 AS best, p.score > r.score AS beats_reference FROM (SELECT *, rank() OVER (PARTITION BY budget, bench ORDER BY score DESC) AS place FROM pub WHERE method <> 'full') p JOIN pub r ON r.method = 'random' AND r.budget = p.budget AND r.bench = p.bench",
        "results_pivot": f"{pub} SELECT x.*, w.wins, f.relative FROM (SELECT setting, budget, method, {', '.join(f'''max(score) FILTER (bench = '{b}') AS {b}''' for b in SCORED_BENCHES)} FROM pub GROUP BY ALL) x LEFT JOIN ({wins}) w USING (setting, budget, method) LEFT JOIN ({rel}) f USING (setting, budget, method)",
        "entropy": head + ent("facet") + " UNION ALL " + ent("style"),
        "jaccard": head + f", r AS ({random_sql(1)}) SELECT count(*) FILTER (d.instance_id IS NOT NULL AND r.instance_id IS NOT NULL) AS both, count(*) AS either, round(count(*) FILTER (d.instance_id IS NOT NULL AND r.instance_id IS NOT NULL) / count(*), 6) AS jaccard FROM drawn d FULL JOIN r ON d.instance_id = r.instance_id",
        "teacher_cost": TEACHER_COST_SQL,
        "selection_cost": SELECTION_COST_SQL,
    }
