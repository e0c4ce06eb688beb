"""Students: cheap scorers and taggers fitted on the teacher's sample."""

from __future__ import annotations

from functools import reduce

from pyspark.ml import Pipeline
from pyspark.ml.classification import LogisticRegression
from pyspark.ml.feature import HashingTF, Normalizer, RegexTokenizer
from pyspark.ml.functions import vector_to_array
from pyspark.ml.regression import LinearRegression
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from facetsel.catalog import FACET_NAMES, STYLES
from facetsel.functions.dialect import TOKEN_GAP

#: Buckets of three features; a cell of the cell-mean student.
CELL = {"b1": "least(n_tokens div 50, 20)", "b2": "least(n_breaks div 2, 5)", "b3": "least(n_bars + n_digits, 5)"}


def cell_features(features: DataFrame) -> DataFrame:
    return features.select("instance_id", *[F.expr(e).cast("int").alias(k) for k, e in CELL.items()])


class CellMeanStudent:
    """The rounded mean of the teacher's scores among rows of like features; the facet's mean where there are none. The
    model is 756 means a facet at most, and is broadcast."""

    def fit(self, cells: DataFrame, long_scores: DataFrame) -> CellMeanStudent:
        rows = cells.join(long_scores.hint("merge"), "instance_id")  # a row for each facet: small in files, not in memory
        self.means = rows.groupBy("facet", *CELL).agg(F.count("*").alias("n"), F.sum("score").alias("total"))
        self.overall = rows.groupBy("facet").agg(F.count("*").alias("n0"), F.sum("score").alias("total0"))
        return self

    def score(self, cells: DataFrame) -> DataFrame:
        wide = cells.crossJoin(F.broadcast(self.overall)).join(F.broadcast(self.means), ["facet", *CELL], "left")
        mean = lambda t, n: f"(2 * {t} + {n}) div (2 * {n})"
        return wide.select("instance_id", "facet", F.expr(f"cast(coalesce({mean('total', 'n')}, {mean('total0', 'n0')}) as int)").alias("score"))


    def fit_wide(self, cells: DataFrame, taught: DataFrame, facets=FACET_NAMES, styles=STYLES) -> CellMeanStudent:
        """The same for all facets and styles at once, of wide judgements; a style is a facet of two levels."""
        self.columns = [f"r_{f}" for f in facets] + [f"g_{s}" for s in styles]
        rows = cells.select("instance_id", *CELL).join(taught.select("instance_id", *self.columns), "instance_id")
        mean = lambda c: F.expr(f"cast((2 * sum({c}) + count({c})) div (2 * count({c})) as int)")
        self.wide = rows.groupBy(*CELL).agg(*[mean(c).alias(f"m_{c}") for c in self.columns])
        self.whole = rows.agg(*[mean(c).alias(f"w_{c}") for c in self.columns])
        return self

    def score_wide(self, cells: DataFrame) -> DataFrame:
        """instance_id, source, lang and all columns: one join with a model of 756 rows at most, nothing is exploded."""
        told = cells.join(F.broadcast(self.wide), list(CELL), "left").crossJoin(F.broadcast(self.whole))
        return told.select("instance_id", "source", "lang", *[F.coalesce(f"m_{c}", f"w_{c}").alias(c) for c in self.columns])


def _text_stages(bits: int) -> list:
    return [RegexTokenizer(inputCol="body", outputCol="__t", pattern=TOKEN_GAP, minTokenLength=1), HashingTF(inputCol="__t", outputCol="__f", numFeatures=1 << bits), Normalizer(inputCol="__f", outputCol="__x")]


class LinearStudent:
    """One feature column of hashed tokens, a linear regression a facet, rounded and clamped."""

    def __init__(self, facets=FACET_NAMES, bits: int = 12):
        self.facets, self.bits = tuple(facets), bits

    def fit(self, sample: DataFrame) -> LinearStudent:
        self.text = Pipeline(stages=_text_stages(self.bits)).fit(sample)
        x = self.text.transform(sample).select("__x", *[F.col(f"r_{f}").cast("double").alias(f"r_{f}") for f in self.facets]).persist()
        self.models = [LinearRegression(featuresCol="__x", labelCol=f"r_{f}", predictionCol=f"p_{f}", regParam=0.01, solver="l-bfgs", maxIter=20).fit(x) for f in self.facets]
        x.unpersist()
        return self

    def score(self, pool: DataFrame) -> DataFrame:
        out = reduce(lambda df, m: m.transform(df), self.models, self.text.transform(pool))
        clamp = lambda f: F.greatest(F.lit(0), F.least(F.lit(5), F.floor(F.col(f"p_{f}") + 0.5))).cast("int")
        return out.select("instance_id", "source", "lang", *[clamp(f).alias(f"r_{f}") for f in self.facets])


class OrdinalStudent(LinearStudent):
    """Five logistic regressions a facet, for a score of at least 1 to 5; the score is how many say yes."""

    def fit(self, sample: DataFrame) -> OrdinalStudent:
        self.text = Pipeline(stages=_text_stages(self.bits)).fit(sample)
        x = self.text.transform(sample)
        self.models, self.constant = [], {}
        for f in self.facets:
            for k in range(1, 6):
                y = x.select("__x", (F.col(f"r_{f}") >= k).cast("double").alias("label")).persist()
                lo, hi = y.agg(F.min("label"), F.max("label")).first()
                if lo == hi:
                    self.constant[f, k] = int(hi or 0)
                else:
                    self.models.append(LogisticRegression(featuresCol="__x", labelCol="label", predictionCol=f"p_{f}_{k}", probabilityCol=f"q_{f}_{k}", rawPredictionCol=f"w_{f}_{k}", regParam=0.001, maxIter=20).fit(y))
                y.unpersist()
        return self

    def score(self, pool: DataFrame) -> DataFrame:
        out = reduce(lambda df, m: m.transform(df), self.models, self.text.transform(pool))
        level = lambda f: sum((F.lit(self.constant[f, k]) if (f, k) in self.constant else F.col(f"p_{f}_{k}").cast("int") for k in range(1, 6)), F.lit(0))
        return out.select("instance_id", "source", "lang", *[level(f).alias(f"r_{f}") for f in self.facets])


class StyleStudent:
    """A logistic regression a style, present from a probability of one half."""

    def __init__(self, styles=STYLES, bits: int = 12):
        self.styles, self.bits = tuple(styles), bits

    def fit(self, sample: DataFrame) -> StyleStudent:
        self.text = Pipeline(stages=_text_stages(self.bits)).fit(sample)
        x = self.text.transform(sample).persist()
        self.models, self.constant = {}, {}
        for s in self.styles:
            lo, hi = x.agg(F.min(f"g_{s}"), F.max(f"g_{s}")).first()
            if lo == hi:
                self.constant[s] = int(hi or 0)
            else:
                self.models[s] = LogisticRegression(featuresCol="__x", labelCol=f"g_{s}", predictionCol=f"p_{s}", probabilityCol=f"q_{s}", rawPredictionCol=f"w_{s}", regParam=0.001, maxIter=20).fit(x.withColumn(f"g_{s}", F.col(f"g_{s}").cast("double")))
        x.unpersist()
        return self

    def tag(self, pool: DataFrame) -> DataFrame:
        out = reduce(lambda df, m: m.transform(df), self.models.values(), self.text.transform(pool))
        flag = lambda s: F.lit(self.constant[s]) if s in self.constant else (F.element_at(vector_to_array(f"q_{s}"), 2) >= 0.5).cast("int")
        return out.select("instance_id", *[flag(s).alias(f"g_{s}") for s in self.styles])


def tag_report(tagged: DataFrame, truth: DataFrame, styles=STYLES) -> DataFrame:
    """Precision, recall and F1 by style."""
    j = tagged.select("instance_id", *[F.col(f"g_{s}").alias(f"p_{s}") for s in styles]).join(truth.select("instance_id", *[f"g_{s}" for s in styles]), "instance_id")
    long = j.selectExpr(f"stack({len(styles)}, " + ", ".join(f"'{s}', p_{s}, g_{s}" for s in styles) + ") as (style, p, g)")
    c = long.groupBy("style").agg(F.sum(F.expr("p * g")).alias("tp"), F.sum("p").alias("said"), F.sum("g").alias("held"))
    return c.select("style", F.expr("try_divide(tp, said)").alias("precision"), F.expr("try_divide(tp, held)").alias("recall"), F.expr("try_divide(2 * tp, said + held)").alias("f1"))
