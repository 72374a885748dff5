"""Edge weights learned from segmented sentences: the probability that two
neighbours belong to one word, from what the corpus statistics say about them."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from cutseg.functions.units import gold_words
from cutseg.operators import affinity
from cutseg.operators.corpus import NgramModel

_FEATURES = ["x1", "x2", "x3"]


def _described(edges: DataFrame, words: DataFrame) -> DataFrame:
    """The edge's weight on two scales, and whether some word holds the pair."""
    inside = affinity.word_bigrams(words).withColumn("_in", F.lit(1.0))
    return edges.join(inside, ["lang", "a", "b"], "left").select(
        *edges.columns, F.log1p(F.greatest(F.col("w"), F.lit(0.0))).alias("x1"), F.least(F.col("w"), F.lit(1.0)).alias("x2"), F.coalesce("_in", F.lit(0.0)).alias("x3"))


class LearnedWeights:
    """Logistic regression of bonds on all training sentences; the fit is
    distributed, the model a handful of numbers."""

    def __init__(self, sents: DataFrame, model: NgramModel, words: DataFrame, rounds: int = 30):
        from pyspark.ml.classification import LogisticRegression
        from pyspark.ml.feature import VectorAssembler
        self.words = words
        lengths = F.transform(gold_words(F.col("raw")), F.length)
        bonds = F.flatten(F.transform(lengths, lambda n: F.concat(F.array_repeat(F.lit(1.0), n - 1), F.array(F.lit(0.0)))))
        # all that is known of a bond is its window: equal ones are one row with a weight
        pairs = affinity.windows(sents.withColumn("sent_id", bonds)).withColumn("y", F.get("sent_id", F.col("i"))).where("y is not null")
        kinds = pairs.groupBy("lang", "o", "a", "b", "x").agg(F.count_if(F.col("y") == 0).alias("n0"), F.count_if(F.col("y") == 1).alias("n1"))
        both = F.inline(F.array(*[F.struct(F.lit(float(y)).alias("y"), F.col(f"n{y}").cast("double").alias("n")) for y in (0, 1)]))
        rows = _described(affinity.kind_weights(kinds, model), words).select(*_FEATURES, both).where("n > 0")
        fitted = LogisticRegression(featuresCol="f", labelCol="y", weightCol="n", maxIter=rounds, regParam=1e-6).fit(VectorAssembler(inputCols=_FEATURES, outputCol="f").transform(rows))
        self.coefficients, self.intercept = [float(c) for c in fitted.coefficients], float(fitted.intercept)

    def weigh(self, edges: DataFrame) -> DataFrame:
        """Edges with the learned probability as weight; plain SQL expressions."""
        z = F.lit(self.intercept)
        for name, c in zip(_FEATURES, self.coefficients):
            z = z + F.lit(c) * F.col(name)
        return _described(edges, self.words).withColumn("w", 1 / (1 + F.exp(-z))).select("sent_id", "lang", "i", "a", "b", "w")
