"""Scores and descriptions of segmentations.

Predictions and gold are rows ``sent_id, ..., words``; a word is right if both
its ends are.  Spans are compared as arrays of one row, so scoring is one join
on the sentence and a sum; the join is merged, as arrays in packed files look small
enough to be collected on the driver.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window as W, functions as F

from cutseg.functions.units import gold_words, spans


def gold(sents: DataFrame) -> DataFrame:
    """Words of the original spacing; other marks are words of their own."""
    return sents.withColumn("words", gold_words(F.col("raw"))).select("sent_id", "lang", "s", "words")


def paired(pred: DataFrame, truth: DataFrame, keep: tuple[str, ...] = ("lang",)) -> DataFrame:
    """``sent_id, <keep>, p, g``: span arrays of every sentence of the truth; one
    without a prediction has no predicted span."""
    right = truth.select("sent_id", *keep, spans(F.col("words")).alias("g"))
    left = pred.select(F.col("sent_id").alias("_id"), spans(F.col("words")).alias("p"))
    rows = right.join(left.hint("merge"), F.col("_id") == F.col("sent_id"), "left")
    return rows.select("sent_id", *keep, F.coalesce("p", F.array().cast("array<bigint>")).alias("p"), "g")


def _rates(tp, n_pred, n_gold) -> list:
    p, r = tp / n_pred, tp / n_gold
    return [p.alias("precision"), r.alias("recall"), F.when(tp > 0, 2 * p * r / (p + r)).otherwise(0.0).alias("f1")]


def _pooled(counts: DataFrame, by: list[str]) -> DataFrame:
    sums = counts.groupBy(*by).agg(*[F.sum(c).cast("long").alias(c) for c in ("tp", "n_pred", "n_gold")])
    return sums.select(*by, "tp", "n_pred", "n_gold", *_rates(F.col("tp"), F.nullif(F.col("n_pred"), F.lit(0)), F.nullif(F.col("n_gold"), F.lit(0))))


def span_counts(pred: DataFrame, truth: DataFrame, keep: tuple[str, ...] = ("lang",)) -> DataFrame:
    """tp, n_pred, n_gold of each sentence."""
    return paired(pred, truth, keep).select("sent_id", *keep, F.size(F.array_intersect("p", "g")).alias("tp"), F.size("p").alias("n_pred"), F.size("g").alias("n_gold"))


def score_words(pred: DataFrame, truth: DataFrame, by: tuple[str, ...] = ("lang",)) -> DataFrame:
    """Pooled precision, recall and F of words."""
    return _pooled(span_counts(pred, truth, by), list(by))


def score_cuts(pred: DataFrame, truth: DataFrame) -> DataFrame:
    """Pooled scores by ``cut`` of predictions that have each sentence of the
    truth once for each cut; words are placed and joined once for all cuts."""
    right = truth.select("sent_id", spans(F.col("words")).alias("g"))
    rows = pred.select("cut", "sent_id", spans(F.col("words")).alias("p")).join(right.hint("merge"), "sent_id")
    return _pooled(rows.select("cut", F.size(F.array_intersect("p", "g")).alias("tp"), F.size("p").alias("n_pred"), F.size("g").alias("n_gold")), ["cut"])


def score_bounds(pred: DataFrame, truth: DataFrame, by: tuple[str, ...] = ("lang",)) -> DataFrame:
    """The same of inner boundaries."""
    inner = lambda c: F.transform(F.slice(c, 1, F.greatest(F.size(c) - 1, F.lit(0))), lambda x: x % 1048576)
    rows = paired(pred, truth, by).select(*by, inner("p").alias("p"), inner("g").alias("g"))
    return _pooled(rows.select(*by, F.size(F.array_intersect("p", "g")).alias("tp"), F.size("p").alias("n_pred"), F.size("g").alias("n_gold")), list(by))


def compare(scores: DataFrame, base: str) -> DataFrame:
    """Each method's F less that of ``base``; ``scores`` has method, lang, f1."""
    b = scores.where(F.col("method") == base).select("lang", F.col("f1").alias("f_base"))
    return scores.join(b, "lang").select("method", "lang", "f1", (F.col("f1") - F.col("f_base")).alias("f_gain"))


def granularity_stats(words: DataFrame, by: tuple[str, ...] = ("lang",)) -> DataFrame:
    """Sentences, words, words a sentence, mean and median word length."""
    rows = words.select(*by, "sent_id", F.explode("words").alias("w"))
    return rows.groupBy(*by).agg(
        F.countDistinct("sent_id").alias("sentences"), F.count("*").alias("n_words"), (F.count("*") / F.countDistinct("sent_id")).alias("words_per_sentence"),
        F.avg(F.length("w")).alias("mean_len"), F.percentile(F.length("w"), F.lit(0.5)).alias("median_len"), F.max(F.length("w")).cast("long").alias("max_len"))


def error_types(pred: DataFrame, truth: DataFrame, by: tuple[str, ...] = ("lang",)) -> DataFrame:
    """Predicted words: right, merged (covers two gold words or more), split
    (inside a gold word), or crossing a gold boundary."""
    def rows(column: str, side: int) -> DataFrame:
        x = paired(pred, truth, by).select("sent_id", *by, F.explode(column).alias("x"))
        return x.select("sent_id", *by, F.floor(F.col("x") / 1048576).alias("a"), (F.col("x") % 1048576).alias("e"), F.lit(side).alias("side"))

    # the gold word that begins last at or before each predicted word; a window has one sentence
    mine, theirs = rows("p", 1), rows("g", 0)
    before = W.partitionBy("sent_id").orderBy("a", "side").rowsBetween(W.unboundedPreceding, 0)
    gold_word = F.last(F.when(F.col("side") == 0, F.struct("a", "e")), ignorenulls=True).over(before)
    placed = mine.unionByName(theirs).withColumn("g", gold_word).where("side = 1")
    stops = theirs.select("sent_id", "e", F.lit(True).alias("stop"))
    kind = (F.when((F.col("g.a") == F.col("a")) & (F.col("g.e") == F.col("e")), "right").when(F.col("e") <= F.col("g.e"), "split")
            .when((F.col("g.a") == F.col("a")) & F.coalesce("stop", F.lit(False)), "merged").otherwise("crossing"))
    return placed.join(stops, ["sent_id", "e"], "left").select(*by, kind.alias("kind")).groupBy(*by, "kind").agg(F.count("*").alias("n"))


def fragmentation(words: DataFrame) -> DataFrame:
    """Sentences with more words than clusters: a cluster came apart in runs."""
    return words.groupBy("lang").agg(F.count("*").alias("sentences"), F.sum((F.size("words") > F.col("k")).cast("long")).alias("fragmented"))


def top_terms(words: DataFrame, n: int = 20, least: int = 2, min_len: int = 2) -> DataFrame:
    """The most frequent words of each language, ties by the word."""
    counts = words.select("lang", F.explode("words").alias("word")).where((F.length("word") >= min_len) & F.col("word").rlike("^\\p{L}+$")).groupBy("lang", "word").agg(F.count("*").alias("cnt"))
    rank = F.row_number().over(W.partitionBy("lang").orderBy(F.desc("cnt"), "word"))
    return counts.where(F.col("cnt") >= least).withColumn("rank", rank).where(F.col("rank") <= n)


def difference_table(a: DataFrame, b: DataFrame, truth: DataFrame) -> DataFrame:
    """Sentences that two segmentations split differently, with the words that
    only one of them has."""
    rows = a.select("sent_id", F.col("words").alias("a")).join(b.select("sent_id", F.col("words").alias("b")), "sent_id").join(
        truth.select("sent_id", "lang", F.col("words").alias("gold")), "sent_id")
    return rows.where("a <> b").select("sent_id", "lang", *[F.array_join(c, " ").alias(c) for c in ("gold", "a", "b")],
                                       F.array_join(F.array_except("a", "b"), " ").alias("only_a"), F.array_join(F.array_except("b", "a"), " ").alias("only_b"))


def form_effect(plain: DataFrame, sym: DataFrame) -> DataFrame:
    """Word count and length spread of two segmentations (methods ``plain`` and
    ``sym``), by number of clusters."""
    both = plain.select(F.lit("plain").alias("form"), "k", "words").unionByName(sym.select(F.lit("sym").alias("form"), "k", "words"))
    rows = both.select("form", "k", F.explode("words").alias("w"))
    return rows.groupBy("form", "k").agg(F.count("*").alias("n_words"), F.avg(F.length("w")).alias("mean_len"), F.stddev_samp(F.length("w")).alias("sd_len"))


def cut_objective(bands: DataFrame, objective: str = "ratio", self_loop: float = 1.0) -> DataFrame:
    """``sent_id, value``: ratio or normalised cut of the partition in column
    ``labels`` (run numbers, one a symbol)."""
    n = F.col("n")
    index = F.sequence(F.lit(0), n - 1)
    at = lambda name, i: F.coalesce(F.get(name, i), F.lit(0.0))
    runs = F.sequence(F.lit(0), F.element_at("labels", -1))

    def crossing(i):
        lab = lambda j: F.get("labels", j)
        out = F.lit(0.0)
        for d, name, base in ((-1, "adj", -1), (1, "adj", 0), (-2, "skip", -2), (2, "skip", 0)):
            out = out + F.when(F.coalesce(lab(i + d) != lab(i), F.lit(False)), at(name, i + base)).otherwise(0.0)
        return out

    def mass(i):
        if objective == "ratio":
            return F.lit(1.0)
        return F.lit(float(self_loop)) + at("adj", i - 1) + at("adj", i) + at("skip", i - 2) + at("skip", i)

    per = F.transform(index, lambda i: F.struct(F.get("labels", i).alias("r"), crossing(i).alias("c"), mass(i).alias("m")))
    total = lambda r, f: F.aggregate(F.filter("per", lambda e: e["r"] == r), F.lit(0.0), lambda acc, e: acc + e[f])
    value = F.aggregate(F.transform(runs, lambda r: F.coalesce(total(r, "c") / F.nullif(total(r, "m"), F.lit(0.0)), F.lit(0.0))), F.lit(0.0), lambda acc, x: acc + x)
    return bands.withColumn("per", per).select("sent_id", value.alias("value"))


def run_labels(words: Column) -> Column:
    """Run number of each symbol from a words array."""
    return F.flatten(F.transform(words, lambda w, j: F.array_repeat(j, F.length(w))))

