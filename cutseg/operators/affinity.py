"""Edge weights between neighbouring symbols, as DataFrame expressions.

Edges are rows ``sent_id, lang, i, a, b, w`` (adjacent, i from 0) or ``sent_id,
lang, i, a, b, c, w`` (one symbol between).  Weights depend on a window of four
symbols only, so they are computed once for each distinct window.
"""

from __future__ import annotations

from collections.abc import Mapping

from pyspark.sql import DataFrame, functions as F

from cutseg.functions.units import symbols
from cutseg.operators.corpus import NgramModel

EMPTY = ""


def windows(sents: DataFrame) -> DataFrame:
    """``sent_id, lang, i, o, a, b, x``: each adjacent pair with the symbol
    before and behind it (empty at the ends)."""
    y = F.concat(F.array(F.lit(EMPTY)), symbols(F.col("s")), F.array(F.lit(EMPTY)))
    at = lambda k: F.element_at("y", k)
    pairs = F.transform(F.sequence(F.lit(1), F.size("y") - 3), lambda i: F.struct(
        (i - 1).alias("i"), at(i).alias("o"), at(i + 1).alias("a"), at(i + 2).alias("b"), at(i + 3).alias("x")))
    return sents.where(F.length("s") >= 2).select("sent_id", "lang", y.alias("y")).select("sent_id", "lang", F.inline(pairs))


def kind_weights(kinds: DataFrame, model: NgramModel) -> DataFrame:
    """``lang, o, a, b, x, w``: the largest of the one-step, two-step and backward
    two-step transition probabilities, times the standardised log count of the
    pair, of distinct windows; other columns of ``kinds`` stay."""
    others = [c for c in kinds.columns if c not in ("lang", "o", "a", "b", "x")]
    two = model.bi.select("lang", "a", "b", "p1", "z")
    before = model.tri.select("lang", F.col("a").alias("o"), F.col("b").alias("a"), F.col("c").alias("b"), "f2")
    behind = model.tri.select("lang", "a", "b", F.col("c").alias("x"), "b2")
    p = F.greatest(*[F.coalesce(c, F.lit(0.0)) for c in ("p1", "f2", "b2")])
    return (kinds.join(two, ["lang", "a", "b"], "left").join(before, ["lang", "o", "a", "b"], "left").join(behind, ["lang", "a", "b", "x"], "left")
            .select("lang", "o", "a", "b", "x", *others, (p * F.coalesce("z", F.lit(0.0))).alias("w")))


def adjacent_weights(sents: DataFrame, model: NgramModel) -> DataFrame:
    """The weight of each pair's window; what is not in the model, or of a null
    language, counts as 0."""
    win = windows(sents)
    weighed = kind_weights(win.select("lang", "o", "a", "b", "x").distinct(), model)
    return win.join(weighed, ["lang", "o", "a", "b", "x"], "left").select("sent_id", "lang", "i", "a", "b", F.coalesce("w", F.lit(0.0)).alias("w"))


def skip_weights(sents: DataFrame, model: NgramModel) -> DataFrame:
    """Probability of the next two symbols given the first, times the
    standardised log count of the three."""
    win = windows(sents).where(F.col("x") != EMPTY).select("sent_id", "lang", "i", "a", "b", F.col("x").alias("c"))
    w = model.tri.select("lang", "a", "b", "c", (F.col("pair") * F.col("z")).alias("w"))
    return win.join(w, ["lang", "a", "b", "c"], "left").select("sent_id", "lang", "i", "a", "b", "c", F.coalesce("w", F.lit(0.0)).alias("w"))


def weaken(edges: DataFrame, sets: DataFrame, divisors: Mapping[int, float] | None = None, except_bigrams: DataFrame | None = None) -> DataFrame:
    """Divide by 4 where an end is in set 1 and by 80 where an end is in set 2,
    one after the other; listed pairs (``lang, a, b``) are exempt.

    ``sets`` (``lang, ch, set_id``) holds a few characters a language.
    """
    out = edges
    for set_id, divisor in (divisors or {1: 4.0, 2: 80.0}).items():
        own = F.broadcast(sets.where(F.col("set_id") == set_id).select("lang", "ch").distinct())
        for end in ("a", "b"):
            out = out.join(own.select("lang", F.col("ch").alias(end), F.lit(True).alias(f"_{end}")), ["lang", end], "left")
        out = out.withColumn("w", F.when(F.coalesce("_a", "_b", F.lit(False)), F.col("w") / divisor).otherwise(F.col("w"))).drop("_a", "_b")
    out = out.select(*edges.columns)
    if except_bigrams is None:
        return out
    free = F.broadcast(except_bigrams.select("lang", "a", "b").distinct())
    return out.join(free, ["lang", "a", "b"], "left_anti").select(*edges.columns).unionByName(edges.join(free, ["lang", "a", "b"], "left_semi").select(*edges.columns))


def block_skip(edges: DataFrame, sets: DataFrame) -> DataFrame:
    """Skip edges are 0 if any of the three symbols is in set 2."""
    hard = F.broadcast(sets.where("set_id = 2").groupBy("lang").agg(F.collect_set("ch").alias("hard")))
    inside = F.coalesce(F.arrays_overlap(F.array("a", "b", "c"), "hard"), F.lit(False))
    return edges.join(hard, "lang", "left").withColumn("w", F.when(inside, 0.0).otherwise(F.col("w"))).select(*edges.columns)


def word_bigrams(words: DataFrame) -> DataFrame:
    """``lang, a, b``: pairs of neighbours inside some word (a context-free test)."""
    y = symbols(F.col("word"))
    pairs = F.transform(F.sequence(F.lit(1), F.size("y") - 1), lambda i: F.struct(F.element_at("y", i).alias("a"), F.element_at("y", i + 1).alias("b")))
    return words.where(F.length("word") >= 2).select("lang", y.alias("y")).select("lang", F.inline(pairs)).distinct()


def boost(edges: DataFrame, words: DataFrame, factor: float = 20.0, max_rank: int | None = None) -> DataFrame:
    """Multiply pairs that are part of a word (with rank below ``max_rank``);
    adds ``boosted``."""
    if max_rank is not None:
        words = words.where(F.col("rank") < max_rank)
    inside = word_bigrams(words).withColumn("_in", F.lit(True))
    out = edges.join(inside, ["lang", "a", "b"], "left").withColumn("boosted", F.coalesce("_in", F.lit(False)))
    return out.withColumn("w", F.when(F.col("boosted"), F.col("w") * factor).otherwise(F.col("w"))).select(*edges.columns, "boosted")


def boost_in_place(edges: DataFrame, sents: DataFrame, words: DataFrame, factor: float = 20.0, max_rank: int | None = None) -> DataFrame:
    """Multiply pairs inside a word that stands at this very place of the
    sentence; adds ``boosted``.

    A sentence gives its substrings of the lengths that a word of two symbols or
    more has; a substring that is a word boosts the pairs it covers.
    """
    if max_rank is not None:
        words = words.where(F.col("rank") < max_rank)
    known = words.where(F.length("word") >= 2).select("lang", "word").distinct()
    lengths = known.groupBy("lang").agg(F.collect_set(F.length("word")).alias("_lengths"))  # a few numbers a language
    held = sents.join(F.broadcast(lengths), "lang").withColumn("m", F.explode("_lengths")).where(F.col("m") <= F.length("s"))
    starts = held.select("sent_id", "lang", "m", "s", F.explode(F.sequence(F.lit(0), F.length("s") - F.col("m"))).alias("p"))
    spans = starts.select("sent_id", "lang", "m", "p", F.substring("s", F.col("p") + 1, F.col("m")).alias("word")).join(known, ["lang", "word"], "left_semi")
    inside = spans.select("sent_id", F.explode(F.sequence(F.col("p"), F.col("p") + F.col("m") - 2)).alias("i")).distinct().withColumn("_in", F.lit(True))
    out = edges.join(inside, ["sent_id", "i"], "left").withColumn("boosted", F.coalesce("_in", F.lit(False)))
    return out.withColumn("w", F.when(F.col("boosted"), F.col("w") * factor).otherwise(F.col("w"))).select(*edges.columns, "boosted")


def _divide(edges: DataFrame, singles: DataFrame, skip_boosted: bool) -> DataFrame:
    """Divide by the larger divisor of the two ends; ``singles``: lang, ch, d."""
    out = edges
    for end in ("a", "b"):
        out = out.join(F.broadcast(singles.select("lang", F.col("ch").alias(end), F.col("d").alias(f"_{end}"))), ["lang", end], "left")
    d = F.greatest("_a", "_b")  # nulls are passed over
    hit = d.isNotNull() & (~F.col("boosted") if skip_boosted else F.lit(True))
    return out.withColumn("w", F.when(hit, F.col("w") / d).otherwise(F.col("w"))).select(*edges.columns)


def split_singles(edges: DataFrame, singles: DataFrame, floor: float = 20.0, numer: float = 1e6, skip_boosted: bool = True) -> DataFrame:
    """Divide pairs with a listed one-character word (``lang, ch, rank``) by
    max(floor, ln(numer / rank)), unless the pair was boosted.  With the default
    floor the rank never acts, as ln(10^6) is below 20."""
    d = F.greatest(F.lit(float(floor)), F.log(F.lit(float(numer)) / F.col("rank")))
    return _divide(edges, singles.select("lang", "ch", d.alias("d")), skip_boosted)


def split_singles_by_count(edges: DataFrame, words: DataFrame, unit: float = 250.0, skip_boosted: bool = False) -> DataFrame:
    """Divide pairs with a one-character training word by max(1, count / unit)."""
    d = F.greatest(F.lit(1.0), F.col("cnt") / F.lit(float(unit)))
    return _divide(edges, words.where(F.length("word") == 1).select("lang", F.col("word").alias("ch"), d.alias("d")), skip_boosted)


def to_bands(sents: DataFrame, adjacent: DataFrame, skip: DataFrame | None = None) -> DataFrame:
    """``sent_id, lang, s, n, adj, skip``: edge rows as arrays, one row a sentence.
    A group has at most as many rows as its sentence has symbols."""
    def arrays(edges: DataFrame, name: str) -> DataFrame:
        return edges.groupBy("sent_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("i", "w"))), lambda e: e["w"]).alias(name))
    none = F.array().cast("array<double>")
    out = sents.select("sent_id", "lang", "s", "n").join(arrays(adjacent, "adj"), "sent_id", "left")
    out = out.join(arrays(skip, "skip"), "sent_id", "left") if skip is not None else out.withColumn("skip", F.transform(F.slice("adj", 2, F.size("adj")), lambda _: F.lit(0.0)))
    return out.withColumn("adj", F.coalesce("adj", none)).withColumn("skip", F.coalesce("skip", none))
