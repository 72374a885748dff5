"""N-gram statistics of a corpus, by group (usually the language)."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window as W, functions as F

from cutseg.functions.units import is_usable, symbols

#: Pads the ends of sentences in the single-pass count; occurs in no text.
PAD = "\x00"


def ngram_counts(sents: DataFrame, n: int, by: str = "lang") -> DataFrame:
    """``by, g, cnt`` of n consecutive symbols inside a sentence.  The sum is
    partial before the exchange, so only distinct grams cross it."""
    syms = symbols(F.col("s"))
    grams = F.transform(F.sequence(F.lit(1), F.size("y") - (n - 1)), lambda i: F.array_join(F.slice("y", i, n), ""))
    rows = sents.where(F.length("s") >= n).select(by, syms.alias("y")).select(by, F.explode(grams).alias("g"))
    return rows.groupBy(by, "g").agg(F.count("*").alias("cnt"))


#: Distinct grams that a task holds before it hands them on.
HELD_GRAMS = 1 << 19


def _counted(codes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Trigrams that begin at a symbol, as 63-bit keys, with their counts."""
    c = codes.astype(np.uint64)
    keys = (c[:-2] << np.uint64(42) | c[1:-1] << np.uint64(21) | c[2:])[codes[:-2] != 0]
    return np.unique(keys, return_counts=True)


def _merged(parts: list) -> tuple[np.ndarray, np.ndarray]:
    keys, back = np.unique(np.concatenate([k for k, _ in parts]), return_inverse=True)
    return keys, np.bincount(back, np.concatenate([n for _, n in parts]), len(keys)).astype(np.int64)


def padded_counts(sents: DataFrame, by: str = "lang") -> DataFrame:
    """``by, p, cnt``: end-padded trigrams of all sentences, in one pass over the
    texts.  A task counts by code points and hands on distinct grams only."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict = {}

        def rows() -> Iterator[pa.RecordBatch]:
            for group, parts in held.items():
                keys, cnt = _merged(parts)
                codes = np.stack([keys >> np.uint64(s) & np.uint64(0x1FFFFF) for s in (42, 21, 0)], axis=1).astype("<u4")
                text = codes.tobytes().decode("utf-32-le", "surrogatepass")
                yield pa.RecordBatch.from_arrays([pa.array([group] * len(keys), pa.string()), pa.array([text[i:i + 3] for i in range(0, len(text), 3)]), pa.array(cnt)], ["by", "p", "cnt"])
            held.clear()

        for batch in batches:
            groups = batch.column(0).dictionary_encode()
            place, names = groups.indices.fill_null(len(groups.dictionary)).to_numpy(zero_copy_only=False), [*groups.dictionary.to_pylist(), None]
            for j in np.unique(place):
                own = batch.column(1).filter(pa.array(place == j)).to_pylist()
                codes = np.frombuffer("".join(s + PAD + PAD for s in own).encode("utf-32-le", "surrogatepass"), "<u4")
                parts = held.setdefault(names[j], [])
                parts.append(_counted(codes))
                if len(parts) > 8:
                    held[names[j]] = [_merged(parts)]
            if sum(len(k) for parts in held.values() for k, _ in parts) > HELD_GRAMS:
                yield from rows()
        yield from rows()

    kind = sents.schema[by].dataType
    counted = sents.where("s <> ''").select(F.col(by).cast("string"), "s").mapInArrow(run, "by string, p string, cnt long")
    return counted.groupBy(F.col("by").cast(kind).alias(by), "p").agg(F.sum("cnt").alias("cnt"))


def ngram_tables(sents: DataFrame, by: str = "lang", padded: DataFrame | None = None) -> dict[int, DataFrame]:
    """Counts of orders 1 to 3 from one pass: end-padded trigrams, rolled up.  A
    caller that has written ``padded_counts`` gives them, so that all three
    orders read what was written."""
    padded = padded_counts(sents, by) if padded is None else padded

    def order(n: int) -> DataFrame:
        g = F.substring("p", 1, n)
        return padded.where(~F.contains(g, F.lit(PAD))).groupBy(by, g.alias("g")).agg(F.sum("cnt").alias("cnt"))
    return {n: order(n) for n in (1, 2, 3)}


def _usable(script: str, *names: str) -> Column:
    out = F.lit(True)
    for c in names:
        out = out & is_usable(F.col(c), script)
    return out


def transitions(grams: DataFrame, kind: str, by: str = "lang", script: str = "letter", zero_rule: bool = True) -> DataFrame:
    """Transition probabilities ``by, a, b[, c], p``.

    ``fwd1`` P(b|a) from bigrams; from trigrams ``fwd2`` P(c|a,b), ``bwd2``
    P(a|b,c) and ``pair`` P(b,c|a).  Denominators count what is followed inside
    the sentence.  With the zero rule, 0 where a symbol is not of the script.
    """
    names = ["a", "b"] if kind == "fwd1" else ["a", "b", "c"]
    given = {"fwd1": ["a"], "fwd2": ["a", "b"], "bwd2": ["b", "c"], "pair": ["a"]}[kind]
    rows = grams.select(by, *[F.substring("g", i + 1, 1).alias(c) for i, c in enumerate(names)], "cnt")
    p = F.col("cnt") / F.sum("cnt").over(W.partitionBy(by, *given))
    return rows.withColumn("p", F.when(_usable(script, *names), p).otherwise(0.0) if zero_rule else p).select(by, *names, "p")


def standardised_log_counts(grams: DataFrame, by: str = "lang", over: str = "types", ddof: int = 1) -> DataFrame:
    """``by, g, z``: ln of the count over the standard deviation of ln counts,
    over distinct grams or (``tokens``) weighted by their counts; no deviation
    counts as 1."""
    x = grams.withColumn("x", F.log(F.col("cnt").cast("double")))
    if over == "types":
        sd = F.stddev_samp("x") if ddof else F.stddev_pop("x")
    else:
        n, s1, s2 = F.sum("cnt"), F.sum(F.col("cnt") * F.col("x")), F.sum(F.col("cnt") * F.col("x") * F.col("x"))
        sd = F.sqrt((s2 - s1 * s1 / n) / (n - ddof))
    scale = x.groupBy(by).agg(sd.alias("sd")).select(by, F.when(F.col("sd") > 0, F.col("sd")).otherwise(1.0).alias("sd"))
    return x.join(F.broadcast(scale), by).select(by, "g", (F.col("x") / F.col("sd")).alias("z"))  # one row a group


@dataclass
class NgramModel:
    """Counts and what edge weights need of them.

    ``bi``: lang, a, b, cnt, p1, z; ``tri``: lang, a, b, c, cnt, f2, b2, pair, z.
    """

    uni: DataFrame
    bi: DataFrame
    tri: DataFrame

    def save(self, path: str) -> None:
        for name in ("uni", "bi", "tri"):
            getattr(self, name).write.mode("overwrite").partitionBy("lang").parquet(f"{path}/{name}")

    @classmethod
    def load(cls, spark, path: str) -> NgramModel:
        return cls(*(spark.read.parquet(f"{path}/{name}") for name in ("uni", "bi", "tri")))


def model_of(uni: DataFrame, bi: DataFrame, tri: DataFrame, script: str = "letter", over: str = "types", ddof: int = 1, zero_rule: bool = True) -> NgramModel:
    """Weights' inputs from plain counts ``lang, g, cnt``."""
    z2, z3 = (standardised_log_counts(g, over=over, ddof=ddof) for g in (bi, tri))
    ab = bi.join(z2, ["lang", "g"]).select("lang", F.substring("g", 1, 1).alias("a"), F.substring("g", 2, 1).alias("b"), "cnt", "z")
    p1 = F.col("cnt") / F.sum("cnt").over(W.partitionBy("lang", "a"))
    ab = ab.withColumn("p1", F.when(_usable(script, "a", "b"), p1).otherwise(0.0) if zero_rule else p1)
    abc = tri.join(z3, ["lang", "g"]).select("lang", *[F.substring("g", i + 1, 1).alias(c) for i, c in enumerate("abc")], "cnt", "z")
    for name, given in (("f2", ["a", "b"]), ("b2", ["b", "c"]), ("pair", ["a"])):
        p = F.col("cnt") / F.sum("cnt").over(W.partitionBy("lang", *given))
        abc = abc.withColumn(name, F.when(_usable(script, "a", "b", "c"), p).otherwise(0.0) if zero_rule else p)
    return NgramModel(uni, ab, abc)


def fit_model(sents: DataFrame, **options) -> NgramModel:
    grams = ngram_tables(sents)
    return model_of(grams[1], grams[2], grams[3], **options)


def merge_counts(*tables: DataFrame) -> DataFrame:
    """Counts of several corpora as one; nothing needs the texts again."""
    out = tables[0]
    for t in tables[1:]:
        out = out.unionByName(t)
    return out.groupBy("lang", "g").agg(F.sum("cnt").alias("cnt"))


def train_words(sents: DataFrame) -> DataFrame:
    """``lang, word, cnt`` of words in the original spacing."""
    from cutseg.functions.units import gold_words
    w = sents.select("lang", F.explode(gold_words(F.col("raw"))).alias("word"))
    return w.where(F.col("word").rlike("^\\p{L}+$")).groupBy("lang", "word").agg(F.count("*").alias("cnt"))


def train_letters(sents: DataFrame) -> DataFrame:
    """``lang, word, cnt``: those rows of ``train_words`` that have one letter."""
    from cutseg.functions.units import gold_words
    alone = F.regexp_extract_all("raw", F.lit("(?<![\\p{L}\\p{N}])\\p{L}(?![\\p{L}\\p{N}])"), F.lit(0))
    # Java looks back by halves of a symbol beyond U+FFFF
    every = F.filter(gold_words(F.col("raw")), lambda w: w.rlike("^\\p{L}$"))
    rows = sents.select("lang", F.explode(F.when(F.col("raw").rlike("[\\x{10000}-\\x{10FFFF}]"), every).otherwise(alone)).alias("word"))
    return rows.groupBy("lang", "word").agg(F.count("*").alias("cnt"))


def ranked(words: DataFrame, keep: tuple[str, ...] = ()) -> DataFrame:
    """``lang, word, rank, <keep>``: 1 is the most frequent, ties by the word.

    Words are ranked among those of equal count and equal first two symbols, so
    that no task sorts a language; the sizes of the groups before are added."""
    group = ["_lang", "cnt", "_head"]
    # a null language is a language
    keyed = words.withColumn("_lang", F.concat_ws(":", F.col("lang").isNull().cast("string"), "lang")).withColumn("_head", F.substring("word", 1, 2))
    sizes = keyed.groupBy(*group).agg(F.count("*").alias("_n"))
    before = F.sum("_n").over(W.partitionBy("_lang").orderBy(F.desc("cnt"), "_head").rowsBetween(W.unboundedPreceding, -1))
    first = sizes.select(*group, F.coalesce(before, F.lit(0)).alias("_before"))
    own = keyed.withColumn("_own", F.row_number().over(W.partitionBy(*group).orderBy("word")))
    return own.join(first, group).select("lang", "word", (F.col("_before") + F.col("_own")).cast("int").alias("rank"), *keep)


def weakening_sets(words: DataFrame, uni: DataFrame, hard: float = 0.5, soft: float = 0.03, least: int = 20) -> DataFrame:
    """``lang, ch, set_id``: characters that are a word by themselves in at least
    ``hard`` (set 2) or ``soft`` (set 1) of their occurrences, seen so ``least``
    times or more."""
    alone = words.where((F.length("word") == 1) & (F.col("cnt") >= least)).select("lang", F.col("word").alias("ch"), F.col("cnt").alias("own"))
    share = alone.join(uni.select("lang", F.col("g").alias("ch"), "cnt"), ["lang", "ch"]).withColumn("share", F.col("own") / F.col("cnt"))
    return share.where(F.col("share") >= soft).select("lang", "ch", F.when(F.col("share") >= hard, 2).otherwise(1).alias("set_id"))
