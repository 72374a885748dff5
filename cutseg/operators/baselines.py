"""Segmenters that the graph methods are compared with."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window as W, functions as F

from cutseg.functions import kernels as K
from cutseg.functions.units import symbols
from cutseg.operators.laplacian import cut_words
from cutseg.operators.segment import with_results
from cutseg.operators.tagger import Tagger  # noqa: F401  the supervised one


#: By how much an entropy must be above the one before it to count as a rise.
RISE = 1e-9


def successor_entropy(bi: DataFrame, direction: str = "forward") -> DataFrame:
    """``lang, ch, h``: entropy (nats) of the symbol behind (or before) ``ch``."""
    key = "a" if direction == "forward" else "b"
    p = F.col("cnt") / F.sum("cnt").over(W.partitionBy("lang", key))
    return bi.withColumn("p", p).groupBy("lang", F.col(key).alias("ch")).agg(F.sum(-F.col("p") * F.log("p")).alias("h"))


def context_entropy(tri: DataFrame) -> DataFrame:
    """``lang, a, b, h``: entropy of the symbol behind a pair (order 2)."""
    p = F.col("cnt") / F.sum("cnt").over(W.partitionBy("lang", "a", "b"))
    return tri.withColumn("p", p).groupBy("lang", "a", "b").agg(F.sum(-F.col("p") * F.log("p")).alias("h"))


def _looked_up(table: str, s):
    return F.transform(symbols(s), lambda c: F.coalesce(F.element_at(table, c), F.lit(0.0)))


def entropy_segment(sents: DataFrame, bi: DataFrame, *, mode: str = "threshold", direction: str = "forward", theta: float = 2.5) -> DataFrame:
    """Boundary where the entropy is above theta, or rises (``mode='rise'``).

    Forward looks at the symbol before the boundary, backward at the one behind;
    ``both`` asks for either.  Entropies of a language are one small map.
    """
    out = sents.select("sent_id", "lang", "s")
    tests = []
    for way in ("forward", "backward") if direction == "both" else (direction,):
        m = successor_entropy(bi, way).groupBy("lang").agg(F.map_from_entries(F.collect_list(F.struct("ch", "h"))).alias(f"h_{way}"))
        out = out.join(F.broadcast(m), "lang", "left")  # one row a language, one entry a symbol
        tests.append(way)
    for way in tests:  # the entropy at each symbol, looked up once
        out = out.withColumn(f"at_{way}", _looked_up(f"h_{way}", F.col("s")))
    # a generator that gives one row: keeps the arrays from being computed again for each symbol
    out = out.select("sent_id", "lang", "s", F.explode(F.array(F.struct(*[f"at_{way}" for way in tests]))).alias("at")).select("sent_id", "lang", "s", "at.*")
    h = lambda way, i: F.coalesce(F.get(f"at_{way}", i), F.lit(0.0))

    def is_cut(i):
        hit = F.lit(False)
        for way in tests:
            at, step = (i, i - 1) if way == "forward" else (i + 1, i + 2)
            # a rise is more than the rounding error of two sums in different orders
            hit = hit | (h(way, at) > theta if mode == "threshold" else (h(way, at) > h(way, step) + RISE))
        return hit

    return out.withColumn("words", cut_words(F.col("s"), is_cut)).select("sent_id", "lang", "s", "words")


def pair_entropy_segment(sents: DataFrame, tri: DataFrame, theta: float = 2.0) -> DataFrame:
    """Boundary where the entropy behind the last two symbols is above theta; a
    pair that the model lacks has none."""
    from cutseg.operators.affinity import windows
    h = context_entropy(tri).select("lang", F.col("a").alias("o"), F.col("b").alias("a"), "h")
    edges = windows(sents).join(h, ["lang", "o", "a"], "left").select("sent_id", "i", (-F.coalesce("h", F.lit(0.0))).alias("w"))
    return threshold_segment(edges, sents, -theta)


def threshold_segment(edges: DataFrame, sents: DataFrame, tau: float) -> DataFrame:
    """Boundary where the adjacent weight is below tau; no spectrum."""
    flags = edges.groupBy("sent_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("i", (F.col("w") < tau).alias("cut")))), lambda e: e["cut"]).alias("cuts"))
    out = sents.select("sent_id", "lang", "s").join(flags, "sent_id", "left")
    return out.select("sent_id", "lang", "s", cut_words(F.col("s"), lambda i: F.coalesce(F.get("cuts", i), F.lit(False))).alias("words"))


def components_segment(edges: DataFrame, sents: DataFrame) -> DataFrame:
    """The ideal case: words are connected components, broken at zero edges."""
    return threshold_segment(edges.withColumn("w", F.when(F.col("w") > 0, 1.0).otherwise(0.0)), sents, 0.5)


def trivial(sents: DataFrame, kind: str) -> DataFrame:
    words = symbols(F.col("s")) if kind == "chars" else F.array("s")
    return sents.select("sent_id", "lang", "s", words.alias("words"))


def _by_words(sents: DataFrame, words: DataFrame, split_one) -> DataFrame:
    """Run ``split_one(table, s)`` on distinct sentences; the words of a language
    are a broadcast table of some 20 bytes a word, whatever their number."""
    held = words.where("lang is not null").select("lang", "word", "cnt").toArrow()
    by_lang = {}
    for lang in held.column("lang").unique().to_pylist():
        own = held.filter(pc.equal(held.column("lang"), lang))
        by_lang[lang] = K.WordTable(own.column("word").to_pylist(), own.column("cnt").to_numpy())
    shared, none = sents.sparkSession.sparkContext.broadcast(by_lang), K.WordTable([], np.zeros(0))

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        tables = shared.value
        for f in frames:
            out = [split_one(tables.get(lang, none), s) for lang, s in zip(f["lang"], f["s"])]
            yield pd.DataFrame({"lang": f["lang"], "s": f["s"], "words": out})

    tasks = 2 * sents.sparkSession.sparkContext.defaultParallelism
    distinct = sents.select("lang", "s").where("s is not null and s <> ''").repartition(tasks, "lang", "s").distinct()
    done = distinct.mapInPandas(run, "lang string, s string, words array<string>")
    return with_results(sents, done, {"words": F.array().cast("array<string>")})


def likelihood_segment(sents: DataFrame, words: DataFrame) -> DataFrame:
    """The words with the largest product of unigram probabilities; an unknown
    symbol costs as much as a word seen a tenth of a time."""
    return _by_words(sents, words, lambda table, s: table.likely(s))


def match_segment(sents: DataFrame, words: DataFrame, backward: bool = False) -> DataFrame:
    return _by_words(sents, words, lambda table, s: table.longest_first(s, backward))
