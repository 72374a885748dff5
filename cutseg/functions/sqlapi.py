"""SQL surface: a scalar function, a table function and views."""

from __future__ import annotations

from dataclasses import replace

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, functions as F
from pyspark.sql.functions import pandas_udf, udtf

from cutseg.operators.corpus import NgramModel
from cutseg.operators.segment import SegmentConfig, _collected, by_language, split_sentences


def _segmenter(model: NgramModel, cfg: SegmentConfig, lists: dict):
    shared = model.bi.sparkSession.sparkContext.broadcast(_collected(model, cfg, lists.get("sets"), lists.get("words"), lists.get("singles")))
    held: list = []  # the weights of this worker's languages

    def words(lang: str, s: str, cut=None) -> list[str]:
        if not held:
            held.append(by_language(cfg, shared))
        own = cfg if cut is None else replace(cfg, cut=float(cut))  # the cut is no part of the weights
        return split_sentences([(s, *held[0](lang).bands(s))], own)[0][2] if s else []
    return words


def register(spark: SparkSession, model: NgramModel, cfg: SegmentConfig, **lists: DataFrame) -> None:
    """``segment_udf(lang, s)`` gives an array of words; ``segment_words(lang, s,
    cut)`` gives rows ``w_no, start, end, word``.  ``lists``: sets, words and
    singles as in ``segment``."""
    words = _segmenter(model, cfg, lists)

    @pandas_udf("array<string>")
    def segment_udf(lang: pd.Series, s: pd.Series) -> pd.Series:
        return pd.Series([words(a, b) for a, b in zip(lang, s)])

    @udtf(returnType="w_no int, start int, end int, word string")
    class SegmentWords:
        def eval(self, lang: str, s: str, cut: float):
            at = 0
            for i, w in enumerate(words(lang, s or "", cut)):
                yield i, at, at + len(w), w
                at += len(w)

    spark.udf.register("segment_udf", segment_udf)
    spark.udtf.register("segment_words", SegmentWords)


def entropy_udaf(cnt: str):
    """Entropy in nats of a column of counts, as a grouped-aggregate function."""
    import numpy as np

    @pandas_udf("double")
    def entropy(v: pd.Series) -> float:
        p = v.to_numpy(float)
        p = p[p > 0] / p.sum()
        return float(-(p * np.log(p)).sum())
    return entropy(cnt)


def entropy_builtin(cnt: str):
    """The same from built-in sums: ln T - sum(c ln c) / T."""
    c = F.col(cnt)
    return F.log(F.sum(c)) - F.sum(c * F.log(c)) / F.sum(c)
