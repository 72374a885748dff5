"""What many queries share: sentence tables and the model of one data folder.

Everything is written once in a session's scratch folder and read from there.
"""

from __future__ import annotations

from dataclasses import replace
from functools import cached_property

from pyspark.sql import DataFrame, SparkSession, functions as F

from cutseg.functions import units
from cutseg.operators import corpus as C, metrics as M, segment as S
from cutseg.operators.learned import LearnedWeights
from cutseg.plans.workspace import Workspace
from cutseg.sources import tables

#: Cuts among which the dev sources choose, beside the printed one.
DEV_CUTS = (0.02, 0.1, 0.3, 0.6)
_HELD: dict[tuple[str, str], "Context"] = {}


def context(spark: SparkSession, sf_dir: str) -> "Context":
    key = (spark.sparkContext.applicationId, sf_dir)
    if key not in _HELD:
        _HELD[key] = Context(spark, sf_dir)
    return _HELD[key]


class Context:
    def __init__(self, spark: SparkSession, sf_dir: str):
        self._dev: dict[str, list[tuple[float, float]]] = {}
        self.spark, self.dir, self.ws = spark, sf_dir, Workspace(spark, "context")

    def table(self, name: str) -> DataFrame:
        return tables.read(self.spark, self.dir, name)

    @cached_property
    def documents(self) -> DataFrame:
        return tables.documents(self.spark, self.dir, self.ws.table)

    def _sents(self, part: str) -> DataFrame:
        docs = tables.split(self.documents, part, self.table("benchmark") if part == "train" else None)
        return self.ws.table(units.sentences(docs), f"sents-{part}")

    @cached_property
    def train(self) -> DataFrame:
        return self._sents("train")

    @cached_property
    def dev(self) -> DataFrame:
        return self._sents("dev")

    @cached_property
    def test(self) -> DataFrame:
        return self._sents("test")

    @cached_property
    def benchmark(self) -> DataFrame:
        items = self.table("benchmark").select("item_id", "text", F.lit("en").alias("lang"))
        return self.ws.table(units.sentences(items, id_col="item_id", keep=("lang",)), "sents-benchmark")

    @cached_property
    def part_names(self) -> DataFrame:
        """Distinct part names as sentences of a closed toy language."""
        names = self.table("part").select(F.lower("p_name").alias("raw")).distinct()
        s = F.regexp_replace("raw", "\\s+", "")
        return self.ws.table(names.select(F.col("raw").alias("sent_id"), F.lit("part").alias("lang"), "raw", s.alias("s"), F.length(s).alias("n")), "sents-part")

    @cached_property
    def conversations(self) -> DataFrame:
        turns = self.table("conversations").select(F.concat_ws("/", F.col("conv_id").cast("string"), F.col("turn").cast("string")).alias("doc_id"), "conv_id", "turn", "text", F.lit("en").alias("lang"))
        return self.ws.table(units.sentences(turns, keep=("lang", "conv_id", "turn")), "sents-conversations")

    @cached_property
    def grams(self) -> dict[int, DataFrame]:
        return self._counted(self.train, "grams")

    def _counted(self, sents: DataFrame, name: str) -> dict[int, DataFrame]:
        """Grams of orders 1 to 3; the texts are read once."""
        padded = self.ws.table(C.padded_counts(sents), f"{name}-padded")
        return {n: self.ws.table(g, f"{name}-{n}") for n, g in C.ngram_tables(sents, padded=padded).items()}

    def _model(self, grams: dict[int, DataFrame], name: str) -> C.NgramModel:
        m = C.model_of(grams[1], grams[2], grams[3])
        return C.NgramModel(m.uni, self.ws.table(m.bi, f"{name}-bi"), self.ws.table(m.tri, f"{name}-tri"))

    @cached_property
    def model(self) -> C.NgramModel:
        return self._model(self.grams, "model")

    @cached_property
    def part_model(self) -> C.NgramModel:
        return self._model(self._counted(self.part_names, "part-grams"), "part-model")

    @cached_property
    def words(self) -> DataFrame:
        return self.ws.table(C.train_words(self.train), "words")

    @cached_property
    def lexicon(self) -> DataFrame:
        """Ranked words with counts."""
        return self.ws.table(C.ranked(self.words, ("cnt",)), "lexicon")

    @cached_property
    def boost_rank(self) -> int:
        """The published share of the vocabulary (25,000 of 56,064 words)."""
        largest = self.lexicon.agg(F.max("rank")).first()[0] or 0
        return max(2, int(largest * 25_000 / 56_064))

    @cached_property
    def sets(self) -> DataFrame:
        # words of one letter are enough, if the others were not asked for
        words = self.words if "words" in self.__dict__ else C.train_letters(self.train)
        return self.ws.table(C.weakening_sets(words, self.grams[1]), "sets")

    @cached_property
    def learned(self) -> LearnedWeights:
        return LearnedWeights(self.train, self.model, self.words)

    def dev_scores(self, method: str) -> list[tuple[float, float]]:
        """Cuts with the pooled F of a method on the dev sources."""
        if method not in self._dev:
            cfg = {"lexicon": replace(S.LEXICON, max_rank=self.boost_rank), "trained": S.TRAINED, "learned": S.LEARNED}[method]
            given = {"lexicon": {"words": self.lexicon, "singles": self.singles}, "trained": {"words": self.words, "singles": self.singles},
                     "learned": {"hook": self.learned.weigh, "by_window": True} if method == "learned" else {}}[method]
            cuts = sorted({cfg.cut, *DEV_CUTS})
            words = self.ws.table(S.segment(self.dev, self.model, cfg, cuts=cuts, **given).select("cut", "sent_id", "words"), f"dev-{method}")
            f1 = {r["cut"]: r["f1"] for r in M.score_cuts(words, M.gold(self.dev)).collect()}
            self._dev[method] = [(cut, float(f1.get(cut) or 0.0)) for cut in cuts]
        return self._dev[method]

    def cut_of(self, method: str) -> float:
        """The cut with the best F on the dev sources, of equal ones the least."""
        return max(self.dev_scores(method), key=lambda r: (r[1], -r[0]))[0]

    @cached_property
    def singles(self) -> DataFrame:
        """One-character words: lang, ch, rank, cnt."""
        one = self.lexicon.where(F.length("word") == 1)
        return one.select("lang", F.col("word").alias("ch"), "rank", "cnt")
