"""A corpus pipeline: toxicity, near duplicates, mixing, packing.

Each stage takes the documents that its predecessor kept and reads what else it
needs from ``sf_dir``; ``run`` writes every stage's result as Parquet in the
shared scratch folder and reads it again for the next.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F

from cutseg.llm.mixing import Mixture, Weights, production_paths
from cutseg.llm.ngram_join import NgramJoin
from cutseg.llm.packing import packed_documents
from cutseg.llm.toxicity import ToxicityModel
from cutseg.plans.workspace import Workspace

#: Share of the incoming tokens that the mixture keeps.
MIX_SHARE = 0.9


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier rejects go; all labelled texts that it may
    learn from are read from the table, whatever ``docs`` holds."""
    model = ToxicityModel.fit(spark.read.parquet(f"{sf_dir}/documents.parquet"), spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return model.keep(docs)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of texts linked at five words and 0.8, the document with
    the smallest id stays, once."""
    groups = NgramJoin(docs, words=5, num=4, den=5).documents()
    kept = groups.where("doc_id = component_id").select("doc_id").distinct()
    unnamed = docs.where("doc_id is null")
    return docs.join(kept, "doc_id", "left_semi").dropDuplicates(["doc_id"]).select(docs.columns).union(unnamed)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Equal weights at every node, no repeats: large sources give way until
    the mixture holds its share of the tokens."""
    chosen = Mixture(docs, production_paths(docs), Weights(), share=MIX_SHARE, epochs=1).selected
    return docs.join(chosen.select("doc_id").distinct(), "doc_id", "left_semi").select(docs.columns)


def pack_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packed_documents(docs)


STAGES = [("toxicity", drop_toxic), ("near_copies", drop_near_copies), ("mixing", mix_sources), ("packing", pack_sequences)]

#: Training and graph search have no SQL; tests hold each stage against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    ws = Workspace(spark, "pipeline")
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        docs = ws.table(stage(spark, docs, sf_dir), name)
    return docs
