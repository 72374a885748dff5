"""Structured Streaming forms: segmenting with a static model, running counts,
event windows and sessions."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, functions as F

from cutseg.functions import units
from cutseg.operators.corpus import NgramModel, ngram_counts
from cutseg.operators.segment import SegmentConfig, _collected, bands_of, by_language, split_sentences
from cutseg.plans.workspace import Workspace


def segment_stream(docs: DataFrame, model: NgramModel, cfg: SegmentConfig, *, sets: DataFrame | None = None, words: DataFrame | None = None, singles: DataFrame | None = None) -> DataFrame:
    """Segment a stream of documents with a model, and sets or word lists, that
    stay as they are."""
    shared = docs.sparkSession.sparkContext.broadcast(_collected(model, cfg, sets, words, singles))

    def run(frames):
        weights = by_language(cfg, shared)
        for f in frames:
            place = {key: j for j, key in enumerate(dict.fromkeys(zip(f["lang"], f["s"])))}
            done = split_sentences(bands_of([lang for lang, _ in place], [s for _, s in place], weights), cfg)
            each = [done[place[key]] for key in zip(f["lang"], f["s"])]
            yield pd.DataFrame({"sent_id": f["sent_id"], "lang": f["lang"], "k": [k for k, _, _ in each], "words": [w for _, _, w in each]})

    # a micro-batch is one file: its sentences go to all cores, equal ones to one task
    tasks = 2 * docs.sparkSession.sparkContext.defaultParallelism
    sents = units.sentences(docs, keep=("lang",)).select("sent_id", "lang", "s").repartition(tasks, "lang", "s")
    return sents.mapInPandas(run, "sent_id string, lang string, k int, words array<string>")


class RunningCounts:
    """Bigram counts of all micro-batches so far, in a table and not in state.

    Each batch writes counts under its own number, so a batch that runs again
    overwrites itself; ``total`` adds them up.
    """

    def __init__(self, spark: SparkSession, n: int = 2):
        self.ws, self.n, self.spark = Workspace(spark, "running-counts"), n, spark

    def update(self, batch: DataFrame, number: int) -> None:
        ngram_counts(units.sentences(batch, keep=("lang",)), self.n).write.mode("overwrite").parquet(f"{self.ws.root}/batch={number}")

    def total(self) -> DataFrame:
        rows = self.spark.read.schema("lang string, g string, cnt long, batch long").parquet(self.ws.root)
        return rows.groupBy("lang", "g").agg(F.sum("cnt").alias("cnt"))


def document_stream(spark: SparkSession, path: str) -> DataFrame:
    """New Parquet files of documents, one a micro-batch."""
    schema = "doc_id long, text string, lang string, source string"
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(path)


def windowed_counts(events: DataFrame, width: str, slide: str | None = None, late: str | None = None) -> DataFrame:
    """Events of each type in tumbling or sliding windows."""
    e = events.withWatermark("ts", late) if late else events
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    return e.groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n"), F.sum("value").alias("total")).select(
        F.col("w.start").alias("start"), F.col("w.end").alias("end"), "event_type", "n", "total")


def sessions(events: DataFrame, gap: str = "12 hours", late: str | None = None) -> DataFrame:
    e = events.withWatermark("ts", late) if late else events
    return e.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n")).select(
        "user_id", F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n")


def run_to_end(stream: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Drive a stream over all that is there now; the result as a table."""
    spark = stream.sparkSession
    ws = Workspace(spark, f"stream-{name}")
    if mode == "append":
        q = (stream.writeStream.format("parquet").option("path", f"{ws.root}/out").option("checkpointLocation", f"{ws.root}/log").outputMode(mode).trigger(availableNow=True).start())
        q.awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{ws.root}/out")

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{ws.root}/out")  # complete mode: the last batch is the result

    stream.writeStream.foreachBatch(keep).option("checkpointLocation", f"{ws.root}/log").outputMode(mode).trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{ws.root}/out")
