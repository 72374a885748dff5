"""Scans of the given tables, corpus splits, and sinks for segmented text."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, functions as F

DEV_SOURCES = ["src14", "src15"]
TEST_SOURCES = ["src16", "src17", "src18", "src19"]
#: Ids of first copies that may be broadcast.
BROADCAST_IDS = 4_000_000


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def first_copies(docs: DataFrame) -> DataFrame:
    """``doc_id``: of exact copies the smallest.  Copies meet by a hash of the
    text, so texts are not sorted."""
    return docs.groupBy(F.sha2("text", 256).alias("h")).agg(F.min("doc_id").alias("doc_id")).select("doc_id")


def documents(spark: SparkSession, sf_dir: str, keep=None) -> DataFrame:
    """Documents with a text, of exact copies that with the smallest id.

    ``keep`` writes a table and returns its scan; then texts are hashed once, and
    not shuffled while the ids may be broadcast (checked)."""
    docs = read(spark, sf_dir, "documents").select("doc_id", "text", "lang", "source").where("text is not null")
    first = first_copies(docs)
    if keep is not None:
        first = keep(first, "first-copies")
        first = F.broadcast(first) if first.count() <= BROADCAST_IDS else first
    return docs.join(first, "doc_id", "left_semi")


def without_passages(docs: DataFrame, passages: list[str]) -> DataFrame:
    """Documents whose ``text`` contains none of the passages; null texts stay.

    The texts are read once whatever the number of passages: places that begin
    like some passage are looked up, and only there passages are compared."""
    held = sorted({p.encode() for p in passages})
    short = [p for p in held if len(p) < 8]
    by_head: dict[int, list[bytes]] = {}
    for p in held:
        if len(p) >= 8:
            by_head.setdefault(int.from_bytes(p[:8], "little"), []).append(p)
    heads, spread = np.array(sorted(by_head), np.uint64), np.uint64(0x9E3779B97F4A7C15)

    def hits(column: pa.Array) -> np.ndarray:
        out, big = np.zeros(len(column), bool), pa.types.is_large_string(column.type)
        _, at, values = column.buffers()
        ends = np.frombuffer(at, np.int64 if big else np.int32)[column.offset:column.offset + len(column) + 1].astype(np.int64)
        raw = memoryview(values if values is not None else b"").cast("B")  # unsigned, as bytes are
        for p in short:
            out |= np.array([p in bytes(raw[a:b]) for a, b in zip(ends, ends[1:])], bool)
        marks = np.zeros(1 << 16, bool)
        marks[(heads * spread) >> np.uint64(48)] = True
        for a in range(int(ends[0]), int(ends[-1]) - 7, 1 << 18) if len(heads) else ():
            part = np.frombuffer(raw[a:min(a + (1 << 18) + 7, int(ends[-1]))], np.uint8)
            words = np.ndarray((len(part) - 7,), "<u8", part, strides=(1,))
            places = np.flatnonzero(marks[(words * spread) >> np.uint64(48)])
            for i in places[np.isin(words[places], heads)].tolist():
                row = int(np.searchsorted(ends, a + i, "right")) - 1
                out[row] |= any(raw[a + i:a + i + len(p)] == p and a + i + len(p) <= ends[row + 1] for p in by_head[int(words[i])])
        return out & column.is_valid().to_numpy(zero_copy_only=False)

    place = docs.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if len(batch):
                yield batch.filter(pa.array(~hits(batch.column(place))))

    return docs.mapInArrow(run, docs.schema) if held else docs


def split(docs: DataFrame, part: str, benchmark: DataFrame | None = None) -> DataFrame:
    """``train``, ``dev`` or ``test`` by source.  Train documents that contain a
    benchmark passage are left out: the passages are few and go to every task."""
    if part == "dev":
        return docs.where(F.col("source").isin(DEV_SOURCES))
    if part == "test":
        return docs.where(F.col("source").isin(TEST_SOURCES))
    train = docs.where(~F.col("source").isin(DEV_SOURCES + TEST_SOURCES))
    if benchmark is None:
        return train
    passages = benchmark.where("text is not null").select("text").distinct().toArrow().column(0).to_pylist()
    return without_passages(train, passages)


def corpus(spark: SparkSession, sf_dir: str, part: str) -> DataFrame:
    return split(documents(spark, sf_dir), part, read(spark, sf_dir, "benchmark") if part == "train" else None)


def page_texts(pages: DataFrame) -> DataFrame:
    """Visible text of pages: no scripts, styles or tags, entities resolved."""
    t = F.col("html")
    for pattern in ("(?is)<script[^>]*>.*?</script>", "(?is)<style[^>]*>.*?</style>", "(?s)<[^>]*>"):
        t = F.regexp_replace(t, pattern, " ")
    for name, mark in (("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "'"), ("&nbsp;", " "), ("&amp;", "&")):
        t = F.replace(t, F.lit(name), F.lit(mark))
    return pages.select("page_id", "url", F.trim(F.regexp_replace(t, "\\s+", " ")).alias("text"))


def write_words(words: DataFrame, path: str, form: str = "parquet") -> None:
    """Segmented sentences as Parquet or JSON partitioned by language, or as
    text with spaces between words."""
    if form == "text":
        words.select(F.array_join("words", " ").alias("value")).write.mode("overwrite").text(path)
    else:
        words.write.mode("overwrite").partitionBy("lang").format(form).save(path)


def read_sentence_files(spark: SparkSession, path: str, form: str = "text") -> DataFrame:
    """Raw texts from text lines, JSON lines or CSV (columns doc_id, text, lang)."""
    if form == "text":
        lines = spark.read.text(path)
        return lines.select(F.xxhash64("value").alias("doc_id"), F.col("value").alias("text"), F.lit("und").alias("lang"))
    schema = "doc_id long, text string, lang string"
    return spark.read.schema(schema).json(path) if form == "json" else spark.read.schema(schema).csv(path, header=True)
