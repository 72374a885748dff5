"""Pack tokenised documents into sequences of at most 2048 tokens.

1. One pass over the texts tokenises each document and cuts it into pieces
   [pieces: ids, place and length].
2. The number of pieces of each length - at most 2048 numbers - goes to the
   driver.  Islands of a grouping genetic algorithm evolve random packings of
   these counts, one task each, and pass their best to the next island.
3. Pieces of equal length are numbered without a gap; number and length give a
   piece its sequence and place in the winning packing.  This looks up a table
   of bin contents, whose size depends on the number of lengths only.
"""

from __future__ import annotations

import json
import random
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window as W, functions as F

from cutseg.llm import grouping_ga as ga
from cutseg.llm.fast_bpe import encoder
from cutseg.llm.words import BATCH_BYTES, bounded, small_batches, tidy
from cutseg.plans.workspace import Workspace

CAPACITY = 2048
VOCABULARY = "word_bpe_49k.json"
_PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"
_IDS = "doc_id long, piece int, start long, length long, ids array<int>"


def vocabulary_path(name: str = VOCABULARY) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def _cut(path: str, capacity: int, end_id: int, whole: bool):
    """Pieces of each text with their ids, or with the ids' checksum only."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words = encoder(path)
        for big in batches:
            for batch in bounded(big, 1, BATCH_BYTES // 2):  # bounds the ids that are held
                flat, ends = words.encode(batch.column(1))
                # the end id behind each document
                flat = np.insert(flat, ends, end_id).astype("<u4")
                ends = ends + np.arange(1, len(ends) + 1)
                sizes = np.diff(ends, prepend=0)
                n = -(-sizes // capacity)
                row = np.repeat(np.arange(len(n)), n)
                piece = np.arange(len(row)) - np.repeat(np.cumsum(n) - n, n)
                start = piece * capacity
                length = np.minimum(capacity, sizes[row] - start)
                begin = (ends - sizes)[row] + start
                columns = [batch.column(0).take(pa.array(row)), pa.array(piece.astype(np.int32)), pa.array(start), pa.array(length)]
                if whole:
                    values = pa.ListArray.from_arrays(pa.array(np.append(begin, len(flat)).astype(np.int32)), pa.array(flat.astype(np.int32)))
                    yield pa.RecordBatch.from_arrays([*columns, values], ["doc_id", "piece", "start", "length", "ids"])
                else:
                    raw = flat.tobytes()
                    crc = [zlib.crc32(raw[4 * b:4 * (b + k)]) for b, k in zip(begin.tolist(), length.tolist())]
                    yield pa.RecordBatch.from_arrays([*columns, pa.array(crc, pa.int64())], ["doc_id", "piece", "start", "length", "ids_crc32"])
    return run


def cut_documents(docs: DataFrame, *, path: str | None = None, capacity: int = CAPACITY, end_id: int = 0, with_ids: bool = True, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Tokenise and cut: a row for each piece.

    A null or empty text is the end id alone; only documents longer than
    ``capacity`` are cut.  Repeated rows give repeated pieces.
    """
    small_batches(docs.sparkSession)
    rows = docs.select(docs[id_col].cast("long").alias("doc_id"), docs[text_col].cast("string").alias("text"))
    return rows.mapInArrow(tidy(_cut(path or vocabulary_path(), capacity, end_id, with_ids)), _IDS if with_ids else _PIECES)


def evolve_islands(spark, counts: dict[int, int], capacity: int = CAPACITY, *, islands: int = 4, epochs: int = 2, seed: int = 7) -> ga.Packing:
    """The best packing of ``counts`` that the islands find.

    Islands start from random packings; between epochs each gets the elite of
    the one before it in the ring.  In the last epoch one island also takes in
    the best-fit packing, so the result is never worse than that.  Epochs end
    early when an elite meets the lower bound.  Island ``i`` of epoch ``e``
    depends on seed, i and e alone, so a task that runs again gives the same
    individual.
    """
    if not counts:
        return {}
    elites: list[ga.Packing] = []
    for epoch in range(epochs):
        pools = [[elites[i], elites[i - 1]] if elites else [] for i in range(islands)]
        if epoch == epochs - 1:
            pools[0].append(ga.best_fit({}, counts, capacity))
        state = spark.sparkContext.broadcast((counts, [[list(p.items()) for p in pool] for pool in pools]))
        rows = spark.range(0, islands, 1, islands).mapInArrow(_island(state, capacity, epoch, seed), "island long, packing string").collect()
        elites = [_packing(json.loads(r["packing"])) for r in sorted(rows, key=lambda r: r["island"])]
        if min(map(ga.bins_of, elites)) <= ga.lower_bound(counts, capacity):
            break
    return max(elites, key=lambda p: ga.fitness(p, capacity))


def _packing(items) -> ga.Packing:
    return {tuple(content): n for content, n in items}


def _island(state, capacity: int, epoch: int, seed: int):
    """The elite of each island of a partition, as JSON."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts, pools = state.value
        for batch in batches:
            for i in batch.column(0).to_pylist():
                rng = random.Random(seed * 1_000_003 + epoch * 1009 + i)
                found = ga.evolve(counts, capacity, [_packing(p) for p in pools[i]], rng)
                yield pa.RecordBatch.from_pydict({"island": [i], "packing": [json.dumps(list(found.items()))]})
    return run


def _places(packing: ga.Packing) -> dict[str, np.ndarray]:
    """For each bin content and item: the numbers of pieces of that length that
    go there, as ``length << 40 | first number``, with first sequence and offset."""
    key, first, sequence, offset, used = [], 0, [], [], {}
    for content in sorted(packing, reverse=True):
        at = 0
        for size in content:
            key.append(size << 40 | used.get(size, 0))
            sequence.append(first)
            offset.append(at)
            used[size] = used.get(size, 0) + packing[content]
            at += size
        first += packing[content]
    order = np.argsort(np.array(key, np.int64), kind="stable")
    return {"key": np.array(key, np.int64)[order], "sequence": np.array(sequence, np.int64)[order], "offset": np.array(offset, np.int64)[order]}


def _place(shared):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = shared.value
        for batch in batches:
            number = batch.column(batch.schema.get_field_index("number")).to_numpy(zero_copy_only=False)
            wanted = (batch.column(batch.schema.get_field_index("length")).to_numpy(zero_copy_only=False) << 40) | number
            i = np.searchsorted(table["key"], wanted, side="right") - 1
            sequence = table["sequence"][i] + (wanted - table["key"][i])
            keep = [c for c in batch.schema.names if c != "number"]
            yield pa.RecordBatch.from_arrays([*(batch.column(batch.schema.get_field_index(c)) for c in keep), pa.array(sequence), pa.array(table["offset"][i])], [*keep, "sequence_id", "offset"])
    return run


def pack(pieces: DataFrame, capacity: int = CAPACITY, *, islands: int = 4, epochs: int = 2, seed: int = 7) -> DataFrame:
    """Add ``sequence_id`` and ``offset`` to rows with a ``length`` column.

    ``pieces`` should be a written table; it is read twice.  Other columns are
    kept as they are; no order among equal rows is promised.
    """
    spark = pieces.sparkSession
    counts = {r["length"]: r["n"] for r in pieces.groupBy("length").agg(F.count("*").alias("n")).collect()}  # at most `capacity` rows
    packing = evolve_islands(spark, counts, capacity, islands=islands, epochs=epochs, seed=seed)
    buckets = max(8, sum(counts.values()) // 2_000_000)
    columns = pieces.columns
    dealt = pieces.withColumn("__bucket", F.pmod(F.xxhash64(*columns), F.lit(buckets)).cast("int"))
    sizes = dealt.groupBy("length", "__bucket").agg(F.count("*").alias("__n"))
    before = W.partitionBy("length").orderBy("__bucket").rowsBetween(W.unboundedPreceding, -1)
    starts = sizes.select("length", "__bucket", F.coalesce(F.sum("__n").over(before), F.lit(0)).alias("__start"))
    inside = W.partitionBy("length", "__bucket").orderBy(*[c for c in columns if c != "length"])
    numbered = (dealt.withColumn("__row", F.row_number().over(inside) - 1).join(starts, ["length", "__bucket"])
                .select(*columns, (F.col("__start") + F.col("__row")).cast("long").alias("number")))
    shared = spark.sparkContext.broadcast(_places(packing))
    kinds = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in pieces.schema)
    return numbered.mapInArrow(tidy(_place(shared)), f"{kinds}, sequence_id long, offset long")


def sequences(placed: DataFrame, pieces: DataFrame) -> DataFrame:
    """The packed sequences themselves: ``sequence_id, ids``, from placed pieces
    and pieces with ids (of unique documents).  A sequence has at most
    ``capacity`` ids, which bounds each group."""
    rows = placed.select("doc_id", "piece", "sequence_id", "offset").join(pieces.select("doc_id", "piece", "ids"), ["doc_id", "piece"])
    parts = F.array_sort(F.collect_list(F.struct("offset", "ids")))
    return rows.groupBy("sequence_id").agg(F.flatten(F.transform(parts, lambda p: p["ids"])).alias("ids"))


def packed_documents(docs: DataFrame, **options) -> DataFrame:
    """``doc_id, piece, start, length, ids_crc32, sequence_id, offset``."""
    ws = Workspace(docs.sparkSession, "packing")
    return pack(ws.table(cut_documents(docs, with_ids=False), "pieces"), **options)


def op5_pack_ga(spark, sf_dir: str) -> DataFrame:
    return packed_documents(spark.read.parquet(f"{sf_dir}/documents.parquet"))
