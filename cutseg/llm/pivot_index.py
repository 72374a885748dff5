"""Near-duplicate vectors through an index of pivot permutations.

A vector is described by its nearest reference points (pivots), taken from a
bounded sample of the vectors themselves and spread apart, so that a large group
of near copies holds few of them.  Vectors of one nearest pivot (a cell) are
compared all with all, in blocks that give counts and a spanning forest and no
row for each pair.  Across cells, inverted lists are kept for pairs of pivots,
which makes them short: two vectors meet in a list if they share both pivots.
Lists are joined, the pivots that both vectors share are counted, and a pair with
enough of them is verified once.  All cosines are in double precision.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, functions as F

from cutseg.operators.components import connected_components
from cutseg.plans.workspace import Workspace

#: Reference points (the sample's bound), nearest ones kept, and shared ones that make a candidate.
PIVOTS, NEAREST, SHARED = 1024, 10, 3
#: Vectors among which pivots are looked for, and the cosine that two pivots stay below.
SAMPLE, SPREAD = 4096, 0.8
#: Vectors of a cell that one block holds.
BLOCK = 512
#: Sizes are guessed from packed files, far too low for rows that grow with the table:
#: such joins are merged, so that nothing of them is collected on the driver.
MERGED = "merge"
_DESCRIBED = "vec_id long, label string, sig binary, near array<smallint>, home smallint"


def _array(v) -> np.ndarray | None:
    """The vector in double precision; None if no cosine is defined."""
    if v is None or not len(v) or any(x is None for x in v):
        return None
    x = np.asarray(v, np.float64)
    return x if np.isfinite(x).all() and x.any() else None


def unit(x: np.ndarray) -> np.ndarray:
    x = x / np.abs(x).max()  # squares of very small or large numbers stay finite
    return x / np.sqrt(x @ x)


def _describe(shared):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pivots = shared.value
        for batch in batches:
            labels = batch.column(1).to_pylist()
            vectors = [_array(v) if label is not None and i is not None else None
                       for i, label, v in zip(batch.column(0).to_pylist(), labels, batch.column(2).to_pylist())]
            near, sigs, homes = [], [], {}
            good = [k for k, v in enumerate(vectors) if v is not None]
            lists: dict[int, list[int]] = {}
            width = pivots.shape[1]
            for i in range(0, len(good), 1024):
                part = good[i:i + 1024]
                x = np.zeros((len(part), width))
                for r, k in enumerate(part):
                    u = unit(vectors[k])[:width]
                    x[r, :len(u)] = u
                score = x @ pivots.T
                top = np.argsort(-score, axis=1, kind="stable")[:, :NEAREST]
                lists |= {k: sorted(t) for k, t in zip(part, top.tolist())}
                homes |= dict(zip(part, top[:, 0].tolist()))
            for k, v in enumerate(vectors):
                near.append(lists.get(k))
                sigs.append(None if v is None else xxhash.xxh3_128_digest(v.tobytes()))
            home = pa.array([homes.get(k) for k in range(len(vectors))], pa.int16())
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(sigs, pa.binary()), pa.array(near, pa.list_(pa.int16())), home],
                                             ["vec_id", "label", "sig", "near", "home"])
    return run


def _verify(least: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            a, b, cos = batch.column(0), batch.column(1), []
            for x, y in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist()):
                x, y = _array(x), _array(y)
                cos.append(float(unit(x) @ unit(y)) if x is not None and y is not None and len(x) == len(y) else -2.0)
            cos = np.array(cos)
            keep = pa.array(cos >= least)
            yield pa.RecordBatch.from_arrays([a.filter(keep), b.filter(keep), pa.array(cos).filter(keep)], ["a", "b", "cosine"])
    return run


def _within(least: float):
    """Links inside one block of a cell, or between two: the copies that each
    vector is linked with, and the smallest vector that it reaches there."""
    def run(f: pd.DataFrame) -> pd.DataFrame:
        f = f.sort_values("rep", ignore_index=True)
        x = np.array([unit(np.asarray(v, np.float64)) for v in f["v"]])
        link = x @ x.T >= least
        np.fill_diagonal(link, False)
        if f["i"].iloc[0] != f["j"].iloc[0]:
            block = f["block"].to_numpy()
            link &= block[:, None] != block[None]
        others, first = link @ f["copies"].to_numpy(np.int64), np.arange(len(f))
        while True:
            least_seen = np.minimum(first, np.where(link, first[None], len(f)).min(1))
            if (least_seen == first).all():
                break
            first = least_seen
        out = pd.DataFrame({"a": f["rep"], "b": f["rep"].to_numpy()[first], "others": others})
        return out[others > 0]
    return run


class PivotIndex:
    """Links of equal-label vectors with cosine of at least ``least``.

    Null, zero and non-finite vectors, vectors with null parts, and rows with a
    null label or id link with nothing; vectors of different lengths do not link
    either.  Equal vectors are one class and are indexed once.  An empty table
    gives empty results.
    """

    def __init__(self, vectors: DataFrame, least: float = 0.93, id_col: str = "vec_id", vector_col: str = "embedding", label_col: str = "label"):
        spark = vectors.sparkSession
        self.ws = ws = Workspace(spark, "pivot-index")
        rows = vectors.select(vectors[id_col].cast("long").alias("vec_id"), vectors[label_col].cast("string").alias("label"), vectors[vector_col].cast("array<double>").alias("v"))
        shared = spark.sparkContext.broadcast(self._sample(rows))
        self.described = ws.table(rows.mapInArrow(_describe(shared), _DESCRIBED), "described")
        self.classes = ws.table(self.described.where("sig is not null").groupBy("label", "sig").agg(
            F.min("vec_id").alias("rep"), F.count("*").alias("copies"), F.first("near").alias("near"), F.first("home").alias("home")), "classes")
        pairs = ws.table(self._candidates(), "pairs")
        own = rows.select("vec_id", "v")
        ids = self.classes.select(F.col("rep").alias("vec_id"))
        needed = own.join(ids.hint(MERGED), "vec_id", "left_semi").dropDuplicates(["vec_id"])
        checked = (pairs.join(needed.select(F.col("vec_id").alias("a"), F.col("v").alias("va")).hint(MERGED), "a")
                   .join(needed.select(F.col("vec_id").alias("b"), F.col("v").alias("vb")).hint(MERGED), "b").select("a", "b", "va", "vb"))
        #: Links between class representatives of different cells, with their cosine.
        self.links = ws.table(checked.mapInArrow(_verify(least), "a long, b long, cosine double"), "links")
        #: Links inside cells, as linked copies of a and the smallest b it reaches in its blocks.
        self.cells = ws.table(self._cells(needed, least), "cells")
        self.component = connected_components(self.links.select("a", "b").union(self.cells.select("a", "b")), ws)

    def _sample(self, rows: DataFrame) -> np.ndarray:
        """At most ``PIVOTS`` vectors, no two within ``SPREAD``: in the order of
        the hash of the id, those that are far from all before them.

        The first ids are found among those below a hash that twice as many
        should be below; vectors join these ids only, so what reaches the driver
        does not grow with the table."""
        ids = rows.where("v is not null and label is not null").select(F.xxhash64("vec_id").alias("order"), "vec_id")
        n = ids.count()
        below = ids.where(F.col("order") < -2**63 + min(2**64 - 1, 2**65 * SAMPLE // max(1, n))) if n > 4 * SAMPLE else ids
        first = lambda some: self.ws.table(some.orderBy("order", "vec_id").limit(SAMPLE), "first")
        held = first(below)
        if held.count() < min(n, SAMPLE):
            held = first(ids)
        vectors = rows.where("v is not null and label is not null").join(F.broadcast(held.select("vec_id").distinct()), "vec_id", "left_semi")
        picked = sorted(vectors.withColumn("order", F.xxhash64("vec_id")).collect(), key=lambda r: (r["order"], r["vec_id"]))[:SAMPLE]
        vectors = [unit(x) for x in (_array(r["v"]) for r in picked) if x is not None]
        width = max((len(v) for v in vectors), default=1)
        pivots, n = np.zeros((PIVOTS, width)), 0
        for v in vectors:
            if n < PIVOTS and (pivots[:n, :len(v)] @ v < SPREAD).all():
                pivots[n, :len(v)], n = v, n + 1
        return pivots[:n]

    def _cells(self, needed: DataFrame, least: float) -> DataFrame:
        """Each pair of blocks of a cell is one group, so no group grows with a cell."""
        cell = ["label", "home", "width"]
        rows = self.classes.select("label", "home", "rep", "copies").join(needed.select(F.col("vec_id").alias("rep"), "v").hint(MERGED), "rep").withColumn("width", F.size("v"))
        blocks = rows.groupBy(cell).agg(F.count("*").alias("size")).where("size > 1").withColumn("blocks", F.ceil(F.col("size") / BLOCK))
        dealt = (rows.join(F.broadcast(blocks), cell).withColumn("block", F.pmod(F.xxhash64("rep"), F.col("blocks")))
                 .withColumn("other", F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1)))  # at most labels x PIVOTS x widths cells
                 .withColumns({"i": F.least("block", "other"), "j": F.greatest("block", "other")}))
        return dealt.groupBy(*cell, "i", "j").applyInPandas(_within(least), "a long, b long, others long")

    def _candidates(self) -> DataFrame:
        places = F.sequence(F.lit(0), F.size("near") - 2)
        keys = F.flatten(F.transform(places, lambda i: F.transform(
            F.slice("near", i + 2, F.size("near")), lambda q: F.element_at("near", i + 1).cast("int") * PIVOTS + q)))
        # with fewer than two pivots there is one cell and nothing across
        keys = F.when(F.size("near") >= 2, keys)
        lists = self.classes.select("label", "rep", "near", "home", F.explode(keys).alias("key"))
        x, y = lists.alias("x"), lists.alias("y")
        both = F.array_intersect("x.near", "y.near")
        enough = F.size(both) >= F.least(F.lit(SHARED), F.size("x.near"), F.size("y.near"))
        # of all lists in which a pair meets, only the first gives it out
        first = F.element_at(both, 1).cast("int") * PIVOTS + F.element_at(both, 2)
        met = (F.col("x.label") == F.col("y.label")) & (F.col("x.key") == F.col("y.key")) & (F.col("x.home") < F.col("y.home"))
        return x.join(y.hint(MERGED), met & enough & (F.col("x.key") == first)).select(F.col("x.rep").alias("a"), F.col("y.rep").alias("b"))

    def vectors(self) -> DataFrame:
        """``vec_id, n_links, component_id, kept``: one row per input row."""
        sizes = self.classes.select(F.col("rep").alias("b"), "copies")
        both = self.links.select("a", "b").union(self.links.select("b", "a"))
        linked = both.join(sizes.hint(MERGED), "b").select("a", F.col("copies").alias("others")).union(self.cells.select("a", "others")).groupBy("a").agg(F.sum("others").alias("others"))
        named = (self.classes.join(linked.hint(MERGED), F.col("rep") == F.col("a"), "left").join(self.component.hint(MERGED), F.col("rep") == F.col("node"), "left")
                 .select(F.col("label").alias("l"), F.col("sig").alias("s"), (F.col("copies") - 1 + F.coalesce("others", F.lit(0))).alias("n"), F.coalesce("component", "rep").alias("c")))
        out = self.described.join(named.hint(MERGED), (F.col("label") == F.col("l")) & (F.col("sig") == F.col("s")), "left")
        return out.select("vec_id", F.coalesce("n", F.lit(0)).cast("long").alias("n_links"), F.coalesce("c", "vec_id").alias("component_id")).withColumn(
            "kept", F.col("vec_id") == F.col("component_id"))


def op2_pivot_permutation(spark, sf_dir: str) -> DataFrame:
    return PivotIndex(spark.read.parquet(f"{sf_dir}/embeddings.parquet")).vectors()


#: Quadratic, for the driver's comparison at small scale only.
OP2_SQL = """
with recursive v as (select vec_id, label, embedding::double[] as e from embeddings),
ok as (select vec_id, label, e, sqrt(list_dot_product(e, e)) as n from v where label is not null and e is not null and list_dot_product(e, e) > 0),
links as (select a.vec_id as a, b.vec_id as b from ok a join ok b on a.label = b.label and a.vec_id <> b.vec_id
  where list_dot_product(a.e, b.e) / (a.n * b.n) >= 0.93),
reach(a, b) as (select a, b from links union select r.a, l.b from reach r join links l on r.b = l.a),
least as (select a, min(b) as m from reach group by a),
degree as (select a, count(*) as n from links group by a)
select v.vec_id, coalesce(d.n, 0)::bigint as n_links, least(v.vec_id, coalesce(l.m, v.vec_id)) as component_id,
  v.vec_id = least(v.vec_id, coalesce(l.m, v.vec_id)) as kept
from v left join least l on l.a = v.vec_id left join degree d on d.a = v.vec_id"""
