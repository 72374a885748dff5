"""Spectral partition of general graphs, component by component."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, functions as F

from cutseg.functions import kernels as K
from cutseg.operators import block_spectrum
from cutseg.operators.components import connected_components
from cutseg.plans.workspace import Workspace

#: Components of up to this many vertices are decomposed as dense matrices, one
#: in a task; larger ones as edge tables over all tasks.
DENSE_VERTICES = 2000


def knn_edges(vectors: DataFrame, k: int = 8, block: int = 512) -> DataFrame:
    """``src, dst, w``: cosine (not below 0) of each vector with its k nearest,
    symmetric.  Vectors are compared in blocks: each block of rows meets all
    rows once, streamed, with only the best k kept."""
    rows = vectors.where("embedding is not null").select("vec_id", "embedding")
    blocks = rows.withColumn("b", F.pmod(F.xxhash64("vec_id"), F.lit(max(1, 1 + rows.count() // block))).cast("int"))
    packed = blocks.groupBy("b").agg(F.collect_list(F.struct("vec_id", "embedding")).alias("v"))  # about `block` rows each

    def best(frames):
        for f in frames:
            for x, y in zip(f["x"], f["y"]):
                ids = np.array([r["vec_id"] for r in x]), np.array([r["vec_id"] for r in y])
                a, b = (np.array([r["embedding"] for r in z], float) for z in (x, y))
                a, b = (m / np.maximum(np.linalg.norm(m, axis=1, keepdims=True), 1e-300) for m in (a, b))
                cos = a @ b.T
                cos[ids[0][:, None] == ids[1][None]] = -2
                top = np.argsort(-cos, axis=1, kind="stable")[:, :k]
                yield pd.DataFrame({"src": np.repeat(ids[0], top.shape[1]), "dst": ids[1][top].ravel(), "w": np.take_along_axis(cos, top, 1).ravel()})

    from pyspark.sql import Window as W
    pairs = packed.select(F.col("v").alias("x")).crossJoin(packed.select(F.col("v").alias("y")))
    near = pairs.mapInPandas(best, "src long, dst long, w double").withColumn("r", F.row_number().over(W.partitionBy("src").orderBy(F.desc("w"), "dst"))).where(f"r <= {k} and w > 0")
    both = near.select("src", "dst", "w").union(near.select("dst", "src", "w"))
    return both.groupBy("src", "dst").agg(F.max("w").alias("w")).where("src < dst")


def partition_graph(edges: DataFrame, *, form: str = "sym", cut: float = 0.3, k: int | None = None, seed: int = 0, weakest: float = 0.0, dense: int = DENSE_VERTICES) -> DataFrame:
    """``node, component, cluster``: clusters inside each connected component of
    the edges heavier than ``weakest``.

    The number of clusters is that of eigenvalues within the cut, or ``k``.  Of an
    edge given repeatedly, or both ways, the largest weight counts; loops and null
    weights are ignored.  Components over ``dense`` vertices are taken one after
    another, each by all tasks.
    """
    ws = Workspace(edges.sparkSession, "graph")
    once = edges.where((F.col("w") > weakest) & (F.col("src") != F.col("dst"))).groupBy(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst")).agg(F.max("w").alias("w"))
    kept = ws.table(once, "edges")
    comp = connected_components(kept.select("src", "dst"), ws)
    sized = ws.table(comp.join(comp.groupBy("component").agg(F.count("*").alias("n")), "component"), "sized")
    named = kept.join(sized.withColumnRenamed("node", "src"), "src")
    own = named.where(F.col("n") <= dense)

    def run(f: pd.DataFrame) -> pd.DataFrame:
        nodes = np.unique(np.concatenate((f["src"], f["dst"])))
        i, j = np.searchsorted(nodes, f["src"]), np.searchsorted(nodes, f["dst"])
        w = np.zeros((len(nodes), len(nodes)))
        w[i, j] = w[j, i] = f["w"]
        d = w.sum(1)
        lap = np.diag(d) - w if form == "plain" else np.eye(len(nodes)) - w / np.sqrt(d[:, None] * d[None])
        values, vectors = np.linalg.eigh(lap)
        m = min(len(nodes), k or int(K.count_within(values, cut)))
        u = vectors[:, :m]
        if form == "sym":
            u = u / np.maximum(np.linalg.norm(u, axis=1, keepdims=True), 1e-300)
        labels = K.kmeans(u, m, "pp", seed) if m > 1 else np.zeros(len(nodes), int)
        return pd.DataFrame({"node": nodes, "component": int(f["component"].iloc[0]), "cluster": labels})

    found = own.groupBy("component").applyInPandas(run, "node long, component long, cluster int")  # a group has at most `dense` vertices
    for row in sized.where(F.col("n") > dense).select("component").distinct().toLocalIterator():
        c = row["component"]
        part = block_spectrum.clusters(named.where(F.col("component") == c), ws, f"component-{c}", form, cut, k, seed)
        found = found.union(part.select("node", F.lit(c).cast("long"), F.col("cluster").cast("int")))
    return found


def agreement(clusters: DataFrame, truth: DataFrame) -> DataFrame:
    """Purity and normalised mutual information of ``node, component, cluster``
    with ``node, label``; one row."""
    named = clusters.select("node", F.concat_ws(":", "component", "cluster").alias("c")).join(truth.select("node", F.col("label").cast("string").alias("l")), "node")
    cells = named.groupBy("c", "l").agg(F.count("*").alias("n"))
    rows = cells.join(cells.groupBy("c").agg(F.sum("n").alias("nc"), F.max("n").alias("top")), "c").join(cells.groupBy("l").agg(F.sum("n").alias("nl")), "l")
    total = named.agg(F.count("*").alias("t"))
    x = rows.crossJoin(F.broadcast(total))  # one row
    h = lambda c: -(F.col(c) / F.col("t")) * F.log(F.col(c) / F.col("t")) * F.col("n") / F.col(c)
    sums = x.agg(F.sum(F.col("n") / F.col("t") * F.log(F.col("n") * F.col("t") / (F.col("nc") * F.col("nl")))).alias("mi"), F.sum(h("nc")).alias("hc"), F.sum(h("nl")).alias("hl"),
                 F.sum(F.col("top") * F.col("n") / F.col("nc") / F.col("t")).alias("purity"))
    return sums.select("purity", (F.col("mi") / F.sqrt(F.nullif(F.col("hc") * F.col("hl"), F.lit(0.0)))).alias("nmi"))
