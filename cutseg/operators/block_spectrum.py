"""First eigenvectors of a Laplacian that no single task can hold.

The Laplacian is an edge table with its diagonal as loops, a block of vectors is
a table of one row per vertex.  A product of both is one join and one sum by
vertex.  Polynomials of the Laplacian damp the eigenvalues above those wanted,
and small matrices (as wide as the block) turn the block to eigenvectors; the
driver sees only these.  The block widens until it holds eigenvalues beyond the
cut, so their number within the cut is that of the whole graph.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, functions as F

from cutseg.functions import kernels as K
from cutseg.plans.workspace import Workspace

#: Columns of the first block, columns kept beyond those wanted, products in a round, rounds at most.
WIDTH, SPARE, DEGREE, ROUNDS = 16, 6, 8, 200
#: Residual of a wanted vector, as a part of the largest eigenvalue possible.
TOLERANCE = 1e-4


def entries(edges: DataFrame, form: str) -> DataFrame:
    """``src, dst, c``: all entries that are not 0 of the Laplacian of
    ``src, dst, w`` (each edge once), the diagonal's too."""
    both = edges.select("src", "dst", "w").union(edges.select("dst", "src", "w"))
    degree = both.groupBy("src").agg(F.sum("w").alias("d"))
    if form == "plain":
        return both.select("src", "dst", -F.col("w")).union(degree.select("src", "src", "d")).toDF("src", "dst", "c")
    scaled = both.join(degree, "src").join(degree.toDF("dst", "e"), "dst")
    return scaled.select("src", "dst", -F.col("w") / F.sqrt(F.col("d") * F.col("e"))).union(degree.select("src", "src", F.lit(1.0))).toDF("src", "dst", "c")


def _step(lap: DataFrame, state: DataFrame, width: int, by: float, own: float, before: float) -> DataFrame:
    """Columns a become ``by`` x Laplacian x a + ``own`` x a + ``before`` x b, columns b what a was."""
    loop = F.col("src") == F.col("dst")
    a, b = ([F.col(f"{x}{j}") for j in range(width)] for x in "ab")
    new = [F.sum(by * F.col("c") * x + F.when(loop, own * x + before * y).otherwise(0.0)).alias(f"a{j}") for j, (x, y) in enumerate(zip(a, b))]
    old = [F.sum(F.when(loop, x).otherwise(0.0)).alias(f"b{j}") for j, x in enumerate(a)]
    return lap.join(state, F.col("dst") == F.col("node")).groupBy("src").agg(*new, *old).withColumnRenamed("src", "node")


def _filtered(lap: DataFrame, state: DataFrame, width: int, low: float, top: float) -> DataFrame:
    """Damp eigenvalues from ``low`` to ``top`` against those below, then multiply
    once more: a is the Laplacian times b."""
    half, mid = (top - low) / 2, (top + low) / 2
    first = scale = -half / mid
    state = _step(lap, state, width, scale / half, -mid * scale / half, 0.0)
    for _ in range(DEGREE - 1):
        follow = 1 / (2 / first - scale)
        state = _step(lap, state, width, 2 * follow / half, -2 * mid * follow / half, -scale * follow)
        scale = follow
    return _step(lap, state, width, 1.0, 0.0, 0.0)


def _products(state: DataFrame, width: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The matrices b'b, b'a and a'a; sums of each partition are added by entry."""
    ca, cb = ([f"{x}{j}" for j in range(width)] for x in "ab")

    def run(frames):
        g, h, r = np.zeros((3, width, width))
        for f in frames:
            x, y = f[cb].to_numpy(float), f[ca].to_numpy(float)
            g, h, r = g + x.T @ x, h + x.T @ y, r + y.T @ y
        i, j = np.indices(g.shape)
        yield pd.DataFrame({"i": i.ravel(), "j": j.ravel(), "g": g.ravel(), "h": h.ravel(), "r": r.ravel()})

    sums = state.mapInPandas(run, "i int, j int, g double, h double, r double").groupBy("i", "j").agg(F.sum("g").alias("g"), F.sum("h").alias("h"), F.sum("r").alias("r"))
    f = sums.toPandas().sort_values(["i", "j"])  # width x width rows
    return tuple((m + m.T) / 2 for m in (f[c].to_numpy().reshape(width, width) for c in "ghr"))


def _turned(state: DataFrame, turn: np.ndarray, width: int) -> DataFrame:
    """Columns b times ``turn``, as columns a; columns b are 0."""
    cb = [f"b{j}" for j in range(turn.shape[0])]
    n = turn.shape[1]

    def run(frames):
        for f in frames:
            x = np.zeros((len(f), 2 * n))
            x[:, :n] = f[cb].to_numpy(float) @ turn
            out = pd.DataFrame(x, columns=[f"{c}{j}" for c in "ab" for j in range(n)])
            out.insert(0, "node", f["node"].to_numpy())
            yield out

    return state.mapInPandas(run, "node long, " + ", ".join(f"{c}{j} double" for c in "ab" for j in range(n)))


def _widened(state: DataFrame, have: int, width: int, seed: int) -> DataFrame:
    """Columns drawn from hashes of the vertex up to the width."""
    new = {f"a{j}": F.xxhash64("node", F.lit(seed), F.lit(j)) / F.lit(2.0**63) for j in range(have, width)}
    return state.withColumns(new | {f"b{j}": F.lit(0.0) for j in range(have, width)}) if new else state


def _ritz(g: np.ndarray, h: np.ndarray, r: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Values, the matrix that turns the block to their vectors, and residuals."""
    scale = 1 / np.sqrt(np.maximum(np.diag(g), 1e-300))
    size, base = np.linalg.eigh(g * scale * scale[:, None])
    sound = size > 1e-11 * size[-1]
    base = scale[:, None] * base[:, sound] / np.sqrt(size[sound])
    values, own = np.linalg.eigh(base.T @ h @ base)
    turn = base @ own
    squares = np.einsum("ij,ik,kj->j", turn, r, turn) - values**2
    return values, turn, np.sqrt(np.maximum(squares, 0))


def first_eigenvectors(edges: DataFrame, ws: Workspace, name: str, form: str, cut: float, k: int | None = None, seed: int = 0) -> tuple[int, DataFrame]:
    """How many eigenvalues are within the cut (or ``k``), and the table
    ``node, a0, a1, ...`` of that many first eigenvectors.

    ``edges`` (``src, dst, w``, each edge once, weights above 0) hold one
    connected component.  A count is taken when each vector within the cut has a
    residual below the tolerance and the next value lies beyond the cut by more
    than its own; eigenvalues closer to the cut than that may fall on either side.
    """
    lap = ws.table(entries(edges, form), f"{name}-laplacian")
    n, largest = lap.where("src = dst").agg(F.count("*"), F.max("c")).first()
    top = (2.0 if form == "sym" else 2 * largest) * (1 + 1e-9)
    width, low = min(n, max(WIDTH, (k or 0) + SPARE)), top / 2
    state = _widened(lap.where("src = dst").select(F.col("src").alias("node")), 0, width, seed)
    for turn_no in range(ROUNDS):
        state = ws.table(_filtered(lap, state, width, low, top), f"{name}-{turn_no}")
        values, turn, residual = _ritz(*_products(state, width))
        wanted = min(n, k or int(K.count_within(values, cut)))
        spare = max(SPARE, wanted // 2)
        wide = min(n, width * 2 if wanted + spare > width else width)
        beyond = wanted == len(values) == n or (wanted < len(values) and (k is not None or values[wanted] - residual[wanted] > cut))
        if wide == width and wanted <= len(values) and beyond and (residual[:wanted] <= TOLERANCE * top).all():
            return wanted, _turned(state, turn[:, :wanted], wanted)
        ws.drop(f"{name}-{turn_no - 1}")
        state = _widened(_turned(state, turn, width), len(values), wide, seed + turn_no + 1)
        width, low = wide, float(np.clip(values[-1], 1e-6 * top, 0.9 * top))
    raise RuntimeError(f"no {wanted} eigenvectors after {ROUNDS} rounds")


def clusters(edges: DataFrame, ws: Workspace, name: str, form: str, cut: float, k: int | None = None, seed: int = 0, starts: int = 3) -> DataFrame:
    """``node, cluster`` of one connected component, by k-means over the rows of
    its first eigenvectors; the best of some starts."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    count, block = first_eigenvectors(edges, ws, name, form, cut, k, seed)
    if count == 1:
        return block.select("node", F.lit(0).alias("cluster"))
    rows = block.select("node", F.array(*[f"a{j}" for j in range(count)]).alias("u"))
    if form == "sym":
        norm = F.sqrt(F.aggregate("u", F.lit(0.0), lambda s, x: s + x * x))
        rows = rows.withColumn("u", F.transform("u", lambda x: x / F.greatest(norm, F.lit(1e-300))))
    rows = ws.table(rows, f"{name}-rows").withColumn("features", array_to_vector("u"))
    models = [KMeans(k=count, seed=seed + s, maxIter=100, tol=1e-9).fit(rows) for s in range(starts)]
    best = min(models, key=lambda m: m.summary.trainingCost)
    return best.transform(rows).select("node", F.col("prediction").alias("cluster"))
