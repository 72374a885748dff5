"""Connected components of an edge table, by alternating star contractions.

Each round rewires every edge towards the smallest vertex that either end has
seen; the edge table stays linear in its first size and no vertex list ever
leaves the executors.  The driver reads one count and one checksum a round.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from cutseg.plans.workspace import Workspace

#: Edges that a join may collect on the driver; sizes guessed from packed files do not bound them.
COLLECTED = 100_000


def _merged(df: DataFrame, rows: int) -> DataFrame:
    return df.hint("merge") if rows > COLLECTED else df


def _larger_to_minimum(edges: DataFrame, rows: int) -> DataFrame:
    both = edges.union(edges.select("v", "u"))
    least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
    return both.join(_merged(least, rows), "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))


def _smaller_to_minimum(edges: DataFrame, rows: int) -> DataFrame:
    down = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).where("u <> v").distinct()
    least = down.groupBy("u").agg(F.min("v").alias("m"))
    moved = down.join(_merged(least, rows), "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return moved.union(least.select("u", F.col("m").alias("v"))).where("u <> v").distinct()


def connected_components(edges: DataFrame, workspace: Workspace, name: str = "components", max_rounds: int = 60) -> DataFrame:
    """Map each vertex of ``edges(u, v)`` to the smallest vertex it can reach.

    Returns ``(node, component)``, one row per vertex that has an edge to some
    other vertex.  Self-loops, repeated edges and rows with a null end are
    ignored; an empty edge table gives an empty result.
    """
    current = workspace.table(
        edges.select(F.col(edges.columns[0]).cast("long").alias("u"), F.col(edges.columns[1]).cast("long").alias("v"))
        .where("u <> v").distinct(), f"{name}-0")
    mark, rows = None, current.count()
    for turn in range(1, max_rounds + 1):
        current = workspace.table(_smaller_to_minimum(_larger_to_minimum(current, rows), rows), f"{name}-{turn}")
        seen = current.agg(F.count("*"), F.bit_xor(F.xxhash64("u", "v"))).first()
        workspace.drop(f"{name}-{turn - 1}")
        if seen == mark or seen[0] == 0:
            break
        mark, rows = seen, seen[0]
    else:
        raise RuntimeError(f"no fixed point after {max_rounds} rounds")
    return current.select(F.col("u").alias("node"), F.col("v").alias("component")).union(
        current.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct())
