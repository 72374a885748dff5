"""Placement of rows on shards by a weighted hash tree (regions, racks, shards).

At each level a row draws ``ln(u) / weight`` for every child, u being a hash of
the row's key and the child's name, and goes down into the largest draw.  A
child's draw depends on nothing but the key, its name and its own weight, so a
change of weights moves rows only into children that gained and out of those
that lost, and only on the path of changed subtrees.

All of it is built-in SQL expressions: one hash and one logarithm for each
child on the way down.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window as W, functions as F


@dataclass(frozen=True)
class Leaf:
    """A shard; its number must be unique in the tree."""

    shard: int
    weight: float = 1.0

    def mass(self) -> float:
        return self.weight


@dataclass(frozen=True)
class Branch:
    """A region or a rack; its weight is that of all shards below."""

    name: str
    children: tuple

    def mass(self) -> float:
        return sum(c.mass() for c in self.children)


def uniform_tree(regions: int, racks: int, shards: int) -> Branch:
    """A tree of equal shards, numbered from 0 in depth-first order."""
    number = iter(range(regions * racks * shards))
    return Branch("root", tuple(
        Branch(f"region{r}", tuple(
            Branch(f"region{r}/rack{k}", tuple(Leaf(next(number)) for _ in range(shards))) for k in range(racks))) for r in range(regions)))


def with_region(tree: Branch, name: str, shards: tuple[Leaf, ...]) -> Branch:
    """The tree with one more region of a single rack.

    Only the draws at the root see a change, so rows move only into the new
    region's shards.
    """
    return Branch(tree.name, (*tree.children, Branch(name, (Branch(f"{name}/rack0", shards),))))


def _draw(key: Column, name: str, weight: float) -> Column:
    u = (F.shiftrightunsigned(F.xxhash64(key, F.lit(name)), 11).cast("double") + 0.5) / float(2**53)
    return F.log(u) / F.lit(float(weight))


def _best(key: Column, level: int, children: tuple) -> Column:
    """Index of the child with the largest draw; on equal draws the later one."""
    live = [(i, c) for i, c in enumerate(children) if c.mass() > 0]
    if len(live) == 1:
        return F.lit(live[0][0])
    draws = [F.struct(_draw(key, f"{level}:{c.shard if isinstance(c, Leaf) else c.name}", c.mass()).alias("d"), F.lit(i).alias("i")) for i, c in live]
    return F.array_max(F.array(*draws))["i"]


def place(df: DataFrame, key: Column, tree: Branch, out: str) -> DataFrame:
    """Add the shard of each row as int column ``out``.

    A null key is a key like any other.  Subtrees of weight 0 get no rows; a
    tree without any weight is an error.
    """
    if tree.mass() <= 0:
        raise ValueError("the tree has no weight")
    level, nodes, at = 0, {0: tree}, None
    while any(isinstance(n, Branch) for n in nodes.values()):
        step, below, first = None, {}, 0
        for number, node in nodes.items():
            if isinstance(node, Leaf):
                children, pick = (node,), F.lit(0)
            else:
                children, pick = node.children, _best(key, level, node.children) if node.mass() > 0 else F.lit(0)
            pick = pick + first
            if at is None:
                step = pick
            else:
                step = F.when(F.col(at) == number, pick) if step is None else step.when(F.col(at) == number, pick)
            below |= {first + i: c for i, c in enumerate(children)}
            first += len(children)
        name = f"__{out}_{level}"
        df = df.withColumn(name, step)
        level, nodes, at = level + 1, below, name
    shards = F.array(*[F.lit(nodes[i].shard) for i in range(len(nodes))])
    df = df.withColumn(out, F.element_at(shards, F.col(at) + 1).cast("int"))
    return df.drop(*[f"__{out}_{i}" for i in range(level)])


def gapless_slots(df: DataFrame, group: str, key: str, ties: list[str], buckets: int = 256) -> DataFrame:
    """Number the rows of each ``group`` from 0 without a gap, as long ``slot``.

    Rows are dealt to hash buckets of ``key``, numbered inside a bucket, and
    shifted by the sizes of the buckets before, so no task sees a whole group.
    """
    df = df.withColumn("__bucket", F.pmod(F.xxhash64(F.col(key), F.lit("slot")), F.lit(buckets)).cast("int"))
    sizes = df.groupBy(group, "__bucket").agg(F.count("*").alias("__n"))
    before = W.partitionBy(group).orderBy("__bucket").rowsBetween(W.unboundedPreceding, -1)
    starts = sizes.select(group, "__bucket", F.coalesce(F.sum("__n").over(before), F.lit(0)).alias("__start"))
    inside = W.partitionBy(group, "__bucket").orderBy(key, *ties)
    numbered = df.withColumn("__row", F.row_number().over(inside) - 1)
    return (numbered.join(starts, [group, "__bucket"]).withColumn("slot", (F.col("__start") + F.col("__row")).cast("long"))
            .drop("__bucket", "__start", "__row"))


def shard_documents(docs: DataFrame, tree: Branch, grown: Branch | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``doc_id, size, text_crc32, shard, slot`` and, with a second tree,
    ``grown_shard``.  A null text has size 16 and checksum 0, as an empty one;
    equal rows get slots of their own."""
    text = docs[text_col].cast("string")
    rows = docs.select(docs[id_col].cast("long").alias("doc_id"), (F.coalesce(F.octet_length(text), F.lit(0)) + 16).cast("long").alias("size"),
                       F.coalesce(F.crc32(text), F.lit(0)).cast("long").alias("text_crc32"))
    rows = place(rows, F.col("doc_id"), tree, "shard")
    rows = place(rows, F.col("doc_id"), grown, "grown_shard") if grown else rows.withColumn("grown_shard", F.lit(None).cast("int"))
    return gapless_slots(rows, "shard", "doc_id", ["text_crc32", "size"])


def write_shards(docs: DataFrame, tree: Branch, path: str, id_col: str = "doc_id", records_per_file: int = 1_000_000) -> None:
    """Write whole rows to ``path/shard=N/``, in files of a bounded number of
    rows; a shard is written by as many tasks as it has hash buckets."""
    rows = place(docs, docs[id_col], tree, "shard")
    rows.withColumn("__b", F.pmod(F.xxhash64(id_col), F.lit(16))).repartition("shard", "__b").drop("__b").write.option(
        "maxRecordsPerFile", records_per_file).partitionBy("shard").mode("overwrite").parquet(path)


#: 4 regions of 2 racks of 5 shards; growth adds a region with shard 40.
PRODUCTION_TREE = uniform_tree(4, 2, 5)
GROWN_TREE = with_region(PRODUCTION_TREE, "region4", (Leaf(40),))


def op4_hash_tree(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    rows = shard_documents(docs, PRODUCTION_TREE, GROWN_TREE)
    return rows.select("doc_id", "size", "text_crc32", F.lit("key").alias("law"), "shard", "slot", "grown_shard")
