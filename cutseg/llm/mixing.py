"""Mix sources to target weights over a tree of domains, languages, sources.

Weights are handed down the tree; a leaf cannot take more than its supply times
the number of epochs.  What a node's subtree cannot take goes to its siblings in
proportion to their weights, and only what they cannot take either goes up.
Each leaf then takes whole epochs of its documents and, of one more epoch in
seeded random order, the prefix that fills its budget.
"""

from __future__ import annotations

from collections.abc import Mapping
from dataclasses import dataclass, field
from fractions import Fraction

from pyspark.sql import Column, DataFrame, Window as W, functions as F

from cutseg.plans.workspace import Workspace

LEVELS = ("domain", "lang", "source")
#: Nodes of the tree are configuration; a wider one is refused, not collected.
MOST_LEAVES = 100_000
#: Parts of an epoch, by the leading bits of the order; only one of them is sorted for each leaf.
PARTS = 4096


@dataclass(frozen=True)
class Weights:
    """Relative weights of nodes by path, e.g. ``("core",)`` or ``("core",
    "en")``; a node that is not named has ``default``."""

    named: Mapping[tuple[str, ...], float] = field(default_factory=dict)
    default: float = 1.0

    def of(self, path: tuple[str, ...]) -> Fraction:
        return Fraction(str(self.named.get(path, self.default)))


def budgets(supply: Mapping[tuple[str, ...], int], weights: Weights, total: int) -> dict[tuple[str, ...], int]:
    """Whole-number budget of each leaf; ``supply`` is the most it can take.

    They sum to ``total``, or to the whole supply if that is less (nodes of
    weight 0 take nothing, so it can be less still).
    """
    if not supply:
        return {}
    tree: dict = {}
    for path in supply:
        node = tree
        for name in path:
            node = node.setdefault(name, {})
    room: dict[tuple, Fraction] = {}

    def fill(path: tuple, node: dict) -> Fraction:
        room[path] = (sum((fill((*path, k), v) for k, v in node.items() if weights.of((*path, k)) > 0), Fraction(0))
                      if node else Fraction(supply[path]))
        return room[path]

    fill((), tree)
    share: dict[tuple, Fraction] = {}

    def hand_down(path: tuple, node: dict, amount: Fraction) -> None:
        if not node:
            share[path] = amount
            return
        open_ = {k: weights.of((*path, k)) for k in node if weights.of((*path, k)) > 0}
        given = {k: Fraction(0) for k in node}
        while open_ and amount > 0:
            mass = sum(open_.values())
            full = [k for k, w in open_.items() if amount * w / mass >= room[(*path, k)]]
            for k in full or open_:
                given[k] = room[(*path, k)] if full else amount * open_[k] / mass
            if not full:
                break
            amount -= sum(given[k] for k in full)
            for k in full:
                del open_[k]
        for k, v in node.items():
            hand_down((*path, k), v, given[k])

    hand_down((), tree, min(Fraction(total), room[()]))
    out = {p: int(x) for p, x in share.items()}
    left = int(sum(share.values())) - sum(out.values())
    for p in sorted(share, key=lambda p: (out[p] - share[p], p))[:left]:  # largest remainders
        out[p] += 1
    return out


def word_count(text: Column) -> Column:
    """Runs of characters that are no ASCII white space."""
    bare = F.trim(F.regexp_replace(text, "[\\x09-\\x0D\\x20]+", " "))
    return F.when(F.coalesce(F.length(bare), F.lit(0)) == 0, 0).otherwise(F.size(F.split(bare, " "))).cast("long")


class Mixture:
    """Budgets and selected rows of a document table.

    ``paths`` gives the columns of the tree's levels; a null is a node named
    ``(null)``.  Documents without words weigh nothing: they come with each
    whole epoch, and with the prefix up to its end.  Repeated rows count each.
    """

    def __init__(self, docs: DataFrame, paths: Mapping[str, Column], weights: Weights, *, share: float = 1.0, epochs: int = 1, seed: int = 17, id_col: str = "doc_id", text_col: str = "text"):
        spark = docs.sparkSession
        ws = Workspace(spark, "mixing")
        self.levels = list(paths)
        named = [F.coalesce(c.cast("string"), F.lit("(null)")).alias(k) for k, c in paths.items()]
        self.rows = rows = ws.table(docs.select(docs[id_col].cast("long").alias("doc_id"), *named, word_count(docs[text_col].cast("string")).alias("tokens")), "measured")
        held = rows.groupBy(*self.levels).agg(F.sum("tokens").alias("tokens")).limit(MOST_LEAVES + 1).collect()
        if len(held) > MOST_LEAVES:
            raise ValueError(f"the tree has more than {MOST_LEAVES} leaves")
        supply = {tuple(r[k] for k in self.levels): r["tokens"] for r in held}
        total = int(Fraction(str(share)) * sum(supply.values()))
        #: leaf -> tokens
        self.budgets = budgets({p: n * epochs for p, n in supply.items()}, weights, total)
        plan = []
        for path, n in supply.items():
            own = self.budgets.get(path, 0)
            whole, rest = divmod(own, n) if n else (int(own == 0 and epochs > 0), 0)
            plan.append((*path, n, own, whole, rest))
        kinds = ", ".join(f"{k} string" for k in self.levels)
        self.plan = spark.createDataFrame(plan, f"{kinds}, supply long, budget long, whole long, rest long")
        known = rows.join(F.broadcast(self.plan.drop("supply", "budget")), self.levels)
        order = F.shiftrightunsigned(F.xxhash64(F.lit(seed), F.col("whole"), F.col("doc_id")), 1)
        known = known.withColumn("order", order).withColumn("part", F.shiftright("order", 51).cast("int"))
        # where the prefix of each leaf ends: at most PARTS rows a leaf
        sums = known.where("rest > 0").groupBy(*self.levels, "part", "rest").agg(F.sum("tokens").alias("n"))
        upto = F.sum("n").over(W.partitionBy(*self.levels).orderBy("part"))
        cut = (sums.withColumn("upto", upto).where("upto >= rest").groupBy(*self.levels)
               .agg(F.min(F.struct("part", (F.col("upto") - F.col("n")).alias("before"))).alias("c"))
               .select(*self.levels, F.col("c.part").alias("cut"), F.col("c.before").alias("before")))
        known = known.join(F.broadcast(cut), self.levels, "left")  # one row a leaf
        columns = ["doc_id", *self.levels, "epoch", "tokens", "take"]
        epochs_of = known.where("whole > 0").withColumn("epoch", F.explode(F.sequence(F.lit(0).cast("long"), F.col("whole") - 1))).withColumn("take", F.col("tokens"))
        early = known.where("rest > 0 and part < cut").withColumn("epoch", F.col("whole")).withColumn("take", F.col("tokens"))
        inside = W.partitionBy(*self.levels).orderBy("order", "doc_id", "tokens").rowsBetween(W.unboundedPreceding, -1)
        edge = (known.where("rest > 0 and part = cut").withColumn("at", F.col("before") + F.coalesce(F.sum("tokens").over(inside), F.lit(0)))
                .where("at < rest").withColumn("epoch", F.col("whole")).withColumn("take", F.least(F.col("tokens"), F.col("rest") - F.col("at"))))
        #: doc_id, levels, epoch, tokens, take: of how many tokens the prefix consists
        self.selected = epochs_of.select(columns).unionByName(early.select(columns)).unionByName(edge.select(columns))


def production_paths(docs: DataFrame) -> dict[str, Column]:
    """Sources with a one-digit number are the core domain, others the tail."""
    return {"domain": F.when(docs["source"].rlike("^src[0-9]$"), "core").otherwise("tail"), "lang": docs["lang"], "source": docs["source"]}


PRODUCTION_WEIGHTS = Weights({("core",): 0.6, ("tail",): 0.4, **{(d, "en"): 2.0 for d in ("core", "tail")}, ("core", "en", "src0"): 0.5})


def op1_mixing(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return Mixture(docs, production_paths(docs), PRODUCTION_WEIGHTS, share=1.0, epochs=4).selected
