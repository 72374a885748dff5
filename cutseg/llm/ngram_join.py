"""Set-similarity self-join of documents on word n-grams.

The join is exact but for two words, or two shingles, with equal 64-bit hashes.

How a run goes, with the tables that are written in brackets:

1. One pass over the texts gives each document the size of its shingle set and
   a 128-bit digest of the set, and counts shingles in a fixed number of
   buckets [profile].  Documents with equal sets form a class; the class is
   represented by its smallest id.
2. Bucket counts (a constant 4 MB) order shingles rare first; any total order
   gives the same links, a good one gives few candidates.  A second pass emits
   the prefix of each class in that order [postings]; shingles that occur in
   one class only are dropped, they link nothing.  Shingles of hot buckets are
   dealt to several tasks by the class.
3. Links are found in rounds.  The first compares neighbours in lists sorted by
   minimum hashes, and all of a prefix list with the document that has the
   shingle earliest; this joins large groups of near copies with a linear number
   of pairs.  Later rounds join the prefixes, under the length and positional
   filters, and take only pairs whose ends are not connected yet: first one pair
   for each document and component, then all that are left.  Each pair is
   verified once, with the suffix filter before the full intersection.

Pairs inside a connected component are skipped as nothing depends on them; with
``all_links=True`` the first rounds are left out and every link is returned.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window as W, functions as F

from cutseg.llm.words import BATCH_BYTES, U64, WordHashes, finish, shingle_set, small_batches, tidy
from cutseg.operators.components import connected_components
from cutseg.operators.dense import collect_sums, emit
from cutseg.plans.workspace import Workspace

#: Buckets of the shingle counts.
BUCKETS = 1 << 20
#: Documents of one task in a list of equal hashes or shingles; longer lists are dealt out.
LIST_ROWS = 1000
#: Documents whose sets may be found by a bitmap (64 bits for each, 32 MB at most); more are joined.
MOST_MARKED = 1 << 22
_PROFILE = "doc_id long, n long, sig binary, half long, h1 long, h2 long, h3 long, block int, counts binary"
_POSTINGS = "token long, class long, n long, pos long, part int"
_BITS = "block int, bits binary"
_BIT_BLOCK = 1 << 16


@dataclass(frozen=True)
class Threshold:
    """Sets link when ``den * intersection >= num * union``, in integers."""

    num: int
    den: int

    def overlap(self, a, b):
        """Least intersection of linked sets with sizes a and b."""
        return -(-self.num * (a + b) // (self.num + self.den))

    def least_size(self, a):
        return -(-self.num * a // self.den)

    def prefix(self, a):
        return a - self.least_size(a) + 1


def _half(digest: bytes) -> int:
    return int.from_bytes(digest[:8], "little", signed=True)


def _profile(n: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes, counts, seen = WordHashes(), np.zeros(BUCKETS, np.int64), set()
        salts = [U64(0), U64(0x9E3779B97F4A7C15), U64(0xC2B2AE3D27D4EB4F)]
        for batch in batches:
            size, sigs, least = [], [], []
            for text in batch.column(1).cast(pa.binary()).to_pylist():
                s = shingle_set(text, n, hashes)
                sig = xxhash.xxh3_128_digest(s.tobytes())
                size.append(len(s))
                sigs.append(sig)
                least.append([int(finish(s ^ x).min().view(np.int64)) for x in salts] if len(s) else [0, 0, 0])
                if sig not in seen:
                    if len(seen) < 20_000:
                        seen.add(sig)
                    np.add.at(counts, s & U64(BUCKETS - 1), 1) if len(s) < 64 else _count(counts, s)
            k = len(size)
            h = np.array(least, np.int64).reshape(k, 3)
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), pa.array(size, pa.int64()), pa.array(sigs, pa.binary()), pa.array([_half(x) for x in sigs], pa.int64()), *(pa.array(h[:, i]) for i in range(3)),
                 pa.nulls(k, pa.int32()), pa.nulls(k, pa.binary())], ["doc_id", "n", "sig", "half", "h1", "h2", "h3", "block", "counts"])
        blocks = emit(counts)
        k = blocks.num_rows
        yield pa.RecordBatch.from_arrays(
            [pa.nulls(k, pa.int64()), pa.nulls(k, pa.int64()), pa.nulls(k, pa.binary()), *(pa.nulls(k, pa.int64()) for _ in range(4)), *blocks.columns],
            ["doc_id", "n", "sig", "half", "h1", "h2", "h3", "block", "counts"])
    return run


def _count(counts: np.ndarray, s: np.ndarray) -> None:
    at, times = np.unique(s & U64(BUCKETS - 1), return_counts=True)
    counts[at.astype(np.int64)] += times


def _ordered(s: np.ndarray, counts: np.ndarray) -> np.ndarray:
    return s[np.lexsort((s, counts[(s & U64(BUCKETS - 1)).astype(np.int64)]))]


def _postings(n: int, limit: Threshold, shared, part_rows: int):
    """Prefixes of texts; a class goes by half of its digest, which two classes
    may share: a pair too many is tried then, and none is lost."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes, counts, seen = WordHashes(), shared.value, set()

        def packed(held: list) -> pa.RecordBatch:
            size = [len(tokens) for tokens, _, _ in held]
            tokens = np.concatenate([tokens for tokens, _, _ in held])
            class_ = np.repeat(np.array([c for _, c, _ in held], np.int64), size)
            parts = counts[(tokens & U64(BUCKETS - 1)).astype(np.int64)] // part_rows + 1
            part = (finish(class_.view(U64)) % parts.astype(U64)).astype(np.int32)
            return pa.RecordBatch.from_arrays(
                [pa.array(tokens.view(np.int64)), pa.array(class_), pa.array(np.repeat(np.array([m for _, _, m in held], np.int64), size)),
                 pa.array(np.concatenate([np.arange(k) for k in size])), pa.array(np.where(parts > 1, part, -1).astype(np.int32))],
                ["token", "class", "n", "pos", "part"])

        for batch in batches:
            held, weight = [], 0
            for text in batch.column(0).cast(pa.binary()).to_pylist():
                s = shingle_set(text, n, hashes)
                sig = xxhash.xxh3_128_digest(s.tobytes())
                if not len(s) or sig in seen:
                    continue
                if len(seen) < 20_000:
                    seen.add(sig)
                k = limit.prefix(len(s))
                held.append((_ordered(s, counts)[:k], _half(sig), len(s)))
                weight += 40 * k
                if weight > BATCH_BYTES:
                    yield packed(held)
                    held, weight = [], 0
            if held:
                yield packed(held)
    return run


def _marks(bits: int):
    """Bits of the ids of a partition, in blocks that are not all zero."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen = np.zeros(bits // 8, np.uint8)
        for batch in batches:
            at = finish(batch.column(0).to_numpy().view(U64)) & U64(bits - 1)
            np.bitwise_or.at(seen, (at >> U64(3)).astype(np.int64), np.uint8(1) << (at & U64(7)).astype(np.uint8))
        blocks = [(i, seen[i * _BIT_BLOCK:(i + 1) * _BIT_BLOCK]) for i in range(-(-len(seen) // _BIT_BLOCK))]
        blocks = [(i, x.tobytes()) for i, x in blocks if x.any()]
        yield pa.RecordBatch.from_arrays([pa.array([i for i, _ in blocks], pa.int32()), pa.array([x for _, x in blocks], pa.binary())], ["block", "bits"])
    return run


def _united(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    total: dict[int, np.ndarray] = {}
    for batch in batches:
        for i, x in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
            x = np.frombuffer(x, np.uint8)
            total[i] = total[i] | x if i in total else x
    yield pa.RecordBatch.from_arrays([pa.array(list(total), pa.int32()), pa.array([x.tobytes() for x in total.values()], pa.binary())], ["block", "bits"])


def _sets(n: int, shared):
    """Shingle sets, smallest hash first, of documents whose bit is set (of
    all without a bitmap)."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        hashes, marks = WordHashes(), shared.value if shared else None
        for batch in batches:
            ids = batch.column(0).to_numpy(zero_copy_only=False).astype(np.int64)
            keep = np.arange(len(ids))
            if marks is not None:
                at = finish(ids.view(U64)) & U64(8 * len(marks) - 1)
                keep = np.flatnonzero(marks[(at >> U64(3)).astype(np.int64)] >> (at & U64(7)).astype(np.uint8) & 1)
            texts = batch.column(1).take(pa.array(keep)).cast(pa.binary()).to_pylist()
            yield pa.RecordBatch.from_arrays(
                [pa.array(ids[keep]), pa.array([shingle_set(t, n, hashes).tobytes() for t in texts], pa.binary())], ["id", "set"])
    return run


def _suffix_allows(x: np.ndarray, y: np.ndarray, differ: int) -> bool:
    """Partition both sets by common pivots; the sizes alone bound how far the
    sets must differ.  False only if they differ in more than ``differ``."""
    cuts = x[len(x) // 8::max(1, len(x) // 8)][:7]
    a, b = np.searchsorted(x, cuts), np.searchsorted(y, cuts)
    return int(np.abs(np.diff(a, prepend=0, append=len(x)) - np.diff(b, prepend=0, append=len(y))).sum()) <= differ


def linked(x: np.ndarray, y: np.ndarray, limit: Threshold) -> bool:
    need = limit.overlap(len(x), len(y))
    if not need or min(len(x), len(y)) < need or not _suffix_allows(x, y, len(x) + len(y) - 2 * need):
        return False
    both = np.concatenate((x, y))
    both.sort()
    return int((both[1:] == both[:-1]).sum()) >= need


def _verify(limit: Threshold):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ok = [linked(np.frombuffer(x, U64), np.frombuffer(y, U64), limit) for x, y in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist())]
            keep = pa.array(ok, pa.bool_())
            yield pa.RecordBatch.from_arrays([batch.column(0).filter(keep), batch.column(1).filter(keep)], ["a", "b"])
    return run


class NgramJoin:
    """Find links and groups of near-equal texts.

    ``docs`` needs an integer id and a text column; others are ignored, whatever
    their names.  Rows that share an id are one node.  Null or wordless texts
    have an empty set and link with nothing; rows with a null id keep their set
    size and belong to no component.  An empty table gives empty results.
    """

    def __init__(self, docs: DataFrame, *, words: int = 5, num: int = 4, den: int = 5, id_col: str = "doc_id", text_col: str = "text", all_links: bool = False):
        self.docs = docs.select(docs[id_col].cast("long").alias("doc_id"), docs[text_col].cast("string").alias("text"))
        self.words, self.limit, self.all_links = words, Threshold(num, den), all_links
        self.spark = docs.sparkSession
        small_batches(self.spark)
        self.ws = Workspace(self.spark, "ngram-join")
        self._run()

    def _run(self) -> None:
        ws, sc = self.ws, self.spark.sparkContext
        profile = ws.table(self.docs.mapInArrow(tidy(_profile(self.words)), _PROFILE), "profile")
        self.profile = profile.where("block is null").select("doc_id", "n", "sig", "half", "h1", "h2", "h3")
        self.classes = ws.table(
            self.profile.where("doc_id is not null and n > 0").groupBy("sig").agg(
                F.min("doc_id").alias("rep"), *(F.first(c).alias(c) for c in ("n", "half", "h1", "h2", "h3"))), "classes")
        sums = collect_sums(profile.where("block is not null").select("block", "counts"), BUCKETS)
        # a list is hot when it is long, and far longer than what shares a bucket by chance
        part_rows = max(LIST_ROWS, 16 * int(sums.mean()))
        counts = sc.broadcast(sums)
        emitted = self.docs.where("doc_id is not null").select("text").mapInArrow(tidy(_postings(self.words, self.limit, counts, part_rows)), _POSTINGS)
        n_tasks = int(self.spark.conf.get("spark.sql.shuffle.partitions"))
        shared = (emitted.repartition(n_tasks, "token", "part").dropDuplicates(["token", "part", "class"])
                  .withColumn("df", F.count("*").over(W.partitionBy("token", "part"))).where("df > 1 or part >= 0").drop("df", "part"))
        # postings by the class's representative; the digest has done its work
        named = self.classes.select(F.col("half").alias("class"), "rep")
        self.postings = ws.table(shared.join(named, "class").select("token", "rep", "n", "pos"), "postings")
        counts.unpersist()

        near = ws.table(self._neighbours().union(self._with_leaders()).distinct(), "pairs-0")
        if self.all_links:
            self.links = self._verified(ws.table(self._candidates(None, "all"), "pairs"), "links")
            self.component = connected_components(self.links, ws)
            return
        links, tried = self._verified(near, "links-0"), near
        self.component = connected_components(links, ws, "components-0")
        for turn in (1, 2):
            pairs = self._candidates(self.component, str(turn), one_each=turn == 1)
            pairs = ws.table(pairs.join(tried, ["a", "b"], "left_anti"), f"pairs-{turn}")
            ws.drop(f"open-{turn}")
            if pairs.isEmpty():
                break
            tried = tried.union(pairs)
            more = self._verified(pairs, f"links-{turn}")
            links = links.union(more)
            if not more.isEmpty():
                self.component = connected_components(self.component.union(more), ws, f"components-{turn}")
        self.links = links
        ws.drop("postings", "pairs-0", "pairs-1", "pairs-2")

    def _neighbours(self) -> DataFrame:
        """Neighbours in lists of classes that share a minimum hash; a long list
        is dealt to several."""
        pairs = []
        for h, then in (("h1", ("h2", "h3")), ("h2", ("h3", "h1")), ("h3", ("h1", "h2"))):
            long_lists = self.classes.groupBy(h).agg(F.count("*").alias("m")).where(F.col("m") > LIST_ROWS)
            dealt = self.classes.join(long_lists, h, "left").withColumn(
                "part", F.coalesce(F.pmod(F.xxhash64("rep"), F.ceil(F.col("m") / LIST_ROWS)), F.lit(0)))
            w = W.partitionBy(h, "part").orderBy(*then, "n", "rep")
            pairs.append(dealt.select("rep", "n", F.lag("rep").over(w).alias("o"), F.lag("n").over(w).alias("m")).where("o is not null"))
        all_pairs = pairs[0].union(pairs[1]).union(pairs[2]).where(self._sizes_fit("n", "m"))
        return all_pairs.select(F.least("rep", "o").alias("a"), F.greatest("rep", "o").alias("b")).where("a <> b")

    def _with_leaders(self) -> DataFrame:
        """Each class with the one that has a shared shingle earliest."""
        lead = self.postings.groupBy("token").agg(F.min(F.struct("pos", "n", "rep")).alias("l"))
        pairs = self.postings.join(lead, "token").where(
            f"rep <> l.rep and {self._sizes_fit('n', 'l.n')} and {self._overlap_fits('n', 'pos', 'l.n', 'l.pos')}")
        return pairs.select(F.least("rep", "l.rep").alias("a"), F.greatest("rep", "l.rep").alias("b"))

    def _overlap_fits(self, n: str, pos: str, m: str, at: str) -> str:
        """The positional filter: what is left from here on can be enough."""
        num, den = self.limit.num, self.limit.den
        return f"{num + den} * least({n} - {pos}, {m} - {at}) >= {num} * ({n} + {m})"

    def _sizes_fit(self, n: str, m: str) -> str:
        num, den = self.limit.num, self.limit.den
        return f"{den} * least({n}, {m}) >= {num} * greatest({n}, {m})"

    def _candidates(self, component: DataFrame | None, name: str, one_each: bool = False) -> DataFrame:
        rows = self.postings
        if component is None:
            rows = rows.withColumn("comp", F.col("rep"))
        else:
            rows = rows.join(component, rows["rep"] == component["node"], "left").select("token", "rep", "n", "pos", F.coalesce("component", "rep").alias("comp"))
            # a list within one component has nothing left to link
            open_lists = rows.groupBy("token").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi")).where("lo <> hi").select("token")
            # written, so that the join below reads plain shuffles, of which a hot one can be split
            rows = self.ws.table(rows.join(open_lists, "token", "left_semi"), f"open-{name}")
        x, y = rows.alias("x"), rows.alias("y")
        found = x.join(y, F.expr(
            f"x.token = y.token and x.rep < y.rep and x.comp <> y.comp and {self._sizes_fit('x.n', 'y.n')}"
            f" and {self._overlap_fits('x.n', 'x.pos', 'y.n', 'y.pos')}"))
        pairs = found.select(F.col("x.rep").alias("a"), F.col("y.rep").alias("b"), F.col("x.comp").alias("ca"), F.col("y.comp").alias("cb"),
                             F.abs(F.expr("x.n - y.n")).alias("gap"))
        if not one_each:
            return pairs.select("a", "b").distinct()
        best = F.min(F.struct("gap", "a", "b")).alias("p")
        left = pairs.groupBy("a", "cb").agg(best).select("p.a", "p.b")
        right = pairs.groupBy("b", "ca").agg(best).select("p.a", "p.b")
        return left.union(right).distinct()

    def _sets_of(self, pairs: DataFrame, name: str) -> DataFrame:
        """Shingle sets of the documents in ``pairs``, and of a few more that
        share a bit with them; up to ``MOST_MARKED`` documents their texts are
        scanned again and not shuffled."""
        docs = self.docs.where("doc_id is not null")
        ends = pairs.select(F.col("a").alias("doc_id")).union(pairs.select("b")).distinct()
        many = ends.limit(MOST_MARKED + 1).count()
        shared = None
        if many > MOST_MARKED:
            docs = docs.join(ends, "doc_id", "left_semi")
        else:
            bits = max(8 * _BIT_BLOCK, 1 << (64 * many).bit_length())
            united = (ends.mapInArrow(tidy(_marks(bits)), _BITS).repartition(max(1, bits // (8 * _BIT_BLOCK)), "block").mapInArrow(tidy(_united), _BITS))
            marks = np.zeros(bits // 8, np.uint8)
            for r in united.collect():
                marks[r["block"] * _BIT_BLOCK:(r["block"] + 1) * _BIT_BLOCK] = np.frombuffer(r["bits"], np.uint8)
            shared = self.spark.sparkContext.broadcast(marks)
        return self.ws.table(docs.mapInArrow(tidy(_sets(self.words, shared)), "id long, set binary"), name)

    def _verified(self, pairs: DataFrame, name: str) -> DataFrame:
        s = self._sets_of(pairs, f"sets-{name}")
        rows = (pairs.join(s.select(F.col("id").alias("a"), F.col("set").alias("sa")), "a")
                .join(s.select(F.col("id").alias("b"), F.col("set").alias("sb")), "b").select("a", "b", "sa", "sb"))
        links = self.ws.table(rows.mapInArrow(tidy(_verify(self.limit)), "a long, b long").distinct(), name)
        self.ws.drop(f"sets-{name}")
        return links

    def documents(self) -> DataFrame:
        """``doc_id, n_shingles, component_id``: one row per input row."""
        named = (self.classes.select("sig", "rep").join(self.component, F.col("rep") == F.col("node"), "left")
                 .select("sig", F.coalesce("component", "rep").alias("component")))
        return (self.profile.join(named, "sig", "left")
                .select("doc_id", F.col("n").cast("long").alias("n_shingles"),
                        F.when(F.col("doc_id").isNotNull(), F.coalesce("component", "doc_id")).alias("component_id")))


def op3_ngram_jaccard(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return NgramJoin(docs, words=4, num=85, den=100).documents()


#: All pairs that share a shingle; for the comparison at small scale only.
OP3_SQL = """
with recursive w as (select doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\\x20\\x09-\\x0D]+') as w from documents),
s as (select distinct doc_id, unnest(case when len(w) = 0 then [] else list_transform(range(1, greatest(len(w) - 3, 1) + 1), lambda i: array_to_string(w[i:i + 3], ' ')) end) as g from w),
n as (select doc_id, count(*) as n from s group by doc_id),
shared as (select a.doc_id as a, b.doc_id as b, count(*) as common from s a join s b on a.g = b.g and a.doc_id < b.doc_id group by all),
links as (select a, b from shared join n x on x.doc_id = a join n y on y.doc_id = b where 100 * common >= 85 * (x.n + y.n - common)),
sym as (select a, b from links union all select b, a from links),
reach(a, b) as (select a, b from sym union select r.a, l.b from reach r join sym l on r.b = l.a),
least as (select a, min(b) as m from reach group by a)
select d.doc_id, coalesce(n.n, 0)::bigint as n_shingles, least(d.doc_id, coalesce(l.m, d.doc_id)) as component_id
from documents d left join n on n.doc_id = d.doc_id left join least l on l.a = d.doc_id"""
