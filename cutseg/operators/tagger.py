"""A supervised tagger of symbols, fitted on distinct feature rows.

What a symbol's window says is eight numbers of a bucket.  Symbols with equal
numbers are one row with a count for each tag, so a round of the fit reads
distinct rows only, and the driver holds one gradient.
"""

from __future__ import annotations

import zlib
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from cutseg.functions.units import gold_words
from cutseg.operators.segment import with_results
from cutseg.plans.workspace import Workspace

#: Begin, middle and end of a word, and a word of one symbol.
TAGS = ["B", "M", "E", "S"]
#: Places of the symbols that a feature names.
WINDOWS = ((-1,), (0,), (1,), (-1, 0), (0, 1), (-2, -1), (1, 2), (-1, 0, 1))
_MIX, _EDGE = np.uint64(0x9E3779B97F4A7C15), ord("#")


def _mixed(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    h = (h ^ (h >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return h ^ (h >> np.uint64(31))


def feature_buckets(langs, texts: list[str], buckets: int) -> np.ndarray:
    """(symbols of all texts, 8): buckets of the windows of each symbol."""
    edge = chr(_EDGE) * 2
    codes = np.frombuffer((edge + edge.join(texts) + edge).encode("utf-32-le", "surrogatepass"), "<u4").astype(np.uint64)
    sizes = np.fromiter(map(len, texts), np.int64, len(texts))
    total = int(sizes.sum())
    at = np.arange(total) + 2 * np.repeat(np.arange(1, len(texts) + 1), sizes)
    known = {lang: zlib.crc32((lang if isinstance(lang, str) else "").encode()) for lang in set(langs)}
    own = np.repeat(np.array([known[lang] for lang in langs], np.uint64), sizes)
    out = np.empty((total, len(WINDOWS)), np.uint16)
    for j, places in enumerate(WINDOWS):
        h = own * np.uint64(64) + np.uint64(j)
        for d in places:
            h = h * _MIX + codes[at + d] + np.uint64(1)
        out[:, j] = _mixed(h) % np.uint64(buckets)
    return out


def tags_of(sizes: np.ndarray, lengths: np.ndarray, of: np.ndarray) -> np.ndarray:
    """Tag of each symbol of texts with so many symbols, from the lengths of their
    words and the text of each word; -1 behind the last word."""
    ends = np.cumsum(lengths)
    words = np.full(int(lengths.sum()), 1)
    words[ends - lengths], words[ends - 1] = 0, 2
    words[ends[lengths == 1] - 1] = 3
    held = np.bincount(of, lengths, len(sizes)).astype(np.int64) if len(of) else np.zeros(len(sizes), np.int64)
    if (held == sizes).all():
        return words
    out, begin = np.full(int(sizes.sum()), -1), np.cumsum(sizes) - sizes
    source = np.cumsum(held) - held
    for j in range(len(sizes)):
        n = min(sizes[j], held[j])
        out[begin[j]:begin[j] + n] = words[source[j]:source[j] + n]
    return out


def feature_counts(sents: DataFrame, buckets: int) -> DataFrame:
    """``f1, f2, n0 .. n3``: distinct feature rows, packed in two numbers, with
    the count of each tag."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts, lengths = batch.column(1).to_pylist(), batch.column(2)
            sizes = np.fromiter(map(len, texts), np.int64, len(texts))
            of = np.repeat(np.arange(len(texts)), lengths.value_lengths().to_numpy(zero_copy_only=False).astype(np.int64))
            tags = tags_of(sizes, lengths.flatten().to_numpy(zero_copy_only=False).astype(np.int64), of)
            rows = np.ascontiguousarray(feature_buckets(batch.column(0).to_pylist(), texts, buckets)).view(np.uint64)[tags >= 0]
            tags = tags[tags >= 0]
            # equal rows are neighbours after a sort by both numbers
            order = np.lexsort((rows[:, 1], rows[:, 0]))
            rows, tags = rows[order], tags[order]
            new = np.flatnonzero(np.concatenate(([True], (rows[1:] != rows[:-1]).any(1)))) if len(rows) else np.zeros(0, int)
            counts = np.zeros((len(new), 4), np.int64)
            np.add.at(counts, (np.searchsorted(new, np.arange(len(rows)), "right") - 1, tags), 1)
            yield pa.RecordBatch.from_arrays([pa.array(rows[new, j].view(np.int64)) for j in (0, 1)] + [pa.array(counts[:, j]) for j in range(4)], ["f1", "f2", "n0", "n1", "n2", "n3"])

    rows = sents.where("s <> ''").select("lang", "s", F.transform(gold_words(F.col("raw")), F.length).alias("lengths"))
    counted = rows.mapInArrow(run, "f1 long, f2 long, n0 long, n1 long, n2 long, n3 long")
    return counted.groupBy("f1", "f2").agg(*[F.sum(f"n{j}").alias(f"n{j}") for j in range(4)])


def _unpacked(batch: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray]:
    f = np.stack([batch.column(j).to_numpy() for j in (0, 1)], axis=1)
    return f.view(np.uint16).astype(np.int64), np.stack([batch.column(j).to_numpy() for j in range(2, 6)], axis=1).astype(float)


def _log_odds(f: np.ndarray, w: np.ndarray) -> np.ndarray:
    """Log probabilities of tags: the last row of ``w`` is the intercept."""
    z = w[f].sum(1) + w[-1]
    z -= z.max(1, keepdims=True)
    return z - np.log(np.exp(z).sum(1, keepdims=True))


def _summed(table: DataFrame, of_chunk: Callable, rows: int) -> np.ndarray:
    """Sum over all feature rows of a (rows, 4) array that chunks give."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((rows, 4))
        for batch in batches:
            for a in range(0, batch.num_rows, 1 << 14):
                total += of_chunk(*_unpacked(batch.slice(a, 1 << 14)))
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(rows))] + [pa.array(total[:, j].copy()) for j in range(4)], ["j", "g0", "g1", "g2", "g3"])

    parts = table.mapInArrow(run, "j long, g0 double, g1 double, g2 double, g3 double")
    found = parts.groupBy("j").agg(*[F.sum(f"g{j}").alias(f"g{j}") for j in range(4)]).toPandas().sort_values("j")
    return found[["g0", "g1", "g2", "g3"]].to_numpy() if len(found) else np.zeros((rows, 4))


def lowest(value: Callable[[np.ndarray], tuple[float, np.ndarray]], x: np.ndarray, rounds: int, kept: int = 10) -> np.ndarray:
    """Limited-memory quasi-Newton descent with halved steps."""
    (f, g), steps = value(x), []
    for r in range(rounds):
        d, along = -g, []
        for s, y in reversed(steps):
            a = (s @ d) / (s @ y)
            along.append(a)
            d = d - a * y
        if steps:
            s, y = steps[-1]
            d = d * ((s @ y) / (y @ y))
        for (s, y), a in zip(steps, reversed(along)):
            d = d + (a - (y @ d) / (s @ y)) * s
        slope, step = g @ d, 1.0 if steps else 1.0 / max(1e-12, np.linalg.norm(g))
        if slope > -1e-14:
            break
        for _ in range(12):
            new, (f1, g1) = x + step * d, value(x + step * d)
            if f1 <= f + 1e-4 * step * slope:
                break
            step /= 2
        else:
            break
        if (new - x) @ (g1 - g) > 1e-14:
            steps = [*steps, (new - x, g1 - g)][-kept:]
        done = abs(f - f1) <= 1e-7 * max(1.0, abs(f))
        x, f, g = new, f1, g1
        if done:
            break
    return x


def best_tags(log_p: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """The best legal tags of sentences, one behind the other: B and M go on with M
    or E, E and S with B or S; sentences begin and end at word edges."""
    go = np.full((4, 4), -np.inf)
    for a, b in ((0, 1), (0, 2), (1, 1), (1, 2), (2, 0), (2, 3), (3, 0), (3, 3)):
        go[a, b] = 0
    order = np.argsort(-sizes, kind="stable")
    begin, n = (np.cumsum(sizes) - sizes)[order], sizes[order]
    out, back = np.zeros(len(log_p), int), np.zeros((len(log_p), 4), np.int8)
    best = log_p[begin] + np.array([0, -np.inf, -np.inf, 0])
    for i in range(1, int(n.max(initial=0))):  # the longer ones come first
        live = int(np.searchsorted(-n, -i))
        total = best[:live, :, None] + go
        back[begin[:live] + i] = total.argmax(1)
        best[:live] = total.max(1) + log_p[begin[:live] + i]
    tag = (best + np.array([-np.inf, -np.inf, 0, 0])).argmax(1)
    for i in range(int(n.max(initial=0)) - 1, -1, -1):
        live = int(np.searchsorted(-n, -i))
        place = begin[:live] + i
        out[place] = tag[:live]
        tag[:live] = back[place, tag[:live]]
    return out


class Tagger:
    """Multinomial logistic regression over hashed window features, with the best
    legal tag sequence of each sentence.  Features count by their deviation, as
    their coefficients are held small on that scale."""

    def __init__(self, gold_sents: DataFrame, buckets: int = 1 << 14, rounds: int = 15, small: float = 1e-4):
        spark, self.buckets = gold_sents.sparkSession, buckets
        table = Workspace(spark, "tagger").table(feature_counts(gold_sents, buckets), "features")
        rows = buckets + 1

        def seen(f: np.ndarray, n: np.ndarray) -> np.ndarray:
            out = np.zeros((rows, 4))
            for j in range(4):
                out[:-1, j] = np.bincount(f.ravel(), np.repeat(n[:, j], f.shape[1]), buckets)
            out[-1] = n.sum(0)
            return out

        counts = _summed(table, seen, rows)
        total = max(1.0, counts[-1].sum())
        share = counts[:-1].sum(1) / total
        scale = np.sqrt(np.maximum(share * (1 - share), 0))
        inverse = np.append(np.where(scale > 0, 1 / np.where(scale > 0, scale, 1), 0), 1.0)[:, None]

        def value(x: np.ndarray) -> tuple[float, np.ndarray]:
            scaled = x.reshape(rows, 4)
            shared = spark.sparkContext.broadcast(scaled * inverse)

            def part(f: np.ndarray, n: np.ndarray) -> np.ndarray:
                log_p = _log_odds(f, shared.value)
                out, miss = np.zeros((rows + 1, 4)), n.sum(1, keepdims=True) * np.exp(log_p) - n
                for j in range(4):
                    out[:-2, j] = np.bincount(f.ravel(), np.repeat(miss[:, j], f.shape[1]), buckets)
                out[-2], out[-1, 0] = miss.sum(0), -(n * log_p).sum()
                return out

            found = _summed(table, part, rows + 1) / total
            shared.destroy()
            own = np.vstack((scaled[:-1], np.zeros((1, 4))))  # the intercept is free
            return float(found[-1, 0] + small / 2 * (own * own).sum()), (found[:-1] * inverse + small * own).ravel()

        first = np.zeros((rows, 4))
        first[-1] = np.log(np.maximum(counts[-1], 1e-3) / total)
        self.weights = lowest(value, first.ravel(), rounds).reshape(rows, 4) * inverse

    def segment(self, sents: DataFrame) -> DataFrame:
        spark, buckets = sents.sparkSession, self.buckets
        shared = spark.sparkContext.broadcast(self.weights)

        def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for f in frames:
                out, texts, langs = [], f["s"].tolist(), f["lang"].tolist()
                ends = np.cumsum([len(s) for s in texts]) >> 16
                for some in np.split(np.arange(len(texts)), np.flatnonzero(np.diff(ends)) + 1):
                    own, sizes = [texts[j] for j in some], np.array([len(texts[j]) for j in some])
                    x = feature_buckets([langs[j] for j in some], own, buckets).astype(np.int64)
                    log_p = np.concatenate([_log_odds(x[a:a + (1 << 14)], shared.value) for a in range(0, len(x), 1 << 14)])
                    tags, at = best_tags(np.maximum(log_p, np.log(1e-12)), sizes), 0
                    for s in own:
                        stops = (np.flatnonzero(tags[at:at + len(s)] >= 2) + 1).tolist()
                        out.append([s[a:b] for a, b in zip([0, *stops], [*stops, len(s)]) if a < b])
                        at += len(s)
                yield pd.DataFrame({"lang": f["lang"], "s": f["s"], "words": out})

        tasks = max(int(spark.conf.get("spark.sql.shuffle.partitions")), 2 * spark.sparkContext.defaultParallelism)
        distinct = sents.select("lang", "s").where("s is not null and s <> ''").repartition(tasks, "lang", "s").distinct()
        return with_results(sents, distinct.mapInPandas(run, "lang string, s string, words array<string>"), {"words": F.array().cast("array<string>")})
