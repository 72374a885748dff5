"""Convolutional text classifier for toxicity, trained in numpy.

Words are hashed to rows of an embedding table, of which rows that too few
training documents hit share one fixed zero vector (else rare words would let
the network learn documents by heart); filters of several widths slide over them,
the largest response of each filter in the whole text feeds one logistic unit.
Labels are only learned from documents outside the held-out fifth, and from all
of those: words are counted over all of them, they are dealt to shards that learn
side by side from the same network, and the networks are averaged between rounds.
Scoring covers all words of all texts.
"""

from __future__ import annotations

import pickle
import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, functions as F

from cutseg.llm.words import small_batches, tidy
from cutseg.operators import dense
from cutseg.plans.workspace import Workspace

_WORD = re.compile(r"[^\W\d_]+")
WIDTHS = (1, 2, 3)
ROWS = 1 << 20
#: Size of the embedding: of the rows, as many as speak most for one of the labels.
VOCABULARY = 1 << 15
#: Rounds, and least epochs of each, where there is more than one shard.
ROUNDS, EPOCHS = 3, 2
#: Labelled documents that a broadcast side may hold.
BROADCAST_LABELS = 2_000_000


class _WordRows(dict):
    """word -> row of the embedding table; remembers a bounded number."""

    def __init__(self, rows: int, limit: int = 50_000):
        super().__init__()
        self.rows, self.limit = rows, limit

    def __missing__(self, word: str) -> int:
        row = xxhash.xxh3_64_intdigest(word) % self.rows
        if len(self) < self.limit:
            self[word] = row
        return row


@dataclass
class TextCnn:
    """Parameters, all float32; ``index`` leads from a word's hashed row to its
    embedding of ``dim`` numbers, number 0 being the zero vector."""

    index: np.ndarray
    embed: np.ndarray
    kernels: list[np.ndarray]  # (width, dim, filters)
    shifts: list[np.ndarray]  # (filters,)
    out: np.ndarray
    bias: float

    @classmethod
    def fresh(cls, used: np.ndarray, dim: int = 8, filters: int = 8, seed: int = 11) -> TextCnn:
        rng, index = np.random.default_rng(seed), np.zeros(ROWS, np.int32)
        index[used] = np.arange(1, len(used) + 1)
        embed = rng.normal(0, 0.1, (len(used) + 1, dim)).astype(np.float32)
        embed[0] = 0
        return cls(index, embed,
                   [rng.normal(0, (w * dim) ** -0.5, (w, dim, filters)).astype(np.float32) for w in WIDTHS],
                   [np.zeros(filters, np.float32) for _ in WIDTHS], rng.normal(0, 0.1, len(WIDTHS) * filters).astype(np.float32), 0.0)

    def __getstate__(self) -> dict:
        """Of the index, the rows in use only: a model travels small."""
        return self.__dict__ | {"index": np.flatnonzero(self.index)}

    def __setstate__(self, state: dict) -> None:
        used, index = state["index"], np.zeros(ROWS, np.int32)
        index[used] = np.arange(1, len(used) + 1)
        self.__dict__.update(state | {"index": index})

    def tables(self) -> list[list[np.ndarray]]:
        """Each word's share in each filter at each place: the convolution of
        hashed words is a sum of rows of these."""
        return [[self.embed @ k[j] for j in range(len(k))] for k in self.kernels]


def word_rows(text: str | None, rows: _WordRows) -> np.ndarray:
    words = _WORD.findall(text.lower()) if text else ()
    return np.fromiter(map(rows.__getitem__, words), np.int64, len(words))


def _responses(ids: np.ndarray, parts: list[np.ndarray]) -> np.ndarray:
    """One filter group's responses at each place of a text."""
    n = len(ids) - len(parts) + 1
    r = parts[0][ids[:n]]
    for j in range(1, len(parts)):
        r = r + parts[j][ids[j:n + j]]
    return r


def pooled(ids: np.ndarray, tables: list[list[np.ndarray]], shifts: list[np.ndarray], step: int = 4096) -> np.ndarray:
    """Largest response of each filter, at least 0; a text shorter than a
    filter gives it 0.  Long texts go in overlapping steps."""
    out = []
    for parts, shift in zip(tables, shifts):
        best, w = np.zeros(len(shift), np.float32), len(parts)
        for i in range(0, len(ids) - w + 1, step):
            best = np.maximum(best, _responses(ids[i:i + step + w - 1], parts).max(0) + shift)
        out.append(best)
    return np.concatenate(out)


def sigmoid(x):
    return 1 / (1 + np.exp(-np.clip(x, -60, 60)))


def train(texts: list[np.ndarray], labels: np.ndarray, epochs: int | None = None, rate: float = 0.02, least_documents: int = 5, seed: int = 5, **shape) -> TextCnn:
    """Adagrad on the logistic loss; classes weigh the same.  Rows that fewer
    than ``least_documents`` texts hit are not used.  Small samples are seen more
    often (8 to 60 epochs)."""
    epochs = epochs or epochs_of(len(texts))
    hits = np.zeros(ROWS, np.int64)
    for t in texts:
        hits[np.unique(t)] += 1
    m = TextCnn.fresh(np.flatnonzero(hits >= least_documents), **shape)
    return advance(m, [m.index[t] for t in texts], labels, float(labels.mean()), epochs, rate, seed)


def epochs_of(n: int) -> int:
    return max(8, min(60, 20_000 // max(1, n)))


def advance(m: TextCnn, texts: list[np.ndarray], labels: np.ndarray, share: float, epochs: int, rate: float = 0.02, seed: int = 5) -> TextCnn:
    """Train ``m`` further on texts as rows of its embedding; ``share`` of all
    labels are 1."""
    rng, dim = np.random.default_rng(seed), m.embed.shape[1]
    n_f = len(m.shifts[0])
    weight = np.where(labels == 1, 0.5 / max(share, 1e-9), 0.5 / max(1 - share, 1e-9))
    seen = {"embed": np.full(m.embed.shape, 1e-3, np.float32), "out": np.full(m.out.shape, 1e-3), "bias": 1e-3,
            "kernels": [np.full(k.shape, 1e-3, np.float32) for k in m.kernels], "shifts": [np.full(n_f, 1e-3, np.float32) for _ in m.shifts]}
    for _ in range(epochs):
        for batch in np.array_split(rng.permutation(len(texts)), max(1, len(texts) // 16)):
            g_out, g_bias = np.zeros_like(m.out, np.float64), 0.0
            g_k, g_s = [np.zeros_like(k) for k in m.kernels], [np.zeros_like(s) for s in m.shifts]
            rows_hit, rows_grad = [], []
            for d in batch:
                ids, h, where = texts[d], [], []
                for k, shift in zip(m.kernels, m.shifts):
                    n = len(ids) - len(k) + 1
                    if n < 1:
                        h.append(np.zeros(n_f, np.float32))
                        where.append(None)
                        continue
                    e = m.embed[ids]
                    r = e[:n] @ k[0]
                    for j in range(1, len(k)):
                        r += e[j:n + j] @ k[j]
                    at = r.argmax(0)
                    h.append(np.maximum(r[at, np.arange(n_f)] + shift, 0))
                    where.append(at)
                hidden = np.concatenate(h)
                slope = weight[d] * (sigmoid(hidden @ m.out + m.bias) - labels[d]) / len(batch)
                g_out += slope * hidden
                g_bias += slope
                back = slope * m.out * (hidden > 0)
                for g, (k, at) in enumerate(zip(m.kernels, where)):
                    if at is None:
                        continue
                    b = back[g * n_f:(g + 1) * n_f].astype(np.float32)
                    g_s[g] += b
                    for j in range(len(k)):
                        hit = ids[at + j]
                        g_k[g][j] += m.embed[hit].T * b
                        rows_hit.append(hit)
                        rows_grad.append(k[j].T * b[:, None])
            if rows_hit:
                hit, inverse = np.unique(np.concatenate(rows_hit), return_inverse=True)
                grad = np.zeros((len(hit), dim), np.float32)
                np.add.at(grad, inverse, np.concatenate(rows_grad))
                grad[hit == 0] = 0
                seen["embed"][hit] += grad**2
                m.embed[hit] -= rate * 5 * grad / np.sqrt(seen["embed"][hit])
            for g in range(len(m.kernels)):
                seen["kernels"][g] += g_k[g] ** 2
                m.kernels[g] -= rate * g_k[g] / np.sqrt(seen["kernels"][g])
                seen["shifts"][g] += g_s[g] ** 2
                m.shifts[g] -= rate * g_s[g] / np.sqrt(seen["shifts"][g])
            seen["out"] += g_out**2
            m.out -= (rate * g_out / np.sqrt(seen["out"])).astype(np.float32)
            seen["bias"] += g_bias**2
            m.bias -= float(rate * g_bias / np.sqrt(seen["bias"]))
    return m


def best_threshold(scores: np.ndarray, labels: np.ndarray, negative: float = 1.0, slack: float = 0.005) -> float:
    """A cut with the best F1, less ``slack``; of those the nearest to 0.5.
    Each 0 in the sample stands for ``negative`` rows."""
    order = np.argsort(-scores, kind="stable")
    s, hit = scores[order], np.cumsum(labels[order])
    f1 = 2 * hit / (hit + negative * np.cumsum(1 - labels[order]) + labels.sum())
    f1[:-1][s[1:] == s[:-1]] = -1  # no cut between equal scores
    cuts = (s + np.append(s[1:], 0)) / 2
    best = np.flatnonzero(f1 >= f1.max() - slack)
    return float(cuts[best[np.abs(cuts[best] - 0.5).argmin()]])


def held_out(doc_id: Column) -> Column:
    return F.crc32(doc_id.cast("string")) % 5 == 0


class ToxicityModel:
    """A trained network with a common cut and cuts by language."""

    def __init__(self, net: TextCnn | None, common: float, by_lang: dict[str, float]):
        self.net, self.common, self.by_lang = net, common, by_lang

    @classmethod
    def fit(cls, docs: DataFrame, labels: DataFrame, *, shard: int = 6000, least_of_lang: int = 20, least_documents: int = 5, **shape) -> ToxicityModel:
        """Learn from all labelled documents outside the held-out fifth, about
        ``shard`` of them in a task.

        A third of them (``turn`` 0) sets the cuts.  Labels other than 0 and 1, and
        rows without id or text, are not used.  Without both classes every score
        is 0.
        """
        spark, ws = docs.sparkSession, Workspace(docs.sparkSession, "toxicity")
        small_batches(spark)
        known = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("toxic").cast("int").alias("toxic")).where("toxic in (0, 1)")
        known = known.where(~held_out(F.col("doc_id"))).groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
        n = known.count()
        shards = max(1, -(-n // shard))
        known = F.broadcast(known) if n <= BROADCAST_LABELS else known
        texts = docs.select(docs["doc_id"].cast("long").alias("doc_id"), docs["text"].cast("string").alias("text"), docs["lang"].cast("string").alias("lang"))
        rows = texts.where("text is not null").join(known, "doc_id").select("doc_id", "toxic", "lang", "text")
        hashed = ws.table(rows.mapInArrow(tidy(_hashed), "doc_id long, toxic int, lang string, turn int, ids binary"), "hashed")
        sizes = {(r["toxic"], r["part"]): r["n"] for r in hashed.groupBy("toxic", (F.col("turn") != 0).alias("part")).agg(F.countDistinct("doc_id").alias("n")).collect()}
        if len({label for label, _ in sizes}) < 2:
            return cls(None, 0.5, {})
        ones, zeros = sizes.get((1, True), 0), sizes.get((0, True), 0)
        fit = hashed.where("turn <> 0")
        # documents of each label that hold a row: figures of a fixed number of rows
        hits = [dense.collect_sums(fit.where(F.col("toxic") == label).select("ids").mapInArrow(_hits, dense.SCHEMA), ROWS).astype(float) for label in (0, 1)]
        net = TextCnn.fresh(telling_rows(*hits, zeros, ones, least_documents), **shape)
        shared = spark.sparkContext.broadcast(net)
        indexed = ws.table(hashed.mapInArrow(_indexed(shared), hashed.schema), "indexed")
        ws.drop("hashed")
        dealt = indexed.where("turn <> 0").withColumns({"order": F.xxhash64("doc_id"), "shard": F.pmod(F.xxhash64("doc_id", F.lit(1)), F.lit(shards))})
        rounds, epochs = (1, epochs_of(ones + zeros)) if shards == 1 else (ROUNDS, max(EPOCHS, epochs_of((ones + zeros) // shards) // ROUNDS))
        for turn in range(rounds if ones + zeros else 0):
            grown = dealt.groupBy("shard").applyInArrow(_advance(spark.sparkContext.broadcast(net), ones / (ones + zeros), epochs, 5 + 1000 * turn), "shard long, model binary")
            few = grown.withColumn("shard", F.col("shard") % -(-shards // 16)).groupBy("shard").applyInArrow(_added, "shard long, model binary")
            net = averaged(net, [pickle.loads(r["model"]) for r in few.orderBy("shard").collect()])
        scored = indexed.where("turn = 0").dropDuplicates(["doc_id"]).mapInArrow(_calibrate(spark.sparkContext.broadcast(net)), "lang string, toxic int, score double")
        found = [(r["lang"], r["toxic"], r["score"], r["n"]) for r in scored.groupBy("lang", "toxic", "score").agg(F.count("*").alias("n")).collect()]

        def cut_of(some: list) -> float | None:
            times = [r[3] for r in some]
            y, s = np.repeat([r[1] for r in some], times), np.repeat(np.array([r[2] for r in some], float), times)
            return best_threshold(s, y) if len(y) and min(y.sum(), len(y) - y.sum()) >= least_of_lang else None
        common = cut_of(sorted(found, key=lambda r: (r[2], r[1], str(r[0]))))
        own = {lang: cut_of(sorted(r for r in found if r[0] == lang)) for lang in sorted({r[0] for r in found} - {None})}
        return cls(net, 0.5 if common is None else common, {lang: cut for lang, cut in own.items() if cut is not None})

    def score(self, docs: DataFrame) -> DataFrame:
        """``doc_id, lang, score, predicted, threshold, rejected``.

        ``score`` moves the common cut to 0.5 and depends on the text alone;
        ``rejected`` applies the language's own cut (the common one where the
        language is null or had too few labelled rows).  Null, empty and
        wordless texts get the score of a text in which no filter responds.
        """
        small_batches(docs.sparkSession)
        rows = docs.select(docs["doc_id"].cast("long").alias("doc_id"), docs["lang"].cast("string").alias("lang"), docs["text"].cast("string").alias("text"))
        shared = docs.sparkSession.sparkContext.broadcast(self.net)
        scored = rows.mapInArrow(tidy(_score(shared, _logit(self.common))), "doc_id long, lang string, score double")
        cut = F.lit(0.5)
        for lang, value in sorted(self.by_lang.items()):
            cut = F.when(F.col("lang") == lang, float(sigmoid(_logit(value) - _logit(self.common)))).otherwise(cut)
        return (scored.withColumn("predicted", (F.col("score") >= 0.5).cast("int")).withColumn("threshold", cut)
                .withColumn("rejected", F.col("score") >= F.col("threshold")))


    def keep(self, docs: DataFrame) -> DataFrame:
        """The rows of ``docs``, all columns, that the language's cut does not
        reject; every batch is scored in place, nothing is shuffled."""
        small_batches(docs.sparkSession)
        names = docs.columns
        shared = docs.sparkSession.sparkContext.broadcast((self.net, self.common, self.by_lang))
        return docs.mapInArrow(tidy(_keep(shared, names.index("text"), names.index("lang"))), docs.schema)


def _logit(p: float) -> float:
    p = min(max(p, 1e-6), 1 - 1e-6)
    return float(np.log(p / (1 - p)))


def _keep(shared, text_at: int, lang_at: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        net, common, by_lang = shared.value
        if net is not None:
            rows, tables = _WordRows(ROWS), net.tables()
        for batch in batches:
            if net is not None:
                cut = np.array([sigmoid(_logit(by_lang.get(lang, common)) - _logit(common)) for lang in batch.column(lang_at).to_pylist()])
                batch = batch.filter(pa.array(_scores(net, tables, rows, batch.column(text_at).to_pylist(), _logit(common)) < cut))
            yield batch
    return run


def _scores(net: TextCnn, tables, rows: _WordRows, texts: list, shift: float) -> np.ndarray:
    hidden = [pooled(net.index[word_rows(t, rows)], tables, net.shifts) for t in texts]
    return sigmoid(np.array(hidden, float).reshape(len(hidden), len(net.out)) @ net.out.astype(float) + net.bias - shift)


def telling_rows(zeros: np.ndarray, ones: np.ndarray, n_zeros: int, n_ones: int, least_documents: int) -> np.ndarray:
    """The rows that at least so many documents hit; of more than ``VOCABULARY``
    those whose shares of the two labels differ most for their size."""
    used = np.flatnonzero(zeros + ones >= least_documents)
    if len(used) <= VOCABULARY:
        return used
    a, b, n, m = zeros[used], ones[used], max(1, n_zeros), max(1, n_ones)
    p = (a + b) / (n + m)
    z = np.abs(b / m - a / n) / np.sqrt(np.maximum(p * (1 - p), 1e-12) * (1 / n + 1 / m))
    return np.sort(used[np.argsort(-z, kind="stable")[:VOCABULARY]])


def _hashed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    rows = _WordRows(ROWS)
    for batch in batches:
        ids = [word_rows(t, rows).astype("<i4").tobytes() for t in batch.column(3).to_pylist()]
        turn = [xxhash.xxh3_64_intdigest(str(i)) % 3 for i in batch.column(0).to_pylist()]
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), batch.column(2), pa.array(turn, pa.int32()), pa.array(ids, pa.binary())], ["doc_id", "toxic", "lang", "turn", "ids"])


def _hits(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    hits = np.zeros(ROWS, np.int64)
    for batch in batches:
        for x in batch.column(0).to_pylist():
            hits[np.unique(np.frombuffer(x, "<i4"))] += 1
    yield dense.emit(hits)


def _indexed(shared):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        index = shared.value.index
        for batch in batches:
            ids = [index[np.frombuffer(x, "<i4")].astype("<i4").tobytes() for x in batch.column(4).to_pylist()]
            yield batch.set_column(4, "ids", pa.array(ids, pa.binary()))
    return run


def _advance(shared, share: float, epochs: int, seed: int):
    """Train the shared network on one shard, in the order of the ids' hashes."""
    def run(t: pa.Table) -> pa.Table:
        t = t.sort_by([("order", "ascending"), ("doc_id", "ascending")])
        doc_ids = t.column("doc_id").to_pylist()
        first = [i for i, d in enumerate(doc_ids) if not i or d != doc_ids[i - 1]]
        ids, y = t.column("ids"), t.column("toxic").to_numpy()[first]
        start = shared.value
        m = pickle.loads(pickle.dumps(start))
        advance(m, [np.frombuffer(ids[i].as_py(), "<i4") for i in first], y, share, epochs, seed=seed)
        part = {"n": 1, "touched": (m.embed != start.embed).any(1).astype(np.int32), "embed": m.embed - start.embed,
                "rest": [a - b for a, b in zip(_rest(m), _rest(start))]}
        return pa.table({"shard": pa.array([t.column("shard")[0].as_py()], pa.int64()), "model": pa.array([pickle.dumps(part)], pa.binary())})
    return run


def _rest(m: TextCnn) -> list[np.ndarray]:
    return [*m.kernels, *m.shifts, m.out, np.float64(m.bias)]


def _plus(a: dict | None, b: dict) -> dict:
    return b if a is None else {"n": a["n"] + b["n"], "touched": a["touched"] + b["touched"], "embed": a["embed"] + b["embed"], "rest": [x + y for x, y in zip(a["rest"], b["rest"])]}


def _added(t: pa.Table) -> pa.Table:
    total = None
    for model in sorted(t.column("model").to_pylist()):  # the same sum whatever came first
        total = _plus(total, pickle.loads(model))
    return pa.table({"shard": pa.array([t.column("shard")[0].as_py()], pa.int64()), "model": pa.array([pickle.dumps(total)], pa.binary())})


def averaged(start: TextCnn, parts: list[dict]) -> TextCnn:
    """The mean of the shards' networks; of an embedding, of those shards that
    met its word."""
    total, m = None, pickle.loads(pickle.dumps(start))
    for p in parts:
        total = _plus(total, p)
    m.embed += total["embed"] / np.maximum(1, total["touched"])[:, None]
    step = [x / total["n"] for x in total["rest"]]
    w = len(m.kernels)
    m.kernels, m.shifts = [k + s.astype(np.float32) for k, s in zip(m.kernels, step)], [k + s.astype(np.float32) for k, s in zip(m.shifts, step[w:])]
    m.out, m.bias = m.out + step[2 * w].astype(np.float32), m.bias + float(step[2 * w + 1])
    return m


def _calibrate(shared):
    """Scores of the rows that set the cuts, in steps of a ten-thousandth."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        net = shared.value
        tables = net.tables()
        for batch in batches:
            hidden = [pooled(np.frombuffer(x, "<i4"), tables, net.shifts) @ net.out.astype(float) + net.bias for x in batch.column(4).to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column(2), batch.column(1), pa.array(np.round(sigmoid(np.array(hidden, float)), 4), pa.float64())], ["lang", "toxic", "score"])
    return run


def _score(shared, shift: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        net = shared.value
        if net is not None:
            rows, tables = _WordRows(ROWS), net.tables()
        for batch in batches:
            score = np.zeros(batch.num_rows) if net is None else _scores(net, tables, rows, batch.column(2).to_pylist(), shift)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(score, pa.float64())], ["doc_id", "lang", "score"])
    return run


def op9_toxicity_cnn(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    model = ToxicityModel.fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return model.score(docs).select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", "predicted", "threshold", "rejected")
