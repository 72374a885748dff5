"""Segmenters: edge weights, Laplacian, spectrum, clusters, words.

``segment`` works on distinct sentences once.  The model (and the word lists)
are broadcast while their checked size allows; above the limit weights come from
joins, and only the spectral kernel runs in Python, on bands.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass, field, replace

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, functions as F

from cutseg.functions import kernels as K
from cutseg.operators import affinity
from cutseg.operators.corpus import PAD, NgramModel

#: Rows of a model that may be broadcast to the kernel.
BROADCAST_ROWS = 2_000_000
#: Words that may be broadcast as a table of hashes, to be matched in place.
BROADCAST_WORDS = 6_000_000
#: Blocks up to this length are decomposed as stacks without a look at their pivots.
TINY_BLOCK = 8
#: Distinct windows whose weights, after a hook, may be broadcast.
BROADCAST_WINDOWS = 4_000_000
_OUT = "lang string, s string, cut int, k int, forced boolean, words array<string>"


@dataclass(frozen=True)
class SegmentConfig:
    """All parameters of a segmenter; see the presets below."""

    form: str = "plain"
    use_skip: bool = True
    self_loop: float = 1.0
    divisors: dict = field(default_factory=lambda: {1: 4.0, 2: 80.0})
    boost: float | None = None
    max_rank: int | None = None
    match: str = "substring"  # or in_place: the word itself stands in the sentence
    singles: str | None = None  # None, rank or count
    floor: float = 20.0
    numer: float = 1e6
    unit: float = 250.0
    skip_boosted: bool = True
    cut: float | str | None = 0.15  # "gap": the sentence's largest relative step
    k: int | None = None
    cluster: str = "kmeans"  # or contiguous
    init: str = "even"
    jitter: float = 0.0
    seed: int = 0
    normalise: bool | None = None
    decompose: bool = False
    max_n: int = 512
    postprocess: bool = False


#: The three published algorithms, literally; SCALE twins decompose at zero edges and split contiguously.
DOMAIN = SegmentConfig()
LEXICON = SegmentConfig(form="sym", use_skip=False, divisors={}, boost=20.0, max_rank=25_000, singles="rank", cut=0.00035, postprocess=True)
TRAINED = SegmentConfig(form="sym", use_skip=False, divisors={}, boost=20.0, singles="count", skip_boosted=False, cut=0.001, postprocess=True)
#: For weights that are probabilities of a bond.
LEARNED = SegmentConfig(form="sym", use_skip=False, divisors={}, decompose=True, cluster="contiguous", cut=0.05)
DOMAIN_SCALE, LEXICON_SCALE, TRAINED_SCALE = (replace(c, decompose=True, cluster="contiguous") for c in (DOMAIN, LEXICON, TRAINED))


def explain_segment(cfg: SegmentConfig, model_rows: int) -> list[str]:
    """What the plan does beyond the literal algorithm."""
    out = ["distinct sentences", "broadcast model" if model_rows <= BROADCAST_ROWS else "model joins on distinct windows"]
    out += ["component decomposition"] * cfg.decompose + ["contiguous split"] * (cfg.cluster == "contiguous")
    out += [f"sentences over {cfg.max_n}: k of the whole by inertia, clusters of parts between weak edges"]
    return out


def _codes(texts: list[str]) -> np.ndarray:
    """Code points of texts, an end mark before, between and behind them."""
    return np.frombuffer((PAD + PAD.join(texts) + PAD).encode("utf-32-le", "surrogatepass"), "<u4").astype(np.uint64)


def _keys(codes: np.ndarray, n: int) -> np.ndarray:
    """n <= 3 neighbouring symbols as one number, for each place where n follow."""
    out = codes[:len(codes) - n + 1]
    for j in range(1, n):
        out = out << np.uint64(21) | codes[j:len(codes) - n + 1 + j]
    return out


class _Lookup:
    """Numbers by key, for arrays of keys; zeros (place -1) where a key is not held."""

    def __init__(self, keys, values=(), columns=None):
        keys = np.asarray(keys, np.uint64)
        order = np.argsort(keys, kind="stable")
        self.keys, self.values = keys[order], [np.asarray(v, float)[order] for v in (zip(*values) if columns is None else columns)]

    def places(self, keys: np.ndarray) -> np.ndarray:
        if not len(self.keys):
            return np.full(len(keys), -1)
        at = np.minimum(np.searchsorted(self.keys, keys), len(self.keys) - 1)
        return np.where(self.keys[at] == keys, at, -1)

    def holds(self, keys: np.ndarray) -> np.ndarray:
        return self.places(keys) >= 0

    def get(self, keys: np.ndarray) -> list[np.ndarray]:
        at = self.places(keys)
        return [np.where(at >= 0, v[at], 0.0) for v in self.values] if len(self.keys) else [np.zeros(len(keys))] * 4


def _by_text(held: dict) -> _Lookup:
    """Numbers by a text of up to three symbols."""
    return _Lookup([sum(ord(c) << 21 * (len(g) - 1 - j) for j, c in enumerate(g)) for g in held], [v if isinstance(v, tuple) else (v,) for v in held.values()])


class _Weights:
    """Edge weights of sentences from the tables of one language."""

    def __init__(self, cfg: SegmentConfig, parts: dict):
        self.cfg, self.bi, self.tri, self.words = cfg, _by_text(parts.get("bi", {})), _by_text(parts.get("tri", {})), parts.get("words")
        self.sets = {i: _by_text(dict.fromkeys(parts.get("sets", {}).get(i, ()), 1.0)) for i in (1, 2)}
        self.pairs, self.singles = _by_text(dict.fromkeys(parts.get("pairs", ()), 1.0)), _by_text(parts.get("singles", {}))
        self.windows = None
        if parts.get("windows") is not None:  # four symbols: places of two pairs
            left, right, w = parts["windows"]
            self.ends = _Lookup(np.unique(np.concatenate((left, right))))
            self.windows = _Lookup(self._window_keys(left, right)[0], columns=[w])

    def _window_keys(self, left: np.ndarray, right: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        p, q = self.ends.places(left), self.ends.places(right)
        return p.astype(np.uint64) << np.uint64(32) | q.astype(np.uint64) & np.uint64(0xFFFFFFFF), (p >= 0) & (q >= 0)

    def many(self, texts: list[str]) -> list[tuple[np.ndarray, np.ndarray]]:
        """Bands of each sentence; all are looked up at once."""
        cfg, codes = self.cfg, _codes(texts)
        pairs = _keys(codes, 2)  # place j: symbols j and j + 1 with the marks counted
        if self.windows is not None:
            keys, known = self._window_keys(pairs[:-2], pairs[2:])
            w = np.concatenate(([0.0], np.where(known, self.windows.get(keys)[0], 0.0), [0.0]))
        tri = self.tri.get(_keys(codes, 3)) if self.windows is None or cfg.use_skip else None
        if self.windows is None:
            p, z, *_ = self.bi.get(pairs)
            p = np.maximum(p, np.concatenate(([0.0], tri[0])))
            w = np.maximum(p, np.concatenate((tri[1], [0.0]))) * z
            for set_id, divisor in cfg.divisors.items():
                own = self.sets[1 if set_id == 1 else 2].holds(codes)
                w = np.where(own[:-1] | own[1:], w / divisor, w)
            boosted = np.zeros(len(w), bool)
            if cfg.boost:
                boosted = self.pairs.holds(pairs) if cfg.match != "in_place" else self.words.inside(codes) if self.words is not None else boosted
                w = np.where(boosted, w * cfg.boost, w)
            if cfg.singles:
                d = self.singles.get(codes)[0]
                d = np.maximum(d[:-1], d[1:])
                w = np.where((d != 0) & ~(boosted & cfg.skip_boosted), w / np.where(d != 0, d, 1.0), w)
        if cfg.use_skip:
            skips = tri[2] * tri[3]
            if cfg.divisors:
                hard = self.sets[2].holds(codes)
                skips = np.where(hard[:-2] | hard[1:-1] | hard[2:], 0.0, skips)
        out, at = [], 1
        for s in texts:
            n = len(s)
            out.append((w[at:at + max(0, n - 1)], skips[at:at + max(0, n - 2)] if cfg.use_skip else np.zeros(max(0, n - 2))))
            at += n + 1
        return out

    def bands(self, s: str) -> tuple[np.ndarray, np.ndarray]:
        return self.many([s])[0]


def _open_places(adj: np.ndarray, skip: np.ndarray) -> list[int]:
    """Where parts begin, as no edge crosses."""
    if not len(adj):
        return []
    s = np.concatenate(([0.0], skip, [0.0]))
    return (np.flatnonzero((adj == 0) & (s[:-1] == 0) & (s[1:] == 0)) + 1).tolist()


def _fragments(adj: np.ndarray, skip: np.ndarray, cfg: SegmentConfig) -> tuple[list[tuple[int, int]], bool]:
    """Parts that are clustered each for itself, and whether a part was forced."""
    n, starts = len(adj) + 1, [0]
    if cfg.decompose or n > cfg.max_n:
        starts += _open_places(adj, skip)
    out, forced = [], False
    for a, b in zip(starts, [*starts[1:], n]):
        while b - a > cfg.max_n:
            cut = a + cfg.max_n // 2 + int(adj[a + cfg.max_n // 2 - 1:a + cfg.max_n - 1].argmin())
            out.append((a, cut))
            a, forced = cut, True
        out.append((a, b))
    return out, forced


def _within(values: np.ndarray, cfg: SegmentConfig, cut) -> int:
    """Number of eigenvalues, which ascend, within the cut."""
    cut = K.gap_cut(values) if cut == "gap" else cut
    return min(len(values), cfg.k) if cfg.k else max(1, int(np.searchsorted(values, cut * (1 + K.SLACK) + K.TINY, "right")))


def _rows_of(values: np.ndarray, vectors: np.ndarray, cfg: SegmentConfig, seed: int, cut) -> tuple[int, np.ndarray | None]:
    """Number of eigenvalues within the cut, and the rows that are clustered;
    none where all or no symbols stay together."""
    k = _within(values, cfg, cut)
    if k in (1, len(values)):
        return k, None
    u = vectors[:, :k]
    if cfg.normalise if cfg.normalise is not None else cfg.form == "sym":
        length = np.linalg.norm(u, axis=1, keepdims=True)
        u = np.where(length > 0, u / np.where(length > 0, length, 1), u)
    if cfg.jitter:
        u = u + np.random.default_rng(seed).normal(0, cfg.jitter, u.shape)
    return k, u


def labels_of(adj: np.ndarray, skip: np.ndarray, cfg: SegmentConfig, seed: int) -> tuple[int, np.ndarray]:
    """Number of eigenvalues within the cut, and the cluster of each symbol."""
    n = len(adj) + 1
    if n == 1:
        return 1, np.zeros(1, int)
    k, u = _rows_of(*np.linalg.eigh(K.laplacians(adj[None], skip[None], cfg.form, cfg.self_loop)[0]), cfg, seed, cfg.cut)
    if u is None:
        return k, np.zeros(n, int) if k == 1 else np.arange(n)
    return k, K.contiguous_split(u, k) if cfg.cluster == "contiguous" else K.kmeans(u, k, cfg.init, seed)


def _spectra(bands: list[tuple[np.ndarray, np.ndarray]], cfg: SegmentConfig, cuts: list, low: bool = False) -> list[tuple[np.ndarray, np.ndarray]]:
    """Eigenvalues, ascending, of each item, and the eigenvectors that the largest
    cut takes.  A matrix falls into blocks where no edge crosses; blocks of equal
    length are decomposed as a stack, and their spectra together are the whole's.

    With ``low`` eigenvalues beyond the largest cut may stand as infinite, and the
    vectors of equal ones may be any (``_low_spectra``)."""
    if low and bands and _by_cut(cfg, cuts):
        return _low_spectra(bands, cfg, cuts)
    found: list[list] = []
    by_n: dict[int, list[tuple[int, int, int]]] = {}
    for j, (adj, skip) in enumerate(bands):
        starts = [0, *_open_places(adj, skip), len(adj) + 1]
        found.append([None] * (len(starts) - 1))
        for i, (a, b) in enumerate(zip(starts, starts[1:])):
            by_n.setdefault(b - a, []).append((j, i, a))
    for n, members in by_n.items():
        adj = np.array([bands[j][0][a:a + n - 1] for j, _, a in members]).reshape(len(members), n - 1)
        skip = np.array([bands[j][1][a:a + max(0, n - 2)] for j, _, a in members]).reshape(len(members), max(0, n - 2))
        for (j, i, a), v, u in zip(members, *np.linalg.eigh(K.laplacians(adj, skip, cfg.form, cfg.self_loop))):
            found[j][i] = a, v, u
    out = []
    for blocks in found:
        values = np.concatenate([v for _, v, _ in blocks]) if len(blocks) > 1 else blocks[0][1]
        order = np.argsort(values, kind="stable")
        values = values[order]
        k = max(_within(values, cfg, cut) for cut in cuts)
        if len(blocks) == 1:
            out.append((values, np.asfortranarray(blocks[0][2][:, :k])))
            continue
        place = np.empty(len(values), int)  # the column of each block's vectors
        place[order] = np.arange(len(values))
        vectors = np.zeros((len(values), k), order="F")
        for a, v, u in blocks:
            own = place[a:a + len(v)]
            own = own[own < k]  # a block's values ascend, so these are its first ones
            vectors[a:a + len(v), own] = u[:, :len(own)]
        out.append((values, vectors))
    return out


def _by_cut(cfg: SegmentConfig, cuts: list) -> bool:
    """Whether only what is within a cut counts: noise is added to coordinates, so
    signs matter there."""
    return not cfg.k and not cfg.jitter and "gap" not in cuts


def _low_spectra(bands: list[tuple[np.ndarray, np.ndarray]], cfg: SegmentConfig, cuts: list) -> list[tuple[np.ndarray, np.ndarray]]:
    """``_spectra`` with infinite eigenvalues beyond the largest cut: a block that
    has none within it but 0 is not decomposed, as its vector is known (so its equal
    rows are equal, and not up to rounding).  Of other blocks over ``TINY_BLOCK``
    symbols only vectors within the cut are found, from the bands."""
    cut = max(cuts)
    one, two, lengths = K.flat_bands(bands)
    rows, degrees = K.band_rows(one, two, cfg.form, cfg.self_loop)
    starts = K.block_starts(one, two)
    sizes = np.diff(starts, append=len(one))
    first = lengths.cumsum() - lengths  # of each item
    item = np.repeat(np.arange(len(lengths)), lengths)
    null = K.null_vectors(degrees, starts, sizes, cfg.form)
    values = np.full(len(one), np.inf)
    values[starts] = 0.0
    known = sizes == 1
    large = np.flatnonzero(sizes > TINY_BLOCK)
    known[large] = K.only_zero_within(rows, starts[large], sizes[large], cut)
    stacks: list[tuple[np.ndarray, np.ndarray]] = []  # starts, vectors (block, symbol, column)
    large = large[~known[large]]
    left = []
    for a, n, got in zip(starts[large], sizes[large], K.low_vectors(rows, starts[large], sizes[large], cut)):
        if got is None:
            left.append((a, n))
            continue
        values[a:a + n] = got[0]
        stacks.append((np.array([a]), got[1][None]))
    few = np.flatnonzero((sizes > 1) & (sizes <= TINY_BLOCK))
    left = np.array([*left, *zip(starts[few], sizes[few])], int).reshape(-1, 2)
    for n in np.unique(left[:, 1]):
        own = left[left[:, 1] == n, 0]
        at = own[:, None] + np.arange(n)
        v, u = np.linalg.eigh(K.laplacians(one[at[:, :-1]], two[at[:, :-2]], cfg.form, cfg.self_loop))
        values[at] = v
        alone = v[:, 1] > cut * (1 + 1e-9) + 1e-12
        u[alone, :, 0] = null[at[alone]]
        stacks.append((own, u))
    order = np.lexsort((values, item))
    place = np.empty(len(values), int)  # the column of each vector in its item
    place[order] = np.arange(len(values)) - first[item[order]]
    values = values[order]
    k = np.maximum(1, np.add.reduceat(values <= cut * (1 + K.SLACK) + K.TINY, first))
    base = (k * lengths).cumsum() - k * lengths
    held = np.zeros(int((k * lengths).sum()))
    # a vector's place in what is held: its item's columns one behind the other
    column = base[item] + place * lengths[item]
    taken = place < k[item]
    row = np.arange(len(values)) - first[item]
    alone = np.flatnonzero(np.repeat(known, sizes))
    head = np.repeat(starts, sizes)[alone]
    some = taken[head]
    held[column[head[some]] + row[alone[some]]] = null[alone[some]]
    for own, u in stacks:
        if len(own) == 1:
            a, n = int(own[0]), u.shape[1]
            c = int(taken[a:a + u.shape[2]].sum())  # a block's values ascend, so these are its first ones
            held[column[a:a + c, None] + np.arange(row[a], row[a] + n)] = u[0].T[:c]
        else:
            at = own[:, None] + np.arange(u.shape[1])
            m, c = np.nonzero(taken[at])
            held[column[at[m, c], None] + row[at[m]]] = u[m, :, c]
    return [(values[a:a + n], held[b:b + m * n].reshape(m, n).T) for a, n, b, m in zip(first.tolist(), lengths.tolist(), base.tolist(), k.tolist())]


def split_cuts(rows: list[tuple[str, np.ndarray, np.ndarray]], cfg: SegmentConfig, cuts: list) -> list[list[tuple[int, bool, list[str]]]]:
    """For each cut: k, forced, words of sentences with their bands.  Parts are
    taken in the order of their length, so that many are worked on as a stack,
    and decomposed once for all cuts."""
    parts = [_fragments(adj, skip, cfg) for _, adj, skip in rows]
    labels: list[dict[tuple[int, int], tuple[int, np.ndarray]]] = [{} for _ in cuts]
    todo = sorted((b - a, r, a) for r, (fragments, _) in enumerate(parts) for a, b in fragments)
    most = 1 << 22 if _by_cut(cfg, cuts) else 1 << 20  # whole matrices are not formed there
    while todo:
        step = max(1, most // todo[-1][0] ** 2)  # the longest go first
        todo, chunk = todo[:-step], todo[-step:]
        spectra = _spectra([(rows[r][1][a:a + n - 1], rows[r][2][a:a + max(0, n - 2)]) for n, r, a in chunk], cfg, cuts, low=True)
        for own, cut in zip(labels, cuts):
            stacks: dict[int, list[tuple]] = {}
            for (n, r, a), spectrum in zip(chunk, spectra):
                # the seed depends on the sentence alone, so no result depends on partitions
                seed = (cfg.seed * 1_000_003 + sum(map(ord, rows[r][0])) * 31 + a) % 2**32
                k, u = _rows_of(*spectrum, cfg, seed, cut)
                if u is None:
                    own[r, a] = k, np.zeros(n, int) if k == 1 else np.arange(n)
                elif cfg.cluster == "contiguous":
                    own[r, a] = k, K.contiguous_split(u, k)
                else:
                    stacks.setdefault(n, []).append((r, a, u, seed))
            for members in stacks.values():
                for (r, a, u, _), found in zip(members, K.kmeans_stack([u for _, _, u, _ in members], cfg.init, [s for *_, s in members])):
                    own[r, a] = u.shape[1], found
    return [_words_of(rows, parts, own, cfg, cut) for own, cut in zip(labels, cuts)]


def _words_of(rows: list, parts: list, labels: dict, cfg: SegmentConfig, cut) -> list[tuple[int, bool, list[str]]]:
    out = []
    for r, (s, _, _) in enumerate(rows):
        fragments, forced = parts[r]
        words, k = [], 0
        for a, b in fragments:
            own, lab = labels[r, a]
            k += own
            edges = [a, *(a + 1 + np.flatnonzero(np.diff(lab))).tolist(), b]
            words += [s[x:y] for x, y in zip(edges, edges[1:])]
        if forced and not cfg.k and cut != "gap":  # the parts' numbers need not add up to the sentence's
            k = K.inertia(*rows[r][1:], cfg.form, cfg.self_loop, cut)
        out.append((k, forced, K.join_numbers_dates(words) if cfg.postprocess else words))
    return out


def split_sentences(rows: list[tuple[str, np.ndarray, np.ndarray]], cfg: SegmentConfig) -> list[tuple[int, bool, list[str]]]:
    """k, forced, words of sentences with their bands."""
    return split_cuts(rows, cfg, [cfg.cut])[0]


def by_language(cfg: SegmentConfig, shared):
    """Weights of a language; one without a model has none."""
    none = _Weights(cfg, {})
    return lambda lang: shared.value.get(lang, none)


def bands_of(langs, texts, weights) -> list[tuple[str, np.ndarray, np.ndarray]]:
    """Sentences with their bands, in their order; those of a language are looked
    up together, up to some 2^16 symbols at once."""
    out, by_lang = [None] * len(texts), {}
    for j, lang in enumerate(langs):
        by_lang.setdefault(lang, []).append(j)
    for lang, places in by_lang.items():
        ends = np.cumsum([len(texts[j]) for j in places]) >> 16
        for some in np.split(np.array(places), np.flatnonzero(np.diff(ends)) + 1):
            for j, (adj, skip) in zip(some, weights(lang).many([texts[j] for j in some])):
                out[j] = texts[j], adj, skip
    return out


def _listed(words: DataFrame | None, cfg: SegmentConfig) -> DataFrame | None:
    """What a broadcast needs of the words: themselves if they are matched in
    place, else the pairs inside them, of which there are few."""
    if words is None or not cfg.boost:
        return None
    words = words if cfg.max_rank is None else words.where(F.col("rank") < cfg.max_rank)
    return words.where(F.length("word") >= 2).select("lang", "word") if cfg.match == "in_place" else affinity.word_bigrams(words)


def _word_tables(listed: DataFrame) -> dict[str, K.WordTable]:
    """Words to be matched in place: some 20 bytes a word."""
    held = listed.where("lang is not null").select("lang", "word").toArrow()
    own = {lang: held.filter(pc.equal(held.column("lang"), lang)).column("word").to_pylist() for lang in held.column("lang").unique().to_pylist()}
    return {lang: K.WordTable(words, np.ones(len(words))) for lang, words in own.items()}


def _collected(model: NgramModel, cfg: SegmentConfig, sets, words, singles, windows: pa.Table | None = None) -> dict[str, _Weights]:
    """The weights of each language; sizes were checked."""
    out: dict = {}
    get = lambda lang: out.setdefault(lang, {"bi": {}, "tri": {}, "sets": {}, "words": None, "pairs": set(), "singles": {}})
    for r in model.bi.select("lang", "a", "b", "p1", "z").toPandas().itertuples(index=False) if windows is None else ():
        get(r.lang)["bi"][r.a + r.b] = (r.p1, r.z)
    for r in model.tri.select("lang", "a", "b", "c", "f2", "b2", "pair", "z").toPandas().itertuples(index=False) if windows is None or cfg.use_skip else ():
        get(r.lang)["tri"][r.a + r.b + r.c] = (r.f2, r.b2, r.pair, r.z)
    for lang in windows.column("lang").unique().to_pylist() if windows is not None else ():
        own = windows.filter(pc.equal(windows.column("lang"), lang))
        get(lang)["windows"] = tuple(own.column(c).to_numpy().astype(kind) for c, kind in (("left", np.uint64), ("right", np.uint64), ("w", float)))
    for r in sets.collect() if sets is not None else ():
        get(r["lang"])["sets"].setdefault(r["set_id"], set()).add(r["ch"])
    listed = _listed(words, cfg)
    if listed is not None and cfg.match == "in_place":
        for lang, table in _word_tables(listed).items():
            get(lang)["words"] = table
    elif listed is not None:
        for r in listed.toPandas().itertuples(index=False):
            get(r.lang)["pairs"].add(r.a + r.b)
    for r in singles.collect() if singles is not None and cfg.singles else ():
        d = max(cfg.floor, float(np.log(cfg.numer / r["rank"]))) if cfg.singles == "rank" else max(1.0, r["cnt"] / cfg.unit)
        get(r["lang"])["singles"][r["ch"]] = d
    if windows is not None:
        for parts in out.values():
            parts.setdefault("windows", (np.zeros(0, np.uint64), np.zeros(0, np.uint64), np.zeros(0)))
    # a language may be null: of such rows no model holds anything
    return {lang: _Weights(cfg, parts) for lang, parts in out.items() if isinstance(lang, str)}


def _weighed(edges: DataFrame, cfg: SegmentConfig, sents, sets, words, singles, hook) -> DataFrame:
    """What the lists and the hook make of plain adjacent edges."""
    if sets is not None and cfg.divisors:
        edges = affinity.weaken(edges, sets, cfg.divisors)
    if cfg.boost and words is not None:
        if cfg.match == "in_place":
            edges = affinity.boost_in_place(edges, sents, words, cfg.boost, cfg.max_rank)
        else:
            edges = affinity.boost(edges, words, cfg.boost, cfg.max_rank)
    if cfg.singles and singles is not None:
        edges = edges if "boosted" in edges.columns else edges.withColumn("boosted", F.lit(False))
        if cfg.singles == "rank":
            edges = affinity.split_singles(edges, singles, cfg.floor, cfg.numer, cfg.skip_boosted)
        else:
            edges = affinity.split_singles_by_count(edges, singles.withColumnRenamed("ch", "word"), cfg.unit, cfg.skip_boosted)
    return hook(edges) if hook else edges


def _window_weights(distinct: DataFrame, model: NgramModel, cfg: SegmentConfig, sets, words, singles, hook) -> pa.Table | None:
    """``lang, left, right, w`` of each distinct window, the hook applied: the code
    points of its two pairs as numbers (0 at an end); None if there are too many
    to broadcast."""
    kinds = window_kinds(distinct).distinct()
    edges = affinity.kind_weights(kinds, model).select(F.concat_ws(":", F.hex("o"), F.hex("x")).alias("sent_id"), "lang", F.lit(0).alias("i"), "a", "b", "w")
    side = lambda j: F.unhex(F.split("sent_id", ":")[j]).cast("string")
    pair = lambda a, b: F.shiftleft(F.ascii(a).cast("long"), 21).bitwiseOR(F.ascii(b).cast("long"))
    rows = _weighed(edges, cfg, None, sets, words, singles, hook).where("lang is not null").select("lang", pair(side(0), F.col("a")).alias("left"), pair(F.col("b"), side(1)).alias("right"), F.col("w").cast("double").alias("w"))
    held = rows.limit(BROADCAST_WINDOWS + 1).toArrow()
    return held if held.num_rows <= BROADCAST_WINDOWS else None


#: Distinct windows that a task holds before it hands them on.
HELD_WINDOWS = 1 << 20


def window_kinds(sents: DataFrame) -> DataFrame:
    """``lang, o, a, b, x`` of the windows of all sentences (``affinity.windows``),
    made distinct in each task by code points: no row is made for a symbol."""
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict = {}

        def rows() -> Iterator[pa.RecordBatch]:
            for lang, found in ((k, v) for k, v in held.items() if v):
                chars = [pa.array(["" if c == 0 and side else chr(c) for c in column], pa.string()) for column, side in zip(zip(*found), (True, False, False, True))]
                yield pa.RecordBatch.from_arrays([pa.array([lang] * len(found), pa.string()), *chars], ["lang", "o", "a", "b", "x"])
            held.clear()

        for batch in batches:
            groups = batch.column(0).dictionary_encode()
            place, names = groups.indices.fill_null(len(groups.dictionary)).to_numpy(zero_copy_only=False), [*groups.dictionary.to_pylist(), None]
            for j in np.unique(place):
                texts = batch.column(1).filter(pa.array(place == j)).to_pylist()
                for some in (texts[i:i + 1000] for i in range(0, len(texts), 1000)):
                    held.setdefault(names[j], set()).update(_kinds(some))
                if sum(map(len, held.values())) > HELD_WINDOWS:
                    yield from rows()
        yield from rows()

    return sents.select("lang", "s").mapInArrow(run, "lang string, o string, a string, b string, x string")


def _kinds(texts: list[str]) -> list[tuple[int, int, int, int]]:
    """Distinct windows as code points, 0 beyond an end."""
    codes, sizes = _codes(texts), np.fromiter(map(len, texts), np.int64, len(texts))
    inside = np.ones(len(codes), bool)
    inside[np.concatenate(([0], np.cumsum(sizes + 1)))] = False  # the end marks
    at = np.flatnonzero(inside[1:-2] & inside[2:-1]) if len(codes) > 3 else np.zeros(0, int)
    left, right = (codes[at + j] << np.uint64(21) | codes[at + j + 1] for j in (0, 2))
    ends = np.unique(np.concatenate((left, right)))
    keys = np.unique(np.searchsorted(ends, left).astype(np.uint64) << np.uint64(32) | np.searchsorted(ends, right).astype(np.uint64))
    left, right, low = ends[(keys >> np.uint64(32)).astype(np.int64)], ends[(keys & np.uint64(0xFFFFFFFF)).astype(np.int64)], np.uint64(0x1FFFFF)
    return list(zip(*[c.tolist() for c in (left >> np.uint64(21), left & low, right >> np.uint64(21), right & low)]))


def bands_by_joins(sents: DataFrame, model: NgramModel, cfg: SegmentConfig, sets=None, words=None, singles=None, hook: Callable[[DataFrame], DataFrame] | None = None) -> DataFrame:
    """The bands of each sentence from joins with the model's tables.  ``hook``
    gets the adjacent edges last (``sent_id, lang, i, a, b, w``) and may weigh
    them anew from any context."""
    edges = affinity.adjacent_weights(sents, model)
    edges = _weighed(edges, cfg, sents, sets, words, singles, hook)
    skip = affinity.skip_weights(sents, model) if cfg.use_skip else None
    if skip is not None and sets is not None and cfg.divisors:
        skip = affinity.block_skip(skip, sets)
    return affinity.to_bands(sents, edges, skip)


def with_results(sents: DataFrame, done: DataFrame, empty: dict, by: tuple[str, ...] = ()) -> DataFrame:
    """``sent_id, lang, s, <by>`` of every sentence with the columns of ``done``,
    which is unique in (lang, s, by); ``empty`` gives those of null and empty
    sentences."""
    found = done.select(F.col("lang").alias("_lang"), F.col("s").alias("_s"), *[F.col(c).alias(f"_{c}") for c in by], *empty)
    same = F.col("_lang").eqNullSafe(F.col("lang")) & (F.col("_s") == F.col("s"))
    for c in by:
        same = same & (F.col(f"_{c}") == F.col(c))
    # texts in packed files look small enough to be collected on the driver
    rows = sents.select("sent_id", "lang", "s", *by).join(found.hint("merge"), same, "left")
    return rows.select("sent_id", "lang", "s", *by, *[F.coalesce(c, value).alias(c) for c, value in empty.items()])


def segment(sents: DataFrame, model: NgramModel, cfg: SegmentConfig, *, sets: DataFrame | None = None, words: DataFrame | None = None, singles: DataFrame | None = None, strategy: str | None = None, hook: Callable[[DataFrame], DataFrame] | None = None, by_window: bool = False, cuts: list[float] | None = None) -> DataFrame:
    """``sent_id, lang, s, k, forced, words`` for each sentence.

    ``sets``: lang, ch, set_id; ``words``: lang, word, rank (or cnt);
    ``singles``: lang, ch, rank or cnt.  A language without a model has zero
    edges: every symbol is a component.  Of a sentence over ``max_n`` symbols
    ``k`` is that of the whole, and parts between zero edges, else weak ones
    (``forced``), are clustered each for itself; a null language is a language like any
    other, without a model.  Null and empty sentences have no words and k = 0.

    With ``cuts`` there is one row for each sentence and cut (column ``cut``); a
    sentence is decomposed once.  ``by_window`` says that the hook's result
    depends on an edge's window alone (o, a, b, x); then it is asked once for
    each distinct window, with a made-up ``sent_id`` and ``i``.
    """
    spark = sents.sparkSession
    # the kernel is bound by CPU: a fixed number of tasks, which a small byte size does not merge
    tasks = max(int(spark.conf.get("spark.sql.shuffle.partitions")), 2 * spark.sparkContext.defaultParallelism)
    distinct = sents.select("lang", "s").where("s is not null and s <> ''").repartition(tasks, "lang", "s").distinct()
    windows, values = None, [cfg.cut] if cuts is None else list(cuts)
    if hook is not None:
        windows = _window_weights(distinct, model, cfg, sets, words, singles, hook) if by_window and cfg.match != "in_place" and strategy != "join" else None
        strategy = "join" if windows is None else "broadcast"
    if strategy is None:
        listed = _listed(words, cfg)
        most = BROADCAST_WORDS if cfg.match == "in_place" else BROADCAST_ROWS
        rows, held = model.tri.limit(BROADCAST_ROWS + 1).count(), listed.limit(most + 1).count() if listed is not None else 0
        strategy = "broadcast" if rows <= BROADCAST_ROWS and held <= most else "join"

    def results(langs: list, rows: list) -> Iterator[pa.RecordBatch]:
        K.one_thread()
        for j, done in enumerate(split_cuts(rows, cfg, values)):
            k, forced, words_ = zip(*done) if done else ((), (), ())
            columns = (langs, pa.string()), ([r[0] for r in rows], pa.string()), ([j] * len(rows), pa.int32()), (k, pa.int32()), (forced, pa.bool_()), (words_, pa.list_(pa.string()))
            yield pa.RecordBatch.from_arrays([pa.array(c, kind) for c, kind in columns], ["lang", "s", "cut", "k", "forced", "words"])

    if strategy == "broadcast":
        shared = spark.sparkContext.broadcast(_collected(model, cfg, sets, words, singles, windows))

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            weights = by_language(cfg, shared)
            for batch in batches:
                langs, texts = (c.to_pylist() for c in batch.columns)
                yield from results(langs, bands_of(langs, texts, weights))

        done = distinct.mapInArrow(run, _OUT)
    else:
        keyed = distinct.withColumn("sent_id", F.sha2(F.concat_ws("|", F.coalesce("lang", F.lit("")), F.col("lang").isNull().cast("string"), "s"), 256)).withColumn("n", F.length("s"))
        bands = bands_by_joins(keyed, model, cfg, sets, words, singles, hook).select("lang", "s", "adj", "skip")

        def run_bands(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for f in frames:
                rows = [(s, np.asarray(a, float), np.asarray(b, float)) for s, a, b in zip(f["s"], f["adj"], f["skip"])]
                yield from (b.to_pandas() for b in results(f["lang"].tolist(), rows))

        done = bands.mapInPandas(run_bands, _OUT)
    empty = {"k": F.lit(0), "forced": F.lit(False), "words": F.array().cast("array<string>")}
    if cuts is None:
        return with_results(sents, done, empty)
    every = sents.select("sent_id", "lang", "s", F.explode(F.sequence(F.lit(0), F.lit(len(values) - 1))).alias("cut"))
    return with_results(every, done, empty, ("cut",)).withColumn("cut", F.element_at(F.array(*[F.lit(float(c)) for c in values]), F.col("cut") + 1))
