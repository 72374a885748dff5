"""What keeps large tables within limits, with the same results as the plain way."""

import ctypes
from dataclasses import replace
from itertools import product

import numpy as np
from pyspark.sql import Window as W, functions as F

from cutseg.functions import kernels as K
from cutseg.operators import affinity, corpus as C, metrics as M, segment as S, tagger as T
from cutseg.sources import tables


def test_grams_are_counted_in_one_pass_without_a_row_for_each_symbol(spark):
    """The texts are read once, and no row is made for a symbol."""
    texts = [("xx", "abcab"), ("xx", "a𝒳é"), (None, "ab"), ("yy", "a"), ("xx", "ab\x00c"), ("yy", ""), ("xx", None)] * 3
    sents = spark.createDataFrame(texts, "lang string, s string").repartition(3)
    padded = C.padded_counts(sents)
    assert "Generate" not in padded._jdf.queryExecution().optimizedPlan().toString()
    for n, found in C.ngram_tables(sents, padded=padded).items():
        want = C.ngram_counts(sents, n).where(~F.contains("g", F.lit(C.PAD)))
        assert sorted(map(str, found.collect())) == sorted(map(str, want.collect()))
        assert found.schema["cnt"].dataType == want.schema["cnt"].dataType


def test_context_counts_grams_from_written_counts(spark, sf_dir, monkeypatch):
    """Three orders of grams do not take three passes."""
    from cutseg.plans.context import Context
    calls, padded_counts = [], C.padded_counts
    monkeypatch.setattr(C, "padded_counts", lambda *a: calls.append(1) or padded_counts(*a))
    x = Context(spark, sf_dir)
    assert sorted(x.grams) == [1, 2, 3] and len(calls) == 1
    assert x.grams[2].exceptAll(C.ngram_counts(x.train, 2)).count() == 0


def test_held_grams_are_handed_on(spark, monkeypatch):
    sents = spark.createDataFrame([("xx", f"{chr(97 + i % 26)}b{chr(97 + i // 26)}") for i in range(400)], "lang string, s string")
    want = sorted(C.ngram_tables(sents)[3].collect())
    monkeypatch.setattr(C, "HELD_GRAMS", 5)
    assert sorted(C.ngram_tables(sents)[3].collect()) == want and len(want) > 100


def plain_bands(cfg, s, bi, tri, sets, pairs, singles, words):
    """Weights of one sentence, symbol by symbol."""
    n, adj, skip = len(s), [], []
    inside = [any(s[a:b] in words for a in range(i + 1) for b in range(i + 2, n + 1)) for i in range(n - 1)]
    for i in range(n - 1):
        p, z = bi.get(s[i:i + 2], (0.0, 0.0))
        p = max(p, tri.get(s[i - 1:i + 2], (0.0,))[0] if i else 0.0, tri.get(s[i:i + 3], (0.0, 0.0))[1])
        w = p * z
        for set_id, divisor in cfg.divisors.items():
            w = w / divisor if set(s[i:i + 2]) & sets[set_id] else w
        hit = bool(cfg.boost) and (inside[i] if cfg.match == "in_place" else s[i:i + 2] in pairs)
        w = w * cfg.boost if hit else w
        d = max(singles.get(c, 0.0) for c in s[i:i + 2])
        adj.append(w / d if cfg.singles and d and not (hit and cfg.skip_boosted) else w)
    for i in range(n - 2):
        _, _, pair, z = tri.get(s[i:i + 3], (0.0,) * 4)
        skip.append(0.0 if not cfg.use_skip or cfg.divisors and set(s[i:i + 3]) & sets[2] else pair * z)
    return adj, skip


def test_weights_of_many_sentences_are_those_of_each(monkeypatch):
    """A language's sentences are weighed at once, and not symbol by symbol."""
    rng, symbols = np.random.default_rng(5), "abcé𝒳."
    bi = {a + b: (rng.random(), rng.random() * 3) for a in symbols for b in symbols if rng.random() < 0.7}
    tri = {g + c: tuple(rng.random(4)) for g in bi for c in symbols if rng.random() < 0.5}
    words, singles, sets = ["ab", "ab𝒳", "caé", "bbbb"], {"a": 2.0, "c": 30.0}, {1: {"b"}, 2: {"c"}}
    parts = {"bi": bi, "tri": tri, "sets": sets, "pairs": {"ab", "é𝒳"}, "singles": singles, "words": K.WordTable(words, np.ones(len(words)))}
    texts = ["".join(rng.choice(list(symbols), n)) for n in rng.integers(1, 40, 60)] + ["a", "zz", "ab"]
    for cfg in (S.DOMAIN, S.LEXICON, S.TRAINED, replace(S.TRAINED_SCALE, match="in_place"), S.SegmentConfig(divisors={})):
        found = S.bands_of(["xx", None, "yy"] * 21, texts, lambda lang: S._Weights(cfg, parts if lang == "xx" else {}))
        for j, (s, adj, skip) in enumerate(found):
            want = plain_bands(cfg, s, *((bi, tri, sets, parts["pairs"], singles, words) if j % 3 == 0 else ({}, {}, {1: set(), 2: set()}, (), {}, ())))
            assert s == texts[j] and (adj.tolist(), skip.tolist()) == want
    calls, many = [], S._Weights.many
    monkeypatch.setattr(S._Weights, "many", lambda self, t: calls.append(len(t)) or many(self, t))
    S.bands_of(["xx"] * 63, texts, lambda _: S._Weights(S.DOMAIN, parts))
    assert calls == [63]


def test_words_in_place_stay_broadcast_beyond_the_model_limit(spark, monkeypatch):
    """a long word list must not lead to joins over all substrings."""
    sents = spark.createDataFrame([(str(i), "xx", s, len(s)) for i, s in enumerate(["abcab", "abd", "cab"])], "sent_id string, lang string, s string, n int")
    words = spark.createDataFrame([("xx", f"ab{'c' * i}", 3) for i in range(60)], "lang string, word string, cnt long")
    model, cfg = C.fit_model(sents), replace(S.TRAINED_SCALE, match="in_place", cut=0.3)
    want = {r["sent_id"]: r["words"] for r in S.segment(sents, model, cfg, words=words, strategy="join").collect()}
    monkeypatch.setattr(S, "BROADCAST_ROWS", 20)
    found = S.segment(sents, model, cfg, words=words)
    assert "adj" not in found._jdf.queryExecution().analyzed().toString()
    assert {r["sent_id"]: r["words"] for r in found.collect()} == want


def test_only_vectors_within_the_cut_are_kept():
    """The spectra of a stack hold no column that no cut takes."""
    rng = np.random.default_rng(6)
    adj, skip = np.where(rng.random(89) < 0.1, 0, rng.random(89)), rng.random(88) * 0.1
    skip[np.flatnonzero(adj[1:] == 0)] = skip[np.flatnonzero(adj[:-1] == 0)] = 0
    values, vectors = np.linalg.eigh(K.laplacians(adj[None], skip[None], "plain")[0])
    (own, some), = S._spectra([(adj, skip)], S.DOMAIN, [0.05, 0.2])
    k = int(K.count_within(values, 0.2))
    assert some.shape == (90, k) and 1 < k < 90 and np.allclose(own, values)
    assert np.allclose(some @ some.T, vectors[:, :k] @ vectors[:, :k].T)


def test_tagger_reads_distinct_feature_rows(spark):
    """equal windows are one row with a count for each tag, not a row for each symbol."""
    raw = ["ab cd ab", "cd ab", "é ab.cd", "𝒳"] * 20
    sents = spark.createDataFrame([(str(i), "xx" if i % 5 else None, t, t.replace(" ", "")) for i, t in enumerate(raw)], "sent_id string, lang string, raw string, s string")
    rows = T.feature_counts(sents, 1 << 10).toPandas()
    symbols = sum(len(t.replace(" ", "")) for t in raw)
    assert rows[["n0", "n1", "n2", "n3"]].to_numpy().sum() == symbols and len(rows) < symbols / 8
    assert not rows.duplicated(["f1", "f2"]).any()
    words = T.Tagger(sents, buckets=1 << 10).segment(sents)
    assert {r["sent_id"]: "".join(r["words"]) for r in words.collect()} == {str(i): t.replace(" ", "") for i, t in enumerate(raw)}


def test_best_tags_are_the_best_legal_ones():
    rng, legal = np.random.default_rng(3), {(0, 1), (0, 2), (1, 1), (1, 2), (2, 0), (2, 3), (3, 0), (3, 3)}
    sizes = np.array([1, 5, 3, 1, 4, 2])
    log_p = np.log(rng.random((sizes.sum(), 4)))
    found, at = T.best_tags(log_p, sizes), 0
    for n in sizes:
        own = [t for t in product(range(4), repeat=n) if t[0] in (0, 3) and t[-1] in (2, 3) and all(p in legal for p in zip(t, t[1:]))]
        assert tuple(found[at:at + n]) == max(own, key=lambda t: sum(log_p[at + i, c] for i, c in enumerate(t)))
        at += n


def test_tags_of_words():
    tags = T.tags_of(np.array([4, 2, 3]), np.array([1, 3, 1, 3]), np.array([0, 0, 1, 2]))
    assert tags.tolist() == [3, 0, 1, 2, 3, -1, 0, 1, 2]


def test_descent_finds_the_least_value():
    a = np.diag([1.0, 5.0, 30.0])
    x = T.lowest(lambda v: (float((v - 1) @ a @ (v - 1)), 2 * a @ (v - 1)), np.zeros(3), 60)
    assert np.allclose(x, 1, atol=1e-3)


def test_cuts_are_scored_in_one_job(spark, sf_dir, monkeypatch):
    """the dev sources are joined once for a method, not once for each cut."""
    from cutseg.plans.context import Context
    calls, score_cuts = [], M.score_cuts
    monkeypatch.setattr(M, "score_cuts", lambda *a: calls.append(a) or score_cuts(*a))
    x = Context(spark, sf_dir)
    found = x.dev_scores("trained")
    (words, truth), = calls
    assert len(found) == 5
    for cut, f1 in found:
        assert f1 == (M.score_words(words.where(F.col("cut") == cut), truth.withColumn("all", F.lit(1)), by=("all",)).first()["f1"] or 0.0)


def test_passages_are_sought_once_for_all(spark):
    """A text is not searched again for each benchmark passage."""
    passages = ["ñandú corre", "ab", "", "𝒳𝒳 passage", "a passage at the end", None]
    texts = ["x ñandú corre", "ñandú corr", "ñandú corre", None, "", "cab", "a passage", "here a passage at the end", "𝒳𝒳𝒳 passage of", "ñandú cor", "re"]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").coalesce(1)
    for some in (passages[:2] + passages[3:], passages, passages[3:5], [None]):
        bench = spark.createDataFrame([(p,) for p in some], "text string")
        want = docs.join(bench.select(F.col("text").alias("passage")), F.contains("text", "passage"), "left_anti")
        found = tables.split(docs.withColumn("source", F.lit("src00")), "train", bench)
        assert "NestedLoop" not in found._jdf.queryExecution().executedPlan().toString()
        assert sorted(r["doc_id"] for r in found.collect()) == sorted(r["doc_id"] for r in want.collect())


def test_passages_over_many_texts(spark):
    rng = np.random.default_rng(8)
    texts = ["".join(rng.choice(list("abé"), rng.integers(0, 400))) for _ in range(3000)]
    passages = ["".join(rng.choice(list("abé"), n)) for n in (7, 8, 9, 10, 11)] + [texts[5][:60], texts[1999][-30:]]
    docs = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id int, text string").coalesce(1)
    found = {r["doc_id"] for r in tables.without_passages(docs, passages).collect()}
    assert found == {i for i, t in enumerate(texts) if not any(p in t for p in passages)} and 0 < len(found) < 3000


def test_letters_that_stand_alone(spark):
    """The weakening sets need no table of all words."""
    sents = spark.createDataFrame([("xx", "a b, é 7 a7 𝒳a 𝒳 a-b aé"), (None, "y o"), ("xx", "a1 1a")] * 2, "lang string, raw string")
    want = C.train_words(sents).where("length(word) = 1")
    assert sorted(map(str, C.train_letters(sents).collect())) == sorted(map(str, want.collect())) and want.count() == 6


def test_ranks_are_found_without_sorting_a_language_in_one_task(spark):
    """words are ranked in small groups."""
    rng = np.random.default_rng(9)
    words = sorted({"".join(rng.choice(list("abé𝒳"), rng.integers(1, 6))) for _ in range(600)})
    table = spark.createDataFrame([(lang, w, int(rng.integers(1, 5))) for lang in ("xx", "yy", None) for w in words], "lang string, word string, cnt long")
    plain = table.withColumn("rank", F.row_number().over(W.partitionBy("lang").orderBy(F.desc("cnt"), "word"))).select("lang", "word", "rank", "cnt")
    found = C.ranked(table, ("cnt",))
    assert found.schema["rank"].dataType == plain.schema["rank"].dataType
    assert sorted(map(str, found.collect())) == sorted(map(str, plain.collect()))
    assert "hashpartitioning(lang#" not in C.ranked(table)._jdf.queryExecution().executedPlan().toString()


def test_first_copies_are_kept_whether_broadcast_or_not(spark, sf_dir, monkeypatch):
    """texts are not shuffled to drop exact copies."""
    from cutseg.plans.workspace import Workspace
    keep, again, want = Workspace(spark, "copies").table, Workspace(spark, "copies").table, sorted(r["doc_id"] for r in tables.documents(spark, sf_dir).select("doc_id").collect())
    found = tables.documents(spark, sf_dir, keep)
    assert "SortMergeJoin" not in found._jdf.queryExecution().executedPlan().toString()
    monkeypatch.setattr(tables, "BROADCAST_IDS", 0)
    for docs in (found, tables.documents(spark, sf_dir, again)):
        assert sorted(r["doc_id"] for r in docs.select("doc_id").collect()) == want


def test_windows_are_made_distinct_without_a_row_for_each_symbol(spark, monkeypatch):
    """a hook's windows are found by code points, and many may be broadcast."""
    texts = [("xx", "abcab"), ("xx", "a𝒳é"), (None, "ab"), ("yy", "a"), ("xx", "abcabé"), ("yy", "ba"), ("xx", "")] * 3
    sents = spark.createDataFrame([(str(i), lang, s, len(s)) for i, (lang, s) in enumerate(texts)], "sent_id string, lang string, s string, n int").repartition(3)
    want = sorted(map(str, affinity.windows(sents).select("lang", "o", "a", "b", "x").distinct().collect()))
    assert "Generate" not in S.window_kinds(sents)._jdf.queryExecution().optimizedPlan().toString()
    assert sorted(map(str, S.window_kinds(sents).distinct().collect())) == want
    monkeypatch.setattr(S, "HELD_WINDOWS", 2)
    assert sorted(map(str, S.window_kinds(sents).distinct().collect())) == want
    model, hook = C.fit_model(sents), lambda edges: edges.withColumn("w", F.col("w") / (1 + F.ascii("a")))
    held = S._window_weights(sents.where("s <> ''"), model, S.DOMAIN, None, None, None, hook)
    assert held.column("left").type == "int64" and held.num_rows == len([w for w in want if "lang=None" not in w])
    one, other = (S.segment(sents, model, S.DOMAIN_SCALE, hook=hook, by_window=w).select("sent_id", "k", "words") for w in (True, False))
    assert sorted(map(str, one.collect())) == sorted(map(str, other.collect()))


def test_blocks_with_one_eigenvalue_within_the_cut_are_not_decomposed(monkeypatch):
    """Their count comes from pivots, and their vector is known."""
    rng = np.random.default_rng(12)
    bands = [(rng.random(n - 1) + 0.01, rng.random(max(0, n - 2)) * 0.2) for n in (1, 2, 3, 5, 9, 20, 33, 60)]
    bands += [(np.array([0.0, 0.0]), np.array([1.0])), (np.array([2.0, 0.0, 0.0, 3.0]), np.array([0.0, 1.0, 1.0]))]
    for form, loop, cut in (("plain", 1.0, 0.1), ("sym", 1.0, 0.05), ("sym", 0.0, 0.1), ("plain", 1.0, 1e-6)):
        alone = K.alone_within(bands, form, loop, cut)
        assert alone.any()
        for (adj, skip), is_alone in zip(bands, alone):
            values, vectors = np.linalg.eigh(K.laplacians(adj[None], skip[None], form, loop)[0])
            assert is_alone == (K.count_within(values, cut) == 1)
            if is_alone:
                assert np.allclose(np.abs(vectors[:, 0]), K.null_vector(adj, skip, form, loop))
    sizes, eigh = [], np.linalg.eigh
    monkeypatch.setattr(np.linalg, "eigh", lambda a: sizes.append(len(a)) or eigh(a))
    joined = [(np.concatenate((a, [0.0], b)), np.concatenate((s, [0.0, 0.0], t))) for (a, s), (b, t) in zip(bands[2:5], bands[5:8])]
    for cfg in (S.DOMAIN, S.LEXICON):
        whole, low = S._spectra(joined, cfg, [0.01]), len(sizes)
        found = S._spectra(joined, cfg, [0.01], low=True)
        assert len(sizes) - low < low
        sizes.clear()
        for (values, u), (own, v) in zip(whole, found):
            k = int(K.count_within(values, 0.01))
            assert int(K.count_within(own, 0.01)) == k and np.allclose(u[:, :k] @ u[:, :k].T, v[:, :k] @ v[:, :k].T)


def test_vectors_of_long_blocks_come_from_their_bands(monkeypatch):
    """no dense matrix of a long block is decomposed; without LAPACK's names all is as before."""
    rng = np.random.default_rng(14)
    bands = [(rng.random(n - 1) * rng.choice([0.01, 1, 8], n - 1) + 1e-3, rng.random(n - 2) * 0.2) for n in (9, 10, 17, 40, 41, 90, 150)]
    bands.append((np.tile([3.0, 2.0, 5.0, 0.02], 20), np.zeros(79)))  # near-equal eigenvalues
    rows = [("".join(rng.choice(list("abcdef"), len(adj) + 1)), adj, skip) for adj, skip in bands]
    sizes, eigh = [], np.linalg.eigh
    for form, loop, cut in (("plain", 1.0, 0.15), ("plain", 1.0, 1.0), ("sym", 1.0, 0.02), ("sym", 0.0, 0.3)):
        one, two, n = K.flat_bands(bands)
        found = K.low_vectors(K.band_rows(one, two, form, loop)[0], n.cumsum() - n, n, cut)
        assert sum(x is not None for x in found) >= len(bands) - 1
        for (adj, skip), x in zip(bands, found):
            values, vectors = eigh(K.laplacians(adj[None], skip[None], form, loop)[0])
            k = int(K.count_within(values, cut))
            if x is not None:
                assert np.allclose(x[0], values, atol=1e-12) and x[1].shape == (len(values), k)
                assert np.abs(x[1].T @ x[1] - np.eye(k)).max() < 1e-12
                assert np.abs(x[1] @ x[1].T - vectors[:, :k] @ vectors[:, :k].T).max() < 1e-9
        cfg = replace(S.DOMAIN, form=form, self_loop=loop, cut=cut)
        with monkeypatch.context() as m:
            m.setattr(np.linalg, "eigh", lambda a: sizes.append(a.shape[-1]) or eigh(a))
            got = S.split_sentences(rows[:-1], cfg)
            assert max(sizes, default=0) <= S.TINY_BLOCK
            m.setattr(K, "_lapack", lambda: None)
            assert S.split_sentences(rows[:-1], cfg) == got and max(sizes) > S.TINY_BLOCK
            sizes.clear()


def test_a_cut_that_takes_all_leaves_other_cuts_their_vectors():
    """cuts scored together, of which the largest parts all symbols."""
    rows = [("abcdefgh", np.array([1.0, 0.7, 0.0, 0.2, 0.9, 0.01, 1.0]), np.zeros(6))]
    both = S.split_cuts(rows, S.DOMAIN, [0.1, 9.0])
    assert both[0] == S.split_sentences(rows, replace(S.DOMAIN, cut=0.1)) and both[1][0][0] == 8
    assert both[0][0][2] == ["abc", "def", "gh"]


def test_tasks_take_one_thread(spark):
    """products of matrices do not wait on threads beside a task's core."""
    def threads(_):
        lib = ctypes.CDLL(np.linalg._umath_linalg.__file__)
        lib.scipy_openblas_set_num_threads64_(2)
        K.one_thread()
        return [lib.scipy_openblas_get_num_threads64_()]
    assert spark.sparkContext.parallelize([0], 1).mapPartitions(threads).collect() == [1]
    assert "one_thread" in str([c.co_names for c in S.segment.__code__.co_consts if hasattr(c, "co_names")])


def test_scores_collect_no_sentences(spark, sf_dir):
    """sizes guessed from packed files had all words of all cuts broadcast by the driver."""
    from cutseg.plans.context import context
    x = context(spark, sf_dir)
    words = x.ws.table(S.segment(x.dev, x.model, S.DOMAIN_SCALE, cuts=[0.1, 0.3]).select("cut", "sent_id", "lang", "words"), "scored-cuts")
    one, truth = words.where("cut = 0.3"), x.ws.table(M.gold(x.dev), "scored-gold")
    for df in (S.segment(x.dev, x.model, S.DOMAIN_SCALE, cuts=[0.1, 0.3]), M.score_cuts(words, truth), M.score_words(one, truth)):
        assert "Broadcast" not in df._jdf.queryExecution().sparkPlan().toString()
    pooled = M.score_words(one, truth, ()).first()
    assert M.score_cuts(words, truth).where("cut = 0.3").first()["f1"] == pooled["f1"] > 0
