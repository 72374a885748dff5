"""The exact toy corpus: counts, probabilities, weights and spectra by hand."""

from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import functions as F

from cutseg.functions import kernels as K, units
from cutseg.operators import affinity as A, baselines as B, corpus as C, laplacian as L, metrics as M, segment as S
from cutseg.operators.learned import LearnedWeights

CORPUS = ["abcab", "abd", "cab", "dab", "bcab", "ab"]


@pytest.fixture(scope="module")
def toy(spark, tmp_path_factory):
    sents = spark.createDataFrame([(str(i), "xx", s, s, len(s)) for i, s in enumerate(CORPUS)], "sent_id string, lang string, raw string, s string, n int")
    path = str(tmp_path_factory.mktemp("model"))
    C.fit_model(sents).save(path)
    return sents, C.NgramModel.load(spark, path)


def test_counts(toy):
    sents, model = toy
    assert {r["a"] + r["b"]: r["cnt"] for r in model.bi.collect()} == {"ab": 7, "bc": 2, "ca": 3, "bd": 1, "da": 1}
    assert {r["a"] + r["b"] + r["c"]: r["cnt"] for r in model.tri.collect()} == {"abc": 1, "bca": 2, "cab": 3, "abd": 1, "dab": 1}
    for n in (1, 2, 3):
        assert sorted(C.ngram_counts(sents, n).collect()) == sorted(C.ngram_tables(sents)[n].collect())


def weights(edges, sent="0"):
    return [round(r["w"], 6) for r in edges.where(F.col("sent_id") == sent).orderBy("i").collect()]


def test_edge_weights(toy, spark):
    sents, model = toy
    adjacent, skip = A.adjacent_weights(sents, model), A.skip_weights(sents, model)
    assert weights(adjacent) == [2.377337, 0.846825, 1.342185, 2.377337]
    assert weights(skip) == [0, 1.355909, 2.149065]
    one = spark.createDataFrame([("xx", "c", 1)], "lang string, ch string, set_id int")
    assert weights(A.weaken(adjacent, one)) == [2.377337, round(0.846825 / 4, 6), round(1.342185 / 4, 6), 2.377337]
    two = spark.createDataFrame([("xx", "c", 2)], "lang string, ch string, set_id int")
    assert weights(A.block_skip(skip, two)) == [0, 0, 0]
    both = spark.createDataFrame([("xx", "c", 1), ("xx", "a", 2)], "lang string, ch string, set_id int")
    assert weights(A.weaken(adjacent, both))[2] == pytest.approx(1.342185 / 320, abs=1e-6)
    free = spark.createDataFrame([("xx", "c", "a")], "lang string, a string, b string")
    assert weights(A.weaken(adjacent, both, except_bigrams=free))[2] == 1.342185


def test_bands_spectra_and_objectives(toy):
    sents, model = toy
    bands = A.to_bands(sents, A.adjacent_weights(sents, model), A.skip_weights(sents, model)).where("sent_id = '0'")
    row = bands.first()
    values = np.linalg.eigvalsh(K.laplacians(np.array([row["adj"]]), np.array([row["skip"]]), "plain"))[0]
    assert np.round(values, 6).tolist() == pytest.approx([0, 1.313475, 5.745823, 5.978546, 7.859471], abs=2e-6)
    plain = L.laplacian(bands, "plain")
    assert [plain.select(L.count_below(F.lit(c)).alias("k")).first()["k"] for c in (1.0, 2.0, 10.0)] == [1, 2, 5]
    thin = bands.withColumn("skip", F.transform("skip", lambda _: F.lit(0.0)))
    sym = L.laplacian(thin, "sym")
    assert np.round(sym.first()["deg"], 6).tolist() == [3.377337, 4.224162, 3.18901, 4.719522, 3.377337]
    assert [sym.select(L.count_below(F.lit(c)).alias("k")).first()["k"] for c in (0.1, 0.5, 1.0)] == [1, 2, 3]
    cut = thin.withColumn("labels", F.array(*[F.lit(v) for v in (0, 0, 1, 1, 1)]))
    assert M.cut_objective(cut, "ratio").first()["value"] == pytest.approx(0.705687, abs=1e-6)
    assert M.cut_objective(cut, "normalised").first()["value"] == pytest.approx(0.186436, abs=1e-6)


def test_both_strategies_agree(toy, spark):
    sents, model = toy
    sets = spark.createDataFrame([("xx", "c", 1), ("xx", "d", 2)], "lang string, ch string, set_id int")
    words = spark.createDataFrame([("xx", "ab", 1, 30), ("xx", "ca", 2, 20), ("xx", "d", 3, 600)], "lang string, word string, rank int, cnt long")
    singles = spark.createDataFrame([("xx", "d", 3, 600)], "lang string, ch string, rank int, cnt long")
    in_place = replace(S.TRAINED_SCALE, match="in_place", cut=0.3)
    for cfg, kw in ((S.DOMAIN, {"sets": sets}), (S.LEXICON, {"words": words, "singles": singles}), (S.TRAINED, {"words": words, "singles": singles}), (S.DOMAIN_SCALE, {"sets": sets}),
                    (replace(S.LEXICON_SCALE, max_rank=2), {"words": words, "singles": singles}), (S.TRAINED_SCALE, {"words": words, "singles": singles}),
                    (in_place, {"words": words, "singles": singles}), (replace(S.DOMAIN, cut="gap"), {"sets": sets})):
        a, b = (sorted(map(tuple, ((r["sent_id"], r["k"], tuple(r["words"])) for r in S.segment(sents, model, cfg, strategy=how, **kw).collect()))) for how in ("broadcast", "join"))
        assert a == b and len(a) == len(CORPUS)
        assert all("".join(w) == CORPUS[int(i)] for i, _, w in a)


def test_no_sentence_is_lost(toy, spark):
    _, model = toy
    rows = [("1", None, "abcab"), ("2", "xx", "abcab"), ("3", "xx", ""), ("4", "xx", None), ("5", "xx", "ab" * 400), ("6", "yy", "ab"), ("7", None, "")]
    sents = spark.createDataFrame(rows, "sent_id string, lang string, s string").withColumn("n", F.length("s"))
    words = spark.createDataFrame([("xx", "ab", 1, 30), ("xx", "cab", 2, 20)], "lang string, word string, rank int, cnt long")
    for cfg in (S.DOMAIN, S.LEXICON_SCALE, replace(S.TRAINED_SCALE, match="in_place")):
        both = [{r["sent_id"]: (r["k"], r["words"]) for r in S.segment(sents, model, cfg, words=words, strategy=how).collect()} for how in ("broadcast", "join")]
        assert both[0] == both[1] and set(both[0]) == {str(i) for i in range(1, 8)}
        assert both[0]["1"] == (5, list("abcab")) and both[0]["3"] == both[0]["4"] == both[0]["7"] == (0, [])
    for found in (B.match_segment(sents, words), B.likelihood_segment(sents, words)):
        got = {r["sent_id"]: r["words"] for r in found.collect()}
        assert got["1"] == list("abcab") and got["6"] == ["a", "b"] and got["3"] == [] and "".join(got["2"]) == "abcab"


def test_gold_without_prediction_counts(spark):
    truth = spark.createDataFrame([("1", "xx", ["ab", "c"]), ("2", "xx", ["d"])], "sent_id string, lang string, words array<string>")
    got = M.score_words(truth.where("sent_id = '1'"), truth).first()
    assert (got["tp"], got["n_pred"], got["n_gold"]) == (2, 2, 3)


def test_learned_weights_and_hook(toy, spark):
    sents, model = toy
    raw = sents.withColumn("raw", F.concat_ws(" ", F.substring("s", 1, 2), F.expr("substring(s, 3)")))
    words = spark.createDataFrame([("xx", "ab", 3)], "lang string, word string, cnt long")
    learned = LearnedWeights(raw, model, words)
    edges = learned.weigh(A.adjacent_weights(sents, model)).collect()
    mean = lambda inside: np.mean([e["w"] for e in edges if (e["a"] + e["b"] == "ab") == inside])
    assert all(0 <= e["w"] <= 1 for e in edges) and mean(True) > mean(False)
    none = S.segment(sents, model, S.DOMAIN, hook=lambda e: e.withColumn("w", F.lit(0.0)))
    assert {len(r["words"]) - len(r["s"]) for r in S.segment(sents, model, replace(S.DOMAIN, use_skip=False), hook=lambda e: e.withColumn("w", F.lit(0.0))).collect()} == {0}
    assert none.count() == len(CORPUS)


def test_special_sentences(toy, spark):
    _, model = toy
    odd = ["a", "zz", "....", "a" * 50, "ab.ab", "𝒳ab", "abc" * 400]
    sents = spark.createDataFrame([(str(i), "xx", s, len(s)) for i, s in enumerate(odd)], "sent_id string, lang string, s string, n int")
    for cfg in (S.DOMAIN, S.DOMAIN_SCALE, S.LEXICON):
        got = {r["sent_id"]: r for r in S.segment(sents, model, cfg).collect()}
        assert {i: "".join(r["words"]) for i, r in got.items()} == {str(i): s for i, s in enumerate(odd)}
    assert got["2"]["words"] == list("....")  # no edges: every mark is a component
    assert got["6"]["forced"] and not got["4"]["forced"]


def test_singular_counts_and_empty_tables(spark):
    one = spark.createDataFrame([("0", "xx", "abc", 3)], "sent_id string, lang string, s string, n int")
    assert {r["z"] for r in C.standardised_log_counts(C.ngram_counts(one, 2)).collect()} == {0.0}
    none = one.where("false")
    assert C.fit_model(none).tri.count() == 0
    assert S.segment(none, C.fit_model(one), S.DOMAIN).count() == 0


def test_rank_divisor_is_constant_by_default(spark):
    edges = spark.createDataFrame([("0", "xx", 0, "a", "b", 20.0, False)], "sent_id string, lang string, i int, a string, b string, w double, boosted boolean")
    singles = spark.createDataFrame([("xx", "a", 1)], "lang string, ch string, rank int")
    assert A.split_singles(edges, singles).first()["w"] == 1.0
    assert A.split_singles(edges, singles, floor=1.0).first()["w"] == pytest.approx(20 / np.log(1e6))


def test_scores_of_length_codes(spark):
    """Word-length codes of four published items, pooled."""
    code = lambda t: [int(c) for c in t.split()]
    gold = ["1 2 4 1 2 1 1 1 2 2 2 2 2 2 1 2 2 2 2 1 2 3 1 1 2 2 2 1 1 2 2 3 2 1 2 2 3 2 1 2 2 1 2 2 1 1 2 2 1 2 1 1 2 1 2 2 1 2 1 2 1",
            "2 2 1 1 1 2 1 1 2 2 1 2 2 1 2 2 1", "2 1 2 2 2 1 2 1 1 2 1 2 2 1 2 2 2 1 2 2 2 2 1 2 2 1 2 2 1", "2 2 3"]
    third = ["1 2 4 1 2 1 1 1 2 2 2 2 2 2 1 2 2 2 2 1 2 3 1 1 2 2 2 1 1 2 2 3 2 1 2 2 3 2 1 2 2 1 2 2 1 1 4 1 2 1 1 2 1 2 3 2 1 2 1",
             "2 2 1 1 1 2 1 1 2 2 1 2 2 1 2 2 1", "2 1 2 2 2 1 3 1 2 1 2 2 1 2 2 2 1 2 2 2 1 1 1 4 1 2 2 1", "2 2 3"]

    def frame(codes):
        return spark.createDataFrame([(str(i), "xx", ["x" * n for n in code(c)]) for i, c in enumerate(codes)], "sent_id string, lang string, words array<string>")

    got = M.score_words(frame(third), frame(gold)).first()
    assert (got["tp"], got["n_pred"], got["n_gold"]) == (101, 107, 110)
    assert got["f1"] == pytest.approx(0.9309, abs=1e-4)
    assert M.score_words(frame(gold), frame(gold)).first()["f1"] == 1.0


def test_baselines(toy, spark):
    sents, model = toy
    join = lambda df: {r["sent_id"]: "|".join(r["words"]) for r in df.collect()}
    assert join(B.trivial(sents, "chars"))["0"] == "a|b|c|a|b" and join(B.trivial(sents, "one"))["0"] == "abcab"
    assert join(B.threshold_segment(A.adjacent_weights(sents, model), sents, 1.0))["0"] == "ab|cab"
    words = spark.createDataFrame([("xx", w, c) for w, c in (("ab", 9), ("cab", 5), ("c", 1))], "lang string, word string, cnt long")
    assert join(B.likelihood_segment(sents, words))["0"] == "ab|cab"
    assert join(B.match_segment(sents, words))["4"] == "b|cab" and join(B.match_segment(sents, words, backward=True))["4"] == "b|cab"
    assert set(join(B.entropy_segment(sents, model.bi, theta=0.5))) == {str(i) for i in range(6)}


def test_tagger_learns_spacing(spark):
    raw = ["ab cd ab", "cd ab", "ab ab cd", "cd cd"] * 10
    sents = units.sentences(spark.createDataFrame([(i, t, "xx", "s") for i, t in enumerate(raw)], "doc_id long, text string, lang string, source string"))
    got = B.Tagger(sents, buckets=256).segment(sents)
    assert M.score_words(got, M.gold(sents)).first()["f1"] == 1.0


def test_post_processing():
    assert K.join_numbers_dates(["1", "9", "9", "8", "年", "，", "2", "0", "%", "3", ".", "5", "x", "4", "."]) == ["1998年", "，", "20%", "3.5", "x", "4", "."]


def test_sentences_and_gold(spark):
    docs = spark.createDataFrame([(1, "Ab c, D!  \n..x y?", "en", "s"), (2, None, "en", "s"), (3, "", "en", "s")], "doc_id long, text string, lang string, source string")
    got = {r["sent_id"]: r for r in units.sentences(docs).collect()}
    assert {k: r["s"] for k, r in got.items()} == {"1:0": "abc,d", "1:2": "xy"} or sorted(r["s"] for r in got.values()) == ["abc,d", "xy"]
    words = M.gold(units.sentences(docs)).orderBy("s").first()["words"]
    assert words == ["ab", "c", ",", "d"]


def test_word_lists_are_broadcast_as_pairs(toy, spark, monkeypatch):
    """a long word list must not lead to joins over all symbols."""
    sents, model = toy
    words = spark.createDataFrame([("xx", f"ab{'c' * i}", i, 3) for i in range(60)], "lang string, word string, rank int, cnt long")
    singles = spark.createDataFrame([("xx", "d", 3, 600)], "lang string, ch string, rank int, cnt long")
    want = {r["sent_id"]: r["words"] for r in S.segment(sents, model, S.TRAINED, words=words, singles=singles, strategy="join").collect()}
    monkeypatch.setattr(S, "BROADCAST_ROWS", 20)
    found = S.segment(sents, model, S.TRAINED, words=words, singles=singles)
    assert "adj" not in found._jdf.queryExecution().analyzed().toString()
    assert {r["sent_id"]: r["words"] for r in found.collect()} == want


def test_cuts_share_one_decomposition(toy, spark, monkeypatch):
    sents, model = toy
    odd = sents.unionByName(spark.createDataFrame([("e", "xx", "", "", 0), ("l", "xx", "", "ab.d" * 90, 360)], sents.schema))
    both = {(r["cut"], r["sent_id"]): (r["k"], r["words"]) for r in S.segment(odd, model, S.DOMAIN, cuts=[0.1, 2.0]).collect()}
    for cut in (0.1, 2.0):
        assert {(cut, r["sent_id"]): (r["k"], r["words"]) for r in S.segment(odd, model, replace(S.DOMAIN, cut=cut)).collect()}.items() <= both.items()
    assert len(both) == 2 * odd.count()
    calls, eigh = [], np.linalg.eigh
    monkeypatch.setattr(np.linalg, "eigh", lambda x: calls.append(1) or eigh(x))
    S.split_cuts([("abcd", np.array([1.0, 2.0, 1.0]), np.array([0.1, 0.1]))], S.DOMAIN, [0.1, 1.0, 2.0])
    assert len(calls) == 1


def test_blocks_are_decomposed_each_for_itself(monkeypatch):
    """A matrix that falls into blocks is never decomposed as a whole."""
    adj, skip = np.tile([1.0, 0.7, 0.0], 30), np.zeros(89)
    sizes, eigh = [], np.linalg.eigh
    whole = S.labels_of(adj, skip, replace(S.DOMAIN, cut=1e-9), 0)
    monkeypatch.setattr(np.linalg, "eigh", lambda x: sizes.append(x.shape[-1]) or eigh(x))
    k, _, words = S.split_sentences([("abc" * 30 + "d", adj, skip)], replace(S.DOMAIN, cut=1e-9))[0]
    assert max(sizes) == 3 and k == whole[0] == 31 and words == ["abc"] * 30 + ["d"]


def test_window_hook_equals_sentence_hook(toy, spark):
    """a hook that sees windows is asked once for each of them."""
    sents, model = toy
    seen = []

    def hook(edges):
        seen.append(edges)
        return edges.withColumn("w", F.col("w") / (1 + F.ascii("a") % 3))
    cfg = replace(S.DOMAIN_SCALE, cut=0.3)
    a, b = ({r["sent_id"]: (r["k"], r["words"]) for r in S.segment(sents, model, cfg, hook=hook, by_window=w).collect()} for w in (True, False))
    assert a == b and len(a) == len(CORPUS)
    assert seen[0].count() < seen[1].count()


def test_stacked_kmeans_equals_single_ones():
    rng = np.random.default_rng(7)
    for n in (12, 90):
        us = [rng.normal(size=(n, k)) for k in (2, 5, 3, 9)]
        for init in ("even", "pp"):
            for u, lab in zip(us, K.kmeans_stack(us, init, [1, 2, 3, 4])):
                own = K.kmeans(u, u.shape[1], init, 1 + [2, 5, 3, 9].index(u.shape[1]))
                assert (own == lab).all()


def test_word_tables_split_as_dictionaries_do():
    """Hashed tables stand for dictionaries of any number of words."""
    rng = np.random.default_rng(8)
    text = lambda n: "".join(rng.choice(list("abcé𝒳"), n))
    counts = {text(int(n)): int(c) for n, c in zip(rng.integers(1, 9, 400), rng.integers(1, 900, 400))}
    table, total = K.WordTable(list(counts), np.array(list(counts.values()))), sum(counts.values())
    log_p = {w: float(np.log(c / total)) for w, c in counts.items()}
    for s in [text(int(n)) for n in rng.integers(1, 60, 80)] + ["zz", "z" * 30 + "a"]:
        assert table.likely(s) == K.likelihood_split(s, log_p, table.longest, table.unknown)
        for backward in (False, True):
            assert table.longest_first(s, backward) == K.longest_match(s, set(counts), table.longest, backward)
    none = K.WordTable([], np.zeros(0))
    assert none.likely("ab") == ["a", "b"] and none.longest_first("ab") == ["a", "b"]


def test_long_word_lists_are_no_error(toy, spark, monkeypatch):
    """no limit on the number of words, and no pandas copy of them on the driver."""
    sents, _ = toy
    words = spark.createDataFrame([("xx", "ab", 9), ("xx", "cab", 5)], "lang string, word string, cnt long")
    monkeypatch.setattr(type(words), "toPandas", lambda self: pytest.fail("the list is copied to pandas"))
    assert {r["sent_id"]: "|".join(r["words"]) for r in B.match_segment(sents, words, backward=True).collect()}["4"] == "b|cab"


def test_stream_kernel_takes_equal_sentences_once(toy, spark, tmp_path, monkeypatch):
    """all cores work on a micro-batch, and equal sentences meet in one task."""
    from cutseg.streaming import streams
    _, model = toy
    docs = spark.createDataFrame([(i, "abcab. dab", "xx", "s") for i in range(40)], "doc_id long, text string, lang string, source string").coalesce(1)
    docs.write.parquet(f"{tmp_path}/docs")
    stream = streams.segment_stream(streams.document_stream(spark, f"file://{tmp_path}/docs"), model, S.DOMAIN_SCALE)
    assert "Repartition" in stream._jdf.queryExecution().analyzed().toString()
    rows = streams.run_to_end(stream, "t").collect()
    want = {r["s"]: r["words"] for r in S.segment(spark.createDataFrame([("0", "xx", "abcab"), ("1", "xx", "dab")], "sent_id string, lang string, s string"), model, S.DOMAIN_SCALE).collect()}
    assert len(rows) == 80 and {r["sent_id"] for r in rows} == {f"{i}:{j}" for i in range(40) for j in (0, 1)}
    assert all(r["words"] == want["".join(r["words"])] for r in rows)
