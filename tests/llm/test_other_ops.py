"""Mixing, pivot index, revisits, pipeline."""

import random
from fractions import Fraction

import duckdb
import numpy as np
import pytest
from hypothesis import given, settings, strategies as st
from pyspark.sql import functions as F

from cutseg.llm import mixing as X, warc
from cutseg.llm.pivot_index import PivotIndex
from cutseg.llm.registry import ORACLE_SQL, QUERIES

# --- mixing --------------------------------------------------------------------


@settings(max_examples=60, deadline=None)
@given(st.dictionaries(st.tuples(st.sampled_from("ab"), st.sampled_from("xy"), st.sampled_from("123")), st.integers(0, 500), min_size=1), st.integers(0, 2500))
def test_budgets(supply, total):
    weights = X.Weights({("a",): 3, ("a", "x"): 0.5})
    got = X.budgets(supply, weights, total)
    assert all(0 <= got[p] <= supply[p] for p in supply) and sum(got.values()) == min(total, sum(supply.values()))
    # a leaf below its supply has no sibling with a larger share for its weight
    for p in supply:
        for q in supply:
            if p[:2] == q[:2] and got[p] < supply[p]:
                assert got[q] <= got[p] + 1


def test_shortage_goes_to_siblings_first():
    supply = {("a", "x"): 10, ("a", "y"): 1000, ("b", "x"): 1000}
    assert X.budgets(supply, X.Weights(), 200) == {("a", "x"): 10, ("a", "y"): 90, ("b", "x"): 100}
    assert X.budgets({("a", "x"): 10, ("a", "y"): 20, ("b", "x"): 1000}, X.Weights(), 200) == {("a", "x"): 10, ("a", "y"): 20, ("b", "x"): 170}
    assert X.budgets(supply, X.Weights({("b",): 0}), 5000)[("b", "x")] == 0
    assert X.Weights({("a",): 0.1}).of(("a",)) == Fraction(1, 10)


def test_mixture(spark):
    rng = random.Random(1)
    rows = [(i, " ".join(["w"] * rng.randint(0, 30)), None if i % 11 == 0 else "en", f"src{0 if i % 3 else i % 12}") for i in range(800)]
    docs = spark.createDataFrame(rows + rows[:2], "doc_id long, text string, lang string, source string").withColumn("tokens", F.lit("x"))
    m = X.Mixture(docs, X.production_paths(docs), X.PRODUCTION_WEIGHTS, share=1.3, epochs=3)
    got = m.selected.collect()
    size = {i: len(t.split()) for i, t, _, _ in rows}
    taken = {}
    for r in got:
        leaf = (r["domain"], r["lang"], r["source"])
        taken[leaf] = taken.get(leaf, 0) + r["take"]
        assert r["tokens"] == size[r["doc_id"]] and r["take"] <= r["tokens"]
    assert {k: v for k, v in taken.items() if v} == {k: v for k, v in m.budgets.items() if v}
    assert sum(r["take"] < r["tokens"] for r in got) <= len(m.budgets)
    assert {r["epoch"] for r in got} <= {0, 1, 2}
    again = X.Mixture(docs.repartition(7), X.production_paths(docs), X.PRODUCTION_WEIGHTS, share=1.3, epochs=3).selected.collect()
    key = lambda rs: sorted((r["doc_id"], r["epoch"], r["take"]) for r in rs)
    assert key(got) == key(again)
    none = docs.where("false")
    assert X.Mixture(none, X.production_paths(none), X.Weights()).selected.count() == 0


def test_word_count(spark):
    texts = [None, "", " ", "a", " a  b\n", "\u00a0x\u00a0 y"]
    got = [r[0] for r in spark.createDataFrame([(t,) for t in texts], "t string").select(X.word_count(F.col("t"))).collect()]
    assert got == [0, 0, 0, 1, 2, 2]


# --- pivot index ------------------------------------------------------------------


def test_pivot_index(spark):
    rng = np.random.default_rng(5)
    rows = []
    for i in range(900):
        rows.append((i, rng.normal(size=32).tolist(), i % 3))
    for i in range(900, 1500):  # near copies at cosines from 0.9 to 1
        base = np.array(rows[int(rng.integers(0, 300))][1])
        noise = rng.normal(size=32)
        noise -= base * (noise @ base) / (base @ base)
        cos = rng.uniform(0.9, 1)
        x = base / np.linalg.norm(base) * cos + noise / np.linalg.norm(noise) * np.sqrt(1 - cos**2)
        rows.append((i, (x * rng.uniform(0.1, 9)).tolist(), int(rng.integers(0, 3))))
    rows += [(2000 + k, rows[5][1], rows[5][2]) for k in range(40)]
    bad = [(3000, None, 1), (3001, [0.0] * 32, 1), (3002, [float("nan")] + [1.0] * 31, 1), (3003, [None] + [1.0] * 31, 1), (3004, rows[5][1], None), (3005, [1.0, 2.0], 2), (3006, [1e-200] * 32, 1), (3007, [1.0] * 32, 1)]
    v = spark.createDataFrame(rows + bad, "vec_id long, embedding array<double>, label int").withColumn("near", F.lit("x"))
    got = {r["vec_id"]: r for r in PivotIndex(v).vectors().collect()}
    ids = np.array([r[0] for r in rows])
    x = np.array([r[1] for r in rows])
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    lab = np.array([r[2] for r in rows])
    link = (x @ x.T >= 0.93) & (lab[:, None] == lab)
    np.fill_diagonal(link, False)
    want = dict(zip(ids.tolist(), link.sum(1).tolist()))
    found, all_ = sum(got[i]["n_links"] for i in want), sum(want.values())
    assert all(got[i]["n_links"] <= want[i] for i in want) and found >= 0.97 * all_
    assert all(got[i]["n_links"] == 0 and got[i]["kept"] for i in (3000, 3001, 3002, 3003, 3004, 3005))
    assert got[3006]["n_links"] == 1 and got[3007]["component_id"] == 3006
    assert got[2039]["n_links"] >= 40 and got[2039]["component_id"] == got[5]["component_id"]
    assert len(got) == len(rows) + len(bad)
    assert PivotIndex(v.where("false")).vectors().count() == 0


@pytest.mark.parametrize("low, high", [(0.97, 1.0), (0.99, 0.9999)])
def test_pivot_index_in_a_hot_group(spark, low, high):
    """A third of the rows are near copies of one centre."""
    rng, n, hot = np.random.default_rng(11), 3000, 1000
    x = rng.normal(size=(n, 64))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    centre, cos = x[0].copy(), rng.uniform(low, high, hot)[:, None]
    away = x[:hot] - (x[:hot] @ centre)[:, None] * centre
    away[0] = rng.normal(size=64)
    away[0] -= (away[0] @ centre) * centre
    x[:hot] = cos * centre + np.sqrt(1 - cos**2) * away / np.linalg.norm(away, axis=1, keepdims=True)
    ids = rng.permutation(n)
    v = spark.createDataFrame([(int(i), r, 1) for i, r in zip(ids, x.tolist())], "vec_id long, embedding array<double>, label int")
    got = {r["vec_id"]: r["n_links"] for r in PivotIndex(v).vectors().collect()}
    want = (x @ x.T >= 0.93).sum(1) - 1
    assert all(got[i] <= w for i, w in zip(ids.tolist(), want.tolist()))
    assert sum(got.values()) >= 0.97 * want.sum()


# --- revisits -----------------------------------------------------------------------


def test_canonical_url(spark):
    same = ["http://www.Example.com:80/a/b/?utm_source=x&b=2&a=1#top", "https://example.com/a/b?a=1&b=2", "example.com/a/b/?b=2&a=1&ref=z"]
    got = [r[0] for r in spark.createDataFrame([(u,) for u in [*same, "http://EXAMPLE.com", None, ""]], "u string").select(warc.canonical_url(F.col("u"))).collect()]
    assert got == ["example.com/a/b?a=1&b=2"] * 3 + ["example.com", None, ""]


def brute_revisits(records):
    out = {}
    full = [r for r in records if r[3] == "response" and r[1] is not None and r[2] is not None]
    for rid, url, ts, kind, headers in records:
        if kind != "revisit":
            continue
        h = {k.lower(): v for k, v in (headers or {}).items()}
        early = [r for r in full if r[1] == url and ts is not None and r[2] < ts]
        if not early:
            out[rid] = (None, "missing", None)
            continue
        hit = max(early, key=lambda r: (r[2], r[0]))
        stored = {k.lower(): v for k, v in (hit[4] or {}).items()}
        if "etag" in h:
            ok = h["etag"].removeprefix("W/") == stored.get("etag", "").removeprefix("W/")
        else:
            ok = "last-modified" not in h or h["last-modified"] == stored.get("last-modified")
        merged = stored | {k: v for k, v in h.items() if k not in warc.FIXED_HEADERS}
        out[rid] = (hit[0], "resolved" if ok else "mismatch", merged if ok else None)
    return out


@pytest.mark.parametrize("seconds", [10, 86_400])
def test_revisits(spark, seconds):
    rng = random.Random(seconds)
    records = []
    for i in range(400):
        kind = rng.choice(["response", "revisit", "revisit"])
        h = {"ETag": rng.choice(['"1"', 'W/"1"', '"2"']), "Content-Length": str(i), "X": str(i)} if rng.random() < 0.7 else rng.choice([None, {}, {"Last-Modified": "m"}, {"Last-Modified": "n", "Date": "d"}])
        records.append((i, rng.choice(["http://a/x", "http://b/", "http://hot/"] + ["http://hot/"] * 5 + [None] * (rng.random() < 0.1)), rng.choice([None] * (i % 50 == 0) + [rng.randint(0, 300)]), kind, h))
    canon = {"http://a/x": "a/x", "http://b/": "b", "http://hot/": "hot", None: None}
    df = spark.createDataFrame(records, "record_id long, url string, ts long, kind string, headers map<string,string>").withColumn("canonical", F.lit("x"))
    got = {r["record_id"]: (r["refers_to"], r["status"], r["headers"]) for r in warc.resolve_revisits(df, seconds).collect()}
    assert got == brute_revisits([(i, canon[u], t, k, h) for i, u, t, k, h in records])
    assert warc.resolve_revisits(df.where("false")).count() == 0


def test_warc_files(spark, tmp_path):
    rows = [(1, "http://a/", 1_700_000_000, "response", {"etag": '"1"'}, b"body\r\n\r\nmore"), (2, "http://a/", 1_700_000_100, "revisit", {"etag": '"1"'}, None)]
    raw = b"".join(warc.record_bytes(*r) for r in rows)
    assert [(r["record_id"], r["url"], r["ts"], r["kind"], r["headers"], r["body"] or None) for r in warc.parse_warc(raw)] == [tuple(r) for r in rows]
    assert len(list(warc.parse_warc(raw[:-20]))) == 1
    df = spark.createDataFrame(rows, warc.RECORDS)
    warc.write_warc(df, str(tmp_path / "w"))
    members = b"".join(bytes(r["warc"]) for r in spark.read.parquet(str(tmp_path / "w")).orderBy("record_id").collect())
    (tmp_path / "f").mkdir()
    (tmp_path / "f" / "x.warc.gz").write_bytes(members)
    assert [r["status"] for r in warc.resolve_revisits(warc.read_warc(spark, str(tmp_path / "f"))).collect()] == ["resolved"]


# --- queries and pipeline --------------------------------------------------------------


@pytest.mark.parametrize("name", sorted(ORACLE_SQL))
def test_twin(spark, sf_dir, name):
    con = duckdb.connect()
    for t in ("documents", "embeddings", "pages"):
        con.sql(f"create view {t} as select * from '{sf_dir}/{t}.parquet'")
    got, want = QUERIES[name](spark, sf_dir).toPandas(), con.sql(ORACLE_SQL[name]).df()
    rows = lambda df: sorted(tuple("" if v is None or v != v else str(int(v)) if isinstance(v, float) else str(v) for v in r) for r in df[sorted(df.columns)].itertuples(index=False, name=None))
    assert rows(got) == rows(want)


def test_pipeline(spark, sf_dir, tmp_path):
    import corpus_pipeline as C
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    columns, ids = docs.columns, {r[0] for r in docs.select("doc_id").collect()}
    for name, stage in C.STAGES:
        path = str(tmp_path / name)
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
        if name != "packing":
            assert docs.columns == columns
            now = [r[0] for r in docs.select("doc_id").collect()]
            assert len(now) == len(set(now)) and set(now) <= ids
            ids = set(now)
    assert {r[0] for r in docs.select("doc_id").distinct().collect()} == ids


def test_pipeline_stages_take_odd_rows(spark, sf_dir):
    import corpus_pipeline as C
    schema = spark.read.parquet(f"{sf_dir}/documents.parquet").schema
    odd = spark.createDataFrame([(None, None, None, None, None), (900001, "", None, "src1", 0), (900001, "", None, "src1", 0), (900002, "x " * 30_000, "en", None, 60_000)], schema)
    for docs in (odd, odd.where("false")):
        for _, stage in C.STAGES:
            stage(spark, docs, sf_dir).count()


# --- brute force: draws, prefixes, odd WARC bytes ---------------------------------


def spark_hash(*values, seed=42):
    """Spark's xxhash64 of longs, (value, 4)-tuples for ints, and strings."""
    import xxhash
    for v in values:
        raw = v.encode() if isinstance(v, str) else v[0].to_bytes(4, "little", signed=True) if isinstance(v, tuple) else v.to_bytes(8, "little", signed=True)
        seed = xxhash.xxh64_intdigest(raw, seed)
    return seed


def test_shard_draws_by_hand(spark):
    import math
    from cutseg.llm import hash_tree as H
    tree = H.Branch("root", (H.Branch("a", (H.Branch("a/x", (H.Leaf(0), H.Leaf(1, 2.0))), H.Branch("a/y", (H.Leaf(2, 0.5),)))), H.Branch("b", (H.Branch("b/x", (H.Leaf(3), H.Leaf(4, 0.0))),))))

    def descend(key):
        node, level = tree, 0
        while isinstance(node, H.Branch):
            live = [c for c in node.children if c.mass() > 0]
            draws = [(math.log(((spark_hash(key, f"{level}:{c.shard if isinstance(c, H.Leaf) else c.name}") >> 11) + 0.5) / 2.0**53) / c.mass(), i) for i, c in enumerate(live)]
            node, level = live[max(draws)[1]], level + 1
        return node.shard
    got = {r["id"]: r["shard"] for r in H.place(spark.range(2000), F.col("id"), tree, "shard").collect()}
    assert got == {i: descend(i) for i in range(2000)} and set(got.values()) == {0, 1, 2, 3}


def test_mixture_rows_by_hand(spark):
    rng = random.Random(8)
    rows = [(i, " ".join("w" * rng.randint(1, 3) for _ in range(rng.randint(0, 40))), rng.choice(["en", "fr"]), rng.choice(["src1", "src2", "src12"])) for i in range(300)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")
    mix = X.Mixture(docs, X.production_paths(docs), X.PRODUCTION_WEIGHTS, share=1.0, epochs=3, seed=5)
    want, leaves = [], {}
    for i, text, lang, source in rows:
        leaves.setdefault(("core" if len(source) == 4 else "tail", lang, source), []).append((i, len(text.split())))
    for path, own in leaves.items():
        total = sum(n for _, n in own)
        whole, rest = divmod(mix.budgets[path], total)
        want += [(i, *path, e, n, n) for e in range(whole) for i, n in own]
        for _, i, n in sorted((spark_hash((5, 4), whole, i) >> 1, i, n) for i, n in own):
            if rest <= 0:
                break
            want.append((i, *path, whole, n, min(n, rest)))
            rest -= n
    assert sorted(map(tuple, mix.selected.collect())) == sorted(want)


def test_odd_warc_bytes():
    import gzip
    good = warc.record_bytes(1, "http://a/", 1_700_000_000, "response", {"X": "é"}, b"body")
    assert [r["headers"] for r in warc.parse_warc(good)] == [{"x": "é"}]
    undated = good.replace(b"WARC-Date", b"X-Date")
    assert [r["ts"] for r in warc.parse_warc(undated + good)] == [None, 1_700_000_000]
    assert list(warc.parse_warc(good.replace(b"Content-Length: ", b"Content-Length: x"))) == []
    assert [r["kind"] for r in warc.parse_warc(good.replace(b"200 OK", b"404 No"))] == ["other"]
    revisit = warc.record_bytes(2, "http://a/", 1, "revisit", {}, b"")
    assert [r["kind"] for r in warc.parse_warc(revisit + revisit.replace(b"server-not-modified", b"identical-payload-digest"))] == ["revisit", "other"]
    members = gzip.compress(good) + gzip.compress(good)
    assert len(list(warc.parse_warc(members))) == 2 and len(list(warc.parse_warc(members[:-20]))) == 1 and list(warc.parse_warc(b"")) == []


def test_pivot_sample_is_found_among_few_ids(spark, monkeypatch):
    """the first vectors by the hash of the id, and no task sends others on."""
    from cutseg.llm import pivot_index as I
    rng = np.random.default_rng(9)
    vectors = rng.normal(size=(600, 6))
    table = spark.createDataFrame([(i, "x" if i % 50 else None, v.tolist() if i % 70 else None) for i, v in enumerate(vectors)], "vec_id long, label string, embedding array<double>")
    monkeypatch.setattr(I, "SAMPLE", 40)
    whole = table.where("embedding is not null and label is not null").orderBy(F.xxhash64("vec_id"), "vec_id").limit(40).collect()
    want = []
    for r in whole:
        v = I.unit(np.array(r["embedding"]))
        if all(v @ w < I.SPREAD for w in want):
            want.append(v)
    limits = []
    frame = type(table)
    plain = frame.limit
    monkeypatch.setattr(frame, "limit", lambda self, n: (limits.append(self.count()), plain(self, n))[1])
    index = PivotIndex.__new__(PivotIndex)
    index.ws = I.Workspace(spark, "t")
    got = index._sample(table.select("vec_id", "label", F.col("embedding").alias("v")))
    assert np.allclose(got, np.array(want)) and max(limits) < 200


def test_pivot_index_collects_no_table_that_grows(spark):
    """sizes guessed from packed files had lists of pivots broadcast by the driver."""
    from cutseg.llm import pivot_index as I
    x = np.random.default_rng(3).normal(size=(60, 8))
    v = spark.createDataFrame([(i, x[i % 40].tolist(), "a") for i in range(60)], "vec_id long, embedding array<double>, label string")
    index = I.PivotIndex(v)
    for df in (index._candidates(), index.vectors()):
        assert "Broadcast" not in df._jdf.queryExecution().sparkPlan().toString()


def test_components_collect_no_large_table(spark, tmp_path, monkeypatch):
    """neither do the rounds of the components, whose count of edges is known."""
    from cutseg.operators import components as G
    from cutseg.plans.workspace import Workspace
    edges = spark.createDataFrame([(i, i + 3) for i in range(30)], "u long, v long")
    want = sorted(map(tuple, G.connected_components(edges, Workspace(spark, "few")).collect()))
    assert want == sorted((i, i % 3) for i in range(33))
    monkeypatch.setattr(G, "COLLECTED", 5)
    for step in (G._larger_to_minimum, G._smaller_to_minimum):
        assert "Broadcast" not in step(edges, 30)._jdf.queryExecution().sparkPlan().toString()
    assert sorted(map(tuple, G.connected_components(edges, Workspace(spark, "many")).collect())) == want
