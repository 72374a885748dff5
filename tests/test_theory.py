"""Spectral theory on random bands, exact partitions by brute force, graphs."""

from itertools import product

import numpy as np
import pytest
from pyspark.sql import functions as F

from cutseg.functions import kernels as K
from cutseg.operators import graph as G, laplacian as L, segment as S
from cutseg.operators.components import connected_components
from cutseg.plans.workspace import Workspace


def random_bands(n, seed, zeros=0.3):
    rng = np.random.default_rng(seed)
    adj, skip = rng.random(n - 1) * 3, rng.random(max(0, n - 2))
    return np.where(rng.random(n - 1) < zeros, 0, adj), np.where(rng.random(max(0, n - 2)) < 0.7, 0, skip)


@pytest.fixture(scope="module")
def bands(spark):
    rows = [(str(s), n, *[x.tolist() for x in random_bands(n, s)]) for s, n in enumerate([2, 3, 4, 5, 8, 13, 21, 40, 2, 6, 9, 30])]
    return spark.createDataFrame(rows, "sent_id string, n int, adj array<double>, skip array<double>")


@pytest.mark.parametrize("form", ["plain", "sym"])
def test_inertia_counts_eigenvalues(bands, form):
    cuts = [0.0, 0.05, 0.3, 0.7, 1.0, 2.0, 5.0]
    rows = L.laplacian(bands, form).withColumn("cut", F.explode(F.array(*[F.lit(c) for c in cuts]))).select("sent_id", "adj", "skip", "cut", L.count_below(F.col("cut")).alias("k")).collect()
    for r in rows:
        v = np.linalg.eigvalsh(K.laplacians(np.array([r["adj"]]), np.array([r["skip"]]).reshape(1, -1), form))[0]
        assert v[0] == pytest.approx(0, abs=1e-9) and v.min() > -1e-9
        if np.abs(v - r["cut"]).min() > 1e-9:
            assert r["k"] == (v <= r["cut"]).sum()


@pytest.mark.parametrize("form", ["plain", "sym"])
@pytest.mark.parametrize("n", [1, 2, 3, 5, 30, 700])
def test_inertia_of_one_sentence(form, n):
    adj, skip = random_bands(n, n)
    v = np.linalg.eigvalsh(K.laplacians(adj[None], skip[None], form)[0])
    for cut in (0.05, 0.31, 0.9, 2.3):
        assert K.inertia(adj, skip, form, 1.0, cut) == max(1, (v <= cut).sum())
    if n == 700:  # over the largest part that is clustered as a whole: k is still that of the sentence
        k, _, words = S.split_sentences([("a" * n, adj, skip)], S.SegmentConfig(form=form, cut=0.31, max_n=64, cluster="contiguous"))[0]
        assert k == (v <= 0.31).sum() and len("".join(words)) == n


def brute_kmeans(u, k):
    """Least squared distance over all labellings."""
    return min(sum(((u[np.array(lab) == j] - u[np.array(lab) == j].mean(0)) ** 2).sum() for j in set(lab)) for lab in product(range(k), repeat=len(u)))


def test_kmeans_finds_the_best_clusters_of_separated_rows():
    rng = np.random.default_rng(4)
    for k in (2, 3):
        u = np.repeat(rng.normal(0, 5, (k, 2)), 3, axis=0)[:7] + rng.normal(0, 0.1, (min(7, 3 * k), 2))
        for init in ("even", "pp"):
            lab = K.kmeans(u, k, init, seed=1)
            cost = sum(((u[lab == j] - u[lab == j].mean(0)) ** 2).sum() for j in set(lab.tolist()))
            assert cost == pytest.approx(brute_kmeans(u, k), abs=1e-9)


def test_zero_eigenvalues_are_components(bands):
    for r in L.components(bands).collect():
        for form in ("plain", "sym"):
            v = np.linalg.eigvalsh(K.laplacians(np.array([r["adj"]]), np.array([r["skip"]]).reshape(1, -1), form))[0]
            reach = K.laplacians(np.array([r["adj"]]), np.array([r["skip"]]).reshape(1, -1), "plain", 0.0)[0] != 0
            np.fill_diagonal(reach, True)
            for _ in range(6):
                reach = reach @ reach
            assert (np.abs(v) < 1e-9).sum() == len({tuple(x) for x in reach})
        if not any(r["skip"]):
            assert r["n_components"] == len({tuple(x) for x in reach})


def test_two_nodes_in_closed_form():
    for a in (0.1, 1.0, 7.0):
        pair = np.array([[a]]), np.zeros((1, 0))
        assert np.linalg.eigvalsh(K.laplacians(*pair, "plain"))[0].tolist() == pytest.approx([0, 2 * a])
        assert np.linalg.eigvalsh(K.laplacians(*pair, "sym"))[0].tolist() == pytest.approx([0, 2 * a / (1 + a)])


def test_ideal_graph_gives_its_components():
    adj = np.array([1.0, 2.0, 0.0, 1.0, 0.0, 3.0])
    for form in ("plain", "sym"):
        for cluster in ("kmeans", "contiguous"):
            k, labels = S.labels_of(adj, np.zeros(5), S.SegmentConfig(form=form, cut=1e-9, cluster=cluster, init="pp"), 1)
            assert k == 3 and np.flatnonzero(np.diff(labels)).tolist() == [2, 4]


@pytest.mark.parametrize("objective", ["ratio", "normalised"])
def test_exact_partition_is_best(objective):
    for seed in range(6):
        adj, skip = random_bands(9, seed, 0.1)
        cost = K.block_costs(adj, skip, objective)
        for k in (2, 3, 4):
            brute = min(K.partition_value(cost, np.cumsum((0, *m))) for m in product((0, 1), repeat=8) if sum(m) == k - 1)
            assert K.exact_partition(adj, skip, k, objective)[0] == pytest.approx(brute)


def test_contiguous_split_is_best():
    rng = np.random.default_rng(3)
    u = rng.random((9, 3))
    for k in (2, 3):
        def loss(lab):
            return sum(((u[lab == j] - u[lab == j].mean(0)) ** 2).sum() for j in set(lab))
        brute = min(loss(np.cumsum((0, *m))) for m in product((0, 1), repeat=8) if sum(m) == k - 1)
        assert loss(K.contiguous_split(u, k)) == pytest.approx(brute)


def test_scaling_weights_and_cut_changes_nothing():
    adj, skip = random_bands(14, 5, 0.0)
    a, b = (S.labels_of(adj * c, skip * c, S.SegmentConfig(cut=0.4 * c), 0)[1].tolist() for c in (1.0, 8.0))
    assert a == b


def test_connected_components(spark):
    rng = np.random.default_rng(1)
    edges = [(int(a), int(b)) for a, b in rng.integers(0, 400, (260, 2))] + [(1000 + i, 1001 + i) for i in range(60)] + [(5000, 5000 + i) for i in range(1, 80)]
    parent: dict = {}

    def root(x):
        while parent.setdefault(x, x) != x:
            x = parent[x]
        return x
    for a, b in edges:
        x, y = sorted((root(a), root(b)))
        parent[y] = x
    got = connected_components(spark.createDataFrame(edges, "a long, b long"), Workspace(spark, "t")).collect()
    want = {x: root(x) for x in parent if any(x in e and e[0] != e[1] for e in edges)}
    assert {r["node"]: r["component"] for r in got} == want and len(got) == len(want)
    assert connected_components(spark.createDataFrame([], "a long, b long"), Workspace(spark, "t")).count() == 0


def test_graph_partition_finds_planted_groups(spark):
    rng = np.random.default_rng(0)
    centres = rng.normal(size=(3, 16))
    rows = [(i, (centres[i % 3] * 3 + rng.normal(size=16) * 0.3).tolist(), i % 3) for i in range(90)]
    v = spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int")
    found = G.partition_graph(G.knn_edges(v, 6, block=20), form="sym", cut=0.05)
    score = G.agreement(found, v.select(F.col("vec_id").alias("node"), "label")).first()
    assert score["purity"] == pytest.approx(1.0)


def planted(groups, size, seed, links=8, across=3):
    """A connected graph of dense groups with few edges between them."""
    rng = np.random.default_rng(seed)
    edges = {}
    for g in range(groups):
        for i in range(size):
            for j in {(i + 1) % size, *rng.integers(0, size, links).tolist()} - {i}:
                edges[tuple(sorted((g * size + i, g * size + j)))] = float(1 + rng.random())
        for _ in range(across):
            a, b = rng.integers(0, size, 2)
            edges[tuple(sorted((g * size + int(a), (g + 1) % groups * size + int(b))))] = 0.5
    return [(a, b, w) for (a, b), w in edges.items()]


def laplacian_values(rows, n, form):
    w = np.zeros((n, n))
    for a, b, x in rows:
        w[a, b] = w[b, a] = x
    d = w.sum(1)
    return np.linalg.eigvalsh(np.diag(d) - w if form == "plain" else np.eye(n) - w / np.sqrt(d[:, None] * d[None]))


@pytest.mark.parametrize("form, cut", [("sym", 0.1), ("plain", 0.8)])
def test_block_spectrum_equals_the_dense_one(spark, form, cut):
    rows = planted(3, 40, 1)
    edges = spark.createDataFrame(rows + rows[:5] + [(b, a, w / 2) for a, b, w in rows[5:9]] + [(7, 7, 9.0)], "src long, dst long, w double")
    small = G.partition_graph(edges, form=form, cut=cut)
    large = G.partition_graph(edges, form=form, cut=cut, dense=50)
    count = int((laplacian_values(rows, 120, form) <= cut).sum())
    assert count > 1 and large.select("cluster").distinct().count() == small.select("cluster").distinct().count() == count
    pairs = small.select("node", F.col("cluster").alias("s")).join(large, "node").select("s", "cluster").distinct().count()
    assert pairs == count and large.count() == 120


def test_large_components_are_partitioned(spark):
    rows = planted(4, 600, 2)
    edges = spark.createDataFrame(rows, "src long, dst long, w double")
    found = G.partition_graph(edges, form="sym", cut=0.1).toPandas()
    assert len(found) == 2400 > G.DENSE_VERTICES and found["component"].unique().tolist() == [0]
    groups = found.groupby(found["node"] // 600)["cluster"].unique()
    assert int((laplacian_values(rows, 2400, "sym") <= 0.1).sum()) == 4 == found["cluster"].nunique() and (groups.str.len() == 1).all()
