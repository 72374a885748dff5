"""Queries against their DuckDB twins at the smallest scale; plans."""

import duckdb
import pandas as pd
import pytest

from cutseg.plans.registry import ORACLE_SQL, QUERIES

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
SOME = ["ngram_all", "p_prev2", "zcount_tri", "weaken_both", "skip_block", "vocab_divide", "train_divide", "laplacian_sym", "granularity_sweep", "ratio_cut", "best_cut_brute", "best_ncut_dp",
        "entropy_rise", "score_words", "merge_split_errors", "asof_model_version", "score_cube", "win_session", "stream_counts", "concatenation"]


@pytest.fixture(scope="module")
def con(sf_dir):
    c = duckdb.connect()
    for t in TABLES:
        c.sql(f"create view {t} as select * from '{sf_dir}/{t}.parquet'")
    return c


def rows(df: pd.DataFrame) -> list:
    df = df[sorted(df.columns)]
    norm = lambda v: "null" if v is None or v is pd.NA or v != v else str(round(float(v), 5)) if isinstance(v, (int, float)) and not isinstance(v, bool) or hasattr(v, "dtype") and v.dtype.kind in "if" else str(v)
    return sorted(tuple(norm(v) for v in r) for r in df.itertuples(index=False, name=None))


@pytest.mark.parametrize("name", SOME)
def test_twin(spark, con, sf_dir, name):
    got, want = QUERIES[name](spark, sf_dir).toPandas(), con.sql(ORACLE_SQL[name]).df()
    assert sorted(got.columns) == sorted(want.columns)
    assert rows(got) == rows(want)


def test_streams_read_all_documents(spark, con, sf_dir):
    test_twin(spark, con, sf_dir, "stream_counts")
    found = {r["lang"] for r in QUERIES["stream_segment"](spark, sf_dir).select("lang").distinct().collect()}
    assert found == {r[0] for r in con.sql("select distinct lang from documents where text is not null").fetchall()} and len(found) > 1


def test_tagger_is_fitted_on_all_of_train(spark, sf_dir, monkeypatch):
    from cutseg.plans import methods
    from cutseg.plans.context import context
    given = []

    class Spy:
        def __init__(self, gold):
            given.append(gold.count())

        def segment(self, sents):
            return sents

    monkeypatch.setattr(methods.B, "Tagger", Spy)
    x = context(spark, sf_dir)
    methods.predictions(x, "tagger")
    assert given == [x.train.count()] and given[0] > 0


def test_entry(spark):
    import __spark_entry__ as e
    assert e.entry(spark).limit(1).count() == 1
    assert set(e.oracle_sql()) <= set(e.queries())


def test_scan_is_pruned_and_filters_are_pushed(spark, sf_dir):
    plan = QUERIES["scan_documents"](spark, sf_dir)._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [" in plan and "LessThanOrEqual(n_chars" in plan and "text" not in plan


def test_sql_surface(spark, sf_dir):
    words = QUERIES["udtf_words"](spark, sf_dir).toPandas()
    joined = words.sort_values("w_no").groupby("sent_id")["word"].agg("".join)
    assert all(v == k.replace(" ", "") for k, v in joined.items())
