"""Every query with an oracle equals it; the others give rows."""

import duckdb
import pandas as pd
import pytest
from relml import catalog

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations"
SLOW = {"tree_depth4_narrow6", "tree_rmse_test", "forest_bagged", "boosted_trees", "linreg_bgd_naive_50", "baseline_ml_gbt", "svm_labels"}


@pytest.fixture(scope="module")
def oracle(sf):
    con = duckdb.connect()
    con.execute("set timezone = 'UTC'")
    for t in TABLES.split():
        con.execute(f"create view {t} as select * from '{sf}/{t}.parquet'")
    return con


def plain(v):
    if v is None or v is pd.NA or v is pd.NaT or v != v:
        return "null"
    if isinstance(v, str):
        return v
    try:
        return repr(float(v))
    except (TypeError, ValueError):
        return str(v)


def rows(df):
    return sorted(tuple(map(plain, r)) for r in df[sorted(df.columns)].itertuples(index=False))


@pytest.mark.parametrize("name", sorted(catalog.ORACLES.keys() - SLOW))
def test_oracle(spark, sf, oracle, name):
    got, want = catalog.QUERIES[name](spark, sf).toPandas(), oracle.execute(catalog.ORACLES[name]).df()
    assert sorted(got.columns) == sorted(want.columns)
    assert rows(got) == rows(want)


@pytest.mark.parametrize("name", sorted(k for k in catalog.QUERIES.keys() - catalog.ORACLES.keys() - SLOW if not k.startswith("wl_")))
def test_rows(spark, sf, name):
    assert catalog.QUERIES[name](spark, sf).count() > 0


WHOLE = {"linreg_predict": "lineitem", "tree_predict": "lineitem", "udf_predict": "lineitem", "project_derived": "lineitem", "encode_interaction": "lineitem", "join_asof": "events"}


@pytest.mark.parametrize("name", sorted(WHOLE))
def test_whole_tables(spark, sf, name):
    assert catalog.QUERIES[name](spark, sf).count() == spark.read.parquet(f"{sf}/{WHOLE[name]}.parquet").count()


def test_frames_hold_all_joined_rows(spark, sf):
    assert catalog.QUERIES["baseline_pandas_frame"](spark, sf).first().n == spark.read.parquet(f"{sf}/lineitem.parquet").count()


@pytest.mark.parametrize("name", ["boosted_trees", "baseline_numpy_lstsq"])
def test_learns_on_train(monkeypatch, spark, sf, name):
    from relml import datasets

    parts, real = [], datasets.narrow6
    monkeypatch.setattr(datasets, "narrow6", lambda s, d, part="full": parts.append(part) or real(s, d, part))
    assert catalog.QUERIES[name](spark, sf).count() > 0 and parts == ["train"]


def test_explain_gives_what_the_job_gives(spark, sf, oracle):
    text = {r.stage: r.text for r in catalog.QUERIES["program_explain"](spark, sf).collect()}
    got = dict(x.split(": ") for x in text["result"].split("\n"))
    assert list(got) == text["sums"].split("\n")
    assert int(got["s*s"]) == oracle.execute("select sum(l_suppkey * l_suppkey) from lineitem").fetchone()[0]


def test_entry(spark):
    import __spark_entry__ as e

    assert e.entry(spark).count() == 5
    assert set(e.oracle_sql()) <= set(e.queries())
