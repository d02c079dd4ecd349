"""Every query with SQL beside it gives that SQL's rows."""

import numpy as np
import pandas as pd
import pytest

from corpuskit.queries import ORACLES, QUERIES
from tests.conftest import SMALL


def plain(value):
    if value is None or value is pd.NaT or value is pd.NA or (isinstance(value, float) and np.isnan(value)):
        return "null"
    if isinstance(value, (bool, np.bool_)):
        return str(value)
    return f"{float(value):.6f}" if isinstance(value, (int, float, np.number)) else str(value)


def rows(df: pd.DataFrame):
    return sorted(tuple(map(plain, r)) for r in df[sorted(df.columns)].itertuples(index=False))


@pytest.mark.parametrize("name", list(ORACLES))
def test_query_equals_its_sql(spark, duck, name):
    want = duck.execute(ORACLES[name]).fetchdf()
    got = QUERIES[name](spark, SMALL).toPandas()
    assert sorted(got.columns) == sorted(want.columns)
    assert rows(got) == rows(want)


@pytest.mark.parametrize("name", ["p1_approx_rate", "p4_mllib", "p5_perplexity", "lid_confusion_models", "fert_hist_trained", "p5_filter_approx", "agg_approx_distinct", "agg_top_k_sketch", "agg_sketch_merge", "lid_sampled", "lid_cascade", "st_late", "scan_binary", "sort_within"])
def test_queries_without_sql_run(spark, name):
    df = QUERIES[name](spark, SMALL)
    assert df.columns and df.count() >= 0


@pytest.mark.parametrize("name", ["lid_bootstrap", "lid_confusion", "lid_f1_summary", "sub_recursive"])
def test_queries_read_the_given_documents_each_time(spark, name):
    for _ in range(2):  # a second query of a session too
        assert any(f.endswith("documents.parquet") for f in QUERIES[name](spark, SMALL).inputFiles())
