"""A cross-section of the registered queries against their SQL on the smallest tables."""

import math

import duckdb
import pytest

import __spark_entry__ as entry

SF = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
NAMES = [
    "u_complete_auc", "u_repartitioned", "u_repartitioned_incomplete", "estimator_grid", "assign_swor", "assign_prop_swr", "kernel_hinge_grad",
    "kernel_kendall", "variance_components", "hoeffding_scores", "theory_variance", "gd_step", "sgd_distributed_step", "join_asof", "agg_cube",
    "window_frames", "fn_doc_features", "udtf_pair_draws", "window_session_stats", "stream_tumbling_auc", "source_synthetic", "w5_imbalance",
]


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"create view {t} as select * from '{SF}/{t}.parquet'")
    return con


def plain(v):
    if v is None or (isinstance(v, float) and math.isnan(v)):
        return None
    if isinstance(v, float):
        return round(v, 6)
    return v if isinstance(v, (int, bool)) else str(v).removesuffix("+00:00")


def rows(columns, data):
    order = sorted(range(len(columns)), key=lambda i: columns[i])
    return sorted((tuple(plain(r[i]) for i in order) for r in data), key=repr)


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_sql(spark, duck, name):
    df = entry.queries()[name](spark, SF)
    got = rows(df.columns, [tuple(r) for r in df.collect()])
    cur = duck.execute(entry.oracle_sql()[name])
    want = rows([c[0] for c in cur.description], cur.fetchall())
    assert sorted(df.columns) == sorted(c[0] for c in cur.description)
    assert len(got) == len(want)
    for a, b in zip(got, want):
        assert all(x == y or (isinstance(x, float) and x == pytest.approx(y, abs=1e-6)) or (isinstance(y, float) and y == pytest.approx(x)) for x, y in zip(a, b)), (a, b)


def test_entry(spark):
    df = entry.entry(spark)
    assert df.count() == 40 and df.columns == ["round", "worker", "tuples", "wins", "value"]


def test_every_oracle_has_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_registry_needs_no_session():
    import subprocess
    import sys

    code = "import __spark_entry__ as e; print(len(e.queries()), len(e.oracle_sql()))"
    run = subprocess.run([sys.executable, "-c", code], capture_output=True, text=True, cwd=entry.__file__.rpartition("/")[0])
    assert run.returncode == 0, run.stderr
