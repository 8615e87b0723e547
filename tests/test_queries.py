"""Queries against DuckDB on the smallest tables, and plans."""

import duckdb
import numpy as np
import pytest

from basepack import queries as K
from basepack.operators import attention, context
from basepack.sources import tables as S

SF = "/root/testdata/sf0.001"
SLOW = {n for n in K.Q if n.startswith(("t1_human_c", "t1_human_b", "t1_human_m", "t3_")) or n not in K.SQL}


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for t in "orders lineitem events documents embeddings pages benchmark labels conversations".split():
        con.execute(f"create view {t} as select * from '{SF}/{t}.parquet'")
    return con


def canon(df):
    df = df[sorted(df.columns)].copy()
    for c in df:
        if df[c].dtype.kind == "M":
            df[c] = df[c].astype("datetime64[us]").astype(str)

        def one(v):
            if v is None or isinstance(v, float) and np.isnan(v):
                return "~"
            return str(float(v)) if isinstance(v, (int, float, np.number)) and not isinstance(v, bool) else str(v)

        df[c] = df[c].map(one)
    return df.sort_values(list(df.columns)).reset_index(drop=True)


@pytest.mark.parametrize("name", sorted(set(K.Q) - SLOW))
def test_equals_duckdb(spark, duck, name):
    a, b = canon(K.Q[name](spark, SF).toPandas()), canon(duck.execute(K.SQL[name]).df())
    assert list(a.columns) == list(b.columns) and a.equals(b)


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_plans(spark):
    p = plan(context.adaptive(S.event_rows(spark, SF), 2))
    assert p.count("Exchange hashpartitioning") <= 2 and "Cartesian" not in p
    p = plan(attention.attend_memory(S.segments(spark, SF), 1))
    assert "NestedLoop" not in p and "Cartesian" not in p
    p = plan(K.Q["scan_prune"](spark, SF))
    assert "PushedFilters: [IsNotNull(n_chars), GreaterThan(n_chars,1000)]" in p and "text" not in p.split("ReadSchema")[1]


@pytest.mark.parametrize("name,table", [("gelu_table", "embeddings"), ("length_for_budget", "documents"), ("model_cost_table", "documents"), ("ngram_vocab", "events")])
def test_reads_a_given_table(spark, duck, name, table):
    df = K.Q[name](spark, SF)
    assert any(f.endswith(f"/{table}.parquet") for f in df.inputFiles())
    assert df.count() == duck.execute(f"SELECT count(*) FROM ({K.SQL[name]})").fetchone()[0] > 0


def test_grouped_is_faster(spark):
    rows = {r["method"]: r for r in K.Q["t4_scores"](spark, SF).collect()}
    assert rows["all"]["seconds"] < rows["none"]["seconds"]


def test_entry(spark):
    import __spark_entry__ as e

    rows = e.entry(spark).collect()
    assert rows and all(r["lossless"] for r in rows)
    assert set(e.oracle_sql()) <= set(e.queries())
