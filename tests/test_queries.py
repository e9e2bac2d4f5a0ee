import os

import duckdb
import pytest

from pipeflow.oracles import ORACLES
from pipeflow.queries import QUERIES

SF = "/root/testdata/sf0.001"


def rows(df):
    def one(v):
        if v is None or isinstance(v, float) and v != v:
            return "null"
        return f"{v:.9g}" if isinstance(v, float) else str(v)

    return sorted(tuple(one(r[c]) for c in sorted(df.columns)) for r in df.to_dict("records"))


@pytest.fixture(scope="module")
def con():
    c = duckdb.connect()
    for f in os.listdir(SF):
        c.execute(f"create view {f.removesuffix('.parquet')} as select * from read_parquet('{SF}/{f}')")
    return c


@pytest.mark.skipif(not os.path.isdir(SF), reason="the given tables aren't here")
@pytest.mark.parametrize("name", sorted(QUERIES))
def test_query_against_sql(spark, con, name):
    got = QUERIES[name](spark, SF).toPandas().astype(object)
    if name in ORACLES:
        want = con.sql(ORACLES[name]).df().astype(object)
        assert sorted(got.columns) == sorted(want.columns) and len(got) == len(want)
        a, b = (df.where(df.notna(), None) for df in (got, want))
        assert rows(a) == rows(b)


@pytest.mark.parametrize("name", ["progress_shares_events", "progress_curve_events", "progress_pace_events", "progress_pace_equal_events"])
def test_runs_that_took_no_time(spark, tmp_path, name):
    """User 1 has a run of 0 seconds beside others, user 2's largest run took 0 seconds, user 3's only run has no value."""
    c = duckdb.connect()
    log = [(1, 1, "view", 2.5), (1, 1, "click", 1.5), (1, 2, "view", 0.0), (2, 1, "view", 0.0), (2, 1, "error", 0.0), (2, 2, "click", 3.0), (3, 1, "view", None)]
    rows_ = ", ".join(f"({i}, TIMESTAMP '2024-01-0{d} 10:00:0{i}', {u}, '{k}', {'NULL' if v is None else v})" for i, (u, d, k, v) in enumerate(log))
    c.execute(f"copy (select event_id::bigint event_id, ts, user_id::bigint user_id, event_type, value::double as value from (values {rows_}) t(event_id, ts, user_id, event_type, value)) to '{tmp_path}/events.parquet'")
    c.execute(f"create view events as select * from '{tmp_path}/events.parquet'")
    # toPandas turns null and NaN into one; the rows themselves keep them apart
    got = QUERIES[name](spark, str(tmp_path))
    assert sorted(map(str, (tuple(r) for r in got.collect()))) == sorted(map(str, c.sql(ORACLES[name]).select(*got.columns).fetchall()))


#: Queries of examples whose data were once made up.
ON_TABLES = ["fn_trig", "cost_extrapolation", "memory_fig", "phases_example", "orders_example", "metadata_reach_example"]


@pytest.mark.skipif(not os.path.isdir(SF), reason="the given tables aren't here")
@pytest.mark.parametrize("name", ON_TABLES)
def test_examples_read_given_tables(spark, name):
    assert QUERIES[name](spark, SF).inputFiles()


@pytest.mark.parametrize("size", [20, 5])
def test_traffic_of_odd_tables(spark, tmp_path, size):
    """Keys that are null or negative, and with size 5 no part that is kept, so that nothing meets from there on."""
    c = duckdb.connect()
    tables = {
        "customer": "select unnest([1, 2, -3, null])::bigint c_custkey, 4 c_nationkey", "orders": "select unnest([10, 11, -12, null])::bigint o_orderkey, unnest([1, 2, 2, 1])::bigint o_custkey, timestamp '2024-05-01' o_orderdate",
        "supplier": "select unnest([7, -8])::bigint s_suppkey", "part": f"select unnest([5, 6, -1])::bigint p_partkey, {size} p_size", "documents": "select unnest([1, 26, -2, null])::bigint doc_id, 'a b c' as text",
        "lineitem": "select unnest([10, 10, 11, -12])::bigint l_orderkey, unnest([5, 6, 9, 5])::bigint l_partkey, 7::bigint l_suppkey, 2.5::double l_extendedprice, 0.1::double l_discount",
    }
    for n, sql in tables.items():
        c.execute(f"copy ({sql}) to '{tmp_path}/{n}.parquet'")
        c.execute(f"create view {n} as select * from '{tmp_path}/{n}.parquet'")
    got = QUERIES["big_pipeline_traffic"](spark, str(tmp_path)).collect()
    assert sorted(map(tuple, got)) == sorted(c.sql(ORACLES["big_pipeline_traffic"]).fetchall())
