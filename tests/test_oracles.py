"""Every registered query of the engine against its SQL on the smallest tables."""

import math

import duckdb
import pytest

from gembed import catalog

SF = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def duck():
    c = duckdb.connect()
    c.execute("set timezone='UTC'")
    for t in TABLES:
        c.execute(f"create view {t} as select * from '{SF}/{t}.parquet'")
    return c


def plain(v):
    if v is None or (isinstance(v, float) and math.isnan(v)):
        return "null"
    if isinstance(v, float):
        return repr(round(v, 9) + 0.0)
    return str(v)[:19] if hasattr(v, "isoformat") else str(v)


@pytest.mark.parametrize("name", sorted(catalog.oracle_sql()))
def test_query_equals_sql(spark, duck, name):
    df = catalog.queries()[name](spark, SF)
    cols = sorted(df.columns)
    got = sorted(tuple(plain(r[c]) for c in cols) for r in df.collect())
    run = duck.execute(catalog.oracle_sql()[name])
    names = [d[0] for d in run.description]
    assert sorted(names) == cols
    assert got == sorted(tuple(plain(row[names.index(c)]) for c in cols) for row in run.fetchall())


def test_queries_without_sql_return_rows(spark):
    for name in ("occupancy", "schedule_rows", "score_hole", "approx_distinct"):
        assert catalog.queries()[name](spark, SF).count() > 0


def test_range_frame_on_parts_of_seconds(spark, tmp_path):
    """Frames begin and end on rounded seconds: an hour less a part of a second, halves, and times before 1970."""
    c = duckdb.connect()
    c.execute("set timezone='UTC'")
    at = [0.4, 0.5, 1.5, 2.5, 3600.4, 3600.6, 3601.4, 3601.5, 3602.5, 7200.9, -0.5, -3600.5, -1.6]
    c.execute("create table events as select * from (values " + ", ".join(f"({i}, {i % 2}, make_timestamp({round(x * 1e6)}::bigint), 'view')" for i, x in enumerate(at)) + ") t(event_id, user_id, ts, event_type)")
    c.execute(f"copy events to '{tmp_path}/events.parquet' (format parquet)")
    want = c.execute(catalog.oracle_sql()["range_frame"]).fetchall()
    got = catalog.queries()["range_frame"](spark, str(tmp_path)).select("event_id", "last_hour", "first_event").collect()
    assert sorted(map(tuple, got)) == sorted(want)


ON_ORDERS = "alignment_check model_size negative_cost order_column_major order_inside_out order_outside_in order_row_major partition_io partition_plan".split()


def test_plans_and_costs_follow_the_orders_table(spark, tmp_path):
    """With a few orders some buckets are empty and all counts differ; the SQL reads the same table."""
    import pyarrow as pa
    import pyarrow.parquet as pq

    pq.write_table(pa.table({"o_orderkey": pa.array(range(9), pa.int64()), "o_custkey": pa.array([k % 3 for k in range(9)], pa.int64())}), f"{tmp_path}/orders.parquet")
    c = duckdb.connect()
    c.execute(f"create view orders as select * from '{tmp_path}/orders.parquet'")
    for name in ON_ORDERS:
        df = catalog.queries()[name](spark, str(tmp_path))
        cols = sorted(df.columns)
        got = sorted(tuple(plain(r[c]) for c in cols) for r in df.collect())
        run = c.execute(catalog.oracle_sql()[name])
        names = [d[0] for d in run.description]
        assert got == sorted(tuple(plain(row[names.index(x)]) for x in cols) for row in run.fetchall()), name
        assert got != sorted(tuple(plain(r[c]) for c in cols) for r in catalog.queries()[name](spark, SF).collect()), name
    few = {(r["machines"], r["parts"]): r for r in catalog.queries()["occupancy"](spark, str(tmp_path)).collect()}
    all_of_them = {(r["machines"], r["parts"]): r for r in catalog.queries()["occupancy"](spark, SF).collect()}
    assert few[8, 32]["later_epochs"] < all_of_them[8, 32]["later_epochs"] and few[1, 2]["later_epochs_by_edges"] == 1
    assert catalog.queries()["bench_negatives"](spark, str(tmp_path)).count() == 8
