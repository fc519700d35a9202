"""Queries follow their tables: held against their SQL over the smallest tables and over a part of one."""

import os

import duckdb
import pyarrow as pa
import pytest

from causemine.operators import counting
from causemine.queries import ORACLES, QUERIES

WHOLE = "/root/testdata/sf0.001"


def answers(spark, name, folder):
    c = duckdb.connect()
    for table in os.listdir(folder):
        c.execute(f"create view {table.removesuffix('.parquet')} as select * from '{folder}/{table}'")
    found = sorted(map(tuple, QUERIES[name](spark, folder).collect()), key=str)
    assert found == sorted(c.execute(ORACLES[name]).fetchall(), key=str)
    return found


@pytest.mark.parametrize(("name", "table", "part"), [
    ("candidate_bounds", "lineitem", "l_returnflag = 'R'"),
    ("condense_annihilation", "lineitem", "l_discount > 0.065"),
    ("condense_examples", "lineitem", "l_linestatus = 'F'"),
    ("confidence_vs_lift", "lineitem", "l_returnflag = 'R'"),
    ("structure_raw_lines", "events", "value > 50"),
])
def test_results_follow_the_table(spark, tmp_path, name, table, part):
    for other in os.listdir(WHOLE):
        if other != f"{table}.parquet":
            os.symlink(f"{WHOLE}/{other}", tmp_path / other)
    duckdb.sql(f"copy (select * from '{WHOLE}/{table}.parquet' where {part}) to '{tmp_path}/{table}.parquet' (format parquet)")
    assert answers(spark, name, WHOLE) != answers(spark, name, str(tmp_path))


def test_a_chain_of_the_tables_is_dropped_at_once(spark):
    assert answers(spark, "condense_annihilation", WHOLE) == [("sequential", 3), ("simultaneous", 0)]


def test_raw_lines_of_events_with_gaps(spark, tmp_path):
    rows = "(1, timestamp '2024-01-01 00:07:59', 4, 'purchase'), (2, timestamp '2024-01-01 00:07:00', null, 'purchase'), (null, timestamp '2024-01-01 00:07:00', 4, 'signup'), (3, null, 4, 'error'), (4, timestamp '2023-12-31 23:59:00', null, 'error'), (5, timestamp '2023-12-31 23:59:00', 1, null), (6, timestamp '2023-12-31 23:58:00', 1, 'view'), (7, timestamp '2024-01-01 00:07:00', 1, 'click')"
    duckdb.sql(f"copy (select * from (values {rows}) t(event_id, ts, user_id, event_type)) to '{tmp_path}/events.parquet' (format parquet)")
    assert answers(spark, "structure_raw_lines", str(tmp_path)) == [("473351:59", 1, 0, 0, 0, None), ("473352:07", 0, 2, 1, 0, "y")]


def test_batches_without_a_frequent_item_are_counted():
    batch = lambda *lists: pa.RecordBatch.from_arrays([pa.array(lists, pa.list_(pa.int32())), pa.array([5] * len(lists), pa.int64()), pa.array([2] * len(lists), pa.int64())], ["items", "n_all", "n_pos"])
    found = counting.counted_in(iter([batch([], []), batch([0, 1], []), batch()]), [[0, 1], [2]])
    assert found.to_pylist() == [{"items": [0, 1], "n_x": 5, "n_xy": 2}]
