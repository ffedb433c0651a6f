"""Queries that answer for the whole domain, on tables that reach beyond the given ones."""

from datetime import datetime, timedelta

import duckdb
import pytest
from oracle import compare, connect

import __spark_entry__ as entry
from gridmask.model import fit_spec
from gridmask.operators import tables as T


@pytest.mark.parametrize("name", ["pivot_turns", "asof_hours"])
def test_equals_sql(spark, sf_dir, name):
    assert compare(entry.queries()[name](spark, sf_dir), connect(sf_dir), entry.oracle_sql()[name]) is None


def test_pivot_keeps_every_cell(spark):
    want = {(conv, turn): float(100 * conv + turn) for conv, n in ((3, 1), (4, 8), (5, 21)) for turn in range(1, n + 1) if turn != 6}
    cells = spark.createDataFrame([(*at, v) for at, v in want.items()], "conv long, turn long, value double")
    rows = T.pivot_blocks(cells, fit_spec(cells, ["conv", "turn"], (16, 8)), "turn", "t").collect()
    assert {(r.conv, r.turn_from + k): r[f"t{k}"] for r in rows for k in range(8) if r[f"t{k}"] is not None} == want
    assert len(rows) == 1 + 1 + 3


def test_pivot_turns_tells_all_turns(spark, sf_dir):
    rows = entry.queries()["pivot_turns"](spark, sf_dir).collect()
    told = sum(r[f"t{k}"] is not None for r in rows for k in range(8))
    texts = spark.read.parquet(f"{sf_dir}/conversations.parquet").where("text is not null")
    assert told == texts.select("conv_id", "turn").distinct().count()


@pytest.fixture
def late_events(spark, tmp_path):
    """Events of 40 days from 2024-01-01 on; user 2 first comes on the last day, below all users of earlier days."""
    first = datetime(2024, 1, 1)
    rows = [(k, first + timedelta(hours=h), u, "view", v, None) for k, (u, h, v) in enumerate([(5, 3, 1.0), (5, 3, 2.0), (9, 30, 3.0), (5, 700, 4.0), (9, 701, None), (9, 730, 5.0), (5, 801, 20.0), (2, 959, 60.0)])]
    df = spark.createDataFrame(rows, "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string")
    df.write.parquet(str(tmp_path / "events.parquet"))
    return str(tmp_path)


def test_asof_hours_beyond_thirty_days(spark, late_events):
    got = {(r.user, r.hour): r.latest for r in entry.queries()["asof_hours"](spark, late_events).collect()}
    want = {}
    for user, cells in {5: {3: 2.0, 700: 4.0, 801: 20.0}, 9: {30: 3.0, 730: 5.0}, 2: {959: 60.0}}.items():
        for hour in range(min(cells), 960):
            want[user, hour] = cells[max(h for h in cells if h <= hour)]
    assert got == want


@pytest.mark.parametrize("name", ["child_edges", "wsse_compare"])
def test_nodes_over_few_values(spark, tmp_path, name):
    """A node whose children hold fewer values than it may have bins: its edges are still the children's bounds."""
    rows = [(p, s, float(1000 * p + s)) for p in (1, 2, 40, 41, 300) for s in (1, 5, 9, 33)]
    spark.createDataFrame(rows, "l_partkey long, l_suppkey long, l_extendedprice double").write.parquet(str(tmp_path / "lineitem.parquet"))
    con = duckdb.connect()
    con.execute(f"create view lineitem as select * from read_parquet('{tmp_path}/lineitem.parquet/*.parquet')")
    assert compare(entry.queries()[name](spark, str(tmp_path)), con, entry.oracle_sql()[name]) is None
