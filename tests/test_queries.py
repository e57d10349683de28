"""Every query runs at the smallest scale, and equals its SQL where it has one."""

from __future__ import annotations

import duckdb
import pytest

import __spark_entry__ as entry

CORE = entry.core_queries
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def con(sf):
    c = duckdb.connect()
    for t in TABLES:
        c.sql(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{sf}/{t}.parquet')")
    return c


def normal(rows, columns):
    def cell(v):
        return round(v, 6) + 0.0 if isinstance(v, float) else v

    return sorted((tuple(cell(r[c]) for c in columns) for r in rows), key=repr)


@pytest.mark.parametrize("name", [n for n in CORE.QUERIES if n in CORE.ORACLE])
def test_query_equals_sql(spark, sf, con, name):
    got = CORE.QUERIES[name](spark, sf)
    columns = sorted(got.columns)
    want = con.sql(CORE.ORACLE[name])
    assert sorted(want.columns) == columns
    rows = [dict(zip(want.columns, r, strict=True)) for r in want.fetchall()]
    assert normal([r.asDict() for r in got.collect()], columns) == normal(rows, columns)


@pytest.mark.parametrize("name", [n for n in CORE.QUERIES if n not in CORE.ORACLE])
def test_other_queries_run(spark, sf, name):
    assert CORE.QUERIES[name](spark, sf).count() > 0


def test_stream_emits_open_sessions_too(spark, sf, con):
    found = {}
    for r in CORE.QUERIES["stream_sessions"](spark, sf).collect():
        sessions, n = found.get(r["user_id"], (0, 0))
        found[r["user_id"]] = sessions + 1, n + r["n"]
    want = con.sql(f"SELECT user_id, sessions, n FROM ({CORE.ORACLE['session_windows_users']})").fetchall()
    assert found == {u: (s, n) for u, s, n in want}


def test_entry(spark):
    rows = entry.entry(spark).collect()
    assert len(rows) == 20 and all(r["ratio"] > 1 for r in rows)


def test_outcomes(spark, sf):
    """What the study reports, on the stand-ins: few bits keep the accuracy; one bit needs its carried error."""
    rows = {r["run"]: r for r in CORE.QUERIES["onebit_compare"](spark, sf).collect()}
    assert rows["q4_512"]["top1"] >= rows["fp32"]["top1"] - 0.02 and rows["q4_512"]["ratio"] > 7.8
    assert rows["onebit"]["train_loss"] < rows["onebit_no_carry"]["train_loss"]
    assert rows["fp32"]["train_loss"] <= rows["onebit"]["train_loss"] + 1e-3
    share = {(r["workload"], r["run"], r["k"]): r["n_bits"] for r in CORE.QUERIES["breakdown_epoch"](spark, sf).collect()}
    assert all(share["wide_cheap", "fp32", k] > 7.5 * share["wide_cheap", "q4_512", k] for k in (2, 4, 8, 16))
