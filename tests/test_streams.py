"""Streams whose event ids are not in the order of event time, against DuckDB."""

import datetime

import duckdb
import pytest

from probejoin import queries_streaming  # noqa: F401
from probejoin.queries import ORACLES, QUERIES


@pytest.fixture(scope="module")
def folder(tmp_path_factory):
    """Events of three days, given three times with shifted ids; user 1 has two events just half an hour apart."""
    path = tmp_path_factory.mktemp("events")
    con = duckdb.connect()
    con.execute(
        "COPY (SELECT CAST(k * 300 + i AS BIGINT) AS event_id, TIMESTAMP '2024-01-01' + INTERVAL 1 MINUTE * (i * 15) AS ts, CAST(k * 3 + i // 2 % 3 AS BIGINT) AS user_id, "
        f"CASE WHEN i % 2 = 0 THEN 'click' ELSE 'purchase' END AS event_type, CAST(i AS DOUBLE) AS value, '{{}}' AS props FROM range(3) r(k), range(300) s(i)) TO '{path}/events.parquet' (FORMAT parquet)"
    )
    first = datetime.datetime(2024, 2, 1)
    con.execute(f"CREATE TABLE more AS SELECT * FROM '{path}/events.parquet'")
    for k in range(2):
        con.execute("INSERT INTO more VALUES (?, ?, 99, 'view', 1.0, '{}')", [900 + k, first + datetime.timedelta(minutes=30 * k)])
    con.execute(f"COPY more TO '{path}/events.parquet' (FORMAT parquet)")
    return str(path)


@pytest.mark.parametrize("name", ["st_dedup", "st_interval_join", "st_session"])
def test_events_out_of_order(spark, folder, name):
    df = QUERIES[name](spark, folder)
    con = duckdb.connect()
    con.execute(f"CREATE VIEW events AS SELECT * FROM '{folder}/events.parquet'")
    cur = con.execute(ORACLES[name])
    names = [d[0] for d in cur.description]
    assert sorted(tuple(r) for r in df.select(*names).collect()) == sorted(cur.fetchall())
