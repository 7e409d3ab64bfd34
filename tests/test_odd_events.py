"""Queries on events beside their SQL over values that the small tables lack."""

import math
from datetime import datetime, timedelta

import duckdb
import pyarrow as pa
import pyarrow.parquet as pq

from tests.compare import same
from tilebalance.queries import load_all


def written(folder, rows):
    """A folder of tables with events of (user_id, ts, value)."""
    users, times, values = zip(*rows)
    n = len(rows)
    columns = {"event_id": pa.array(range(n), pa.int64()), "ts": pa.array(times, pa.timestamp("us")), "user_id": pa.array(users, pa.int64()), "event_type": ["view"] * n, "value": pa.array(values, pa.float64(), from_pandas=False), "props": ["{}"] * n}
    pq.write_table(pa.table(columns), f"{folder}/events.parquet")
    return str(folder)


def test_op_math(spark, tmp_path):
    """Zero and less have no logarithm, large numbers and infinities are no longs, and near ties the scaled number decides."""
    ties = [((2 * k + 1) * 0.5e-6) ** 2 for k in range(1, 2000)]
    odd = [0.0, -0.0, -0.5, -1.0, math.inf, -math.inf, math.nan, None, 1e16, 1e300, -1e300, 2.5, 560.21]
    path = written(tmp_path, [(1, datetime(2024, 1, 1), v) for v in odd + ties])
    run, sql = load_all()["op_math"]
    text = lambda r: [None if v is None else repr(float(v) + 0.0) for v in r]
    theirs = duckdb.sql(sql.replace("FROM events", f"FROM read_parquet('{path}/events.parquet')")).fetchall()
    a, b = ({r[0]: text(r[1:]) for r in rows} for rows in (run(spark, path).collect(), theirs))
    assert len(a) == len(b) == len(odd + ties)
    assert [a[k] for k in range(len(odd))] == [b[k] for k in range(len(odd))]
    # Made ties of powers and logarithms hang on the last bit of each engine's library: not compared.
    whole = (0, 1, 2, 5)
    assert {k: [v[i] for i in whole] for k, v in a.items()} == {k: [v[i] for i in whole] for k, v in b.items()}


def test_st_session_rows_stay_off_the_driver(spark, tmp_path):
    """The stream's complete result lies in files, not in a table in the driver's memory; a gap of just six hours parts sessions."""
    day = datetime(2024, 1, 1)
    path = written(tmp_path, [(u, day + timedelta(microseconds=21_600_000_000 * k - (k == 2)), 1.0) for u in range(300) for k in (0, 1, 1, 2, 5)])
    run, sql = load_all()["st_session"]
    df = run(spark, path)
    assert df.inputFiles()
    assert same(df, sql, path) == 300
    assert not spark.conf.get("spark.sql.streaming.stateStore.providerClass").endswith("RocksDBStateStoreProvider")
