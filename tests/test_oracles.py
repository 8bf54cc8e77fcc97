"""Every registered query that has SQL, against DuckDB on the smallest tables; whole runs on the middle ones."""

import glob
import os

import duckdb
import pytest

from winjoin.plans import registry

SMALL, MIDDLE = "/root/testdata/sf0.001", "/root/testdata/sf0.01"
KINDS = {"bigint": "BIGINT", "int": "INTEGER", "double": "DOUBLE", "string": "VARCHAR", "boolean": "BOOLEAN"}
#: Sweeps of the modelled cluster: minutes each here, so one of them stands for all, beside the single runs.
RUNS = {n for n in registry.ORACLE_SQL if n.startswith("exp_") and n != "exp_w11_buffer_vs_groups" or n == "capacity_grid"}
SHOWN = {"exp_w9_comm_vs_epoch"}
MOVING = {"rebalance_trace", "degree_trace", "supplier_consumer_pairs", "move_cost"}


def tables(sf):
    con = duckdb.connect()
    for f in glob.glob(f"{sf}/*.parquet"):
        con.sql(f"CREATE VIEW {os.path.basename(f)[:-8]} AS SELECT * FROM '{f}'")
    return con


@pytest.fixture(scope="module")
def duck():
    return {sf: tables(sf) for sf in (SMALL, MIDDLE)}


@pytest.mark.parametrize("name", sorted(registry.ORACLE_SQL.keys() - RUNS | SHOWN))
def test_query_equals_sql(spark, duck, name):
    sf = MIDDLE if name in SHOWN | MOVING else SMALL
    df = registry.QUERIES[name](spark, sf)
    want = duck[sf].sql(registry.ORACLE_SQL[name])
    columns = sorted(df.columns)
    assert columns == sorted(want.columns)
    assert {c: KINDS[t] for c, t in df.dtypes} == {c: str(t) for c, t in zip(want.columns, want.types)}
    at = [want.columns.index(c) for c in columns]
    rows = sorted(str(tuple(r[c] for c in columns)) for r in df.collect())
    assert rows == sorted(str(tuple(r[i] for i in at)) for r in want.fetchall())
    assert rows or sf == SMALL


def test_runs_on_events_show_what_they_sweep(duck):
    """From the SQL, to which the registered query is equal: groups move, and every swept parameter changes a result."""
    con = duck[MIDDLE]
    assert con.sql(f"SELECT sum(moved_groups) FROM ({registry.ORACLE_SQL['rebalance_trace']})").fetchall()[0][0] > 0
    degrees = con.sql(f"SELECT count(DISTINCT active), sum(moved) FROM ({registry.ORACLE_SQL['degree_trace']})").fetchall()[0]
    assert degrees[0] >= 4 and degrees[1] > 0
    found = con.sql(registry.ORACLE_SQL["exp_w12_ablations"])
    wide: dict[str, dict[str, dict]] = {}
    for r in (dict(zip(found.columns, r)) for r in found.fetchall()):
        wide.setdefault(r["param"], {}).setdefault(r["scenario"], {})[r["measure"]] = r["value"]
    for param, cases in wide.items():
        assert len({str(sorted(m.items())) for m in cases.values()}) > 1, param
    delay = {s: m["delay_avg_us"] for cases in wide.values() for s, m in cases.items()}
    assert delay["w12/tr_over_td=2"] < delay["w12/tr_over_td=10"] < delay["w12/static/tr_over_td=0"]
    assert delay["w12/theta=0.25"] < delay["w12/theta=1"] < delay["w12/theta=4"]
    assert delay["w12/n_part=48"] < delay["w12/n_part=12"] < delay["w12/per_node/n_part=4"]
    assert delay["w12/shedding/kept=0.5"] < delay["w12/shedding/kept=0.75"] < delay["w12/theta=1"]


def test_entry(spark):
    import __spark_entry__

    assert __spark_entry__.entry(spark).count() == 189
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())
