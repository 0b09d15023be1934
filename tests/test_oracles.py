"""Every registered query of the library against its DuckDB counterpart, on the smallest tables."""

import os

import duckdb
import pytest

from splitcount.queries import ORACLES, QUERIES

from .conftest import SF

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for t in TABLES:
        p = f"{SF}/{t}.parquet"
        con.sql(f"create view {t} as select * from '{p + '/*.parquet' if os.path.isdir(p) else p}'")
    return con


@pytest.mark.parametrize("name", sorted(QUERIES))
def test_query(spark, duck, name):
    df = QUERIES[name](spark, SF)
    cols = sorted(df.columns)
    got = sorted(tuple(map(repr, r)) for r in df.select(*cols).collect())
    if name not in ORACLES:
        assert got
        return
    r = duck.sql(ORACLES[name])
    order = sorted(range(len(r.columns)), key=lambda i: r.columns[i])
    assert cols == [r.columns[i] for i in order]
    want = sorted(tuple(repr(x[i]) for i in order) for x in r.fetchall())
    assert got == want


@pytest.fixture(scope="module")
def half(spark, tmp_path_factory):
    """The tables with every second key."""
    d = tmp_path_factory.mktemp("half")
    for t, key in (("lineitem", "l_orderkey"), ("events", "event_id")):
        spark.read.parquet(f"{SF}/{t}.parquet").where(f"{key} % 2 = 0").write.parquet(f"{d}/{t}.parquet")
    return str(d)


_ON_TABLES = "calculators reduction_law rse src_pairs theorem_bits w04_pairs w06_update_time w07_total_time w08_load_factor w08_load_time w10_closed w10_sizes"


@pytest.mark.parametrize("name", [f"q_{n}" for n in _ON_TABLES.split()])
def test_the_table_decides(spark, half, name):
    """These experiments take their items from a table: with half of its keys their figures change."""
    got = [sorted(tuple(map(repr, r)) for r in QUERIES[name](spark, d).drop("seconds", "per_item").collect()) for d in (SF, half)]
    assert got[0] and got[1] and got[0] != got[1]


def test_streams_of_a_table(spark):
    """Copies with shifted ids fill a stream; runs of one repetition get the same first items; a run takes as many as it asks."""
    from splitcount import measures, workloads

    ids = workloads.event_stream(spark, SF, 5_000)
    assert ids.count() == ids.distinct().count() >= 5_000
    runs = [(v, p, n, 0, kind) for v in ("opt", "reg6") for p in (4, 10) for n in (16, 4_096) for kind in ("pairs", "integers", "strings")]
    got = {tuple(r[k] for k in ("variant", "p", "n", "input")): r["est"] for r in measures.sequential(spark, runs, ids).collect()}
    assert len(got) == len(runs)
    assert all(got["opt", p, n, k] == got["reg6", p, n, k] and abs(got["opt", p, n, k] / n - 1) < (1 if p == 4 else 0.2) for _, p, n, _, k in runs)
