from __future__ import annotations

import duckdb
import pytest

from ldpspark import queries as core
from ldpspark.sources.tables import TABLES

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def duck():
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"create view {t} as select * from '{SF}/{t}.parquet'")
    return c


@pytest.mark.parametrize("name", sorted(core.ORACLES))
def test_query_equals_its_sql(spark, duck, name):
    df = core.QUERIES[name](spark, SF)
    want = duck.execute(core.ORACLES[name])
    columns = [x[0] for x in want.description]
    assert sorted(columns) == sorted(df.columns)
    order = sorted(columns)
    rows = lambda found: sorted([tuple(r) for r in found], key=str)
    a = rows(df.select(*order).collect())
    b = rows([[r[columns.index(c)] for c in order] for r in want.fetchall()])
    assert a == b


def test_constants_are_those_of_their_own_dimensions(spark):
    # the dimensions of w14_dimension_sweep once took their place
    assert sorted(r["d"] for r in core.QUERIES["halfspace_constants"](spark, SF).collect()) == list(range(1, 13))


#: Queries that once made their data up, and a column that they must read.
MOVED = {
    "audit_empirical": "l_orderkey", "audit_exact": "l_discount", "batch_size_grid": "l_extendedprice", "communication_cost": "l_extendedprice", "frequency_radius": "l_returnflag",
    "halfspace_constants": "o_custkey", "halfspace_violation": "o_custkey", "mean_radius": "l_returnflag", "projection_distortion": "l_linenumber", "variance_grid": "l_extendedprice",
}


@pytest.mark.parametrize("name", sorted(MOVED))
def test_query_answers_for_the_rows_of_its_table(spark, tmp_path, name):
    table = "orders" if MOVED[name].startswith("o_") else "lineitem"
    (tmp_path / "all").mkdir()
    for t in TABLES:
        (tmp_path / "all" / f"{t}.parquet").symlink_to(f"{SF}/{t}.parquet")
    (tmp_path / "all" / f"{table}.parquet").unlink()
    few = spark.read.parquet(f"{SF}/{table}.parquet").where("l_linenumber = 1 and l_discount > 0.02" if table == "lineitem" else "o_custkey < 40")
    few.write.parquet(str(tmp_path / "all" / f"{table}.parquet"))
    rows = lambda sf: sorted(map(str, core.QUERIES[name](spark, sf).collect()))
    assert rows(SF) != rows(str(tmp_path / "all"))


def test_entry_points():
    import __spark_entry__ as e

    assert set(e.oracle_sql()) <= set(e.queries())
