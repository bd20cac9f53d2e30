"""Outer joins over whole tables, against brute force; and against the earlier statements on filtered orders."""

import duckdb
import pyarrow.compute as pc
import pyarrow.parquet as pq
import pytest

from motifmill import catalogue

from .test_catalogue import SF, plain


@pytest.mark.parametrize("how", ["left", "right", "full"])
def test_outer_joins_take_every_order(spark, tmp_path, how):
    customers = pq.read_table(f"{SF}/customer.parquet", columns=["c_custkey"]).column(0).to_pylist()
    table = pq.read_table(f"{SF}/orders.parquet")
    orders = list(zip(table.column("o_custkey").to_pylist(), table.column("o_orderkey").to_pylist()))
    known, used = set(customers), {c for c, _ in orders}
    expected = [(c, o) for c, o in orders if c in known]
    expected += [(c, None) for c in customers if c not in used] if how != "right" else []
    expected += [(None, o) for c, o in orders if c not in known] if how != "left" else []
    got = [tuple(r) for r in catalogue.QUERIES[f"op_join_{how}"](spark, SF).collect()]
    assert sorted(map(str, got)) == sorted(map(str, expected)) and len(used) > 1

    con = duckdb.connect()
    few = table.filter(pc.is_in(table.column("o_orderkey"), pc.filter(table.column("o_orderkey"), pc.equal(pc.subtract(table.column("o_orderkey"), pc.multiply(pc.floor(pc.divide(table.column("o_orderkey"), 7)), 7)), 0))))
    pq.write_table(few, tmp_path / "orders.parquet")
    pq.write_table(pq.read_table(f"{SF}/customer.parquet"), tmp_path / "customer.parquet")
    earlier = f"SELECT c_custkey, o_orderkey FROM '{SF}/customer.parquet' {how.upper()} JOIN (SELECT * FROM '{SF}/orders.parquet' WHERE o_orderkey % 7 = 0) ON c_custkey = o_custkey"
    assert plain(catalogue.QUERIES[f"op_join_{how}"](spark, str(tmp_path)).toPandas()) == plain(con.sql(earlier).df())
