"""Queries that must read whole tables, against counts in pandas."""

import pandas as pd

from fsketch.plans import relational

SF = "/root/testdata/sf0.001"


def test_full_join_reads_whole_tables(spark):
    got = relational.Q["ops_join_full"][0](spark, SF).first().asDict()
    orders, lines = (pd.read_parquet(f"{SF}/{t}.parquet") for t in ("orders", "lineitem"))
    orders, lines = orders.assign(day=orders["o_orderdate"].dt.date), lines.assign(day=lines["l_shipdate"].dt.date)
    want = orders.merge(lines, how="outer", left_on=["o_orderkey", "day"], right_on=["l_orderkey", "day"], indicator=True)
    met = int((want["_merge"] == "both").sum())
    assert got == {"n": len(want), "orders": int(want["o_orderkey"].count()), "lines": int(want["l_orderkey"].count()), "met": met}
    assert got["lines"] >= len(lines) and got["orders"] >= len(orders) and 0 < got["met"] < min(len(orders), len(lines))


def test_explode_takes_whole_arrays(spark):
    got = {(r.vec_id, r.i): r.v for r in relational.Q["ops_explode"][0](spark, SF).collect()}
    vectors = pd.read_parquet(f"{SF}/embeddings.parquet")
    want = {(v, i): float(x) for v, e in zip(vectors["vec_id"], vectors["embedding"], strict=True) for i, x in enumerate(e)}
    assert got.keys() == want.keys() and all(abs(got[k] - want[k]) < 1e-6 for k in want)
