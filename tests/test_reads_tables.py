"""Queries whose job is done on a given table, against pandas."""

import numpy as np
import pandas as pd

from fsketch.functions.hashing import py_normal
from fsketch.operators import solve
from fsketch.plans import queries, relational

SF = "/root/testdata/sf0.001"


def test_no_solution_of_a_model_of_parts(spark, monkeypatch):
    seen = []
    whole = solve.coupled
    monkeypatch.setattr(solve, "coupled", lambda s, model, budget: seen.append(model) or whole(s, model, budget))
    assert queries.Q["coupled_no_solution"][0](spark, SF).first().asDict() == {"status": "no_solution", "states": 6**10}
    assert len(seen[0].linear) == 60 and np.abs(seen[0].linear).min() > 0


def test_frequencies_of_parts(spark):
    got = {r.j: (r.w0, r.w1) for r in queries.Q["freq_draw"][0](spark, SF).collect()}
    assert got.keys() == set(pd.read_parquet(f"{SF}/part.parquet").p_partkey)
    assert all(np.allclose(w, [py_normal("w", 42, j, c) for c in range(2)], atol=1e-6) for j, w in got.items())


def test_bits_of_orders(spark):
    got = {r.i: (r.a, r.o, r.x, r.s, r.b) for r in relational.Q["ops_bits"][0](spark, SF).collect()}
    assert got == {int(i): (i & 12, i | 3, i ^ 5, i >> 1, int(i).bit_count()) for i in pd.read_parquet(f"{SF}/orders.parquet").o_orderkey}


def test_function_over_parts(spark):
    got = {r.g: r.cost for r in relational.Q["ops_sql_function"][0](spark, SF).collect()}
    parts = pd.read_parquet(f"{SF}/part.parquet")
    assert np.allclose([got[k] for k in parts.p_partkey], (parts.p_size - 1.5) ** 2 + (parts.p_retailprice / 2) ** 2) and len(got) == len(parts)


def test_resources_of_suppliers(spark):
    got = queries.Q["resources_grid"][0](spark, SF).collect()
    sizes = set(pd.read_parquet(f"{SF}/lineitem.parquet").groupby("l_suppkey").size())
    assert {r.b for r in got} == sizes and len(got) == 45 * len(sizes)
    assert all(r.peak_qubits == max(r.d, max(1, (r.b - 1).bit_length()) + 1) for r in got)
