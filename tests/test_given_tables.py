"""Queries that once made their data up read a given table."""

from __future__ import annotations

import numpy as np
import pytest

from eigenlake.linalg.small import gaussian
from eigenlake.queries import QUERIES, measures, methods, relational

SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize("name,source", [("cheb_coeffs", "events"), ("mem_compare", "orders"), ("mem_device_grid", "orders"), ("mem_host_grid", "orders"), ("plan_min_nodes", "orders"), ("random_start", "part"), ("recursive_cte_powers", "events"), ("spectral_source_entries", "customer"), ("sql_functions", "orders")])
def test_reads(spark, monkeypatch, name, source):
    read = []
    for module in (measures, methods, relational):
        monkeypatch.setattr(module, "table", lambda s, sf, t, f=module.table: read.append(t) or f(s, sf, t))
    assert QUERIES[name](spark, SF).count() > 0
    assert read == [source]


def test_random_rows_are_those_of_the_solver(spark):
    got = QUERIES["random_start"](spark, SF).collect()
    want = gaussian(np.arange(len(got) // 3), 3, 7)
    assert all(r.v == want[r.i, r.col] for r in got)
