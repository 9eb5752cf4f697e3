"""Queries whose job stands on given tables: no rows of their own making."""

import numpy as np
import pytest

from dagframe import workloads
from dagframe.operators import workload_learning

GIVEN = ["audit_arithmetic", "baseline_planted", "bound_peeled_first", "bound_scaling", "bound_thresholds", "constraint_audit", "constraint_costs", "correlation_arithmetic", "cube_arithmetic", "cube_results", "edge_confusion", "edge_set_algebra"]


@pytest.mark.parametrize("name", GIVEN)
def test_reads_a_given_table(spark, tmp_path, name):
    with pytest.raises(Exception, match="PATH_NOT_FOUND"):
        workloads.queries()[name](spark, str(tmp_path)).collect()


def test_planted_noise_comes_from_every_given_line(spark, sf):
    given = workload_learning._line_noise(spark, sf, (1, 2), 4)
    assert sum(n for (kind, _), (n, _) in given.items() if kind == "exp") == spark.read.parquet(f"{sf}/lineitem.parquet").count()
    for (kind, _), (_, c) in given.items():
        assert np.abs(np.diag(c) / {"gauss": 1, "exp": 1, "gumbel": np.pi**2 / 6}[kind] - 1).max() < 0.2 and np.abs(c - np.diag(np.diag(c))).max() < 0.15


def test_scaling_edges_are_the_same_for_any_number(spark, sf):
    few, more = (workload_learning._line_edges(spark, sf, 1000, n).collect() for n in (50, 2000))
    assert few == more[:50] and len({(r["src"], r["dst"]) for r in more}) == len(more) == 2000 and all(r["src"] != r["dst"] for r in more)
