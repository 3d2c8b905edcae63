"""Registered queries against their SQL twins on the smallest tables."""

import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from bandloom.kernel.banding import Bank
from bandloom.plans.planning import eps_homogeneous, rows_for
from bandloom.queries import core, tour

HEAVY = ("_semi_join", "static_", "_no_false_negative", "bound")


@pytest.mark.parametrize("name", [n for n in core.ORACLES if not n.startswith("workload") and not any(h in n for h in HEAVY)] + ["std_semi_join", "static_priority_lookup", "trim_no_false_negative", "overhead_within_bound"])
def test_query_equals_sql(same, name):
    same(core.QUERIES[name], core.ORACLES[name])


@pytest.mark.parametrize("name", ["workload_one_percent", "workload_access_model", "workload_span_probability", "workload_elasticity"])
def test_workload_has_rows(spark, sf, name):
    assert core.QUERIES[name](spark, sf).count() > 0


@pytest.mark.parametrize("name", ["access_model_icm", "alpha_plan", "bucket_plan", "eps_recommended", "fractional_model", "info_bound_grid", "op_recursion"])
def test_closed_forms_take_their_parameters_from_a_table(spark, sf, name):
    read = core.QUERIES[name](spark, sf).inputFiles()
    assert read and all(sf in f for f in read)


def test_span_of_random_equations_is_expected_at_size(spark):
    """Rates and overheads of the lines' keys, and twice the span that random equations have, which is not expected."""
    from bandloom.experiments import workloads

    rows = [("homogeneous", w, r, None, None, n, 10**8, bits, f, bits / -math.log2(f) - 1) for w, r, n, bits, f in (
        (16, 11.0, 3_600_000, 15.646, 0.00325), (32, 11.0, 36_000_000, 13.325, 0.000823), (16, 7.0, 36_000_000, 9.5185, 0.0133), (64, 7.0, 3_600_000, 7.632, 0.00807),
        (16, 11.0, 3_600_000, 15.646, 0.0059), (32, 11.0, 36_000_000, 13.325, 0.00117), (16, 7.0, 36_000_000, 9.5185, 0.0188), (64, 7.0, 3_600_000, 7.632, 0.0110))]
    scores = spark.createDataFrame(rows, "filter string, w int, r double, eps double, sharding string, n long, probes long, bits_per_key double, fp_rate double, overhead double").withColumn("hits", (F.col("fp_rate") * F.col("probes")).cast("long"))
    got = scores.select(workloads.rate_is_expected().alias("a"), workloads.space_is_expected().alias("b")).collect()
    assert [tuple(g) for g in got[:4]] == [(True, True)] * 4
    assert not any(g.a for g in got[4:])


@pytest.mark.parametrize("w, r", [(16, 11), (32, 3)])
def test_span_law_holds_for_random_equations(w, r):
    from bandloom.experiments.workloads import SPAN

    rng, n, eps = np.random.default_rng(5), 1 << 19, eps_homogeneous(r, w)
    m = rows_for(n, eps, w)
    draw = lambda k: (rng.integers(0, m - w + 1, k), (rng.integers(0, 1 << w, k, dtype=np.uint64) | np.uint64(1))[None])
    bank = Bank(m)
    bank.insert(*draw(n), np.zeros(n, np.uint64))
    law = SPAN[w][0] * math.exp(-SPAN[w][1] * (eps * w - 4.25))
    assert abs(bank.in_span(*draw(1 << 18)).mean() - law) < 0.15 * law + 5 * math.sqrt(law * w * w / 6 / n)


def test_entry(spark):
    import __spark_entry__

    assert __spark_entry__.entry(spark).count() > 0
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())
    assert tour
