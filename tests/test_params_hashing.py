import math

import pytest
from pyspark.sql import functions as F

from filterfleet.functions.hashing import positions, probe_bits
from filterfleet.functions.params import FilterSpec, derive_k, derive_m, expected_fp, optimal_k, pruning_sets, saturating_sets
from filterfleet.operators.tree import height_bound, ideal_cost


def test_published_sizes():
    assert (derive_k(0.01), derive_m(10_000, 7)) == (7, 100_992)
    assert (derive_k(1e-7), derive_k(0.1)) == (24, 4)
    assert expected_fp(100_000, 100_992, 7) == pytest.approx(0.993, abs=1e-3)
    assert optimal_k(100_992, 10_000) == 7


def test_limits_of_pruning():
    assert saturating_sets(100_992, 7, 100) == pytest.approx(1660, rel=0.01)
    assert pruning_sets(100_992, 7, 100) == pytest.approx(340, rel=0.01)


def test_ideal_cost_is_least_near_e():
    assert ideal_cost(1000, 3) == pytest.approx(19.86, abs=0.01)
    assert ideal_cost(1000, 2) == pytest.approx(20.93, abs=0.01) and ideal_cost(1000, 4) == pytest.approx(20.93, abs=0.01)
    assert ideal_cost(1000, 10) == pytest.approx(31.0, abs=0.01)
    assert height_bound(4, 2) == 1 and height_bound(1000, 2) == 1 + math.floor(math.log2(500))


@pytest.mark.parametrize("family", ["linear_odd", "md5_double", "xx64_double", "mod_identity"])
def test_positions_stay_inside(spark, family):
    spec = FilterSpec(100, family=family)
    data = spark.createDataFrame([(x,) for x in (0, 1, -5, 2**40, 10**9)], "element long")
    for row in data.select(positions(F.col("element"), spec).alias("p")).collect():
        assert len(row.p) == (1 if family == "mod_identity" else spec.k) and all(0 <= p < spec.m for p in row.p)


def test_python_and_spark_hash_alike(spark):
    from filterfleet.sources.index_source import python_positions

    for family in ("linear_odd", "md5_double", "mod_identity"):
        spec = FilterSpec(300, family=family)
        for row in spark.range(0, 5000, 617).select("id", positions(F.col("id"), spec).alias("p")).collect():
            assert row.p == python_positions(row.id, family, spec.k, spec.m, list(spec.seeds))


def test_colliding_positions_and_null_probes(spark):
    spec = FilterSpec(1, family="linear_odd", k=4, m=64, seeds=(1, 65, 129, 3))
    asked = spark.createDataFrame([(1, 5), (2, None), (1, 5)], "query_id long, element long").distinct()
    rows = probe_bits(asked, spec).collect()
    assert {r.query_id for r in rows} == {1} and all(r.k_distinct == 2 for r in rows) and {r.pos for r in rows} == {5, 15}
