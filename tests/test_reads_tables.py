import pytest

from lowrank_spark import catalog

#: Queries that Spark must compute from a given table, not from rows made up on the driver.
NAMES = [
    "step_sizes",
    "space_table",
    "graph_ops",
    "rotation_plan",
    "model_params",
    "collision_theory",
]


@pytest.mark.parametrize("name", NAMES)
def test_reads_a_given_table(spark, sf, name):
    assert any(sf in f for f in catalog.queries()[name](spark, sf).inputFiles())
