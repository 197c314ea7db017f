import pytest

import __spark_entry__ as entry

SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize("name", ["sig_direct_integer", "sig_replicated_whole"])
def test_draws_are_not_shuffled(spark, name):
    """Rows are dealt by bag before they multiply; the minima of components need no shuffle of their own."""
    df = entry.queries()[name](spark, SF)
    plan = df._jdf.queryExecution().executedPlan().toString()
    above = plan[: plan.index("Generate explode")]
    assert "Exchange" not in above
