"""Queries of formulas take their numbers from the tables."""

import pytest

from wsig import queries
from wsig import queries_more  # noqa: F401
from wsig.plans import verify

SF = "/root/testdata/sf0.001"
FROM_TABLES = [
    "case_exact_jaccard",
    "expected_cost_formulas",
    "expected_error_rollup",
    "halving_rounds",
    "rounding_negligible",
    "variance_formulas",
]


@pytest.mark.parametrize("name", FROM_TABLES)
def test_reads_a_table(spark, name):
    assert queries.QUERIES[name](spark, SF).inputFiles()


def test_fixed_cases_have_the_similarity_named(spark):
    rows = [(c, a, b) for c in verify.CASES for a, b in verify.case_weights(c)]
    got = {r["case"]: r["j"] for r in verify.exact_case_jaccard(spark.createDataFrame(rows, "case string, wa double, wb double")).collect()}
    assert got == pytest.approx({c: j for c, (_, j) in verify.CASES.items()})
