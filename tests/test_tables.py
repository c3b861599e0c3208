"""Queries work on the given tables: without them they fail."""

import pytest
from pyspark.errors import AnalysisException

from patcard.plans import registry


@pytest.mark.parametrize("name", ["W18", "coverage_toy", "htblind_toy", "op_pandas_udf", "op_udtf", "samplespace_toy", "varbound"])
def test_reads_a_given_table(spark, tmp_path, name):
    with pytest.raises(AnalysisException):
        registry.queries()[name](spark, str(tmp_path)).collect()


def test_blind_sample_meets_a_common_pattern(spark):
    row = registry.queries()["htblind_toy"](spark, "/root/testdata/sf0.01").first()
    assert row["n_calls"] == 4000 and row["est"] > 0
