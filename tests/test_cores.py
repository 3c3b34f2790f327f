"""Core numbers settle or raise."""

import pytest

from graphdelta.sources.stats import core_numbers


def test_unsettled_core_numbers_are_not_returned(spark):
    path = spark.createDataFrame([(i, i + 1) for i in range(9)], "src long, dst long").coalesce(1)
    with pytest.raises(RuntimeError):
        core_numbers(path, most_rounds=2)
    assert {r["core"] for r in core_numbers(path).collect()} == {1}
