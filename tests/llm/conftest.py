"""Shared tables of the operator tests."""

import pytest
from pyspark.sql import Row


@pytest.fixture
def docs(spark):
    """Nulls, empty and long texts, ties, repeated rows, and an extra column with a clashing name."""

    def make(texts, first=0):
        rows = [Row(doc_id=first + i, text=t, score=1.5) for i, t in enumerate(texts)]
        return spark.createDataFrame(rows, "doc_id long, text string, score double").repartition(2)

    return make
