"""Queries that once made their data up read a given table now: without tables they fail."""

import pytest
from pyspark.errors import AnalysisException

from finegrain import catalog

NAMES = [
    "cube_planted_expression",
    "cube_planted",
    "dct_basis",
    "dim_calendar",
    "flop_model",
    "gram_aggregate",
    "gram_r2",
    "mean_worked_example",
    "leaderboard",
    "improvement",
    "oracle_gap",
]


@pytest.mark.parametrize("name", NAMES)
def test_reads_a_given_table(spark, name):
    with pytest.raises(AnalysisException, match="PATH_NOT_FOUND"):
        catalog.QUERIES[name](spark, "/nowhere").collect()
