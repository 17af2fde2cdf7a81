import pytest

from waypath.llm.common import components


def test_unsettled_components_are_refused(spark):
    chain = [(i, i + 1) for i in range(20)]
    with pytest.raises(RuntimeError, match="not settled"):
        components(spark.createDataFrame(chain, "u long, v long"), 2)
