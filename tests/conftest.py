import sys
from pathlib import Path

import pytest

sys.path.insert(0, str(Path(__file__).resolve().parents[1]))

from proxembed.plans.session import session  # noqa: E402

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="session")
def spark():
    return session("local[4]", 4, "4g")


@pytest.fixture(scope="session")
def five(spark):
    """The five-vertex graph: (0,1), (1,2), (2,3), (2,4), (3,4), weight 1, two parts by vertex."""
    from proxembed.operators import graph, partition

    raw = spark.createDataFrame([("a", "b", 1), ("b", "c", 1), ("c", "d", 1), ("c", "e", 1), ("d", "e", 1)], "a string, b string, w long")
    return partition.stored(partition.cut_by_vertex(graph.build(raw), 2))


@pytest.fixture(scope="session")
def copurchase(spark):
    from proxembed.operators import partition
    from proxembed.sources import builders

    return partition.stored(partition.cut_by_vertex(builders.graph(spark, SF, "copurchase"), 4))
