import sys
from pathlib import Path

import pytest

sys.path.insert(0, str(Path(__file__).resolve().parent.parent))


@pytest.fixture(scope="session")
def spark():
    from pyspark.sql import SparkSession

    session = (
        SparkSession.builder.master("local[4]")
        .config("spark.sql.shuffle.partitions", "4")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.driver.memory", "4g")
        .getOrCreate()
    )
    session.sparkContext.setLogLevel("ERROR")
    yield session
    session.stop()


@pytest.fixture(scope="session")
def toy(spark):
    """Two slices of two triangles; the bridge between these differs."""
    from chronocluster.schemas import EDGES
    from chronocluster.temporal import TemporalGraph

    triangles = [(0, 1), (1, 2), (0, 2), (3, 4), (4, 5), (3, 5)]
    rows = [(s, *sorted(e), 1.0) for s, bridge in ((1, (2, 3)), (2, (0, 5))) for e in [*triangles, bridge]]
    return TemporalGraph(spark.createDataFrame(rows, EDGES))


@pytest.fixture(scope="session")
def toy_labels(spark):
    from chronocluster.schemas import LABELS

    return spark.createDataFrame([(s, v, v // 3) for s in (1, 2) for v in range(6)], LABELS)


@pytest.fixture(scope="session")
def sf():
    return "/root/testdata/sf0.001"
