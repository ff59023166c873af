import sys
from pathlib import Path

import pytest

ROOT = Path(__file__).resolve().parents[1]
sys.path.insert(0, str(ROOT))
SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="session")
def spark():
    from pyspark.sql import SparkSession

    session = (
        SparkSession.builder.master("local[4]").appName("tests").config("spark.sql.shuffle.partitions", "4").config("spark.ui.enabled", "false")
        .config("spark.driver.memory", "3g").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )
    session.sparkContext.setLogLevel("OFF")
    from allpairs.workers import ship

    ship(session)
    yield session
    session.stop()


@pytest.fixture(scope="session")
def tiny(spark):
    """Four multisets whose similarities are known by hand."""
    cells = {1: {"a": 3, "b": 1, "c": 2}, 2: {"a": 1, "b": 1, "d": 2}, 3: {"a": 3, "b": 1, "c": 2}, 4: {"e": 5}}
    return spark.createDataFrame([(e, x, m) for e, row in cells.items() for x, m in row.items()], "entity long, element string, mult long").cache()
