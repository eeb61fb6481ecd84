import os
import sys
from pathlib import Path

import pytest

ROOT = Path(__file__).resolve().parents[1]
sys.path.insert(0, str(ROOT))
os.environ["PYTHONPATH"] = f"{ROOT}:{os.environ.get('PYTHONPATH', '')}"


@pytest.fixture(scope="session")
def spark():
    from pyspark.sql import SparkSession

    session = (
        SparkSession.builder.master("local[4]")
        .config("spark.sql.shuffle.partitions", "4")
        .config("spark.ui.enabled", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.driver.memory", "4g")
        .config("spark.ui.showConsoleProgress", "false")
        .getOrCreate()
    )
    session.sparkContext.setLogLevel("ERROR")
    yield session
    session.stop()


T5 = [(1, 166, "Marcel Kittel", "Russia", "Berlin"), (2, 166, "Marcel Kittel", "Germany", "Berlin"), (3, 166, "Andre Greipel", "Germany", "Berlin"), (4, 21, "Emanuel Buchmann", "Germany", "Berlin"), (5, 98, "Paul Martens", "Germany", "Berlin")]
T6 = [*T5[:3], (4, 133, "Andre Greipel", "Germany", "Berlin"), (5, *T5[3][1:]), (6, *T5[4][1:])]
SCHEMA = "tid int, rank int, cyclist string, country string, capital string"
TWO = "cyclist -> country; country -> capital"
FOUR = "rank -> cyclist; cyclist -> rank; " + TWO


@pytest.fixture(scope="session")
def t5(spark):
    return spark.createDataFrame(T5, SCHEMA)


@pytest.fixture(scope="session")
def t6(spark):
    return spark.createDataFrame(T6, SCHEMA)
