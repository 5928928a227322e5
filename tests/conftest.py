import pytest
from pyspark.sql import SparkSession


@pytest.fixture(scope="session")
def spark():
    own = (
        SparkSession.builder.master("local[8]")
        .config("spark.sql.shuffle.partitions", "4")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.driver.memory", "6g")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    own.sparkContext.setLogLevel("ERROR")
    return own
