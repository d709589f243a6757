import pytest
from pyspark.sql import SparkSession


@pytest.fixture(scope="session")
def spark():
    import chronoweave

    s = SparkSession.builder.master("local[4]").config("spark.sql.shuffle.partitions", "4").config("spark.ui.enabled", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    s.sparkContext.setLogLevel("ERROR")
    chronoweave.ship(s)
    return s
