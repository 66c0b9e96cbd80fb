import pytest


@pytest.fixture(scope="session", autouse=True)
def _few_partitions(spark):
    spark.conf.set("spark.sql.shuffle.partitions", "2")
