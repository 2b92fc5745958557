import os
import sys

import pytest

sys.path.insert(0, os.path.dirname(os.path.dirname(os.path.abspath(__file__))))


@pytest.fixture(scope="session")
def spark():
    from pyspark.sql import SparkSession

    s = (
        SparkSession.builder.master("local[4]")
        .config("spark.sql.shuffle.partitions", "8")
        .config("spark.ui.enabled", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.driver.memory", "8g")
        .getOrCreate()
    )
    s.sparkContext.setLogLevel("ERROR")
    yield s
    s.stop()


@pytest.fixture(scope="session")
def sf():
    return "/root/testdata/sf0.001"


@pytest.fixture
def shuffled(spark):
    """A function that runs another one without broadcast joins: (its result, bytes that its stages wrote for shuffles)."""
    sc = spark.sparkContext

    def stages():
        sc._jsc.sc().listenerBus().waitUntilEmpty()
        found = sc._jsc.sc().statusStore().stageList(None, False, False, sc._gateway.new_array(sc._jvm.double, 0), sc._jvm.java.util.ArrayList())
        return {(s := found.apply(i)).stageId(): s.shuffleWriteBytes() for i in range(found.size())}

    def run(make):
        name = "spark.sql.autoBroadcastJoinThreshold"
        old, before = spark.conf.get(name), stages()
        spark.conf.set(name, "-1")
        try:
            out = make()
        finally:
            spark.conf.set(name, old)
        return out, sum(n for k, n in stages().items() if k not in before)

    return run
