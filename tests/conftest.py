from __future__ import annotations

import sys
from datetime import date, datetime
from pathlib import Path

import pytest

sys.path.insert(0, str(Path(__file__).resolve().parents[1]))


@pytest.fixture(scope="session")
def spark():
    from pyspark.sql import SparkSession

    s = (
        SparkSession.builder.master("local[4]").appName("tests").config("spark.sql.shuffle.partitions", "4").config("spark.ui.enabled", "false")
        .config("spark.sql.session.timeZone", "UTC").config("spark.driver.memory", "4g").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    )
    s.sparkContext.setLogLevel("ERROR")
    yield s
    s.stop()


@pytest.fixture
def db(spark):
    from standq.clock import ManualClock
    from standq.scratch import scratch
    from standq.sources.store import Database

    return Database(spark, scratch(spark), ManualClock(datetime(2024, 1, 1, 12)))


#: Golden inputs: one sensor's thirteen readings of November 2019, one commit each.
READINGS = [(15, 30), (16, 32), (17, 30), (18, 31), (19, 34), (20, 30), (21, 33), (22, 35), (26, 35), (27, 34), (28, 33), (29, 34), (30, 34)]


@pytest.fixture
def sensor(db, spark):
    from standq.operators.constraints import Increasing

    def make(grace=None):
        db.create_table("sensor", "place string, day date, measure int", insert_only=True, increasing=[Increasing("day", grace=grace)])
        rows = spark.createDataFrame([("SF", date(2019, 11, d), m, n) for n, (d, m) in enumerate(READINGS, 1)], "place string, day date, measure int, n int")
        from pyspark.sql import functions as F

        db.ingest_history("sensor", rows, F.col("n"))
        return db

    return make
