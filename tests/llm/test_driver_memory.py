"""The driver's JVM returns native memory after every staged table."""

import pytest
from pyspark.sql import functions as F

from pathlore.llm import common

pytestmark = pytest.mark.filterwarnings("ignore")


def test_the_jvm_trims_its_native_heap(spark):
    spark.range(1000).groupBy((F.col("id") % 10).alias("k")).count().collect()
    assert common.trim_driver(spark).startswith("Trim native heap")


def test_every_staged_table_is_followed_by_a_trim(spark, monkeypatch):
    given = []
    monkeypatch.setattr(common, "trim_driver", given.append)
    rows = spark.createDataFrame([(2, 1), (3, 2), (9, 8)], "a long, b long")
    assert sorted(map(tuple, common.stage(rows, "rows").collect())) == [(2, 1), (3, 2), (9, 8)]
    assert given == [spark]
    found = common.connected_components(rows)
    assert sorted(map(tuple, found.collect())) == [(1, 1), (2, 1), (3, 1), (8, 8), (9, 8)]
    assert len(given) >= 3


def test_a_jvm_without_the_command_is_left_alone():
    class Other:
        _jvm = property(lambda self: self)
        sparkContext = property(lambda self: self)  # noqa: N815
        _gateway = property(lambda self: self)

        def new_array(self, *_):
            raise RuntimeError("no such command")

    assert common.trim_driver(Other()) == ""
