"""Tables in the shared folder."""

import os

from pyspark.sql import functions as F

from veilstream.shared import FREE_SHUFFLES, discard, materialize


def test_discard_deletes_what_materialize_wrote_and_nothing_else(spark):
    before = spark.conf.get(FREE_SHUFFLES, "false")
    first = materialize(spark.range(1000).groupBy((F.col("id") % 7).alias("k")).count(), "first")
    second = materialize(first.join(first.select("k"), "k"), "second")
    path = first.inputFiles()[0].removeprefix("file://").rsplit("/", 1)[0]
    assert os.path.isdir(path) and spark.conf.get(FREE_SHUFFLES, "false") == before
    discard(first, first, spark.range(3))
    assert not os.path.exists(path)
    assert sorted(map(tuple, second.collect())) == [(k, 143 if k < 6 else 142) for k in range(7)]
    read = spark.read.parquet(second.inputFiles()[0].rsplit("/", 1)[0])
    discard(read)
    assert read.count() == 7
