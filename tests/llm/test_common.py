"""Batches that the operators of this package ask for."""

import pytest

from metricblock.llm import common, simhash

KEY = "spark.sql.execution.arrow.maxRecordsPerBatch"


@pytest.mark.parametrize(("given", "left"), [("10000", common.BATCH_ROWS), ("0", common.BATCH_ROWS), ("-1", common.BATCH_ROWS), ("7", 7)])
def test_batches_are_bounded_and_a_smaller_setting_stays(spark, given, left):
    before = spark.conf.get(KEY)
    try:
        spark.conf.set(KEY, given)
        common.released(lambda batches: batches)
        assert int(spark.conf.get(KEY)) == left
    finally:
        spark.conf.set(KEY, before)


def test_results_do_not_depend_on_the_batches(spark):
    docs = spark.createDataFrame([(i, " ".join(f"w{j}" for j in range(i % 9))) for i in range(50)] + [(None, None)], "doc_id long, text string").coalesce(1)
    before = spark.conf.get(KEY)
    try:
        spark.conf.set(KEY, "3")
        small = sorted(simhash.simhash(docs).collect(), key=str)
        spark.conf.set(KEY, "10000")
        assert sorted(simhash.simhash(docs).collect(), key=str) == small
    finally:
        spark.conf.set(KEY, before)
