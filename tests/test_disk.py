"""What counting the pairs of all lines leaves on disk: no shuffled texts, rounds of bounded width, no files of finished rounds."""

import gc
import time

import pytest
from pyspark.sql import functions as F

from headcount.operators import paircounts as C
from headcount.sources import storage
from headcount.sources import tables as R


@pytest.mark.parametrize("tables", [1, 8, 25, 60])
def test_rounds_are_bounded(tables):
    rounds = list(C.rounds(tables))
    assert [t for r in rounds for t in r] == list(range(tables))
    assert all(len(r) == 1 or sum(t + 3 for t in r) <= C.NUMBERS for r in rounds)


def test_texts_of_lines_are_not_shuffled(spark, tiny):
    got = R.line_texts(spark, tiny)
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert "hashpartitioning(text" not in plan and "Aggregate" not in plan
    rows = got.groupBy("text").agg(F.sum("w").alias("w")).collect()
    want = R.lines(spark, tiny).groupBy("text").agg(F.count("*").alias("w")).collect()
    assert sorted(map(tuple, rows)) == sorted(map(tuple, want)) and len(want) > 1000


def test_release_drops_shuffles_that_python_holds_in_a_cycle(spark):
    def left():
        files = spark._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllFiles()
        return {str(files.apply(i).getName()) for i in range(files.size()) if files.apply(i).getName().endswith(".data")}

    storage.release(spark)
    time.sleep(2)
    before = left()
    gc.disable()
    try:
        df = spark.range(1000).repartition(3)
        assert df._jdf.queryExecution().toRdd().count() == 1000
        cycle = [df]
        cycle.append(cycle)
        assert left() - before
        del df, cycle
        for _ in range(20):
            storage.release(spark)
            time.sleep(0.5)
            if not left() - before:
                break
        assert not left() - before
    finally:
        gc.enable()
