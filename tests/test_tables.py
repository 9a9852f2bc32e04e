"""Queries that once made their rows up read a given table."""

import pytest

from rankfeed import queries
from tests.conftest import SF

NAMES = [
    "bytes_per_epoch",
    "cost_model",
    "lr_schedule",
    "lr_schedule_recursive",
    "matrix_view",
    "phase_breakdown",
    "relative_time",
    "scaling_curve",
    "range_join_schedule",
    "start_factor",
]


def rows_read(spark) -> int:
    context = spark.sparkContext
    stages = context._jsc.sc().statusStore().stageList(None, False, False, context._gateway.new_array(context._jvm.double, 0), None)
    return sum(stages.apply(k).inputRecords() for k in range(stages.size()))


@pytest.mark.parametrize("name", NAMES)
def test_reads_a_given_table_whole(spark, name):
    import time

    least = min(spark.read.parquet(f"{SF}/{t}.parquet").count() for t in ("orders", "lineitem"))
    before = rows_read(spark)
    queries.queries()[name](spark, SF).collect()
    for _ in range(20):  # the listener follows a moment later
        if rows_read(spark) - before >= least:
            break
        time.sleep(0.1)
    assert rows_read(spark) - before >= least
