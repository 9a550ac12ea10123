"""What a piece of work reads, moves and writes, from Spark's own stage records."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import SparkSession

FIELDS = ["inputBytes", "inputRecords", "outputBytes", "outputRecords", "shuffleReadBytes", "shuffleWriteBytes", "shuffleWriteRecords", "diskBytesSpilled"]


def _stages(spark: SparkSession):
    sc = spark.sparkContext
    sc._jsc.sc().listenerBus().waitUntilEmpty()
    stages = sc._jsc.sc().statusStore().stageList(None, False, False, sc._gateway.new_array(sc._jvm.double, 0), sc._jvm.java.util.ArrayList())
    return [stages.apply(k) for k in range(stages.size())]


def measure(spark: SparkSession, work: Callable[[], object]) -> dict[str, float]:
    """Seconds of ``work`` and what its stages read, moved, wrote and spilled."""
    last, start = max((s.stageId() for s in _stages(spark)), default=-1), time.perf_counter()
    work()
    seconds = round(time.perf_counter() - start, 3)
    own = [s for s in _stages(spark) if s.stageId() > last]
    return {"seconds": seconds} | {field: sum(getattr(s, field)() for s in own) for field in FIELDS}
