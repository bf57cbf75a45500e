"""What a run shuffled, from the counters that Spark keeps of its stages."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import SparkSession


def _stages(spark: SparkSession) -> list:
    context, gateway = spark.sparkContext._jsc.sc(), spark.sparkContext._gateway
    context.listenerBus().waitUntilEmpty(30_000)
    empty = gateway.jvm.java.util.ArrayList()
    stages = context.statusStore().stageList(empty, False, False, gateway.new_array(gateway.jvm.double, 0), empty)
    return [stages.apply(i) for i in range(stages.size())]


def shuffled(spark: SparkSession, run: Callable[[], object]) -> dict[str, int]:
    """Rows and bytes that run writes to shuffles, for runs of no more stages than Spark keeps (spark.ui.retainedStages)."""
    last = max((s.stageId() for s in _stages(spark)), default=-1)
    run()
    new = [s for s in _stages(spark) if s.stageId() > last]
    return {"shuffled_rows": sum(s.shuffleWriteRecords() for s in new), "shuffled_bytes": sum(s.shuffleWriteBytes() for s in new)}
