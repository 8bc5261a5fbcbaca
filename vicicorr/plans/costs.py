"""What a run cost, from the status store that Spark keeps with or without its web interface."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import SparkSession


@dataclass(frozen=True)
class RunCost:
    stages: int
    tasks: int
    shuffle_bytes: int
    spilled_bytes: int
    rows_read: int
    peak_memory: int
    cpu_ms: int


def run_cost(spark: SparkSession, run: Callable[[], object]) -> RunCost:
    """Sums over the stages that ``run`` starts; other runs of the application at the same time count too."""
    sc = spark.sparkContext._jsc.sc()
    store, none = sc.statusStore(), None
    args = (none, False, False, spark.sparkContext._gateway.new_array(spark._jvm.double, 0), spark._jvm.java.util.ArrayList())

    def stages():
        it, out = store.stageList(*args).iterator(), {}
        while it.hasNext():
            x = it.next()
            out[x.stageId(), x.attemptId()] = x
        return out

    before = set(stages())
    run()
    sc.listenerBus().waitUntilEmpty()
    new = [x for k, x in stages().items() if k not in before and x.numCompleteTasks()]
    total = lambda f: int(sum(f(x) for x in new))
    return RunCost(
        len(new), total(lambda x: x.numCompleteTasks()), total(lambda x: x.shuffleWriteBytes()), total(lambda x: x.diskBytesSpilled()),
        total(lambda x: x.inputRecords() + x.shuffleReadRecords()), max((int(x.peakExecutionMemory()) for x in new), default=0), total(lambda x: x.executorCpuTime() / 1e6),
    )
