"""What a piece of work cost: seconds, and the bytes its stages read, exchanged and spilled, as Spark counts them."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator
from contextlib import contextmanager

from pyspark.sql import SparkSession

#: Stage counters: our name, Spark's.
COUNTERS = {
    "input_bytes": "inputBytes", "output_bytes": "outputBytes", "shuffle_read_bytes": "shuffleReadBytes", "shuffle_write_bytes": "shuffleWriteBytes",
    "fetch_wait_ms": "shuffleFetchWaitTime", "spilled_bytes": "diskBytesSpilled", "task_ms": "executorRunTime", "cpu_ns": "executorCpuTime", "gc_ms": "jvmGcTime",
}


def _stages(spark: SparkSession) -> list:
    """Data of the stages that the session still knows (Spark keeps the last 1,000)."""
    sc = spark.sparkContext
    sc._jsc.sc().listenerBus().waitUntilEmpty()
    found = sc._jsc.sc().statusStore().stageList(None, False, False, sc._gateway.new_array(sc._jvm.double, 0), None)
    return [found.apply(i) for i in range(found.size())]


@contextmanager
def metered(spark: SparkSession) -> Iterator[dict[str, float]]:
    """A dictionary that holds, after the block, its seconds, its number of stages and the sums of ``COUNTERS`` over them."""
    out: dict[str, float] = {}
    before = max((s.stageId() for s in _stages(spark)), default=-1)
    began = time.time()
    try:
        yield out
    finally:
        out["seconds"] = time.time() - began
        mine = [s for s in _stages(spark) if s.stageId() > before]
        out["stages"] = len(mine)
        for name, counter in COUNTERS.items():
            out[name] = sum(getattr(s, counter)() for s in mine)


def measure(spark: SparkSession, work: Callable[[], object]) -> dict[str, float]:
    with metered(spark) as cost:
        work()
    return cost
