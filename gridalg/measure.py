"""Run time, split times, shuffled bytes and outcomes of queries."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession


def run(df: DataFrame) -> None:
    """Computes all rows and columns and drops them."""
    df.write.format("noop").mode("overwrite").save()


def timed(make: Callable[[], DataFrame], k: int = 3, warm: bool = True) -> float:
    """Mean seconds over k runs after one that does not count."""
    if warm:
        run(make())
    t = time.perf_counter()
    for _ in range(k):
        run(make())
    return (time.perf_counter() - t) / k


def shuffled(spark: SparkSession, make: Callable[[], DataFrame]) -> tuple[int, int]:
    """Bytes and records that the stages of one run write to shuffles."""
    store = spark.sparkContext._jsc.sc().statusStore()

    def total() -> tuple[int, int]:
        none = spark.sparkContext._gateway.new_array(spark.sparkContext._jvm.double, 0)
        stages = store.stageList(None, False, False, none, None)
        done = [stages.apply(i) for i in range(stages.size())]
        return sum(s.shuffleWriteBytes() for s in done), sum(s.shuffleWriteRecords() for s in done)

    before = total()
    run(make())
    spark.sparkContext._jsc.sc().listenerBus().waitUntilEmpty(10_000)
    after = total()
    return after[0] - before[0], after[1] - before[1]


def split(load: Callable[[], DataFrame], rest: Callable[[DataFrame], DataFrame]) -> tuple[float, float]:
    """Seconds to place and materialise the inputs, and seconds of the rest."""
    from gridalg.functions.lineage import cut

    t = time.perf_counter()
    placed = cut(load())
    u = time.perf_counter()
    run(rest(placed))
    return u - t, time.perf_counter() - u


def outcome(make: Callable[[], DataFrame], spark: SparkSession, limit: float = 60.0) -> tuple[str, float]:
    """'done', 'timeout', 'too large', 'out of memory', 'out of disk' or 'error', with seconds. A run over the limit is cancelled."""
    import threading

    t = time.perf_counter()
    late = threading.Event()

    def stop() -> None:
        late.set()
        spark.sparkContext.cancelAllJobs()

    timer = threading.Timer(limit, stop)
    timer.start()
    try:
        run(make())
        said = "done"
    except Exception as e:  # the kinds of failure are the result here
        text = f"{type(e).__name__} {e}"
        said = "timeout" if late.is_set() else "too large" if "TooLarge" in text else "out of memory" if "OutOfMemory" in text else "out of disk" if "No space left" in text else "error"
    finally:
        timer.cancel()
    return said, time.perf_counter() - t
