"""What the engine itself reports about a run: bytes exchanged, rows and bytes read."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import SparkSession


def measured(spark: SparkSession, run: Callable[[], object]) -> dict[str, int]:
    """Runs ``run`` and sums shuffle and input figures of the stages that it started."""
    jvm, store = spark._jvm, spark.sparkContext._jsc.sc().statusStore()
    none = jvm.java.util.ArrayList()

    def stages() -> dict[tuple[int, int], object]:
        found = store.stageList(none, False, False, spark.sparkContext._gateway.new_array(jvm.double, 0), none)
        return {(found.apply(i).stageId(), found.apply(i).attemptId()): found.apply(i) for i in range(found.size())}

    before = set(stages())
    run()
    spark.sparkContext._jsc.sc().listenerBus().waitUntilEmpty()
    own = [s for key, s in stages().items() if key not in before]
    return {
        "shuffle_written": sum(s.shuffleWriteBytes() for s in own),
        "shuffle_records": sum(s.shuffleWriteRecords() for s in own),
        "rows_read": sum(s.inputRecords() for s in own),
        "bytes_read": sum(s.inputBytes() for s in own),
        "stages": len(own),
    }
