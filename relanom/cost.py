"""What a run costs: wall-clock and rows of named steps, and tasks, bytes and spill of stages from an event log."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

_TASK = "`Task Metrics`"
#: Fields of a task that the report sums: name, path in the event log.
SUMMED = {
    "run_ms": f"{_TASK}.`Executor Run Time`",
    "cpu_ns": f"{_TASK}.`Executor CPU Time`",
    "gc_ms": f"{_TASK}.`JVM GC Time`",
    "input_bytes": f"{_TASK}.`Input Metrics`.`Bytes Read`",
    "shuffle_read": f"{_TASK}.`Shuffle Read Metrics`.`Remote Bytes Read` + {_TASK}.`Shuffle Read Metrics`.`Local Bytes Read`",
    "shuffle_write": f"{_TASK}.`Shuffle Write Metrics`.`Shuffle Bytes Written`",
    "spilled": f"{_TASK}.`Disk Bytes Spilled`",
}
_LONG = "BIGINT"
EVENTS = (
    f"`Event` STRING, `Stage ID` {_LONG}, `Task Info` STRUCT<`Launch Time`: {_LONG}, `Finish Time`: {_LONG}, `Failed`: BOOLEAN>, "
    f"`Task Metrics` STRUCT<`Executor Run Time`: {_LONG}, `Executor CPU Time`: {_LONG}, `JVM GC Time`: {_LONG}, `Peak Execution Memory`: {_LONG}, `Disk Bytes Spilled`: {_LONG}, "
    f"`Input Metrics`: STRUCT<`Bytes Read`: {_LONG}>, `Shuffle Read Metrics`: STRUCT<`Remote Bytes Read`: {_LONG}, `Local Bytes Read`: {_LONG}>, `Shuffle Write Metrics`: STRUCT<`Shuffle Bytes Written`: {_LONG}>>"
)


def stages(spark: SparkSession, path: str) -> DataFrame:
    """One row per stage of an event log (a file or a folder of them): tasks, failures, sums of ``SUMMED``, peak memory of a task, skew.

    ``skew`` is the longest task's run time over the mean. Only task-end lines with the listed fields are parsed.
    """
    ends = spark.read.schema(EVENTS).json(path).filter("`Event` = 'SparkListenerTaskEnd'")
    sums = [F.coalesce(F.sum(F.expr(c)), F.lit(0)).alias(name) for name, c in SUMMED.items()]
    run = F.expr(SUMMED["run_ms"])
    return ends.groupBy(F.col("`Stage ID`").alias("stage")).agg(
        F.count("*").alias("tasks"), F.count_if("`Task Info`.`Failed`").alias("failed"), *sums,
        F.coalesce(F.max(f"{_TASK}.`Peak Execution Memory`"), F.lit(0)).alias("peak_bytes"), F.coalesce(F.try_divide(F.max(run), F.avg(run)), F.lit(1.0)).alias("skew"),
    )


def timed(spark: SparkSession, steps: dict[str, Callable[[], DataFrame]]) -> DataFrame:
    """(step, rows, seconds) of each step run to its end; rows are counted in the same pass."""
    out = []
    for name, make in steps.items():
        start, seen = time.time(), Observation()
        make().observe(seen, F.count(F.lit(1)).alias("rows")).write.format("noop").mode("overwrite").save()
        out.append((name, int(seen.get["rows"]), round(time.time() - start, 3)))
    return spark.createDataFrame(out, "step string, rows long, seconds double")


def parameters(shapes: dict[str, tuple]) -> int:
    """Number of trained parameters of a model's shapes."""
    total = 0
    for shape in shapes.values():
        size = 1
        for n in shape:
            size *= n
        total += size
    return total
