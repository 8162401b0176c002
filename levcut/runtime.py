"""Checkpoints, bounded collects, iteration counters."""

from __future__ import annotations

import pickle
import tempfile
import time
import uuid
from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark import cloudpickle
from pyspark.sql import DataFrame, SparkSession

import levcut

# Functions of this package travel to the executors inside the task, so the
# executors need no installed copy of it. Objects of its classes go by ship().
cloudpickle.register_pickle_by_value(levcut)

#: Bytes below which a derived table may be broadcast.
BROADCAST_BYTES = 256 << 20


class TooLarge(ValueError):
    """A result that was to be small is not; nothing is ever truncated."""


def ship(spark: SparkSession, value, keep: bool = True) -> Callable[[], object]:
    """What gives the value inside a task; it is broadcast with its classes by value.

    Without ``keep`` every call reads it anew and holds nothing afterwards.
    """
    held, known = spark.sparkContext.broadcast(cloudpickle.dumps(value)), []

    def get():
        if known:
            return known[0]
        found = pickle.loads(held.value)
        if keep:
            known.append(found)
        else:
            vars(held).pop("_value", None)
        return found

    return get


def checkpoint_folder(spark: SparkSession) -> str:
    """spark.checkpoint.dir; where none is set, a folder of our own if all runs in this process, as in tests."""
    context = spark.sparkContext
    if context.getCheckpointDir() is None:
        folder = spark.conf.get("spark.checkpoint.dir", None)
        if not folder:
            master = context.master
            if master != "local" and not master.startswith("local["):
                raise ValueError("spark.checkpoint.dir names no shared folder")
            folder = tempfile.mkdtemp(prefix="levcut-")
        context.setCheckpointDir(folder)
    return context.getCheckpointDir()


def cut_lineage(df: DataFrame) -> DataFrame:
    """A reliable checkpoint in the shared folder."""
    checkpoint_folder(df.sparkSession)
    return df.checkpoint(eager=True)


def release(spark: SparkSession) -> None:
    """Let Spark delete shuffle files and checkpoints that nothing refers to any more.

    Its cleaner acts only on what the driver's JVM has collected, and rounds of
    small plans can fill the disk long before that heap is full.
    """
    spark.sparkContext._jvm.System.gc()


def bounded(df: DataFrame, most: int) -> list:
    """All rows, which must not be more than ``most``."""
    rows = df.limit(most + 1).collect()
    if len(rows) > most:
        raise TooLarge(f"more than {most} rows for the driver")
    return rows


@dataclass
class Trace:
    """What a method has cost: wall seconds, Spark jobs, stages and tasks, and notes of its own."""

    seconds: float = 0.0
    jobs: int = 0
    stages: int = 0
    tasks: int = 0
    notes: dict = field(default_factory=dict)


def traced(spark: SparkSession, method: Callable[[], object]) -> tuple[object, Trace]:
    """The method's result and its cost, counted over a job group of its own."""
    context, group = spark.sparkContext, f"trace-{uuid.uuid4().hex}"
    before = context.getLocalProperty("spark.jobGroup.id")
    context.setLocalProperty("spark.jobGroup.id", group)
    began = time.perf_counter()
    try:
        out = method()
    finally:
        context.setLocalProperty("spark.jobGroup.id", before)
    seconds = time.perf_counter() - began
    tracker = context.statusTracker()
    jobs = tracker.getJobIdsForGroup(group)
    stages = {s for j in jobs if (job := tracker.getJobInfo(j)) for s in job.stageIds}
    tasks = sum(x.numCompletedTasks for s in stages if (x := tracker.getStageInfo(s)))
    return out, Trace(seconds, len(jobs), len(stages), tasks)
