"""What a walk step costs Spark: jobs, stages, tasks, rows and bytes, from the session's own status store."""

from __future__ import annotations

import time
import uuid

from pyspark.sql import DataFrame, SparkSession

from ..graph import Graph
from ..session import cut
from .walk import Run, fetch, runs_frame, start, step

SCHEMA = "t int, jobs long, stages long, tasks long, rows_read long, bytes_read long, shuffle_rows long, shuffle_bytes long, seconds double"


def group_cost(spark: SparkSession, group: str) -> tuple[int, ...]:
    """Sums over the jobs of a job group; stages that Spark skipped count nothing."""
    sc = spark.sparkContext
    jvm = sc._jsc.sc()
    jvm.listenerBus().waitUntilEmpty()
    store, jobs, stages = jvm.statusStore(), sc.statusTracker().getJobIdsForGroup(group), set()
    for job in jobs:
        ids = store.job(job).stageIds()
        stages |= {ids.apply(i) for i in range(ids.size())}
    ran = [x for x in map(store.lastStageAttempt, sorted(stages)) if x.status().toString() != "SKIPPED"]
    sums = [sum(getattr(x, f)() for x in ran) for f in ("numCompleteTasks", "inputRecords", "inputBytes", "shuffleWriteRecords", "shuffleWriteBytes")]
    return len(jobs), len(ran), *sums


def step_costs(g: Graph, runs: list[Run], steps: int) -> DataFrame:
    """One row per step of the walk on stored adjacency; the store itself is built before the first."""
    spark, rf, rows = g.spark, runs_frame(g, runs), []
    sc = spark.sparkContext
    before = sc.getLocalProperty("spark.jobGroup.id"), sc.getLocalProperty("spark.job.description")
    state = cut(start(rf))
    _ = g.near
    try:
        for t in range(1, steps + 1):
            group, began = f"step-{uuid.uuid4().hex}", time.time()
            sc.setJobGroup(group, f"walk step {t}")
            state = cut(step(g, fetch(g, state), rf))
            rows.append((t, *group_cost(spark, group), time.time() - began))
    finally:
        sc.setLocalProperty("spark.jobGroup.id", before[0])
        sc.setLocalProperty("spark.job.description", before[1])
    return spark.createDataFrame(rows, SCHEMA)
