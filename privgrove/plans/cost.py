"""What a piece of work costs the engine: jobs, tasks, bytes read, rows and bytes shuffled, from Spark's own status store."""

from __future__ import annotations

import time
import uuid
from collections.abc import Callable

from pyspark.sql import SparkSession

FIELDS = {"tasks": "numTasks", "input_bytes": "inputBytes", "shuffle_records": "shuffleWriteRecords", "shuffle_bytes": "shuffleWriteBytes"}


def measured(spark: SparkSession, work: Callable[[], object]) -> dict[str, float]:
    """Run the work as a job group of its own and sum over its stages."""
    context, group = spark.sparkContext, f"cost-{uuid.uuid4().hex}"
    context.setJobGroup(group, "measured")
    began = time.time()
    try:
        work()
    finally:
        context.setLocalProperty("spark.jobGroup.id", None)
    seconds = time.time() - began
    jvm = context._jsc.sc()
    jvm.listenerBus().waitUntilEmpty()
    store, gateway = jvm.statusStore(), context._gateway
    jobs, out, stages = store.jobsList(None), {"jobs": 0, **dict.fromkeys(FIELDS, 0)}, set()
    for k in range(jobs.size()):
        job = jobs.apply(k)
        if job.jobGroup().isDefined() and job.jobGroup().get() == group:
            out["jobs"] += 1
            stages.update(job.stageIds().apply(i) for i in range(job.stageIds().size()))
    held = store.stageList(None, False, False, gateway.new_array(gateway.jvm.double, 0), None)
    for k in range(held.size()):
        stage = held.apply(k)
        if stage.stageId() in stages and stage.status().toString() == "COMPLETE":
            for name, field in FIELDS.items():
                out[name] += getattr(stage, field)()
    return out | {"seconds": round(seconds, 3)}
