"""What a run costs Spark: jobs, stages, rows and bytes read, bytes shuffled and spilled."""

from __future__ import annotations

import threading
import uuid
from collections.abc import Callable
from dataclasses import dataclass

from py4j.protocol import Py4JJavaError
from pyspark.sql import DataFrame, SparkSession

#: Finished stages are noted so often.
POLL_SECONDS = 0.2


@dataclass(frozen=True)
class SparkCost:
    jobs: int
    stages: int
    rows_read: int
    bytes_read: int
    shuffle_bytes: int
    spilled_bytes: int
    cpu_seconds: float


def spark_cost(spark: SparkSession, run: Callable[[], object]) -> SparkCost:
    """Cost of all jobs that `run` starts from this thread; a DataFrame that it returns is computed too and its rows thrown away.

    Figures come from the driver's own status store. It keeps the last 1000 stages and drops skipped ones first, so finished
    stages are noted while the run goes on, and a stage that was dropped unnoted is one that never ran.
    """
    sc = spark.sparkContext
    group = f"cost-{uuid.uuid4().hex}"
    before = {key: sc.getLocalProperty(key) for key in ("spark.jobGroup.id", "spark.job.description")}
    sc.setJobGroup(group, "measured")
    jobs, stages, data, over = set(), set(), {}, threading.Event()
    store, tracker = sc._jsc.sc().statusStore(), sc.statusTracker()

    def note() -> None:
        for job in set(tracker.getJobIdsForGroup(group)) - jobs:
            info = tracker.getJobInfo(job)
            if info is not None:
                jobs.add(job)
                stages.update(info.stageIds)
        for i in stages - set(data):
            try:
                seen = store.lastStageAttempt(i)
            except Py4JJavaError as e:
                if "NoSuchElementException" not in str(e.java_exception):
                    raise
                continue
            if seen.status().toString() == "COMPLETE":
                data[i] = seen

    def watch() -> None:
        while not over.wait(POLL_SECONDS):
            note()

    watcher = threading.Thread(target=watch, daemon=True)
    watcher.start()
    try:
        out = run()
        if isinstance(out, DataFrame):
            out.write.format("noop").mode("overwrite").save()
    finally:
        for key, value in before.items():
            sc.setLocalProperty(key, value)
        over.set()
        watcher.join()
    sc._jsc.sc().listenerBus().waitUntilEmpty(10_000)
    note()
    total = lambda *names: sum(getattr(d, n)() for d in data.values() for n in names)
    return SparkCost(
        len(jobs), len(data), total("inputRecords"), total("inputBytes"), total("shuffleWriteBytes"),
        total("memoryBytesSpilled", "diskBytesSpilled"), total("executorCpuTime") / 1e9,
    )
