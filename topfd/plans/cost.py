"""What a run costs Spark and the JVM: stages, shuffled bytes, rows read, peak memory. Sampled around one run, so earlier runs don't count."""

from __future__ import annotations

import uuid

from py4j.protocol import Py4JError
from pyspark.sql import SparkSession

_GROUP = ("spark.jobGroup.id", "spark.job.description")


def _pools(session: SparkSession):
    beans = session.sparkContext._jvm.java.lang.management.ManagementFactory.getMemoryPoolMXBeans()
    return [b for b in beans if str(b.getType()) == "Heap memory"]


class Meter:
    """Started before a run and read after it. Without a JVM of one's own (no session, or a remote one), all measures are empty."""

    def __init__(self, session: SparkSession | None):
        self.session = session if session is not None and hasattr(session, "_jvm") else None
        if self.session is None:
            return
        context = self.session.sparkContext
        # what earlier runs left is collected, and each pool's peak starts from what is in use now
        context._jvm.java.lang.System.gc()
        for pool in _pools(self.session):
            pool.resetPeakUsage()
        self.group = f"topfd-{uuid.uuid4().hex}"
        self.before = [context.getLocalProperty(x) for x in _GROUP]
        context.setJobGroup(self.group, "dependency search")

    def peak(self) -> float:
        """Of the heap so far, in MB."""
        return sum(b.getPeakUsage().getUsed() for b in _pools(self.session)) / 1e6 if self.session is not None else float("nan")

    def read(self) -> dict:
        found = {"peak_heap_mb": float("nan"), "stages": 0, "shuffle_mb": 0.0, "rows_read": 0, "peak_task_mb": 0.0}
        if self.session is None:
            return found
        context = self.session.sparkContext
        for name, value in zip(_GROUP, self.before, strict=True):
            context.setLocalProperty(name, value)
        found["peak_heap_mb"] = self.peak()
        try:
            core = context._jsc.sc()
            core.listenerBus().waitUntilEmpty()
            store, tracker, seen = core.statusStore(), context.statusTracker(), set()
            for job in tracker.getJobIdsForGroup(self.group):
                info = tracker.getJobInfo(job)
                seen |= set(info.stageIds) if info else set()
            for stage in seen:
                data = store.lastStageAttempt(stage)
                if str(data.status()) != "COMPLETE":
                    continue
                found["stages"] += 1
                found["shuffle_mb"] += data.shuffleWriteBytes() / 1e6
                found["rows_read"] += data.inputRecords()
                found["peak_task_mb"] = max(found["peak_task_mb"], data.peakExecutionMemory() / 1e6)
        except Py4JError:
            # the status store keeps a bounded number of jobs; a run's older ones may be gone
            pass
        return found
