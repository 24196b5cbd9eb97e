"""Cost of a query: wall time, jobs, stages, tasks, rows and shuffled bytes by stage, read from Spark's status store."""

from __future__ import annotations

import time
import uuid
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession


@dataclass
class StageMeter:
    """with StageMeter(spark) as m: ...  then m.seconds, m.jobs, m.stages, m.tasks, m.shuffle_bytes; m.by_stage() has a row a stage."""

    spark: SparkSession
    label: str = "query"
    seconds: float = 0.0
    jobs: int = 0
    stages: int = 0
    tasks: int = 0
    shuffle_bytes: int = 0
    entries: list[tuple] = field(default_factory=list)
    group: str = field(default_factory=lambda: f"meter-{uuid.uuid4().hex}")

    def __enter__(self) -> "StageMeter":
        self.spark.sparkContext.setJobGroup(self.group, self.label)
        self.began = time.perf_counter()
        return self

    def __exit__(self, *_) -> None:
        self.seconds = time.perf_counter() - self.began
        tracker = self.spark.sparkContext.statusTracker()
        stages = set()
        for job in tracker.getJobIdsForGroup(self.group):
            self.jobs += 1
            info = tracker.getJobInfo(job)
            stages |= set(info.stageIds if info else ())
        store = self.spark.sparkContext._jsc.sc().statusStore()
        self.spark.sparkContext._jsc.sc().listenerBus().waitUntilEmpty(30_000)
        for s in sorted(stages):
            info = tracker.getStageInfo(s)
            if info and info.numCompletedTasks:
                cost = store.lastStageAttempt(s)
                self.stages += 1
                self.tasks += info.numCompletedTasks
                self.shuffle_bytes += cost.shuffleWriteBytes()
                self.entries.append((self.label, s, info.numCompletedTasks, cost.inputRecords() + cost.shuffleReadRecords(), cost.outputRecords() + cost.shuffleWriteRecords(), cost.shuffleReadBytes(), cost.shuffleWriteBytes(), cost.diskBytesSpilled()))
        self.spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)

    def to_df(self) -> DataFrame:
        return self.spark.createDataFrame([(self.label, self.seconds, self.jobs, self.stages, self.tasks, self.shuffle_bytes)], "label string, seconds double, jobs int, stages int, tasks int, shuffle_bytes long")

    def by_stage(self) -> DataFrame:
        return self.spark.createDataFrame(self.entries, "label string, stage int, tasks int, rows_in long, rows_out long, shuffle_read long, shuffle_written long, spilled long")
