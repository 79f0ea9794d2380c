"""What the engine's runs cost, from Spark's own status store. These are proxies: Spark has no access to hardware counters."""

from __future__ import annotations

from contextlib import contextmanager

from pyspark.sql import SparkSession


@contextmanager
def counted(spark: SparkSession, group: str):
    """Jobs started inside belong to group."""
    sc = spark.sparkContext
    sc.setJobGroup(group, group)
    try:
        yield
    finally:
        sc.setLocalProperty("spark.jobGroup.id", None)


def counters(spark: SparkSession, group: str) -> dict[str, float]:
    """Of the stages of a job group: cpu_s (in place of instructions), stalled_s (run time without CPU: waits and GC),
    read_mb_s (input and shuffle read per run second), records_per_cpu_s (in place of instructions per cycle), records."""
    store = spark.sparkContext._jsc.sc().statusStore()
    tracker = spark.sparkContext.statusTracker()
    cpu = run = gc = read = records = 0
    seen = set()
    for job in tracker.getJobIdsForGroup(group):
        info = tracker.getJobInfo(job)
        for stage in info.stageIds if info else ():
            if stage in seen:
                continue
            seen.add(stage)
            try:
                data = store.lastStageAttempt(stage)
            except Exception:  # a skipped stage has no attempt
                continue
            cpu += data.executorCpuTime() / 1e9
            run += data.executorRunTime() / 1e3
            gc += data.jvmGcTime() / 1e3
            read += (data.inputBytes() + data.shuffleReadBytes()) / 1e6
            records += data.inputRecords() + data.shuffleReadRecords()
    return {"cpu_s": cpu, "stalled_s": max(0.0, run - cpu), "gc_s": gc, "read_mb_s": read / run if run else 0.0, "records_per_cpu_s": records / cpu if cpu else 0.0, "records": records}


def normalised(rows: dict[str, dict[str, float]], base: str = "engine") -> dict[str, dict[str, float]]:
    """Each system's counters over those of base."""
    own = rows[base]
    return {k: {m: (v / own[m] if own[m] else 0.0) for m, v in x.items()} for k, x in rows.items()}
