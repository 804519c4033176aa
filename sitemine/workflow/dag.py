"""Small workflows: jobs with order constraints, run in parallel, resumed after a crash.

A job is a function of the session and its predecessors' results that returns a
DataFrame; the result is written under ``path/name``.  A job whose output holds Spark's
success marker is not run again, so a workflow continues where it broke off.
"""

from __future__ import annotations

import time
from collections.abc import Callable
from concurrent.futures import FIRST_COMPLETED, ThreadPoolExecutor, wait
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession

Job = Callable[..., DataFrame]


@dataclass
class RunInfo:
    """When each job ran: name -> (began, ended), or ``resumed``."""

    times: dict[str, tuple[float, float]] = field(default_factory=dict)
    resumed: list[str] = field(default_factory=list)


class Dag:
    def __init__(self, path: str):
        self.path = path
        self.jobs: dict[str, tuple[Job, tuple[str, ...]]] = {}

    def add(self, name: str, job: Job, after: tuple[str, ...] | list[str] = ()) -> Dag:
        if name in self.jobs:
            raise ValueError(f"{name} is there already")
        if missing := [a for a in after if a not in self.jobs]:
            raise ValueError(f"{name} comes after unknown jobs: {', '.join(missing)}")
        self.jobs[name] = (job, tuple(after))
        return self

    def order(self) -> list[str]:
        """A topological order; jobs are added after those they follow, so it is that of adding."""
        return list(self.jobs)

    def done(self, spark: SparkSession, name: str) -> bool:
        marker = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{self.path}/{name}/_SUCCESS")
        return marker.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(marker)

    def run(self, spark: SparkSession, workers: int = 4) -> tuple[dict[str, DataFrame], RunInfo]:
        info, results, running = RunInfo(), {}, {}

        def one(name: str) -> None:
            job, after = self.jobs[name]
            began = time.time()
            spark.sparkContext.setLocalProperty("spark.scheduler.pool", name)
            job(spark, *[results[a] for a in after]).write.mode("overwrite").parquet(f"{self.path}/{name}")
            info.times[name] = (began, time.time())

        with ThreadPoolExecutor(workers) as pool:
            todo = self.order()
            while todo or running:
                for name in [n for n in todo if all(a in results for a in self.jobs[n][1])]:
                    todo.remove(name)
                    if self.done(spark, name):
                        info.resumed.append(name)
                        results[name] = spark.read.parquet(f"{self.path}/{name}")
                    else:
                        running[pool.submit(one, name)] = name
                if running:
                    ended, _ = wait(running, return_when=FIRST_COMPLETED)
                    for f in ended:
                        name = running.pop(f)
                        f.result()
                        results[name] = spark.read.parquet(f"{self.path}/{name}")
        return results, info
