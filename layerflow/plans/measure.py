"""What a run costs: wall time and the bytes of its stages, and a process's CPU and memory once a second."""

from __future__ import annotations

import os
import threading
import time
from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession


@dataclass
class Cost:
    seconds: float = 0.0
    read_bytes: int = 0
    shuffle_bytes: int = 0
    spill_bytes: int = 0
    task_seconds: float = 0.0


def _stages(spark: SparkSession) -> dict[int, object]:
    gateway = spark.sparkContext._gateway
    rows = spark.sparkContext._jsc.sc().statusStore().stageList(None, False, False, gateway.new_array(gateway.jvm.double, 0), None)
    return {rows.apply(i).stageId(): rows.apply(i) for i in range(rows.size())}


def measured(spark: SparkSession, run: Callable[[], DataFrame]) -> Cost:
    """Runs a query to the end without keeping its rows."""
    before = set(_stages(spark))
    began = time.time()
    run().write.format("noop").mode("overwrite").save()
    cost = Cost(round(time.time() - began, 3))
    for k, s in _stages(spark).items():
        if k not in before:
            cost.read_bytes += s.inputBytes()
            cost.shuffle_bytes += s.shuffleWriteBytes()
            cost.spill_bytes += s.diskBytesSpilled()
            cost.task_seconds += s.executorRunTime() / 1000
    return cost


@dataclass
class ProcessTrace:
    """Samples of a process's CPU seconds and resident bytes."""

    pid: int
    every: float = 1.0
    samples: list[tuple[float, float, int]] = field(default_factory=list)

    def __enter__(self) -> ProcessTrace:
        self._stop = threading.Event()
        self._thread = threading.Thread(target=self._watch, daemon=True)
        self._thread.start()
        return self

    def __exit__(self, *_) -> None:
        self._stop.set()
        self._thread.join()

    def _watch(self) -> None:
        tick, page = os.sysconf("SC_CLK_TCK"), os.sysconf("SC_PAGE_SIZE")
        while True:
            try:
                with open(f"/proc/{self.pid}/stat") as f:
                    parts = f.read().rsplit(")", 1)[1].split()
            except OSError:
                return
            self.samples.append((time.time(), (int(parts[11]) + int(parts[12])) / tick, int(parts[21]) * page))
            if self._stop.wait(self.every):
                return

    def cpu_percent(self) -> float:
        if len(self.samples) < 2:
            return 0.0
        (t0, c0, _), (t1, c1, _) = self.samples[0], self.samples[-1]
        return 100 * (c1 - c0) / max(1e-9, t1 - t0)

    def peak_bytes(self) -> int:
        return max((m for *_, m in self.samples), default=0)
