"""What a piece of work cost Spark: jobs, stages, CPU seconds, shuffled, spilled and broadcast bytes, from its own status stores."""

from __future__ import annotations

import re
import time
from dataclasses import dataclass

from pyspark.sql import SparkSession

UNITS = {"B": 1, "KiB": 1 << 10, "MiB": 1 << 20, "GiB": 1 << 30, "TiB": 1 << 40}


@dataclass
class Cost:
    jobs: int = 0
    stages: int = 0
    cpu_s: float = 0.0
    shuffle_bytes: int = 0
    spill_bytes: int = 0
    broadcast_bytes: int = 0
    seconds: float = 0.0


def _items(seq) -> list:
    return [seq.apply(i) for i in range(seq.size())]


class Meter:
    """with Meter(spark) as m: ...; then m.cost. One at a time: it counts all work of the application meanwhile. Works without the web pages of Spark."""

    def __init__(self, spark: SparkSession):
        self.spark, self.cost = spark, Cost()
        self.store = spark.sparkContext._jsc.sc().statusStore()
        self.queries = spark._jsparkSession.sharedState().statusStore()

    def _stages(self) -> list:
        gateway = self.spark.sparkContext._gateway
        return _items(self.store.stageList(None, False, False, gateway.new_array(gateway.jvm.double, 0), None))

    def _jobs(self) -> set[int]:
        return {j.jobId() for j in _items(self.store.jobsList(None))}

    def _settle(self) -> None:
        self.spark.sparkContext._jsc.sc().listenerBus().waitUntilEmpty()

    def __enter__(self) -> Meter:
        self._settle()
        self.before = {(s.stageId(), s.attemptId()) for s in self._stages()}, self._jobs(), {e.executionId() for e in _items(self.queries.executionsList())}
        self.begin = time.monotonic()
        return self

    def _broadcast(self, execution: int) -> int:
        values, total = self.queries.executionMetrics(execution), 0
        for node in _items(self.queries.planGraph(execution).allNodes()):
            if node.name() == "BroadcastExchange":
                for m in _items(node.metrics()):
                    told = values.get(m.accumulatorId())
                    if m.name() == "data size" and told.isDefined():
                        number = re.search(r"([0-9.,]+) ([KMGT]?i?B)", told.get())
                        total += int(float(number[1].replace(",", "")) * UNITS[number[2]]) if number else 0
        return total

    def __exit__(self, *_) -> None:
        self.cost.seconds = round(time.monotonic() - self.begin, 3)
        self._settle()
        fresh = [s for s in self._stages() if (s.stageId(), s.attemptId()) not in self.before[0] and s.numCompleteTasks()]
        self.cost.jobs, self.cost.stages = len(self._jobs() - self.before[1]), len(fresh)
        self.cost.cpu_s = round(sum(s.executorCpuTime() for s in fresh) / 1e9, 3)
        self.cost.shuffle_bytes = sum(s.shuffleWriteBytes() for s in fresh)
        self.cost.spill_bytes = sum(s.diskBytesSpilled() for s in fresh)
        self.cost.broadcast_bytes = sum(self._broadcast(e.executionId()) for e in _items(self.queries.executionsList()) if e.executionId() not in self.before[2])
