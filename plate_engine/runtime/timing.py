"""Seconds of each stage of a run."""

from __future__ import annotations

import time
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

STAGES = ("network construction", "code generation", "graph construction", "inference")


class Stopwatch:
    def __init__(self) -> None:
        self.seconds = dict.fromkeys(STAGES, 0.0)

    @contextmanager
    def stage(self, name: str) -> Iterator[None]:
        began = time.perf_counter()
        try:
            yield
        finally:
            self.seconds[name] = self.seconds.get(name, 0.0) + time.perf_counter() - began

    def table(self, spark: SparkSession) -> DataFrame:
        total = sum(self.seconds.values()) or 1.0
        return spark.createDataFrame([(k, v, 100 * v / total) for k, v in self.seconds.items()], "stage string, seconds double, pct double")
