"""Rules that end the rounds, and lineage cuts."""

from __future__ import annotations

import atexit
import re
import shutil
import tempfile
import uuid
from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession


@dataclass
class View:
    """What a callback sees after the start (round 0) and after every round; False ends the rounds."""

    model: object
    round: int

    @property
    def elbo(self) -> float:
        return self.model.lower_bound()


def stop_on_elbo(rel: float = 1e-3, min_rounds: int = 2) -> Callable[[View], bool]:
    """End when the bound moved by less than ``rel`` of its last value, after ``min_rounds`` rounds at least."""
    last: list[float] = []

    def go_on(view: View) -> bool:
        if view.round == 0:
            return True
        now = view.elbo
        small = bool(last) and abs(now - last[-1]) < rel * abs(last[-1])
        last.append(now)
        return not (view.round >= min_rounds and small)

    return go_on


def shared_folder(spark: SparkSession) -> str:
    """The checkpoint folder that the cluster names; one of our own only in local mode."""
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        named = spark.conf.get("spark.checkpoint.dir", None)
        if named is None:
            if not re.fullmatch(r"local(\[[\d*, ]+\])?", sc.master):
                raise RuntimeError("name a folder that driver and executors share in spark.checkpoint.dir")
            named = tempfile.mkdtemp(prefix="plates-")
            atexit.register(shutil.rmtree, named, True)
        sc.setCheckpointDir(named)
    return sc.getCheckpointDir()


def checkpointed(df: DataFrame) -> DataFrame:
    """A reliable checkpoint in the shared folder."""
    shared_folder(df.sparkSession)
    return df.checkpoint(eager=True)


class Scratch:
    """Tables in the shared folder, for state that the rounds pass on."""

    def __init__(self, spark: SparkSession):
        self.spark, self.root = spark, f"{shared_folder(spark)}/rounds-{uuid.uuid4().hex}"
        self.paths: dict[str, list[str]] = {}

    def table(self, df: DataFrame, what: str, partition_by: list[str] | None = None, rows: int = 8) -> DataFrame:
        """``df`` written and read again; a file has at most so many rows, with 0 all of its task."""
        path = f"{self.root}/{what}-{len(self.paths.get(what, []))}-{uuid.uuid4().hex[:8]}"
        # Rows may be megabytes: a reader takes a file's at once, so files are short.
        writer = df.write.options(compression="zstd", maxRecordsPerFile=rows)
        (writer.partitionBy(*partition_by) if partition_by else writer).parquet(path)
        self.paths.setdefault(what, []).append(path)
        return self.spark.read.schema(df.schema).parquet(path)

    def forget(self, what: str, keep: int = 0) -> None:
        """Delete all tables of the name but the last ``keep``."""
        sc = self.spark.sparkContext
        while len(self.paths.get(what, [])) > keep:
            path = sc._jvm.org.apache.hadoop.fs.Path(self.paths[what].pop(0))
            path.getFileSystem(sc._jsc.hadoopConfiguration()).delete(path, True)
