"""Intermediate tables that cut the lineage and survive lost executors."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Observation, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The folder that the session names for checkpoints. Only a local master, as in tests, may go without one."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named:
        if not spark.conf.get("spark.master", "local").split("[")[0] == "local":
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        named = f"{tempfile.gettempdir()}/graphkw-stages"
    return named.rstrip("/")


def _delete(spark: SparkSession, path: str) -> None:
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


class Snapshot:
    """A table written to the shared folder; ``seen`` holds the aggregates ``watch`` over it, taken while it was written."""

    def __init__(self, df: DataFrame, watch: Sequence[Column] = ()):
        self.spark = df.sparkSession
        self.path = f"{shared_dir(self.spark)}/round-{uuid.uuid4().hex}"
        self.schema = df.schema
        seen = Observation()
        (df.observe(seen, *watch) if watch else df).write.parquet(self.path)
        self.seen: dict = seen.get if watch else {}

    @property
    def df(self) -> DataFrame:
        return self.spark.read.schema(self.schema).parquet(self.path)

    def drop(self) -> None:
        _delete(self.spark, self.path)


class Bucketed:
    """A table in the shared folder, dealt and sorted by ``key`` once, so that joins on it move only their other side."""

    def __init__(self, df: DataFrame, key: str, buckets: int | None = None):
        self.spark = df.sparkSession
        self.name = f"gk_{uuid.uuid4().hex}"
        self.path = f"{shared_dir(self.spark)}/{self.name}"
        n = buckets or int(self.spark.conf.get("spark.sql.shuffle.partitions"))
        df.repartition(n, key).write.bucketBy(n, key).sortBy(key).option("path", self.path).saveAsTable(self.name)

    @property
    def df(self) -> DataFrame:
        return self.spark.table(self.name)

    def drop(self) -> None:
        self.spark.sql(f"DROP TABLE IF EXISTS {self.name}")
        _delete(self.spark, self.path)
