"""Helpers that the operators of this folder share."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable, Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that the session names for checkpoints. Only a local master, as in tests, may go without one."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named:
        if spark.conf.get("spark.master", "local").split("[")[0] != "local":
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        named = f"{tempfile.gettempdir()}/graphkw-stages"
    return named.rstrip("/")


#: Spark's setting that deletes the shuffle files of a job when it ends.
CLEANED = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


class Stage:
    """A table written to the shared folder: cuts the lineage, outlives executors, can be dropped. The shuffle files of the job that writes it go with the job."""

    def __init__(self, df: DataFrame, label: str, codec: str | None = None):
        self.spark = df.sparkSession
        self.path = f"{shared_dir(self.spark)}/{label}-{uuid.uuid4().hex}"
        # The caller still holds ``df`` here, so a collection of garbage would free the shuffle files a job later.
        before = self.spark.conf.get(CLEANED, "false")
        self.spark.conf.set(CLEANED, "true")
        try:
            df.write.parquet(self.path, compression=codec)
        finally:
            self.spark.conf.set(CLEANED, before)
        self.spark.sparkContext._jvm.System.gc()  # lets Spark delete what other jobs have left

    @property
    def df(self) -> DataFrame:
        return self.spark.read.parquet(self.path)

    def drop(self) -> None:
        jvm = self.spark.sparkContext._jvm
        path = jvm.org.apache.hadoop.fs.Path(self.path)
        path.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def text_of(name: str = "text"):
    """A text column with null read as empty."""
    return F.coalesce(F.col(name), F.lit(""))


def by_bytes(texts: list[str | bytes | None], limit: int) -> Iterator[tuple[int, int]]:
    """Ranges of consecutive texts with about ``limit`` bytes of UTF-8 each; a longer text stands alone."""
    start, held = 0, 0
    for i, t in enumerate(texts):
        n = 0 if not t else len(t) if isinstance(t, bytes) or t.isascii() else len(t.encode("utf-8", "surrogatepass"))
        if held and held + n > limit:
            yield start, i
            start, held = i, 0
        held += n
    if start < len(texts):
        yield start, len(texts)


def map_batches(df: DataFrame, make: Callable[[], Callable[[pa.RecordBatch], Iterable[pa.RecordBatch]]], schema: str) -> DataFrame:
    """``mapInArrow`` with a worker function built once per task by ``make``."""

    def run(batches):
        work = make()
        for batch in batches:
            if batch.num_rows:
                yield from work(batch)

    return df.mapInArrow(run, schema)
