"""Where intermediate relations live: tables in the folder that driver and executors share."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from py4j.protocol import Py4JJavaError
from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F


def shared_root(spark: SparkSession) -> str:
    """``spark.checkpoint.dir`` of the session; a folder of our own only where it is unset and all executors are on this machine."""
    found = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.sparkContext.getCheckpointDir()
    if not found:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        found = "file://" + tempfile.mkdtemp(prefix="pathq-")
        spark.sparkContext.setCheckpointDir(found)
    return found.rstrip("/")


def observed(o: Observation) -> int:
    """The count that an observation made; 0 where adaptive execution found its input empty and dropped the node."""
    try:
        return int(o.get["n"])
    except Py4JJavaError as e:
        if "assertion failed" in str(e):
            return 0
        raise


EXCLUDED = "spark.sql.adaptive.optimizer.excludedRules"
DROPS_EMPTY = "org.apache.spark.sql.execution.adaptive.AQEPropagateEmptyRelation"


@contextmanager
def whole_plans(spark: SparkSession) -> Iterator[None]:
    """Within it, adaptive execution keeps stages whose result turned out empty, and with them what they observed."""
    before = spark.conf.get(EXCLUDED, None)
    spark.conf.set(EXCLUDED, f"{before},{DROPS_EMPTY}" if before else DROPS_EMPTY)
    try:
        yield
    finally:
        if before is None:
            spark.conf.unset(EXCLUDED)
        else:
            spark.conf.set(EXCLUDED, before)


def remove(spark: SparkSession, path: str) -> None:
    """Delete a folder, in whatever file system it lies."""
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)


class Store:
    """A fresh folder for the relations of one evaluation. Reading a table back starts a new, short plan."""

    def __init__(self, spark: SparkSession, name: str):
        self.spark, self.root, self._n = spark, f"{shared_root(spark)}/{name}-{uuid.uuid4().hex}", 0
        self.read_later = False  # answers are found when they are read, from tables that have to stay

    def table(self, df: DataFrame, name: str) -> DataFrame:
        return self.counted(df, name)[0]

    def counted(self, df: DataFrame, name: str) -> tuple[DataFrame, int]:
        """(the table, its number of rows), in one action."""
        self._n += 1
        where, seen = f"{self.root}/{self._n:04d}-{name}", Observation()
        with whole_plans(self.spark):
            df.observe(seen, F.count(F.lit(1)).alias("n")).write.parquet(where)
        return self.spark.read.schema(df.schema).parquet(where), observed(seen)

    def finish(self, df: DataFrame, name: str = "answers") -> tuple[DataFrame, int]:
        """(``df`` written beside the folder, its number of rows); the folder with all that led to it is removed."""
        where, seen = f"{self.root}-{name}", Observation()
        with whole_plans(self.spark):
            df.observe(seen, F.count(F.lit(1)).alias("n")).write.parquet(where)
        n = observed(seen)
        self.close()
        return self.spark.read.schema(df.schema).parquet(where), n

    def close(self) -> None:
        """Remove all tables. What was built on them can no longer be read, so write answers first."""
        remove(self.spark, self.root)
