"""What the operators of this subpackage share: the shared folder, tables that cut lineage, text and id helpers."""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from pathq.store import remove, shared_root


@contextmanager
def small_batches(spark: SparkSession, rows: int = 500, size: int = 8 << 20) -> Iterator[None]:
    """Within it, Python workers get at most ``rows`` rows or about ``size`` bytes at a time: texts and sets are long, and batches are held twice."""
    limits = {"spark.sql.execution.arrow.maxRecordsPerBatch": rows, "spark.sql.execution.arrow.maxBytesPerBatch": size}
    before = {key: spark.conf.get(key, None) for key in limits}
    for key, most in limits.items():
        spark.conf.set(key, str(most))
    try:
        yield
    finally:
        for key, value in before.items():
            spark.conf.unset(key) if value is None else spark.conf.set(key, value)


class Workspace:
    """A fresh folder below the shared one, for the intermediate tables and files of one run."""

    def __init__(self, spark: SparkSession, name: str):
        self.spark, self.root = spark, f"{shared_root(spark)}/{name}-{uuid.uuid4().hex}"
        self._n = 0

    def path(self, name: str) -> str:
        self._n += 1
        return f"{self.root}/{self._n:03d}-{name}"

    def table(self, df: DataFrame, name: str) -> DataFrame:
        """Write ``df`` and read it back: later plans start from files that survive a lost executor."""
        where = self.path(name)
        with small_batches(self.spark):
            df.write.parquet(where)
        return self.spark.read.schema(df.schema).parquet(where)

    def close(self) -> None:
        """Remove the folder; what was built on it can no longer be read."""
        remove(self.spark, self.root)

    def finish(self, df: DataFrame) -> DataFrame:
        """Write the result beside the folder, and remove the folder with all intermediate tables."""
        where = f"{self.root}-result"
        df.write.parquet(where)
        remove(self.spark, self.root)
        return self.spark.read.schema(df.schema).parquet(where)


def filesystem(uri: str):
    """(pyarrow file system, path) of a folder in the shared store; works on the driver and in Python workers."""
    from pyarrow import fs

    return fs.FileSystem.from_uri(uri if "://" in uri or uri.startswith("file:") else "file://" + uri)


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def ascii_lower(text: Column) -> Column:
    """Lower-case A-Z and nothing that could turn into ASCII.

    ``lower`` is the fast path. Only U+212A and U+0130 have lower-case forms with an ASCII letter, so texts
    that hold one of them take the exact character map. Other letters may change case, which no caller sees:
    this is for matching ASCII phrases and for counting words.
    """
    odd = text.contains("K") | text.contains("İ")
    return F.when(odd, F.translate(text, UPPER, LOWER)).otherwise(F.lower(text))


FILTER_BITS = 1 << 26


def prefilter(df: DataFrame, ids: DataFrame, column: str, out: bool = False) -> DataFrame:
    """Rows of ``df`` whose ``column`` may be in ``ids``, to be followed by an exact join; with ``out`` the others, which surely are not.

    The ids set bits in a map of 2**26 bits (8 MB, whatever their number), which is broadcast, so that wide rows
    that will not match are not shuffled.
    """
    page = 32768
    spot = F.pmod(F.xxhash64(F.col(column)), F.lit(FILTER_BITS))
    bits = ids.select(spot.alias("s")).groupBy((F.col("s") / page).cast("int").alias("__page")).agg(F.bitmap_construct_agg((F.col("s") % page).cast("long")).alias("__bits"))
    marked = df.withColumn("__spot", spot).withColumn("__page", (F.col("__spot") / page).cast("int")).join(F.broadcast(bits), "__page", "left")
    byte = "cast(conv(hex(substring(__bits, cast((__spot % 32768) div 8 as int) + 1, 1)), 16, 10) as int)"
    there = F.coalesce(F.expr(f"(shiftright({byte}, cast(__spot % 8 as int)) & 1) = 1"), F.lit(False))
    return marked.filter(~there if out else there).select(*df.columns)
