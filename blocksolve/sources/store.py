"""Block store, versioned state and interchange files. All tables go to the folder that every executor shares."""

from __future__ import annotations

import re
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_dir(spark: SparkSession) -> str:
    at = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not at:
        if not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="blocksolve-"))
        at = spark.sparkContext.getCheckpointDir()
    return at.rstrip("/")


def commit(df: DataFrame, name: str) -> DataFrame:
    """Write a state and read it back: the lineage ends here and a lost executor costs one read."""
    path = f"{shared_dir(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def forget(df: DataFrame) -> None:
    """Delete a committed state's files."""
    spark = df.sparkSession
    for folder in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        p = spark._jvm.org.apache.hadoop.fs.Path(folder)
        p.getFileSystem(spark._jsc.hadoopConfiguration()).delete(p, True)


class Parts:
    """A state kept by column block: a round rewrites the blocks that it changed, and reading is one scan over the current ones."""

    def __init__(self, spark: SparkSession, name: str, ddl: str):
        self.spark, self.ddl = spark, ddl
        self.root = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
        self.at: dict[int, str] = {}
        self.version = 0

    def _fs(self, path: str):
        p = self.spark._jvm.org.apache.hadoop.fs.Path(path)
        return p.getFileSystem(self.spark._jsc.hadoopConfiguration()), p

    def read(self, blocks: list[int] | None = None) -> DataFrame:
        """The given blocks' rows, or all."""
        paths = [p for cb, p in sorted(self.at.items()) if blocks is None or cb in blocks]
        return self.spark.read.schema(self.ddl).parquet(*paths) if paths else self.spark.createDataFrame([], self.ddl)

    def write(self, rows: DataFrame, blocks: list[int]) -> list[str]:
        """Replace the given blocks; gives the folders that are no longer current (the caller drops them when nothing reads them)."""
        self.version += 1
        to = f"{self.root}/v{self.version}"
        rows.withColumn("part", F.col("cb")).write.partitionBy("part").parquet(to)
        old = [self.at.pop(cb) for cb in blocks if cb in self.at]
        for cb in blocks:
            fs, p = self._fs(f"{to}/part={cb}")
            if fs.exists(p):
                self.at[cb] = f"{to}/part={cb}"
        return old

    def drop(self, folders: list[str]) -> None:
        for folder in folders:
            fs, p = self._fs(folder)
            fs.delete(p, True)


def write_blocks(entries: DataFrame, path: str, files: int) -> None:
    """One folder a column block, sorted by row block inside, so that picks prune folders and skip row groups."""
    entries.repartitionByRange(files, "cb", "rb").sortWithinPartitions("cb", "rb", "row_id").write.mode("overwrite").partitionBy("cb").parquet(path)


def read_blocks(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(path).select(F.col("cb").cast("int").alias("cb"), "rb", "row_id", "col_id", "val")


def write_epoch(state: DataFrame, path: str, epoch: int, keep: int = 2) -> None:
    """Version ``epoch`` of a state; versions older than ``keep`` epochs are deleted."""
    state.write.mode("overwrite").parquet(f"{path}/epoch={epoch}")
    spark = state.sparkSession
    old = spark._jvm.org.apache.hadoop.fs.Path(f"{path}/epoch={epoch - keep}")
    old.getFileSystem(spark._jsc.hadoopConfiguration()).delete(old, True)


def write_coordinates(entries: DataFrame, path: str) -> None:
    """Text lines "row column value" from 1, as coordinate files of sparse matrices have them."""
    entries.select(F.concat_ws(" ", F.col("row_id") + 1, F.col("col_id") + 1, "val").alias("value")).write.mode("overwrite").text(path)


def read_coordinates(spark: SparkSession, path: str) -> DataFrame:
    """row_id, col_id, val of such files; lines that begin with % are skipped (a size line must begin so)."""
    lines = spark.read.text(path).where("NOT startswith(value, '%') AND trim(value) <> ''")
    p = F.split(F.trim("value"), r"\s+")
    return lines.select((p[0].cast("bigint") - 1).alias("row_id"), (p[1].cast("bigint") - 1).alias("col_id"), p[2].cast("double").alias("val"))
