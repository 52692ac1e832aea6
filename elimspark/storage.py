"""Level stores and scratch tables: Parquet in the folder that all executors share."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """``spark.checkpoint.dir`` of the session; a local folder only where it is unset and the session is local."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if folder:
        return folder
    context = spark.sparkContext
    if context.getCheckpointDir() is None:
        if not context.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        context.setCheckpointDir(tempfile.mkdtemp(prefix="elimspark-"))
    return context.getCheckpointDir()


class LevelStore:
    """Frontiers of a search by (k, level), written once and read back without lineage."""

    def __init__(self, spark: SparkSession, name: str = "levels"):
        self.spark = spark
        self.root = f"{shared_dir(spark).rstrip('/')}/{name}-{uuid.uuid4().hex}"

    def path(self, k: int, level: int) -> str:
        return f"{self.root}/k={k}/level={level}"

    def write(self, frame: DataFrame, k: int, level: int) -> DataFrame:
        frame.write.mode("overwrite").parquet(self.path(k, level))
        return self.read(k, level, frame.schema)

    def read(self, k: int, level: int, schema=None) -> DataFrame:
        reader = self.spark.read.schema(schema) if schema is not None else self.spark.read
        return reader.parquet(self.path(k, level))

    def bytes(self, k: int, level: int) -> int:
        """Size of a stored level."""
        path, files = self._files(self.path(k, level))
        return files.getContentSummary(path).getLength()

    def _files(self, where: str):
        path = self.spark.sparkContext._jvm.org.apache.hadoop.fs.Path(where)
        return path, path.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration())

    def drop(self, k: int | None = None, level: int | None = None) -> None:
        """Delete one level, or the whole store."""
        path, files = self._files(self.root if k is None else self.path(k, level))
        files.delete(path, True)
