"""Written tables in the session's shared folder, which cut lineage between rounds."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_root(spark: SparkSession) -> str:
    """``spark.checkpoint.dir`` of the session; a temporary folder only in local mode, where all tasks run on this machine."""
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not named:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        spark.sparkContext.setCheckpointDir("file://" + tempfile.mkdtemp(prefix="gridtide-"))
        named = spark.sparkContext.getCheckpointDir()
    return named.rstrip("/")


class Workspace:
    """A private folder of written tables."""

    def __init__(self, spark: SparkSession, purpose: str):
        self.spark, self.path = spark, f"{shared_root(spark)}/gridtide/{purpose}-{uuid.uuid4().hex}"

    def put(self, frame: DataFrame, name: str, by: str | None = None) -> DataFrame:
        """Write ``frame``, in a folder for each value of ``by`` if given, and read it back."""
        if by:
            frame.repartition(by).write.mode("overwrite").partitionBy(by).parquet(f"{self.path}/{name}")
        else:
            frame.write.mode("overwrite").parquet(f"{self.path}/{name}")
        return self.spark.read.schema(frame.schema).parquet(f"{self.path}/{name}")

    def drop(self, name: str = "") -> None:
        """Delete a table, or the whole folder, that nothing reads any more."""
        path = self.spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{self.path}/{name}" if name else self.path)
        path.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)
