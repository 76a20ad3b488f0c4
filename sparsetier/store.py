"""Written intermediate tables in the folder that all executors share."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_OWN: dict[str, str] = {}


def work_dir(spark: SparkSession) -> str:
    """The shared folder named by spark.checkpoint.dir. Where that is unset (tests) a temporary one, and only in local mode: on a
    cluster other machines would not see it."""
    shared = spark.conf.get("spark.checkpoint.dir", None)
    if shared:
        return shared.rstrip("/")
    if spark.sparkContext.master.split("[")[0] != "local":
        raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
    return _OWN.setdefault("dir", tempfile.mkdtemp(prefix="sparsetier_"))


class Scratch:
    """Written intermediate tables: lineage ends at files that survive lost executors. ``clear`` deletes those no longer needed."""

    def __init__(self, spark: SparkSession):
        self.spark, self.paths = spark, []

    def path(self, tag: str) -> str:
        self.paths.append(f"{work_dir(self.spark)}/{tag}_{uuid.uuid4().hex}")
        return self.paths[-1]

    def write(self, df: DataFrame, tag: str) -> DataFrame:
        path = self.path(tag)
        df.write.parquet(path)
        return self.spark.read.schema(df.schema).parquet(path)

    def clear(self, but: int = 0):
        """Delete all written tables, or all but the last ``but``."""
        gone, self.paths = self.paths[:len(self.paths) - but], self.paths[len(self.paths) - but:]
        for path in gone:
            at = self.spark._jvm.org.apache.hadoop.fs.Path(path)
            at.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(at, True)
