"""Written intermediate tables in the folder that all executors share."""

from __future__ import annotations

import atexit
import os
import re
import uuid

from pyspark.sql import DataFrame, SparkSession

#: Used only where the session names no shared folder and everything runs in one process, as in local tests.
FALLBACK = "/tmp/ranked_theta_shared"


def shared_root(spark: SparkSession) -> str:
    """The folder of ``spark.checkpoint.dir``; a local one only if that is unset and the master is ``local``."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        if not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
            raise ValueError("spark.checkpoint.dir must name a folder that the driver and all executors share")
        root = FALLBACK
    return root if ":" in root.split("/")[0] else "file://" + os.path.abspath(root)


class Staging:
    """A private folder below the shared root; ``save`` cuts the lineage there."""

    def __init__(self, spark: SparkSession, label: str):
        self.spark, self.path = spark, f"{shared_root(spark)}/{label}-{uuid.uuid4().hex[:12]}"
        atexit.register(self.drop)

    def save(self, df: DataFrame, name: str) -> DataFrame:
        df.write.mode("overwrite").parquet(f"{self.path}/{name}")
        return self.spark.read.schema(df.schema).parquet(f"{self.path}/{name}")

    def at(self, name: str) -> str:
        return f"{self.path}/{name}"

    def drop(self) -> None:
        context = self.spark.sparkContext
        if context._jvm is None or context._jsc is None:
            return
        try:
            path = context._jvm.org.apache.hadoop.fs.Path(self.path)
            path.getFileSystem(context._jsc.hadoopConfiguration()).delete(path, True)
        except Exception:  # the JVM may be gone when the interpreter ends
            return
