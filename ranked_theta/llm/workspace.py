"""Intermediate tables and files in the folder that all executors share."""

from __future__ import annotations

import atexit
import os
import re
import uuid
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

#: Used only where the session names no shared folder and everything runs in one process, as in local tests.
FALLBACK = "/tmp/ranked_theta_shared"


#: Rows of an Arrow batch while a table is written; the setting and the most of them.
BATCH, ROWS = "spark.sql.execution.arrow.maxRecordsPerBatch", 1000
#: What was shuffled for a table goes when the table is written, not when the driver collects its garbage.
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def shared_root(spark: SparkSession) -> str:
    """The folder of ``spark.checkpoint.dir``; a local one only if that is unset and the master is ``local``."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        if not re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master):
            raise ValueError("spark.checkpoint.dir must name a folder that the driver and all executors share")
        root = FALLBACK
    return root if ":" in root.split("/")[0] else "file://" + os.path.abspath(root)


def importable(spark: SparkSession) -> None:
    """Lets Python workers on this machine import the package from where the driver did.

    On a cluster the package is shipped with the job, as any other.
    """
    home = str(Path(__file__).resolve().parents[2])
    env = spark.sparkContext.environment
    if home not in env.get("PYTHONPATH", "").split(os.pathsep):
        env["PYTHONPATH"] = os.pathsep.join(x for x in (home, env.get("PYTHONPATH", "")) if x)


class Workspace:
    """A private folder below the shared root.

    ``save`` writes a DataFrame as Parquet and reads it back, which cuts the lineage
    with replicated files, so a lost executor costs only its running tasks. Tables are
    kept until ``drop`` or the end of the driver.
    """

    def __init__(self, spark: SparkSession, label: str):
        importable(spark)
        self.spark = spark
        self.path = f"{shared_root(spark)}/{label}-{uuid.uuid4().hex[:12]}"
        atexit.register(self.drop)

    def at(self, name: str) -> str:
        return f"{self.path}/{name}"

    def save(self, df: DataFrame, name: str, codec: str | None = None) -> DataFrame:
        # rows may hold whole texts or sets of hashes: few of them go to a worker at once
        conf = self.spark.conf
        before = {k: conf.get(k, None) for k in (BATCH, CLEANUP)}
        conf.set(BATCH, str(min(ROWS, int(before[BATCH] or ROWS))))
        conf.set(CLEANUP, "true")
        try:
            out = df.write.mode("overwrite")
            (out.option("compression", codec) if codec else out).parquet(self.at(name))
        finally:
            for k, v in before.items():
                conf.unset(k) if v is None else conf.set(k, v)
        return self.spark.read.schema(df.schema).parquet(self.at(name))

    def names(self) -> list[str]:
        path = self.spark.sparkContext._jvm.org.apache.hadoop.fs.Path(self.path)
        return [x.getPath().getName() for x in path.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).listStatus(path)]

    def keep(self, *names: str) -> None:
        """Drops all tables and files but these."""
        for name in self.names():
            if name not in names:
                self.drop(name)

    def drop(self, name: str | None = None) -> None:
        jvm = self.spark.sparkContext._jvm
        if jvm is None or self.spark.sparkContext._jsc is None:
            return
        try:
            path = jvm.org.apache.hadoop.fs.Path(self.at(name) if name else self.path)
            path.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)
        except Exception:  # the JVM may be gone when the interpreter ends
            return
