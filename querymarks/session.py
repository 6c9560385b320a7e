"""Intermediate tables in the folder that all executors share."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


class Workspace:
    """Tables below the folder that ``spark.checkpoint.dir`` names.

    A saved table cuts the lineage as checkpoint() does, and survives lost executors. Where the setting is absent and
    the master is local (tests on one machine) a temporary folder of this machine serves instead, deleted at exit; on a
    cluster, whose machines do not share such a folder, that is an error.
    """

    def __init__(self, spark: SparkSession, name: str):
        self.spark = spark
        shared = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("querymarks.workspace", "")
        if not shared:
            master = spark.sparkContext.master
            if master != "local" and not master.startswith("local["):
                raise ValueError("spark.checkpoint.dir must name a folder that driver and executors share")
            shared = tempfile.mkdtemp(prefix="querymarks-")
            atexit.register(shutil.rmtree, shared, True)
            spark.conf.set("querymarks.workspace", shared)
        self.root = f"{shared.rstrip('/')}/{name}-{uuid.uuid4().hex}"
        self.count = 0

    def save(self, df: DataFrame, label: str = "part") -> DataFrame:
        self.count += 1
        path = f"{self.root}/{self.count:03d}-{label}"
        df.write.option("compression", "zstd").parquet(path)
        saved = self.spark.read.schema(df.schema).parquet(path)
        saved._workspace_path = path
        return saved

    def drop(self, df: DataFrame) -> None:
        """Deletes a saved table that nothing reads any more."""
        path = self.spark._jvm.org.apache.hadoop.fs.Path(df._workspace_path)
        path.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(path, True)
