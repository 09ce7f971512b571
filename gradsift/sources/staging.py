"""Intermediate tables in the folder that driver and executors share."""

from __future__ import annotations

import atexit
import gc
import shutil
import tempfile
import time
import uuid

from pyspark.sql import DataFrame, SparkSession

_LOCAL: list[str] = []


def shared_dir(spark: SparkSession) -> str:
    """``spark.checkpoint.dir`` of the session.

    Where it is unset: a folder that ends with the process on a local master,
    else a folder of the warehouse, which a cluster shares too.
    """
    found = spark.conf.get("spark.checkpoint.dir", None)
    if found:
        return found.rstrip("/")
    if spark.sparkContext.master.split("[")[0] == "local":
        if not _LOCAL:
            _LOCAL.append(tempfile.mkdtemp(prefix="gradsift-"))
            atexit.register(shutil.rmtree, _LOCAL[0], ignore_errors=True)
        return f"file://{_LOCAL[0]}"
    return spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/gradsift-stage"


class Stage:
    """Writes tables to the shared folder and reads them back, which cuts lineage.

    A table that no later plan needs is removed with ``drop``.
    """

    def __init__(self, spark: SparkSession, name: str):
        self.spark = spark
        self.root = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
        self._n = 0
        self._paths: dict[int, str] = {}

    def put(self, df: DataFrame) -> DataFrame:
        path = f"{self.root}/t{self._n}"
        self._n += 1
        df.write.parquet(path)
        out = self.spark.read.schema(df.schema).parquet(path)
        self._paths[id(out)] = path
        out._gradsift_path = path
        return out

    def sweep(self) -> None:
        """Lets the cleaner remove the shuffle files of plans that nothing refers to any more.

        Python's handles are let go within a second of their collection; only then can the
        JVM collect what they held.
        """
        gc.collect()
        time.sleep(1.2)
        self.spark._jvm.System.gc()
        time.sleep(0.3)

    def drop(self, *tables: DataFrame) -> None:
        jvm = self.spark._jvm
        conf = self.spark._jsc.hadoopConfiguration()
        for t in tables:
            path = jvm.org.apache.hadoop.fs.Path(t._gradsift_path)
            path.getFileSystem(conf).delete(path, True)


def staged(df: DataFrame, name: str = "ratings") -> DataFrame:
    """The table written once and read back: later passes don't repeat what made it."""
    return Stage(df.sparkSession, name).put(df)
