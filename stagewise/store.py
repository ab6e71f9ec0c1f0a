"""Tables in the folder that all machines of a cluster share: intermediate results, and the durable plan.

``spark.checkpoint.dir`` names that folder.  Only a local session without the
setting gets a folder of its own; anything else would not be seen by executors.
"""

from __future__ import annotations

import atexit
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_OWN: list[str] = []


def shared_dir(spark: SparkSession) -> str:
    found = spark.conf.get("spark.checkpoint.dir", None)
    if found:
        return found.rstrip("/")
    if spark.sparkContext.master.split("[")[0] != "local":
        raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
    if not _OWN:
        _OWN.append("file://" + tempfile.mkdtemp(prefix="stagewise-"))
    return _OWN[0]


def _path(spark: SparkSession, path: str):
    """(file system, path) of the JVM."""
    jvm = spark.sparkContext._jvm
    where = jvm.org.apache.hadoop.fs.Path(path)
    return where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()), where


def exists(spark: SparkSession, path: str) -> bool:
    system, where = _path(spark, path)
    return system.exists(where)


def delete(spark: SparkSession, path: str) -> None:
    system, where = _path(spark, path)
    system.delete(where, True)


class Scratch:
    """Parquet tables of one run of an operator.

    ``save`` cuts the lineage: the written files outlive any executor.  ``drop``
    removes a table that no later plan reads; the rest goes when Python exits.
    """

    def __init__(self, spark: SparkSession, name: str):
        self.spark = spark
        self.root = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
        atexit.register(self._end)

    def _end(self) -> None:
        if self.spark.sparkContext._jsc is not None:
            try:
                delete(self.spark, self.root)
            except Exception:  # noqa: BLE001 - the session may be gone already
                return

    def save(self, df: DataFrame, name: str) -> DataFrame:
        path = f"{self.root}/{name}"
        df.write.mode("overwrite").parquet(path)
        return self.spark.read.schema(df.schema).parquet(path)

    def drop(self, *names: str) -> None:
        for name in names:
            delete(self.spark, f"{self.root}/{name}")


#: Facts of a plan, one narrow row each; a node's line is the way to it from its root.
PLAN_TABLES = {
    "nodes": "path string, parent string, start bigint, cfg string, depth int, line array<struct<path string, start bigint>>",
    "requests": "path string, step bigint",
    "asked": "study string, trial bigint, path string, step bigint",
    "ckpts": "path string, step bigint, ckpt binary",
    "metrics": "path string, step bigint, value double",
    "profile": "cfg string, sec double",
}


class PlanStore:
    """The tables of one plan under ``root``, each partitioned by the plan's key; facts are appended and never changed.

    Each append is a folder of its own, named by the caller: a part that is written again after a failure replaces itself, and
    readers take whole parts only.
    """

    def __init__(self, spark: SparkSession, root: str, key: str):
        self.spark, self.root, self.key = spark, root.rstrip("/"), key

    def _folder(self, name: str) -> str:
        return f"{self.root}/{name}/plan_key={self.key}"

    def append(self, name: str, rows: DataFrame, part: str) -> None:
        columns = self.spark.createDataFrame([], PLAN_TABLES[name]).columns
        rows.select(*columns).write.mode("overwrite").parquet(f"{self._folder(name)}/part={part}")

    def _whole(self, name: str) -> list[str]:
        """The folders of the parts that are written to their end."""
        if not exists(self.spark, self._folder(name)):
            return []
        system, where = _path(self.spark, self._folder(name))
        found = [x.getPath().toString() for x in system.listStatus(where) if x.isDirectory()]
        return sorted(x for x in found if exists(self.spark, f"{x}/_SUCCESS"))

    def read(self, name: str) -> DataFrame:
        """All rows of the plan; none if nothing was written."""
        parts = self._whole(name)
        if not parts:
            return self.spark.createDataFrame([], PLAN_TABLES[name])
        return self.spark.read.schema(PLAN_TABLES[name]).parquet(*parts)

    def parts(self, name: str) -> int:
        return len(self._whole(name))

    def compact(self, name: str, files: int = 1) -> None:
        """Writes all parts of a table as one, sorted by node, and then takes the old ones away; a reader of that moment may see rows twice, never too few."""
        old = self._whole(name)
        if len(old) < 2:
            return
        rows = self.read(name)
        sort = "path" if "path" in rows.columns else "cfg"
        self.append(name, rows.distinct().repartition(files, F.col(sort)).sortWithinPartitions(sort), f"whole-{uuid.uuid4().hex}")
        for x in old:
            delete(self.spark, x)
