"""Tables that cut lineage: written to the folder all executors share."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_OWN: list[str] = []


def shared_folder(spark: SparkSession) -> str:
    """``spark.checkpoint.dir``; where that is unset, a temporary folder in local mode and the warehouse on a cluster."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if found:
        return found.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        return spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/hopwise-work"
    if not _OWN:
        _OWN.append("file://" + tempfile.mkdtemp(prefix="hopwise-"))
    return _OWN[0]


def written(df: DataFrame, name: str) -> DataFrame:
    """``df`` written to the shared folder and read back: its lineage is cut and a lost executor costs no recomputation."""
    path = f"{shared_folder(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    schema = df.schema
    df.write.parquet(path)
    out = df.sparkSession.read.schema(schema).parquet(path)
    out._hopwise_path = path
    return out


def forget(df: DataFrame) -> None:
    """Delete a table made by ``written`` that no later step reads."""
    path, jvm = df._hopwise_path, df.sparkSession._jvm
    at = jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(df.sparkSession._jsc.hadoopConfiguration()).delete(at, True)


class RoundLog:
    """An append-only table of rounds: each is written once to a folder of its own, and any run of rounds is one scan."""

    def __init__(self, spark: SparkSession, name: str, schema: str):
        self.spark, self.schema = spark, f"{schema}, round int"
        self.path = f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"
        self.rounds = 0

    def append(self, df: DataFrame) -> None:
        df.write.parquet(f"{self.path}/round={self.rounds}")
        self.rounds += 1

    def since(self, first: int = 0) -> DataFrame:
        folders = [f"{self.path}/round={i}" for i in range(max(first, 0), self.rounds)]
        return self.spark.read.schema(self.schema).option("basePath", self.path).parquet(*folders)

    def last(self) -> DataFrame:
        return self.since(self.rounds - 1)


def save_bucketed(df: DataFrame, table: str, key: str, buckets: int) -> DataFrame:
    """A catalog table bucketed and sorted by ``key``: later joins on the key with as many buckets need no exchange."""
    df.repartition(buckets, key).write.bucketBy(buckets, key).sortBy(key).mode("overwrite").saveAsTable(table)
    return df.sparkSession.table(table)
