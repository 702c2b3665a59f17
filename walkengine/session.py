"""Session helpers shared by all parts: tables, the shared folder, staged tables and partition counts."""

from __future__ import annotations

import atexit
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given Parquet tables."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that the driver and all executors share: ``spark.checkpoint.dir``.  A temporary one where that is unset
    and Spark runs in one process; on a cluster executors would write to their own disks, so there it is refused."""
    context = spark.sparkContext
    folder = context.getConf().get("spark.checkpoint.dir") or context.getCheckpointDir()
    if not folder:
        if not context.master.startswith("local") or context.master.startswith("local-cluster"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        folder = tempfile.mkdtemp(prefix="walkengine-")
        context.setCheckpointDir(folder)
        folder = context.getCheckpointDir() or folder
    return folder.rstrip("/")


def fresh_folder(spark: SparkSession, name: str) -> str:
    """A new path in the shared folder; what is written there goes when the driver's JVM ends."""
    path = f"{shared_dir(spark)}/staged-{name}-{uuid.uuid4().hex[:12]}"
    try:
        jvm = spark.sparkContext._jvm
        target = jvm.org.apache.hadoop.fs.Path(path)
        target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).deleteOnExit(target)
    except AttributeError:  # a session without a JVM gateway: the files stay
        pass
    return path


def staged(df: DataFrame, name: str) -> DataFrame:
    """Writes ``df`` as Parquet into the shared folder and reads it back, which cuts lineage and survives lost
    executors."""
    path = fresh_folder(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


class Parts:
    """A table that grows by parts, each written once into a folder of its own; filters on ``by`` prune folders, so a
    round neither rewrites nor re-plans what earlier rounds have written."""

    def __init__(self, spark: SparkSession, name: str, by: str, kind: str = "int"):
        self.spark, self.by, self.kind, self.path, self.schema = spark, by, kind, fresh_folder(spark, name), None

    def add(self, df: DataFrame, value: int) -> DataFrame:
        """Writes the rows of one part and returns them."""
        rows = df.drop(self.by)
        self.schema = rows.schema if self.schema is None else self.schema
        folder = f"{self.path}/{self.by}={value}"
        rows.write.parquet(folder)
        return self.spark.read.schema(self.schema).parquet(folder).withColumn(self.by, F.lit(value).cast(self.kind))

    def all(self) -> DataFrame:
        fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in self.schema)
        return self.spark.read.schema(f"{fields}, `{self.by}` {self.kind}").parquet(self.path)


def bucketed(df: DataFrame, key: str, name: str) -> DataFrame:
    """The same rows as a table bucketed by ``key``: a join on it leaves this side where it lies, however often it is
    joined.  The table is temporary like staged files and is dropped when Python ends.  Where the catalog takes no tables
    the rows are staged plainly, which gives the same results with a shuffle a join."""
    spark = df.sparkSession
    n = shuffle_partitions(spark)
    table = f"walk_{name}_{uuid.uuid4().hex[:12]}"
    path = fresh_folder(spark, name)
    try:
        df.repartition(n, key).write.bucketBy(n, key).sortBy(key).option("path", path).format("parquet").saveAsTable(table)
    except Exception:  # a fault of the data comes up again here
        return staged(df, name)
    atexit.register(_drop, spark, table)
    return spark.table(table)


def _drop(spark: SparkSession, table: str) -> None:
    try:
        if spark.sparkContext._jsc is not None:
            spark.sql(f"DROP TABLE IF EXISTS {table}")
    except Exception:  # the session has ended, and a catalog in memory with it
        pass


def shuffle_partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))
