"""Written tables that cut lineage, in the folder that all executors share."""

from __future__ import annotations

import atexit
import gc
import tempfile
import uuid

from py4j.protocol import Py4JError
from pyspark.errors import PySparkException
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: A side is broadcast only if it was counted to hold at most so many rows, in tables of at most so many bytes; beyond that the join is shuffled.
BROADCAST_ROWS = 50_000
BROADCAST_BYTES = 32 << 20


class Scratch:
    """A folder of written tables, removed when the program ends (results are read lazily until then).

    It lies in ``spark.checkpoint.dir`` of the session. Only where that is unset on a local master (tests on one
    machine) a temporary folder is made; on a cluster an unset folder is an error.
    """

    def __init__(self, spark: SparkSession, tag: str) -> None:
        self.spark = spark
        root = spark.conf.get("spark.checkpoint.dir", None)
        if not root:
            master = spark.conf.get("spark.master", "local")
            if not master.startswith("local") or master.startswith("local-cluster"):
                raise ValueError(f"spark.checkpoint.dir is unset: executors of {master} share no folder")
            root = f"file://{tempfile.gettempdir()}/ripplegraph-scratch"
        self.root = f"{root.rstrip('/')}/{tag}-{uuid.uuid4().hex}"
        self._round = 0
        self.tables: list[str] = []
        atexit.register(self._leave)

    def path(self, name: str) -> str:
        return f"{self.root}/{name}"

    def save(self, df: DataFrame, name: str | None = None) -> DataFrame:
        """Write ``df`` once and return a frame that reads what was written."""
        if name is None:
            self._round += 1
            name = f"step{self._round}"
        df.write.mode("overwrite").parquet(self.path(name))
        return self.spark.read.schema(df.schema).parquet(self.path(name))

    def bucketed(self, df: DataFrame, column: str) -> DataFrame:
        """``df`` as a table bucketed by ``column`` into as many buckets as a shuffle has partitions: joins on it move the other side only."""
        n = int(self.spark.conf.get("spark.sql.shuffle.partitions"))
        name = f"ripple_{uuid.uuid4().hex}"
        df.repartition(n, column).write.bucketBy(n, column).sortBy(column).option("path", self.path(name)).saveAsTable(name)
        self.tables.append(name)
        return self.spark.table(name)

    def drop(self, name: str = "") -> None:
        """Delete one table, or all of them."""
        jvm = self.spark._jvm
        path = jvm.org.apache.hadoop.fs.Path(self.path(name) if name else self.root)
        path.getFileSystem(jvm.org.apache.hadoop.conf.Configuration() if self.spark._jsc is None else self.spark._jsc.hadoopConfiguration()).delete(path, True)

    def _leave(self) -> None:
        try:
            for name in self.tables:
                self.spark.sql(f"DROP TABLE IF EXISTS {name}")
            self.drop()
        except (Py4JError, PySparkException, OSError, AttributeError):  # the JVM has gone before us: nothing can be deleted through it
            return

    def release(self) -> None:
        """Let Spark remove the shuffle files of stages whose results are written."""
        gc.collect()
        self.spark._jvm.System.gc()


def bounded_broadcast(df: DataFrame, rows: int) -> DataFrame:
    """``df`` marked for broadcast if its counted rows and the plan's bytes stay within the bounds; else as it is, for a shuffled join."""
    if rows > BROADCAST_ROWS:
        return df
    size = df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()
    return F.broadcast(df) if int(str(size)) <= BROADCAST_BYTES else df
