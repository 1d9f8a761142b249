"""The shared folder for tables that cut a lineage, and its cleaning."""

from __future__ import annotations

import atexit
import tempfile
import uuid

from py4j.protocol import Py4JError
from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``. Only a local session, whose
    executors are this very process, may do without; one is then made and set. Raises on a cluster."""
    at = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not at:
        master = spark.sparkContext.master
        if not (master == "local" or master.startswith("local[")):
            raise RuntimeError("spark.checkpoint.dir must name a folder that driver and executors share")
        at = f"file://{tempfile.mkdtemp(prefix='sparkspan-')}"
        spark.sparkContext.setCheckpointDir(at)
    return at.rstrip("/")


class Workspace:
    """Written tables in a folder of their own below the shared one. They survive lost executors and cut the
    lineage. ``drop`` removes a table that no later step reads, ``clear`` all of them, which also
    happens when the driver's program ends: results are read from them until then."""

    def __init__(self, spark: SparkSession, name: str = "run"):
        self.spark, self.base, self.n = spark, f"{shared_dir(spark)}/sparkspan/{name}-{uuid.uuid4().hex}", 0
        atexit.register(self.clear)

    def save(self, df: DataFrame) -> DataFrame:
        self.n += 1
        path = f"{self.base}/{self.n}"
        df.write.mode("overwrite").parquet(path)
        out = self.spark.read.schema(df.schema).parquet(path)
        out._at = path
        return out

    def drop(self, df: DataFrame) -> None:
        self._delete(df._at)

    def clear(self) -> None:
        atexit.unregister(self.clear)
        try:
            self._delete(self.base)
        except (AttributeError, Py4JError, OSError):  # the session has ended before
            pass

    def _delete(self, at: str) -> None:
        path = self.spark.sparkContext._jvm.org.apache.hadoop.fs.Path(at)
        path.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def shuffled_bytes(spark: SparkSession) -> int | None:
    """Bytes that finished stages of this session have written to shuffles, from the status store; None
    where there is none to ask."""
    try:
        sc, jvm = spark.sparkContext, spark.sparkContext._jvm
        none = jvm.java.util.ArrayList()
        stages = sc._jsc.sc().statusStore().stageList(none, False, False, sc._gateway.new_array(jvm.double, 0), none)
        return sum(stages.apply(i).shuffleWriteBytes() for i in range(stages.size()))
    except (AttributeError, Py4JError):
        return None
