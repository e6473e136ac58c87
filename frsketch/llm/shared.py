"""Tables that cut lineage, kept in the folder that every executor sees; memory of the Python workers."""

from __future__ import annotations

import ctypes
import gc
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

CACHE_BYTES = 48 << 20
BATCH_BYTES = 4 << 20


def shared_dir(spark: SparkSession) -> str:
    """The session's ``spark.checkpoint.dir``. Where it is unset a temporary folder serves if driver and
    executors are one process (tests); a cluster without a shared folder is an error."""
    got = spark.sparkContext.getConf().get("spark.checkpoint.dir", None) or spark.conf.get("spark.checkpoint.dir", None)
    if not got:
        master = spark.sparkContext.master
        if master != "local" and not master.startswith("local["):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        got = "file://" + tempfile.mkdtemp(prefix="frsketch-")
        spark.conf.set("spark.checkpoint.dir", got)
    return got.rstrip("/")


def stored(df: DataFrame, name: str) -> DataFrame:
    """``df`` written once as Parquet in the shared folder and read back: a lost executor costs no
    recomputation, and the plan starts anew."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def drop_stored(df: DataFrame) -> None:
    """Deletes the files behind a ``stored`` table that no later plan reads."""
    spark = df.sparkSession
    jvm = spark.sparkContext._jvm
    for f in df.inputFiles()[:1]:
        parent = jvm.org.apache.hadoop.fs.Path(f).getParent()
        parent.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(parent, True)


def release(spark: SparkSession) -> None:
    """Between stages: the driver drops what no plan refers to any more, shuffle files included, and the executors'
    JVMs return the heap that they do not use, which the Python workers beside them may need."""
    gc.collect()
    give_back()
    spark.sparkContext._jvm.System.gc()
    n = spark.sparkContext.defaultParallelism
    spark.range(0, n, 1, n).select(F.java_method(F.lit("java.lang.System"), F.lit("gc"))).toDF("x").write.format("noop").mode("overwrite").save()


def texts(docs: DataFrame) -> DataFrame:
    """``docs``, with Arrow batches to Python workers bounded in bytes from now on (a run-time setting of the
    session, kept where it is set already): rows are counted in thousands, and texts may be long."""
    conf = docs.sparkSession.conf
    if conf.get("spark.sql.execution.arrow.maxBytesPerBatch", None) is None:
        conf.set("spark.sql.execution.arrow.maxBytesPerBatch", str(BATCH_BYTES))
    return docs


def unused(name: str, columns: list[str]) -> str:
    """``name``, with as many underscores before it as keep it apart from ``columns``."""
    taken = {c.lower() for c in columns}
    while name.lower() in taken:
        name = "_" + name
    return name


class Cache(dict):
    """A worker's cache that starts anew rather than outgrow ``limit`` bytes: keys are counted by their length,
    each entry by ``cost`` besides. It changes speed alone."""

    def __init__(self, cost: int, limit: int = CACHE_BYTES):
        super().__init__()
        self.cost, self.limit, self.used = cost, limit, 0

    def lacking(self, keys) -> list:
        """The distinct ``keys`` that the caller has to add now; all others are there."""
        new = [k for k in keys if k not in self]
        need = sum(map(len, new)) + self.cost * len(new)
        if self.used + need > self.limit and len(self):
            self.clear()
            new = list(keys)
            need = sum(map(len, new)) + self.cost * len(new)
        self.used += need
        return new

    def clear(self) -> None:
        super().clear()
        self.used = 0


def give_back() -> None:
    """Freed memory returns to the system at the end of a task, since idle workers live on."""
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):
        pass  # another C library
