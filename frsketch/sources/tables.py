"""Reading inputs and keeping sketches."""

from __future__ import annotations

import tempfile

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from frsketch.params import FrsParams


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read(spark: SparkSession, path: str, kind: str = "parquet", schema: T.StructType | str | None = None, **options) -> DataFrame:
    """parquet, orc, csv or json; text formats need a schema, so nothing is inferred by a second pass."""
    if kind in ("csv", "json") and schema is None:
        raise ValueError(f"{kind} needs a schema")
    reader = spark.read.format(kind).options(**options)
    return (reader.schema(schema) if schema is not None else reader).load(path)


def shared_dir(spark: SparkSession) -> str:
    """The session's ``spark.checkpoint.dir``; a temporary folder where it is unset (tests)."""
    got = spark.sparkContext.getConf().get("spark.checkpoint.dir", None) or spark.conf.get("spark.checkpoint.dir", None)
    if not got:
        got = "file://" + tempfile.mkdtemp(prefix="frsketch-")
        spark.conf.set("spark.checkpoint.dir", got)
    return got.rstrip("/")


def save_sketch(sk: DataFrame, path: str, params: FrsParams, partition_by: list[str] | None = None, mode: str = "overwrite") -> None:
    """Long sketches as Parquet, clustered by bucket, with the parameters as columns of constant value."""
    out = sk
    for name, value in params.tag().items():
        out = out.withColumn(f"_{name}", F.lit(value))
    writer = out.sortWithinPartitions("bucket").write.mode(mode)
    (writer.partitionBy(*partition_by) if partition_by else writer).parquet(path)


def load_sketch(spark: SparkSession, path: str, params: FrsParams) -> DataFrame:
    """A saved sketch; raises where it was built with other parameters."""
    df = spark.read.parquet(path)
    tag = params.tag()
    row = df.select(*[f"_{n}" for n in tag]).limit(1).collect()
    if row and row[0].asDict() != {f"_{n}": v for n, v in tag.items()}:
        raise ValueError(f"{path} was built with {row[0].asDict()}")
    return df.drop(*[f"_{n}" for n in tag]).withMetadata("reg", {"frs": tag})
