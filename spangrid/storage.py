"""Tables written to cut lineage."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share, as the session names it. Where none is named, a session on one machine gets a temporary one,
    and any other is told to name one."""
    at = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir", None)
    if not at:
        if not spark.sparkContext.master.split("[")[0] == "local":
            raise ValueError("spark.checkpoint.dir must name a folder that the driver and all executors share")
        at = tempfile.mkdtemp(prefix="spangrid-")
        spark.conf.set("spark.checkpoint.dir", at)
    return at


def written(df: DataFrame, label: str, by: str | None = None) -> DataFrame:
    """df written once to the shared folder and read from there; in folders by a column, if one is named."""
    spark = df.sparkSession
    at = f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"
    (df.write.partitionBy(by) if by else df.write).parquet(at)
    out = spark.read.schema(df.schema).parquet(at)
    out._spangrid_at = at
    return out


def forget(*tables: DataFrame) -> None:
    """Deletes what written() has written, once nothing reads it any more."""
    for t in tables:
        at = getattr(t, "_spangrid_at", None)
        if at:
            spark = t.sparkSession
            path = spark._jvm.org.apache.hadoop.fs.Path(at)
            path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)
