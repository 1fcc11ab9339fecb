"""Tables in the folder that driver and executors share: they cut lineage and survive lost executors."""

from __future__ import annotations

import gc
import tempfile
import uuid
from collections.abc import Iterable

from pyspark.sql import DataFrame, SparkSession


def shared_root(spark: SparkSession) -> str:
    """The folder named in spark.checkpoint.dir; a local one only where none is set and Spark is local."""
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not root:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        root = "file://" + tempfile.mkdtemp(prefix="cellbalance-")
        spark.sparkContext.setCheckpointDir(root)
    return root


def fresh_path(spark: SparkSession, kind: str = "table") -> str:
    return f"{shared_root(spark)}/{kind}-{uuid.uuid4().hex}"


def written(df: DataFrame) -> DataFrame:
    """df as a table in the shared folder: rereads neither lineage nor cache."""
    path = fresh_path(df.sparkSession)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def gathered(parts: Iterable[DataFrame]) -> DataFrame:
    """Tables of one schema, made and written one behind the other into one table. Spark deletes the shuffles
    of a part when their plan is garbage, so that is collected in between: parts do not add up on disk."""
    path = None
    for df in parts:
        spark, schema, path = df.sparkSession, df.schema, path or fresh_path(df.sparkSession)
        released(spark)
        df.write.mode("append").parquet(path)
        del df
    released(spark)
    return spark.read.schema(schema).parquet(path)


def released(spark: SparkSession) -> None:
    """Let the driver's cleaner delete shuffle files of finished steps."""
    gc.collect()
    spark._jvm.System.gc()


def dropped(df: DataFrame) -> None:
    """Delete a written table that no later step reads."""
    spark = df.sparkSession
    for f in df.inputFiles()[:1]:
        path = spark._jvm.org.apache.hadoop.fs.Path(f).getParent()
        path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def cut_lineage(df: DataFrame) -> DataFrame:
    """Reliable checkpoint in the shared folder."""
    sc = df.sparkSession.sparkContext
    if not sc.getCheckpointDir():
        sc.setCheckpointDir(shared_root(df.sparkSession))
    return df.checkpoint()
