"""Work with the session as given: table loading, and lineage cut through the shared checkpoint folder."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def checkpoint_dir(spark: SparkSession) -> str:
    """The cluster's spark.checkpoint.dir if there is one; a folder under the warehouse where none is set, as in tests: an error on a cluster whose warehouse is a local folder."""
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        shared, warehouse = spark.conf.get("spark.checkpoint.dir", None), spark.conf.get("spark.sql.warehouse.dir").rstrip("/")
        if not shared and not sc.master.startswith("local[") and sc.master != "local" and warehouse.startswith(("/", "file:")):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        sc.setCheckpointDir(shared or warehouse + "/_checkpoints")
    return sc.getCheckpointDir()


def shared_folder(spark: SparkSession, name: str) -> str:
    """A new folder's path beside the checkpoints."""
    return f"{checkpoint_dir(spark)}/{name}-{uuid.uuid4()}"


def cut(df: DataFrame) -> DataFrame:
    checkpoint_dir(df.sparkSession)
    return df.checkpoint()


def kept(df: DataFrame) -> DataFrame:
    """The same rows from Parquet beside the checkpoints: compressed, for rows as many as the input's."""
    path = shared_folder(df.sparkSession, "rows")
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def fresh(df: DataFrame) -> DataFrame:
    """The same rows as a plan without estimates. Estimates of joins multiply from round to round of a loop, without bound."""
    spark = df.sparkSession
    return DataFrame(spark._jsparkSession.createDataFrame(df._jdf.javaRDD(), df._jdf.schema()), spark)
