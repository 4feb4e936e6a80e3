"""The folder that driver and executors share."""

from __future__ import annotations

import tempfile
from uuid import uuid4

from pyspark.sql import DataFrame, SparkSession


def shared_folder(spark: SparkSession) -> str:
    """``spark.checkpoint.dir``; in local mode, where it is unset, a temporary folder that the session remembers."""
    where = spark.conf.get("spark.checkpoint.dir", None) or spark.conf.get("linkgraph.core.dir", None)
    if not where:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        where = "file://" + tempfile.mkdtemp(prefix="linkgraph-")
        spark.conf.set("linkgraph.core.dir", where)
    return where.rstrip("/")


def written(df: DataFrame) -> DataFrame:
    """The rows as a table in the shared folder: smaller than a checkpoint of them."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/table-{uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)
