"""Typed access to the given tables, temporary views, and a shared scratch folder for written intermediate results."""

import uuid

from pyspark.sql import DataFrame, SparkSession

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    if name not in TABLES:
        raise ValueError(f"unknown table {name}")
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def register_all(spark: SparkSession, sf_dir: str, prefix: str = "") -> None:
    for name in TABLES:
        load(spark, sf_dir, name).createOrReplaceTempView(prefix + name)


def scratch(spark: SparkSession, what: str) -> str:
    """A new folder below the checkpoint folder of the session (or of its context), else below the warehouse."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if base is None:
        given = spark.sparkContext._jsc.sc().getCheckpointDir()
        base = given.get() if given.isDefined() else spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_scratch"
    return f"{base.rstrip('/')}/{what}-{uuid.uuid4().hex}"


def stored(df: DataFrame, what: str = "step") -> DataFrame:
    """Write to the shared scratch folder and read again: ends the lineage at files that outlive executors."""
    path = scratch(df.sparkSession, what)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
