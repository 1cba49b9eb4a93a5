"""Outputs: JSON lines for evaluation, CSV sheets for audit, partitioned Parquet, a graph bucketed by head and by tail."""

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def write_jsonl(df: DataFrame, path: str, *, by: tuple[str, ...] = ()) -> None:
    writer = df.write.mode("overwrite")
    (writer.partitionBy(*by) if by else writer).json(path)


def write_audit_csv(df: DataFrame, path: str) -> None:
    """Nested columns as JSON text, so that a sheet can hold them."""
    flat = df.select(*[F.to_json(c).alias(c) if t.startswith(("struct", "array", "map")) else F.col(c) for c, t in df.dtypes])
    flat.write.mode("overwrite").option("header", True).option("quoteAll", True).csv(path)


def write_partitioned(df: DataFrame, path: str, *by: str) -> None:
    df.write.mode("overwrite").partitionBy(*by).parquet(path)


def write_kg_bucketed(kg: DataFrame, table: str, *, buckets: int = 8) -> None:
    """Two copies, so that expansion along either direction joins without moving the edges."""
    kg.write.mode("overwrite").bucketBy(buckets, "h").sortBy("h").saveAsTable(f"{table}_by_head")
    kg.write.mode("overwrite").bucketBy(buckets, "t").sortBy("t").saveAsTable(f"{table}_by_tail")


def quality_gate(df: DataFrame, score: str, least: float) -> DataFrame:
    """Rows whose score is known and at least ``least``."""
    return df.filter(F.col(score) >= least)
