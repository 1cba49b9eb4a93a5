"""SQL surface: temporary functions, views, a path table function, approximate statistics."""

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf

from graftmill.sources.tables import register_all

from .scores import lcs_words


def register(spark: SparkSession, sf_dir: str | None = None) -> None:
    """cosine_at_least(d, na2, nb2, num, den), hash32(text), lcs_words(a, b), expand_paths(path, max_len) and, with sf_dir, a view for each table."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION cosine_at_least(d BIGINT, a BIGINT, b BIGINT, num INT, den INT) RETURNS BOOLEAN RETURN d > 0 AND den * den * d * d >= num * num * a * b")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION hash32(x STRING) RETURNS BIGINT RETURN cast(conv(substring(md5(x), 1, 8), 16, 10) AS BIGINT)")
    spark.udf.register("lcs_words", lcs_words)
    spark.udtf.register("expand_paths", expand_paths())
    if sf_dir is not None:
        register_all(spark, sf_dir)


def expand_paths():
    """Table function: every prefix of a path up to max_len nodes, as (length, prefix)."""

    class ExpandPaths:
        def eval(self, path: list, max_len: int):
            for n in range(1, min(len(path or ()), max_len) + 1):
                yield n, path[:n]

    return udtf(ExpandPaths, returnType="length int, prefix array<string>")


def approx_stats(df: DataFrame, col: str, number: str) -> DataFrame:
    """Sketched distinct count and percentiles: mergeable, one pass."""
    return df.agg(F.approx_count_distinct(col).alias("n_distinct"), F.hll_sketch_estimate(F.hll_sketch_agg(col)).alias("n_hll"), F.percentile_approx(number, [0.1, 0.5, 0.9], 1000).alias("percentiles"))


def lateral_topk(spark: SparkSession, groups: str, rows: str, key: str, order: str, k: int) -> DataFrame:
    """For each row of the view ``groups`` the k rows of the view ``rows`` with the same key, by ``order``."""
    return spark.sql(f"SELECT g.{key}, t.* EXCEPT ({key}) FROM {groups} g, LATERAL (SELECT * FROM {rows} r WHERE r.{key} = g.{key} ORDER BY {order} LIMIT {k}) t")
