"""General relational operators that the methods lean on: as-of, banded and interval joins, top-k, margins, fixpoints."""

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from graftmill.sources.tables import stored


def topk_per_group(df: DataFrame, keys: list[str], order: list[Column], k: int) -> DataFrame:
    return df.withColumn("rank", F.row_number().over(Window.partitionBy(*keys).orderBy(*order))).filter(F.col("rank") <= k)


def topk(df: DataFrame, order: list[Column], k: int) -> DataFrame:
    """The first k rows of a total order: each task keeps k rows, so nothing is sorted as a whole."""
    return df.orderBy(*order).limit(k)


def asof_last(left: DataFrame, right: DataFrame, *, by: str, ts: str, order: str, cols: list[str]) -> DataFrame:
    """left with, for each of ``cols``, the value of the latest right row of the same ``by`` before it (as right_<col>, and right_<ts>).

    One exchange by key: both sides are stacked and the last right value is carried forward. Ties in time go by ``order``.
    """
    names = left.columns
    a = left.select(F.struct(*names).alias("row"), F.col(by).alias("__by"), F.col(ts).alias("__ts"), F.col(order).alias("__o"), F.lit(None).cast(right.select(F.struct(*cols, ts)).dtypes[0][1]).alias("got"))
    b = right.select(F.lit(None).cast(left.select(F.struct(*names)).dtypes[0][1]).alias("row"), F.col(by).alias("__by"), F.col(ts).alias("__ts"), F.col(order).alias("__o"), F.struct(*cols, ts).alias("got"))
    w = Window.partitionBy("__by").orderBy("__ts", "__o").rowsBetween(Window.unboundedPreceding, -1)
    x = a.unionByName(b).withColumn("got", F.last("got", ignorenulls=True).over(w)).filter("row is not null")
    return x.select("row.*", *[F.col(f"got.{c}").alias(f"right_{c}") for c in [*cols, ts]])


def banded_join(a: DataFrame, b: DataFrame, *, by: str, pos: str, width: int) -> DataFrame:
    """Pairs of rows of the same key whose positions differ by less than width: an equi-join on shifted positions."""
    left = a.select(*[F.col(c).alias(f"a_{c}") for c in a.columns]).withColumn("__p", F.explode(F.sequence(F.col(f"a_{pos}") - (width - 1), F.col(f"a_{pos}") + (width - 1))))
    right = b.select(*[F.col(c).alias(f"b_{c}") for c in b.columns])
    return left.join(right, (F.col(f"a_{by}") == F.col(f"b_{by}")) & (F.col("__p") == F.col(f"b_{pos}"))).drop("__p")


def margins(df: DataFrame, dims: list[str], measures: list[Column], kind: str = "cube") -> DataFrame:
    return (df.cube(*dims) if kind == "cube" else df.rollup(*dims)).agg(*measures)


def semi_naive(seed: DataFrame, step, keys: list[str], *, max_iter: int = 50) -> DataFrame:
    """Fixpoint: step(frontier) gives rows; those with new keys are the next frontier. Each round is written to the shared folder."""
    seen = frontier = stored(seed.dropDuplicates(keys), "fixpoint")
    for _ in range(max_iter):
        new = step(frontier).dropDuplicates(keys).join(seen.select(*keys), keys, "left_anti")
        frontier = stored(new, "fixpoint")
        if frontier.isEmpty():
            return seen
        seen = seen.unionByName(frontier)
    raise RuntimeError("no fixpoint within max_iter")


def recursive_sql(spark: SparkSession, sql: str) -> DataFrame:
    return spark.sql(sql)


def bm25(queries: DataFrame, docs: DataFrame, *, k: int = 3, k1: float = 1.2, b: float = 0.75) -> DataFrame:
    """q_id, doc_id, score, rank: retrieval of context fragments by a postings join. queries: q_id, term, docs: doc_id, term (one row each occurrence)."""
    tf = docs.groupBy("doc_id", "term").agg(F.count(F.lit(1)).alias("tf"))
    dl = docs.groupBy("doc_id").agg(F.count(F.lit(1)).alias("dl"))
    stats = dl.agg(F.count(F.lit(1)).alias("n"), F.avg("dl").alias("mean"))
    df = tf.groupBy("term").agg(F.count(F.lit(1)).alias("df"))
    x = queries.select("q_id", "term").distinct().join(df, "term").join(tf, "term").join(dl, "doc_id").crossJoin(F.broadcast(stats))
    w = F.ln(1 + (F.col("n") - F.col("df") + 0.5) / (F.col("df") + 0.5)) * F.col("tf") * (k1 + 1) / (F.col("tf") + k1 * (1 - b + b * F.col("dl") / F.col("mean")))
    s = x.groupBy("q_id", "doc_id").agg(F.round(F.sum(w), 6).alias("score"))
    return topk_per_group(s, ["q_id"], [F.desc("score"), F.col("doc_id")], k)
