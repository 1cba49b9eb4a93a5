"""Connected components of an edge table by alternating large-star and small-star steps."""

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common


def signature(edges: DataFrame) -> tuple:
    r = edges.agg(F.count(F.lit(1)).alias("n"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")).alias("s")).first()
    return r["n"], r["s"]


#: Neighbours of a centre that one task may get.
STAR = 1000


def connected_components(edges: DataFrame, *, max_rounds: int = 60) -> DataFrame:
    """(node, comp) for every node of the edges (u, v), both bigint; comp is the smallest node of the component.

    Every round is an aggregate and a join on the node, written to the shared folder; the least neighbour of a star centre with
    more than STAR neighbours reaches them by a broadcast of bounded size.
    """
    cur = common.stored(edges.filter("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct(), "edges")
    seen = signature(cur)
    for _ in range(max_rounds):
        both = cur.unionByName(cur.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m"), F.count(F.lit(1)).alias("c")).select("u", F.least("u", "m").alias("m"), "c")
        large = common.met(both, low, ["u"], "c", 2 * seen[0], STAR).filter("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").select(F.explode(F.array(F.struct("u", F.col("m").alias("v")), F.struct(F.col("v").alias("u"), F.col("m").alias("v")))).alias("e")).select("e.u", "e.v").filter("u <> v").distinct()
        cur = common.stored(small, "edges")
        now = signature(cur)
        if now == seen:
            break
        seen = now
    else:
        raise RuntimeError("components did not settle")
    leaves = cur.groupBy("u").agg(F.min("v").alias("comp")).withColumnRenamed("u", "node")
    centres = cur.select(F.col("v").alias("node"), F.col("v").alias("comp")).distinct()
    return leaves.unionByName(centres)
