"""Text fragments that state facts of the tables, with slips, and the ways to read triples out of them.

Every order gives one fragment: a sentence that places its customer in a nation. A hashed share of the fragments has a slip, the same for
every method that reads them: an unknown nation, head and tail exchanged, names in another spelling, another wording of the relation, or a
wrong nation that looks right.
"""

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graftmill.functions.hashing import hash32, hash_uniform
from graftmill.sources.tables import load

from .build import kind_of

#: Upper ends of the shares of each slip among hashed numbers in [0, 1); the rest has none.
SLIPS = {"unknown": 0.15, "flipped": 0.27, "spelling": 0.39, "wording": 0.51, "wrong": 0.75}
STATEMENT = r"^(\S+) ([a-z ]+) (\S+)\.$"


def spelled(entity):
    """kind:key as KIND#key."""
    return F.concat(F.upper(kind_of(entity)), F.lit("#"), F.substring_index(entity, ":", -1))


def fragments(spark: SparkSession, sf_dir: str) -> DataFrame:
    """frag_id, q_id (the customer it belongs to), text, slip."""
    c = load(spark, sf_dir, "customer").select(F.col("c_custkey").alias("o_custkey"), "c_nationkey")
    x = load(spark, sf_dir, "orders").select("o_orderkey", "o_custkey").join(c, "o_custkey")
    u = hash_uniform("o_orderkey", seed="slip")
    slip = F.lit("none")
    for name, end in reversed(SLIPS.items()):
        slip = F.when(u < end, name).otherwise(slip)
    n = F.col("c_nationkey")
    wrong = (n + 1 + hash32("o_orderkey", seed="wrong") % 24) % 25
    x = x.withColumn("slip", slip).withColumn("h", F.concat(F.lit("customer:"), "o_custkey"))
    x = x.withColumn("t", F.concat(F.lit("nation:"), F.when(F.col("slip") == "unknown", n + 100).when(F.col("slip") == "wrong", wrong).otherwise(n)))
    is_ = lambda s: F.col("slip") == s
    h = F.when(is_("flipped"), F.col("t")).when(is_("spelling"), spelled(F.col("h"))).otherwise(F.col("h"))
    t = F.when(is_("flipped"), F.col("h")).when(is_("spelling"), spelled(F.col("t"))).otherwise(F.col("t"))
    text = F.concat(F.concat_ws(" ", h, F.when(is_("wording"), "lives near").otherwise("in nation"), t), F.lit("."))
    return x.select(F.col("o_orderkey").cast("long").alias("frag_id"), F.col("o_custkey").cast("long").alias("q_id"), text.alias("text"), "slip")


def aliases(kg: DataFrame) -> DataFrame:
    """alias, canonical of every entity of a graph."""
    return kg.select(F.explode(F.array("h", "t")).alias("canonical")).distinct().select(spelled(F.col("canonical")).alias("alias"), "canonical")


def stated(frags: DataFrame) -> DataFrame:
    """frag_id, q_id, h, r, t as the sentences say it: the pattern extractor."""
    parts = [F.regexp_extract("text", STATEMENT, i).alias(n) for i, n in ((1, "h"), (2, "r"), (3, "t"))]
    return frags.select("frag_id", "q_id", *parts).filter("h <> ''").withColumn("r", F.regexp_replace("r", " ", "_"))


def cooccurring(frags: DataFrame, kg: DataFrame, schema: DataFrame) -> DataFrame:
    """frag_id, q_id, h, r, t: known entities that a sentence names together, with the relation that the schema has for their kinds."""
    nodes = kg.select(F.explode(F.array("h", "t")).alias("e")).distinct()
    named = frags.select("frag_id", "q_id", F.explode(F.split(F.regexp_replace("text", r"\.$", ""), " ")).alias("e")).join(nodes, "e", "left_semi").distinct()
    a, b = named.select("frag_id", "q_id", F.col("e").alias("h")), named.select("frag_id", F.col("e").alias("t"))
    rel = F.broadcast(schema.groupBy("domain", "range").agg(F.min("relation").alias("r")))  # a few rows
    both = a.join(b, "frag_id").filter("h <> t").withColumn("domain", kind_of(F.col("h"))).withColumn("range", kind_of(F.col("t")))
    return both.join(rel, ["domain", "range"]).select("frag_id", "q_id", "h", "r", "t")
