"""Mixing sources to target weights by Poisson replication (DataFrame functions only).

Every document draws its number of copies from a Poisson distribution whose mean is the
repetition rate that its source needs to reach its target share. The draw inverts the
distribution function at a uniform number hashed from (seed, doc_id, part), so a rerun, another
partitioning or a lost executor gives the same corpus. Copies are exploded where the document
lies and then dealt out by a hashed key, once.

Defined results: null source is a source of its own; null text is carried along; a repeated row
draws the same count as its twin (same doc_id); an empty table gives an empty table; an input
column named ``copy`` or ``shuffle_key`` is replaced by the operator's own.
"""

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import common

#: A mean above this is drawn as the sum of several Poisson numbers of smaller mean: exp(-mean) stays far from 0.
PART_MEAN = 16.0
#: Largest count with a probability above 2**-53 for a mean of PART_MEAN, generously.
PART_MAX = 96
#: The table of rates is broadcast only up to this many sources; beyond, the join is salted and shuffled.
BROADCAST_SOURCES = 10_000
SALTS = 64


def uniform(*parts: Column) -> Column:
    """52 bits of an md5 as a number in [0, 1)."""
    return F.conv(F.substring(F.md5(F.concat_ws("|", *parts)), 1, 13), 16, 10).cast("long") / F.lit(float(2**52))


def source_rates(docs: DataFrame, weights: dict | None, epochs: float, key: str, own: str) -> DataFrame:
    """(source, rate, parts, cdf): mean copies of a document of each source, and the inverted table; ``own`` begins the names of columns that docs lacks."""
    sizes = docs.groupBy(key).agg(F.count(F.lit(1)).alias(f"{own}n"))
    if weights is None:
        sizes = sizes.withColumn(f"{own}w", F.lit(1.0))
    else:
        items = [x for k, v in weights.items() for x in (F.lit(k), F.lit(float(v)))]
        sizes = sizes.withColumn(f"{own}w", F.coalesce(F.create_map(*items)[F.col(key)], F.lit(0.0)) if items else F.lit(0.0))
    total = sizes.agg(F.sum(f"{own}n").alias("n"), F.sum(f"{own}w").alias("w")).first()  # two numbers
    rate = F.lit(float(epochs)) * F.col(f"{own}w") / F.lit(total["w"]) * F.lit(total["n"]) / F.col(f"{own}n") if total["w"] else F.lit(0.0)
    out = sizes.select(F.col(key), rate.alias(f"{own}rate"))
    out = out.withColumn(f"{own}parts", F.greatest(F.lit(1), F.ceil(F.col(f"{own}rate") / PART_MEAN)).cast("int"))
    mean = F.col(f"{own}rate") / F.col(f"{own}parts")
    step = lambda acc, k: F.struct(
        (acc["p"] * acc["m"] / k).alias("p"), acc["m"].alias("m"),
        F.concat(acc["cdf"], F.array(F.element_at(acc["cdf"], -1) + acc["p"] * acc["m"] / k)).alias("cdf"))
    start = F.struct(F.exp(-mean).alias("p"), mean.alias("m"), F.array(F.exp(-mean)).alias("cdf"))
    cdf = F.aggregate(F.sequence(F.lit(1), F.lit(PART_MAX)), start, step, lambda acc: acc["cdf"])
    return out.withColumn(f"{own}cdf", cdf)


def with_rates(docs: DataFrame, rates: DataFrame, key: str, broadcast_sources: int, own: str) -> DataFrame:
    rates = rates.withColumnRenamed(key, f"{own}key")
    if rates.select(f"{own}key").limit(broadcast_sources + 1).count() <= broadcast_sources:
        return docs.join(F.broadcast(rates), docs[key].eqNullSafe(rates[f"{own}key"]), "left").drop(f"{own}key")
    rates = rates.withColumn(f"{own}salt_r", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    docs = docs.withColumn(f"{own}salt", F.pmod(F.xxhash64("doc_id"), F.lit(SALTS)).cast("int"))
    return docs.join(rates, docs[key].eqNullSafe(rates[f"{own}key"]) & (docs[f"{own}salt"] == rates[f"{own}salt_r"]), "left").drop(f"{own}key", f"{own}salt", f"{own}salt_r")


def mix_sources(docs: DataFrame, weights: dict | None = None, *, epochs: float = 1.0, seed: int = 17, key: str = "source", broadcast_sources: int = BROADCAST_SOURCES) -> DataFrame:
    """The rows of ``docs``, each as often as its Poisson draw says, in a globally hashed order.

    weights: target share of each source (any positive scale; a source not named gets none);
    None gives every source the same share. epochs: expected rows out / rows in.
    Adds ``copy`` (from 1) and ``shuffle_key``; ordering by shuffle_key is the global order, and each
    partition is sorted by it.
    """
    docs = docs.drop("copy", "shuffle_key")
    names = docs.columns
    doc = F.coalesce(F.col("doc_id").cast("string"), F.lit("null"))
    own = common.prefix(docs)
    drawn = with_rates(docs, source_rates(docs, weights, epochs, key, own), key, broadcast_sources, own)
    one = lambda j: F.size(F.filter(F.col(f"{own}cdf"), lambda c: c <= uniform(F.lit(str(seed)), doc, j.cast("string"))))
    count = F.aggregate(F.sequence(F.lit(1), F.col(f"{own}parts")), F.lit(0), lambda acc, j: acc + one(j))
    drawn = drawn.withColumn(f"{own}copies", F.when(F.col(f"{own}rate") > 0, count).otherwise(0)).filter(F.col(f"{own}copies") > 0)
    mixed = drawn.select(*names, F.explode(F.sequence(F.lit(1), F.col(f"{own}copies"))).alias("copy"))
    place = F.conv(F.substring(F.md5(F.concat_ws("|", F.lit(f"order{seed}"), doc, F.col("copy").cast("string"))), 1, 15), 16, 10).cast("long")
    return mixed.withColumn("shuffle_key", place).repartition("shuffle_key").sortWithinPartitions("shuffle_key", "doc_id", "copy")
