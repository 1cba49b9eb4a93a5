"""Completion of a graph: missing tails by relation prior, by votes of shared attributes, by mined composition rules."""

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from graftmill.functions.hashing import hash32


def hide(kg: DataFrame, *, one_in: int = 10, seed: str = "hide") -> tuple[DataFrame, DataFrame]:
    """(rest, probes): a hashed tenth of the triples becomes probes (h, r, t_gold)."""
    hidden = hash32("h", "r", "t", seed=seed) % one_in == 0
    return kg.filter(~hidden), kg.filter(hidden).select("h", "r", F.col("t").alias("t_gold"))


def ranked(scored: DataFrame, k: int) -> DataFrame:
    w = Window.partitionBy("h", "r").orderBy(F.desc("score"), "t")
    return scored.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= k)


def by_prior(kg: DataFrame, probes: DataFrame, *, k: int = 10) -> DataFrame:
    """h, r, t, score, rank: the k most frequent tails of the relation."""
    n = kg.groupBy("r", "t").agg(F.count(F.lit(1)).cast("double").alias("score"))
    w = Window.partitionBy("r").orderBy(F.desc("score"), "t")
    top = n.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= k)
    return probes.select("h", "r").distinct().join(top, "r").select("h", "r", "t", "score", "rank")


def relations_by_kind(kg: DataFrame, probes: DataFrame) -> DataFrame:
    """h, t, r, score, rank: for (h, ?, t) the relations by how often they join the kinds of the two ends."""
    ends = lambda df: df.withColumn("kh", F.substring_index("h", ":", 1)).withColumn("kt", F.substring_index("t", ":", 1))
    n = ends(kg).groupBy("kh", "kt", "r").agg(F.count(F.lit(1)).cast("double").alias("score"))
    w = Window.partitionBy("kh", "kt").orderBy(F.desc("score"), "r")
    return ends(probes.select("h", "t").distinct()).join(n.withColumn("rank", F.row_number().over(w)), ["kh", "kt"]).select("h", "t", "r", "score", "rank")


def counts_by_attribute(kg: DataFrame, asked: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(h, r2, t2 of every triple; r, t, r2, t2, n): how many heads with the attribute (r2, t2) have the tail, for the relations in asked. Heads are never paired with heads."""
    attr = kg.select("h", F.col("r").alias("r2"), F.col("t").alias("t2"))
    goal = kg.join(asked.select("r").distinct(), "r", "left_semi")
    return attr, goal.join(attr, "h").filter("r <> r2").groupBy("r", "t", "r2", "t2").agg(F.count(F.lit(1)).alias("n"))


def votes(kg: DataFrame, asked: DataFrame) -> DataFrame:
    """h, r, t, score: tails for the asked (h, r) by heads that share an attribute, weighted by how often the attribute goes with the tail."""
    attr, n = counts_by_attribute(kg, asked)
    size = n.groupBy("r", "r2", "t2").agg(F.sum("n").alias("all"))
    share = n.join(size, ["r", "r2", "t2"]).select("r", "t", "r2", "t2", (F.col("n") / F.col("all")).alias("p"))
    return asked.select("h", "r").distinct().join(attr, "h").filter("r <> r2").join(share, ["r", "r2", "t2"]).groupBy("h", "r", "t").agg(F.round(F.sum("p"), 6).alias("score"))


def by_neighbours(kg: DataFrame, probes: DataFrame, *, k: int = 10) -> DataFrame:
    """The k tails of each probe (h, r, ?) with most votes."""
    return ranked(votes(kg, probes), k)


def heads_by_neighbours(kg: DataFrame, probes: DataFrame, *, k: int = 10) -> DataFrame:
    """r, t, h, score, rank: for (?, r, t) the k heads with most votes for t, among the entities of the relation's kinds that lack the relation.

    probes: r, t. A tail for which no such head has a vote gets no row.
    """
    kind = F.substring_index("h", ":", 1).alias("kind")
    want = probes.select("r", "t").distinct()
    kinds = kg.join(want.select("r").distinct(), "r", "left_semi").select("r", kind).distinct()
    lack = kg.select("h", kind).distinct().join(kinds, "kind").select("h", "r").join(kg.select("h", "r"), ["h", "r"], "left_anti")
    w = Window.partitionBy("r", "t").orderBy(F.desc("score"), "h")
    return votes(kg, lack).join(want, ["r", "t"]).withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= k).select("r", "t", "h", "score", "rank")


def by_vectors(kg: DataFrame, probes: DataFrame, *, k: int = 10) -> DataFrame:
    """Tails by the cosine of two sparse vectors over attributes: the head's own, and the sum of those of the heads that have the tail."""
    attr, n = counts_by_attribute(kg, probes)
    norm = n.groupBy("r", "t").agg(F.sum(F.col("n") * F.col("n")).alias("nn"))
    mine = probes.select("h", "r").distinct().join(attr, "h").filter("r <> r2")
    own = mine.groupBy("h", "r").agg(F.count(F.lit(1)).alias("m"))
    dot = mine.join(n, ["r", "r2", "t2"]).groupBy("h", "r", "t").agg(F.sum("n").alias("dot"))
    s = dot.join(norm, ["r", "t"]).join(own, ["h", "r"]).select("h", "r", "t", F.round(F.col("dot") / F.sqrt((F.col("nn") * F.col("m")).cast("double")), 9).alias("score"))
    return ranked(s, k)


def mine_rules(kg: DataFrame, *, min_support: int = 2, min_conf: float = 0.5) -> DataFrame:
    """r1, r2, r3, support, n_paths, conf: h -r1-> m -r2-> t implies h -r3-> t.

    Confidence counts only paths whose head has r3 at all.
    """
    a = kg.select("h", F.col("r").alias("r1"), F.col("t").alias("m"))
    b = kg.select(F.col("h").alias("m"), F.col("r").alias("r2"), "t")
    two = a.join(b, "m").select("h", "r1", "r2", "t").distinct()
    heads = kg.select("h", F.col("r").alias("r3")).distinct()
    base = two.join(heads, "h").groupBy("r1", "r2", "r3").agg(F.count(F.lit(1)).alias("n_paths"))
    hit = two.join(kg.select("h", F.col("r").alias("r3"), "t"), ["h", "t"]).groupBy("r1", "r2", "r3").agg(F.count(F.lit(1)).alias("support"))
    out = base.join(hit, ["r1", "r2", "r3"]).withColumn("conf", F.round(F.col("support") / F.col("n_paths"), 6))
    return out.filter((F.col("support") >= min_support) & (F.col("conf") >= min_conf))


def by_rules(kg: DataFrame, probes: DataFrame, rules: DataFrame, *, k: int = 10) -> DataFrame:
    """Tails that a rule reaches, by the best confidence. Rules are as many as triples of relation names: broadcast-sized by the optimizer's check."""
    a = kg.select("h", F.col("r").alias("r1"), F.col("t").alias("m"))
    b = kg.select(F.col("h").alias("m"), F.col("r").alias("r2"), "t")
    goal = probes.select("h", F.col("r").alias("r3")).distinct()
    s = goal.join(a, "h").join(b, "m").join(rules.select("r1", "r2", "r3", "conf"), ["r1", "r2", "r3"]).groupBy("h", F.col("r3").alias("r"), "t").agg(F.max("conf").alias("score"))
    return ranked(s, k)


def ranking_metrics(probes: DataFrame, answers: DataFrame, *, ks=(1, 3, 10)) -> DataFrame:
    """r, n, hits_at_k..., mrr over probes; an unanswered probe counts as a miss."""
    a = answers.select("h", "r", F.col("t").alias("t_gold"), "rank")
    j = probes.join(a, ["h", "r", "t_gold"], "left")
    hits = [F.round(F.avg((F.coalesce("rank", F.lit(10**6)) <= k).cast("double")), 6).alias(f"hits_{k}") for k in ks]
    return j.groupBy("r").agg(F.count(F.lit(1)).alias("n"), *hits, F.round(F.avg(F.coalesce(1.0 / F.col("rank"), F.lit(0.0))), 6).alias("mrr"))
