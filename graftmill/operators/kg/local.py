"""Query-specific graphs: expansion along association paths, semi-naive, all queries in one batch."""

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from graftmill.sources.tables import stored

from .build import degrees


def adjacency(kg: DataFrame, *, direction: str = "both", hub_cap: int | None = None) -> DataFrame:
    """node, nbr, h, r, t: a step along each triple; a node above hub_cap is reached against an edge but not left against one."""
    out = kg.select(F.col("h").alias("node"), F.col("t").alias("nbr"), "h", "r", "t")
    if direction == "out":
        return out
    back = kg.select(F.col("t").alias("node"), F.col("h").alias("nbr"), "h", "r", "t")
    if hub_cap is not None:
        back = back.join(degrees(kg).filter(F.col("degree") > hub_cap).select("node"), "node", "left_anti")
    return out.unionByName(back)


def local_nodes(kg: DataFrame, seeds: DataFrame, *, direction: str = "both", max_hops: int | None = None, beam: int | None = None, hub_cap: int | None = None, rounds: int = 64) -> DataFrame:
    """q_id, node, hop of every node reached from a query's seeds (q_id, entity).

    Only the last hop's new nodes are expanded. beam keeps that many new nodes of each query and hop: those met by most edges,
    ties by name. Each hop is written to the shared folder.
    """
    step = stored(adjacency(kg, direction=direction, hub_cap=hub_cap).select("node", "nbr"), "adjacency")
    visited = stored(seeds.select("q_id", F.col("entity").alias("node"), F.lit(0).alias("hop")).distinct(), "visited")
    frontier = visited
    for hop in range(1, (max_hops or rounds) + 1):
        met = frontier.join(step, "node").groupBy("q_id", F.col("nbr").alias("node")).agg(F.count(F.lit(1)).alias("n"))
        new = met.join(visited.select("q_id", "node"), ["q_id", "node"], "left_anti")
        if beam is not None:
            w = Window.partitionBy("q_id").orderBy(F.desc("n"), "node")
            new = new.withColumn("k", F.row_number().over(w)).filter(F.col("k") <= beam)
        frontier = stored(new.select("q_id", "node", F.lit(hop).alias("hop")), "frontier")
        if frontier.isEmpty():
            return visited
        visited = visited.unionByName(frontier)
    if max_hops is None:
        raise RuntimeError(f"the expansion goes on after {rounds} hops")
    return visited


def hop_counts(kg: DataFrame, seeds: DataFrame, *, max_hops: int) -> DataFrame:
    """hop, n: nodes reached at each hop from all seeds (q_id, entity; one entity each), along edges in both directions without a cap.

    Seeds with the same neighbours reach the same nodes, so each such group is walked once and counts as often as it has seeds.
    """
    step = adjacency(kg, direction="both", hub_cap=None).select("node", "nbr").filter("node <> nbr").distinct()
    near = seeds.select("q_id", F.col("entity").alias("node")).distinct().join(step, "node").groupBy("q_id").agg(F.sort_array(F.collect_set("nbr")).alias("nbrs"))
    groups = stored(near.groupBy("nbrs").agg(F.min("q_id").alias("q_id"), F.count(F.lit(1)).alias("m")), "groups")
    zero = seeds.select("q_id").distinct().agg(F.count(F.lit(1)).alias("n")).select(F.lit(0).alias("hop"), "n")
    starts = groups.select("q_id", F.explode("nbrs").alias("entity"))
    met = local_nodes(kg, starts, max_hops=max_hops - 1) if max_hops > 1 else starts.select("q_id", F.lit(0).alias("hop"))
    each = met.groupBy("q_id", F.col("hop") + 1).agg(F.count(F.lit(1)).alias("n")).toDF("q_id", "hop", "n")
    rest = each.join(groups.select("q_id", "m"), "q_id").select("hop", (F.col("m") * (F.col("n") - (F.col("hop") == 2).cast("int"))).alias("n"))  # a group comes back to the seed itself in its second hop
    return zero.union(rest).filter("n > 0").groupBy("hop").agg(F.sum("n").alias("n"))


def local_kg(kg: DataFrame, nodes: DataFrame) -> DataFrame:
    """q_id, h, r, t, hop: triples with both ends in the query's nodes; hop is where the triple became known."""
    n = nodes.select("q_id", "node", "hop")
    a = kg.join(n.select("q_id", F.col("node").alias("h"), F.col("hop").alias("hh")), "h")
    return a.join(n.select("q_id", F.col("node").alias("t"), F.col("hop").alias("ht")), ["q_id", "t"]).select("q_id", "h", "r", "t", F.greatest("hh", "ht").alias("hop"))


def paths(kg: DataFrame, seeds: DataFrame, *, max_len: int = 2) -> DataFrame:
    """q_id, path (array of nodes), rels: simple forward paths from the seeds up to max_len edges."""
    cur = seeds.select("q_id", F.array("entity").alias("path"), F.array().cast("array<string>").alias("rels"))
    out = None
    for _ in range(max_len):
        cur = cur.join(kg, F.element_at("path", -1) == kg["h"]).filter(~F.array_contains("path", F.col("t"))).select("q_id", F.concat("path", F.array("t")).alias("path"), F.concat("rels", F.array("r")).alias("rels"))
        out = cur if out is None else out.unionByName(cur)
    return out


def decompose(queries: DataFrame, kg: DataFrame) -> DataFrame:
    """q_id, part_no, part, entity (if the part names one), relations (candidate relations of the entity)."""
    parts = queries.select("q_id", F.posexplode(F.split("query", r"(?i)\s*(?:,|;|\band\b|\?)\s*")).alias("part_no", "part")).filter("trim(part) <> ''")
    named = parts.withColumn("entity", F.regexp_extract("part", r"([a-z]+:\S+)", 1))
    rels = kg.groupBy("h").agg(F.sort_array(F.collect_set("r")).alias("relations"))  # as many as there are relation names
    return named.join(rels, named["entity"] == rels["h"], "left").select("q_id", "part_no", "part", F.nullif("entity", F.lit("")).alias("entity"), "relations")


def consolidate(candidates: DataFrame, known: DataFrame | None = None) -> DataFrame:
    """q_id, h, r, t, n, score: multiset of candidate triples as counts, with the best score; known triples are added with count 0."""
    c = candidates.select("q_id", "h", "r", "t", "score", F.lit(1).alias("one"))
    if known is not None:
        c = c.unionByName(known.select("q_id", "h", "r", "t", F.lit(1.0).alias("score"), F.lit(0).alias("one")))
    return c.groupBy("q_id", "h", "r", "t").agg(F.sum("one").alias("n"), F.max("score").alias("score"))


def multiset_except(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.exceptAll(b)
