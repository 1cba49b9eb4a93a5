"""The propose-verify-refine episode as a decision process over all queries at once.

State of a query: how many of its candidate triples are proposed, verified and rejected, and what it has tried. Policy: a column expression from
the state to an action. Action: an agent's function from the queries that chose it to candidate triples, which the verifier judges. Transition: the
verdicts change the counts. Reward: triples newly verified less ``cost`` for each one judged.
"""

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from graftmill.operators.kg import fragments as N
from graftmill.operators.kg import verify as V
from graftmill.sources.tables import stored

CHECKS = ("format", "entity", "relation", "type", "functional", "loop")


@dataclass(frozen=True)
class World:
    """What the agents may look at: the graph without the hidden triples, its schema and spellings, and the text fragments."""

    kg: DataFrame
    schema: DataFrame
    frags: DataFrame
    aliases: DataFrame


@dataclass(frozen=True)
class Agent:
    """A role: what it is told, and what it does: (world, queries (q_id), rejected (q_id, agent, h, r, t, tries, reasons, ok), the numbers of tries among them) to (q_id, agent, h, r, t, tries)."""

    name: str
    identity: str
    act: Callable[[World, DataFrame, DataFrame, list[int]], DataFrame]


def read_statements(world: World, queries: DataFrame, rejected: DataFrame, tried: list[int]) -> DataFrame:
    return N.stated(world.frags.join(queries, "q_id", "left_semi")).select("q_id", F.lit("relations").alias("agent"), "h", "r", "t", F.lit(0).alias("tries"))


def read_entities(world: World, queries: DataFrame, rejected: DataFrame, tried: list[int]) -> DataFrame:
    return N.cooccurring(world.frags.join(queries, "q_id", "left_semi"), world.kg, world.schema).select("q_id", F.lit("entities").alias("agent"), "h", "r", "t", F.lit(0).alias("tries"))


def recall_graph(world: World, queries: DataFrame, rejected: DataFrame, tried: list[int]) -> DataFrame:
    """What the graph itself says of the entity that a query is about."""
    about = world.frags.join(queries, "q_id", "left_semi").select("q_id", F.concat(F.lit("customer:"), "q_id").alias("h")).distinct()
    return about.join(world.kg, "h").select("q_id", F.lit("graph").alias("agent"), "h", "r", "t", F.lit(0).alias("tries"))


def repair(world: World, queries: DataFrame, rejected: DataFrame, tried: list[int]) -> DataFrame:
    """The distiller mends one thing at a time: spelling, direction, relation, tail, by how often a triple was tried."""
    own = rejected.join(queries, "q_id", "left_semi")
    out = None
    for k in tried:
        one = V.refine(own.filter(F.col("tries") == k), kg=world.kg, schema=world.schema, aliases=world.aliases, round_no=k + 1)
        one = one.select("q_id", "agent", "h", "r", "t", F.lit(k + 1).alias("tries"))
        out = one if out is None else out.unionByName(one)
    return out


AGENTS = {a.name: a for a in (
    Agent("relations", "You state how two entities of a passage are related, one triple a line.", read_statements),
    Agent("entities", "You name the entities of a passage that the graph knows and pair those that stand together.", read_entities),
    Agent("graph", "You recall what the graph holds about the entities of the question.", recall_graph),
    Agent("distiller", "You mend rejected triples one change at a time.", repair),
)}


def default_policy(s: DataFrame) -> Column:
    """Read first, then ask the graph, then mend while there is something to mend; stop when nothing is left to try."""
    return (F.when(~F.col("has_relations"), "relations").when(~F.col("has_graph"), "graph").when(F.col("open") > 0, "distiller").otherwise("stop"))


def thorough_policy(s: DataFrame) -> Column:
    """Also lets the entity agent read."""
    return F.when(~F.col("has_relations"), "relations").when(~F.col("has_entities"), "entities").when(~F.col("has_graph"), "graph").when(F.col("open") > 0, "distiller").otherwise("stop")


def run_episode(world: World, queries: DataFrame, *, policy=default_policy, max_steps: int = 8, cost: float = 0.1, checks=CHECKS) -> tuple[DataFrame, DataFrame]:
    """(verified candidates q_id, agent, h, r, t, tries; log step, action, n_queries, n_judged, n_ok, n_rejected, reward).

    Candidates that several fragments or agents state are kept as often. Ends when every query stops, or after max_steps; what is rejected four times is dropped.
    """
    spark = queries.sparkSession
    queries = queries.select("q_id").distinct()
    seen = ("relations", "entities", "graph")
    state = queries.select("q_id", *[F.lit(False).alias(f"has_{a}") for a in seen], F.lit(0).cast("long").alias("open"))
    verified, rejected, log, tried = None, None, [], set()
    empty = spark.createDataFrame([], "q_id long, agent string, h string, r string, t string, tries int, reasons array<string>, ok boolean")
    for step in range(max_steps):
        acted = stored(state.withColumn("action", policy(state)), "state")
        chosen = {r["action"]: r["count"] for r in acted.groupBy("action").count().collect()}  # as many rows as actions
        if not set(chosen) - {"stop"}:
            break
        pool = empty if rejected is None else rejected
        made, kept = None, pool
        for action in sorted(set(chosen) - {"stop"}):
            own = acted.filter(F.col("action") == action).select("q_id")
            one = AGENTS[action].act(world, own, pool, sorted(tried))
            made = one if made is None else made.unionByName(one)
            if action == "distiller":
                kept = kept.join(own, "q_id", "left_anti")
        judged = stored(V.verify(made, kg=world.kg, schema=world.schema, checks=checks), "verdicts")
        n = judged.agg(F.count(F.lit(1)).alias("n"), F.count_if("ok").alias("ok"), F.collect_set(F.when(~F.col("ok") & (F.col("tries") < 4), F.col("tries"))).alias("tries")).first()
        tried = (set() if set(chosen) <= {"distiller", "stop"} else tried) | set(n["tries"])
        log.append((step, "+".join(sorted(set(chosen) - {"stop"})), sum(v for k, v in chosen.items() if k != "stop"), n["n"], n["ok"], n["n"] - n["ok"], round(n["ok"] - cost * n["n"], 6)))
        good = judged.filter("ok").drop("reasons", "ok")
        verified = good if verified is None else verified.unionByName(good)
        rejected = stored(kept.unionByName(judged.filter("not ok and tries < 4").select(*kept.columns)), "rejected")
        left = rejected.groupBy("q_id").agg(F.count(F.lit(1)).alias("n"))
        marks = [(F.col(f"has_{a}") | (F.col("action") == a)).alias(f"has_{a}") for a in seen]
        state = acted.join(left, "q_id", "left").select("q_id", *marks, F.coalesce("n", F.lit(0)).cast("long").alias("open"))
    names = "step int, action string, n_queries long, n_judged long, n_ok long, n_rejected long, reward double"
    return (verified if verified is not None else empty.drop("reasons", "ok")), spark.createDataFrame(log, names)
