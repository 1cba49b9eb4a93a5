"""Answer selection over a candidate model (q_id, answer, p): sampling, voting, debate, reflection.

All queries go together; q_id is part of every key. Ties are settled by count, mass and answer, so results never depend on partitioning.
"""

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from graftmill.functions.hashing import hash_uniform

TEMPERATURE, TOP_P = 0.8, 0.85


def nucleus(cands: DataFrame, *, temperature: float = TEMPERATURE, top_p: float = TOP_P) -> DataFrame:
    """q_id, answer, p: tempered, the least set of likeliest answers whose mass reaches top_p, renormalised."""
    x = cands.withColumn("w", F.pow("p", F.lit(1 / temperature)))
    x = x.withColumn("w", F.col("w") / F.sum("w").over(Window.partitionBy("q_id")))
    order = Window.partitionBy("q_id").orderBy(F.desc("w"), "answer")
    x = x.withColumn("before", F.coalesce(F.sum("w").over(order.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0))).filter(F.col("before") < top_p)
    return x.select("q_id", "answer", (F.col("w") / F.sum("w").over(Window.partitionBy("q_id"))).alias("p"))


def draw(cands: DataFrame, *, draws: int, seed: int = 7) -> DataFrame:
    """q_id, draw, answer, p: hashed draws from each query's distribution."""
    order = Window.partitionBy("q_id").orderBy(F.desc("p"), "answer")
    cum = cands.withColumn("hi", F.sum("p").over(order.rowsBetween(Window.unboundedPreceding, 0)))
    cum = cum.withColumn("lo", F.col("hi") - F.col("p")).withColumn("last", F.lead("answer").over(order).isNull())
    u = hash_uniform("q_id", "draw", seed=seed)
    return cum.withColumn("draw", F.explode(F.sequence(F.lit(1), F.lit(draws)))).filter((u >= F.col("lo")) & ((u < F.col("hi")) | F.col("last"))).select("q_id", "draw", "answer", "p")


def vote(drawn: DataFrame) -> DataFrame:
    """q_id, answer, votes: most votes, then mass, then the smaller answer."""
    n = drawn.groupBy("q_id", "answer").agg(F.count(F.lit(1)).alias("votes"), F.sum("p").alias("mass"))
    w = Window.partitionBy("q_id").orderBy(F.desc("votes"), F.desc("mass"), "answer")
    return n.withColumn("k", F.row_number().over(w)).filter("k = 1").select("q_id", "answer", "votes")


def self_consistency(cands: DataFrame, *, draws: int = 5, seed: int = 7) -> DataFrame:
    return vote(draw(cands, draws=draws, seed=seed))


def views(cands: DataFrame, agents: int, seed: int = 7) -> DataFrame:
    """agent, q_id, answer, p: each agent misses a hashed third of the candidates (never its last one)."""
    u = hash_uniform("q_id", "answer", "agent", seed=f"view{seed}")
    x = cands.withColumn("agent", F.explode(F.sequence(F.lit(0), F.lit(agents - 1)))).withColumn("seen", u >= 1 / 3)
    return x.withColumn("any", F.max("seen").over(Window.partitionBy("q_id", "agent"))).filter("seen or not any").select("agent", "q_id", "answer", "p")


def best(cands: DataFrame, *keys: str) -> DataFrame:
    w = Window.partitionBy(*keys).orderBy(F.desc("p"), "answer")
    return cands.withColumn("k", F.row_number().over(w)).filter("k = 1").drop("k")


def debate(cands: DataFrame, *, agents: int = 3, rounds: int = 3, seed: int = 7) -> DataFrame:
    """q_id, answer, rounds: every agent proposes its best; a round lets each switch to the rival with the best evidence if that beats its own.

    The referee ends when all agree, or after the last round takes the answer with the most summed evidence.
    """
    state = best(views(cands, agents, seed), "agent", "q_id").withColumn("rounds", F.lit(0))
    for _ in range(rounds):
        rival = Window.partitionBy("q_id").orderBy(F.desc("p"), "answer")
        whole = rival.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
        top, mass = F.first("answer").over(whole), F.first("p").over(whole)
        split = F.min("answer").over(Window.partitionBy("q_id")) != F.max("answer").over(Window.partitionBy("q_id"))
        x = state.withColumn("top", top).withColumn("mass", mass).withColumn("split", split)
        switch = F.col("split") & (F.col("mass") > F.col("p"))
        state = x.select("agent", "q_id", F.when(switch, F.col("top")).otherwise(F.col("answer")).alias("answer"), F.when(switch, F.col("mass")).otherwise(F.col("p")).alias("p"), (F.col("rounds") + F.col("split").cast("int")).alias("rounds"))
    total = state.groupBy("q_id", "answer").agg(F.sum("p").alias("p"), F.max("rounds").alias("rounds"))
    return best(total, "q_id").select("q_id", "answer", "rounds")


def self_reflect(cands: DataFrame, *, max_rounds: int = 3, conf_stop: float = 0.6, seed: int = 7) -> DataFrame:
    """q_id, answer, rounds: one agent starts from its own view and revises to the next better candidate while it is not confident.

    A confident first answer is never revised, right or wrong: the effect of getting stuck.
    """
    state = best(views(cands, 1, seed), "q_id").select("q_id", F.col("answer").alias("own"), F.col("p").alias("own_p"), F.lit(0).alias("rounds"))
    for _ in range(max_rounds):
        better = cands.join(state, "q_id").filter((F.col("p") > F.col("own_p")) & (F.col("own_p") < conf_stop))
        w = Window.partitionBy("q_id").orderBy("p", "answer")  # the critique raises the answer one step
        step = better.withColumn("k", F.row_number().over(w)).filter("k = 1").select("q_id", F.col("answer").alias("new"), F.col("p").alias("new_p"))
        state = state.join(step, "q_id", "left").select("q_id", F.coalesce("new", "own").alias("own"), F.coalesce("new_p", "own_p").alias("own_p"), (F.col("rounds") + F.col("new").isNotNull().cast("int")).alias("rounds"))
    return state.select("q_id", F.col("own").alias("answer"), "rounds")


def greedy(cands: DataFrame) -> DataFrame:
    return best(cands, "q_id").select("q_id", "answer")


def accuracy(answers: DataFrame, gold: DataFrame) -> DataFrame:
    """n, correct, accuracy (%) over all gold queries; an unanswered query is wrong."""
    j = gold.join(answers.select("q_id", "answer"), "q_id", "left")
    right = F.coalesce(F.col("answer") == F.col("gold"), F.lit(False))
    return j.agg(F.count(F.lit(1)).alias("n"), F.count_if(right).alias("correct"), F.round(100.0 * F.count_if(right) / F.count(F.lit(1)), 6).alias("accuracy"))
