"""Verification of candidate triples, the refinement loop, degradation of graphs, and grounded instruction samples."""

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from graftmill.functions.hashing import hash32, hash_uniform
from graftmill.sources.tables import stored

from .build import kind_of

CHECKS = ("format", "entity", "relation", "type", "functional", "membership", "loop")


def verify(triples: DataFrame, *, kg: DataFrame, schema: DataFrame, checks=CHECKS, min_votes: int | None = None, support: DataFrame | None = None) -> DataFrame:
    """triples with ``reasons`` (sorted) and ``ok``. triples: id, h, r, t (and votes for min_votes).

    format      a part is null or blank            entity      a part is not an entity of the graph
    relation    the relation is not in the schema  type        the kinds do not fit the relation
    functional  the graph has another tail for a functional relation
    membership  neither the triple nor a path of two edges from head to tail is in the graph
    loop        head and tail are the same         votes       fewer than min_votes agents agree
    text        support (h, r, t) does not hold it
    The schema is a few rows and is broadcast; the graph is joined by key.
    """
    cols = triples.columns
    s = F.broadcast(schema.groupBy("relation").agg(F.collect_set(F.struct("domain", "range")).alias("__types"), F.bool_or("functional").alias("__functional")))
    x = triples.join(s, triples["r"] == s["relation"], "left")
    reasons = []
    blank = lambda c: F.coalesce(F.trim(F.col(c)), F.lit("")) == ""
    if "format" in checks:
        reasons.append(F.when(blank("h") | blank("r") | blank("t"), "format"))
    if "loop" in checks:
        reasons.append(F.when(F.col("h") == F.col("t"), "loop"))
    if "relation" in checks:
        reasons.append(F.when(F.col("__types").isNull(), "relation"))
    if "type" in checks:
        reasons.append(F.when(F.col("__types").isNotNull() & ~F.exists("__types", lambda p: (p["domain"] == kind_of(F.col("h"))) & (p["range"] == kind_of(F.col("t")))), "type"))
    if "entity" in checks:
        nodes = kg.select(F.explode(F.array("h", "t")).alias("node")).distinct()
        for c in ("h", "t"):
            x = x.join(nodes.select(F.col("node").alias(f"__{c}")), F.col(c) == F.col(f"__{c}"), "left")
        reasons.append(F.when(F.col("__h").isNull() | F.col("__t").isNull(), "entity"))
    if "functional" in checks or "membership" in checks:
        tails = kg.groupBy("h", "r").agg(F.min("t").alias("__t1"), F.count(F.lit(1)).alias("__nt"))
        x = x.join(tails.withColumnRenamed("h", "__kh").withColumnRenamed("r", "__kr"), (F.col("h") == F.col("__kh")) & (F.col("r") == F.col("__kr")), "left")
    if "functional" in checks:
        reasons.append(F.when(F.col("__functional") & (F.col("__nt") == 1) & (F.col("__t1") != F.col("t")), "functional"))
    if "membership" in checks:
        own = kg.select(F.col("h").alias("__mh"), F.col("r").alias("__mr"), F.col("t").alias("__mt")).distinct()
        x = x.join(own, (F.col("h") == F.col("__mh")) & (F.col("r") == F.col("__mr")) & (F.col("t") == F.col("__mt")), "left")
        wanted = triples.select("h", "t").distinct()
        first = kg.select(F.col("h"), F.col("t").alias("m"))
        two = wanted.join(first, "h").join(kg.select(F.col("h").alias("m"), F.col("t").alias("t2")), "m").filter("t = t2").select(F.col("h").alias("__ph"), F.col("t").alias("__pt")).distinct()
        x = x.join(two, (F.col("h") == F.col("__ph")) & (F.col("t") == F.col("__pt")), "left")
        reasons.append(F.when(F.col("__mh").isNull() & F.col("__ph").isNull(), "membership"))
    if support is not None:
        sup = support.select(F.col("h").alias("__sh"), F.col("r").alias("__sr"), F.col("t").alias("__st")).distinct()
        x = x.join(sup, (F.col("h") == F.col("__sh")) & (F.col("r") == F.col("__sr")) & (F.col("t") == F.col("__st")), "left")
        reasons.append(F.when(F.col("__sh").isNull(), "text"))
    if min_votes is not None:
        reasons.append(F.when(F.col("votes") < min_votes, "votes"))
    out = x.select(*cols, F.sort_array(F.array_compact(F.array(*reasons))).alias("reasons"))
    return out.withColumn("ok", F.size("reasons") == 0)


def refine(rejected: DataFrame, *, kg: DataFrame, schema: DataFrame, aliases: DataFrame | None = None, round_no: int = 1) -> DataFrame:
    """One refinement of rejected triples: alias, then direction, then relation, then tail; the first that changes something applies.

    A round tries one kind of repair, in this order over the rounds, so that each verdict judges one change.
    """
    cols = [c for c in rejected.columns if c not in ("reasons", "ok")]
    kind = (round_no - 1) % 4
    x = rejected
    if kind == 0 and aliases is not None:
        for c in ("h", "t"):
            a = aliases.select(F.col("alias").alias("__a"), F.col("canonical").alias("__c"))
            x = x.join(a, F.col(c) == F.col("__a"), "left").withColumn(c, F.coalesce("__c", c)).drop("__a", "__c")
    elif kind == 1:
        types = F.broadcast(schema.select(F.col("relation").alias("__r"), F.col("domain").alias("__d"), F.col("range").alias("__g")))
        back = x.join(types, (F.col("r") == F.col("__r")) & (kind_of(F.col("t")) == F.col("__d")) & (kind_of(F.col("h")) == F.col("__g")), "left")
        flip = F.col("__r").isNotNull() & F.array_contains("reasons", "type")
        x = back.withColumn("__h", F.when(flip, F.col("t")).otherwise(F.col("h"))).withColumn("t", F.when(flip, F.col("h")).otherwise(F.col("t"))).withColumn("h", F.col("__h"))
    elif kind == 2:
        types = F.broadcast(schema.groupBy("domain", "range").agg(F.min("relation").alias("__rel")))
        x = x.join(types, (kind_of(F.col("h")) == F.col("domain")) & (kind_of(F.col("t")) == F.col("range")), "left")
        wrong = F.array_contains("reasons", "relation") | F.array_contains("reasons", "type")
        x = x.withColumn("r", F.when(wrong & F.col("__rel").isNotNull(), F.col("__rel")).otherwise(F.col("r")))
    elif kind == 3:
        best = kg.groupBy(F.col("h").alias("__h"), F.col("r").alias("__r")).agg(F.min("t").alias("__best"))
        x = x.join(best, (F.col("h") == F.col("__h")) & (F.col("r") == F.col("__r")), "left").withColumn("t", F.coalesce("__best", "t"))
    return x.select(*cols)


def refine_until_valid(triples: DataFrame, *, kg: DataFrame, schema: DataFrame, aliases: DataFrame | None = None, max_rounds: int = 8, checks=CHECKS) -> tuple[DataFrame, DataFrame]:
    """(verified triples with the round that accepted them, log (round, n_in, n_ok, n_rejected)).

    Only rejected triples go round again; after max_rounds the rest is dropped, so the loop always ends.
    """
    spark = triples.sparkSession
    todo, accepted, log = triples, None, []
    for k in range(max_rounds + 1):
        judged = stored(verify(todo, kg=kg, schema=schema, checks=checks), "verdicts")
        n = {r["ok"]: r["count"] for r in judged.groupBy("ok").count().collect()}
        log.append((k, sum(n.values()), n.get(True, 0), n.get(False, 0)))
        good = judged.filter("ok").drop("reasons", "ok").withColumn("round", F.lit(k))
        accepted = good if accepted is None else accepted.unionByName(good)
        if not n.get(False) or k == max_rounds:
            break
        todo = refine(judged.filter("not ok"), kg=kg, schema=schema, aliases=aliases, round_no=k + 1)
    return accepted, spark.createDataFrame(log, "round int, n_in long, n_ok long, n_rejected long")


def corrupt(triples: DataFrame, *, rate: float, part: str = "t", seed: int = 7) -> DataFrame:
    """triples with ``is_valid``: a hashed share has its head, relation or tail replaced by another value of the same relation's pool.

    The pool of a relation is numbered by a window over its distinct values; the replacement is the next value after the own one, in a ring, so
    it always differs where the pool has two values.
    """
    pool = triples.select("r", F.col(part).alias("own")).distinct() if part != "r" else triples.select(F.lit("").alias("r"), F.col("r").alias("own")).distinct()
    w = Window.partitionBy("r").orderBy("own")
    whole = Window.partitionBy("r")
    ring = pool.select("r", "own", F.coalesce(F.lead("own").over(w), F.min("own").over(whole)).alias("other"))
    ring = ring.withColumnRenamed("r", "__r")
    hit = hash_uniform("h", "r", "t", seed=f"corrupt{seed}") < rate
    x = triples.withColumn("__hit", hit).join(ring, (F.col(part) == F.col("own")) & ((F.col("__r") == "") if part == "r" else (F.col("__r") == F.col("r"))), "left")
    new = F.when(F.col("__hit"), F.col("other")).otherwise(F.col(part))
    return x.withColumn("is_valid", ~F.col("__hit") | (new == F.col(part))).withColumn(part, new).drop("__hit", "__r", "own", "other")


def thin(triples: DataFrame, *, keep: float, seed: int = 7) -> DataFrame:
    """A hashed share of the triples; a smaller share is a subset of a larger one."""
    return triples.filter(hash_uniform("h", "r", "t", seed=f"thin{seed}") < keep)


def instructions_from_kg(triples: DataFrame, *, tasks=("rte", "kgc", "qa")) -> DataFrame:
    """task, key, instruction, input, output of grounded samples.

    rte: a rendered sentence for each head, out come its triples as JSON; kgc: a triple with one part masked (by hash), out comes the part;
    qa: a question for the tail, out come the tail and the triple as evidence.
    """
    out = []
    sentence = F.concat_ws(" ", "h", F.regexp_replace("r", "_", " "), "t")
    if "rte" in tasks:
        rows = F.sort_array(F.collect_list(F.struct("h", "r", "t")))
        g = triples.groupBy("h").agg(rows.alias("z"), F.array_join(F.sort_array(F.collect_list(sentence)), ". ").alias("input"))
        out.append(g.select(F.lit("rte").alias("task"), F.col("h").alias("key"), F.lit("Extract the triples.").alias("instruction"), "input", F.to_json("z").alias("output")))
    if "kgc" in tasks:
        k = (hash32("h", "r", "t", seed="mask") % 3).cast("int")
        masked = F.concat_ws(" | ", F.when(k == 0, "?").otherwise(F.col("h")), F.when(k == 1, "?").otherwise(F.col("r")), F.when(k == 2, "?").otherwise(F.col("t")))
        answer = F.when(k == 0, F.col("h")).when(k == 1, F.col("r")).otherwise(F.col("t"))
        out.append(triples.select(F.lit("kgc").alias("task"), F.concat_ws("|", "h", "r", "t").alias("key"), F.lit("Fill in the missing part.").alias("instruction"), masked.alias("input"), answer.alias("output")))
    if "qa" in tasks:
        q = F.concat(F.lit("What does "), F.col("h"), F.lit(" have as "), F.regexp_replace("r", "_", " "), F.lit("?"))
        out.append(triples.select(F.lit("qa").alias("task"), F.concat_ws("|", "h", "r", "t").alias("key"), F.lit("Answer from the graph.").alias("instruction"), q.alias("input"), F.concat(F.col("t"), F.lit(" because "), sentence).alias("output")))
    made = out[0]
    for x in out[1:]:
        made = made.unionByName(x)
    return made
