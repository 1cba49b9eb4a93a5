"""Students without a graph on conversations, mixed training arms, path search, and single-query reports."""

from pyspark.sql import functions as F

from graftmill.functions import scores as S
from graftmill.functions import text as T
from graftmill.operators import corpus as C
from graftmill.operators.kg import build as K
from graftmill.operators.kg import local as L
from graftmill.operators.student.nearest import nearest
from graftmill.sources.tables import load, stored

from .corpus import TURNS_SQL
from .graph import kg_sql
from .registry import query
from .theory import PW


def split_pairs(spark, sf):
    """key, instruction, input, output, split of the conversation pairs; a conversation is never parted."""
    q = C.split_items(C.qa_from_turns(load(spark, sf, "conversations")), "turn", group="conv_id")
    return q.select((F.col("conv_id") * 1000 + F.col("turn")).alias("key"), "instruction", "input", "output", "split")


SPLIT = "CASE WHEN ('0x' || substr(md5('7:' || conv_id), 1, 8))::UBIGINT / 4294967296.0 < 0.6 THEN 'train' WHEN ('0x' || substr(md5('7:' || conv_id), 1, 8))::UBIGINT / 4294967296.0 < 0.6 + 0.2 THEN 'test' ELSE 'val' END"
NEAR_SQL = f"""WITH {TURNS_SQL}, p AS (SELECT conv_id * 1000 + turn AS key, input, output, {SPLIT} AS split FROM pairs),
w AS (SELECT DISTINCT key, split, unnest({PW.format('input')}) AS w FROM p), n AS (SELECT key, count(*) AS n FROM w GROUP BY key),
s AS (SELECT a.key, b.key AS demo, count(*) AS shared FROM w a JOIN w b ON a.w = b.w AND a.split = 'test' AND b.split = 'train' GROUP BY ALL),
k AS (SELECT s.*, row_number() OVER (PARTITION BY s.key ORDER BY round(shared / sqrt(na.n * nb.n), 9) DESC, demo) AS rank FROM s JOIN n na ON na.key = s.key JOIN n nb ON nb.key = demo)"""


@query("encoder_nearest", NEAR_SQL + " SELECT key, demo FROM k WHERE rank = 1")
def encoder_nearest(spark, sf):
    return nearest(split_pairs(spark, sf), 1).select("key", "demo")


@query("in_context_demos", NEAR_SQL + " SELECT key, demo, rank::INT AS rank FROM k WHERE rank <= 3")
def in_context_demos(spark, sf):
    return nearest(split_pairs(spark, sf), 3)


def answers(items, method: str, near=None):
    """key, hyp of the test items for a text baseline; near: the twenty nearest training items of each, if they are there already."""
    test, train = items.filter("split = 'test'"), items.filter("split = 'train'")
    if method == "zero-shot":  # the head of the question
        return test.select("key", F.element_at(F.split("input", r"[.!?\n]"), 1).alias("hyp"))
    if method == "few-shot":  # one fixed demonstration for all
        fixed = train.agg(F.min_by("output", "key").alias("hyp"))
        return test.select("key").crossJoin(F.broadcast(fixed))
    if method == "instruction-tuned":  # the nearest answer among items with the same instruction
        near = (nearest(items, 20) if near is None else near).join(items.select(F.col("key").alias("demo"), F.col("instruction").alias("i2"), "output"), "demo").join(test.select("key", "instruction"), "key")
        near = near.withColumn("r", F.struct((F.col("i2") != F.col("instruction")).cast("int"), "rank"))
        return near.groupBy("key").agg(F.min_by("output", "r").alias("hyp"))
    return (nearest(items, 1) if near is None else near.filter("rank = 1")).join(items.select(F.col("key").alias("demo"), "output"), "demo").select("key", F.col("output").alias("hyp"))


@query("text_benchmark")
def text_benchmark(spark, sf):
    """BLEU, ROUGE-L and the judge stand-in of the text baselines on held-out turns."""
    items = stored(split_pairs(spark, sf), "items")
    near, out = stored(nearest(items, 20), "nearest"), None
    for m in ("zero-shot", "few-shot", "encoder", "instruction-tuned"):
        p = items.filter("split = 'test'").join(answers(items, m, near), "key", "left").select(F.col("key").alias("id"), F.coalesce("hyp", F.lit("")).alias("hyp"), F.col("output").alias("ref"))
        p = stored(p, "answers")
        grams = stored(S.gram_matches_by_row(p), "grams")
        one = S.bleu_sentence(p, matches=grams).agg(F.round(F.avg("bleu"), 6).alias("bleu")).crossJoin(S.rouge_l(p).agg(F.round(100 * F.avg("f1"), 6).alias("rouge_l"))).crossJoin(S.rubric_judge(p, matches=grams).agg(F.round(F.avg("judge"), 6).alias("judge")))
        one = one.select(F.lit(m).alias("method"), "bleu", "rouge_l", "judge", F.lit(True).alias("stand_in"))
        out = one if out is None else out.unionByName(one)
    return out


@query("mixed_training")
def mixed_training(spark, sf):
    """Human, generated and mixed arms: how many test words each training arm covers."""
    human = split_pairs(spark, sf)
    made = load(spark, sf, "documents").select(F.col("text").alias("input"))
    test = human.filter("split = 'test'").select(F.explode(T.words(F.col("output"))).alias("w")).distinct()
    own = human.filter("split = 'train'").select(F.explode(T.words(F.col("output"))).alias("w")).distinct()
    gen = made.select(F.explode(T.words(F.col("input"))).alias("w")).distinct()
    total = test.agg(F.count(F.lit(1)).alias("n"))
    out = None
    for name, vocab in (("human", own), ("generated", gen), ("mixed", own.union(gen).distinct())):
        one = test.join(vocab, "w", "left_semi").agg(F.count(F.lit(1)).alias("hit")).crossJoin(total).select(F.lit(name).alias("arm"), "n", F.round(100.0 * F.col("hit") / F.col("n"), 6).alias("coverage"))
        out = one if out is None else out.unionByName(one)
    return out


@query("path_search", f"WITH {kg_sql(K.PLACES)} SELECT a.h, b.t AS answer FROM kg a JOIN kg b ON b.h = a.t WHERE a.h LIKE 'customer:%' AND b.r = 'in_region'")
def path_search(spark, sf):
    """Multi-step reasoning over paths: enumerate two-step paths of each customer, keep those that end in a region."""
    kg = K.kg_from_tables(spark, sf, K.PLACES)
    q = load(spark, sf, "customer").select(F.col("c_custkey").cast("long").alias("q_id"), F.concat(F.lit("customer:"), "c_custkey").alias("entity"))
    p = L.paths(kg, q, max_len=2).filter(F.element_at("rels", -1) == "in_region")
    return p.select(F.element_at("path", 1).alias("h"), F.element_at("path", -1).alias("answer"))


@query("emergency_case")
def emergency_case(spark, sf):
    """One supplier's question with its evidence path, answer and scores of the candidates."""
    kg = K.kg_from_tables(spark, sf, K.PLACES)
    q = spark.createDataFrame([(1, "supplier:1")], "q_id long, entity string")
    p = L.paths(kg, q, max_len=2)
    return p.select("q_id", F.array_join("path", " > ").alias("evidence"), F.array_join("rels", " > ").alias("relations"), F.element_at("path", -1).alias("answer"), F.round(1.0 / F.size("rels"), 6).alias("score"))
