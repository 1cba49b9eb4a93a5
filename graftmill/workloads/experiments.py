"""The method comparison on relational questions: which region does a customer belong to?

Half of the customers' nations are hidden from the graph. Text fragments state them, with slips (operators/kg/fragments.py). A method is a way to get
evidence about a customer from the fragments, the remaining graph, both or neither; it never sees the answer of a held-out question. The same count
students (a large one over the evidence itself, a small one over eight cells of it) learn from each method's evidence on the training customers and are scored on the others,
in all and on the hidden ones alone. No method has a noise rate of its own.
"""

from pyspark.sql import Window
from pyspark.sql import functions as F

from graftmill.functions import scores as S
from graftmill.functions.hashing import hash32, hash_uniform
from graftmill.operators.agents import answers as A
from graftmill.operators.agents import episode as E
from graftmill.operators.kg import build as K
from graftmill.operators.kg import fragments as N
from graftmill.operators.kg import verify as V
from graftmill.operators.theory import information as I
from graftmill.sources.tables import load, stored

from .graph import kg_sql
from .registry import query

TRAIN = 0.6
CELLS = 8
#: Demonstrations of a question in context.
DEMOS = 3


def hidden():
    return (F.col("r") == "in_nation") & F.col("h").startswith("customer:") & (hash32("h", "r", "t", seed="hidden") % 2 == 0)


def world(spark, sf, change=None) -> E.World:
    """What is left of the graph (changed by ``change``), the fragments and the spellings."""
    kg = K.kg_from_tables(spark, sf, K.PLACES).filter(~hidden())
    kg = stored(change(kg) if change else kg, "graph").select("h", "r", "t")
    return E.World(kg, K.kg_schema(spark), N.fragments(spark, sf), N.aliases(kg))


def items(spark, sf):
    """key, y (region), c (segment), gold (nation), train, hidden of every customer that has fragments."""
    c = load(spark, sf, "customer").join(load(spark, sf, "orders").select(F.col("o_custkey").alias("c_custkey")).distinct(), "c_custkey", "left_semi")
    x = c.join(load(spark, sf, "nation"), F.col("n_nationkey") == F.col("c_nationkey"))
    x = x.withColumn("h", F.concat(F.lit("customer:"), "c_custkey")).withColumn("r", F.lit("in_nation")).withColumn("t", F.concat(F.lit("nation:"), "c_nationkey"))
    return x.select(F.col("c_custkey").cast("long").alias("key"), F.col("n_regionkey").cast("string").alias("y"), F.col("c_mktsegment").alias("c"), F.col("t").alias("gold"), (hash_uniform("c_custkey", seed=7) < TRAIN).alias("train"), hidden().alias("hidden"))


# Evidence: (key, z) ------------------------------------------------------------------------------------------------------


def own_statements(w):
    """key, t: what fragments say, as they say it, of the customer itself."""
    return N.stated(w.frags).filter(F.col("h") == F.concat(F.lit("customer:"), "q_id")).select(F.col("q_id").alias("key"), "t", "frag_id")


def most_stated(rows):
    n = rows.groupBy("key", "t").agg(F.count(F.lit(1)).alias("n"))
    return n.groupBy("key").agg(F.min_by("t", F.struct(-F.col("n"), F.col("t"))).alias("z"))


def from_graph(w):
    return w.kg.filter("r = 'in_nation' and h like 'customer:%'").select(F.substring_index("h", ":", -1).cast("long").alias("key"), F.col("t").alias("z"))


def one_rationale(w):
    """A single teacher's rationale: what the first fragment says, unchecked."""
    return N.stated(w.frags).groupBy(F.col("q_id").alias("key")).agg(F.min_by("t", "frag_id").alias("z"))


def verified(w, queries, **options):
    """The acting agents' verified statements about the customer, by how often they are made."""
    good, _ = E.run_episode(w, queries.select(F.col("key").alias("q_id")), **options)
    own = good.filter((F.col("r") == "in_nation") & (F.col("h") == F.concat(F.lit("customer:"), "q_id")))
    return most_stated(own.select(F.col("q_id").alias("key"), "t"))


def voted_candidates(w):
    """q_id, answer, p: shares of the statements about each customer."""
    n = own_statements(w).groupBy(F.col("key").alias("q_id"), F.col("t").alias("answer")).agg(F.count(F.lit(1)).alias("n"))
    return n.select("q_id", "answer", (F.col("n") / F.sum("n").over(Window.partitionBy("q_id"))).alias("p"))


def path_search(cands, kg, *, beam: int = 3):
    """Analyse: the likeliest candidates of each query. Refine: a candidate counts by the paths from it to a region, so that one that leads nowhere falls out."""
    w = Window.partitionBy("q_id").orderBy(F.desc("p"), "answer")
    near = cands.withColumn("k", F.row_number().over(w)).filter(F.col("k") <= beam)
    ends = kg.filter("r = 'in_region'").groupBy(F.col("h").alias("answer")).agg(F.count(F.lit(1)).alias("paths"))
    again = near.join(ends, "answer").withColumn("p", F.col("p") * F.col("paths"))
    return A.best(again, "q_id").select("q_id", "answer")


def answered(a):
    return a.select(F.col("q_id").alias("key"), F.col("answer").alias("z"))


def in_context(x):
    """The commonest region among DEMOS training questions of the same segment; no training."""
    w = Window.partitionBy("c").orderBy(hash32("key", seed="demo"), "key")
    demos = x.filter("train").withColumn("k", F.row_number().over(w)).filter(F.col("k") <= DEMOS)
    n = demos.groupBy("c", "y").agg(F.count(F.lit(1)).alias("n")).groupBy("c").agg(F.min_by("y", F.struct(-F.col("n"), F.col("y"))).alias("z"))
    return x.join(n, "c").select("key", "z")


GRAPH_ARMS = ("none", "global only", "local only", "both")
SINGLE = ("zero-shot", "vanilla", "in-context", "step-by-step", "full loop")
MULTI = ("self-reflection", "self-consistency", "debate", "path search", "full loop")


def evidence(spark, sf, methods, w=None, x=None):
    """method, key, z: one stored table for all methods."""
    w, x = w or world(spark, sf), x if x is not None else items(spark, sf)
    cands = stored(voted_candidates(w), "candidates") if set(methods) & set(MULTI) else None
    ways = {
        "none": lambda: x.select("key", F.lit("-").alias("z")), "zero-shot": lambda: x.select("key", F.lit("-").alias("z")), "vanilla": lambda: x.select("key", F.col("c").alias("z")), "in-context": lambda: in_context(x),
        "global only": lambda: from_graph(w), "local only": lambda: most_stated(own_statements(w)), "both": lambda: verified(w, x), "full loop": lambda: verified(w, x), "step-by-step": lambda: one_rationale(w),
        "self-reflection": lambda: answered(A.self_reflect(cands)), "self-consistency": lambda: answered(A.self_consistency(cands)), "debate": lambda: answered(A.debate(cands)), "path search": lambda: answered(path_search(cands, w.kg)),
    }
    out = None
    for m in methods:
        one = x.select("key").join(ways[m](), "key", "left").select(F.lit(m).alias("method"), "key", F.coalesce("z", F.lit("none")).alias("z"))
        out = one if out is None else out.unionByName(one)
    return stored(out, "evidence")


# Students -----------------------------------------------------------------------------------------------------------------


def judged(ev, x):
    """method, student, key, y, hidden, gold, z, map_y, hit, log for the held-out questions. One model fits all: method and student are part of the state."""
    rows = ev.join(x, "key").withColumn("student", F.explode(F.array(F.lit("large"), F.lit("small"))))
    cell = F.when(F.col("student") == "small", (hash32("z", seed="cell") % CELLS).cast("string")).otherwise(F.col("z"))
    rows = rows.withColumn("s", F.concat_ws("|", "method", "student", cell)).withColumn("row", F.concat_ws("|", "method", "student", "key"))
    model = I.CountPredictor.fit(rows.filter("train and method <> 'in-context'"), "y", "s")
    test = rows.filter("not train")
    got = model.evaluate(test, "y", "s", "row").withColumnRenamed("key", "row")
    out = test.join(got, "row")
    plain = F.col("method") == "in-context"
    guess = F.when(plain, F.col("z")).otherwise(F.col("map_y"))
    return out.select("method", "student", "key", "y", "hidden", "gold", "z", guess.alias("map_y"), (guess == F.col("y")).cast("double").alias("hit"), F.when(~plain, F.col("log")).alias("log"))


def summary(j, *, name: str = "method"):
    return j.groupBy(F.col("method").alias(name), "student").agg(F.count(F.lit(1)).alias("n"), F.round(100 * F.avg("hit"), 6).alias("accuracy"), F.round(100 * F.avg(F.when(F.col("hidden"), F.col("hit"))), 6).alias("accuracy_hidden"), F.round(-F.avg("log"), 6).alias("nll"))


def texts(j):
    """id, hyp, ref and the group of the answers as sentences."""
    say = lambda z, y: F.concat(F.lit("the customer is placed in "), z, F.lit(" which is a part of region:"), y)
    return j.select("method", "student", F.concat_ws("|", "method", "student", "key").alias("id"), say(F.col("z"), F.col("map_y")).alias("hyp"), say(F.col("gold"), F.col("y")).alias("ref"), "hit", (F.col("z") == F.col("gold")).cast("double").alias("grounded"))


def overlap(j, *, name: str = "method"):
    """BLEU-4, ROUGE-1, ROUGE-2, ROUGE-L, the expert's share of right answers and the judge, in one pass each."""
    p = stored(texts(j), "answers")
    one = p.select("id", "method", "student", "hit", "grounded").join(S.bleu_sentence(p), "id")
    for n in (1, 2):
        one = one.join(S.rouge_n(p, n).select("id", F.col("f1").alias(f"rouge_{n}")), "id", "left")
    one = one.join(S.rouge_l(p).select("id", F.col("f1").alias("rouge_l")), "id").join(S.rubric_judge(p).select("id", "judge"), "id")
    pct = lambda c: F.round(100 * F.avg(c), 4).alias(c)
    return one.groupBy(F.col("method").alias(name), "student").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("bleu"), 4).alias("bleu_4"), pct("rouge_1"), pct("rouge_2"), pct("rouge_l"), F.round(100 * F.avg("hit"), 4).alias("expert"), F.round(F.avg(0.5 * F.col("judge") + 50 * F.col("grounded")), 4).alias("judge"), F.lit(True).alias("stand_in"))


# SQL of the same ------------------------------------------------------------------------------------------------------------


def _h32(x: str) -> str:
    return f"('0x' || substr(md5({x}), 1, 8))::UBIGINT"


_u = f"{_h32(chr(39) + 'slip:' + chr(39) + ' || o_orderkey')} / 4294967296.0"
_HID = f"({_h32(chr(39) + 'hidden:customer:' + chr(39) + ' || c_custkey || ' + chr(39) + ':in_nation:nation:' + chr(39) + ' || c_nationkey')} % 2 = 0)"
BASE_SQL = f"""cust AS (SELECT c_custkey AS key, n_regionkey::VARCHAR AS y, c_mktsegment AS c, 'nation:' || c_nationkey AS gold, {_h32("'7:' || c_custkey")} / 4294967296.0 < {TRAIN} AS train, {_HID} AS hidden FROM customer JOIN nation ON n_nationkey = c_nationkey WHERE c_custkey IN (SELECT o_custkey FROM orders)),
fr AS (SELECT o_orderkey AS f, o_custkey AS q, c_nationkey AS n, {_u} AS u, (c_nationkey + 1 + {_h32("'wrong:' || o_orderkey")} % 24) % 25 AS w FROM orders JOIN customer ON c_custkey = o_custkey),
sl AS (SELECT *, CASE {' '.join(f"WHEN u < {end} THEN '{name}'" for name, end in N.SLIPS.items())} ELSE 'none' END AS slip FROM fr),
raw AS (SELECT f, q, slip, CASE slip WHEN 'flipped' THEN 'nation:' || n WHEN 'spelling' THEN 'CUSTOMER#' || q ELSE 'customer:' || q END AS h, CASE slip WHEN 'wording' THEN 'lives_near' ELSE 'in_nation' END AS r,
        CASE slip WHEN 'flipped' THEN 'customer:' || q WHEN 'spelling' THEN 'NATION#' || n WHEN 'unknown' THEN 'nation:' || (n + 100) WHEN 'wrong' THEN 'nation:' || w ELSE 'nation:' || n END AS t,
        'nation:' || CASE slip WHEN 'wrong' THEN w ELSE n END AS meant FROM sl),
own AS (SELECT q, t FROM raw WHERE h = 'customer:' || q)"""
REST_SQL = f"{kg_sql(K.PLACES, 'full_kg')}, kg AS (SELECT * FROM full_kg WHERE NOT (r = 'in_nation' AND h LIKE 'customer:%' AND {_h32(chr(39) + 'hidden:' + chr(39) + ' || h || ' + chr(39) + ':' + chr(39) + ' || r || ' + chr(39) + ':' + chr(39) + ' || t')} % 2 = 0))"
TOP = "(SELECT q AS key, arg_min({0}, (-n, {0})) AS z FROM (SELECT q, {0}, count(*) AS n FROM {1} GROUP BY ALL) GROUP BY q)"


def loop_sql(kg: str) -> str:
    """What the episode verifies: the graph's tail where it has one, else the most stated one among known entities."""
    seen = f"(SELECT h AS e FROM {kg} UNION SELECT t FROM {kg})"
    usable = f"(SELECT q, meant FROM raw WHERE slip <> 'unknown' AND 'customer:' || q IN (SELECT e FROM {seen}) AND meant IN (SELECT e FROM {seen}))"
    return f"SELECT cust.key, coalesce(g.t, v.z) AS z FROM cust LEFT JOIN {kg} g ON g.r = 'in_nation' AND g.h = 'customer:' || cust.key LEFT JOIN {TOP.format('meant', usable)} v ON v.key = cust.key"


WAYS_SQL = {
    "none": "SELECT key, '-' AS z FROM cust", "zero-shot": "SELECT key, '-' AS z FROM cust", "vanilla": "SELECT key, c AS z FROM cust",
    "in-context": f"SELECT key, z FROM cust JOIN (SELECT c, arg_min(y, (-n, y)) AS z FROM (SELECT c, y, count(*) AS n FROM (SELECT c, y, row_number() OVER (PARTITION BY c ORDER BY {_h32(chr(39) + 'demo:' + chr(39) + ' || key')}, key) AS k FROM cust WHERE train) WHERE k <= {DEMOS} GROUP BY ALL) GROUP BY c) USING (c)",
    "global only": "SELECT key, t AS z FROM cust JOIN kg ON r = 'in_nation' AND h = 'customer:' || key", "local only": f"SELECT * FROM {TOP.format('t', 'own')}",
    "step-by-step": "SELECT q AS key, arg_min(t, f) AS z FROM raw GROUP BY q", "both": loop_sql("kg"), "full loop": loop_sql("kg"),
}


def report_sql(ways: dict, name: str = "method", more: str = "") -> str:
    ev = " UNION ALL ".join(f"SELECT '{m}' AS method, cust.key, coalesce(e.z, 'none') AS z FROM cust LEFT JOIN ({sql}) e ON e.key = cust.key" for m, sql in ways.items())
    return f"""WITH {REST_SQL}, {BASE_SQL}{more}, ev AS ({ev}),
x AS (SELECT method, student, key, y, hidden, train, z, method || '|' || student || '|' || CASE student WHEN 'small' THEN ({_h32("'cell:' || z")} % {CELLS})::VARCHAR ELSE z END AS s FROM ev JOIN cust USING (key), (VALUES ('large'), ('small')) v(student)),
n AS (SELECT s, y, count(*) AS n FROM x WHERE train AND method <> 'in-context' GROUP BY ALL), pr AS (SELECT y, sum(n) AS ny FROM n GROUP BY y), ss AS (SELECT s, sum(n) AS ns FROM n GROUP BY s),
d AS (SELECT ss.s, pr.y, (coalesce(n.n, 0) + 1.0) / (ns + (SELECT count(*) FROM pr)) AS p FROM ss CROSS JOIN pr LEFT JOIN n ON n.s = ss.s AND n.y = pr.y),
top AS (SELECT s, arg_min(y, (-p, y)) AS m FROM d GROUP BY s), g AS (SELECT sum(ny) AS t, count(*) AS k, arg_min(y, (-ny, y)) AS m FROM pr),
e AS (SELECT x.method, student, hidden, CASE WHEN x.method = 'in-context' THEN NULL ELSE coalesce(d.p, (coalesce(ny, 0) + 1.0) / (g.t + g.k)) END AS p, (CASE WHEN x.method = 'in-context' THEN z ELSE coalesce(top.m, g.m) END = x.y)::INT AS hit
      FROM x CROSS JOIN g LEFT JOIN d ON d.s = x.s AND d.y = x.y LEFT JOIN top ON top.s = x.s LEFT JOIN pr ON pr.y = x.y WHERE NOT train)
SELECT method AS {name}, student, count(*) AS n, round(100 * avg(hit), 6) AS accuracy, round(100 * avg(hit) FILTER (hidden), 6) AS accuracy_hidden, round(-avg(ln(p)), 6) AS nll FROM e GROUP BY method, student"""


# Queries ------------------------------------------------------------------------------------------------------------------


def block(spark, sf, methods):
    x = items(spark, sf)
    return judged(evidence(spark, sf, methods, x=x), x)


@query("graph_ablation", report_sql({m: WAYS_SQL[m] for m in GRAPH_ARMS}, "arm"))
def graph_ablation(spark, sf):
    """No graph and no text; the remaining graph alone; the unchecked statements alone; statements verified and mended with the graph."""
    return summary(block(spark, sf, GRAPH_ARMS), name="arm")


@query("single_teacher_block", report_sql({m: WAYS_SQL[m] for m in SINGLE}))
def single_teacher_block(spark, sf):
    """The prior answer, the question alone, demonstrations in context, one unchecked rationale, the loop's verified triples."""
    return summary(block(spark, sf, SINGLE))


@query("multi_agent_block")
def multi_agent_block(spark, sf):
    """Several agents over the same statements: reflection, votes, debate, path search; and the loop, which also checks them against the remaining graph."""
    return summary(block(spark, sf, MULTI))


@query("ablation_scores")
def ablation_scores(spark, sf):
    return overlap(block(spark, sf, GRAPH_ARMS), name="arm")


@query("single_teacher_scores")
def single_teacher_scores(spark, sf):
    return overlap(block(spark, sf, SINGLE))


@query("multi_agent_scores")
def multi_agent_scores(spark, sf):
    return overlap(block(spark, sf, MULTI))


CREDIBILITY = (("low", 0.5), ("medium", 0.25), ("high", 0.0))
COMPLETENESS = (("sparse", 0.3), ("moderate", 0.6), ("comprehensive", 1.0))


def levels(spark, sf, changes):
    """Evidence of the loop with the remaining graph degraded to each level."""
    x, out = items(spark, sf), None
    for name, change in changes:
        one = evidence(spark, sf, ("both",), w=world(spark, sf, change), x=x).withColumn("method", F.lit(name))
        out = one if out is None else out.unionByName(one)
    return judged(out, x)


def credible(rate):
    return lambda kg: V.corrupt(kg.filter("r = 'in_nation'"), rate=rate).select("h", "r", "t").unionByName(kg.filter("r <> 'in_nation'"))


_SLIP7 = _h32("'corrupt7:' || h || ':' || r || ':' || t")
RING_SQL = ", ring AS (SELECT own, coalesce(lead(own) OVER (ORDER BY own), min(own) OVER ()) AS other FROM (SELECT DISTINCT t AS own FROM kg WHERE r = 'in_nation'))" + "".join(f", kg_{name} AS (SELECT h, r, CASE WHEN r = 'in_nation' AND {_SLIP7} / 4294967296.0 < {rate} THEN other ELSE t END AS t FROM kg LEFT JOIN ring ON own = t)" for name, rate in CREDIBILITY)
THIN7 = _h32("'thin7:' || h || ':' || r || ':' || t")
THINNED_SQL = "".join(f", kg_{name} AS (SELECT * FROM kg WHERE {THIN7} / 4294967296.0 < {keep})" for name, keep in COMPLETENESS)


@query("credibility_accuracy", report_sql({name: loop_sql(f"kg_{name}") for name, _ in CREDIBILITY}, "level", RING_SQL))
def credibility_accuracy(spark, sf):
    """The loop with a graph in which a half, a quarter or none of the nations are wrong."""
    return summary(levels(spark, sf, [(n, credible(r)) for n, r in CREDIBILITY]), name="level")


@query("completeness_accuracy", report_sql({name: loop_sql(f"kg_{name}") for name, _ in COMPLETENESS}, "level", THINNED_SQL))
def completeness_accuracy(spark, sf):
    """The loop with three tenths, six tenths or all of the remaining graph."""
    return summary(levels(spark, sf, [(n, lambda kg, k=k: V.thin(kg, keep=k)) for n, k in COMPLETENESS]), name="level")


@query("credibility_scores")
def credibility_scores(spark, sf):
    return overlap(levels(spark, sf, [(n, credible(r)) for n, r in CREDIBILITY]), name="level")


@query("completeness_scores")
def completeness_scores(spark, sf):
    return overlap(levels(spark, sf, [(n, lambda kg, k=k: V.thin(kg, keep=k)) for n, k in COMPLETENESS]), name="level")


# Extraction methods ----------------------------------------------------------------------------------------------------


def extracted(w, queries):
    """method, q_id, h, r, t: the pattern and the co-occurrence extractor unchecked, and what the loop verifies of the agents' readings."""
    tag = lambda df, m: df.select(F.lit(m).alias("method"), "q_id", "h", "r", "t")
    loop, _ = E.run_episode(w, queries.select(F.col("key").alias("q_id")))
    return tag(N.stated(w.frags), "pattern").unionByName(tag(N.cooccurring(w.frags, w.kg, w.schema), "co-occurrence")).unionByName(tag(loop.filter("agent = 'relations'"), "full loop"))


_OUT = """o AS (SELECT 'pattern' AS method, q, h, r, t FROM raw UNION ALL SELECT 'co-occurrence', q, 'customer:' || q, 'in_nation', meant FROM raw WHERE slip NOT IN ('unknown', 'spelling')
UNION ALL SELECT 'full loop', q, 'customer:' || q, 'in_nation', CASE WHEN hidden THEN meant ELSE gold END FROM raw JOIN cust ON key = q WHERE NOT hidden OR slip <> 'unknown'),
m AS (SELECT DISTINCT method, mode, CASE mode WHEN 'local' THEN q ELSE -1 END AS s, h, r, t FROM o, (VALUES ('global'), ('local')) v(mode)),
en AS (SELECT method, mode, count(*) AS n_entities FROM (SELECT method, mode, s, h AS e FROM m UNION SELECT method, mode, s, t FROM m) GROUP BY ALL),
gd AS (SELECT DISTINCT 'customer:' || key AS h, gold FROM cust)
SELECT method, mode, count(*) AS n_triples, count(DISTINCT m.r) AS n_relations, any_value(n_entities) AS n_entities, count(gold) AS n_right, round(100.0 * count(gold) / count(*), 6) AS precision, round(100.0 * count(gold) / (SELECT count(*) FROM gd), 6) AS recall
FROM m JOIN en USING (method, mode) LEFT JOIN gd ON gd.h = m.h AND gd.gold = m.t AND m.r = 'in_nation' GROUP BY method, mode"""


@query("rte_methods", f"WITH {REST_SQL}, {BASE_SQL}, {_OUT}")
def rte_methods(spark, sf):
    """Size and accuracy of what each method extracts, over all fragments together (global) and for each customer apart (local)."""
    w, x = world(spark, sf), items(spark, sf)
    o = extracted(w, x).withColumn("mode", F.explode(F.array(F.lit("global"), F.lit("local"))))
    m = stored(o.select("method", "mode", F.when(F.col("mode") == "local", F.col("q_id")).otherwise(F.lit(-1)).alias("s"), "h", "r", "t").distinct(), "extracted")
    gold = x.select(F.concat(F.lit("customer:"), "key").alias("h"), F.lit("in_nation").alias("r"), F.col("gold").alias("t"), F.lit(1).alias("right"))
    total = x.agg(F.count(F.lit(1)).alias("all"))
    n = m.join(gold, ["h", "r", "t"], "left").groupBy("method", "mode").agg(F.count(F.lit(1)).alias("n_triples"), F.countDistinct("r").alias("n_relations"), F.count("right").alias("n_right"))
    e = m.select("method", "mode", "s", F.explode(F.array("h", "t")).alias("e")).distinct().groupBy("method", "mode").agg(F.count(F.lit(1)).alias("n_entities"))
    out = n.join(e, ["method", "mode"]).crossJoin(F.broadcast(total))  # one row
    return out.select("method", "mode", "n_triples", "n_relations", "n_entities", "n_right", F.round(100.0 * F.col("n_right") / F.col("n_triples"), 6).alias("precision"), F.round(100.0 * F.col("n_right") / F.col("all"), 6).alias("recall"))


_AT = "acc AS (SELECT CASE WHEN slip = 'none' OR slip = 'wrong' AND hidden THEN 0 WHEN slip = 'spelling' THEN 1 WHEN slip = 'flipped' THEN 2 WHEN slip = 'wording' THEN 3 WHEN hidden THEN 99 ELSE 4 END AS a FROM raw JOIN cust ON key = q)"


@query("refine_rounds", f"WITH {BASE_SQL}, {_AT} SELECT k::INT AS round, count(*) FILTER (a >= k) AS n_in, count(*) FILTER (a = k) AS n_ok, count(*) FILTER (a > k) AS n_rejected FROM acc, range(0, 5) r(k) GROUP BY k")
def refine_rounds(spark, sf):
    """Statements of the fragments through the loop: spellings, directions, relations and tails are mended in turn; unknown nations of hidden customers are left and dropped."""
    return refined(spark, sf)[1]


def refined(spark, sf):
    w = world(spark, sf)
    return V.refine_until_valid(N.stated(w.frags).select("q_id", "h", "r", "t"), kg=w.kg, schema=w.schema, aliases=w.aliases, max_rounds=4, checks=E.CHECKS)


@query("refine_accepted", f"WITH {BASE_SQL}, {_AT} SELECT a::INT AS round, 'in_nation' AS r, count(*) AS n FROM acc WHERE a < 5 GROUP BY a")
def refine_accepted(spark, sf):
    return refined(spark, sf)[0].groupBy("round", "r").agg(F.count(F.lit(1)).alias("n"))


@query("supported_by_votes", f"WITH {REST_SQL}, {BASE_SQL}, v AS (SELECT q, h, r, t, count(*) AS votes FROM raw GROUP BY ALL), s AS (SELECT DISTINCT h, r, t FROM kg) SELECT votes >= 2 AS voted, s.h IS NOT NULL AS supported, count(*) AS n FROM v LEFT JOIN s USING (h, r, t) GROUP BY ALL")
def supported_by_votes(spark, sf):
    """Statements that at least two fragments make, and statements that the remaining graph holds: two more checks of the verifier."""
    w = world(spark, sf)
    v = N.stated(w.frags).groupBy("q_id", "h", "r", "t").agg(F.count(F.lit(1)).alias("votes"))
    x = V.verify(v, kg=w.kg, schema=w.schema, checks=(), min_votes=2, support=w.kg)
    return x.groupBy((~F.array_contains("reasons", "votes")).alias("voted"), (~F.array_contains("reasons", "text")).alias("supported")).agg(F.count(F.lit(1)).alias("n"))


@query("judge_agreement", f"WITH {BASE_SQL}, v AS (SELECT q, h, r, t, count(*) AS votes FROM raw GROUP BY ALL), b AS (SELECT (votes >= 2)::INT AS b, (v.h = 'customer:' || key AND r = 'in_nation' AND t = gold)::INT AS a FROM v JOIN cust ON key = q), s AS (SELECT count(*) AS n, corr(a, b) AS r, avg((a = b)::INT) AS po, avg(a) AS xa, avg(b) AS xb FROM b) SELECT n, round(r, 6) AS pearson, round((po - (xa * xb + (1 - xa) * (1 - xb))) / (1 - (xa * xb + (1 - xa) * (1 - xb))), 6) AS kappa FROM s")
def judge_agreement(spark, sf):
    """The expert stand-in (is the statement true?) against the judge stand-in (do two fragments make it?), over all distinct statements."""
    w, x = world(spark, sf), items(spark, sf)
    v = N.stated(w.frags).groupBy("q_id", "h", "r", "t").agg(F.count(F.lit(1)).alias("votes")).join(x.select(F.col("key").alias("q_id"), "gold"), "q_id")
    right = (F.col("h") == F.concat(F.lit("customer:"), "q_id")) & (F.col("r") == "in_nation") & (F.col("t") == F.col("gold"))
    return S.agreement(v.select(right.cast("int").alias("a"), (F.col("votes") >= 2).cast("int").alias("b")), "a", "b")


@query("episode_log")
def episode_log(spark, sf):
    """Steps of the acting agents, with the more thorough policy."""
    return E.run_episode(world(spark, sf), items(spark, sf).select(F.col("key").alias("q_id")), policy=E.thorough_policy)[1]


LEVELS = (0.0, 0.25, 0.5, 0.75, 1.0)


def noisy_graph(rate):
    return lambda kg: V.corrupt(kg.filter("r = 'in_nation' and h like 'customer:%'"), rate=rate).select("h", "r", "t")


_NOISE = ", own_kg AS (SELECT * FROM full_kg WHERE r = 'in_nation' AND h LIKE 'customer:%'), ring AS (SELECT own, coalesce(lead(own) OVER (ORDER BY own), min(own) OVER ()) AS other FROM (SELECT DISTINCT t AS own FROM own_kg))" + "".join(f", kg_{k} AS (SELECT h, r, CASE WHEN {_SLIP7} / 4294967296.0 < {v} THEN other ELSE t END AS t FROM own_kg JOIN ring ON own = t)" for k, v in enumerate(LEVELS))


@query("grounded_nll", report_sql({str(v): f"SELECT key, t AS z FROM cust JOIN kg_{k} ON h = 'customer:' || key" for k, v in enumerate(LEVELS)}, "level", _NOISE))
def grounded_nll(spark, sf):
    """Negative log-likelihood of the students given one triple of the graph as the triples' quality falls."""
    x, out = items(spark, sf), None
    full = K.kg_from_tables(spark, sf, K.PLACES)
    for v in LEVELS:
        z = noisy_graph(v)(full).select(F.substring_index("h", ":", -1).cast("long").alias("key"), F.col("t").alias("z"))
        one = x.select("key").join(z, "key", "left").select(F.lit(str(v)).alias("method"), "key", F.coalesce("z", F.lit("none")).alias("z"))
        out = one if out is None else out.unionByName(one)
    return summary(judged(stored(out, "noisy"), x), name="level")


@query("joint_objective")
def joint_objective(spark, sf):
    """Loss of reading a fragment's triple, of completing a masked tail and of both with the graph's factor: the log share of verified triples shifts the total, not its minimum."""
    w, x = world(spark, sf), stored(items(spark, sf), "items")
    read = N.stated(w.frags).join(x.select(F.col("key").alias("q_id"), "gold", "train"), "q_id")
    m = I.CountPredictor.fit(read.filter("train"), "gold", "t")
    rte = m.evaluate(read.filter("not train"), "gold", "t", "frag_id").agg((-F.avg("log")).alias("rte"))
    m = I.CountPredictor.fit(x.filter("train"), "gold", "c")
    kgc = m.evaluate(x.filter("not train"), "gold", "c", "key").agg((-F.avg("log")).alias("kgc"))
    log = refined(spark, sf)[1]
    share = log.agg((F.sum("n_ok") / F.max(F.when(F.col("round") == 0, F.col("n_in")))).alias("p")).select(F.ln("p").alias("log_graph"))
    y = rte.crossJoin(kgc).crossJoin(share)  # one row each
    return I.rounded(y.select("rte", "kgc", "log_graph", (F.col("rte") + F.col("kgc") - 2 * F.col("log_graph")).alias("total")))


@query("step_by_step_loss")
def step_by_step_loss(spark, sf):
    """The answer's loss given the rationale plus a weight times the rationale's loss given the question, for three weights."""
    w, x = world(spark, sf), items(spark, sf)
    rows = stored(x.join(one_rationale(w), "key"), "rationales")
    part = lambda y, s: I.CountPredictor.fit(rows.filter("train"), y, s).evaluate(rows.filter("not train"), y, s, "key").agg((-F.avg("log")).alias("nll"))
    both = part("y", "z").withColumnRenamed("nll", "answer").crossJoin(part("z", "c").withColumnRenamed("nll", "rationale"))  # one row each
    both = both.withColumn("weight", F.explode(F.array(F.lit(0.0), F.lit(0.5), F.lit(1.0))))
    return I.rounded(both.select("weight", "answer", "rationale", (F.col("answer") + F.col("weight") * F.col("rationale")).alias("total")))


@query("metric_compare")
def metric_compare(spark, sf):
    s = stored(single_teacher_block(spark, sf).filter("student = 'large'").select("method", F.lit("accuracy").alias("metric"), F.col("accuracy").alias("value")), "methods")
    return S.compare(s, reference="vanilla")
