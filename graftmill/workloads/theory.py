"""Scores, information measures, baselines and control on the given tables."""

from pyspark.sql import functions as F

from graftmill.functions import scores as S
from graftmill.functions.hashing import hash_uniform
from graftmill.operators import corpus as C
from graftmill.operators.agents import answers as A
from graftmill.operators.kg import build as K
from graftmill.operators.kg import complete as M
from graftmill.operators.student.lowrank import LowRankStudent
from graftmill.operators.theory import control as P
from graftmill.operators.theory import information as I
from graftmill.operators.theory import sgd as G
from graftmill.sources.tables import load, stored

from .corpus import TURNS_SQL
from .graph import ATTR, HIDE_SQL, seeds
from .registry import query

# Overlap scores: the user's turn as hypothesis for the assistant's answer ------------------------------------------


def pairs(spark, sf):
    q = C.qa_from_turns(load(spark, sf, "conversations"))
    return q.select((F.col("conv_id") * 1000 + F.col("turn")).alias("id"), F.col("input").alias("hyp"), F.col("output").alias("ref"))


PW = "list_filter(regexp_split_to_array(lower(coalesce({0}, '')), '[ \\t\\r\\n]+'), lambda x: x <> '')"
GRAM_SQL = f"""WITH {TURNS_SQL}, p AS (SELECT conv_id * 1000 + turn AS id, {PW.format('input')} AS h, {PW.format('output')} AS r FROM pairs),
g AS (SELECT id, k, 'hyp' AS side, array_to_string(h[i:i+k-1], ' ') AS g FROM p, range(1, 5) a(k), range(1, len(h) - k + 2) b(i) UNION ALL SELECT id, k, 'ref', array_to_string(r[i:i+k-1], ' ') FROM p, range(1, 5) a(k), range(1, len(r) - k + 2) b(i)),
c AS (SELECT id, k, g, count(*) FILTER (side = 'hyp') AS hyp, count(*) FILTER (side = 'ref') AS ref FROM g GROUP BY ALL),
m AS (SELECT id, k, sum(least(hyp, ref)) AS hit, sum(hyp) AS hyp, sum(ref) AS ref FROM c GROUP BY ALL)
"""


@query("bleu_corpus", GRAM_SQL + """, s AS (SELECT k, sum(hit) AS hit, sum(hyp) AS hyp, sum(ref) AS ref FROM m GROUP BY k)
SELECT round(CASE WHEN min(hit) = 0 THEN 0 ELSE 100 * exp(avg(ln(hit / hyp)) + CASE WHEN max(hyp) FILTER (k = 1) >= max(ref) FILTER (k = 1) THEN 0 ELSE 1 - max(ref) FILTER (k = 1) / max(hyp) FILTER (k = 1) END) END, 6) AS bleu FROM s""")
def bleu_corpus(spark, sf):
    return S.bleu_corpus(pairs(spark, sf))


@query("bleu_sentence", GRAM_SQL + """, i AS (SELECT id, k, coalesce(hit, 0) AS hit, coalesce(hyp, 0) AS hyp, coalesce(ref, 0) AS ref FROM (SELECT DISTINCT id FROM m) CROSS JOIN range(1, 5) a(k) LEFT JOIN m USING (id, k)),
s AS (SELECT id, avg(ln((hit + 1.0) / (hyp + 1.0))) AS l, max(hyp) FILTER (k = 1) AS h1, max(ref) FILTER (k = 1) AS r1 FROM i GROUP BY id)
SELECT id, round(100 * exp(l + CASE WHEN h1 >= r1 THEN 0 WHEN h1 = 0 THEN -1e9 ELSE 1 - r1 / h1 END), 6) AS bleu FROM s WHERE r1 > 0""")
def bleu_sentence(spark, sf):
    return S.bleu_sentence(pairs(spark, sf))


def _rouge(n):
    return GRAM_SQL + f" SELECT count(*) AS n, round(100 * avg(hit / ref), 6) AS recall, round(100 * avg(CASE WHEN hyp > 0 THEN hit / hyp ELSE 0 END), 6) AS prec, round(100 * avg(CASE WHEN hit > 0 THEN 2 * hit / (hyp + ref) ELSE 0 END), 6) AS f1 FROM m WHERE k = {n} AND ref > 0"


def _means(df):
    m = lambda c, a: F.round(100 * F.avg(c), 6).alias(a)
    return df.agg(F.count(F.lit(1)).alias("n"), m("recall", "recall"), m("precision", "prec"), m("f1", "f1"))


@query("rouge1", _rouge(1))
def rouge1(spark, sf):
    return _means(S.rouge_n(pairs(spark, sf), 1))


@query("rouge2", _rouge(2))
def rouge2(spark, sf):
    return _means(S.rouge_n(pairs(spark, sf), 2))


@query("rouge_l")
def rouge_l(spark, sf):
    return _means(S.rouge_l(pairs(spark, sf)))


@query("bleu_fourgram_only", GRAM_SQL + " SELECT round(CASE WHEN sum(hit) = 0 THEN 0 ELSE 100 * exp(ln(sum(hit) / sum(hyp)) + CASE WHEN (SELECT sum(hyp) FROM m WHERE k = 1) >= (SELECT sum(ref) FROM m WHERE k = 1) THEN 0 ELSE 1 - (SELECT sum(ref) FROM m WHERE k = 1) / (SELECT sum(hyp) FROM m WHERE k = 1) END) END, 6) AS bleu FROM m WHERE k = 4")
def bleu_fourgram_only(spark, sf):
    return S.bleu_corpus(pairs(spark, sf), only=True)


@query("judge_scores")
def judge_scores(spark, sf):
    return S.rubric_judge(pairs(spark, sf))


@query("human_eval", "SELECT lang, count(*) AS n, round(100 * avg(quality), 6) AS human FROM labels JOIN documents USING (doc_id) GROUP BY lang")
def human_eval(spark, sf):
    d = load(spark, sf, "documents").select("doc_id", "lang").join(load(spark, sf, "labels"), "doc_id")
    return S.human_eval(d.select("lang", F.col("quality").alias("score")), "lang")



# Information ---------------------------------------------------------------------------------------------------------

CUST_SQL = "obs AS (SELECT n_regionkey AS y, n_nationkey AS z, c_mktsegment AS c FROM customer JOIN nation ON n_nationkey = c_nationkey)"
DOC_SQL = "obs AS (SELECT quality AS y, floor(log10(greatest(n_chars, 1)))::INT AS z, lang AS c FROM labels JOIN documents USING (doc_id))"
MI_SQL = """cell AS (SELECT c, z, y, count(*)::DOUBLE AS n FROM obs GROUP BY ALL), t AS (SELECT sum(n) AS n FROM cell),
a AS (SELECT sum(-n * ln(n / m)) AS s FROM (SELECT n, sum(n) OVER (PARTITION BY c) AS m FROM (SELECT c, y, sum(n) AS n FROM cell GROUP BY ALL))),
b AS (SELECT sum(-n * ln(n / m)) AS s, count(*) AS k FROM (SELECT n, sum(n) OVER (PARTITION BY c, z) AS m FROM cell))"""


def places(spark, sf):
    return load(spark, sf, "customer").join(load(spark, sf, "nation"), F.col("n_nationkey") == F.col("c_nationkey")).select("c_custkey", F.col("n_regionkey").alias("y"), F.col("n_nationkey").alias("z"), F.col("c_mktsegment").alias("c"))


def graded(spark, sf):
    d = load(spark, sf, "labels").join(load(spark, sf, "documents").select("doc_id", "lang", "n_chars", "source"), "doc_id")
    return d.select("doc_id", F.col("quality").alias("y"), F.floor(F.log10(F.greatest("n_chars", F.lit(1)))).cast("int").alias("z"), F.col("lang").alias("c"), "source")


@query("entropy_given", f"WITH {CUST_SQL}, {MI_SQL} SELECT round(a.s / t.n, 6) AS h_c, round(b.s / t.n, 6) AS h_cz FROM a, b, t")
def entropy_given(spark, sf):
    return I.rounded(I.measures(I.cells(places(spark, sf), "y", "z", "c")).select("h_c", "h_cz"))


@query("conditional_mi", f"WITH {DOC_SQL}, {MI_SQL} SELECT round(greatest(a.s / t.n - b.s / t.n, 0), 6) AS mi, k AS n_cells FROM a, b, t")
def conditional_mi(spark, sf):
    return I.rounded(I.measures(I.cells(graded(spark, sf), "y", "z", "c")).select("mi", "n_cells"))


@query("prior_quality", " UNION ALL ".join(f"SELECT * FROM (WITH {o}, {MI_SQL} SELECT '{n}' AS workload, round((a.s - b.s) / a.s, 6) AS gamma, false AS degenerate FROM a, b)" for n, o in (("places", CUST_SQL), ("documents", DOC_SQL))))
def prior_quality(spark, sf):
    one = lambda df, n: I.rounded(I.prior_quality(df, "y", "z", "c").select(F.lit(n).alias("workload"), "gamma", "degenerate"))
    return one(places(spark, sf), "places").unionByName(one(graded(spark, sf), "documents"))


@query("prior_quality_corrected")
def prior_quality_corrected(spark, sf):
    """Plug-in value by source, its corrected value, and what shuffled labels give."""
    g = graded(spark, sf)
    plain = I.measures(I.cells(g, "y", "source", "c")).select(F.lit("plug-in").alias("kind"), "gamma")
    fixed = I.measures(I.cells(g, "y", "source", "c"), correction="miller-madow").select(F.lit("corrected").alias("kind"), "gamma")
    null = I.shuffled_quality(g, "y", "source", "c", key="doc_id").select(F.concat(F.lit("shuffled "), "shuffle").alias("kind"), "gamma")
    return I.rounded(plain.unionByName(fixed).unionByName(null))


LEVELS = (0.0, 0.25, 0.5, 0.75, 1.0)


@query("monotone_ladder", f"""WITH {CUST_SQL}, cell AS (SELECT c, z, y, count(*)::DOUBLE AS n FROM obs GROUP BY ALL), zs AS (SELECT DISTINCT z FROM cell),
g AS (SELECT e AS level, c, k.z AS z, y, sum(n * (CASE WHEN k.z = cell.z THEN 1 - e ELSE 0 END + e / (SELECT count(*) FROM zs))) AS n FROM cell, zs k, (VALUES (0.0::DOUBLE), (0.25), (0.5), (0.75), (1.0)) v(e) GROUP BY ALL HAVING sum(n * (CASE WHEN k.z = cell.z THEN 1 - e ELSE 0 END + e / (SELECT count(*) FROM zs))) > 0),
x AS (SELECT *, sum(n) OVER (PARTITION BY level, c, z) AS m, sum(n) OVER (PARTITION BY level, c) AS mc, sum(n) OVER (PARTITION BY level, c, y) AS my, max(n) OVER (PARTITION BY level, c, z) AS mt FROM g)
SELECT level, round(1 + sum(n * ln(n / m)) / sum(-n * ln(my / mc)), 6) AS gamma, round(sum(n * ln(n / m)) / sum(n), 6) AS reward, round(1 - sum(n * mt / m) / sum(n), 6) AS bayes_risk, round(1 - sum(n * n / m) / sum(n), 6) AS grad_variance FROM x GROUP BY level""")
def monotone_ladder(spark, sf):
    return I.ladder(I.cells(places(spark, sf), "y", "z", "c"), LEVELS)


@query("fano", f"WITH {CUST_SQL}, {MI_SQL.replace('PARTITION BY c, z', 'PARTITION BY c')} SELECT round(greatest(0, (a.s / t.n - ln(2)) / ln((SELECT count(DISTINCT y) FROM obs))), 6) AS bound, round(1 - (SELECT sum(n) FROM (SELECT max(n) AS n FROM (SELECT c, y, count(*) AS n FROM obs GROUP BY ALL) GROUP BY c)) / t.n, 6) AS error FROM a, t")
def fano(spark, sf):
    """Least error that the context alone allows, and the error of the best guess by context."""
    p = places(spark, sf)
    h = I.measures(I.cells(p, "y", None, "c")).select("n", "h_c")
    n = p.groupBy("c", "y").agg(F.count(F.lit(1)).alias("k"))
    hit = n.groupBy("c").agg(F.max("k").alias("k")).agg(F.sum("k").alias("hit"))
    labels = p.agg(F.countDistinct("y").alias("labels"))
    return h.crossJoin(hit).crossJoin(labels).select(F.round(I.fano_column(F.col("h_c"), F.col("labels")), 6).alias("bound"), F.round(1 - F.col("hit") / F.col("n"), 6).alias("error"))


# Students on relational questions: which region does a customer belong to? --------------------------------------------

KEY = "('0x' || substr(md5('7:' || c_custkey), 1, 8))::UBIGINT / 4294967296.0"
NOISE = "('0x' || substr(md5('noise:' || c_custkey), 1, 8))::UBIGINT / 4294967296.0"


def questions(spark, sf, rate: float = 0.0, keep: float = 1.0):
    """key, y (region), c (segment), z (nation triple: corrupted at rate, kept at keep, else missing), train."""
    p = places(spark, sf)
    u = hash_uniform("c_custkey", seed="noise")
    wrong = (F.col("z") + 7) % 25
    v = hash_uniform("c_custkey", seed="keep")
    z = F.when(v >= keep, "none").otherwise(F.when(u < rate, wrong).otherwise(F.col("z")).cast("string"))
    return p.select(F.col("c_custkey").alias("key"), F.col("y").cast("string").alias("y"), "c", z.alias("z"), (hash_uniform("c_custkey", seed=7) < 0.6).alias("train"))


def run_student(items, state):
    x = items.withColumn("s", state)
    model = I.CountPredictor.fit(x.filter("train"), "y", "s")
    return model.evaluate(x.filter("not train"), "y", "s", "key")


def summary(ev, **tags):
    cols = [F.lit(v).alias(k) for k, v in tags.items()]
    return ev.agg(F.count(F.lit(1)).alias("n"), F.round(100 * F.avg("zero_one"), 6).alias("accuracy"), F.round(-F.avg("log"), 6).alias("nll")).select(*cols, "n", "accuracy", "nll")


def student_sql(tag, state, rate=0.0, keep=1.0):
    """One arm: count predictor with add-one smoothing over the labels, states from the training part."""
    return f"""SELECT * FROM (WITH b AS (SELECT c_custkey, n_regionkey AS y, c_mktsegment AS c, CASE WHEN ('0x' || substr(md5('keep:' || c_custkey), 1, 8))::UBIGINT / 4294967296.0 >= {keep} THEN 'none' WHEN {NOISE} < {rate} THEN ((n_nationkey + 7) % 25)::VARCHAR ELSE n_nationkey::VARCHAR END AS z, {KEY} < 0.6 AS train FROM customer JOIN nation ON n_nationkey = c_nationkey),
x AS (SELECT *, {state} AS s FROM b), n AS (SELECT s, y, count(*) AS n FROM x WHERE train GROUP BY ALL), pr AS (SELECT y, sum(n) AS ny FROM n GROUP BY y), ss AS (SELECT s, sum(n) AS ns FROM n GROUP BY s),
d AS (SELECT ss.s, pr.y, (coalesce(n.n, 0) + 1.0) / (ns + (SELECT count(*) FROM pr)) AS p FROM ss CROSS JOIN pr LEFT JOIN n ON n.s = ss.s AND n.y = pr.y),
top AS (SELECT s, arg_min(y, (-p, y::VARCHAR)) AS m FROM d GROUP BY s), g AS (SELECT sum(ny) AS t, count(*) AS k, arg_min(y, (-ny, y::VARCHAR)) AS m FROM pr),
e AS (SELECT coalesce(d.p, (coalesce(ny, 0) + 1.0) / (t + k)) AS p, (coalesce(top.m, g.m) = x.y)::INT AS hit FROM x CROSS JOIN g LEFT JOIN d ON d.s = x.s AND d.y = x.y LEFT JOIN top ON top.s = x.s LEFT JOIN pr ON pr.y = x.y WHERE NOT train)
SELECT {tag}, count(*) AS n, round(100 * avg(hit), 6) AS accuracy, round(-avg(ln(p)), 6) AS nll FROM e)"""


def state_of(s):
    return F.col("c") if s == "c" else F.lit("-") if s == "'-'" else F.concat_ws("/", "c", "z")


@query("count_predictor", student_sql("'segment' AS state", "c"))
def count_predictor(spark, sf):
    return summary(run_student(questions(spark, sf), F.col("c")), state="segment")


# Answer selection over completion candidates ---------------------------------------------------------------------------

CAND_SQL = f"""WITH {ATTR}, {HIDE_SQL}, n AS (SELECT g.r, g.t, a.r AS r2, a.t AS t2, count(*) AS n FROM rest g JOIN rest a ON a.h = g.h AND a.r <> g.r WHERE g.r IN (SELECT r FROM probe) GROUP BY ALL),
sh AS (SELECT *, n::DOUBLE / sum(n) OVER (PARTITION BY r, r2, t2) AS p FROM n),
s AS (SELECT q.h, q.r, sh.t, round(sum(p), 6) AS score FROM (SELECT DISTINCT h, r FROM probe) q JOIN rest a ON a.h = q.h AND a.r <> q.r JOIN sh ON sh.r = q.r AND sh.r2 = a.r AND sh.t2 = a.t GROUP BY ALL),
k AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY h, r ORDER BY score DESC, t) AS rank FROM s) WHERE rank <= 5),
cand AS (SELECT h || '|' || r AS q_id, t AS answer, score / sum(score) OVER (PARTITION BY h, r) AS p FROM k)
"""


def candidates(spark, sf):
    """(q_id, answer, p), (q_id, gold): five candidates for each hidden tail, by neighbour votes."""
    rest, probes = M.hide(K.kg_from_tables(spark, sf, K.ATTRIBUTES))
    top = M.by_neighbours(rest, probes, k=5).withColumn("q_id", F.concat_ws("|", "h", "r"))
    from pyspark.sql import Window
    p = F.col("score") / F.sum("score").over(Window.partitionBy("h", "r").orderBy("rank").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))
    return top.select("q_id", F.col("t").alias("answer"), p.alias("p")), probes.select(F.concat_ws("|", "h", "r").alias("q_id"), F.col("t_gold").alias("gold"))


@query("nucleus_keep_set", CAND_SQL + """, w AS (SELECT q_id, answer, pow(p, 1.25) / sum(pow(p, 1.25)) OVER (PARTITION BY q_id) AS w FROM cand),
b AS (SELECT *, coalesce(sum(w) OVER (PARTITION BY q_id ORDER BY w DESC, answer ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before FROM w)
SELECT q_id, answer, round(w / sum(w) OVER (PARTITION BY q_id), 6) AS p FROM b WHERE before < 0.85""")
def nucleus_keep_set(spark, sf):
    return A.nucleus(candidates(spark, sf)[0]).withColumn("p", F.round("p", 6))


@query("majority_vote", CAND_SQL + """, c AS (SELECT *, sum(p) OVER (PARTITION BY q_id ORDER BY p DESC, answer ROWS UNBOUNDED PRECEDING) AS hi, lead(answer) OVER (PARTITION BY q_id ORDER BY p DESC, answer) IS NULL AS last FROM cand),
d AS (SELECT q_id, answer, p, u FROM (SELECT c.*, ('0x' || substr(md5('7:' || q_id || ':' || j), 1, 8))::UBIGINT / 4294967296.0 AS u FROM c, range(1, 6) r(j)) WHERE u >= hi - p AND (u < hi OR last)),
v AS (SELECT q_id, answer, count(*) AS votes, sum(p) AS mass FROM d GROUP BY ALL)
SELECT q_id, answer, votes FROM (SELECT *, row_number() OVER (PARTITION BY q_id ORDER BY votes DESC, mass DESC, answer) AS k FROM v) WHERE k = 1""")
def majority_vote(spark, sf):
    return A.self_consistency(candidates(spark, sf)[0])


@query("debate_final", CAND_SQL + """, w AS (SELECT cand.*, a AS agent, ('0x' || substr(md5('view7:' || q_id || ':' || answer || ':' || a), 1, 8))::UBIGINT / 4294967296.0 >= 1.0 / 3 AS seen FROM cand, range(0, 3) r(a)),
x AS (SELECT * FROM (SELECT *, bool_or(seen) OVER (PARTITION BY q_id, agent) AS any_seen FROM w) WHERE seen OR NOT any_seen),
first AS (SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY q_id, agent ORDER BY p DESC, answer) AS k FROM x) WHERE k = 1),
m AS (SELECT *, max(p) OVER (PARTITION BY q_id) AS mx FROM first), t AS (SELECT q_id, min(answer) AS top FROM m WHERE p = mx GROUP BY q_id),
y AS (SELECT q_id, answer, CASE WHEN p < mx THEN top ELSE answer END AS now FROM m JOIN t USING (q_id)),
nn AS (SELECT q_id, now, count(*) AS n FROM y GROUP BY ALL), r AS (SELECT q_id, CASE WHEN count(DISTINCT answer) = 1 THEN 0 WHEN count(DISTINCT now) = 1 THEN 1 ELSE 3 END AS rounds FROM y GROUP BY q_id)
SELECT q_id, arg_min(now, (-n, now)) AS answer, any_value(rounds)::INT AS rounds FROM nn JOIN r USING (q_id) GROUP BY q_id""")
def debate_final(spark, sf):
    return A.debate(candidates(spark, sf)[0])


@query("self_reflection")
def self_reflection(spark, sf):
    return A.self_reflect(candidates(spark, sf)[0])


# Gradient descent, control ----------------------------------------------------------------------------------------------

@query("sgd_simulation")
def sgd_simulation(spark, sf):
    """Descent with the values of the events as gradient noise, sixty events a run, against the bound."""
    rows = load(spark, sf, "events").filter("event_id is not null and value is not null").select(F.floor(F.col("event_id") / 60).alias("run"), F.col("event_id").alias("at"), F.col("value").alias("v"))
    setting = dict(alpha=0.5, eigs=(0.5, 1.0), sigma=0.5)
    return G.against_bound(G.simulate_on_rows(rows, **setting), **setting)


LETTERS = "abcdefghijklmnopqrstuvwxyz"


@query("lowrank_training")
def lowrank_training(spark, sf):
    """Languages of documents from the shares of their letters: loss of each epoch on the training part, accuracy on the held-out part (epoch -1)."""
    low = F.lower(F.coalesce("text", F.lit("")))
    share = lambda c: (F.length(low) - F.length(F.replace(low, F.lit(c), F.lit("")))) / F.greatest(F.length(low), F.lit(1))
    d = load(spark, sf, "documents").filter("lang is not null").select(F.col("doc_id").alias("key"), F.array(*[10.0 * share(c) for c in LETTERS]).alias("x"), F.col("lang").alias("y"))
    d = stored(d.withColumn("train", hash_uniform("key", seed="lowrank") < 0.7), "letters")
    labels = [r["y"] for r in d.select("y").distinct().orderBy("y").collect()]  # the label space
    m = LowRankStudent(len(LETTERS), labels, rank=4, alpha=16, lr=0.1, batch=32, epochs=5).fit(d.filter("train"))
    hit = m.predict(d.filter("not train")).join(d.select(F.col("key").cast("string").alias("key"), "y"), "key").agg(F.avg((F.col("answer") == F.col("y")).cast("double"))).first()[0]
    return spark.createDataFrame([*[(k, float(v)) for k, v in m.log], (-1, float(hit or 0.0))], "epoch int, loss double")


#: The five kinds of events are the agents of the observed systems, in this order.
KINDS = ("click", "view", "signup", "purchase", "error")


def day_of(ts):
    return F.date_format(ts, "yyyy-MM-dd")


def observed(spark, sf):
    """topology, src, dst, w: one system a day, its weights the shares of the steps between two kinds, both ways, among all steps of the users on that day."""
    from pyspark.sql import Window
    kind = F.array_position(F.array(*[F.lit(k) for k in KINDS]), F.col("event_type")).cast("int") - 1
    e = load(spark, sf, "events").filter(F.col("event_type").isin(*KINDS) & F.col("ts").isNotNull()).select(day_of("ts").alias("day"), "user_id", "ts", "event_id", kind.alias("src"))
    e = e.withColumn("dst", F.lead("src").over(Window.partitionBy("day", "user_id").orderBy("ts", "event_id"))).filter("dst <> src")
    n = e.groupBy("day", F.least("src", "dst").alias("a"), F.greatest("src", "dst").alias("b")).agg(F.count(F.lit(1)).alias("n"))
    w = n.withColumn("w", F.col("n") / F.sum("n").over(Window.partitionBy("day")))  # at most ten rows a day
    return w.select(F.concat(F.lit("events "), "day").alias("topology"), F.inline(F.array(F.struct(F.col("a").alias("src"), F.col("b").alias("dst")), F.struct(F.col("b").alias("src"), F.col("a").alias("dst")))), "w")


@query("controllability_grid")
def controllability_grid(spark, sf):
    """Named and random topologies, and the observed ones of every day."""
    return P.controllability(P.laplacian(P.topologies(spark, randoms=5, roles=True).unionByName(observed(spark, sf))))


def day_states(spark, sf):
    """x0_id, x0: for each day and kind of event by how many standard deviations the mean value differs from that of the other days; 0 where it has none."""
    e = load(spark, sf, "events").filter(F.col("event_type").isin(*KINDS) & F.col("ts").isNotNull()).select(day_of("ts").alias("day"), "event_type", F.round(100 * F.col("value")).cast("long").alias("v"))
    own = stored(e.groupBy("day").agg(*[F.avg(F.when(F.col("event_type") == k, F.col("v"))).alias(k) for k in KINDS]), "days")  # as many rows as days
    over = own.agg(*[f(k).alias(f"{k}_{n}") for k in KINDS for n, f in (("m", F.avg), ("sd", F.stddev_pop))])
    x0 = F.array(*[F.coalesce(F.try_divide(F.col(k) - F.col(f"{k}_m"), F.col(f"{k}_sd")), F.lit(0.0)) for k in KINDS])
    return own.crossJoin(F.broadcast(over)).select(F.datediff(F.to_date("day"), F.lit("1970-01-01")).alias("x0_id"), x0.alias("x0"))


@query("agent_trajectories")
def agent_trajectories(spark, sf):
    """Steps until each agent stays near its last value, from the state of every day of the events, under central and under decentral control."""
    starts = stored(day_states(spark, sf), "starts")
    lap, out = P.laplacian(P.topologies(spark, randoms=5, roles=True)), None
    for control in ("central", "decentral"):
        one = P.settle_time(P.simulate_agents(lap, starts, control=control)).withColumn("control", F.lit(control))
        out = one if out is None else out.unionByName(one)
    return out


@query("role_laplacian", """WITH t AS (SELECT role AS a, lead(role) OVER (PARTITION BY conv_id ORDER BY turn) AS b FROM conversations), w AS (SELECT a, b, count(*)::DOUBLE AS w FROM t WHERE b IS NOT NULL AND a <> b GROUP BY ALL)
SELECT a AS i, b AS j, -w AS l FROM w UNION ALL SELECT a, a, sum(w) FROM w GROUP BY a""")
def role_laplacian(spark, sf):
    from pyspark.sql import Window
    t = load(spark, sf, "conversations").select(F.col("role").alias("src"), F.lead("role").over(Window.partitionBy("conv_id").orderBy("turn")).alias("dst"))
    e = t.filter("dst is not null").groupBy("src", "dst").agg(F.count(F.lit(1)).cast("double").alias("w")).withColumn("topology", F.lit("roles"))
    return P.laplacian(e).select("i", "j", "l")


@query("event_transition_laplacian", """WITH t AS (SELECT event_type AS a, lead(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS b FROM events), w AS (SELECT a, b, count(*)::DOUBLE AS w FROM t WHERE b IS NOT NULL AND a <> b GROUP BY ALL)
SELECT a AS i, b AS j, -w AS l FROM w UNION ALL SELECT a, a, sum(w) FROM w GROUP BY a""")
def event_transition_laplacian(spark, sf):
    from pyspark.sql import Window
    t = load(spark, sf, "events").select(F.col("event_type").alias("src"), F.lead("event_type").over(Window.partitionBy("user_id").orderBy("ts", "event_id")).alias("dst"))
    e = t.filter("dst is not null").groupBy("src", "dst").agg(F.count(F.lit(1)).cast("double").alias("w")).withColumn("topology", F.lit("events"))
    return P.laplacian(e).select("i", "j", "l")
