"""Graphs from tables and text, local graphs, verification, completion and instruction samples on the given tables."""

from pyspark.sql import functions as F

from graftmill.operators.kg import build as K
from graftmill.operators.kg import complete as M
from graftmill.operators.kg import local as L
from graftmill.operators.kg import verify as V
from graftmill.sources.tables import load

from .corpus import SENTENCES_SQL
from .registry import query

_SQL = {name: f"SELECT {'' if f else 'DISTINCT '}'{hk}:' || {hc} AS h, '{name.split('.')[1]}' AS r, '{tk}:' || {tc} AS t FROM {table}" for name, (table, hk, hc, tk, tc, f) in K.MAPPING.items()}


def kg_sql(names, alias: str = "kg") -> str:
    return f"{alias} AS ({' UNION ALL '.join(_SQL[n] for n in names)})"


FULL, PLACES, ATTR = kg_sql(K.MAPPING), kg_sql(K.PLACES), kg_sql(K.ATTRIBUTES)
STATS = "(SELECT count(*) FROM (SELECT DISTINCT h, r, t FROM {0})) AS n_triples, (SELECT count(DISTINCT r) FROM {0}) AS n_relations, (SELECT count(*) FROM (SELECT h FROM {0} UNION SELECT t FROM {0})) AS n_entities"


def seeds(spark, sf, every: int = 1):
    """The query set of the local-graph workloads: the customers whose key is divisible by ``every``."""
    c = load(spark, sf, "customer").filter(F.col("c_custkey") % every == 0)
    return c.select(F.col("c_custkey").cast("long").alias("q_id"), F.concat(F.lit("customer:"), F.col("c_custkey")).alias("entity"))


@query("kg_relational", f"WITH {FULL} SELECT r, split_part(h, ':', 1) AS domain, count(*) AS n_triples, count(DISTINCT h) AS n_heads, count(DISTINCT t) AS n_tails FROM kg GROUP BY ALL")
def kg_relational(spark, sf):
    kg = K.kg_from_tables(spark, sf)
    return kg.groupBy("r", K.kind_of(F.col("h")).alias("domain")).agg(F.count(F.lit(1)).alias("n_triples"), F.countDistinct("h").alias("n_heads"), F.countDistinct("t").alias("n_tails"))


@query("kg_stats_relational", f"WITH {FULL} SELECT {STATS.format('kg')}")
def kg_stats_relational(spark, sf):
    return K.kg_stats(K.kg_from_tables(spark, sf))


@query("entity_degree", f"WITH {FULL} SELECT degree, count(*) AS n FROM (SELECT count(*) AS degree FROM (SELECT h AS e FROM kg UNION ALL SELECT t FROM kg) GROUP BY e) GROUP BY degree")
def entity_degree(spark, sf):
    return K.degrees(K.kg_from_tables(spark, sf)).groupBy("degree").agg(F.count(F.lit(1)).alias("n"))


W = r"([^ \t\r\n,;.!?]+)"
COP_SQL = SENTENCES_SQL + ", cp AS (" + " UNION ALL ".join(f"SELECT doc_id, lower(unnest(regexp_extract_all(sent, '{W} {v} {W}', 1))) AS h, '{v}' AS r, lower(unnest(regexp_extract_all(sent, '{W} {v} {W}', 2))) AS t FROM sent JOIN documents USING (doc_id) WHERE lang = '{k}'" for k, v in K.COPULA.items()) + ")"
CN = f"{W} ({'|'.join(K.CONNECTIVES)}) {W}"
CON_SQL = f", cn AS (SELECT doc_id, lower(unnest(regexp_extract_all(sent, '{CN}', 1))) AS h, unnest(regexp_extract_all(sent, '{CN}', 2)) AS r, lower(unnest(regexp_extract_all(sent, '{CN}', 3))) AS t FROM sent JOIN documents USING (doc_id) WHERE lang = 'en')"
TEXT_SQL = COP_SQL + CON_SQL + ", tk AS (SELECT h, r, t, count(*) AS support, count(DISTINCT doc_id) AS n_frags FROM (SELECT * FROM cp UNION ALL SELECT * FROM cn) GROUP BY h, r, t)"


@query("rte_copular", f"WITH {COP_SQL} SELECT r, count(*) AS n, count(DISTINCT h || chr(9) || t) AS n_distinct FROM cp GROUP BY r")
def rte_copular(spark, sf):
    x = K.extract_copular(load(spark, sf, "documents"))
    return x.groupBy("r").agg(F.count(F.lit(1)).alias("n"), F.countDistinct("h", "t").alias("n_distinct"))


@query("rte_connective", f"WITH {SENTENCES_SQL}{CON_SQL} SELECT r, count(*) AS n, count(DISTINCT h || chr(9) || t) AS n_distinct FROM cn GROUP BY r")
def rte_connective(spark, sf):
    x = K.extract_connective(load(spark, sf, "documents"))
    return x.groupBy("r").agg(F.count(F.lit(1)).alias("n"), F.countDistinct("h", "t").alias("n_distinct"))


@query("kg_text", f"WITH {TEXT_SQL} SELECT * FROM tk WHERE support >= 2")
def kg_text(spark, sf):
    return K.build_global_kg(load(spark, sf, "documents"), min_support=2)


@query("kg_stats_text", f"WITH {TEXT_SQL} SELECT 'copular' AS method, {STATS.format('cp')} UNION ALL SELECT 'connective', {STATS.format('cn')} UNION ALL SELECT 'both', {STATS.format('tk')}")
def kg_stats_text(spark, sf):
    d = load(spark, sf, "documents")
    a, b = K.extract_copular(d).select("h", "r", "t"), K.extract_connective(d).select("h", "r", "t")
    tag = lambda x, m: x.select(F.lit(m).alias("method"), "h", "r", "t")
    return K.kg_stats(tag(a, "copular").unionByName(tag(b, "connective")).unionByName(tag(a, "both")).unionByName(tag(b, "both")), by="method")


@query("kg_text_support", f"WITH {TEXT_SQL} SELECT n_frags, count(*) AS n, sum(support)::BIGINT AS support FROM tk GROUP BY n_frags")
def kg_text_support(spark, sf):
    return K.build_global_kg(load(spark, sf, "documents")).groupBy("n_frags").agg(F.count(F.lit(1)).alias("n"), F.sum("support").alias("support"))


@query("entities_dictionary", f"""WITH v AS (SELECT DISTINCT unnest(regexp_split_to_array(lower(text), '[^\\p{{L}}\\p{{N}}]+')) AS entity FROM benchmark),
w AS (SELECT doc_id, unnest(regexp_split_to_array(lower(text), '[^\\p{{L}}\\p{{N}}]+')) AS entity FROM documents)
SELECT entity, count(*) AS n, count(DISTINCT doc_id) AS n_docs FROM w WHERE entity <> '' AND entity IN (SELECT entity FROM v) GROUP BY entity""")
def entities_dictionary(spark, sf):
    vocab = load(spark, sf, "benchmark").select(F.explode(F.split(F.lower("text"), r"[^\p{L}\p{N}]+")).alias("entity"))
    x = K.extract_dictionary(load(spark, sf, "documents"), vocab)
    return x.groupBy("entity").agg(F.sum("n").alias("n"), F.count(F.lit(1)).alias("n_docs"))


@query("entities_pattern", r"WITH x AS (SELECT doc_id, unnest(regexp_extract_all(text, '[^.!?\n] (\p{Lu}[\p{L}]+)', 1)) AS entity FROM documents) SELECT doc_id, count(*) AS n, count(DISTINCT entity) AS n_entities FROM x GROUP BY doc_id")
def entities_pattern(spark, sf):
    return K.extract_pattern(load(spark, sf, "documents")).groupBy("doc_id").agg(F.sum("n").alias("n"), F.count(F.lit(1)).alias("n_entities"))


@query("entities_salient", r"""WITH w AS (SELECT doc_id, unnest(regexp_split_to_array(lower(text), '[^\p{L}\p{N}]+')) AS entity FROM documents),
tf AS (SELECT doc_id, entity, count(*) AS tf FROM w WHERE entity <> '' GROUP BY ALL), df AS (SELECT entity, count(*) AS df FROM tf GROUP BY entity),
s AS (SELECT doc_id, entity, tf, df, round(tf * ln((SELECT count(*) FROM documents)::DOUBLE / df), 6) AS score FROM tf JOIN df USING (entity))
SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY doc_id ORDER BY score DESC, entity)::INT AS rank FROM s) WHERE rank <= 5""")
def entities_salient(spark, sf):
    return K.extract_salient(load(spark, sf, "documents"))


@query("latent_links_topk", """WITH m AS (SELECT DISTINCT l_orderkey AS f, l_partkey AS e FROM lineitem), k AS (SELECT f FROM m GROUP BY f HAVING count(*) BETWEEN 2 AND 200), m2 AS (SELECT * FROM m WHERE f IN (SELECT f FROM k)),
p AS (SELECT x.e AS a, y.e AS b, count(*) AS n FROM m2 x JOIN m2 y ON x.f = y.f AND x.e <> y.e GROUP BY ALL HAVING count(*) >= 2), c AS (SELECT e, count(*) AS c FROM m GROUP BY e),
s AS (SELECT a, b, n, round(ln(n::DOUBLE * (SELECT count(DISTINCT f) FROM m) / (ca.c::DOUBLE * cb.c)), 6) AS pmi FROM p JOIN c ca ON ca.e = a JOIN c cb ON cb.e = b)
SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY a ORDER BY pmi DESC, n DESC, b)::INT AS rank FROM s) WHERE rank <= 3""")
def latent_links_topk(spark, sf):
    return K.latent_links(load(spark, sf, "lineitem"), fragment="l_orderkey", entity="l_partkey")


@query("kg_communities")
def kg_communities(spark, sf):
    kg = K.kg_from_tables(spark, sf, K.ATTRIBUTES)
    return K.community_summary(kg, K.communities(kg, hub_cap=200))


@query("kg_label_communities")
def kg_label_communities(spark, sf):
    """Communities by label propagation, with their sizes and commonest relations."""
    kg = K.kg_from_tables(spark, sf, K.ATTRIBUTES)
    return K.community_summary(kg, K.propagated_labels(kg))


@query("kg_salience")
def kg_salience(spark, sf):
    return K.salience(K.kg_from_tables(spark, sf, K.ATTRIBUTES)).select("node", F.round("rank", 6).alias("rank"))


@query("kg_plot_sample")
def kg_plot_sample(spark, sf):
    return K.kg_sample_for_plot(K.kg_from_tables(spark, sf, K.PLACES))


BFS_SQL = """WITH RECURSIVE {kg}, deg AS (SELECT e, count(*) AS d FROM (SELECT h AS e FROM kg UNION ALL SELECT t FROM kg) GROUP BY e),
adj AS (SELECT h AS node, t AS nbr FROM kg UNION ALL SELECT t, h FROM kg JOIN deg ON e = t WHERE d <= {cap}),
walk AS (SELECT c_custkey::BIGINT AS q_id, 'customer:' || c_custkey AS node, 0 AS hop FROM customer WHERE c_custkey % {every} = 0
         UNION SELECT q_id, nbr, hop + 1 FROM walk JOIN adj USING (node) WHERE hop < {hops}),
node AS (SELECT q_id, node, min(hop) AS hop FROM walk GROUP BY ALL)
"""


@query("bfs_hops", BFS_SQL.format(kg=PLACES, cap=20, hops=3, every=1) + "SELECT q_id, hop::INT AS hop, count(*) AS n FROM node GROUP BY ALL")
def bfs_hops(spark, sf):
    n = L.local_nodes(K.kg_from_tables(spark, sf, K.PLACES), seeds(spark, sf), hub_cap=20, max_hops=3)
    return n.groupBy("q_id", "hop").agg(F.count(F.lit(1)).alias("n"))


@query("lhkg_fixpoint", BFS_SQL.format(kg=PLACES, cap=-1, hops=5, every=1) + ", e AS (SELECT a.q_id, h, r, t FROM kg JOIN node a ON a.node = h JOIN node b ON b.node = t AND b.q_id = a.q_id) SELECT q_id, count(*) AS n_triples, count(DISTINCT r) AS n_relations FROM e GROUP BY q_id")
def lhkg_fixpoint(spark, sf):
    """Out edges until nothing new."""
    kg = K.kg_from_tables(spark, sf, K.PLACES)
    x = L.local_kg(kg, L.local_nodes(kg, seeds(spark, sf), direction="out"))
    return x.groupBy("q_id").agg(F.count(F.lit(1)).alias("n_triples"), F.countDistinct("r").alias("n_relations"))


@query("lhkg_hub_growth", BFS_SQL.format(kg=PLACES, cap=1000000, hops=2, every=50) + "SELECT hop::INT AS hop, count(*) AS n FROM node GROUP BY hop")
def lhkg_hub_growth(spark, sf):
    """Without a hub cap, from one customer in fifty: two hops reach every customer of the nation and the segment; seeds with the same neighbours are walked once."""
    return L.hop_counts(K.kg_from_tables(spark, sf, K.PLACES), seeds(spark, sf, 50), max_hops=2)


@query("lhkg_hub_growth_all")
def lhkg_hub_growth_all(spark, sf):
    """The same from every customer; groups of customers with the same neighbours are walked once."""
    return L.hop_counts(K.kg_from_tables(spark, sf, K.PLACES), seeds(spark, sf), max_hops=2)


@query("lhkg_beam", f"""WITH {PLACES}, deg AS (SELECT e, count(*) AS d FROM (SELECT h AS e FROM kg UNION ALL SELECT t FROM kg) GROUP BY e),
adj AS (SELECT h AS node, t AS nbr FROM kg UNION ALL SELECT t, h FROM kg JOIN deg ON e = t WHERE d <= 100),
v0 AS (SELECT c_custkey::BIGINT AS q_id, 'customer:' || c_custkey AS node FROM customer),
v1 AS (SELECT q_id, nbr AS node FROM (SELECT q_id, nbr, row_number() OVER (PARTITION BY q_id ORDER BY count(*) DESC, nbr) AS k FROM v0 JOIN adj USING (node) GROUP BY q_id, nbr) WHERE k <= 3),
v2 AS (SELECT q_id, nbr AS node FROM (SELECT q_id, nbr, row_number() OVER (PARTITION BY q_id ORDER BY count(*) DESC, nbr) AS k FROM v1 JOIN adj USING (node) WHERE (q_id, nbr) NOT IN (SELECT q_id, node FROM v0 UNION ALL SELECT q_id, node FROM v1) GROUP BY q_id, nbr) WHERE k <= 3)
SELECT *, 0::INT AS hop FROM v0 UNION ALL SELECT *, 1 FROM v1 UNION ALL SELECT *, 2 FROM v2""")
def lhkg_beam(spark, sf):
    return L.local_nodes(K.kg_from_tables(spark, sf, K.PLACES), seeds(spark, sf), hub_cap=100, max_hops=2, beam=3)


@query("kg_paths", f"WITH {PLACES} SELECT a.r || '/' || b.r AS rels, count(*) AS n, count(DISTINCT b.t) AS n_ends FROM kg a JOIN kg b ON b.h = a.t WHERE a.h LIKE 'customer:%' GROUP BY 1")
def kg_paths(spark, sf):
    p = L.paths(K.kg_from_tables(spark, sf, K.PLACES), seeds(spark, sf), max_len=2).filter(F.size("rels") == 2)
    return p.groupBy(F.array_join("rels", "/").alias("rels")).agg(F.count(F.lit(1)).alias("n"), F.countDistinct(F.element_at("path", -1)).alias("n_ends"))


@query("query_decomposition", f"WITH {PLACES}, q AS (SELECT c_custkey::BIGINT AS q_id FROM customer) SELECT q_id, 0 AS part_no, 'customer:' || q_id AS entity, (SELECT count(DISTINCT r) FROM kg WHERE h = 'customer:' || q_id) AS n_relations FROM q UNION ALL SELECT q_id, 1, 'nation:' || (q_id % 25), 1 FROM q")
def query_decomposition(spark, sf):
    kg = K.kg_from_tables(spark, sf, K.PLACES)
    q = seeds(spark, sf).select("q_id", F.concat(F.lit("Where is "), F.col("entity"), F.lit(" and what region has nation:"), F.col("q_id") % 25, F.lit("?")).alias("query"))
    d = L.decompose(q, kg)
    return d.select("q_id", "part_no", "entity", F.coalesce(F.size("relations"), F.lit(0)).cast("long").alias("n_relations"))


def _cut(x: str) -> str:
    return f"('0x' || substr(md5({x}), 1, 8))::UBIGINT"


CORRUPT_SQL = """ring AS (SELECT r, own, coalesce(lead(own) OVER (PARTITION BY r ORDER BY own), min(own) OVER (PARTITION BY r)) AS other FROM (SELECT DISTINCT r, t AS own FROM kg)),
bad AS (SELECT kg.h, kg.r, kg.t AS t0, CASE WHEN {cut} / 4294967296.0 < {rate} THEN other ELSE kg.t END AS t, NOT ({cut} / 4294967296.0 < {rate}) OR other = kg.t AS is_valid FROM kg JOIN ring ON ring.r = kg.r AND own = kg.t)"""
CUT7 = _cut("'corrupt7:' || kg.h || ':' || kg.r || ':' || kg.t")


def corrupt_sql(rate):
    return CORRUPT_SQL.format(cut=CUT7, rate=rate)


@query("corrupt_counts", " UNION ALL ".join(f"SELECT * FROM (WITH {ATTR}, {corrupt_sql(x)} SELECT {x} AS rate, r, count(*) AS n, count(*) FILTER (is_valid) AS n_valid FROM bad GROUP BY r)" for x in (0.5, 0.25, 0.0)))
def corrupt_counts(spark, sf):
    kg = K.kg_from_tables(spark, sf, K.ATTRIBUTES)
    out = None
    for rate in (0.5, 0.25, 0.0):
        one = V.corrupt(kg, rate=rate).groupBy("r").agg(F.count(F.lit(1)).alias("n"), F.count_if("is_valid").alias("n_valid")).select(F.lit(rate).alias("rate"), "r", "n", "n_valid")
        out = one if out is None else out.unionByName(one)
    return out


THIN_SQL = f"SELECT h, r, t, {_cut(chr(39) + 'thin7:' + chr(39) + ' || h || chr(58) || r || chr(58) || t')} / 4294967296.0 AS u FROM kg"


@query("thin_counts", f"WITH {ATTR}, u AS ({THIN_SQL}) SELECT k AS keep, count(*) AS n_triples, count(DISTINCT r) AS n_relations FROM u, (VALUES (0.3::DOUBLE), (0.6), (1.0)) v(k) WHERE u < k GROUP BY k")
def thin_counts(spark, sf):
    kg = K.kg_from_tables(spark, sf, K.ATTRIBUTES)
    out = None
    for keep in (0.3, 0.6, 1.0):
        one = V.thin(kg, keep=keep).agg(F.count(F.lit(1)).alias("n_triples"), F.countDistinct("r").alias("n_relations")).select(F.lit(keep).alias("keep"), "n_triples", "n_relations")
        out = one if out is None else out.unionByName(one)
    return out


def candidates(spark, sf, rate: float = 0.25):
    kg = K.kg_from_tables(spark, sf, K.ATTRIBUTES)
    return kg, V.corrupt(kg, rate=rate)


VERIFY_SQL = f"""WITH {ATTR}, {corrupt_sql(0.25)},
node AS (SELECT h AS e FROM kg UNION SELECT t FROM kg),
two AS (SELECT DISTINCT a.h, b.t FROM kg a JOIN kg b ON b.h = a.t),
own AS (SELECT h, r, min(t) AS t1, count(*) AS nt FROM kg GROUP BY ALL),
v AS (SELECT bad.h, bad.r, bad.t, is_valid, CASE WHEN own.nt = 1 AND own.t1 <> bad.t THEN 'functional' END AS f,
             CASE WHEN NOT EXISTS (SELECT 1 FROM kg k WHERE k.h = bad.h AND k.r = bad.r AND k.t = bad.t) AND NOT EXISTS (SELECT 1 FROM two k WHERE k.h = bad.h AND k.t = bad.t) THEN 'membership' END AS m
      FROM bad LEFT JOIN own ON own.h = bad.h AND own.r = bad.r)
"""


@query("verify_reasons", VERIFY_SQL + "SELECT r, is_valid, concat_ws(',', f, m) AS reasons, count(*) AS n FROM v GROUP BY ALL")
def verify_reasons(spark, sf):
    kg, bad = candidates(spark, sf)
    x = V.verify(bad, kg=kg, schema=K.kg_schema(spark))
    return x.groupBy("r", "is_valid", F.array_join("reasons", ",").alias("reasons")).agg(F.count(F.lit(1)).alias("n"))


@query("verify_functional", VERIFY_SQL + "SELECT r, count(*) FILTER (f IS NOT NULL) AS n_conflicts, count(*) AS n FROM v GROUP BY r")
def verify_functional(spark, sf):
    kg, bad = candidates(spark, sf)
    x = V.verify(bad, kg=kg, schema=K.kg_schema(spark), checks=("functional",))
    return x.groupBy("r").agg(F.count_if(~F.col("ok")).alias("n_conflicts"), F.count(F.lit(1)).alias("n"))


@query("kg_qa_items", f"""WITH {PLACES}, m AS (SELECT *, {_cut("'mask:' || h || ':' || r || ':' || t")} % 3 AS k, h || ' ' || replace(r, '_', ' ') || ' ' || t AS s FROM kg)
SELECT 'kgc' AS task, h || '|' || r || '|' || t AS key, concat_ws(' | ', CASE WHEN k = 0 THEN '?' ELSE h END, CASE WHEN k = 1 THEN '?' ELSE r END, CASE WHEN k = 2 THEN '?' ELSE t END) AS input, CASE k WHEN 0 THEN h WHEN 1 THEN r ELSE t END AS output FROM m
UNION ALL SELECT 'qa', h || '|' || r || '|' || t, 'What does ' || h || ' have as ' || replace(r, '_', ' ') || '?', t || ' because ' || s FROM m
UNION ALL SELECT 'rte', h, string_agg(s, '. ' ORDER BY s), to_json(list({{'h': h, 'r': r, 't': t}} ORDER BY r, t))::VARCHAR FROM m GROUP BY h""")
def kg_qa_items(spark, sf):
    return V.instructions_from_kg(K.kg_from_tables(spark, sf, K.PLACES)).select("task", "key", "input", "output")


@query("multiset_except", f"WITH {ATTR}, {corrupt_sql(0.25)} SELECT r, count(*) AS n FROM (SELECT h, r, t FROM bad EXCEPT ALL SELECT h, r, t FROM kg) GROUP BY r")
def multiset_except(spark, sf):
    kg, bad = candidates(spark, sf)
    return L.multiset_except(bad.select("h", "r", "t"), kg).groupBy("r").agg(F.count(F.lit(1)).alias("n"))


@query("consolidated_candidates", f"WITH {ATTR}, {corrupt_sql(0.25)}, c AS (SELECT h, r, t, 0.5 AS s FROM bad UNION ALL SELECT h, r, t, 0.9 FROM kg) SELECT n, score, count(*) AS n_triples FROM (SELECT count(*) AS n, max(s)::DOUBLE AS score FROM c GROUP BY h, r, t) GROUP BY ALL")
def consolidated_candidates(spark, sf):
    kg, bad = candidates(spark, sf)
    c = bad.select(F.lit(1).alias("q_id"), "h", "r", "t", F.lit(0.5).alias("score")).unionByName(kg.select(F.lit(1).alias("q_id"), "h", "r", "t", F.lit(0.9).alias("score")))
    return L.consolidate(c).groupBy(F.col("n").cast("long").alias("n"), "score").agg(F.count(F.lit(1)).alias("n_triples"))


HIDE_SQL = f"cut AS (SELECT *, {_cut(chr(39) + 'hide:' + chr(39) + ' || h || chr(58) || r || chr(58) || t')} % 10 = 0 AS hid FROM kg), rest AS (SELECT h, r, t FROM cut WHERE NOT hid), probe AS (SELECT h, r, t AS t_gold FROM cut WHERE hid)"
METRIC_SQL = "SELECT p.r, count(*) AS n, round(avg((coalesce(rank, 1000000) <= 1)::INT), 6) AS hits_1, round(avg((coalesce(rank, 1000000) <= 3)::INT), 6) AS hits_3, round(avg((coalesce(rank, 1000000) <= 10)::INT), 6) AS hits_10, round(avg(coalesce(1.0 / rank, 0)), 6) AS mrr FROM probe p LEFT JOIN ans ON ans.h = p.h AND ans.r = p.r AND ans.t = p.t_gold GROUP BY p.r"


@query("kgc_prior", f"""WITH {ATTR}, {HIDE_SQL}, top AS (SELECT * FROM (SELECT r, t, row_number() OVER (PARTITION BY r ORDER BY count(*) DESC, t) AS rank FROM rest GROUP BY r, t) WHERE rank <= 10),
ans AS (SELECT DISTINCT p.h, p.r, top.t, rank FROM probe p JOIN top USING (r)) {METRIC_SQL}""")
def kgc_prior(spark, sf):
    rest, probes = M.hide(K.kg_from_tables(spark, sf, K.ATTRIBUTES))
    return M.ranking_metrics(probes, M.by_prior(rest, probes))


@query("kgc_neighbor", f"""WITH {ATTR}, {HIDE_SQL}, n AS (SELECT g.r, g.t, a.r AS r2, a.t AS t2, count(*) AS n FROM rest g JOIN rest a ON a.h = g.h AND a.r <> g.r WHERE g.r IN (SELECT r FROM probe) GROUP BY ALL),
sh AS (SELECT *, n::DOUBLE / sum(n) OVER (PARTITION BY r, r2, t2) AS p FROM n),
s AS (SELECT q.h, q.r, sh.t, round(sum(p), 6) AS score FROM (SELECT DISTINCT h, r FROM probe) q JOIN rest a ON a.h = q.h AND a.r <> q.r JOIN sh ON sh.r = q.r AND sh.r2 = a.r AND sh.t2 = a.t GROUP BY ALL),
ans AS (SELECT h, r, t, rank FROM (SELECT *, row_number() OVER (PARTITION BY h, r ORDER BY score DESC, t) AS rank FROM s) WHERE rank <= 10) {METRIC_SQL}""")
def kgc_neighbor(spark, sf):
    rest, probes = M.hide(K.kg_from_tables(spark, sf, K.ATTRIBUTES))
    return M.ranking_metrics(probes, M.by_neighbours(rest, probes))


@query("kgc_heads", f"""WITH {ATTR}, {HIDE_SQL}, kd AS (SELECT DISTINCT r, split_part(h, ':', 1) AS kind FROM rest WHERE r IN (SELECT r FROM probe)),
lack AS (SELECT e.h, kd.r FROM (SELECT DISTINCT h FROM rest) e JOIN kd ON kd.kind = split_part(e.h, ':', 1) WHERE (e.h, kd.r) NOT IN (SELECT (h, r) FROM rest)),
n AS (SELECT g.r, g.t, a.r AS r2, a.t AS t2, count(*) AS n FROM rest g JOIN rest a ON a.h = g.h AND a.r <> g.r WHERE g.r IN (SELECT r FROM lack) GROUP BY ALL),
sh AS (SELECT *, n::DOUBLE / sum(n) OVER (PARTITION BY r, r2, t2) AS p FROM n),
s AS (SELECT q.h, q.r, sh.t, round(sum(p), 6) AS score FROM lack q JOIN rest a ON a.h = q.h AND a.r <> q.r JOIN sh ON sh.r = q.r AND sh.r2 = a.r AND sh.t2 = a.t GROUP BY ALL),
k AS (SELECT s.*, row_number() OVER (PARTITION BY s.r, s.t ORDER BY score DESC, h) AS rank FROM s WHERE (s.r, s.t) IN (SELECT (r, t_gold) FROM probe))
SELECT p.r, count(*) AS n, round(avg((coalesce(rank, 1000000) <= 10)::INT), 6) AS hits_10, round(avg(CASE WHEN rank <= 10 THEN 1.0 / rank ELSE 0 END), 6) AS mrr FROM probe p LEFT JOIN k ON k.h = p.h AND k.r = p.r AND k.t = p.t_gold GROUP BY p.r""")
def kgc_heads(spark, sf):
    """Hidden heads (?, r, t) by votes of shared attributes; a probe counts as a hit if its head is among the ten first for its tail."""
    rest, probes = M.hide(K.kg_from_tables(spark, sf, K.ATTRIBUTES))
    asked = probes.select("h", "r", F.col("t_gold").alias("t"))
    got = asked.join(M.heads_by_neighbours(rest, asked), ["h", "r", "t"], "left")
    return got.groupBy("r").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg(F.col("rank").isNotNull().cast("double")), 6).alias("hits_10"), F.round(F.avg(F.coalesce(1.0 / F.col("rank"), F.lit(0.0))), 6).alias("mrr"))


@query("kgc_vectors", f"""WITH {ATTR}, {HIDE_SQL}, n AS (SELECT g.r, g.t, a.r AS r2, a.t AS t2, count(*) AS n FROM rest g JOIN rest a ON a.h = g.h AND a.r <> g.r WHERE g.r IN (SELECT r FROM probe) GROUP BY ALL),
nn AS (SELECT r, t, sum(n * n) AS nn FROM n GROUP BY ALL), mine AS (SELECT q.h, q.r, a.r AS r2, a.t AS t2 FROM (SELECT DISTINCT h, r FROM probe) q JOIN rest a ON a.h = q.h AND a.r <> q.r),
own AS (SELECT h, r, count(*) AS m FROM mine GROUP BY ALL), dot AS (SELECT h, r, n.t, sum(n) AS dot FROM mine JOIN n USING (r, r2, t2) GROUP BY ALL),
s AS (SELECT h, r, t, round(dot::DOUBLE / sqrt((nn * m)::DOUBLE), 9) AS score FROM dot JOIN nn USING (r, t) JOIN own USING (h, r)),
ans AS (SELECT h, r, t, rank FROM (SELECT *, row_number() OVER (PARTITION BY h, r ORDER BY score DESC, t) AS rank FROM s) WHERE rank <= 10) {METRIC_SQL}""")
def kgc_vectors(spark, sf):
    """Hidden tails by the cosine of attribute vectors."""
    rest, probes = M.hide(K.kg_from_tables(spark, sf, K.ATTRIBUTES))
    return M.ranking_metrics(probes, M.by_vectors(rest, probes))


@query("kgc_relations", f"""WITH {ATTR}, {HIDE_SQL}, n AS (SELECT split_part(h, ':', 1) AS kh, split_part(t, ':', 1) AS kt, r, count(*) AS n FROM rest GROUP BY ALL), k AS (SELECT *, row_number() OVER (PARTITION BY kh, kt ORDER BY n DESC, r) AS rank FROM n)
SELECT p.r, count(*) AS n, round(avg((coalesce(rank, 1000000) = 1)::INT), 6) AS hits_1 FROM probe p LEFT JOIN k ON kh = split_part(p.h, ':', 1) AND kt = split_part(p.t_gold, ':', 1) AND k.r = p.r GROUP BY p.r""")
def kgc_relations(spark, sf):
    """Hidden relations (h, ?, t) by the kinds of the two ends."""
    rest, probes = M.hide(K.kg_from_tables(spark, sf, K.ATTRIBUTES))
    asked = probes.select("h", "r", F.col("t_gold").alias("t"))
    got = asked.join(M.relations_by_kind(rest, asked), ["h", "t", "r"], "left")
    return got.groupBy("r").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg((F.coalesce("rank", F.lit(10**6)) == 1).cast("double")), 6).alias("hits_1"))


def with_regions(spark, sf):
    """Places plus the region of every customer and supplier as an explicit triple, the goal of the composition rules."""
    kg = K.kg_from_tables(spark, sf, K.PLACES)
    two = L.paths(kg, kg.select(F.lit(0).alias("q_id"), F.col("h").alias("entity")).filter(K.kind_of(F.col("h")) != "nation").distinct(), max_len=2).filter(F.array_join("rels", "/") == "in_nation/in_region")
    return kg.unionByName(two.select(F.element_at("path", 1).alias("h"), F.lit("located_in").alias("r"), F.element_at("path", 3).alias("t")))


REGION_SQL = f"{kg_sql(K.PLACES, 'base')}, kg AS (SELECT * FROM base UNION ALL SELECT a.h, 'located_in', b.t FROM base a JOIN base b ON b.h = a.t AND a.r = 'in_nation' AND b.r = 'in_region')"
RULES_SQL = """two AS (SELECT DISTINCT a.h, a.r AS r1, b.r AS r2, b.t FROM rest a JOIN rest b ON b.h = a.t), hd AS (SELECT DISTINCT h, r AS r3 FROM rest),
base2 AS (SELECT r1, r2, r3, count(*) AS n_paths FROM two JOIN hd USING (h) GROUP BY ALL), hit AS (SELECT r1, r2, rest.r AS r3, count(*) AS support FROM two JOIN rest ON rest.h = two.h AND rest.t = two.t GROUP BY ALL),
rules AS (SELECT r1, r2, r3, n_paths, support, round(support::DOUBLE / n_paths, 6) AS conf FROM base2 JOIN hit USING (r1, r2, r3) WHERE support >= 2 AND support::DOUBLE / n_paths >= 0.5)"""


@query("rule_mining", f"WITH {REGION_SQL}, {HIDE_SQL}, {RULES_SQL} SELECT * FROM rules")
def rule_mining(spark, sf):
    rest, _ = M.hide(with_regions(spark, sf))
    return M.mine_rules(rest)


@query("rule_completion", f"""WITH {REGION_SQL}, {HIDE_SQL}, {RULES_SQL}, s AS (SELECT q.h, q.r, b.t, max(conf) AS score FROM (SELECT DISTINCT h, r FROM probe) q JOIN rest a ON a.h = q.h JOIN rest b ON b.h = a.t JOIN rules ON r1 = a.r AND r2 = b.r AND r3 = q.r GROUP BY ALL),
ans AS (SELECT h, r, t, row_number() OVER (PARTITION BY h, r ORDER BY score DESC, t) AS rank FROM s) {METRIC_SQL}""")
def rule_completion(spark, sf):
    rest, probes = M.hide(with_regions(spark, sf))
    return M.ranking_metrics(probes, M.by_rules(rest, probes, M.mine_rules(rest)))
