"""Corpus building on the given tables."""

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from graftmill.functions import text as T
from graftmill.functions.vectors import cosine, dot, l2, norm
from graftmill.operators import corpus as C
from graftmill.operators import segment as S
from graftmill.sources.tables import load

from .registry import query

WORDS_SQL = "list_filter(regexp_split_to_array(lower(coalesce(text, '')), '[ \\t\\r\\n]+'), lambda x: x <> '')"
SENTENCES_SQL = """
raw AS (SELECT doc_id, list_filter(list_transform(regexp_split_to_array(coalesce(text, ''), '[.!?\\n]+'), lambda x: trim(x)), lambda x: x <> '') AS ss FROM documents),
sent AS (SELECT doc_id, i - 1 AS sent_no, ss[i] AS sent, len(list_filter(string_split(ss[i], ' '), lambda x: x <> '')) AS n_tok FROM raw, range(1, len(ss) + 1) r(i))
"""
BUCKETS_SQL = SENTENCES_SQL + """,
gram AS (SELECT doc_id, sent_no, ('0x' || substr(md5(substr(sent, j::INT, 2)), 1, 8))::UBIGINT % 384 AS bucket FROM sent, range(1, length(sent)) r(j)),
enc AS (SELECT doc_id, sent_no, bucket::INT AS bucket, count(*) AS n FROM gram GROUP BY ALL),
norms AS (SELECT doc_id, sent_no, sum(n * n)::HUGEINT AS n2 FROM enc GROUP BY ALL),
near AS (SELECT a.doc_id, a.sent_no AS i, b.sent_no AS j, sum(a.n * b.n)::HUGEINT AS d FROM enc a JOIN enc b ON a.doc_id = b.doc_id AND a.bucket = b.bucket AND b.sent_no < a.sent_no AND b.sent_no > a.sent_no - 8 GROUP BY ALL),
pass AS (SELECT near.doc_id, i, max(j) AS j FROM near JOIN norms x ON x.doc_id = near.doc_id AND x.sent_no = i JOIN norms y ON y.doc_id = near.doc_id AND y.sent_no = j WHERE d > 0 AND 4 * d * d >= x.n2 * y.n2 GROUP BY ALL),
latest AS (SELECT sent.doc_id, sent.sent_no, n_tok, coalesce(j, -1) AS latest FROM sent LEFT JOIN pass ON pass.doc_id = sent.doc_id AND i = sent_no)
"""
SPLIT_SQL = "CASE WHEN ('0x' || substr(md5('7:' || {key}), 1, 8))::UBIGINT / 4294967296.0 < 0.6 THEN 'train' WHEN ('0x' || substr(md5('7:' || {key}), 1, 8))::UBIGINT / 4294967296.0 < 0.6 + 0.2 THEN 'test' ELSE 'val' END"
TURNS_SQL = """
t AS (SELECT *, lead(role) OVER w AS next_role, lead(text) OVER w AS next_text FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)),
sys AS (SELECT conv_id, arg_min(text, turn) AS system FROM conversations WHERE role = 'system' AND text IS NOT NULL GROUP BY conv_id),
pairs AS (SELECT t.conv_id, turn, coalesce(system, 'Answer the question.') AS instruction, text AS input, next_text AS output FROM t LEFT JOIN sys USING (conv_id) WHERE role = 'user' AND next_role = 'assistant')
"""
ITEMS_SQL = f"WITH {TURNS_SQL}, items AS (SELECT 'human' AS origin, 'c' || conv_id || ':' || turn AS key FROM pairs UNION ALL SELECT 'generated', 'd' || doc_id FROM documents), sp AS (SELECT *, {SPLIT_SQL.format(key='key')} AS split FROM items)"
THEME_SQL = "coalesce((['transportation', 'health', 'general', 'environment', 'equipment', 'production', 'electricity', 'disaster'])[try_cast(regexp_extract(source, '(\\d+)$', 1) AS INT) % 8 + 1], 'general')"


def docs(spark, sf) -> DataFrame:
    return load(spark, sf, "documents")


def items(spark, sf) -> DataFrame:
    human = C.qa_from_turns(load(spark, sf, "conversations")).select(F.concat(F.lit("c"), F.col("conv_id"), F.lit(":"), F.col("turn")).alias("key"))
    made = docs(spark, sf).select(F.concat(F.lit("d"), F.col("doc_id")).alias("key"))
    return C.mix(human, made)


@query("theme_shares", f"SELECT theme, count(*) AS n, round(100.0 * count(*) / sum(count(*)) OVER (), 6) AS pct FROM (SELECT {THEME_SQL} AS theme FROM documents) GROUP BY theme")
def theme_shares(spark, sf):
    return C.theme_shares(docs(spark, sf))


@query("split_stats", ITEMS_SQL + " SELECT origin, count(*) FILTER (split = 'train') AS n_train, count(*) FILTER (split = 'test') AS n_test, count(*) FILTER (split = 'val') AS n_val, count(*) AS n FROM sp GROUP BY origin")
def split_stats(spark, sf):
    return C.dataset_stats(C.split_items(items(spark, sf), "key"))


@query("split_stats_rollup", ITEMS_SQL + " SELECT coalesce(origin, 'all') AS origin, coalesce(split, 'all') AS split, count(*) AS n FROM sp GROUP BY ROLLUP (origin, split)")
def split_stats_rollup(spark, sf):
    r = C.split_items(items(spark, sf), "key").rollup("origin", "split").agg(F.count(F.lit(1)).alias("n"))
    return r.select(F.coalesce("origin", F.lit("all")).alias("origin"), F.coalesce("split", F.lit("all")).alias("split"), "n")


@query("split_stratified", f"""
WITH x AS (SELECT doc_id, lang, percent_rank() OVER (PARTITION BY lang ORDER BY ('0x' || substr(md5('7:' || doc_id), 1, 8))::UBIGINT, doc_id) AS u FROM documents)
SELECT lang, CASE WHEN u < 0.6 THEN 'train' WHEN u < 0.6 + 0.2 THEN 'test' ELSE 'val' END AS split, count(*) AS n FROM x GROUP BY ALL""")
def split_stratified(spark, sf):
    return C.split_items(docs(spark, sf).select("doc_id", "lang"), "doc_id", stratify="lang").groupBy("lang", "split").agg(F.count(F.lit(1)).alias("n"))


@query("split_by_conversation", f"WITH {TURNS_SQL} SELECT {SPLIT_SQL.format(key='conv_id')} AS split, count(*) AS n, count(DISTINCT conv_id) AS n_groups FROM pairs GROUP BY 1")
def split_by_conversation(spark, sf):
    p = C.split_items(C.qa_from_turns(load(spark, sf, "conversations")), "turn", group="conv_id")
    return p.groupBy("split").agg(F.count(F.lit(1)).alias("n"), F.countDistinct("conv_id").alias("n_groups"))


CLEAN_SQL = "lower(trim(regexp_replace(coalesce(text, ''), '[ \\t\\r\\n]+', ' ', 'g')))"


@query("exact_dedup", f"SELECT md5({CLEAN_SQL}) AS digest, min(doc_id) AS doc_id, count(*) AS copies FROM documents GROUP BY 1")
def exact_dedup(spark, sf):
    return C.dedup_exact(docs(spark, sf), "text")


@query("dedup_survivors", f"WITH k AS (SELECT min(doc_id) AS doc_id FROM documents GROUP BY md5({CLEAN_SQL})) SELECT lang, count(*) AS n_all, count(k.doc_id) AS n_kept FROM documents LEFT JOIN k USING (doc_id) GROUP BY lang")
def dedup_survivors(spark, sf):
    d = docs(spark, sf).select("doc_id", "lang", "text")
    kept = C.dedup_exact(d, "text").select("doc_id", F.lit(1).alias("k"))
    return d.select("doc_id", "lang").join(kept, "doc_id", "left").groupBy("lang").agg(F.count(F.lit(1)).alias("n_all"), F.count("k").alias("n_kept"))


@query("near_dedup")
def near_dedup(spark, sf):
    return C.dedup_near(docs(spark, sf).select("doc_id", "text"), "text")


def _mask_sql():
    sql, cur = [], "coalesce(text, '')"
    for name, p in T.PATTERNS.items():
        p = p.replace("'", "''")
        sql.append(f"len(regexp_extract_all({cur}, '{p}'))::BIGINT AS n_{name}")
        cur = f"regexp_replace({cur}, '{p}', '<{name}>', 'g')"
    return f"SELECT doc_id, md5({cur}) AS masked, {', '.join(sql)} FROM documents"


@query("deidentify_counts", _mask_sql())
def deidentify_counts(spark, sf):
    out = T.deidentify(docs(spark, sf).select("doc_id", "text"), "text")
    return out.select("doc_id", F.md5("masked").alias("masked"), *[f"n_{n}" for n in T.PATTERNS])


@query("sentences", f"WITH {SENTENCES_SQL} SELECT doc_id, sent_no::INT AS sent_no, md5(sent) AS sent, n_tok FROM sent")
def sentences(spark, sf):
    return T.sentences(docs(spark, sf)).withColumn("sent", F.md5("sent"))


@query("sentence_token_counts", f"WITH {SENTENCES_SQL} SELECT n_tok, count(*) AS n FROM sent GROUP BY n_tok")
def sentence_token_counts(spark, sf):
    return T.sentences(docs(spark, sf)).groupBy("n_tok").agg(F.count(F.lit(1)).alias("n"))


@query("token_df", f"SELECT w, count(DISTINCT doc_id) AS df, count(*) AS tf FROM (SELECT doc_id, unnest({WORDS_SQL}) AS w FROM documents) GROUP BY w")
def token_df(spark, sf):
    tf = docs(spark, sf).select("doc_id", F.explode(T.words(F.col("text"))).alias("w")).groupBy("w", "doc_id").agg(F.count(F.lit(1)).alias("n"))
    return tf.groupBy("w").agg(F.count(F.lit(1)).alias("df"), F.sum("n").alias("tf"))


@query("hashed_encoding", f"WITH {BUCKETS_SQL} SELECT bucket, sum(n)::BIGINT AS n, count(*) AS n_sentences FROM enc GROUP BY bucket")
def hashed_encoding(spark, sf):
    return S.encoded(docs(spark, sf)).groupBy("bucket").agg(F.sum("n").alias("n"), F.count(F.lit(1)).alias("n_sentences"))


@query("adjacent_cosine_flags", f"WITH {BUCKETS_SQL} SELECT doc_id, count(*) AS n_sentences, count(*) FILTER (latest = sent_no - 1 AND sent_no > 0) AS n_alike FROM latest GROUP BY doc_id")
def adjacent_cosine_flags(spark, sf):
    f = S.similarity_flags(docs(spark, sf), w=2)
    return f.groupBy("doc_id").agg(F.count(F.lit(1)).alias("n_sentences"), F.count_if(F.col("latest") >= 0).alias("n_alike"))


@query("window_cosine_flags", f"WITH {BUCKETS_SQL} SELECT doc_id, sent_no::INT AS sent_no, latest::INT AS latest FROM latest")
def window_cosine_flags(spark, sf):
    return S.similarity_flags(docs(spark, sf))


SEGMENTS = ("doc_id", "first_sent", "last_sent", "n_sents", "n_tok")


@query("segments_adjacent", f"""WITH {BUCKETS_SQL},
b AS (SELECT *, sum(CASE WHEN latest = sent_no - 1 AND sent_no > 0 THEN 0 ELSE 1 END) OVER (PARTITION BY doc_id ORDER BY sent_no) AS g FROM latest)
SELECT doc_id, min(sent_no)::INT AS first_sent, max(sent_no)::INT AS last_sent, count(*)::INT AS n_sents, sum(n_tok)::BIGINT AS n_tok FROM b GROUP BY doc_id, g""")
def segments_adjacent(spark, sf):
    return S.segment(docs(spark, sf), mode="adjacent", limits=False).select(*SEGMENTS)


WINDOWED_SQL = f"""WITH RECURSIVE {BUCKETS_SQL},
fold AS (SELECT doc_id, sent_no, n_tok, 0::BIGINT AS start FROM latest WHERE sent_no = 0
         UNION ALL SELECT l.doc_id, l.sent_no, l.n_tok, CASE WHEN l.latest < f.start THEN l.sent_no ELSE f.start END FROM fold f JOIN latest l ON l.doc_id = f.doc_id AND l.sent_no = f.sent_no + 1),
seg AS (SELECT doc_id, min(sent_no)::INT AS first_sent, max(sent_no)::INT AS last_sent, count(*)::INT AS n_sents, sum(n_tok)::BIGINT AS n_tok FROM fold GROUP BY doc_id, start)
"""


@query("segments_windowed", WINDOWED_SQL + "SELECT * FROM seg")
def segments_windowed(spark, sf):
    return S.segment(docs(spark, sf), limits=False).select(*SEGMENTS)


@query("segment_size_hist", WINDOWED_SQL + "SELECT n_sents, count(*) AS n FROM seg GROUP BY n_sents")
def segment_size_hist(spark, sf):
    return S.segment(docs(spark, sf), limits=False).groupBy("n_sents").agg(F.count(F.lit(1)).alias("n"))


@query("segments_pairs")
def segments_pairs(spark, sf):
    return S.segment(docs(spark, sf), mode="pairs").select("seg_no", "cap_orphan", *SEGMENTS)


@query("segments_window_components")
def segments_window_components(spark, sf):
    return S.segment(docs(spark, sf), mode="window_components").select("seg_no", "cap_orphan", *SEGMENTS)


@query("segments_final")
def segments_final(spark, sf):
    """Windowed, at least two sentences, at most 512 tokens."""
    return S.segment(docs(spark, sf)).select("seg_no", "cap_orphan", *SEGMENTS, F.md5("text").alias("text"))


@query("segments_short_policies")
def segments_short_policies(spark, sf):
    out = None
    for policy in S.POLICIES:
        one = S.segment(docs(spark, sf), short_policy=policy).groupBy("n_sents").agg(F.count(F.lit(1)).alias("n")).withColumn("policy", F.lit(policy))
        out = one if out is None else out.unionByName(one)
    return out


@query("segments_bucket_cap", f"WITH {SENTENCES_SQL}, c AS (SELECT *, (sum(n_tok) OVER (PARTITION BY doc_id ORDER BY sent_no) // 512)::BIGINT AS seg FROM sent) SELECT doc_id, seg, count(*) AS n_sents, sum(n_tok)::BIGINT AS n_tok FROM c GROUP BY doc_id, seg")
def segments_bucket_cap(spark, sf):
    s = T.sentences(docs(spark, sf))
    c = s.withColumn("seg", F.floor(F.sum("n_tok").over(Window.partitionBy("doc_id").orderBy("sent_no")) / 512).cast("long"))
    return c.groupBy("doc_id", "seg").agg(F.count(F.lit(1)).alias("n_sents"), F.sum("n_tok").alias("n_tok"))


@query("segments_greedy_cap", f"""WITH RECURSIVE {SENTENCES_SQL},
f AS (SELECT doc_id, sent_no, n_tok, n_tok AS run, 0 AS seg FROM sent WHERE sent_no = 0
      UNION ALL SELECT s.doc_id, s.sent_no, s.n_tok, CASE WHEN f.run + s.n_tok > 512 THEN s.n_tok ELSE f.run + s.n_tok END, CASE WHEN f.run + s.n_tok > 512 THEN f.seg + 1 ELSE f.seg END
      FROM f JOIN sent s ON s.doc_id = f.doc_id AND s.sent_no = f.sent_no + 1)
SELECT doc_id, seg::INT AS seg, count(*) AS n_sents, sum(n_tok)::BIGINT AS n_tok FROM f GROUP BY doc_id, seg""")
def segments_greedy_cap(spark, sf):
    """The running segment closes when the next sentence would pass 512 tokens; a fold over each document's sentence sizes, JVM-side."""
    sizes = F.transform(T.sentence_array(F.col("text")), lambda s: F.size(F.filter(F.split(s, " +"), lambda x: x != "")))
    step = lambda a, n: F.when(a["run"] + n > 512, F.struct((a["seg"] + (a["run"] > 0).cast("int")).alias("seg"), n.alias("run"), F.concat(a["out"], F.array(F.struct((a["seg"] + (a["run"] > 0).cast("int")).alias("seg"), n.alias("n")))).alias("out"))).otherwise(
        F.struct(a["seg"].alias("seg"), (a["run"] + n).alias("run"), F.concat(a["out"], F.array(F.struct(a["seg"].alias("seg"), n.alias("n")))).alias("out")))
    start = F.struct(F.lit(0).alias("seg"), F.lit(0).alias("run"), F.array().cast("array<struct<seg:int,n:int>>").alias("out"))
    x = docs(spark, sf).select("doc_id", F.inline(F.aggregate(sizes, start, step, lambda a: a["out"])))
    return x.groupBy("doc_id", "seg").agg(F.count(F.lit(1)).alias("n_sents"), F.sum("n").alias("n_tok"))


@query("qa_turn_pairs", f"WITH {TURNS_SQL} SELECT * FROM pairs")
def qa_turn_pairs(spark, sf):
    return C.qa_from_turns(load(spark, sf, "conversations"))


EVERY_SQL = f"""WITH {SENTENCES_SQL}, one AS (SELECT doc_id, sent_no, sent, string_split(sent, ' ') AS p, ('0x' || substr(md5('template:' || doc_id || ':' || sent_no), 1, 8))::UBIGINT::BIGINT % 3 AS k FROM sent)"""


def _heads():
    got = F.from_json("output", "map<string,string>")
    fields = {t[0]: t[2] for t in C.TEMPLATES}
    pick = lambda i: F.coalesce(*[F.when(F.col("template") == t, got[f[i]]) for t, f in fields.items()])
    return pick(0).alias("head"), pick(1).alias("rest")


def _verdicts(q):
    q = q.withColumn("output", F.when(F.col("doc_id") % 5 == 0, F.lit(" ")).otherwise(F.col("output")))
    j = q.withColumn("json", F.to_json(F.struct("instruction", "input", "output")))
    j = j.withColumn("json", F.when(F.col("doc_id") % 7 == 0, F.expr("substr(json, 1, length(json) div 2)")).otherwise(F.col("json")))
    return C.validate_qa(j).groupBy(F.coalesce("reason", F.lit("valid")).alias("verdict")).agg(F.count(F.lit(1)).alias("n"))


@query("qa_templates", EVERY_SQL + """ SELECT doc_id, sent_no, (['property', 'process', 'equation'])[k + 1] AS template, p[1] AS head, array_to_string(p[2:], ' ') AS rest FROM one""")
def qa_templates(spark, sf):
    """An item of every sentence of every document."""
    out = C.build_qa(T.sentences(docs(spark, sf)), key=("doc_id", "sent_no"))
    return out.select("doc_id", F.col("sent_no").cast("long").alias("sent_no"), "template", *_heads())


@query("qa_validation", EVERY_SQL + """ SELECT coalesce(CASE WHEN doc_id % 7 = 0 THEN 'malformed' WHEN doc_id % 5 = 0 THEN 'blank:output' END, 'valid') AS verdict, count(*) AS n FROM one GROUP BY 1""")
def qa_validation(spark, sf):
    """Every seventh document's items are cut in half and every fifth one's have a blank answer; the gate must find exactly these."""
    return _verdicts(C.build_qa(T.sentences(docs(spark, sf)), key=("doc_id", "sent_no")))


@query("vertical_tags", f"SELECT {THEME_SQL} AS theme, CASE WHEN regexp_matches(text, '[0-9]{{2,}}') THEN 'measurement' WHEN regexp_matches(text, '[|]') THEN 'table' WHEN regexp_matches(text, '[@#]') THEN 'contact' WHEN regexp_matches(text, '(?i)(license|rights)') THEN 'legal' ELSE 'description' END AS task, count(*) AS n FROM documents GROUP BY ALL")
def vertical_tags(spark, sf):
    return C.annotate_vertical(docs(spark, sf), "text").groupBy("theme", "task").agg(F.count(F.lit(1)).alias("n"))


@query("mix_counts", f"WITH {TURNS_SQL} SELECT 'human' AS origin, count(*) AS n FROM pairs UNION ALL SELECT 'generated', count(*) FROM documents WHERE ('0x' || substr(md5('mix7:d' || doc_id), 1, 8))::UBIGINT / 4294967296.0 < 0.4")
def mix_counts(spark, sf):
    human = C.qa_from_turns(load(spark, sf, "conversations")).select(F.concat(F.lit("c"), F.col("conv_id"), F.lit(":"), F.col("turn")).alias("key"))
    made = docs(spark, sf).select(F.concat(F.lit("d"), F.col("doc_id")).alias("key"))
    return C.mix(human, made, ratio=0.4).groupBy("origin").agg(F.count(F.lit(1)).alias("n"))


GRAMS_SQL = f"""d AS (SELECT doc_id, {WORDS_SQL} AS w FROM documents), b AS (SELECT item_id, {WORDS_SQL} AS w FROM benchmark),
dg AS (SELECT DISTINCT doc_id, array_to_string(w[i:i+7], ' ') AS g FROM d, range(1, len(w) - 6) r(i)), bg AS (SELECT DISTINCT item_id, array_to_string(w[i:i+7], ' ') AS g FROM b, range(1, len(w) - 6) r(i)),
hits AS (SELECT doc_id, item_id, count(*) AS shared FROM dg JOIN bg USING (g) GROUP BY ALL)"""


@query("decontam_hits", f"WITH {GRAMS_SQL} SELECT * FROM hits")
def decontam_hits(spark, sf):
    return C.decontaminate(docs(spark, sf), load(spark, sf, "benchmark"))


@query("decontam_clean", f"WITH {GRAMS_SQL} SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM hits)")
def decontam_clean(spark, sf):
    return C.without_leaks(docs(spark, sf), load(spark, sf, "benchmark")).select("doc_id")


@query("challenge_profile", f"""WITH w AS (SELECT lang, {WORDS_SQL} AS w FROM documents)
SELECT lang, count(*) AS n_docs, round(avg(len(w)), 6) AS mean_words, round(stddev_pop(len(w)), 6) AS dev_words, round(sum(len(list_filter(w, lambda x: length(x) >= 12))) / sum(len(w)), 6) AS term_density FROM w GROUP BY lang""")
def challenge_profile(spark, sf):
    return C.challenge_profile(docs(spark, sf))


@query("page_titles", r"""SELECT page_id, regexp_extract(html, '<html[^>]*\slang="([^"]*)"', 1) AS lang, trim(regexp_extract(html, '(?is)<title[^>]*>(.*?)</title>', 1)) AS title, len(regexp_extract_all(html, '(?i)<a\s[^>]*href="'))::BIGINT AS n_links FROM pages""")
def page_titles(spark, sf):
    return C.page_text(load(spark, sf, "pages")).drop("plain")


@query("page_plain_text")
def page_plain_text(spark, sf):
    return C.page_text(load(spark, sf, "pages")).select("page_id", F.length("plain").alias("n_chars"), F.md5("plain").alias("digest"))


@query("annotation_queue", "SELECT CASE WHEN quality IS NULL THEN 'review' WHEN quality = 1 AND toxic = 0 THEN 'accepted' ELSE 'rejected' END AS verdict, count(*) AS n FROM documents LEFT JOIN labels USING (doc_id) GROUP BY 1")
def annotation_queue(spark, sf):
    d = docs(spark, sf).select("doc_id")
    v = load(spark, sf, "labels").select("doc_id", ((F.col("quality") == 1) & (F.col("toxic") == 0)).alias("accept"))
    yes, open_ = C.apply_annotations(d, v)
    n = lambda df, s: df.agg(F.count(F.lit(1)).alias("n")).select(F.lit(s).alias("verdict"), "n")
    no = d.join(v.filter("not accept"), "doc_id", "left_semi")
    return n(yes, "accepted").unionByName(n(open_, "review")).unionByName(n(no, "rejected"))


ALIAS_SQL = """spell AS (SELECT DISTINCT p_name AS name FROM part UNION SELECT DISTINCT upper(p_name) FROM part UNION SELECT DISTINCT p_name || 's' FROM part),
form AS (SELECT name AS alias, regexp_replace(regexp_replace(lower(trim(name)), '^[^a-z0-9]+|[^a-z0-9]+$', '', 'g'), '^(.{3,}[^s])s$', '\\1') AS form FROM spell)"""


@query("alias_resolution", f"WITH {ALIAS_SQL} SELECT alias, min(alias) OVER (PARTITION BY form) AS canonical FROM form")
def alias_resolution(spark, sf):
    p = load(spark, sf, "part").select("p_name").distinct()
    spell = p.select(F.col("p_name").alias("name")).union(p.select(F.upper("p_name"))).union(p.select(F.concat("p_name", F.lit("s")))).distinct()
    m = C.alias_map(spell, "name")
    return C.resolve_synonyms(spell.select(F.col("name").alias("alias"), F.col("name").alias("canonical")), "canonical", m)


@query("entity_normal_forms", f"WITH {ALIAS_SQL} SELECT form, count(*) AS n FROM form GROUP BY form")
def entity_normal_forms(spark, sf):
    p = load(spark, sf, "part").select("p_name").distinct()
    spell = p.select(F.col("p_name").alias("name")).union(p.select(F.upper("p_name"))).union(p.select(F.concat("p_name", F.lit("s")))).distinct()
    return spell.groupBy(T.normalize_entity(F.col("name")).alias("form")).agg(F.count(F.lit(1)).alias("n"))


PAIR_SQL = "v AS (SELECT vec_id, label, embedding::DOUBLE[] AS e FROM embeddings), p AS (SELECT a.vec_id, a.label, a.e, b.e AS f FROM v a JOIN v b ON b.vec_id = a.vec_id + 1)"


@query("embedding_kernels", f"WITH {PAIR_SQL} SELECT label, count(*) AS n, round(avg(list_inner_product(e, f)), 6) AS dot, round(avg(sqrt(list_inner_product(e, e))), 6) AS norm, round(avg(list_distance(e, f)), 6) AS l2, count(*) FILTER (10 * list_inner_product(e, f) >= sqrt(list_inner_product(e, e) * list_inner_product(f, f))) AS n_alike FROM p GROUP BY label")
def embedding_kernels(spark, sf):
    e = load(spark, sf, "embeddings")
    n = e.select((F.col("vec_id") - 1).alias("vec_id"), F.col("embedding").alias("f"))
    p = e.join(n, "vec_id")
    a, b = F.col("embedding"), F.col("f")
    return p.groupBy("label").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg(dot(a, b)), 6).alias("dot"), F.round(F.avg(norm(a)), 6).alias("norm"), F.round(F.avg(l2(a, b)), 6).alias("l2"), F.count_if(cosine(a, b) >= 0.1).alias("n_alike"))


@query("longest_documents", "SELECT doc_id, n_chars FROM documents ORDER BY n_chars DESC NULLS LAST, doc_id LIMIT 20")
def longest_documents(spark, sf):
    """The twenty longest documents: a top-k report."""
    from graftmill.operators.relational import topk
    return topk(docs(spark, sf).select("doc_id", "n_chars"), [F.desc_nulls_last("n_chars"), F.col("doc_id")], 20)


REPORTED = ("theme_shares", "kg_text", "latent_links_topk", "kgc_neighbor", "exact_dedup")


@query("run_report")
def run_report(spark, sf):
    """What the plans of a few queries do: exchanges, broadcasts, joins, Python stages; and how many rows they give, as run on the tables."""
    from graftmill.plans.report import plan_report

    from .registry import QUERIES
    rows = []
    for name in REPORTED:
        df = QUERIES[name](spark, sf)
        r = plan_report(df)
        rows.append((name, *(int(r[k]) for k in ("exchanges", "broadcasts", "sort_merge_joins", "hash_joins", "nested_loops", "cartesian", "python")), df.count()))
    return spark.createDataFrame(rows, "query string, exchanges int, broadcasts int, sort_merge_joins int, hash_joins int, nested_loops int, cartesian int, python int, n_rows long")
