"""Fault diagnosis, windows and margins on the event and document tables."""

from pyspark.sql import functions as F

from graftmill.functions import text as T
from graftmill.operators import relational as R
from graftmill.operators.corpus import assign_theme
from graftmill.sources.tables import load, scratch
from graftmill.streaming import upkeep as U

from .corpus import SENTENCES_SQL, THEME_SQL, WORDS_SQL
from .registry import query


@query("error_cause_asof", """WITH e AS (SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS i FROM events),
m AS (SELECT event_id, user_id, event_type, max(CASE WHEN event_type <> 'error' THEN i END) OVER (PARTITION BY user_id ORDER BY i ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS j FROM e)
SELECT m.event_id, e.event_id AS cause_id, e.event_type AS cause_type FROM m LEFT JOIN e ON e.user_id = m.user_id AND e.i = m.j WHERE m.event_type = 'error'""")
def error_cause_asof(spark, sf):
    e = load(spark, sf, "events").select("event_id", "user_id", "event_type", "ts")
    x = R.asof_last(e.filter("event_type = 'error'"), e.filter("event_type <> 'error'"), by="user_id", ts="ts", order="event_id", cols=["event_id", "event_type"])
    return x.select("event_id", F.col("right_event_id").alias("cause_id"), F.col("right_event_type").alias("cause_type"))


@query("sessionized_events", """WITH e AS (SELECT user_id, ts, lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS p FROM events),
s AS (SELECT user_id, ts, sum(CASE WHEN p IS NULL OR ts >= p + INTERVAL 6 HOUR THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM e)
SELECT user_id, count(*) AS n_sessions, max(n) AS longest FROM (SELECT user_id, k, count(*) AS n FROM s GROUP BY ALL) GROUP BY user_id""")
def sessionized_events(spark, sf):
    e = load(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    return U.windowed_counts(e, "session", gap="6 hours").groupBy("user_id").agg(F.count(F.lit(1)).alias("n_sessions"), F.max("n").alias("longest"))


@query("tumbling_counts", "SELECT epoch(time_bucket(INTERVAL 1 DAY, ts))::BIGINT AS start, event_type, count(*) AS n FROM events GROUP BY ALL")
def tumbling_counts(spark, sf):
    e = load(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    return U.windowed_counts(e).select(F.unix_timestamp("start").alias("start"), "event_type", "n")


@query("sliding_counts", "SELECT epoch(time_bucket(INTERVAL 12 HOUR, ts))::BIGINT - k * 43200 AS start, event_type, count(*) AS n FROM events, (VALUES (0), (1)) v(k) GROUP BY ALL")
def sliding_counts(spark, sf):
    e = load(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    return U.windowed_counts(e, "sliding").select(F.unix_timestamp("start").alias("start"), "event_type", "n")


@query("cube_theme_lang", f"SELECT coalesce(theme, 'all') AS theme, coalesce(lang, 'all') AS lang, count(*) AS n, sum(n_chars)::BIGINT AS chars FROM (SELECT {THEME_SQL} AS theme, lang, n_chars FROM documents) GROUP BY CUBE (theme, lang)")
def cube_theme_lang(spark, sf):
    m = R.margins(assign_theme(load(spark, sf, "documents")).select("theme", "lang", "n_chars"), ["theme", "lang"], [F.count(F.lit(1)).alias("n"), F.sum("n_chars").alias("chars")])
    return m.select(F.coalesce("theme", F.lit("all")).alias("theme"), F.coalesce("lang", F.lit("all")).alias("lang"), "n", "chars")


@query("banded_pairs", f"WITH {SENTENCES_SQL} SELECT a.doc_id, count(*) AS n FROM sent a JOIN sent b ON a.doc_id = b.doc_id AND abs(a.sent_no - b.sent_no) < 3 WHERE a.n_tok = b.n_tok AND a.sent_no < b.sent_no GROUP BY a.doc_id")
def banded_pairs(spark, sf):
    s = T.sentences(load(spark, sf, "documents")).select("doc_id", "sent_no", "n_tok")
    j = R.banded_join(s, s, by="doc_id", pos="sent_no", width=3).filter("a_n_tok = b_n_tok and a_sent_no < b_sent_no")
    return j.groupBy(F.col("a_doc_id").alias("doc_id")).agg(F.count(F.lit(1)).alias("n"))


@query("context_retrieval", f"""WITH d AS (SELECT doc_id, unnest({WORDS_SQL}) AS term FROM documents), q AS (SELECT DISTINCT item_id AS q_id, unnest({WORDS_SQL}) AS term FROM benchmark),
tf AS (SELECT doc_id, term, count(*) AS tf FROM d GROUP BY ALL), dl AS (SELECT doc_id, sum(tf) AS dl FROM tf GROUP BY doc_id), df AS (SELECT term, count(*) AS df FROM tf GROUP BY term), st AS (SELECT count(*) AS n, avg(dl) AS mean FROM dl),
s AS (SELECT q_id, doc_id, round(sum(ln(1 + (n - df + 0.5) / (df + 0.5)) * tf * 2.2 / (tf + 1.2 * (0.25 + 0.75 * dl / mean))), 6) AS score FROM q JOIN df USING (term) JOIN tf USING (term) JOIN dl USING (doc_id), st GROUP BY ALL)
SELECT q_id, doc_id, score, rank FROM (SELECT *, row_number() OVER (PARTITION BY q_id ORDER BY score DESC, doc_id)::INT AS rank FROM s) WHERE rank <= 3""")
def context_retrieval(spark, sf):
    d = load(spark, sf, "documents").select("doc_id", F.explode(T.words(F.col("text"))).alias("term"))
    q = load(spark, sf, "benchmark").select(F.col("item_id").alias("q_id"), F.explode(T.words(F.col("text"))).alias("term"))
    return R.bm25(q, d)


def arrived(spark, sf, table):
    """The table as a folder of a few files, as a stream would find them."""
    path = scratch(spark, f"arrived-{table}")
    load(spark, sf, table).repartition(4).write.parquet(path)
    return path


@query("stream_tumbling_counts")
def stream_tumbling_counts(spark, sf):
    """The tumbling counts from a stream over the event file, all windows of the last state."""
    out = scratch(spark, "stream-counts")
    e = U.windowed_counts(U.stream_events(spark, arrived(spark, sf, "events")))
    U.run_available(e, lambda b, i: b.write.mode("overwrite").parquet(f"{out}/last") if not b.isEmpty() else None, scratch(spark, "stream-state"), mode="complete")
    return spark.read.parquet(f"{out}/last").select(F.unix_timestamp("start").alias("start"), "event_type", "n")


@query("stream_triples")
def stream_triples(spark, sf):
    """Graph supports kept up from a stream of fragments; equal to the batch graph."""
    out = scratch(spark, "stream-kg")
    U.run_available(U.stream_triples(U.stream_fragments(spark, arrived(spark, sf, "documents"))), U.upsert_kg(out), scratch(spark, "stream-kg-state"))
    return U.read_kg(spark, out)
