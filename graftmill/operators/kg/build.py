"""Global graphs from tables and from text, latent links, statistics."""

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from graftmill.functions.text import sentence_array
from graftmill.operators.corpus import components
from graftmill.sources.tables import load, stored

#: relation -> (table, head kind, head column, tail kind, tail column, functional)
MAPPING = {
    "customer.in_nation": ("customer", "customer", "c_custkey", "nation", "c_nationkey", True),
    "supplier.in_nation": ("supplier", "supplier", "s_suppkey", "nation", "s_nationkey", True),
    "nation.in_region": ("nation", "nation", "n_nationkey", "region", "n_regionkey", True),
    "customer.in_segment": ("customer", "customer", "c_custkey", "segment", "c_mktsegment", True),
    "part.has_brand": ("part", "part", "p_partkey", "brand", "p_brand", True),
    "part.has_type": ("part", "part", "p_partkey", "type", "p_type", True),
    "part.named": ("part", "part", "p_partkey", "name", "p_name", True),
    "order.placed_by": ("orders", "order", "o_orderkey", "customer", "o_custkey", True),
    "order.has_status": ("orders", "order", "o_orderkey", "status", "o_orderstatus", True),
    "order.has_priority": ("orders", "order", "o_orderkey", "priority", "o_orderpriority", True),
    "order.contains": ("lineitem", "order", "l_orderkey", "part", "l_partkey", False),
    "supplier.supplies": ("lineitem", "supplier", "l_suppkey", "part", "l_partkey", False),
}
PLACES = ("customer.in_nation", "supplier.in_nation", "nation.in_region", "customer.in_segment")
ATTRIBUTES = (*PLACES, "part.has_brand", "part.has_type", "part.named")

COPULA = {"en": "is", "fr": "est", "de": "ist", "es": "es"}
CONNECTIVES = ("of", "in", "to", "for", "with", "on", "at", "by", "from")
WORD = r"([^ \t\r\n,;.!?]+)"


def kg_from_tables(spark: SparkSession, sf_dir: str, relations=tuple(MAPPING)) -> DataFrame:
    """Triples of the foreign keys and attributes; multi-valued relations are made distinct."""
    out = None
    for name in relations:
        table, hk, hc, tk, tc, functional = MAPPING[name]
        one = load(spark, sf_dir, table).select(F.concat(F.lit(f"{hk}:"), F.col(hc)).alias("h"), F.lit(name.split(".")[1]).alias("r"), F.concat(F.lit(f"{tk}:"), F.col(tc)).alias("t"))
        one = one if functional else one.distinct()
        out = one if out is None else out.unionByName(one)
    return out


def kg_schema(spark: SparkSession) -> DataFrame:
    """relation, domain, range, functional: a few rows."""
    rows = [(name.split(".")[1], hk, tk, f) for name, (_, hk, _, tk, _, f) in MAPPING.items()]
    return spark.createDataFrame(rows, "relation string, domain string, range string, functional boolean")


def kind_of(entity: Column) -> Column:
    return F.substring_index(entity, ":", 1)


def extract_copular(docs: DataFrame) -> DataFrame:
    """doc_id, h, r, t for 'word copula word' in the copula of the document's language."""
    sent = docs.select("doc_id", "lang", F.explode(sentence_array(F.col("text"))).alias("s"))
    r = F.coalesce(*[F.when(F.col("lang") == k, F.lit(v)) for k, v in COPULA.items()])
    pattern = F.concat(F.lit(WORD + " "), r, F.lit(" " + WORD))
    pairs = F.arrays_zip(F.regexp_extract_all("s", pattern, F.lit(1)).alias("h"), F.regexp_extract_all("s", pattern, F.lit(2)).alias("t"))
    return sent.filter(r.isNotNull()).select("doc_id", r.alias("r"), F.inline(pairs).alias("h", "t")).select("doc_id", F.lower("h").alias("h"), "r", F.lower("t").alias("t"))


def extract_connective(docs: DataFrame, lang: str = "en") -> DataFrame:
    """doc_id, h, r, t for 'word preposition word'."""
    sent = docs.filter(F.col("lang") == lang).select("doc_id", F.explode(sentence_array(F.col("text"))).alias("s"))
    pattern = F.lit(f"{WORD} ({'|'.join(CONNECTIVES)}) {WORD}")
    parts = F.arrays_zip(*[F.regexp_extract_all("s", pattern, F.lit(i)).alias(n) for i, n in ((1, "h"), (2, "r"), (3, "t"))])
    return sent.select("doc_id", F.inline(parts).alias("h", "r", "t")).select("doc_id", F.lower("h").alias("h"), "r", F.lower("t").alias("t"))


EXTRACTORS = {"copular": extract_copular, "connective": extract_connective}


def build_global_kg(docs: DataFrame, *, extractors=("copular", "connective"), min_support: int = 1) -> DataFrame:
    """h, r, t, support (mentions), n_frags (documents): merged over all fragments."""
    mentions = None
    for name in extractors:
        one = EXTRACTORS[name](docs)
        mentions = one if mentions is None else mentions.unionByName(one)
    per_doc = mentions.groupBy("h", "r", "t", "doc_id").agg(F.count(F.lit(1)).alias("n"))
    return per_doc.groupBy("h", "r", "t").agg(F.sum("n").alias("support"), F.count(F.lit(1)).alias("n_frags")).filter(F.col("support") >= min_support)


def extract_dictionary(docs: DataFrame, vocabulary: DataFrame) -> DataFrame:
    """doc_id, entity, n: words of the text that the vocabulary (entity) lists. The join is left to the optimizer: a vocabulary may be large."""
    words = docs.select("doc_id", F.explode(F.split(F.lower("text"), r"[^\p{L}\p{N}]+")).alias("entity")).filter("entity <> ''")
    return words.join(vocabulary.select("entity").distinct(), "entity", "left_semi").groupBy("doc_id", "entity").agg(F.count(F.lit(1)).alias("n"))


def extract_pattern(docs: DataFrame) -> DataFrame:
    """doc_id, entity, n: capitalised words inside a sentence."""
    hits = F.explode(F.regexp_extract_all("text", F.lit(r"[^.!?\n] (\p{Lu}[\p{L}]+)"), F.lit(1)))
    return docs.select("doc_id", hits.alias("entity")).groupBy("doc_id", "entity").agg(F.count(F.lit(1)).alias("n"))


def extract_salient(docs: DataFrame, *, k: int = 5) -> DataFrame:
    """doc_id, entity, tf, df, score, rank: the k words of each document with the largest tf x ln(N / df)."""
    tf = docs.select("doc_id", F.explode(F.split(F.lower("text"), r"[^\p{L}\p{N}]+")).alias("entity")).filter("entity <> ''").groupBy("doc_id", "entity").agg(F.count(F.lit(1)).alias("tf"))
    df = tf.groupBy("entity").agg(F.count(F.lit(1)).alias("df"))
    n = docs.agg(F.count(F.lit(1)).alias("n_docs"))
    scored = tf.join(df, "entity").crossJoin(F.broadcast(n)).withColumn("score", F.round(F.col("tf") * F.ln(F.col("n_docs") / F.col("df")), 6))  # one row
    w = Window.partitionBy("doc_id").orderBy(F.desc("score"), "entity")
    return scored.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= k).drop("n_docs")


def latent_links(mentions: DataFrame, *, fragment: str, entity: str, min_count: int = 2, top_k: int = 3, block: int = 256) -> DataFrame:
    """a, b, n, pmi, rank: pairs that share fragments, by pointwise mutual information.

    Entities of fewer than ``min_count`` fragments cannot be in such a pair and are left out of the pairing. A fragment of more than
    ``block`` others is paired in blocks, one group for each pair of blocks.
    """
    m = mentions.select(F.col(fragment).alias("f"), F.col(entity).alias("e")).distinct()
    often = m.groupBy("e").agg(F.count(F.lit(1)).alias("c")).filter(F.col("c") >= min_count).select("e")
    m2 = m.join(often, "e")
    sizes = m2.groupBy("f").agg(F.ceil(F.count(F.lit(1)) / block).cast("int").alias("nb"))
    m2 = m2.join(sizes, "f").withColumn("blk", F.pmod(F.xxhash64("e"), F.col("nb")).cast("int")).withColumn("o", F.explode(F.sequence(F.lit(0), F.col("nb") - 1)))
    x, y = (m2.select("f", F.least("blk", "o").alias("lo"), F.greatest("blk", "o").alias("hi"), F.col("e").alias(e), F.col("blk").alias(f"blk_{e}")) for e in ("a", "b"))
    both = x.join(y, ["f", "lo", "hi"]).filter((F.col("a") < F.col("b")) & ((F.col("lo") == F.col("hi")) | (F.col("blk_a") != F.col("blk_b"))))
    half = both.groupBy("a", "b").agg(F.count(F.lit(1)).alias("n")).filter(F.col("n") >= min_count)
    pairs = half.select("n", F.explode(F.array(F.struct("a", "b"), F.struct(F.col("b").alias("a"), F.col("a").alias("b")))).alias("p")).select("p.a", "p.b", "n")
    each = m.groupBy("e").agg(F.count(F.lit(1)).alias("c"))
    total = m.select("f").distinct().agg(F.count(F.lit(1)).alias("frags"))
    p = pairs.join(each.select(F.col("e").alias("a"), F.col("c").alias("ca")), "a").join(each.select(F.col("e").alias("b"), F.col("c").alias("cb")), "b").crossJoin(F.broadcast(total))
    p = p.withColumn("pmi", F.round(F.ln(F.col("n").cast("double") * F.col("frags") / (F.col("ca").cast("double") * F.col("cb"))), 6))
    w = Window.partitionBy("a").orderBy(F.desc("pmi"), F.desc("n"), "b")
    return p.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= top_k).select("a", "b", "n", "pmi", "rank")


def kg_stats(triples: DataFrame, by: str | None = None) -> DataFrame:
    """triples, relations, entities (heads and tails together) of distinct triples."""
    keys = [by] if by else []
    d = triples.select(*keys, "h", "r", "t").distinct()
    n = d.groupBy(*keys).agg(F.count(F.lit(1)).alias("n_triples"), F.countDistinct("r").alias("n_relations"))
    e = d.select(*keys, F.explode(F.array("h", "t")).alias("e")).distinct().groupBy(*keys).agg(F.count(F.lit(1)).alias("n_entities"))
    return n.join(e, by) if by else n.crossJoin(e)  # one row each


def degrees(triples: DataFrame) -> DataFrame:
    return triples.select(F.explode(F.array("h", "t")).alias("node")).groupBy("node").agg(F.count(F.lit(1)).alias("degree"))


def salience(triples: DataFrame, *, iterations: int = 3, damping: float = 0.85) -> DataFrame:
    """node, rank: a few power iterations over the undirected graph, starting from 1."""
    edges = triples.select(F.col("h").alias("a"), F.col("t").alias("b")).union(triples.select("t", "h"))
    out = edges.groupBy("a").agg(F.count(F.lit(1)).alias("d"))
    rank = out.select(F.col("a").alias("node"), F.lit(1.0).alias("rank"))
    for _ in range(iterations):
        sent = edges.join(out, "a").join(rank, F.col("a") == rank["node"]).groupBy("b").agg(F.sum(F.col("rank") / F.col("d")).alias("s"))
        rank = sent.select(F.col("b").alias("node"), (F.lit(1 - damping) + damping * F.col("s")).alias("rank"))
    return rank


def communities(triples: DataFrame, *, hub_cap: int = 50) -> DataFrame:
    """node, community: connected groups once nodes of high degree are left out as connectors; a hub stands alone."""
    hubs = degrees(triples).filter(F.col("degree") > hub_cap).select("node")
    inner = triples.join(hubs, triples["h"] == hubs["node"], "left_anti").join(hubs, F.col("t") == hubs["node"], "left_anti")
    comp = components(inner.select(F.col("h").alias("src"), F.col("t").alias("dst")))
    nodes = triples.select(F.explode(F.array("h", "t")).alias("node")).distinct()
    return nodes.join(comp, "node", "left").select("node", F.coalesce("component", "node").alias("community"))


def propagated_labels(triples: DataFrame, *, rounds: int = 8) -> DataFrame:
    """node, community by synchronous label propagation: every node takes the commonest label among itself and its neighbours, ties to the smaller label.

    Labels are counted per node before anything is compared, so a hub's neighbours travel as counts. Two labellings that alternate end at the last round.
    """
    both = triples.select(F.col("h").alias("a"), F.col("t").alias("b")).union(triples.select("t", "h"))
    nodes = both.select(F.col("a").alias("b")).distinct()
    near = stored(both.unionByName(nodes.select("b", F.col("b").alias("a"))), "neighbours")
    label = nodes.select(F.col("b").alias("node"), F.col("b").alias("community"))
    for _ in range(rounds):
        n = near.join(label, near["a"] == label["node"]).groupBy("b", "community").agg(F.count(F.lit(1)).alias("n"))
        new = stored(n.groupBy(F.col("b").alias("node")).agg(F.min_by("community", F.struct(-F.col("n"), F.col("community"))).alias("community")), "labels")
        same = new.join(label.withColumnRenamed("community", "old"), "node").filter("community <> old").isEmpty()
        label = new
        if same:
            break
    return label


def community_summary(triples: DataFrame, members: DataFrame) -> DataFrame:
    """community, n_nodes, n_triples, top_relation (most frequent, ties by name)."""
    inside = triples.join(members.select(F.col("node").alias("h"), F.col("community").alias("ch")), "h").join(members.select(F.col("node").alias("t"), F.col("community").alias("ct")), "t").filter("ch = ct")
    rel = inside.groupBy(F.col("ch").alias("community"), "r").agg(F.count(F.lit(1)).alias("n"))
    top = rel.groupBy("community").agg(F.sum("n").alias("n_triples"), F.min_by("r", F.struct(-F.col("n"), F.col("r"))).alias("top_relation"))
    return members.groupBy("community").agg(F.count(F.lit(1)).alias("n_nodes")).join(top, "community", "left").select("community", "n_nodes", F.coalesce("n_triples", F.lit(0)).alias("n_triples"), "top_relation")


def kg_sample_for_plot(triples: DataFrame, *, top: int = 50) -> DataFrame:
    """The triples among the ``top`` nodes of highest degree (a sampling operator)."""
    nodes = degrees(triples).orderBy(F.desc("degree"), "node").limit(top).select("node")
    return triples.join(F.broadcast(nodes.withColumnRenamed("node", "h")), "h", "left_semi").join(F.broadcast(nodes.withColumnRenamed("node", "t")), "t", "left_semi")
