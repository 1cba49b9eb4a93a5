"""Building the question-answer corpus: cleaning, duplicates, aliases, construction, tags, splits, mixing, leak control."""

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from graftmill.functions.hashing import hash32, hash_uniform
from graftmill.functions.text import clean_text, ngrams, normalize_entity, words
from graftmill.sources.tables import stored

#: Eight themes, by channel number modulo 8.
THEMES = ("transportation", "health", "general", "environment", "equipment", "production", "electricity", "disaster")


# Cleaning and duplicates ---------------------------------------------------------------------------------------------

def dedup_exact(df: DataFrame, col: str, *, key: str = "doc_id") -> DataFrame:
    """One row for each normalised text: the smallest key and the number of copies. Partial aggregates make a hot text cheap."""
    return df.groupBy(F.md5(clean_text(F.coalesce(F.col(col), F.lit("")), lower=True)).alias("digest")).agg(F.min(key).alias(key), F.count(F.lit(1)).alias("copies"))


def minhash_bands(df: DataFrame, col: str, *, key: str = "doc_id", k: int = 5, bands: int = 16, rows: int = 4) -> DataFrame:
    """key, band, sig: one row for each band. Shingles are exploded and reduced by plain minimum aggregates."""
    grams = df.select(key, F.explode(F.array_distinct(ngrams(words(F.col(col)), k))).alias("g"))
    mins = [F.min(F.xxhash64(F.lit(i), "g")).alias(f"m{i}") for i in range(bands * rows)]
    sig = grams.groupBy(key).agg(*mins)
    parts = [F.struct(F.lit(b).alias("band"), F.xxhash64(*[f"m{b * rows + r}" for r in range(rows)]).alias("sig")) for b in range(bands)]
    return sig.select(key, F.explode(F.array(*parts)).alias("x")).select(key, "x.*")


def dedup_near(df: DataFrame, col: str, *, key: str = "doc_id", k: int = 5, bands: int = 16, rows: int = 4, jaccard: float = 0.8) -> DataFrame:
    """key, cluster: texts joined by verified near-duplicate pairs; the cluster is its smallest key.

    Members of a bucket are compared with its smallest member first. Then all pairs of a bucket that these links leave in
    different clusters are compared, in blocks, so no pair that could join two clusters is left out.
    """
    exact = dedup_exact(df, col, key=key)
    unique = df.join(exact.select(key), key, "left_semi")
    band = stored(minhash_bands(unique, col, key=key, k=k, bands=bands, rows=rows), "bands")
    low = band.groupBy("band", "sig").agg(F.min(key).alias("other"), F.count(F.lit(1)).alias("n")).filter("n > 1").drop("n")
    pairs = band.join(low, ["band", "sig"]).filter(F.col(key) > F.col("other")).select(key, "other").distinct()
    grams = lambda name: unique.select(F.col(key).alias(name), F.array_distinct(ngrams(words(F.col(col)), k)).alias(f"g_{name}"))
    shared = F.size(F.array_intersect("g_a", "g_b"))

    def verified(pairs):
        both = pairs.join(grams("a"), pairs[key] == F.col("a")).join(grams("b"), pairs["other"] == F.col("b"))
        return both.filter(shared >= jaccard * (F.size("g_a") + F.size("g_b") - shared)).select(F.col("other").alias("src"), F.col(key).alias("dst"))

    good = stored(verified(pairs), "links")
    known = components(good)
    ties = band.join(known, band[key] == known["node"], "left").select(key, "band", "sig", F.coalesce("component", key).alias("c"))
    open_ = ties.groupBy("band", "sig").agg(F.count(F.lit(1)).alias("n"), F.min("c").alias("c0"), F.max("c").alias("c1")).filter("c0 < c1")
    dealt = in_blocks(ties.join(open_.select("band", "sig", "n"), ["band", "sig"]), key, "n")
    x, y = (dealt.select("band", "sig", "lo", "hi", F.col(key).alias(name), F.col("c").alias(f"c_{name}"), F.col("blk").alias(f"blk_{name}")) for name in (key, "other"))
    apart = x.join(y, ["band", "sig", "lo", "hi"]).filter((F.col(key) > F.col("other")) & (F.col(f"c_{key}") != F.col("c_other")) & ((F.col("lo") == F.col("hi")) | (F.col(f"blk_{key}") != F.col("blk_other"))))
    comps = components(good.unionByName(verified(apart.select(key, "other").distinct())))
    digest = F.md5(clean_text(F.coalesce(F.col(col), F.lit("")), lower=True))
    first = df.select(key, digest.alias("digest")).join(exact.select("digest", F.col(key).alias("rep")), "digest")
    return first.join(comps, first["rep"] == comps["node"], "left").select(first[key], F.coalesce("component", "rep").alias("cluster"))


def in_blocks(df: DataFrame, key: str, n: str, *, block: int = 256) -> DataFrame:
    """df with blk, lo, hi: members of a group of n rows in blocks, once for each pair of blocks (lo, hi) that theirs is in."""
    df = df.withColumn("__nb", F.ceil(F.col(n) / block).cast("int")).withColumn("blk", F.pmod(F.xxhash64(key), F.col("__nb")).cast("int"))
    df = df.withColumn("__o", F.explode(F.sequence(F.lit(0), F.col("__nb") - 1)))
    return df.withColumn("lo", F.least("blk", "__o")).withColumn("hi", F.greatest("blk", "__o")).drop("__nb", "__o")


def components(edges: DataFrame, *, max_rounds: int = 50) -> DataFrame:
    """node, component (smallest node) of an edge table (src, dst): minimum labels travel until none changes."""
    both = stored(edges.select("src", "dst").union(edges.select("dst", "src")).filter("src <> dst").distinct(), "edges")
    label = stored(both.select(F.col("src").alias("node")).distinct().withColumn("component", F.col("node")), "labels")
    for _ in range(max_rounds):
        near = both.join(label, both["dst"] == label["node"]).groupBy("src").agg(F.min("component").alias("c"))
        step = label.join(near, label["node"] == near["src"], "left").select("node", F.least("component", F.coalesce("c", "component")).alias("component"))
        jump = step.select(F.col("node").alias("n2"), F.col("component").alias("c2"))
        new = stored(step.join(jump, step["component"] == jump["n2"], "left").select("node", F.coalesce("c2", "component").alias("component")), "labels")
        changed = new.join(label.withColumnRenamed("component", "old"), "node").filter("component <> old").isEmpty()
        label = new
        if changed:
            return label
    raise RuntimeError("labels did not settle")


# Aliases -------------------------------------------------------------------------------------------------------------

def resolve_synonyms(df: DataFrame, col: str, aliases: DataFrame, *, closure: bool = False, max_rounds: int = 64) -> DataFrame:
    """Replace surface forms by canonical ones; closure follows chains of any length to their end, and a name in a cycle becomes the cycle's smallest name.

    An alias with several canonical forms takes the smallest.
    """
    a = aliases.filter("alias <> canonical").groupBy(F.col("alias").alias("__alias")).agg(F.min("canonical").alias("__canonical"))
    if closure:
        a = closed(a, max_rounds)
    return df.join(a, df[col] == a["__alias"], "left").withColumn(col, F.coalesce("__canonical", col)).drop("__alias", "__canonical")


def closed(a: DataFrame, max_rounds: int) -> DataFrame:
    """Chains by doubling: a round halves what is left of each, and __least is the smallest name met on the way."""
    a = stored(a.withColumn("__least", F.col("__canonical")), "aliases")
    moves = a.count()
    for _ in range(max_rounds):
        b = a.select(F.col("__alias").alias("__next"), F.col("__canonical").alias("__far"), F.col("__least").alias("__low"))
        joined = a.join(b, a["__canonical"] == b["__next"], "left")
        a = stored(joined.select("__alias", F.coalesce("__far", "__canonical").alias("__canonical"), F.least("__least", F.coalesce("__low", "__least")).alias("__least"), F.col("__next").isNull().alias("__end")), "aliases")
        left = a.filter("not __end").count()
        if left == 0 or left == moves and a.join(a.select(F.col("__alias").alias("__x"), F.col("__least").alias("__y")), F.col("__canonical") == F.col("__x")).filter("__least <> __y").isEmpty():
            break  # what is left are cycles, and the smallest name has come round
        moves = left
        a = a.drop("__end")
    else:
        raise RuntimeError("chains of aliases did not settle")
    return a.select("__alias", F.when(F.col("__end"), F.col("__canonical")).otherwise(F.least("__least", "__alias")).alias("__canonical"))


def alias_map(names: DataFrame, col: str) -> DataFrame:
    """alias, canonical: every spelling of a name to the smallest spelling with the same normal form."""
    forms = names.select(F.col(col).alias("alias"), normalize_entity(F.col(col)).alias("form")).distinct()
    return forms.join(forms.groupBy("form").agg(F.min("alias").alias("canonical")), "form").select("alias", "canonical")


# Construction of items -----------------------------------------------------------------------------------------------

def qa_from_turns(turns: DataFrame) -> DataFrame:
    """A user turn followed by an assistant turn is an item; the conversation's system turn, if any, is its instruction."""
    w = Window.partitionBy("conv_id").orderBy("turn")
    whole = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    t = turns.withColumn("next_role", F.lead("role").over(w)).withColumn("next_text", F.lead("text").over(w))
    t = t.withColumn("system", F.first(F.when(F.col("role") == "system", F.col("text")), ignorenulls=True).over(whole))
    return t.filter("role = 'user' and next_role = 'assistant'").select("conv_id", "turn", F.coalesce("system", F.lit("Answer the question.")).alias("instruction"), F.col("text").alias("input"), F.col("next_text").alias("output"))


#: Three families of construction tasks: what to ask, and the fields of the answer.
TEMPLATES = (
    ("property", "Name the subject and its property in the passage.", ("subject", "property")),
    ("process", "Name the key elements of the process in the passage.", ("start", "steps")),
    ("equation", "Rewrite the passage as left and right side of a reaction.", ("left", "right")),
)


def build_qa(segments: DataFrame, *, key: str | tuple = "doc_id", text: str = "sent", demos: DataFrame | None = None, templates=TEMPLATES) -> DataFrame:
    """instruction, input, output of one item for each segment; the template is drawn by hash.

    The default generator puts the first word into the first field and the others into the second; demonstrations, if
    given (instruction, input, output; a small table), are put before the instruction.
    """
    key = (key,) if isinstance(key, str) else key
    pick = (hash32(*key, seed="template") % len(templates)).cast("int")
    items = segments.withColumn("template", F.element_at(F.array(*[F.lit(t[0]) for t in templates]), pick + 1))
    items = items.withColumn("instruction", F.element_at(F.array(*[F.lit(t[1]) for t in templates]), pick + 1))
    head, tail = F.element_at(F.split(text, " "), 1), F.array_join(F.slice(F.split(text, " "), F.lit(2), F.size(F.split(text, " "))), " ")
    out = F.coalesce(*[F.when(F.col("template") == t[0], F.to_json(F.struct(head.alias(t[2][0]), tail.alias(t[2][1])))) for t in templates])
    items = items.select(*key, "template", "instruction", F.col(text).alias("input"), out.alias("output"))
    if demos is not None:
        shown = demos.agg(F.array_join(F.sort_array(F.collect_list(F.concat_ws(" => ", "input", "output"))), "\n").alias("shown"))
        items = items.crossJoin(F.broadcast(shown)).withColumn("instruction", F.concat_ws("\n", "shown", "instruction")).drop("shown")
    return items


def pick_demos(items: DataFrame, pool: DataFrame, *, k: int, by: str, score: Column) -> DataFrame:
    """For each item the k pool rows of the same ``by`` with the best score (ties by demo id)."""
    joined = items.join(pool.withColumnRenamed("key", "demo"), by)
    w = Window.partitionBy("key").orderBy(F.desc("__s"), "demo")
    return joined.withColumn("__s", score).withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= k).drop("__s")


QA_SCHEMA = "instruction string, input string, output string"


def validate_qa(df: DataFrame, col: str = "json") -> DataFrame:
    """valid and reason for JSON items: malformed, missing or blank fields."""
    parsed = F.from_json(F.col(col), QA_SCHEMA + ", _bad string", {"mode": "PERMISSIVE", "columnNameOfCorruptRecord": "_bad"})
    out = df.withColumn("item", parsed)
    blank = F.array_compact(F.array(*[F.when(F.coalesce(F.trim(F.col(f"item.{f}")), F.lit("")) == "", F.lit(f)) for f in ("instruction", "input", "output")]))
    reason = F.when(F.col("item").isNull() | F.col("item._bad").isNotNull(), "malformed").when(F.size(blank) > 0, F.concat(F.lit("blank:"), F.array_join(blank, ",")))
    return out.withColumn("reason", reason).withColumn("valid", F.col("reason").isNull())


# Tags, splits, mixing ------------------------------------------------------------------------------------------------

def theme_of(source: Column) -> Column:
    number = F.expr("try_cast(substr(source, 4) as int)") if source is None else F.regexp_extract(source, r"(\d+)$", 1).try_cast("int")
    return F.coalesce(F.element_at(F.array(*[F.lit(t) for t in THEMES]), F.pmod(number, F.lit(8)) + 1), F.lit("general"))


def assign_theme(df: DataFrame) -> DataFrame:
    return df.withColumn("theme", theme_of(F.col("source")))


def theme_shares(df: DataFrame) -> DataFrame:
    """theme, n, pct of all rows."""
    n = assign_theme(df).groupBy("theme").agg(F.count(F.lit(1)).alias("n"))
    return n.withColumn("pct", F.round(100.0 * F.col("n") / F.sum("n").over(Window.partitionBy()), 6))  # eight rows


#: Second-level tags: first rule that matches wins.
TAG_RULES = ((1, "[0-9]{2,}", "measurement"), (2, "[|]", "table"), (3, "[@#]", "contact"), (4, "(?i)(license|rights)", "legal"))


def annotate_vertical(df: DataFrame, text: str, rules=TAG_RULES) -> DataFrame:
    """tags: [theme, task]."""
    task = F.coalesce(*[F.when(F.col(text).rlike(p), F.lit(tag)) for _, p, tag in sorted(rules)], F.lit("description"))
    return assign_theme(df).withColumn("task", task).withColumn("tags", F.array("theme", "task"))


def split_items(df: DataFrame, key: str, *, fractions=(0.6, 0.2, 0.2), stratify: str | None = None, group: str | None = None, seed: int = 7) -> DataFrame:
    """split: train, test or val by hash of the key (of the group, so that a group is never parted).

    stratify ranks the hashes within each stratum, so that every stratum is cut at the fractions.
    """
    u = hash_uniform(group or key, seed=seed)
    if stratify:
        df = df.withColumn("__u", F.percent_rank().over(Window.partitionBy(stratify).orderBy(hash32(group or key, seed=seed), group or key)))
        u = F.col("__u")
    out = df.withColumn("split", F.when(u < fractions[0], "train").when(u < fractions[0] + fractions[1], "test").otherwise("val"))
    return out.drop("__u")


def mix(human: DataFrame, generated: DataFrame, *, key: str = "key", ratio: float | None = None, seed: int = 7) -> DataFrame:
    """Both arms with their origin; ratio keeps that share of the generated arm, by hash."""
    if ratio is not None:
        generated = generated.filter(hash_uniform(key, seed=f"mix{seed}") < ratio)
    return human.withColumn("origin", F.lit("human")).unionByName(generated.withColumn("origin", F.lit("generated")))


def dataset_stats(items: DataFrame) -> DataFrame:
    """origin, n_train, n_test, n_val, n."""
    n = lambda s: F.count_if(F.col("split") == s).alias(f"n_{s}")
    return items.groupBy("origin").agg(n("train"), n("test"), n("val"), F.count(F.lit(1)).alias("n"))


# Leak control, profile, annotation -----------------------------------------------------------------------------------

def decontaminate(items: DataFrame, bench: DataFrame, *, key: str = "doc_id", n: int = 8) -> DataFrame:
    """key, item_id, shared: distinct word n-grams of an item that occur in a benchmark passage."""
    grams = lambda df, k: df.select(k, F.explode(F.array_distinct(ngrams(words(F.col("text")), n))).alias("g"))
    return grams(items, key).join(grams(bench, "item_id"), "g").groupBy(key, "item_id").agg(F.count(F.lit(1)).alias("shared"))


def without_leaks(items: DataFrame, bench: DataFrame, *, key: str = "doc_id", n: int = 8, min_overlap: int = 1) -> DataFrame:
    hit = decontaminate(items, bench, key=key, n=n).filter(F.col("shared") >= min_overlap).select(key).distinct()
    return items.join(hit, key, "left_anti")


def challenge_profile(docs: DataFrame, *, by: str = "lang", long_word: int = 12) -> DataFrame:
    """Per group: documents, mean and deviation of the length in words, share of long words (terms), share of rare words."""
    w = docs.select(by, "doc_id", words(F.col("text")).alias("w"))
    lengths = w.groupBy(by).agg(F.count(F.lit(1)).alias("n_docs"), F.round(F.avg(F.size("w")), 6).alias("mean_words"), F.round(F.stddev_pop(F.size("w").cast("double")), 6).alias("dev_words"),
                                F.sum(F.size(F.filter("w", lambda x: F.length(x) >= long_word))).alias("__long"), F.sum(F.size("w")).alias("__all"))
    return lengths.select(by, "n_docs", "mean_words", "dev_words", F.round(F.try_divide(F.col("__long"), F.col("__all")), 6).alias("term_density"))


def apply_annotations(df: DataFrame, verdicts: DataFrame, *, key: str = "doc_id") -> tuple[DataFrame, DataFrame]:
    """(rows with an accepting verdict, rows still to be reviewed)."""
    return df.join(verdicts.filter("accept").select(key), key, "left_semi"), df.join(verdicts.select(key), key, "left_anti")


def page_text(pages: DataFrame) -> DataFrame:
    """page_id, lang, title, n_links, plain: a crawl's raw pages by pattern (no layout)."""
    body = F.regexp_replace(F.regexp_replace(F.col("html"), r"(?is)<(script|style)[^>]*>.*?</(script|style)>|<!--.*?-->", " "), r"<[^>]+>", " ")
    return pages.select(
        "page_id", F.regexp_extract("html", r'<html[^>]*\slang="([^"]*)"', 1).alias("lang"), F.trim(F.regexp_extract("html", r"(?is)<title[^>]*>(.*?)</title>", 1)).alias("title"),
        F.regexp_count("html", F.lit(r'(?i)<a\s[^>]*href="')).cast("long").alias("n_links"), clean_text(body).alias("plain"))


def recovered(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(QA_SCHEMA).json(path)
