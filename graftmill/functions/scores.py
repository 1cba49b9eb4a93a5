"""Overlap scores of hypothesis and reference texts, as relations: n-gram bags, clipped matches, sums before ratios."""

from collections import Counter

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import LongType

from .text import chars, ngrams, words


def _items(col: Column, unit: str) -> Column:
    return words(col) if unit == "word" else chars(col)


def gram_matches(pairs: DataFrame, *, n: int = 4, unit: str = "word") -> DataFrame:
    """id, k, hit (clipped matches), hyp (n-grams of the hypothesis), ref, for k = 1..n. pairs: id, hyp, ref."""
    bags = []
    for side in ("hyp", "ref"):
        for k in range(1, n + 1):
            bags.append(pairs.select("id", F.lit(k).alias("k"), F.lit(side).alias("side"), F.explode(ngrams(_items(F.col(side), unit), k)).alias("g")))
    all_grams = bags[0]
    for b in bags[1:]:
        all_grams = all_grams.unionByName(b)
    count = lambda s: F.count_if(F.col("side") == s).alias(s)
    per = all_grams.groupBy("id", "k", "g").agg(count("hyp"), count("ref"))
    return per.groupBy("id", "k").agg(F.sum(F.least("hyp", "ref")).alias("hit"), F.sum("hyp").alias("hyp"), F.sum("ref").alias("ref"))


def gram_matches_by_row(pairs: DataFrame, *, n: int = 4) -> DataFrame:
    """What gram_matches gives for pairs whose ids differ, counted row by row without an exchange of n-grams. pairs: id (long), hyp, ref."""

    def run(batches):
        for batch in batches:
            out = []
            for one, h, r in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                for k in range(1, n + 1):
                    a, b = (Counter(zip(*(w[i:] for i in range(k)), strict=False)) for w in (h, r))
                    out.append((one, k, sum(min(c, b[g]) for g, c in a.items() if g in b), max(0, len(h) - k + 1), max(0, len(r) - k + 1)))
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True), types, strict=True)], names=names) if out else pa.RecordBatch.from_arrays([pa.array([], t) for t in types], names=names)

    names, types = ["id", "k", "hit", "hyp", "ref"], [pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64()]
    return pairs.select("id", words(F.col("hyp")), words(F.col("ref"))).mapInArrow(run, "id long, k int, hit long, hyp long, ref long")


def bleu_corpus(pairs: DataFrame, *, n: int = 4, unit: str = "word", only: bool = False, by: str | None = None) -> DataFrame:
    """bleu of the whole set (of each group): clipped precisions multiplied, brevity penalty, no smoothing. only: the n-gram precision alone."""
    m = gram_matches(pairs, n=n, unit=unit)
    keys = [by] if by else []
    if by:
        m = m.join(pairs.select("id", by), "id")
    s = m.groupBy(*keys).agg(*[F.coalesce(F.sum(F.when(F.col("k") == k, F.col(c))), F.lit(0)).alias(f"{c}{k}") for k in range(1, n + 1) for c in ("hit", "hyp", "ref")])
    ks = [n] if only else list(range(1, n + 1))
    logs = sum((F.ln(F.col(f"hit{k}") / F.col(f"hyp{k}")) for k in ks), F.lit(0.0)) / len(ks)
    zero = F.array_contains(F.array(*[F.col(f"hit{k}") for k in ks]).cast("array<long>"), F.lit(0).cast("long"))
    brevity = F.when(F.col("hyp1") >= F.col("ref1"), 0.0).otherwise(1 - F.col("ref1") / F.col("hyp1"))
    return s.select(*keys, F.round(F.when(zero, 0.0).otherwise(100 * F.exp(logs + brevity)), 6).alias("bleu"))


def bleu_sentence(pairs: DataFrame, *, n: int = 4, unit: str = "word", smooth: float = 1.0, matches: DataFrame | None = None) -> DataFrame:
    """id, bleu with ``smooth`` added to matches and totals; an empty reference gives no row. matches: those of the pairs, if they are there already."""
    m = gram_matches(pairs, n=n, unit=unit) if matches is None else matches
    s = m.groupBy("id").agg(*[F.coalesce(F.sum(F.when(F.col("k") == k, F.col(c))), F.lit(0)).alias(f"{c}{k}") for k in range(1, n + 1) for c in ("hit", "hyp", "ref")])
    logs = sum((F.ln((F.col(f"hit{k}") + smooth) / (F.col(f"hyp{k}") + smooth)) for k in range(1, n + 1)), F.lit(0.0)) / n
    brevity = F.when(F.col("hyp1") >= F.col("ref1"), 0.0).when(F.col("hyp1") == 0, F.lit(-1e9)).otherwise(1 - F.col("ref1") / F.col("hyp1"))
    return s.filter("ref1 > 0").select("id", F.round(100 * F.exp(logs + brevity), 6).alias("bleu"))


def rouge_n(pairs: DataFrame, n: int, *, unit: str = "word", matches: DataFrame | None = None) -> DataFrame:
    """id, recall, precision, f1 of n-grams; ids whose reference has none are left out."""
    m = (gram_matches(pairs, n=n, unit=unit) if matches is None else matches).filter(F.col("k") == n).filter("ref > 0")
    r, p = F.col("hit") / F.col("ref"), F.coalesce(F.try_divide(F.col("hit"), F.col("hyp")), F.lit(0.0))
    return m.select("id", r.alias("recall"), p.alias("precision"), F.coalesce(F.try_divide(2 * r * p, r + p), F.lit(0.0)).alias("f1"))


def lcs_length(a: list, b: list) -> int:
    """Longest common subsequence by bit rows: one big-integer step for each item of a."""
    at: dict = {}
    for i, x in enumerate(b):
        at[x] = at.get(x, 0) | 1 << i
    row = 0
    for x in a:
        u = row | at.get(x, 0)
        row = u & ~(u - ((row << 1) | 1))
    return row.bit_count()


@F.pandas_udf(LongType())
def lcs_words(a: pd.Series, b: pd.Series) -> pd.Series:
    return pd.Series([lcs_length(list(x), list(y)) for x, y in zip(a, b, strict=True)], dtype=np.int64)


def rouge_l(pairs: DataFrame) -> DataFrame:
    """id, recall, precision, f1 of the longest common subsequence of words."""
    w = pairs.select("id", words(F.col("hyp")).alias("h"), words(F.col("ref")).alias("r")).filter(F.size("r") > 0)
    w = w.withColumn("l", lcs_words("h", "r"))
    r, p = F.col("l") / F.size("r"), F.coalesce(F.try_divide(F.col("l"), F.size("h")), F.lit(0.0))
    return w.select("id", r.alias("recall"), p.alias("precision"), F.coalesce(F.try_divide(2 * r * p, r + p), F.lit(0.0)).alias("f1"))


def human_eval(scores: DataFrame, by: str) -> DataFrame:
    """Mean expert score of each group, as a percentage."""
    return scores.groupBy(by).agg(F.count(F.lit(1)).alias("n"), F.round(100 * F.avg("score"), 6).alias("human"))


def rubric_judge(pairs: DataFrame, *, matches: DataFrame | None = None) -> DataFrame:
    """id, judge: the default stand-in for a model judge, half word F1, half recall of the reference's rare (long) words; marked as stand-in."""
    f = rouge_n(pairs, 1, matches=matches).select("id", "f1")
    long = lambda c: F.array_distinct(F.filter(words(F.col(c)), lambda x: F.length(x) >= 6))
    k = pairs.select("id", long("hyp").alias("h"), long("ref").alias("r"))
    k = k.select("id", F.coalesce(F.try_divide(F.size(F.array_intersect("h", "r")), F.size("r")), F.lit(0.0)).alias("k"))
    return f.join(k, "id").select("id", F.round(50 * F.col("f1") + 50 * F.col("k"), 6).alias("judge"), F.lit(True).alias("stand_in"))


def compare(scores: DataFrame, *, reference: str) -> DataFrame:
    """method, metric, value, delta to the reference method's value, rel_gain (%), best. scores: method, metric, value (a small result table)."""
    ref = scores.filter(F.col("method") == reference).select("metric", F.col("value").alias("__ref"))
    top = scores.groupBy("metric").agg(F.max("value").alias("__top"))
    out = scores.join(ref, "metric").join(top, "metric")
    delta = F.round(F.col("value") - F.col("__ref"), 6)
    return out.select("method", "metric", "value", delta.alias("delta"), F.round(100 * F.try_divide(F.col("value") - F.col("__ref"), F.col("__ref")), 6).alias("rel_gain"), (F.col("value") == F.col("__top")).alias("best"))


def agreement(rows: DataFrame, a: str, b: str) -> DataFrame:
    """pearson and kappa of two 0/1 verdict columns, in one aggregate."""
    n, both, xa, xb = (F.count(F.lit(1)), F.sum((F.col(a) == F.col(b)).cast("double")), F.avg(F.col(a).cast("double")), F.avg(F.col(b).cast("double")))
    s = rows.agg(n.alias("n"), F.round(F.corr(F.col(a).cast("double"), F.col(b).cast("double")), 6).alias("pearson"), (both / n).alias("po"), (xa * xb + (1 - xa) * (1 - xb)).alias("pe"))
    return s.select("n", "pearson", F.round(F.try_divide(F.col("po") - F.col("pe"), 1 - F.col("pe")), 6).alias("kappa"))
