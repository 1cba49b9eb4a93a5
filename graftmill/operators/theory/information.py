"""Plug-in information measures from counts of cells, in nats unless a base is given.

Rows are reduced to cells (c, z, y) first, so everything after the first aggregate is as small as the number of cells.
"""

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from graftmill.functions.hashing import hash32


def cells(df: DataFrame, y: str, z: str | None, c: str | None) -> DataFrame:
    pick = lambda x, name: (F.col(x).cast("string") if x else F.lit("-")).alias(name)
    return df.groupBy(pick(c, "c"), pick(z, "z"), pick(y, "y")).agg(F.count(F.lit(1)).cast("double").alias("n"))


def measures(counts: DataFrame, *, correction: str | None = None) -> DataFrame:
    """n, h_c = H(Y|C), h_cz = H(Y|C,Z), mi, gamma, degenerate, n_cells from cells (c, z, y, n) or exact masses.

    gamma is mi / h_c, null and degenerate where h_c is 0. Miller-Madow adds (cells - groups) / 2n to each entropy.
    """
    cy = counts.groupBy("c", "y").agg(F.sum("n").alias("n"), F.count(F.lit(1)).alias("k"))
    wc = Window.partitionBy("c")
    h1 = cy.withColumn("m", F.sum("n").over(wc)).agg(F.sum("n").alias("n"), F.sum(-F.col("n") * F.ln(F.col("n") / F.col("m"))).alias("s1"), F.count(F.lit(1)).alias("k1"), F.countDistinct("c").alias("g1"))
    wz = Window.partitionBy("c", "z")
    h2 = counts.filter("n > 0").withColumn("m", F.sum("n").over(wz)).agg(F.sum(-F.col("n") * F.ln(F.col("n") / F.col("m"))).alias("s2"), F.count(F.lit(1)).alias("k2"), F.countDistinct("c", "z").alias("g2"))
    one = h1.crossJoin(h2)  # one row each
    fix = (lambda k, g: (F.col(k) - F.col(g)) / (2 * F.col("n"))) if correction == "miller-madow" else (lambda k, g: F.lit(0.0))
    a, b = F.col("s1") / F.col("n") + fix("k1", "g1"), F.col("s2") / F.col("n") + fix("k2", "g2")
    mi = F.greatest(a - b, F.lit(0.0))
    return one.select("n", a.alias("h_c"), b.alias("h_cz"), mi.alias("mi"), F.when(a > 1e-12, mi / a).alias("gamma"), (a <= 1e-12).alias("degenerate"), F.col("k2").alias("n_cells"))


def rounded(df: DataFrame, digits: int = 6) -> DataFrame:
    return df.select(*[F.round(c, digits).alias(c) if t == "double" else F.col(c) for c, t in df.dtypes])


def conditional_entropy(df: DataFrame, y: str, given: str | None) -> DataFrame:
    return measures(cells(df, y, given, None)).select(F.col("h_cz").alias("h"))


def prior_quality(df: DataFrame, y: str, z: str, given: str | None, *, correction: str | None = None) -> DataFrame:
    return measures(cells(df, y, z, given), correction=correction)


def shuffled_quality(df: DataFrame, y: str, z: str, given: str, *, key: str, shuffles: int = 5) -> DataFrame:
    """shuffle, gamma after the labels are dealt anew within each context: what plug-in bias alone gives."""
    rows = df.select(F.col(key).alias("k"), F.col(y).cast("string").alias("y"), F.col(z).cast("string").alias("z"), F.col(given).cast("string").alias("c"))
    w = lambda seed: Window.partitionBy("c").orderBy(hash32("k", seed=seed), "k")
    out = None
    for s in range(shuffles):
        a = rows.select("c", "z", F.row_number().over(w("left")).alias("i"))
        b = rows.select("c", "y", F.row_number().over(w(f"right{s}")).alias("i"))
        one = measures(cells(a.join(b, ["c", "i"]), "y", "z", "c")).select(F.lit(s).alias("shuffle"), "gamma")
        out = one if out is None else out.unionByName(one)
    return out


def garble(counts: DataFrame, kernel: DataFrame) -> DataFrame:
    """Exact law after a stochastic kernel (level, z, z2, k) on the observation: cells with level and masses n."""
    return counts.join(kernel, "z").groupBy("level", "c", F.col("z2").alias("z"), "y").agg(F.sum(F.col("n") * F.col("k")).alias("n")).filter("n > 0")


def uniform_kernel(counts: DataFrame, levels: tuple[float, ...]) -> DataFrame:
    """Replace the observation by a uniform one with probability level. The alphabet of z is small by design (a label space)."""
    z = counts.select("z").distinct()
    size = z.agg(F.count(F.lit(1)).alias("m"))
    grid = z.join(z.withColumnRenamed("z", "z2")).join(F.broadcast(size)).withColumn("level", F.explode(F.array(*[F.lit(x) for x in levels])))
    return grid.select("level", "z", "z2", (F.when(F.col("z") == F.col("z2"), 1 - F.col("level")).otherwise(0.0) + F.col("level") / F.col("m")).alias("k"))


def is_garbling(fine: DataFrame, coarse: DataFrame, kernel: DataFrame, tol: float = 1e-9) -> bool:
    """Whether the coarse joint law is the fine one pushed through the kernel (one level)."""
    made = garble(fine, kernel).select("c", "z", "y", F.col("n").alias("a"))
    gap = made.join(coarse.select("c", "z", "y", F.col("n").alias("b")), ["c", "z", "y"], "full").agg(F.max(F.abs(F.coalesce("a", F.lit(0.0)) - F.coalesce("b", F.lit(0.0))))).first()[0]
    return (gap or 0.0) <= tol


def ladder(counts: DataFrame, levels: tuple[float, ...]) -> DataFrame:
    """For each garbling level: gamma, reward (mean log-score of the true posterior), bayes_risk (one less the mean largest posterior),
    grad_variance (mean squared distance of the softmax gradient, label less posterior, from its mean of zero)."""
    g = garble(counts, uniform_kernel(counts, levels))
    wz, wc, wcy = Window.partitionBy("level", "c", "z"), Window.partitionBy("level", "c"), Window.partitionBy("level", "c", "y")
    x = g.withColumn("m", F.sum("n").over(wz)).withColumn("mc", F.sum("n").over(wc)).withColumn("my", F.sum("n").over(wcy)).withColumn("top", F.max("n").over(wz))
    s = x.groupBy("level").agg(F.sum("n").alias("n"), F.sum(F.col("n") * F.ln(F.col("n") / F.col("m"))).alias("r"), F.sum(-F.col("n") * F.ln(F.col("my") / F.col("mc"))).alias("h"), F.sum(F.col("n") * F.col("top") / F.col("m")).alias("b"), F.sum(F.col("n") * F.col("n") / F.col("m")).alias("v"))
    return s.select("level", F.round(1 + F.col("r") / F.col("h"), 6).alias("gamma"), F.round(F.col("r") / F.col("n"), 6).alias("reward"), F.round(1 - F.col("b") / F.col("n"), 6).alias("bayes_risk"), F.round(1 - F.col("v") / F.col("n"), 6).alias("grad_variance"))


def monotone(report: DataFrame) -> bool:
    """Reward never falls as gamma rises (a handful of rows)."""
    rows = sorted((r["gamma"], r["reward"]) for r in report.collect())
    return all(b[1] >= a[1] - 1e-9 for a, b in zip(rows, rows[1:], strict=False))


def fano_bound(h: float, n_labels: int, *, base: float = math.e, form: str = "exact") -> float:
    """Least error probability that an entropy of h (in units of base) allows among n_labels.

    exact subtracts the binary entropy's maximum in the same unit; printed subtracts 1 whatever the base.
    """
    one = math.log(2, base) if form == "exact" else 1.0
    return max(0.0, (h - one) / math.log(n_labels, base)) if n_labels > 1 else 0.0


def fano_column(h: Column, n_labels: Column) -> Column:
    return F.greatest(F.lit(0.0), (h - math.log(2)) / F.ln(n_labels))


class CountPredictor:
    """p(y | state) with add-lambda smoothing over the labels seen; an unseen state backs off to p(y)."""

    def __init__(self, table: DataFrame, prior: DataFrame, lam: float):
        self.table, self.prior, self.lam = table, prior, lam

    @classmethod
    def fit(cls, df: DataFrame, y: str, state: str, *, lam: float = 1.0) -> "CountPredictor":
        n = df.groupBy(F.col(state).alias("s"), F.col(y).alias("y")).agg(F.count(F.lit(1)).cast("double").alias("n"))
        prior = n.groupBy("y").agg(F.sum("n").alias("ny"))
        return cls(n, prior, lam)

    def distribution(self) -> DataFrame:
        """s, y, p for seen states and every label."""
        states = self.table.groupBy("s").agg(F.sum("n").alias("ns"))
        labels = self.prior.select("y")
        k = labels.agg(F.count(F.lit(1)).alias("k"))
        full = states.join(F.broadcast(labels)).join(F.broadcast(k)).join(self.table, ["s", "y"], "left")  # labels: a finite label space
        return full.select("s", "y", ((F.coalesce("n", F.lit(0.0)) + self.lam) / (F.col("ns") + self.lam * F.col("k"))).alias("p"))

    def evaluate(self, df: DataFrame, y: str, state: str, key: str) -> DataFrame:
        """key, p (of the true label), map_y (point prediction, ties to the smaller label), log, brier, zero_one."""
        d = self.distribution()
        best = d.groupBy("s").agg(F.min_by("y", F.struct(-F.col("p"), F.col("y"))).alias("map_y"), F.sum(F.col("p") * F.col("p")).alias("sq"))
        t = self.prior.agg(F.sum("ny").alias("t"), F.count(F.lit(1)).alias("k"), F.min_by("y", F.struct(-F.col("ny"), F.col("y"))).alias("top"))
        rows = df.select(F.col(key).alias("key"), F.col(y).alias("y"), F.col(state).alias("s"))
        j = rows.join(d, ["s", "y"], "left").join(best, "s", "left").join(self.prior, "y", "left").join(F.broadcast(t))
        back = (F.coalesce("ny", F.lit(0.0)) + self.lam) / (F.col("t") + self.lam * F.col("k"))
        p = F.coalesce("p", back)
        m = F.coalesce("map_y", "top")
        return j.select("key", p.alias("p"), m.alias("map_y"), F.ln(p).alias("log"), (2 * p - F.coalesce("sq", p * p)).alias("brier"), (m == F.col("y")).cast("double").alias("zero_one"))
