"""Stochastic gradient descent under a Polyak-Lojasiewicz condition: bounds and their check on a known quadratic."""

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def factor_and_floor(*, alpha: float, L: float, mu: float, sigma2: float, form: str = "exact") -> tuple[float, float]:
    """Per-step factor and the floor of the gap.

    exact: 1 - 2 alpha mu (1 - alpha L / 2), valid for alpha < 2 / L. simplified: 1 - alpha mu with floor alpha L sigma2 / (2 mu), valid for
    alpha <= 1 / L only.
    """
    if form == "simplified":
        if alpha > 1 / L:
            raise ValueError("the simplified bound needs a step of at most 1 / L")
        return 1 - alpha * mu, alpha * L * sigma2 / (2 * mu)
    if not 0 < alpha < 2 / L:
        raise ValueError("the step must lie below 2 / L")
    damp = 1 - alpha * L / 2
    return 1 - 2 * alpha * mu * damp, alpha * L * sigma2 / (4 * mu * damp)


def sgd_bound(k: int, *, gap0: float, **setting) -> float:
    factor, floor = factor_and_floor(**setting)
    return factor**k * gap0 + floor


def simulate_sgd(spark: SparkSession, *, alpha: float, eigs: tuple[float, ...], sigma: float, steps: int = 60, seeds: int = 400, x0: float = 1.0) -> DataFrame:
    """k, gap: mean gap of f(x) = sum(eig x^2) / 2 over seeded runs with Gaussian gradient noise of total variance sigma^2 (on the last axis)."""
    e = np.array(eigs)

    def run(batches):
        for pdf in batches:
            rows = []
            for seed in pdf["id"]:
                rng = np.random.default_rng(int(seed))
                x = np.full(len(e), x0)
                for k in range(steps + 1):
                    rows.append((k, float((e * x * x).sum() / 2)))
                    noise = np.zeros(len(e))
                    noise[-1] = rng.normal(0, sigma)
                    x = x - alpha * (e * x + noise)
            yield pd.DataFrame(rows, columns=["k", "gap"])

    return spark.range(seeds).mapInPandas(run, "k long, gap double").groupBy("k").agg(F.avg("gap").alias("gap"))


def simulate_on_rows(rows: DataFrame, *, alpha: float, eigs: tuple[float, ...], sigma: float, x0: float = 1.0) -> DataFrame:
    """k, gap: the same with gradient noise from a table. rows: run, at, v; the steps of a run go by at, its noise is v made to mean 0 and total variance sigma^2 over all rows.

    A run is a handful of rows; runs that end before step k are not in its mean.
    """
    over = rows.agg(F.avg("v").alias("m"), F.stddev_pop("v").alias("sd"))
    z = rows.crossJoin(F.broadcast(over)).select("run", "at", F.coalesce(F.try_divide(F.col("v") - F.col("m"), F.col("sd")), F.lit(0.0)).alias("z"))  # one row
    runs = z.groupBy("run").agg(F.transform(F.sort_array(F.collect_list(F.struct("at", "z"))), lambda s: s["z"]).alias("z"))
    *still, last = eigs
    step = lambda xs, n: F.concat(xs, F.array((1 - alpha * last) * F.element_at(xs, -1) - alpha * sigma * n))
    at = runs.select(F.posexplode(F.aggregate("z", F.array(F.lit(float(x0))), step)).alias("k", "x")).withColumn("k", F.col("k").cast("long"))
    quiet = sum((F.lit(e / 2 * x0 * x0) * F.pow(F.lit((1 - alpha * e) ** 2), F.col("k")) for e in still), F.lit(0.0))
    return at.groupBy("k").agg(F.avg(F.lit(last / 2) * F.col("x") * F.col("x")).alias("noisy")).select("k", (F.col("noisy") + quiet).alias("gap"))


def bound_report(spark: SparkSession, *, alpha: float, eigs: tuple[float, ...], sigma: float, **run) -> DataFrame:
    """k, gap, bound (exact form), holds (with three standard errors of slack folded into 5%)."""
    return against_bound(simulate_sgd(spark, alpha=alpha, eigs=eigs, sigma=sigma, **run), alpha=alpha, eigs=eigs, sigma=sigma, x0=run.get("x0", 1.0))


def against_bound(sim: DataFrame, *, alpha: float, eigs: tuple[float, ...], sigma: float, x0: float = 1.0) -> DataFrame:
    factor, floor = factor_and_floor(alpha=alpha, L=max(eigs), mu=min(eigs), sigma2=sigma**2)
    gap0 = sum(eigs) / 2 * x0**2
    bound = F.pow(F.lit(factor), F.col("k")) * gap0 + floor
    return sim.select("k", "gap", bound.alias("bound"), (F.col("gap") <= 1.05 * bound).alias("holds"))
