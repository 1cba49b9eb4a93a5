"""Control of a small agent system dx/dt = A x + B u with A = -L - B K: rank test, spectrum, trajectories.

A system has as many states as agents (five), so its algebra is a small dense problem; many systems are handled as groups.
"""

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

EDGES = {
    "path": [(0, 1), (1, 2), (2, 3), (3, 4)], "ring": [(0, 1), (1, 2), (2, 3), (3, 4), (4, 0)], "star": [(0, i) for i in range(1, 5)],
    "complete": [(i, j) for i in range(5) for j in range(i + 1, 5)], "tree": [(0, 1), (0, 2), (1, 3), (1, 4)],
}


# The five roles in the order in which they hand their results on, with the verifier's way back to the one that asks; fixed.
ROLES = ("master", "entities", "relations", "distiller", "verifier")
ROLE_EDGES = [(0, 1), (0, 2), (1, 3), (2, 3), (3, 4), (4, 0)]


def random_edges(seed: int, n: int = 5, p: float = 0.5) -> list[tuple[int, int]]:
    """A connected random graph: a path in shuffled order, and each other pair with probability p."""
    rng = np.random.default_rng(seed)
    order = rng.permutation(n).tolist()
    path = {tuple(sorted(e)) for e in zip(order, order[1:], strict=False)}
    return sorted(path | {(i, j) for i in range(n) for j in range(i + 1, n) if rng.random() < p})


def topologies(spark: SparkSession, randoms: int = 0, roles: bool = False) -> DataFrame:
    """topology, src, dst, w of undirected unit edges, both ways; with ``roles`` that of the agents, with ``randoms`` that many random ones."""
    edges = EDGES | ({"roles": ROLE_EDGES} if roles else {}) | {f"random {s}": random_edges(s) for s in range(randoms)}
    rows = [(name, a, b, 1.0) for name, es in edges.items() for x, y in es for a, b in ((x, y), (y, x))]
    return spark.createDataFrame(rows, "topology string, src int, dst int, w double")


def laplacian(edges: DataFrame) -> DataFrame:
    """topology, i, j, l: degree minus weight, as rows."""
    off = edges.filter("src <> dst").groupBy("topology", F.col("src").alias("i"), F.col("dst").alias("j")).agg((-F.sum("w")).alias("l"))
    diag = edges.filter("src <> dst").groupBy("topology", F.col("src").alias("i")).agg(F.sum("w").alias("l")).select("topology", "i", F.col("i").alias("j"), "l")
    return off.unionByName(diag)


def matrix(pdf: pd.DataFrame, n: int = 5) -> np.ndarray:
    out = np.zeros((n, n))
    out[pdf["i"].to_numpy(int), pdf["j"].to_numpy(int)] = pdf["l"]
    return out


def controllability_rank(a: np.ndarray, b: np.ndarray) -> int:
    cols, block = [], b
    for _ in range(len(a)):
        cols.append(block)
        block = a @ block
    return int(np.linalg.matrix_rank(np.hstack(cols), tol=1e-8))


def controllability(lap: DataFrame, *, gain: float = 1.0, n: int = 5) -> DataFrame:
    """topology, node (the input), rank, rank_feedback (after u = -K x), spectrum of -L, stable."""

    def one(pdf: pd.DataFrame) -> pd.DataFrame:
        l, rows = matrix(pdf, n), []
        for node in range(n):
            b = np.zeros((n, 1))
            b[node] = 1
            k = np.zeros((1, n))
            k[0, node] = gain
            closed = -l - b @ k
            rows.append((pdf["topology"].iloc[0], node, controllability_rank(-l, b), controllability_rank(closed, b), [round(float(x) + 0.0, 6) for x in sorted(np.linalg.eigvals(-l).real)], bool(np.linalg.eigvals(closed).real.max() < -1e-9)))
        return pd.DataFrame(rows, columns=["topology", "node", "rank", "rank_feedback", "spectrum", "stable"])

    return lap.groupBy("topology").applyInPandas(one, "topology string, node int, rank int, rank_feedback int, spectrum array<double>, stable boolean")


def simulate_agents(lap: DataFrame, starts: DataFrame, *, gain: float = 1.0, dt: float = 0.05, steps: int = 200, node: int = 0, control: str = "central", n: int = 5) -> DataFrame:
    """topology, x0_id, step, agent, x: exact steps of the closed loop from each start (x0_id, x0). decentral: every agent feeds back how far it is from the mean of its neighbours, which is all that it sees of the others."""

    def one(key, l_pdf: pd.DataFrame, x_pdf: pd.DataFrame) -> pd.DataFrame:
        l = matrix(l_pdf, n)
        k = np.zeros((n, n))
        if control == "decentral":
            k = gain * l / np.maximum(np.diag(l), 1e-12)[:, None]
        elif control != "central":
            raise ValueError("control must be central or decentral")
        k[node, node] += gain
        w, v = np.linalg.eig((-l - k) * dt)
        step = (v @ np.diag(np.exp(w)) @ np.linalg.inv(v)).real
        rows = []
        for i, x0 in zip(x_pdf["x0_id"], x_pdf["x0"], strict=True):
            x = np.array(x0, float)
            for s in range(steps + 1):
                rows += [(key[0], int(i), s, a, float(x[a])) for a in range(n)]
                x = step @ x
        return pd.DataFrame(rows, columns=["topology", "x0_id", "step", "agent", "x"])

    names = lap.select(F.col("topology").alias("name")).distinct()
    grid = starts.join(names).select(F.col("name").alias("grid_topology"), "x0_id", "x0")  # both sides are handfuls of rows
    return lap.groupBy("topology").cogroup(grid.groupBy("grid_topology")).applyInPandas(one, "topology string, x0_id int, step int, agent int, x double")


def settle_time(traj: DataFrame, *, tol: float = 0.05) -> DataFrame:
    """topology, agent, settle: first step from which every start stays within tol of its last value."""
    w = Window.partitionBy("topology", "x0_id", "agent")
    last = F.max_by("x", "step").over(w)
    off = traj.withColumn("off", F.abs(F.col("x") - last) > tol)
    per = off.groupBy("topology", "x0_id", "agent").agg(F.coalesce(F.max(F.when(F.col("off"), F.col("step"))), F.lit(-1)).alias("m"))
    return per.groupBy("topology", "agent").agg((F.max("m") + 1).alias("settle"))
