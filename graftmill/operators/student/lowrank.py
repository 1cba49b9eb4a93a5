"""A softmax student whose weights are frozen but for a low-rank update (alpha / rank) B A.

An epoch is one pass: every partition walks through its rows in batches from the same start, and the driver averages what the partitions end with,
weighted by rows. A partition sends rank x (inputs + labels) numbers. The published setting is the default; a linear stand-in needs a larger rate, given by argument.
"""

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame

RANK, ALPHA, LR, BATCH, EPOCHS = 16, 64, 2e-5, 64, 5


class LowRankStudent:
    def __init__(self, dim: int, labels: list[str], *, rank: int = RANK, alpha: float = ALPHA, lr: float = LR, batch: int = BATCH, epochs: int = EPOCHS, seed: int = 0):
        rng = np.random.default_rng(seed)
        self.dim, self.labels, self.rank, self.lr, self.batch, self.epochs = dim, labels, rank, lr, batch, epochs
        self.scale = alpha / rank
        self.w0 = np.zeros((len(labels), dim))
        self.a = rng.normal(0, dim**-0.5, (rank, dim))
        self.b = np.zeros((len(labels), rank))
        self.log: list[tuple[int, float]] = []

    def weights(self) -> np.ndarray:
        return self.w0 + self.scale * self.b @ self.a

    def fit(self, rows: DataFrame) -> "LowRankStudent":
        """rows: key, x (array of dim doubles), y. The log holds the mean loss of each epoch, taken before each batch's step."""
        index, scale, lr, size = {y: i for i, y in enumerate(self.labels)}, self.scale, self.lr, self.batch
        w0, n_labels, dim, rank = self.w0, len(self.labels), self.dim, self.rank
        dealt = rows.select("x", "y")
        for epoch in range(self.epochs):
            start = rows.sparkSession.sparkContext.broadcast((self.a, self.b))  # rank x (dim + labels), a fixed size

            def walk(batches, start=start):
                a, b = (m.copy() for m in start.value)
                loss, n = 0.0, 0
                for pdf in batches:
                    for lo in range(0, len(pdf), size):
                        part = pdf.iloc[lo:lo + size]
                        x, y = np.array(part["x"].tolist()), part["y"].map(index).to_numpy()
                        z = x @ (w0 + scale * b @ a).T
                        z -= z.max(axis=1, keepdims=True)
                        p = np.exp(z) / np.exp(z).sum(axis=1, keepdims=True)
                        loss -= float(np.log(p[np.arange(len(y)), y]).sum())
                        n += len(y)
                        p[np.arange(len(y)), y] -= 1
                        g = p.T @ x / len(y)
                        a, b = a - lr * scale * b.T @ g, b - lr * scale * g @ a.T
                if n:
                    yield pd.DataFrame({"loss": [loss], "n": [n], "a": [a.ravel().tolist()], "b": [b.ravel().tolist()]})

            ends = dealt.mapInPandas(walk, "loss double, n long, a array<double>, b array<double>").collect()
            n = sum(r["n"] for r in ends)
            if not n:
                break
            self.a = np.sum([np.array(r["a"]) * r["n"] for r in ends], axis=0).reshape(rank, dim) / n
            self.b = np.sum([np.array(r["b"]) * r["n"] for r in ends], axis=0).reshape(n_labels, rank) / n
            self.log.append((epoch, sum(r["loss"] for r in ends) / n))
            start.destroy()
        return self

    def predict(self, rows: DataFrame) -> DataFrame:
        """key, answer."""
        w, labels = self.weights(), self.labels

        def run(batches):
            for pdf in batches:
                if len(pdf):
                    z = np.array(pdf["x"].tolist()) @ w.T
                    yield pd.DataFrame({"key": pdf["key"].astype(str), "answer": [labels[i] for i in z.argmax(axis=1)]})

        return rows.select("key", "x").mapInPandas(run, "key string, answer string")
