"""Principal components: exact, dual when items are fewer than dimensions, or by randomized passes."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, functions as F

from hybridrec.linalg import vector_sums


class Projection:
    def __init__(self, mean: np.ndarray, axes: np.ndarray, variances: np.ndarray):
        self.mean, self.axes, self.variances = mean, axes, variances


def _matrix_sums(df: DataFrame, fn, shape: tuple[int, int]) -> np.ndarray:
    """Sum over batches of fn(X): one partial matrix per task, added pairwise on the cluster."""

    def part(batches):
        total = np.zeros(shape)
        for pdf in batches:
            if len(pdf):
                total += fn(np.array(pdf["f"].tolist(), float), pdf)
        yield pd.DataFrame({"r": range(shape[0]), "v": list(total)})

    out = np.zeros(shape)
    for r, v in vector_sums(df.mapInPandas(part, "r int, v array<double>"), "r", "v"):
        out[r] = v
    return out


def fit_pca(df: DataFrame, r: int, method: str = "exact", passes: int = 4, oversample: int = 8, seed: int = 0) -> Projection:
    """The first ``r`` axes of (item_id, f). ``exact`` sums the d x d covariance, ``dual`` collects the n x d rows (n < d, checked small),
    ``randomized`` refines a random subspace with two products of the data per pass and never forms d x d."""
    first = df.select(F.size("f").alias("d")).first()
    d = first["d"]
    n = df.count()
    mean = _matrix_sums(df.select("f"), lambda x, _: x.sum(0, keepdims=True), (1, d))[0] / n
    if method == "dual":
        if n * d > 50_000_000:
            raise ValueError("too many rows for the dual method")
        x = np.array([row["f"] for row in df.select("f").collect()], float) - mean
        _, s, vt = np.linalg.svd(x, full_matrices=False)
        axes, variances = vt[:r].T, s[:r] ** 2 / n
    elif method == "exact":
        c = _matrix_sums(df.select("f"), lambda x, _: (x - mean).T @ (x - mean), (d, d)) / n
        w, v = np.linalg.eigh(c)
        axes, variances = v[:, ::-1][:, :r], w[::-1][:r]
    elif method == "randomized":
        q, _ = np.linalg.qr(np.random.default_rng(seed).normal(size=(d, min(d, r + oversample))))
        for _ in range(passes):
            q, _ = np.linalg.qr(_matrix_sums(df.select("f"), lambda x, _, q=q: (x - mean).T @ ((x - mean) @ q), q.shape))
        small = _matrix_sums(df.select("f"), lambda x, _: ((x - mean) @ q).T @ ((x - mean) @ q), (q.shape[1],) * 2) / n
        w, v = np.linalg.eigh(small)
        axes, variances = (q @ v)[:, ::-1][:, :r], w[::-1][:r]
    else:
        raise ValueError(f"no method {method!r}")
    sign = np.sign(axes[np.abs(axes).argmax(0), np.arange(axes.shape[1])])
    return Projection(mean, axes * np.where(sign == 0, 1, sign), variances)


def project(df: DataFrame, p: Projection) -> DataFrame:
    shared = df.sparkSession.sparkContext.broadcast(p)

    def run(batches):
        q = shared.value
        for pdf in batches:
            x = np.array(pdf["f"].tolist(), float).reshape(len(pdf), len(q.mean))
            yield pd.DataFrame({"item_id": pdf["item_id"], "f": list((x - q.mean) @ q.axes)})

    return df.select("item_id", "f").mapInPandas(run, "item_id long, f array<double>")
