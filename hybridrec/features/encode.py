"""Descriptor sets to one vector per item: residual and gradient encodings over a codebook."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from hybridrec.functions import signed_sqrt, unit
from hybridrec.linalg import list_column, matrix, summed, vector_sums

__all__ = ["fisher_vectors", "fit_codebook", "fit_diag_gmm", "signed_sqrt", "vlad_vectors"]


def _start(desc: DataFrame, k: int) -> np.ndarray:
    """k starting centres: the descriptors with the smallest hashes, the same on any partitioning."""
    rows = desc.select("vec", F.xxhash64("item_id", "frame").alias("h")).orderBy("h").limit(k).collect()
    return np.array([r["vec"] for r in rows], float)


def first_moments(desc: DataFrame, k: int) -> list[tuple[int, int]]:
    """Item and frame of the same descriptors."""
    return [(r["item_id"], r["frame"]) for r in desc.select("item_id", "frame", F.xxhash64("item_id", "frame").alias("h")).orderBy("h").limit(k).collect()]


def _vec(b: pa.RecordBatch) -> np.ndarray:
    return matrix(b.column("vec"))


def _passed(batches, read: Callable):
    """The descriptors of a task, some thousand rows at a time."""
    for whole in batches:
        for a in range(0, whole.num_rows, 2048):
            yield read(whole.slice(a, 2048))


def fit_codebook(desc: DataFrame, k: int, rounds: int = 8, start: Callable[[int], np.ndarray] | None = None, read: Callable = _vec) -> np.ndarray:
    """K-means by partial sums: each round sends k centres out and k sums per task back. ``read`` gives the descriptors of an Arrow batch, ``start`` the first centres, where ``desc`` has none."""
    centres = start(k) if start else _start(desc, k)
    for _ in range(rounds):
        shared = desc.sparkSession.sparkContext.broadcast(centres)

        def part(batches, shared=shared):
            c = shared.value
            s, n = np.zeros_like(c), np.zeros(len(c))
            for x in _passed(batches, read):
                one = np.eye(len(c))[_near(x, c)]
                s, n = s + one.T @ x, n + one.sum(0)
            yield pa.RecordBatch.from_arrays([pa.array(range(len(c)), pa.int32()), pa.array(n), list_column(s)], names=["c", "n", "s"])

        sums = vector_sums(desc.mapInArrow(part, "c int, n double, s array<double>"), "c", "s", "n")
        for c, n, s in sums:
            if n:
                centres[c] = np.array(s) / n
    return centres


def _near(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    """The nearest centre of each row, the first among equals."""
    return np.stack([((x - y) ** 2).sum(1) for y in c], 1).argmin(1)


def _unit_rows(f: np.ndarray) -> np.ndarray:
    n = np.sqrt((f * f).sum(1))
    return f * np.where(n > 0, 1.0 / np.where(n > 0, n, 1.0), 1.0)[:, None]


def vlad_of(x: np.ndarray, codebook: np.ndarray) -> np.ndarray:
    """``vlad_vectors`` of (items, frames, components)."""
    one = np.eye(len(codebook))[_near(x.reshape(-1, x.shape[2]), codebook)].reshape(*x.shape[:2], -1)
    gaps = [(one[:, :, i, None] * (x - c)).sum(1) for i, c in enumerate(codebook)]
    return _unit_rows(np.stack(gaps, 1).reshape(len(x), -1))


def vlad_vectors(desc: DataFrame, codebook: np.ndarray, normalize: bool = True) -> DataFrame:
    """item_id, f: residuals to the nearest centre, summed per centre and laid end to end. All in column expressions; ties to the first centre."""
    k, d = codebook.shape
    centres = F.array(*[F.array(*[F.lit(float(x)) for x in c]) for c in codebook])
    gaps = F.transform(centres, lambda c: F.aggregate(F.zip_with(F.col("vec"), c, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, x: s + x))
    near = desc.select("item_id", "vec", gaps.alias("g")).select("item_id", "vec", F.array_position("g", F.array_min("g")).cast("int").alias("c"))
    res = near.select("item_id", "c", F.zip_with("vec", F.element_at(centres, F.col("c")), lambda x, y: x - y).alias("r"))
    sums = res.groupBy("item_id", "c").agg(summed("r").alias("s"))
    per = sums.groupBy("item_id").agg(F.map_from_entries(F.collect_list(F.struct("c", "s"))).alias("m"))  # at most k entries
    zero = F.array_repeat(F.lit(0.0), d)
    flat = F.flatten(F.transform(F.sequence(F.lit(1), F.lit(k)), lambda i: F.coalesce(F.try_element_at("m", i), zero)))
    return per.select("item_id", (unit(flat) if normalize else flat).alias("f"))


class Mixture:
    """Gaussian mixture with diagonal covariances."""

    def __init__(self, weights: np.ndarray, means: np.ndarray, variances: np.ndarray):
        self.weights, self.means, self.variances = weights, means, variances

    def responsibilities(self, x: np.ndarray) -> tuple[np.ndarray, float]:
        centre = self.means.mean(0)  # squares are taken about it, which keeps digits
        x, m, inverse = x - centre, self.means - centre, 1 / self.variances
        far = (x * x) @ inverse.T - 2 * (x @ (m * inverse).T) + (m * m * inverse).sum(1)
        log = np.log(self.weights) - 0.5 * (np.log(2 * np.pi * self.variances).sum(1) + far)
        top = log.max(1, keepdims=True)
        e = np.exp(log - top)
        total = e.sum(1, keepdims=True)
        return e / total, float((np.log(total) + top).sum())


def _spread(desc: DataFrame, read: Callable) -> np.ndarray:
    """Variance of each component: a count, a mean and squares about it per task, put together on the driver."""

    def part(batches):
        n, mean, squares = 0, 0.0, 0.0
        for x in _passed(batches, read):
            n, mean, squares = _together((n, mean, squares), (len(x), x.mean(0), ((x - x.mean(0)) ** 2).sum(0)))
        if n:
            yield pa.RecordBatch.from_arrays([pa.array([n]), list_column(mean[None]), list_column(squares[None])], names=["n", "m", "s"])

    whole = (0, 0.0, 0.0)
    for r in desc.mapInArrow(part, "n long, m array<double>, s array<double>").collect():  # one row a task
        whole = _together(whole, (r["n"], np.array(r["m"]), np.array(r["s"])))
    return whole[2] / max(whole[0], 1)


def _together(a: tuple, b: tuple) -> tuple:
    n = a[0] + b[0]
    gap = b[1] - a[1]
    return n, a[1] + gap * b[0] / n, a[2] + b[2] + gap**2 * (a[0] * b[0] / n)


def fit_diag_gmm(desc: DataFrame, k: int, rounds: int = 8, floor: float = 1e-4, start: Callable[[int], np.ndarray] | None = None, read: Callable = _vec) -> Mixture:
    """Expectation-maximization by partial sums: a round sends the mixture out and k x (2 d + 1) sums per task back. ``start`` and ``read`` as in ``fit_codebook``."""
    spread = _spread(desc, read)
    means = start(k) if start else _start(desc, k)
    g = Mixture(np.full(k, 1 / k), means, np.tile(np.maximum(spread, floor), (k, 1)))
    for _ in range(rounds):
        shared = desc.sparkSession.sparkContext.broadcast(g)

        def part(batches, shared=shared):
            m = shared.value
            n, s1, s2 = np.zeros(len(m.weights)), np.zeros_like(m.means), np.zeros_like(m.means)
            for x in _passed(batches, read):
                r, _ = m.responsibilities(x)
                n, s1, s2 = n + r.sum(0), s1 + r.T @ x, s2 + r.T @ x**2
            yield pa.RecordBatch.from_arrays([pa.array(range(len(n)), pa.int32()), pa.array(n), list_column(np.hstack([s1, s2]))], names=["c", "n", "s"])

        d = means.shape[1]
        for c, n, s in vector_sums(desc.mapInArrow(part, "c int, n double, s array<double>"), "c", "s", "n"):
            if n > 1e-9:
                mu = np.array(s[:d]) / n
                g.weights[c], g.means[c], g.variances[c] = n, mu, np.maximum(np.array(s[d:]) / n - mu**2, floor)
        g.weights = np.maximum(g.weights / g.weights.sum(), 1e-12)
    return g


def fisher_of(x: np.ndarray, g: Mixture) -> np.ndarray:
    """``fisher_vectors`` of (items, frames, components)."""
    n, frames, d = x.shape
    r = g.responsibilities(x.reshape(-1, d))[0].reshape(n, frames, -1)
    sd = np.sqrt(g.variances)
    out = np.empty((n, 2, len(sd), d))
    for i in range(len(sd)):
        z = (x - g.means[i]) / sd[i]
        own = r[:, None, :, i]
        out[:, 0, i] = (own @ z)[:, 0] / (np.sqrt(g.weights[i]) * frames)
        out[:, 1, i] = (own @ (z * z) - own.sum(2, keepdims=True))[:, 0] / (np.sqrt(2 * g.weights[i]) * frames)
    out = out.reshape(n, -1)
    return _unit_rows(np.copysign(np.sqrt(np.abs(out)), out))


def fisher_vectors(desc: DataFrame, g: Mixture, normalize: bool = True) -> DataFrame:
    """item_id, f: gradients by mean and deviation, 2 x k x d values. Batches give partial sums, so no item has to fit into a task."""
    shared = desc.sparkSession.sparkContext.broadcast(g)

    def part(batches):
        m = shared.value
        sd = np.sqrt(m.variances)
        for batch in batches:
            if not batch.num_rows:
                continue
            x = matrix(batch.column("vec"))
            r, _ = m.responsibilities(x)
            z = (x[:, None, :] - m.means) / sd
            a = (r[:, :, None] * z).reshape(len(x), -1)
            b = (r[:, :, None] * (z**2 - 1)).reshape(len(x), -1)
            ids, inv = np.unique(batch.column("item_id").to_numpy(zero_copy_only=False), return_inverse=True)
            sums = np.zeros((len(ids), a.shape[1] * 2))
            np.add.at(sums, inv, np.hstack([a, b]))
            yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(np.bincount(inv)), list_column(sums)], names=["item_id", "n", "s"])

    d = g.means.shape[1]
    sums = desc.select("item_id", "vec").mapInArrow(part, "item_id long, n long, s array<double>").groupBy("item_id").agg(F.sum("n").alias("n"), summed("s").alias("s"))
    factors = [1 / np.sqrt(w) for w in g.weights] + [1 / np.sqrt(2 * w) for w in g.weights]  # one a component and half, not one a value
    known = F.array(*[F.lit(float(x)) for x in factors])
    f = F.transform("s", lambda x, i: x * F.get(known, F.floor(i / d).cast("int")) / F.col("n"))
    out = sums.select("item_id", f.alias("f"))
    return out.select("item_id", unit(signed_sqrt(F.col("f"))).alias("f")) if normalize else out


