"""Embedding-coupled matrix factorization: item factors tied to a linear image of their content.

The confidence-weighted core with a pluggable content side serves all hybrids of its family; the models differ only in where
the prior mean of an item's factor comes from.
"""

from __future__ import annotations

import time
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from hybridrec.functions import dot
from hybridrec.features.made import hold, only, rows_of, width
from hybridrec.linalg import gram, half_step, layout, list_column, matrix, partial, summed, vector_sums
from hybridrec.models import Model
from hybridrec.models.init import hash_vectors
from hybridrec.runtime import discard, materialize


@dataclass(frozen=True)
class EmfParams:
    k: int = 50
    lam_u: float = 0.1
    lam_v: float = 10.0
    lam_e: float = 1000.0
    c_pos: float = 1.0
    c_zero: float = 0.01
    iters: int = 10
    #: Stop when the objective falls by less than this share; 0 runs all iterations and skips the objective.
    tol: float = 0.0
    seed: int = 17
    strategy: str = "auto"
    solver: str = "auto"


def content_sums(features: DataFrame, d: int, targets: DataFrame | None = None, k: int = 0) -> np.ndarray:
    """Sum of f f' (d x d), or of f h' (d x k) against the targets (id, v): partial matrices per task, added on the cluster."""
    wide = k if targets is not None else d
    aimed = targets is not None
    rows, vectors = rows_of(features, targets.select(F.col("id").alias("item_id"), "v") if aimed else None)

    def part(batches):
        total = np.zeros((d, wide))
        for b in batches:
            if b.num_rows:
                f = vectors(b)
                total += f.T @ (matrix(b.column("v")) if aimed else f)
        yield partial(total)

    out = np.zeros((d, wide))
    for r, v in vector_sums(rows.mapInArrow(part, "r int, v array<double>"), "r", "v"):
        out[r] = v
    return out


def choose_solver(n: int, d: int) -> str:
    """Direct up to 2,048 dimensions; dual when items are fewer than dimensions and fit; conjugate gradients beyond."""
    if d <= 2048:
        return "direct"
    return "dual" if n < d and n <= 4096 else "cg"


def solve_embedding(features: DataFrame, targets: DataFrame, lam_v: float, lam_e: float, k: int, solver: str = "auto", start: np.ndarray | None = None, ff: np.ndarray | None = None, rounds: int = 200, tol: float = 1e-10) -> np.ndarray:
    """Ridge regression of item factors on content: (lam_v F F' + lam_e I) E = lam_v F H'."""
    d = width(features)
    if solver == "auto":
        solver = choose_solver(features.count() if d > 2048 else 0, d)
    if solver == "dual":
        rows = features.join(targets.select(F.col("id").alias("item_id"), "v"), "item_id").select("f", "v").collect()  # n < d, n bounded by choose_solver
        f, h = np.array([r["f"] for r in rows], float), np.array([r["v"] for r in rows], float)
        return lam_v * f.T @ np.linalg.solve(lam_v * f @ f.T + lam_e * np.eye(len(f)), h)
    right = lam_v * content_sums(features, d, targets, k)
    if solver == "direct":
        return np.linalg.solve(lam_v * (content_sums(features, d) if ff is None else ff) + lam_e * np.eye(d), right)
    # matrix-free conjugate gradients, all k columns at once: two products with the data per pass, d x d never formed
    rows, vectors = rows_of(only(features, targets.select(F.col("id").alias("item_id"))))

    def times(x: np.ndarray) -> np.ndarray:
        shared = features.sparkSession.sparkContext.broadcast(x)

        def part(batches):
            total = np.zeros((d, k))
            for b in batches:
                if b.num_rows:
                    f = vectors(b)
                    total += f.T @ (f @ shared.value)
            yield partial(total)

        out = np.zeros((d, k))
        for r, v in vector_sums(rows.mapInArrow(part, "r int, v array<double>"), "r", "v"):
            out[r] = v
        return lam_v * out + lam_e * x

    x = np.zeros((d, k)) if start is None else start.copy()
    r = right - times(x) if start is not None else right.copy()
    p, rr = r.copy(), (r**2).sum(0)
    for _ in range(rounds):
        if rr.max() <= tol**2 * max((right**2).sum(0).max(), 1e-300):
            break
        ap = times(p)
        a = rr / np.maximum((p * ap).sum(0), 1e-300)
        x += a * p
        r -= a * ap
        new = (r**2).sum(0)
        p = r + (new / np.maximum(rr, 1e-300)) * p
        rr = new
    return x


def embed(features: DataFrame, e: np.ndarray) -> DataFrame:
    """id, v: the linear image of every content vector. The matrix, d x k, is broadcast."""
    shared = features.sparkSession.sparkContext.broadcast(e)

    def run(batches):
        for b in batches:
            if b.num_rows:
                yield pa.RecordBatch.from_arrays([b.column("item_id").cast(pa.int64()), list_column(vectors(b) @ shared.value)], names=["id", "v"])

    rows, vectors = rows_of(features)
    return rows.mapInArrow(run, "id long, v array<double>")


def embed_sparse(features: DataFrame, e_rows: DataFrame, k: int) -> DataFrame:
    """The same for sparse vectors over a table of rows (dim_id, e): work follows the non-zeros, and the matrix may exceed any memory."""
    flat = features.select(F.col("item_id").alias("id"), F.explode(F.arrays_zip("f.idx", "f.val")).alias("x")).select("id", F.col("x.idx").alias("dim_id"), F.col("x.val").alias("x"))
    return flat.join(e_rows, "dim_id").select("id", F.transform("e", lambda y: y * F.col("x")).alias("v")).groupBy("id").agg(summed("v").alias("v"))


class ContentSide:
    """Where prior means come from. ``fit`` sees the training items' current factors, ``transform`` serves all items with content."""

    def fit(self, factors: DataFrame) -> None:
        raise NotImplementedError

    def transform(self) -> DataFrame | None:
        raise NotImplementedError

    def penalty(self) -> float:
        return 0.0


class LinearSide(ContentSide):
    def __init__(self, features: DataFrame, train_items: DataFrame, p: EmfParams):
        self.all, self.p, self.e = features, p, None
        self.known = only(features, train_items)
        self.d = width(features)
        self.solver = choose_solver(0, self.d) if p.solver == "auto" else p.solver
        self.ff = content_sums(self.known, self.d) if self.solver == "direct" else None  # constant over iterations

    def fit(self, factors):
        self.e = solve_embedding(self.known, factors, self.p.lam_v, self.p.lam_e, self.p.k, self.solver, self.e if self.solver == "cg" else None, self.ff)

    def transform(self):
        return embed(self.all, np.zeros((self.d, self.p.k)) if self.e is None else self.e)

    def penalty(self):
        return 0.0 if self.e is None else self.p.lam_e / 2 * float((self.e**2).sum())


def objective(train: DataFrame, w: DataFrame, h: DataFrame, prior: DataFrame | None, p: EmfParams, penalty: float = 0.0) -> float:
    """The negative log-likelihood. The sum over all cells is that of the zeros, by two Gram matrices, corrected on the positives."""
    gw, gh = gram(w, p.k), gram(h, p.k)
    zeros = p.c_zero / 2 * float((gw * gh).sum())
    s = dot(F.col("w"), F.col("h"))
    pairs = train.join(w.select(F.col("id").alias("user_id"), F.col("v").alias("w")), "user_id").join(h.select(F.col("id").alias("item_id"), F.col("v").alias("h")), "item_id")
    pos = pairs.agg(F.sum(p.c_pos / 2 * (s - 1) * (s - 1) - p.c_zero / 2 * s * s).alias("x")).collect()[0]["x"] or 0.0
    off = h if prior is None else offsets(h, prior).select("id", F.col("offset").alias("v"))
    return zeros + float(pos) + p.lam_u / 2 * float(np.trace(gw)) + p.lam_v / 2 * float(np.trace(gram(off, p.k))) + penalty


def offsets(h: DataFrame, content: DataFrame) -> DataFrame:
    """id, offset, norm: what an item's factor has beyond its content; without content all of it."""
    both = h.join(content.select("id", F.col("v").alias("c")), "id", "left")
    off = F.when(F.col("c").isNull(), F.col("v")).otherwise(F.zip_with("v", "c", lambda a, b: a - b))
    return both.select("id", off.alias("offset")).select("id", "offset", F.sqrt(F.aggregate("offset", F.lit(0.0), lambda s, x: s + x * x)).alias("norm"))


def _solved(factors: DataFrame, name: str) -> DataFrame:
    """A half-step written; then the opposite table goes from the memory of driver and workers."""
    out = materialize(factors, name)
    if factors.sent is not None:
        factors.sent.destroy()
    return out


def fit_confidence(train: DataFrame, side: ContentSide | None, p: EmfParams) -> Model:
    """Alternating closed-form updates: users, items, content side. ``history`` has the seconds of each iteration, with all it writes."""
    by_user, by_item = layout(train, "user_id", "item_id"), layout(train, "item_id", "user_id")
    h = materialize(hash_vectors(train.select("item_id"), "item_id", p.k, p.seed), "h0")
    items = train.select(F.col("item_id").alias("id")).distinct()
    w, content, history = None, None, []
    n_users, n_items = train.select("user_id").distinct().count(), items.count()
    for i in range(p.iters):
        begun = time.perf_counter()
        old, old_content = (w, h), content
        w = _solved(half_step(by_user, h, p.k, p.lam_u, p.c_pos, p.c_zero, None, p.strategy, size=n_items), "w")
        prior = None
        if content is not None:
            prior = content.join(items, "id", "left_semi")
        h = _solved(half_step(by_item, w, p.k, p.lam_v, p.c_pos, p.c_zero, prior, p.strategy, size=n_users), "h")
        if side is not None:
            side.fit(h)
            content = materialize(side.transform(), "content")
            discard(old_content)
        discard(*old)
        history.append({"iteration": i, "seconds": time.perf_counter() - begun})
        if p.tol:
            history[-1].update({"objective": objective(train, w, h, content.join(items, "id", "left_semi") if content is not None else None, p, side.penalty() if side else 0.0)})
            if i and history[-2]["objective"] - history[-1]["objective"] < p.tol * abs(history[-2]["objective"]):
                break
    discard(by_user, by_item)
    return Model(w, h, content, history, {"params": p, "side": side})


def fit_emf(train: DataFrame, features: DataFrame, p: EmfParams = EmfParams()) -> Model:
    """The content-coupled model on one real-valued feature (item_id, f). Items held out of training enter by their content only."""
    features = hold(features, "features")
    return fit_confidence(train, LinearSide(features, train.select("item_id").distinct(), p), p)


def simulate(users: int, items: int, d: int, p: EmfParams, seed: int = 0) -> dict[str, np.ndarray]:
    """A draw from the generative story, for recovery tests on small sizes."""
    rng = np.random.default_rng(seed)
    w = rng.normal(0, p.lam_u**-0.5, (users, p.k))
    e = rng.normal(0, p.lam_e**-0.5, (d, p.k))
    f = rng.normal(0, 1, (items, d))
    h = f @ e + rng.normal(0, p.lam_v**-0.5, (items, p.k))
    return {"w": w, "e": e, "f": f, "h": h, "scores": w @ h.T}
