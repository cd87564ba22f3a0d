"""Small dense networks trained by synchronous data-parallel gradients."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from hybridrec.features.made import rows_of
from hybridrec.linalg import list_column, matrix, vector_sums


def init_layers(sizes: list[int], seed: int) -> list[tuple[np.ndarray, np.ndarray]]:
    rng = np.random.default_rng(seed)
    return [(rng.normal(0, np.sqrt(2.0 / (a + b)), (a, b)), np.zeros(b)) for a, b in zip(sizes, sizes[1:], strict=False)]


def forward(layers, x: np.ndarray, linear: set[int]) -> list[np.ndarray]:
    """Activations of every layer, input first; layers in ``linear`` have no squashing."""
    out = [x]
    for i, (w, b) in enumerate(layers):
        z = out[-1] @ w + b
        out.append(z if i in linear else np.tanh(z))
    return out


def backward(layers, acts: list[np.ndarray], grads: dict[int, np.ndarray], linear: set[int]) -> list[tuple[np.ndarray, np.ndarray]]:
    """Gradients of weights and biases given the loss gradients on some activations (by index, input is 0)."""
    g, out = None, []
    for i in range(len(layers) - 1, -1, -1):
        if i + 1 in grads:
            g = grads[i + 1] if g is None else g + grads[i + 1]
        z = g if i in linear else g * (1 - acts[i + 1] ** 2)
        out.append((acts[i].T @ z, z.sum(0)))
        g = z @ layers[i][0].T
    return out[::-1]


def flat(parts) -> np.ndarray:
    return np.concatenate([x.ravel() for pair in parts for x in pair])


def unflat(v: np.ndarray, like) -> list[tuple[np.ndarray, np.ndarray]]:
    out, at = [], 0
    for w, b in like:
        out.append((v[at : at + w.size].reshape(w.shape), v[at + w.size : at + w.size + b.size]))
        at += w.size + b.size
    return out


#: Rows that meet the net at once, so that their activations stay small.
ROWS_AT_ONCE = 2048


def values(batch, name: str) -> np.ndarray:
    """A vector column of a batch of rows, in whatever form it has come."""
    x = batch[name]
    return x if isinstance(x, np.ndarray) and x.ndim == 2 else np.array(x.tolist(), float)


def _arrays(b: pa.RecordBatch, vectors: Callable | None) -> dict[str, np.ndarray]:
    own = {n: b.column(n) for n in b.schema.names}
    out = {n: matrix(c) if pa.types.is_list(c.type) else c.to_numpy(zero_copy_only=False) for n, c in own.items()}
    return out if vectors is None else out | {"f": vectors(b)}


def train_net(rows: DataFrame, layers, loss: Callable, epochs: int, rate: float, decay: float = 1e-4, chunk: int = 4096, vectors: Callable | None = None):
    """Adam on full-batch gradients. ``loss(layers, batch, epoch) -> (value, gradient parts)`` runs in the workers on item_id, f and v of some rows as arrays
    (``vectors`` gives f of an Arrow batch that does not have it); a round sends the net out and one gradient back, summed on the cluster in chunks, so results do not depend on partitioning beyond rounding."""
    v = flat(layers)
    m1, m2, history = np.zeros_like(v), np.zeros_like(v), []
    pieces = -(-len(v) // chunk)
    for t in range(1, epochs + 1):
        shared = rows.sparkSession.sparkContext.broadcast((unflat(v, layers), t))

        def part(batches, shared=shared):
            total, value, n = np.zeros(len(v)), 0.0, 0
            for whole in batches:
                for a in range(0, whole.num_rows, ROWS_AT_ONCE):
                    b = whole.slice(a, ROWS_AT_ONCE)
                    x, g = loss(shared.value[0], _arrays(b, vectors), shared.value[1])
                    total, value, n = total + flat(g), value + x, n + b.num_rows
            padded = np.pad(total, (0, pieces * chunk - len(total))).reshape(pieces, chunk)
            rest = [0] * (pieces - 1)
            yield pa.RecordBatch.from_arrays([pa.array(range(pieces), pa.int32()), pa.array([value, *rest], pa.float64()), pa.array([n, *rest], pa.int64()), list_column(padded)], names=["piece", "loss", "n", "g"])

        sums = rows.mapInArrow(part, "piece int, loss double, n long, g array<double>")
        g, value, n = np.zeros(pieces * chunk), 0.0, 0
        for piece, lost, seen, own in vector_sums(sums, "piece", "g", "loss", "n"):
            g[piece * chunk : (piece + 1) * chunk] = own
            value, n = value + lost, n + seen
        g = g[: len(v)] / max(n, 1) + decay * v
        m1, m2 = 0.9 * m1 + 0.1 * g, 0.999 * m2 + 0.001 * g**2
        v = v - rate * (m1 / (1 - 0.9**t)) / (np.sqrt(m2 / (1 - 0.999**t)) + 1e-8)
        history.append(value / max(n, 1))
    return unflat(v, layers), history


def apply_net(features: DataFrame, layers, linear: set[int], layer: int) -> DataFrame:
    """id, v: activation ``layer`` for every content vector."""
    shared = features.sparkSession.sparkContext.broadcast(layers)

    def run(batches):
        for b in batches:
            if b.num_rows:
                yield pa.RecordBatch.from_arrays([b.column("item_id").cast(pa.int64()), list_column(forward(shared.value, vectors(b), linear)[layer])], names=["id", "v"])

    rows, vectors = rows_of(features)
    return rows.mapInArrow(run, "id long, v array<double>")
