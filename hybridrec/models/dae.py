"""Factorization with a stacked denoising autoencoder as content side."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, functions as F

from hybridrec.features.made import hold, rows_of, width
from hybridrec.models import Model
from hybridrec.models.emf import ContentSide, EmfParams, fit_confidence
from hybridrec.models.nets import apply_net, backward, forward, init_layers, train_net, values
from hybridrec.runtime import materialize, scratch


@dataclass(frozen=True)
class DaeParams:
    lam_n: float = 1000.0
    #: ``gaussian``: squared error on real values; ``binary``: cross-entropy on values in [0, 1].
    visible: str = "gaussian"
    corruption: float = 0.3
    hidden: int = 0
    epochs: int = 30
    rate: float = 0.01
    decay: float = 1e-4
    seed: int = 5


def corrupted(x: np.ndarray, ids: np.ndarray, share: float, round_: int) -> np.ndarray:
    """Zeroes a share of the entries by a hash of item, dimension and round; every epoch of every fit has its own."""
    with np.errstate(over="ignore"):
        h = ids.astype(np.uint64)[:, None] * np.uint64(0x9E3779B97F4A7C15) + np.arange(x.shape[1], dtype=np.uint64) * np.uint64(0xC2B2AE3D27D4EB4F) + np.uint64(round_)
        h = (h ^ (h >> np.uint64(31))) * np.uint64(0x7FB5D329728EA185)
    return np.where((h >> np.uint64(40)).astype(float) / (1 << 24) < share, 0.0, x)


def coupled_loss(p: DaeParams, lam_v: float, round_: int):
    """Reconstruction of the clean input from the corrupted one, and closeness of the middle code to the item's factor."""

    def loss(layers, batch, epoch: int = 0):
        x, y = values(batch, "f"), values(batch, "v")
        middle, last = len(layers) // 2, len(layers)
        acts = forward(layers, corrupted(x, np.asarray(batch["item_id"]), p.corruption, 1_000_003 * round_ + epoch), {middle - 1, last - 1})
        if p.visible == "binary":
            prob = 1 / (1 + np.exp(-np.clip(acts[-1], -30, 30)))
            rec = -(x * np.log(prob + 1e-12) + (1 - x) * np.log(1 - prob + 1e-12)).sum()
            seen = prob - x
        else:
            seen = acts[-1] - x
            rec = (seen**2).sum() / 2
        gap = acts[middle] - y
        scale = p.lam_n / (p.lam_n + lam_v)
        return scale * float(rec) + (1 - scale) * float((gap**2).sum()) / 2, backward(layers, acts, {last: scale * seen, middle: (1 - scale) * gap}, {middle - 1, last - 1})

    return loss


class AutoencoderSide(ContentSide):
    def __init__(self, features: DataFrame, k: int, lam_v: float, p: DaeParams):
        if p.visible not in ("gaussian", "binary"):
            raise ValueError(f"no visible layer {p.visible!r}")
        self.all, self.p, self.lam_v, self.round = features, p, lam_v, 0
        d = width(features)
        wide = p.hidden or 4 * k
        self.layers = init_layers([d, wide, k, wide, d], p.seed)
        self.history: list[float] = []

    def fit(self, factors):
        rows, vectors = rows_of(self.all, factors.select(F.col("id").alias("item_id"), "v"))
        self.round += 1
        with scratch(factors.sparkSession):
            self.layers, seen = train_net(materialize(rows, "dae-rows"), self.layers, coupled_loss(self.p, self.lam_v, self.round), self.p.epochs, self.p.rate, self.p.decay, vectors=vectors)
        self.history += seen

    def transform(self):
        middle = len(self.layers) // 2
        return apply_net(self.all, self.layers, {middle - 1, len(self.layers) - 1}, middle)


def fit_dae_hybrid(train: DataFrame, features: DataFrame, p: EmfParams = EmfParams(), dae: DaeParams = DaeParams()) -> Model:
    features = hold(features, "features")
    return fit_confidence(train, AutoencoderSide(features, p.k, p.lam_v, dae), p)
