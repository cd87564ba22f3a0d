"""Factorization with a multilayer perceptron as content side."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, functions as F

from hybridrec.features.made import hold, rows_of, width
from hybridrec.models import Model
from hybridrec.models.emf import ContentSide, EmfParams, fit_confidence
from hybridrec.models.nets import apply_net, backward, forward, init_layers, train_net, values
from hybridrec.runtime import materialize, scratch


@dataclass(frozen=True)
class NetParams:
    hidden: tuple[int, ...] = ()
    epochs: int = 30
    rate: float = 0.02
    decay: float = 1e-4
    seed: int = 3


def regression_loss(layers, batch, epoch: int = 0):
    x, y = values(batch, "f"), values(batch, "v")
    acts = forward(layers, x, {len(layers) - 1})
    gap = acts[-1] - y
    return float((gap**2).sum()) / 2, backward(layers, acts, {len(layers): gap}, {len(layers) - 1})


class NetSide(ContentSide):
    """Regresses the training items' factors on content; each ``fit`` goes on from the last weights."""

    def __init__(self, features: DataFrame, k: int, net: NetParams):
        self.all, self.net = features, net
        d = width(features)
        self.layers = init_layers([d, *(net.hidden or (4 * k,)), k], net.seed)
        self.history: list[float] = []

    def fit(self, factors):
        rows, vectors = rows_of(self.all, factors.select(F.col("id").alias("item_id"), "v"))
        with scratch(factors.sparkSession):
            self.layers, seen = train_net(materialize(rows, "net-rows"), self.layers, regression_loss, self.net.epochs, self.net.rate, self.net.decay, vectors=vectors)
        self.history += seen

    def transform(self):
        return apply_net(self.all, self.layers, {len(self.layers) - 1}, len(self.layers))


def fit_mlp_hybrid(train: DataFrame, features: DataFrame, p: EmfParams = EmfParams(), net: NetParams = NetParams(), mode: str = "alternating") -> Model:
    """``alternating`` couples net and factors in every iteration; ``two_stage`` factorizes first and regresses once."""
    features = hold(features, "features")
    side = NetSide(features, p.k, net)
    if mode == "alternating":
        return fit_confidence(train, side, p)
    if mode != "two_stage":
        raise ValueError(f"no mode {mode!r}")
    m = fit_confidence(train, None, p)
    side.fit(m.item_factors)
    m.content_latents = materialize(side.transform(), "content")
    m.extra["side"] = side
    return m
