"""Early fusion: one model over several features."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, functions as F

from hybridrec.features.made import only, width, written
from hybridrec.features.registry import concat
from hybridrec.functions import add
from hybridrec.models import Model
from hybridrec.models.emf import ContentSide, EmfParams, content_sums, embed, fit_confidence, fit_emf, solve_embedding


def fit_concat(train: DataFrame, features: dict[str, DataFrame], p: EmfParams = EmfParams()) -> Model:
    """One content vector: all features end to end."""
    return fit_emf(train, concat(features), p)


class StackSide(ContentSide):
    """A sum of linear images, one matrix per feature, each with its own penalty.

    The matrices are solved one after the other on what the others leave, ``sweeps`` times an iteration: with equal penalties and enough
    sweeps this reaches the same optimum as concatenation, without ever solving in all dimensions at once.
    """

    def __init__(self, features: dict[str, DataFrame], train_items: DataFrame, p: EmfParams, lam_e: dict[str, float], sweeps: int):
        self.all, self.p, self.lam, self.sweeps = features, p, {n: lam_e.get(n, p.lam_e) for n in features}, sweeps
        self.known = {n: written(only(df, train_items), f"known-{n}") for n, df in features.items()}
        self.ff = {n: content_sums(df, width(df)) for n, df in self.known.items()}
        self.e: dict = {}

    def _image(self, names, which) -> DataFrame | None:
        parts = [embed(which[n], self.e[n]) for n in names if n in self.e]
        if not parts:
            return None
        return reduce(lambda a, b: a.join(b.withColumnRenamed("v", "o"), "id").select("id", add(F.col("v"), F.col("o")).alias("v")), parts)

    def fit(self, factors):
        for _ in range(self.sweeps):
            for n in self.all:
                rest = self._image([x for x in self.all if x != n], self.known)
                target = factors if rest is None else factors.join(rest.withColumnRenamed("v", "o"), "id").select("id", F.zip_with("v", "o", lambda a, b: a - b).alias("v"))
                self.e[n] = solve_embedding(self.known[n], target, self.p.lam_v, self.lam[n], self.p.k, "direct", None, self.ff[n])

    def transform(self):
        return self._image(list(self.all), self.all)

    def penalty(self):
        return sum(self.lam[n] / 2 * float((e**2).sum()) for n, e in self.e.items())


def fit_stack(train: DataFrame, features: dict[str, DataFrame], p: EmfParams = EmfParams(), lam_e: dict[str, float] | None = None, sweeps: int = 1) -> Model:
    """Content latents of several features added up. Items need all features."""
    ids = reduce(lambda a, b: a.join(b, "item_id"), [getattr(df, "ids", df).select("item_id") for df in features.values()])
    held = {n: written(only(df, ids), f"feature-{n}") for n, df in features.items()}
    return fit_confidence(train, StackSide(held, train.select("item_id").distinct(), p, lam_e or {}, sweeps), p)
