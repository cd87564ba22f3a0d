"""Features whose vectors are made of item ids where they are needed, so that none of them is written or moved."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from hybridrec.linalg import list_column, matrix
from hybridrec.runtime import materialize

#: Items whose vectors are made at once, so that what is made on the way stays small.
ITEMS_AT_ONCE = 512


class Made:
    """Vectors of a feature, ``d`` components each, from ids: the encoding of the items' local descriptors."""

    def __init__(self, local: Callable[[np.ndarray], np.ndarray], encode: Callable[[np.ndarray], np.ndarray], d: int):
        self.local, self.encode, self.d = local, encode, d

    def __call__(self, ids: np.ndarray) -> np.ndarray:
        out = np.empty((len(ids), self.d))
        for a in range(0, len(ids), ITEMS_AT_ONCE):
            out[a : a + ITEMS_AT_ONCE] = self.encode(self.local(ids[a : a + ITEMS_AT_ONCE]))
        return out


class Concat:
    """Several features end to end."""

    def __init__(self, parts: list):
        self.parts, self.d = parts, sum(p.d for p in parts)

    def __call__(self, ids: np.ndarray) -> np.ndarray:
        return np.hstack([p(ids) for p in self.parts])


def of_ids(ids: DataFrame, made) -> DataFrame:
    """item_id, f of a made feature. Whoever knows ``made`` and ``ids`` makes the vectors; for others the table has them."""

    def run(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([b.column(0), list_column(made(b.column(0).to_numpy(zero_copy_only=False)))], names=["item_id", "f"])

    out = ids.select("item_id").mapInArrow(run, "item_id long, f array<double>")
    out.made, out.ids = made, ids.select("item_id")
    return out


def hold(features: DataFrame, name: str) -> DataFrame:
    """The features written for many reads; of a made feature only its ids are read again, which are written already."""
    return features if getattr(features, "made", None) else materialize(features, name)


def written(features: DataFrame, name: str) -> DataFrame:
    """The features, or the ids of a made one, written for many reads."""
    made = getattr(features, "made", None)
    return of_ids(materialize(features.ids, name), made) if made else materialize(features, name)


def width(features: DataFrame) -> int:
    made = getattr(features, "made", None)
    return made.d if made else features.select(F.size("f").alias("d")).first()["d"]


def only(features: DataFrame, items: DataFrame) -> DataFrame:
    """The features of the given items (item_id)."""
    made = getattr(features, "made", None)
    return of_ids(features.ids.join(items.select("item_id"), "item_id", "left_semi"), made) if made else features.join(items.select("item_id"), "item_id", "left_semi")


def rows_of(features: DataFrame, others: DataFrame | None = None) -> tuple[DataFrame, Callable[[pa.RecordBatch], np.ndarray]]:
    """item_id, what ``others`` has for it, and what a worker needs for the vectors; with a function that gives the vectors of a batch."""
    made = getattr(features, "made", None)
    rows = features.ids if made else features.select("item_id", "f")
    if others is not None:
        rows = rows.join(others, "item_id")
    if made:
        return rows, lambda b: made(b.column("item_id").to_numpy(zero_copy_only=False))
    return rows, lambda b: matrix(b.column("f"))
