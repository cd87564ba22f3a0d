"""Vectors are made for the split's items only where the others play no part."""

import pytest

from hybridrec.experiments import Workload
from hybridrec.models.emf import EmfParams


def test_vectors_of_the_splits_items_give_the_same_fit(spark, sf):
    p, got = EmfParams(k=3, iters=2, lam_e=10.0), []
    for own in (False, True):
        w = Workload(spark, sf, "events", p=p, own_items=own)
        m = w.fit("emf", "audio")
        got.append(({r["id"]: r["v"] for r in m.content_latents.collect()}, {(s, r["k"]): r["hits"] for s in ("in", "out") for r in w.accuracy(m, s, ks=(5, 10)).collect()}))
    (all_items, want), (mine, hits) = got
    assert hits == want and len(mine) < len(all_items)
    items = {r[0] for df in (w.train, *w.tests.values()) for r in df.select("item_id").distinct().collect()}
    assert set(mine) == items & set(all_items)
    assert all(mine[i] == pytest.approx(all_items[i], abs=1e-9) for i in mine)
