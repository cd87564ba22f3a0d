"""Timed fits share one split and leave nothing else."""

import os

from hybridrec.experiments import x08_timing
from hybridrec.runtime import shared_dir


def test_timed_fits_leave_the_split_alone(spark, sf):
    stages = lambda: {x for x in os.listdir(shared_dir(spark).removeprefix("file://")) if x.startswith("stage-")}
    before = stages()
    rows = x08_timing(spark, sf, features=("audio",), models=("wmf", "bpr", "emf"), k=2).collect()
    assert [(r["model"], r["feature"]) for r in rows] == [("wmf", None), ("bpr", None), ("emf", "audio")] and all(r["sec_per_iter"] >= 0 for r in rows)
    left = sorted(x.rsplit("-", 1)[0] for x in stages() - before)
    assert left == ["stage-items-audio", "stage-positives", "stage-split"]
