"""What nets and metadata write and move."""

from pyspark.sql import functions as F

from hybridrec.features import meta, registry
from hybridrec.models import dae, mlp
from hybridrec.models.dae import AutoencoderSide, DaeParams
from hybridrec.models.mlp import NetParams, NetSide


def test_nets_write_ids_and_factors_only(spark, sf, monkeypatch):
    features = registry.load(spark, sf, "audio")
    factors = spark.range(40).select("id", F.array(F.col("id") * 0.01, F.lit(0.5)).alias("v"))
    for module, side in ((mlp, NetSide(features, 2, NetParams(epochs=2))), (dae, AutoencoderSide(features, 2, 1.0, DaeParams(lam_n=1.0, epochs=2)))):
        columns, real = [], module.materialize
        monkeypatch.setattr(module, "materialize", lambda df, name, real=real, columns=columns: columns.append(df.columns) or real(df, name))
        side.fit(factors)
        assert columns == [["item_id", "v"]] and len(side.history) == 2
        assert side.transform().count() == 200


def test_stacked_features_are_held_as_ids(spark, sf):
    from hybridrec.fusion.early import StackSide
    from hybridrec.models.emf import EmfParams

    held = {n: registry.load(spark, sf, n) for n in ("audio", "scene")}
    side = StackSide(held, spark.range(50).select(F.col("id").alias("item_id")), EmfParams(k=2), {}, 1)
    assert all(df.made and df.ids.count() == 50 for df in side.known.values())
    assert registry.concat(held).made.d == 256


def test_lines_are_dealt_once_for_metadata(spark, sf):
    plan = meta.meta_tokens(spark, sf)._jdf.queryExecution().executedPlan().toString()
    supply = plan.split("+- Union")[1].split(":- ")[2] if "+- Union" in plan else plan
    assert "REPARTITION_BY_COL" in plan and supply.count("Exchange hashpartitioning") == 0
