"""The study's experiments on the given tables. Each function returns the rows its table or figure would show."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession, functions as F

from hybridrec import interactions
from hybridrec.evaluation import split as sp
from hybridrec.evaluation import stats
from hybridrec.evaluation.accuracy import KS, accuracy_at, lift
from hybridrec.evaluation.timing import time_iterations
from hybridrec.evaluation.topk import recommend
from hybridrec.evaluation.tuning import grid_search
from hybridrec.features import registry
from hybridrec.features.made import hold, only, written
from hybridrec.functions import dot
from hybridrec.fusion import early, late, learned
from hybridrec.models import Model
from hybridrec.models.bpr import BprParams, fit_bpr, fit_content_bpr
from hybridrec.models.dae import DaeParams, fit_dae_hybrid
from hybridrec.models.emf import EmfParams, fit_emf
from hybridrec.models.mlp import NetParams, fit_mlp_hybrid
from hybridrec.models.topic import fit_topic_hybrid
from hybridrec.models.wmf import fit_wmf
from hybridrec.runtime import materialize, scratch
from hybridrec.sources import table

#: Published penalties fit tens of thousands of items; on the small tables the embedding penalty must be lower.
SMALL = EmfParams(k=8, iters=4, lam_e=10.0)


class Workload:
    """One dataset, one fold: split, features on demand, fits and accuracies shared by the experiments.

    With ``own_items`` features have the vectors of the split's items only; vocabularies and codebooks are still those of all items. Fits that learn
    from training items alone give the same.
    """

    def __init__(self, spark: SparkSession, sf_dir: str, dataset: str = "mixed", fold: int = 0, p: EmfParams = SMALL, encoded: bool = True, own_items: bool = False):
        self.spark, self.sf_dir, self.p, self.encoded = spark, sf_dir, p, encoded
        split = materialize(sp.make_split(materialize(interactions.positives(spark, sf_dir, dataset), "positives"), fold), "split")
        self.train, self.tests = sp.part(split, "train"), {"in": sp.part(split, "in_test"), "out": sp.part(split, "out_test")}
        self._features: dict[str, DataFrame] = {}
        self.items = materialize(split.select("item_id").distinct(), "split-items") if own_items else None

    def feature(self, name: str) -> DataFrame:
        if name not in self._features:
            plain = name in registry.NON_TEXT and not self.encoded
            f = registry.slices(self.spark, self.sf_dir, name) if plain else registry.load(self.spark, self.sf_dir, name)
            self._features[name] = hold(f, f"feature-{name}") if self.items is None else written(only(f, self.items), f"feature-{name}")
        return self._features[name]

    def counts(self, name: str) -> DataFrame:
        """Words or metadata as counted, for topics."""
        key = f"{name}-counts"
        if key not in self._features:
            self._features[key] = materialize(registry.load(self.spark, self.sf_dir, name, counts=True), f"feature-{key}")
        return self._features[key]

    def fit(self, model: str, feature: str | None = None, train: DataFrame | None = None) -> Model:
        train = self.train if train is None else train
        f = self.feature(feature) if feature and model != "topic_hybrid" else None
        bpr = BprParams(k=self.p.k, epochs=self.p.iters)
        return {
            "wmf": lambda: fit_wmf(train, EmfParams(k=self.p.k, iters=self.p.iters, lam_u=0.01, lam_v=0.01)),
            "bpr": lambda: fit_bpr(train, bpr),
            "content_bpr": lambda: fit_content_bpr(train, f, bpr),
            "topic_hybrid": lambda: fit_topic_hybrid(train, self.counts(feature), self.p, 10),
            "mlp_hybrid": lambda: fit_mlp_hybrid(train, f, self.p, NetParams(epochs=10)),
            "dae_hybrid": lambda: fit_dae_hybrid(train, f, self.p, DaeParams(lam_n=1.0, epochs=10)),
            "emf": lambda: fit_emf(train, f, self.p),
        }[model]()

    def accuracy(self, m: Model, scenario: str, test: DataFrame | None = None, train: DataFrame | None = None, ks: tuple[int, ...] = KS) -> DataFrame:
        """Candidates: training items without the user's own, or the held-out items. Users without a test pair need no list."""
        test = self.tests[scenario] if test is None else test
        train = self.train if train is None else train
        users = m.user_factors.join(test.select(F.col("user_id").alias("id")), "id", "left_semi")
        if scenario == "in":
            lists = recommend(users, m.item_factors, train, max(ks), test)
        else:
            pool = test.select(F.col("item_id").alias("id")).distinct()
            lists = recommend(users, m.content_latents.join(pool, "id", "left_semi"), None, max(ks), test)
        return accuracy_at(lists, test, ks).withColumn("scenario", F.lit(scenario))


def _union(frames: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, frames)


def x01_dataset(spark, sf_dir):
    """Users, videos, ratings, densities before and after dropping items without a document of their own."""
    rated = materialize(interactions.ratings(spark, sf_dir), "ratings")
    docs = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("item_id"))
    return _union([stats.dataset_stats(r).withColumn("stage", F.lit(s)) for s, r in (("original", rated), ("processed", interactions.restrict(rated, docs)))])


def x02_lengths(spark, sf_dir):
    """Least, largest and mean length of English and other documents."""
    docs = table(spark, sf_dir, "documents")
    return docs.groupBy(F.when(F.col("lang") == "en", "en").otherwise("others").alias("set")).agg(F.min("n_chars").alias("min"), F.max("n_chars").alias("max"), F.avg("n_chars").alias("mean"))


def _point(w: Workload, model: str, feature: str | None, ks=(30,)) -> list[DataFrame]:
    m = w.fit(model, feature)
    out = [w.accuracy(m, "in", ks=ks)]
    if m.content_latents is not None:
        out.append(w.accuracy(m, "out", ks=ks))
    return [df.withColumns({"model": F.lit(model), "feature": F.lit(feature)}) for df in out]


def x03_scatter(spark, sf_dir, **kw):
    """In- and out-of-matrix accuracy of the baselines with their own features."""
    w = Workload(spark, sf_dir, **kw)
    combos = [("wmf", None), ("bpr", None), *[(m, f) for f in ("word", "meta") for m in ("dae_hybrid", "content_bpr", "topic_hybrid")], *[(m, "audio") for m in ("dae_hybrid", "content_bpr", "mlp_hybrid")], *[(m, "deep_fv") for m in ("dae_hybrid", "content_bpr")]]
    rows = _union([df for m, f in combos for df in _point(w, m, f)])
    return rows.groupBy("model", "feature").pivot("scenario", ["in", "out"]).agg(F.first("accuracy")).withColumnsRenamed({"in": "in30", "out": "out30"})


def x04_in_models(spark, sf_dir, feature="meta", **kw):
    w = Workload(spark, sf_dir, **kw)
    runs = [(m, None if m in ("wmf", "bpr") else feature) for m in ("wmf", "bpr", "content_bpr", "topic_hybrid", "mlp_hybrid", "dae_hybrid", "emf")]
    return _union([w.accuracy(w.fit(m, f), "in").withColumn("model", F.lit(m)) for m, f in runs])


def x05_in_features(spark, sf_dir, **kw):
    w = Workload(spark, sf_dir, **kw)
    return _union([w.accuracy(w.fit("emf", f), "in").withColumn("feature", F.lit(f)) for f in registry.ALL])


def x06_out_grid(spark, sf_dir, models=("emf", "dae_hybrid", "content_bpr", "mlp_hybrid"), features=registry.ALL, **kw):
    """Out-of-matrix accuracy by model and feature; topics run on counts only."""
    w = Workload(spark, sf_dir, **kw)
    runs = [(m, f) for m in models for f in features] + [("topic_hybrid", f) for f in features if f in ("word", "meta")]
    return _union([w.accuracy(w.fit(m, f), "out").withColumns({"model": F.lit(m), "feature": F.lit(f)}) for m, f in runs])


def x07_sparse_text(spark, sf_dir, **kw):
    """Title words alone against the features that need no text."""
    w = Workload(spark, sf_dir, **kw)
    return _union([w.accuracy(w.fit("emf", f), "out").withColumn("feature", F.lit(f)) for f in ("title", *registry.NON_TEXT)])


def x08_timing(spark, sf_dir, features=("word", "deep_fv"), models=("wmf", "bpr", "topic_hybrid", "mlp_hybrid", "dae_hybrid", "content_bpr", "emf"), dataset="quantity", k=50):
    """Seconds per iteration, with all it writes: the second iteration's own time, or for models that do not tell it the difference of two fits."""
    rows = []
    w = Workload(spark, sf_dir, dataset, p=EmfParams(k=k, iters=2))  # one split for all fits; what a fit writes goes after it
    for f in features:
        for m in models:
            if m in ("wmf", "bpr") and f != features[0]:
                continue
            own = None if m in ("wmf", "bpr") else f
            if own:
                (w.counts if m == "topic_hybrid" else w.feature)(f)
            if m not in ("bpr", "content_bpr"):
                with scratch(spark):
                    rows.append((m, own, dataset, w.fit(m, own).history[-1]["seconds"]))
                continue
            took = []
            for iters in (1, 2):
                w.p = EmfParams(k=k, iters=iters)
                with scratch(spark):
                    took.append(time_iterations(lambda m=m, own=own: w.fit(m, own), 1, 1 if iters == 1 else 0)["seconds"])
            rows.append((m, own, dataset, max(took[1] - took[0], 0.0)))
    return spark.createDataFrame(rows, "model string, feature string, dataset string, sec_per_iter double")


class Fusion:
    """Everything the fusion experiments share for a feature set: inner validation fits, their scores, the final fits."""

    def __init__(self, spark, sf_dir, features, valid_share: float = 0.25, **kw):
        self.w, self.features = Workload(spark, sf_dir, **kw), list(features)
        inner = materialize(sp.validation_cut(self.w.train, valid_share, "item"), "inner")
        self.inner, self.valid = (inner.where(F.col("inner") == x).select("user_id", "item_id") for x in ("train", "valid"))
        self.inner_models = {f: self.w.fit("emf", f, self.inner) for f in self.features}
        rows = [(f, self.w.accuracy(m, "out", self.valid, self.inner, (30,)).collect()[0]["accuracy"] or 0.0) for f, m in self.inner_models.items()]
        self.acc = spark.createDataFrame(rows, "feature string, accuracy double")
        self.models = {f: self.w.fit("emf", f) for f in self.features}

    def valid_scores(self) -> DataFrame:
        """feature, user_id, item_id, score on the validation items, for every user with a validation pair."""
        pool = self.valid.select("item_id").distinct()
        users = self.valid.select("user_id").distinct()
        out = []
        for f, m in self.inner_models.items():
            u = m.user_factors.select(F.col("id").alias("user_id"), F.col("v").alias("w")).join(users, "user_id", "left_semi")
            i = m.content_latents.select(F.col("id").alias("item_id"), F.col("v").alias("h")).join(pool, "item_id", "left_semi")
            out.append(u.crossJoin(i).select(F.lit(f).alias("feature"), "user_id", "item_id", dot(F.col("w"), F.col("h")).alias("score")))  # validation items by users: what learning to rank learns from
        return materialize(_union(out), "valid-scores")

    def weights(self, with_learned: bool = True) -> dict[str, DataFrame]:
        out = {"gpf": late.priority_weights(self.acc), "acc_fusion": late.accuracy_weights(self.acc), "avg_fusion": late.average_weights(self.acc)}
        if with_learned:
            pts = materialize(learned.sampled_points(self.inner_models, self.valid), "points")
            out |= {"pointwise_fusion": learned.pointwise_weights(pts, self.features), "pairwise_fusion": learned.pairwise_weights(pts, self.features)}
        return out

    def accuracies(self, with_early: bool = True, with_learned: bool = True) -> DataFrame:
        w, test = self.w, self.w.tests["out"]
        users, items = test.select(F.col("user_id").alias("id")).distinct(), test.select(F.col("item_id").alias("id")).distinct()
        out = [late.fused_accuracy(self.models, late.weight_map(x), users, items, test).withColumn("method", F.lit(n)) for n, x in self.weights(with_learned).items()]
        first = late.single_best(self.acc).collect()[0]["feature"]
        out.append(w.accuracy(self.models[first], "out").drop("scenario").withColumn("method", F.lit("single_best")))
        if with_early:
            feats = {f: w.feature(f) for f in self.features}
            for name, m in (("concat_fusion", early.fit_concat(w.train, feats, w.p)), ("stack_fusion", early.fit_stack(w.train, feats, w.p))):
                out.append(w.accuracy(m, "out").drop("scenario").withColumn("method", F.lit(name)))
        return materialize(_union(out), "fusion")


def x09_fusion_nontext(spark, sf_dir, **kw):
    return lift(Fusion(spark, sf_dir, registry.NON_TEXT, **kw).accuracies(), "single_best")


def x10_fusion_all(spark, sf_dir, **kw):
    return lift(Fusion(spark, sf_dir, registry.ALL, **kw).accuracies(), "single_best")


def x11_weights(spark, sf_dir, features=registry.ALL, **kw):
    """Normalized weights by fusion method and feature."""
    return _union([late.normalize(x).select(F.lit(n).alias("method"), "feature", "weight") for n, x in Fusion(spark, sf_dir, features, **kw).weights().items()])


def x12_p_grid(spark, sf_dir, sets=("all", "non_text"), **kw):
    rows = []
    for s in sets:
        f = Fusion(spark, sf_dir, registry.feature_set(s), **kw)
        rows += [(s, p, a) for p, a in late.tune_priority(f.valid_scores(), f.acc, f.valid)[1]]
    return spark.createDataFrame(rows, "set string, p double, acc double")


def x13_fusion_models(spark, sf_dir, models=("content_bpr", "dae_hybrid", "mlp_hybrid"), features=("meta", "word", "deep_fv"), **kw):
    """Priority fusion over other models' scores, with each model's divergence between features."""
    out = []
    for name in models:
        w = Workload(spark, sf_dir, **kw)
        fits = {f: w.fit(name, f) for f in features}
        single = {f: w.accuracy(m, "out", ks=(30,)).collect()[0]["accuracy"] or 0.0 for f, m in fits.items()}
        acc = spark.createDataFrame(list(single.items()), "feature string, accuracy double")
        test = w.tests["out"]
        users, items = test.select(F.col("user_id").alias("id")).distinct(), test.select(F.col("item_id").alias("id")).distinct()
        spread = max(single.values()) / max(min(single.values()), 1e-9)
        for method, weights in (("gpf", late.priority_weights(acc)), ("avg_fusion", late.average_weights(acc))):
            r = late.fused_accuracy(fits, late.weight_map(weights), users, items, test, (30,)).collect()[0]
            out.append((name, method, r["accuracy"], spread))
        out.append((name, "single_best", max(single.values()), spread))
    return spark.createDataFrame(out, "model string, method string, acc double, divergence double")


def x14_example(spark, sf_dir=None):
    """Weights of four ranked features at one half."""
    acc = spark.createDataFrame([("META", 0.4), ("CNNFV", 0.3), ("IDT", 0.2), ("MFCC", 0.1)], "feature string, accuracy double")
    return late.priority_weights(acc, 0.5)


def x15_events(spark, sf_dir, **kw):
    """The denser interaction set: purchases of events, with the blend vectors of their items."""
    w = Workload(spark, sf_dir, "events", p=EmfParams(k=6, iters=3, lam_e=10.0), own_items=True, **kw)
    return _union([w.accuracy(w.fit("emf", f), s, ks=(5, 10)).withColumns({"model": F.lit("emf"), "feature": F.lit(f)}) for f in ("deep_fv", "meta") for s in ("in", "out")])


def x16_tuning(spark, sf_dir, feature="meta", grid=tuple({"lam_e": e} for e in (1.0, 10.0, 100.0, 1000.0)), **kw):
    """Validation accuracy over a grid of penalties."""
    from dataclasses import replace

    w = Workload(spark, sf_dir, **kw)
    inner = materialize(sp.validation_cut(w.train, 0.25, "item"), "inner")
    train, valid = (inner.where(F.col("inner") == x).select("user_id", "item_id") for x in ("train", "valid"))
    f = w.feature(feature)
    score = lambda point: w.accuracy(fit_emf(train, f, replace(w.p, **point)), "out", valid, train, (30,)).collect()[0]["accuracy"] or 0.0
    _, curve = grid_search(score, grid)
    return spark.createDataFrame([("emf", str(p), a) for p, a in curve], "model string, params string, acc double")

