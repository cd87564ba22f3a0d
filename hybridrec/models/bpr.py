"""Pairwise ranking models: liked items should score above sampled others, by factors alone or with linear content."""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from hybridrec.features.made import hold, only, width, written
from hybridrec.functions import dot, portable_hash
from hybridrec.linalg import BROADCAST_BYTES, list_column, matrix, on_driver, summed
from hybridrec.models import Model
from hybridrec.models.init import hash_vectors
from hybridrec.runtime import discard, materialize, scratch


@dataclass(frozen=True)
class BprParams:
    k: int = 50
    lam_u: float = 0.0025
    lam_i: float = 0.0025
    lam_j: float = 0.00025
    lam_b: float = 0.0
    lam_p: float = 0.0025
    lam_e: float = 0.0
    rate: float = 0.05
    epochs: int = 5
    batches: int = 2
    retries: int = 3
    seed: int = 23


def sample_triples(train: DataFrame, epoch: int, seed: int, batches: int = 1, retries: int = 3) -> DataFrame:
    """user_id, i, j, batch: each positive with one hashed item the user does not like.

    Items are numbered densely; each try hashes to a number, and the first try that is no positive wins. A try is made for the pairs that
    lost all before, which are few, and written. A pair with no win in all tries gets an exact draw from its user's other items; only users
    who like every item sit out.
    """
    items = materialize(train.select("item_id").distinct(), "items")
    n = items.count()
    # dense numbers by hash bucket: bucket sizes are few, so no global sort is needed
    size = 1024
    b = F.pmod(F.xxhash64("item_id"), F.lit(size)).cast("int")
    from pyspark.sql import Window

    per = items.groupBy(b.alias("b")).agg(F.count("*").alias("c"))
    first = per.select("b", (F.sum("c").over(Window.orderBy("b")) - F.col("c")).alias("first"))  # 1,024 rows
    numbered = items.withColumn("b", b).withColumn("r", F.row_number().over(Window.partitionBy("b").orderBy("item_id")) - 1).join(F.broadcast(first), "b").select(F.col("item_id").alias("j"), (F.col("first") + F.col("r")).alias("no"))
    numbered = materialize(numbered, "numbered")
    liked = train.select("user_id", F.col("item_id").alias("j"), F.lit(True).alias("liked"))
    lost, won = train.select("user_id", F.col("item_id").alias("i")), []
    for t in range(retries):
        no = F.pmod(portable_hash(F.col("user_id"), F.col("i"), seed + 101 * epoch + 7 * t), F.lit(n))
        tried = lost.select("user_id", "i", no.alias("no")).join(numbered, "no").select("user_id", "i", "j")
        drawn = materialize(tried.join(liked, ["user_id", "j"], "left").select("user_id", "i", "j", "liked").distinct(), "drawn")
        won.append(drawn.where("liked is null").select("user_id", "i", "j"))
        lost = drawn.where("liked").select("user_id", "i")
        if lost.isEmpty():
            break
    else:
        won.append(_from_unliked(lost.distinct(), liked.select("user_id", "j").distinct(), numbered, n, seed + 101 * epoch + 7 * retries))
    return reduce(DataFrame.unionByName, won).select("user_id", "i", "j", (portable_hash(F.col("user_id"), F.col("i"), seed + epoch) % batches).cast("int").alias("batch"))


def _from_unliked(lost: DataFrame, liked: DataFrame, numbered: DataFrame, n: int, seed: int) -> DataFrame:
    """user_id, i, j: for each lost pair the item at a hashed rank among those its user does not like.

    The item of rank r has the number r plus the count of liked numbers that exceed their own place p by at most r. One sort a user
    counts them for all ranks, so rows stay those of the lost pairs and of their users' likes.
    """
    from pyspark.sql import Window

    mine = liked.join(lost.select("user_id").distinct(), "user_id", "left_semi").join(numbered, "j")
    gaps = mine.select("user_id", (F.col("no") - F.row_number().over(Window.partitionBy("user_id").orderBy("no")) + 1).alias("at"), F.lit(0).alias("ask"), F.lit(None).cast("long").alias("i"))
    left = mine.groupBy("user_id").agg((F.lit(n) - F.count("*")).alias("left")).where("left > 0")
    asks = lost.join(left, "user_id").select("user_id", F.pmod(portable_hash(F.col("user_id"), F.col("i"), seed), F.col("left")).alias("at"), F.lit(1).alias("ask"), "i")
    before = F.count(F.when(F.col("ask") == 0, 1)).over(Window.partitionBy("user_id").orderBy("at", "ask").rowsBetween(Window.unboundedPreceding, 0))
    ranked = gaps.unionByName(asks).withColumn("no", F.col("at") + before).where("ask = 1")
    return ranked.join(numbered, "no").select("user_id", "i", "j")


def _summed(grads: DataFrame, k: int, extra: bool = False) -> DataFrame:
    cols = [F.array(*[F.sum(F.col("g")[x]) for x in range(k)]).alias("g")]
    return grads.groupBy("id").agg(*cols, F.sum("gb").alias("gb") if extra else F.lit(0.0).alias("gb"))


def _moved(table: DataFrame, grads: DataFrame, rate: float, bias: bool) -> DataFrame:
    both = table.join(grads, "id", "left")
    v = F.when(F.col("g").isNull(), F.col("v")).otherwise(F.zip_with("v", "g", lambda a, g: a + rate * g))
    if not bias:
        return both.select("id", v.alias("v"))
    return both.select("id", v.alias("v"), (F.col("b") + rate * F.coalesce("gb", F.lit(0.0))).alias("b"))


def step(w: DataFrame, h: DataFrame, triples: DataFrame, p: BprParams) -> tuple[DataFrame, DataFrame]:
    """One batch: gradients of the pairwise log-likelihood, summed per user and, twice a triple, per item."""
    joined = triples.join(w.select(F.col("id").alias("user_id"), F.col("v").alias("w")), "user_id").join(h.select(F.col("id").alias("i"), F.col("v").alias("hi"), F.col("b").alias("bi")), "i").join(h.select(F.col("id").alias("j"), F.col("v").alias("hj"), F.col("b").alias("bj")), "j")
    margin = dot(F.col("w"), F.zip_with("hi", "hj", lambda a, b: a - b)) + F.col("bi") - F.col("bj")
    t = joined.withColumn("g", 1.0 / (1.0 + F.exp(margin)))
    up = lambda x, y, lam: F.zip_with(x, y, lambda a, b: F.col("g") * a - lam * b)
    user = t.select(F.col("user_id").alias("id"), F.zip_with(F.zip_with("hi", "hj", lambda a, b: F.col("g") * (a - b)), "w", lambda a, b: a - p.lam_u * b).alias("g"), F.lit(0.0).alias("gb"))
    plus = t.select(F.col("i").alias("id"), up("w", "hi", p.lam_i).alias("g2"), (F.col("g") - p.lam_b * F.col("bi")).alias("gb"))
    minus = t.select(F.col("j").alias("id"), F.zip_with("w", "hj", lambda a, b: -F.col("g") * a - p.lam_j * b).alias("g2"), (-F.col("g") - p.lam_b * F.col("bj")).alias("gb"))
    item = plus.unionByName(minus).withColumnRenamed("g2", "g")
    return _moved(w, _summed(user, p.k), p.rate, False), _moved(h, _summed(item, p.k, True), p.rate, True)


#: Roles of a triple's ids, each of which gets a gradient.
USER_ROLE, LIKED, OTHER = 0, 1, 2
#: Roles that one task adds up.
ROLES_A_TASK = 400_000


class _Sent:
    """Vectors of a bounded table on the workers, by id."""

    def __init__(self, spark, table: DataFrame, k: int, size: int):
        self.shared = spark.sparkContext.broadcast(on_driver(table, k, lambda ids, _: np.argsort(ids), size))

    def places(self, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        known = self.shared.value[0]
        at = np.minimum(np.searchsorted(known, ids), max(len(known) - 1, 0))
        return at, known[at] == ids if len(known) else np.zeros(len(ids), bool)


def _role_gradients(role: int, w: np.ndarray, hi: np.ndarray, hj: np.ndarray, p: BprParams) -> np.ndarray:
    """Gradients of triples for the ids of one role; the last value of an item's vector is its bias."""
    k = w.shape[1]
    with np.errstate(over="ignore"):
        g = 1.0 / (1.0 + np.exp((w * (hi - hj)[:, :k]).sum(1) + hi[:, k] - hj[:, k]))[:, None]
    if role == USER_ROLE:
        return g * (hi - hj)[:, :k] - p.lam_u * w
    if role == LIKED:
        return np.hstack([g * w - p.lam_i * hi[:, :k], g - p.lam_b * hi[:, k:]])
    return np.hstack([-g * w - p.lam_j * hj[:, :k], -g - p.lam_b * hj[:, k:]])


def step_sent(w: DataFrame, h: DataFrame, triples: DataFrame, p: BprParams, users: int, items: int, size: int) -> tuple[DataFrame, DataFrame]:
    """``step`` for tables that are small enough to be sent: triples move as ids alone, once for each of their roles, to where the role's id is added up."""
    spark = triples.sparkSession
    sides = _Sent(spark, w, p.k, users), _Sent(spark, with_bias(h), p.k + 1, items)
    roles = F.explode(F.array(*[F.struct(F.lit(role).alias("role"), F.col(c).alias("id")) for role, c in ((USER_ROLE, "user_id"), (LIKED, "i"), (OTHER, "j"))])).alias("r")
    dealt = triples.select("user_id", "i", "j", roles).select("r.role", "r.id", "user_id", "i", "j")
    dealt = dealt.repartition(max(1, -(-3 * size // ROLES_A_TASK)), F.col("role") == USER_ROLE, "id").select("role", "user_id", "i", "j")

    def run(batches):
        rows = [np.stack([b.column(c).to_numpy(zero_copy_only=False).astype(np.int64) for c in range(4)], 1) for b in batches if b.num_rows]
        if not rows:
            return
        role, *ids = np.concatenate(rows).T
        (u, ok), (i, ok_i), (j, ok_j) = (side.places(x) for side, x in zip((sides[0], sides[1], sides[1]), ids, strict=True))
        ok &= ok_i & ok_j
        vectors = sides[0].shared.value[1], sides[1].shared.value[1]
        for of_users in (True, False):
            asked = [(r, np.flatnonzero(ok & (role == r))) for r in ((USER_ROLE,) if of_users else (LIKED, OTHER))]
            own = [ids[r][at] for r, at in asked]
            known, place = np.unique(np.concatenate(own), return_inverse=True)
            total = np.zeros((len(known), p.k + (not of_users)))
            done = 0
            for r, at in asked:
                for a in range(0, len(at), 65536):
                    x = at[a : a + 65536]
                    g = _role_gradients(r, vectors[0][u[x]], vectors[1][i[x]], vectors[1][j[x]], p)
                    for c in range(g.shape[1]):
                        total[:, c] += np.bincount(place[done : done + len(x)], g[:, c], len(known))
                    done += len(x)
            if len(known):
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(known), of_users)), pa.array(known), list_column(total)], names=["of_users", "id", "g"])

    grads = materialize(dealt.mapInArrow(run, "of_users boolean, id long, g array<double>"), "gradients")
    for side in sides:
        side.shared.destroy()
    of_items = grads.where(~F.col("of_users")).select("id", F.slice("g", 1, p.k).alias("g"), F.col("g")[p.k].alias("gb"))
    return _moved(w, grads.where("of_users").select("id", "g"), p.rate, False), _moved(h, of_items, p.rate, True)


def with_bias(h: DataFrame) -> DataFrame:
    """id, v: the bias as one more coordinate, which users meet with a one."""
    return h.select("id", F.concat(F.col("v"), F.array(F.col("b"))).alias("v"))


def fit_bpr(train: DataFrame, p: BprParams = BprParams()) -> Model:
    """In-matrix only. An epoch visits every positive once, in hashed mini-batches with full sums, so partitioning does not matter."""
    w = materialize(hash_vectors(train.select("user_id"), "user_id", p.k, p.seed), "w")
    h = materialize(hash_vectors(train.select("item_id"), "item_id", p.k, p.seed + 1).withColumn("b", F.lit(0.0)), "h")
    users, items = w.count(), h.count()
    small = 8 * (users * (p.k + 1) + items * (p.k + 2)) <= BROADCAST_BYTES
    stale: list[str] = []
    for epoch in range(p.epochs):
        with scratch(train.sparkSession) as used:
            with scratch(train.sparkSession) as drawn:
                triples = materialize(sample_triples(train, epoch, p.seed, p.batches, p.retries), "triples")
                drawn.pop()
            sizes = dict(triples.groupBy("batch").count().collect())  # one row a batch
            for b in range(p.batches):
                batch = triples.where(F.col("batch") == b)
                w2, h2 = step_sent(w, h, batch, p, users, items, sizes.get(b, 0)) if small else step(w, h, batch, p)
                w, h = materialize(w2, "w"), materialize(h2, "h")
            kept = used[-2:]
            used[:] = [x for x in used[:-2] if x not in kept] + stale
            stale = kept
    return Model(w.select("id", F.concat("v", F.array(F.lit(1.0))).alias("v")), with_bias(h), None, [], {"params": p})


def pairwise_batch(rows, e: np.ndarray, beta: np.ndarray, p: BprParams):
    """Gradients of one Arrow batch of triples with content: user, items, embedding, content bias, and the log-likelihood."""
    arr = lambda c: np.array(rows[c].tolist(), float)
    w, v, hi, hj, fi, fj = arr("w"), arr("u"), arr("hi"), arr("hj"), arr("fi"), arr("fj")
    bi, bj = rows["bi"].to_numpy(float), rows["bj"].to_numpy(float)
    df = fi - fj
    c = df @ e
    margin = (w * (hi - hj)).sum(1) + (v * c).sum(1) + df @ beta + bi - bj
    g = 1 / (1 + np.exp(np.clip(margin, -30, 30)))
    s = g[:, None]
    return {
        "w": s * (hi - hj) - p.lam_u * w,
        "u": s * c - p.lam_p * v,
        "hi": s * w - p.lam_i * hi,
        "hj": -s * w - p.lam_j * hj,
        "bi": g - p.lam_b * bi,
        "bj": -g - p.lam_b * bj,
        "e": df.T @ (s * v),
        "beta": df.T @ g,
        "loss": float(-np.logaddexp(0, -margin).sum()),
    }


USER, ITEM, LOSS = 0, 1, 2


def image_gradients(t: pa.RecordBatch, k: int, p: BprParams):
    """Gradients of one Arrow batch of triples by the images ``ci`` and ``cj`` of their content, whose last value is the content bias: of users (w, u),
    of liked and of other items (h, b, and by their image), and the log-likelihood."""
    w, u, hi, hj, ci, cj = (matrix(t.column(c)) for c in ("w", "u", "hi", "hj", "ci", "cj"))
    bi, bj = (t.column(c).to_numpy(zero_copy_only=False) for c in ("bi", "bj"))
    c = ci[:, :k] - cj[:, :k]
    margin = (w * (hi - hj)).sum(1) + (u * c).sum(1) + ci[:, k] - cj[:, k] + bi - bj
    g = 1 / (1 + np.exp(np.clip(margin, -30, 30)))
    s = g[:, None]
    image = np.hstack([s * u, s])
    user = np.hstack([s * (hi - hj) - p.lam_u * w, s * c - p.lam_p * u])
    i = np.hstack([s * w - p.lam_i * hi, (g - p.lam_b * bi)[:, None], image])
    j = np.hstack([-s * w - p.lam_j * hj, (-g - p.lam_b * bj)[:, None], -image])
    return user, i, j, float(-np.logaddexp(0, -margin).sum())


def _content_joined(w: DataFrame, own: DataFrame, triples: DataFrame, p: BprParams) -> tuple[DataFrame, DataFrame, float]:
    """(id, g) of users and of items for one batch, and its log-likelihood: the vectors of all sides are joined to the triples."""
    k = p.k
    side = lambda t, x: t.join(own.select(F.col("id").alias(x), F.col("v").alias(f"h{x}"), F.col("b").alias(f"b{x}"), F.col("c").alias(f"c{x}")), x)
    rows = side(side(triples.join(w.select(F.col("id").alias("user_id"), F.slice("v", 1, k).alias("w"), F.slice("v", k + 1, k).alias("u")), "user_id"), "i"), "j")

    def run(batches):
        for t in batches:
            if t.num_rows:
                user, i, j, loss = image_gradients(t, k, p)
                one = lambda kind, ids, g: pa.RecordBatch.from_arrays([pa.array(np.full(len(g), kind, np.int32)), ids.cast(pa.int64()), list_column(g)], names=["kind", "id", "g"])
                yield one(USER, t.column("user_id"), user)
                yield one(ITEM, t.column("i"), i)
                yield one(ITEM, t.column("j"), j)
                yield one(LOSS, pa.array([0]), np.array([[loss]]))

    grads = materialize(rows.mapInArrow(run, "kind int, id long, g array<double>"), "gradients")
    sums = materialize(grads.where(F.col("kind") == ITEM).groupBy("id").agg(summed("g").alias("g")), "item-gradients")
    loss = grads.where(F.col("kind") == LOSS).agg(F.sum(F.col("g")[0])).collect()[0][0] or 0.0
    return grads.where(F.col("kind") == USER).groupBy("id").agg(summed("g").alias("g")), sums, loss


#: Triples that one task has together.
TRIPLES_A_TASK = 200_000


def _content_sent(w: DataFrame, own: DataFrame, triples: DataFrame, p: BprParams, users: int, items: int, size: int) -> tuple[DataFrame, DataFrame, float]:
    """The same for tables that are small enough to be sent, one at a time.

    Where a user's triples meet, the items' sides are known and each triple gets its slope, a single number. Where an item's slopes meet, the users'
    vectors are known. So triples move as ids and slopes, and no vector moves with them.
    """
    k, spark, tasks = p.k, triples.sparkSession, max(1, -(-size // TRIPLES_A_TASK))
    sides = _Sent(spark, own.select("id", F.concat("v", F.array("b"), "c").alias("v")), 2 * k + 2, items)
    met = triples.select("user_id", "i", "j").repartition(tasks, "user_id").join(w.select(F.col("id").alias("user_id"), "v"), "user_id").select("user_id", "i", "j", "v")

    def slopes(batches):
        vectors, loss = sides.shared.value[1], 0.0
        for t in batches:
            u, i, j = (t.column(c).to_numpy(zero_copy_only=False).astype(np.int64) for c in range(3))
            (a, ok), (b, ok_j) = sides.places(i), sides.places(j)
            ok &= ok_j
            if not ok.any():
                continue
            u, i, j, v, gap = u[ok], i[ok], j[ok], matrix(t.column(3))[ok], vectors[a[ok]] - vectors[b[ok]]
            margin = (v[:, :k] * gap[:, :k]).sum(1) + (v[:, k:] * gap[:, k + 1 : -1]).sum(1) + gap[:, -1] + gap[:, k]
            s = 1 / (1 + np.exp(np.clip(margin, -30, 30)))
            loss -= float(np.logaddexp(0, -margin).sum())
            g = s[:, None] * np.hstack([gap[:, :k], gap[:, k + 1 : -1]])
            g[:, :k] -= p.lam_u * v[:, :k]
            g[:, k:] -= p.lam_p * v[:, k:]
            ids, place = np.unique(u, return_inverse=True)
            yield _slope_rows(LIKED, u, i, j, s, None)
            yield _slope_rows(USER_ROLE, ids, ids, ids, np.zeros(len(ids)), np.stack([np.bincount(place, x, len(ids)) for x in g.T], 1))
        one = np.zeros(1, np.int64)
        yield _slope_rows(LOSS_ROLE, one, one, one, np.array([loss]), None)

    passed = materialize(met.mapInArrow(slopes, "kind int, user_id long, i long, j long, s double, g array<double>"), "gradients")
    sides.shared.destroy()
    sent = _Sent(spark, w, 2 * k, users)
    role = F.explode(F.array(F.struct(F.col("i").alias("id"), F.col("s").alias("s"), F.lit(True).alias("liked")), F.struct(F.col("j").alias("id"), (-F.col("s")).alias("s"), F.lit(False).alias("liked")))).alias("r")
    dealt = passed.where(F.col("kind") == LIKED).select("user_id", role).select("r.id", "user_id", "r.s", "r.liked").repartition(max(1, -(-2 * size // ROLES_A_TASK)), "id")

    def added(batches):
        rows = [[b.column(c).to_numpy(zero_copy_only=False) for c in range(4)] for b in batches if b.num_rows]
        if not rows:
            return
        ids, u, s, liked = (np.concatenate(x) for x in zip(*rows, strict=True))
        known, place = np.unique(ids, return_inverse=True)
        at, ok = sent.places(u)
        vectors, total = sent.shared.value[1], np.zeros((len(known), 2 * k + 4))
        for a in range(0, len(ids), 65536):
            x = np.arange(a, min(a + 65536, len(ids)))[ok[a : a + 65536]]
            v = vectors[at[x]] * s[x, None]
            columns = [*v.T[:k], s[x], *v.T[k:], s[x], liked[x], ~liked[x]]
            for c, column in enumerate(columns):
                total[:, c] += np.bincount(place[x], column, len(known))
        yield pa.RecordBatch.from_arrays([pa.array(known), list_column(total)], names=["id", "g"])

    raw = materialize(dealt.mapInArrow(added, "id long, g array<double>"), "item-sums")
    sent.shared.destroy()
    # what is drawn back is the item's own, once a triple
    n, m = F.col("g")[2 * k + 2], F.col("g")[2 * k + 3]
    back = F.zip_with(F.slice("g", 1, k), "v", lambda g, v: g - (p.lam_i * n + p.lam_j * m) * v)
    sums = raw.join(own.select("id", "v", "b"), "id").select("id", F.concat(back, F.array(F.col("g")[k] - p.lam_b * (n + m) * F.col("b")), F.slice("g", k + 2, k + 1)).alias("g"))
    sums = materialize(sums, "item-gradients")
    discard(raw)
    loss = passed.where(F.col("kind") == LOSS_ROLE).agg(F.sum("s")).collect()[0][0] or 0.0
    return passed.where(F.col("kind") == USER_ROLE).groupBy(F.col("user_id").alias("id")).agg(summed("g").alias("g")), sums, loss


LOSS_ROLE = 3


def _slope_rows(kind: int, u: np.ndarray, i: np.ndarray, j: np.ndarray, s: np.ndarray, g: np.ndarray | None) -> pa.RecordBatch:
    vectors = pa.nulls(len(u), pa.list_(pa.float64())) if g is None else list_column(g)
    return pa.RecordBatch.from_arrays([pa.array(np.full(len(u), kind, np.int32)), pa.array(u), pa.array(i), pa.array(j), pa.array(s), vectors], names=["kind", "user_id", "i", "j", "s", "g"])


def fit_content_bpr(train: DataFrame, features: DataFrame, p: BprParams = BprParams()) -> Model:
    """Pairwise ranking with a linear content term for a second user vector; content alone scores unseen items.

    Triples never meet content vectors: they meet their k + 1 images under the matrix and the bias, and the gradients by these, summed per item, meet
    the content vectors once a batch in one d x (k + 1) partial per task.
    """
    from hybridrec.models.emf import content_sums, embed

    features = hold(features, "features")
    d, k = width(features), p.k
    known = train.join(getattr(features, "ids", features).select("item_id"), "item_id", "left_semi").select("user_id", "item_id")
    known = materialize(known, "known")
    w = materialize(hash_vectors(known.select("user_id"), "user_id", 2 * k, p.seed), "w")
    h = materialize(hash_vectors(known.select("item_id"), "item_id", k, p.seed + 1).withColumn("b", F.lit(0.0)), "h")
    of_items = written(only(features, known.select("item_id").distinct()), "known-items")  # all that triples have
    e, beta, history = np.random.default_rng(p.seed).normal(0, 0.01, (d, k)), np.zeros(d), []
    users, items = w.count(), h.count()
    small = 8 * max(users * (2 * k + 1), items * (2 * k + 3)) <= BROADCAST_BYTES  # one of the tables is sent at a time
    for epoch in range(p.epochs):
        with scratch(train.sparkSession) as drawn:
            triples = materialize(sample_triples(known, epoch, p.seed, p.batches, p.retries), "triples")
            drawn.pop()
        sizes = dict(triples.groupBy("batch").count().collect())  # one row a batch
        total = 0.0
        for b in range(p.batches):
            with scratch(train.sparkSession) as used:
                image = embed(of_items, np.hstack([e, beta[:, None]])).select("id", F.col("v").alias("c"))
                own = materialize(h.join(image, "id"), "sides")
                batch = triples.where(F.col("batch") == b)
                users_g, sums, loss = _content_sent(w, own, batch, p, users, items, sizes.get(b, 0)) if small else _content_joined(w, own, batch, p)
                discard(own)
                step_e = content_sums(of_items, d, sums.select("id", F.slice("g", k + 2, k + 1).alias("v")), k + 1)
                e, beta = e + p.rate * (step_e[:, :k] - p.lam_e * e), beta + p.rate * step_e[:, k]
                total += loss
                old = w, h
                w = materialize(_moved(w, users_g.withColumn("gb", F.lit(0.0)), p.rate, False), "w")
                used.pop()
                h = materialize(_moved(h, sums.select("id", F.slice("g", 1, k).alias("g"), F.col("g")[k].alias("gb")), p.rate, True), "h")
                used.pop()
                discard(*old)
        discard(triples)
        history.append({"iteration": epoch, "objective": total})
    table = np.hstack([e, beta[:, None]])
    latents = embed(features, table)  # k content values and the content bias
    zero = F.array_repeat(F.lit(0.0), k)
    users = w.select("id", F.concat("v", F.array(F.lit(1.0), F.lit(1.0))).alias("v"))
    content = latents.select("id", F.concat(zero, F.slice("v", 1, k), F.slice("v", k + 1, 1), F.array(F.lit(0.0))).alias("v"))
    seen = h.join(latents.select("id", F.col("v").alias("c")), "id").select("id", F.concat("v", F.slice("c", 1, k), F.slice("c", k + 1, 1), F.array("b")).alias("v"))
    return Model(users, seen, materialize(content, "content"), history, {"params": p, "e": e, "beta": beta})


