"""Mixing to target weights with soft membership, in column expressions alone.

1. A classifier learns the domains from the labelled table: a multinomial model over the most telling words and all others as one, fitted on a bounded sample
   of labelled documents, gives every document the posterior of each domain; priors are even or the domains' shares of the labelled documents.
2. Nonnegative rates r minimise the squared distance between the expected domain totals, sum of r x tokens x posterior, and the targets,
   plus a small pull to rate 1. A document's rate is the projection onto the bounds of rate 1 less a multiple of its gradient, which is linear in its
   posteriors with one multiplier a domain. Ascent steps on the multipliers, scaled by the curvature of the documents off their bounds, run until such
   a projected-gradient step changes nothing: a step is one aggregate over all documents and a few numbers on the driver.
3. A document is taken floor(r) times and once more with the probability of the fraction, decided by a hash of its id.

Domains: ``toxic`` if labelled so, else ``good`` or ``plain`` by quality. Unlabelled documents, empty texts and words never seen take the
prior. Null text has no tokens. Rows that share a doc_id share a rate. With no usable label at all every domain is equally likely. Labels
that are null or contradict each other for a document do not teach. Extra columns are ignored by :func:`rates` and kept by
:func:`mix`; an empty table gives an empty result.
"""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import reduce

import numpy as np
from pyspark.sql import Column, DataFrame, Window, functions as F

from hybridrec.llm.texts import ascii_lower
from hybridrec.runtime import materialize

DOMAINS = ("good", "plain", "toxic")


@dataclass(frozen=True)
class Mix:
    #: Share of the tokens each domain should have.
    shares: dict = field(default_factory=lambda: {"good": 0.93, "plain": 0.06, "toxic": 0.01})
    #: All tokens wanted, as a multiple of what the documents have; None: as many as need the domain of the largest share whole, at rate one.
    size: float | None = 1.0
    most: float = 4.0
    pull: float = 1e-4
    steps: int = 60
    #: Stop when the gradient of every multiplier, in shares of all tokens, is within this.
    tolerance: float = 1e-7
    #: Documented bound of the labelled sample, in documents a domain (those with the smallest hash), and of the words used.
    sample: int = 1500
    words: int = 1024
    #: Least likelihood ratio (G squared) of a telling word: under chance alone one in hundreds of thousands has so much.
    telling: float = 24.0
    #: ``even``: every domain that has a labelled document is equally likely before the text is read; ``labels``: as likely as its share of these documents.
    priors: str = "even"
    #: Evidence counts as if a document had so many words at most: longer ones would be all too sure of themselves.
    certain_words: float = 400.0


def _words(text: Column) -> Column:
    """Words of a text; white space is made one kind first, so that splitting needs no pattern."""
    plain = F.translate(ascii_lower(F.coalesce(text, F.lit(""))), "\t\n\x0b\x0c\r", "     ")
    return F.split(plain, " ")


def labelled(docs: DataFrame, labels: DataFrame, mix: Mix) -> DataFrame:
    """doc_id, domain, text of the labelled sample: of each domain the documents with the smallest hash, at most ``mix.sample``; ``stands``: for how many labelled ones each stands."""
    quality, toxic = F.col("quality"), F.col("toxic")
    domain = F.when(toxic == 1, "toxic").when(quality == 1, "good").when(quality == 0, "plain")
    clear = labels.select(F.col("doc_id").cast("long").alias("doc_id"), domain.alias("domain")).where("domain is not null and doc_id is not null").groupBy("doc_id").agg(F.min("domain").alias("domain"), F.max("domain").alias("other")).where("domain = other")
    # a threshold on the hash first, so that no domain's documents meet in one task
    sizes = clear.groupBy("domain").agg(F.count("*").alias("n"))
    h = F.xxhash64("doc_id", F.lit(5))
    thin = clear.join(F.broadcast(sizes), "domain").where((F.pmod(h, F.lit(1 << 20)) < 3.0 * mix.sample / F.col("n") * (1 << 20)) | (F.col("n") <= 4 * mix.sample))
    w = Window.partitionBy("domain").orderBy(h, "doc_id")
    chosen = thin.withColumn("r", F.row_number().over(w)).where(F.col("r") <= mix.sample).select("doc_id", "domain", (F.col("n") / F.least(F.col("n"), F.lit(mix.sample))).alias("stands"))
    texts = docs.select(F.col("doc_id").cast("long").alias("id"), "text")
    return texts.join(F.broadcast(chosen), F.col("id") == F.col("doc_id")).select("doc_id", "domain", "text", "stands")  # at most sample x domains rows


def learn(sample: DataFrame, mix: Mix) -> tuple[list[tuple], list[float], list[float]]:
    """Log-weights of the most telling words per domain, bounded by ``mix.words``; of any other word; and log-priors."""
    k = len(DOMAINS)
    words = sample.select("domain", F.explode(_words(F.col("text"))).alias("word")).where("word != ''")
    counts = words.groupBy("word").agg(*[F.count_if(F.col("domain") == d).alias(d) for d in DOMAINS])
    counts = materialize(counts, "domain-words")
    totals = counts.agg(*[F.coalesce(F.sum(d), F.lit(0)).alias(d) for d in DOMAINS], F.count("*").alias("v")).collect()[0]
    size = [float(totals[d]) for d in DOMAINS]
    v = float(totals["v"])
    # smoothed against the pooled frequency, so that a word absent from a small domain is no proof
    pooled = sum((F.col(d) for d in DOMAINS[1:]), F.col(DOMAINS[0])) / F.lit(max(sum(size), 1.0))
    logs = [F.log((F.col(d) + 2.0 * pooled * F.lit(v) + 0.01) / F.lit(n + 2.0 * v + 0.01 * v)) for d, n in zip(DOMAINS, size, strict=True)]
    all_ = sum((F.col(d) for d in DOMAINS[1:]), F.col(DOMAINS[0]))
    gain = [F.when(F.col(d) > 0, F.col(d) * F.log(F.col(d) * F.lit(sum(size)) / (all_ * F.lit(n)))).otherwise(0.0) for d, n in zip(DOMAINS, size, strict=True) if n]
    weight = 2.0 * sum(gain[1:], gain[0]) if gain else F.lit(0.0)
    top = counts.select("word", *[x.alias(d) for d, x in zip(DOMAINS, logs, strict=True)], weight.alias("weight")).where(F.col("weight") >= mix.telling).orderBy(F.desc("weight"), "word").limit(mix.words).collect()
    own = np.array([[r[d] for d in DOMAINS] for r in top]).reshape(-1, k)
    rest = np.log(np.maximum(1.0 - np.exp(own).sum(0), 1e-12))  # telling words that are missing tell as well
    share = {r["domain"]: r["n"] for r in sample.groupBy("domain").agg(F.sum("stands").alias("n")).collect()}
    if mix.priors == "even":
        share = dict.fromkeys(share, 1.0)
    elif mix.priors != "labels":
        raise ValueError(f"no priors {mix.priors!r}")
    prior = [float(np.log(share[d] / sum(share.values()))) if d in share else -20.0 if share else 0.0 for d in DOMAINS]
    centred = own - own.mean(1, keepdims=True)
    return [(r["word"], *map(float, x)) for r, x in zip(top, centred, strict=True)], [float(x) for x in rest - rest.mean()], prior


def posteriors(docs: DataFrame, weights: list[tuple], rest: list[float], prior: list[float], mix: Mix) -> DataFrame:
    """doc_id, tokens and one posterior per domain, one row per document id."""
    spark = docs.sparkSession
    table = spark.createDataFrame(weights, "word string, " + ", ".join(f"w_{d} double" for d in DOMAINS))
    words = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.explode_outer(_words(F.col("text"))).alias("word"))
    scored = words.join(F.broadcast(table), "word", "left")  # mix.words rows at most
    sums = scored.groupBy("doc_id").agg(F.count_if(F.col("word") != "").alias("tokens"), F.count(f"w_{DOMAINS[0]}").alias("telling"), *[F.coalesce(F.sum(f"w_{d}"), F.lit(0.0)).alias(f"s_{d}") for d in DOMAINS])
    scale = F.least(F.lit(1.0), F.lit(mix.certain_words) / F.greatest(F.col("tokens"), F.lit(1)))
    logits = [(F.col(f"s_{d}") + (F.col("tokens") - F.col("telling")) * F.lit(r)) * scale + F.lit(p) for d, r, p in zip(DOMAINS, rest, prior, strict=True)]
    top = F.greatest(*logits)
    powers = [F.exp(x - top) for x in logits]
    return sums.select("doc_id", "tokens", *[(p / sum(powers[1:], powers[0])).alias(f"p_{d}") for d, p in zip(DOMAINS, powers, strict=True)])


#: Lengths tried in one pass, of the step by the free documents' curvature and of the one by all documents'. The latter, at length one, always climbs.
FREE_LENGTHS, SAFE_LENGTHS = (1.0, 0.25), (1.0, 8.0, 64.0)


def fit_rates(members: DataFrame, mix: Mix) -> Column:
    """The rate as an expression of ``members``' posterior columns.

    Minimises half of the sum over domains of weight x (total - target)^2, in shares of all tokens, plus half of ``pull`` times the token-weighted
    squared distance from rate 1, for rates in [0, most]. Weighing by the second moments makes small domains count. At the optimum each rate is
    the projection of 1 - u . posteriors, where ``pull`` x u = weight x (total - target); the concave dual in u is climbed by Newton steps
    or, where too few documents are off their bounds, by steps that the curvature of all documents makes safe; a pass tries several and keeps the best.
    """
    p = [F.col(f"p_{d}") for d in DOMAINS]
    k = len(DOMAINS)
    total = lambda x: F.coalesce(F.sum(F.col("tokens") * x), F.lit(0.0))
    cells = [(i, j) for i in range(k) for j in range(i, k)]
    first = members.agg(F.coalesce(F.sum("tokens"), F.lit(0)).alias("z"), *[total(p[i] * p[j]).alias(f"m{i}{j}") for i, j in cells], *[total(x).alias(f"n{i}") for i, x in enumerate(p)]).collect()[0]
    z = float(first["z"]) or 1.0
    whole = np.array([[first[f"m{min(i, j)}{max(i, j)}"] / z for j in range(k)] for i in range(k)])
    weight = domain_weights(whole)
    wanted = np.array([mix.shares.get(d, 0.0) for d in DOMAINS])
    wanted = wanted / max(wanted.sum(), 1e-12)
    size = mix.size
    if size is None:
        main = int(np.argmax(wanted))
        size = first[f"n{main}"] / z / max(wanted[main], 1e-12)
    wanted, pull = size * wanted, max(mix.pull, 1e-9)

    def free(u: np.ndarray) -> Column:
        return F.lit(1.0) - reduce(lambda x, y: x + y, [x * float(c) for x, c in zip(p, u, strict=True)])

    def rate(u: np.ndarray) -> Column:
        return F.greatest(F.lit(0.0), F.least(F.lit(float(mix.most)), free(u)))

    def look(us: list[np.ndarray]) -> list[tuple[float, np.ndarray, np.ndarray]]:
        """Height, gradient and curvature of the dual at each of ``us``, from one pass."""
        sums, shown = [], members
        for n, u in enumerate(us):
            shown = shown.withColumns({f"r{n}": rate(u), f"f{n}": free(u).between(0.0, mix.most).cast("double")})
        for n in range(len(us)):
            r = F.col(f"r{n}")
            sums += [total((r - 1.0) * (r - 1.0)).alias(f"d{n}"), *[total(r * x).alias(f"t{n}_{i}") for i, x in enumerate(p)], *[total(F.col(f"f{n}") * p[i] * p[j]).alias(f"h{n}_{i}{j}") for i, j in cells]]
        got, out = shown.agg(*sums).collect()[0], []
        for n, u in enumerate(us):
            v, t = pull * u, np.array([got[f"t{n}_{i}"] / z for i in range(k)])
            curve = np.array([[got[f"h{n}_{min(i, j)}{max(i, j)}"] / z for j in range(k)] for i in range(k)])
            out.append((0.5 * pull * got[f"d{n}"] / z + v @ (t - wanted) - (v * v / weight).sum() / 2, t - wanted - v / weight, curve + np.diag(pull / weight)))
        return out

    u = np.zeros(k)
    height, slope, curve = look([u])[0]
    for _ in range(mix.steps):
        if np.abs(slope).max() <= mix.tolerance:
            break
        push, safe = np.linalg.solve(curve, slope), np.linalg.solve(whole + np.diag(pull / weight), slope)
        tried = [u + part * push for part in FREE_LENGTHS] + [u + part * safe for part in SAFE_LENGTHS]
        seen = look(tried)
        best = max(range(len(seen)), key=lambda n: seen[n][0])
        if seen[best][0] <= height:
            break  # no length gains anything: as far as double precision goes
        u, (height, slope, curve) = tried[best], seen[best]
    return rate(u)


def domain_weights(moments: np.ndarray) -> np.ndarray:
    """1 / second moment of each domain's posterior; domains hardly present count as one in 10,000."""
    return 1.0 / np.maximum(np.diag(moments), 1e-4)


def rates(docs: DataFrame, labels: DataFrame, mix: Mix = Mix()) -> DataFrame:
    """doc_id, tokens, posteriors, rate and copies, one row per document id."""
    members = materialize(posteriors(docs, *learn(labelled(docs, labels, mix), mix), mix), "members")
    rate = F.when(F.col("tokens") >= 0, fit_rates(members, mix))
    drawn = F.pmod(F.xxhash64("doc_id", F.lit(11)), F.lit(1 << 24)) / F.lit(float(1 << 24))
    out = members.withColumn("rate", rate)
    return out.withColumn("copies", F.floor("rate") + F.when(drawn < F.col("rate") - F.floor("rate"), 1).otherwise(0))


def mix(docs: DataFrame, labels: DataFrame, how: Mix = Mix()) -> DataFrame:
    """The documents, each as often as its copies say, with all their columns."""
    chosen = rates(docs, labels, how).where("copies > 0").select(F.col("doc_id").alias("id"), "copies")
    own = docs.select(F.struct(*docs.columns).alias("d"))
    many = own.join(chosen, F.col("d.doc_id").cast("long").eqNullSafe(F.col("id"))).select("d", F.explode(F.array_repeat(F.lit(1), F.col("copies").cast("int"))).alias("one"))
    return many.select(*[F.col("d")[c].alias(c) for c in docs.columns])
