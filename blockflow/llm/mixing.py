"""Mixing documents to target domain weights by soft membership, in DataFrame functions only.

Membership. A document has a handful of discretised features of its text and a bag of hashed words. From the labelled
documents, a naive Bayes classifier learns how features and word buckets are distributed in each domain, and gives every
document its posterior over the domains; so a document without a label, or one between domains, belongs to several in part.

Rates. Document i has n_i tokens (words) and posteriors p_i. Its rate w_i >= floor is how often it should be read. The
expected tokens of domain d are the sum of w_i n_i p_id. The rates are those that meet the targets to within `tolerance` and
else stay as near to 1 as they can, which are projections onto the floor of 1 plus p_i times one number for each domain. These
numbers are found by Newton's method, a round of which needs one aggregation over the documents; only numbers for each domain
and pair of domains reach the driver. Where no rates meet the targets, the distance left is logged as a warning.

Domains are the labelled table's (quality, toxic) pairs; the classifier is fitted on at most `sample` labelled rows.

Defined cases: null text counts as empty; an empty text has no tokens and keeps the rate it starts with, 1; rows are rated one
by one; without labelled rows every document belongs to one domain, `all`; a target for a domain that no document can belong
to is ignored, as no rates reach it; an empty table gives an empty result.
"""

from __future__ import annotations

import logging
import math
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from blockflow.session import materialize


@dataclass(frozen=True)
class MixConfig:
    sample: int = 20_000
    buckets: int = 1024
    smoothing: float = 1.0
    #: Weight of a document's words beside its other features, as words are far from independent.
    tempering: float = 30.0
    #: Least rate of a document.
    floor: float = 0.0
    #: Whether the targets are shares of as many tokens as the corpus has, or of so many that no domain must shrink.
    grow: bool = False
    #: Distance of the domains' tokens from their targets, in shares of the corpus.
    tolerance: float = 1e-4


LOG = logging.getLogger(__name__)

GAP = r"[\x20\x09-\x0D]+"
_STEPS = {"symbols": "[#*$%&|<>]", "stress": "[!?]", "upper": "[A-Z]", "digits": "[0-9]", "stops": "[.,;:]"}


def features(docs: DataFrame, config: MixConfig) -> DataFrame:
    """Add n_tokens, mix_f (codes of discretised features) and mix_b (the hash bucket of each word)."""
    text = F.coalesce(F.col("text"), F.lit(""))
    staged = docs.withColumn("mix_w", F.filter(F.split(text, GAP), lambda w: w != ""))
    staged = staged.withColumn("n_tokens", F.size("mix_w").cast("long"))
    staged = staged.withColumn("mix_b", F.expr(f"transform(mix_w, w -> cast(pmod(hash(w), {config.buckets}) as int))")).drop("mix_w")
    n = F.greatest(F.length(text), F.lit(1))
    share = lambda chars: F.least(F.lit(7), F.floor(F.log2(1 + 256 * F.regexp_count(text, F.lit(chars)) / n))).cast("int")
    codes = [F.least(F.lit(15), F.floor(F.log2(1 + F.col("n_tokens")))).cast("int"), *[share(c) for c in _STEPS.values()]]
    varied = F.floor(8 * F.size(F.array_distinct("mix_b")) / F.greatest(F.least(F.col("n_tokens"), F.lit(config.buckets)), F.lit(1))).cast("int")
    return staged.withColumn("mix_f", F.array(*[c + 16 * k for k, c in enumerate([*codes, F.least(F.lit(15), varied)])]))


#: Feature codes run below this.
CODES = 16 * (len(_STEPS) + 2)


@dataclass(frozen=True)
class DomainModel:
    domains: tuple[str, ...]
    log_prior: tuple[float, ...]
    #: By feature code, then by domain; by word bucket, then by domain.
    log_code: tuple[tuple[float, ...], ...]
    log_bucket: tuple[tuple[float, ...], ...]


def fit_domains(docs: DataFrame, labelled: DataFrame, config: MixConfig) -> DomainModel:
    """Naive Bayes of labelled (doc_id, domain) over features(docs); counts of codes and buckets alone reach the driver."""
    known = labelled.where("doc_id is not null and domain is not null").groupBy("doc_id").agg(F.min("domain").alias("domain"))
    # at most config.sample rows of an id and a short label, so this may be broadcast
    chosen = known.orderBy(F.xxhash64("doc_id"), "doc_id").limit(config.sample)
    rows = features(docs.select("doc_id", "text").join(F.broadcast(chosen), "doc_id"), config)
    items = rows.select("domain", F.explode(F.concat(F.array(F.lit(-1)), "mix_f", F.transform("mix_b", lambda b: b + CODES))).alias("item"))
    counts = items.groupBy("domain", "item").agg(F.count(F.lit(1)).alias("n")).collect()
    domains = tuple(sorted({r["domain"] for r in counts})) or ("all",)
    table = {(r["domain"], r["item"]): r["n"] for r in counts}
    docs = [table.get((d, -1), 0) for d in domains]
    prior = tuple(math.log((n + config.smoothing) / (sum(docs) + config.smoothing * len(domains))) for n in docs)
    a = config.smoothing
    code = tuple(tuple(math.log((table.get((d, k), 0) + a) / (n + 16 * a)) for d, n in zip(domains, docs, strict=True)) for k in range(CODES))
    words = [sum(table.get((d, k), 0) for k in range(CODES, CODES + config.buckets)) for d in domains]
    bucket = tuple(tuple(math.log((table.get((d, k + CODES), 0) + a) / (n + config.buckets * a)) for d, n in zip(domains, words, strict=True)) for k in range(config.buckets))
    return DomainModel(domains, prior, code, bucket)


def posteriors(featured: DataFrame, model: DomainModel, config: MixConfig) -> DataFrame:
    """Add p, the array of domain posteriors in the model's order."""
    lit = lambda table, d: F.array(*[F.lit(row[d]) for row in table])
    # log odds against the first domain, so that this one needs no sum
    staged, logs = featured, [F.lit(0.0)]
    for d in range(1, len(model.domains)):
        over = lambda table, d=d: [(row[d] - row[0],) for row in table]
        staged = staged.withColumn(f"mix_c{d}", lit(over(model.log_code), 0)).withColumn(f"mix_t{d}", lit(over(model.log_bucket), 0))
        word = F.expr(f"aggregate(mix_b, cast(0 as double), (a, b) -> a + mix_t{d}[b])")
        code = F.expr(f"aggregate(mix_f, cast(0 as double), (a, b) -> a + mix_c{d}[b])")
        # a long text's words weigh no more than `tempering` of them would
        weight = F.least(F.lit(1.0), F.lit(config.tempering) / F.greatest(F.size("mix_b"), F.lit(1)))
        logs.append(F.lit(model.log_prior[d] - model.log_prior[0]) + code + word * weight)
    staged = staged.withColumn("mix_l", F.array(*logs)).drop(*[f"mix_{x}{d}" for x in "ct" for d in range(1, len(logs))])
    staged = staged.withColumn("mix_l", F.expr("transform(mix_l, x -> exp(x - array_max(mix_l)))"))
    return staged.withColumn("p", F.expr("transform(mix_l, x -> x / aggregate(mix_l, cast(0 as double), (a, b) -> a + b))")).drop("mix_l", "mix_b", "mix_f")


def _raised(lift: list[float], floor: float) -> Column:
    """A document's rate before it is held above the floor."""
    return sum((F.lit(float(x)) * F.get("p", F.lit(d)) for d, x in enumerate(lift)), F.lit(max(1.0, floor)))


def _rate(lift: list[float], floor: float) -> Column:
    return F.greatest(F.lit(floor), _raised(lift, floor))


#: Weights of the rates' distance from 1 beside the targets, from the first to the last that is tried.
_EASE = [10.0**-e for e in range(2, 10)]
#: Newton rounds for a weight; halved steps in a round.
_ROUNDS, _HALVES = 60, 20


def fit_rates(members: DataFrame, targets: list[float], config: MixConfig) -> tuple[list[float], float]:
    """What each domain adds to the rates of (n_tokens, p) to meet target shares, and the distance left from the targets.

    Tokens are counted in shares of the corpus, which targets keep at its size unless config.grow. For a weight e, the lift x minimises
    the convex dual, the sum of n_i psi(1 + x p_i) - goal x + e/2 x D x, where psi' is the projection onto the floor and D the
    domains' shares; then the residual is e D x, so that it goes to 0 with e if rates can meet the targets. Where it no
    longer falls with e they can't, and the last weight that helped stands, as smaller ones only move the rates further.
    """
    k = len(targets)
    p = [F.get("p", F.lit(d)) for d in range(k)]
    pairs = [(a, b) for a in range(k) for b in range(a, k)]
    head = members.agg(F.sum("n_tokens").cast("double").alias("n"), *[F.sum(F.col("n_tokens") * p[d]).alias(f"d{d}") for d in range(k)]).first()
    if not head["n"]:
        return [0.0] * k, 0.0
    own = np.array([head[f"d{d}"] / head["n"] for d in range(k)])
    goal = np.where(own > 0, targets, 0.0)
    goal = goal / (goal.sum() or 1.0)
    if config.grow:
        goal = goal * max((s / g for s, g in zip(own, goal, strict=True) if g > 0), default=1.0)
    metric = np.maximum(own, 1e-12)
    low = F.lit(config.floor)

    def at(x: np.ndarray) -> tuple[np.ndarray, np.ndarray, float]:
        """Residual, second derivatives and value of the dual without its last term."""
        u, n = F.col("u"), F.col("n_tokens")
        free = F.when(u >= low, n).otherwise(0)
        psi = F.when(u >= low, u * u / 2).otherwise(low * u - low * low / 2)
        sums = [F.sum(n * F.greatest(low, u) * p[d]).alias(f"d{d}") for d in range(k)]
        row = members.withColumn("u", _raised(x.tolist(), config.floor)).agg(F.sum(n * psi).alias("psi"), *sums, *[F.sum(free * p[a] * p[b]).alias(f"m{a}_{b}") for a, b in pairs]).first()
        second = np.array([[row[f"m{min(a, b)}_{max(a, b)}"] for b in range(k)] for a in range(k)]) / head["n"]
        return goal - np.array([row[f"d{d}"] for d in range(k)]) / head["n"], second, row["psi"] / head["n"] - float(goal @ x)

    x = np.zeros(k)
    residual, second, value = at(x)
    stands = (x.tolist(), float(np.linalg.norm(residual)))
    if stands[1] < config.tolerance:
        return stands
    for ease in _EASE:
        for _ in range(_ROUNDS):
            slope = residual - ease * metric * x
            # near enough to this weight's minimum for the next one
            if np.linalg.norm(slope) < 0.1 * np.linalg.norm(residual):
                break
            step = np.linalg.solve(second + ease * np.diag(metric), slope)
            now, share = value + ease / 2 * float(metric @ x**2), 1.0
            for _ in range(_HALVES):
                there = x + share * step
                residual, second, value = at(there)
                if np.linalg.norm(residual) < config.tolerance:
                    return there.tolist(), float(np.linalg.norm(residual))
                if value + ease / 2 * float(metric @ there**2) <= now - 1e-4 * share * float(slope @ step):
                    break
                share /= 2
            x = there
        left = float(np.linalg.norm(residual))
        if ease < 1e-4 and left > 0.99 * stands[1]:
            break
        stands = (x.tolist(), left)
    LOG.warning("rates miss the targets by %.2e of the corpus's tokens; the tolerance is %.0e", stands[1], config.tolerance)
    return stands


def domains_of(labels: DataFrame) -> DataFrame:
    """(doc_id, domain) of the labelled table."""
    return labels.where("quality is not null and toxic is not null").select("doc_id", F.concat_ws("_", F.concat(F.lit("q"), F.col("quality")), F.concat(F.lit("t"), F.col("toxic"))).alias("domain"))


def tempered(shares: list[float], power: float) -> list[float]:
    """Target shares between the natural ones (power 1) and equal ones (power 0)."""
    raised = [s**power if s > 0 else 0.0 for s in shares]
    return [r / (sum(raised) or 1.0) for r in raised]


def mix(docs: DataFrame, labels: DataFrame, targets: dict[str, float] | None = None, power: float = 0.7, emphasis: dict[str, float] | None = None, config: MixConfig = MixConfig()) -> tuple[DataFrame, DomainModel, dict[str, float]]:
    """All columns of docs but text, with n_tokens, p and rate; the classifier; the target shares.

    Without targets, they are the documents' expected shares raised to `power`, times `emphasis` where it names a domain. docs needs a doc_id and a text.
    """
    model = fit_domains(docs, domains_of(labels), config)
    members = materialize(posteriors(features(docs, config), model, config).drop("text"), "members")
    k = len(model.domains)
    if targets is None:
        row = members.agg(*[F.sum(F.col("n_tokens") * F.get("p", F.lit(d))).alias(f"d{d}") for d in range(k)]).first()
        sums = [row[f"d{d}"] or 0.0 for d in range(k)]
        wanted = [t * (emphasis or {}).get(d, 1.0) for t, d in zip(tempered([s / (sum(sums) or 1.0) for s in sums], power), model.domains, strict=True)]
    else:
        wanted = [targets.get(d, 0.0) for d in model.domains]
    lift, _ = fit_rates(members, wanted, config)
    return members.withColumn("rate", _rate(lift, config.floor)), model, dict(zip(model.domains, wanted, strict=True))


def copies(rate: Column, doc_id: Column) -> Column:
    """How often a document is read: its rate, rounded up or down by a hash of its id, so that totals keep in expectation."""
    chance = F.pmod(F.xxhash64(doc_id, F.lit(17)), F.lit(1_000_000)) / F.lit(1_000_000.0)
    return (F.floor(rate) + F.when(chance < rate - F.floor(rate), 1).otherwise(0)).cast("int")
