"""Mixing sources to target weights by soft membership.

A Gaussian classifier, fitted by one aggregate over the labelled rows, gives each document a posterior over domains.
Document rates r >= 0 are then fitted by projected gradient least squares, so that the expected tokens of each domain
sum of r * tokens * posterior meet the targets. The gradient needs one sum for each domain, so an iteration is one
aggregate over all documents and sends as many numbers to the driver as there are domains. Built-in functions only.
"""

from __future__ import annotations

import math
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import let, materialise, table
from .op5_quality_rules import word_list

FEATURES = ("upper", "digit", "mark", "symbol", "wide", "repeat", "length")
TARGETS = {"clean": 0.80, "noisy": 0.15, "harsh": 0.05}
#: At most so many domains: the classifier's parameters and the gradient are held by the driver.
MAX_DOMAINS = 64


def domain_of_labels() -> Column:
    """The domain of a labelled row of `labels`: harsh where toxic, else clean or noisy by quality; null if unknown."""
    return F.when(F.col("toxic") == 1, "harsh").when(F.col("quality") == 1, "clean").when(F.col("quality") == 0, "noisy")


def shape_features(docs: DataFrame) -> DataFrame:
    """doc_id, row (one number for each row), tokens (words), and the logs of shape figures x: array<double>."""
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    share = lambda n, of: F.log(n / F.greatest(of, F.lit(1)) + 0.002)
    chars = F.char_length("text")
    counted = docs.select("doc_id", text.alias("text")).select(
        "doc_id",
        F.expr("uuid()").alias("row"),
        let(word_list(F.col("text")), lambda w: F.struct(F.size(w).cast("long").alias("n"), F.size(F.array_distinct(w)).alias("d"))).alias("w"),
        chars.alias("chars"),
        (F.octet_length("text") - chars).alias("wide"),
        *[F.regexp_count("text", F.lit(p)).alias(n) for n, p in (("upper", "[A-Z]"), ("digit", "[0-9]"), ("mark", "[.,;:!?'\"()-]"), ("symbol", "[#*$%&|<>]"))],
    )
    n = F.col("w.n")
    x = [share(F.col(c), F.col("chars")) for c in ("upper", "digit", "mark", "symbol", "wide")] + [share(n - F.col("w.d"), n), F.log1p(n.cast("double"))]
    return counted.select("doc_id", "row", n.alias("tokens"), F.array(*x).alias("x"))


def fit_domains(features: DataFrame, labelled: DataFrame) -> dict[str, tuple[float, list[float], list[float]]]:
    """Log prior, means and variances of each domain. labelled: doc_id, domain."""
    size = len(FEATURES)
    cell = lambda i: F.get("x", F.lit(i))
    stats = (
        features.join(labelled.where("domain IS NOT NULL"), "doc_id")
        .groupBy("domain")
        .agg(F.count("*").alias("n"), *[F.avg(cell(i)).alias(f"m{i}") for i in range(size)], *[F.var_pop(cell(i)).alias(f"v{i}") for i in range(size)])
        .limit(MAX_DOMAINS + 1)
        .collect()
    )
    if len(stats) > MAX_DOMAINS:
        raise ValueError(f"more than {MAX_DOMAINS} domains")
    total = sum(r["n"] for r in stats)
    return {r["domain"]: (math.log(r["n"] / total), [r[f"m{i}"] for i in range(size)], [r[f"v{i}"] + 0.01 for i in range(size)]) for r in sorted(stats, key=lambda r: r["domain"])}


def posteriors(features: DataFrame, model: dict, temperature: float = float(len(FEATURES))) -> DataFrame:
    """Adds p: array<double>, one posterior for each domain of the model in its order.

    The features are not independent: their log likelihood is divided by `temperature`, so memberships stay soft.
    """
    logs = []
    for prior, mean, var in model.values():
        terms = [(F.get("x", F.lit(i)) - m) * (F.get("x", F.lit(i)) - m) / (2 * v) + 0.5 * math.log(v) for i, (m, v) in enumerate(zip(mean, var))]
        logs.append(F.lit(prior) - sum(terms[1:], terms[0]) / temperature)
    scored = features.withColumn("l", F.array(*logs))
    weights = let(F.array_max("l"), lambda top: F.transform("l", lambda v: F.exp(v - top)))
    p = let(weights, lambda e: let(F.aggregate(e, F.lit(0.0), lambda a, v: a + v), lambda t: F.transform(e, lambda v: v / t)))
    return scored.withColumn("p", p).drop("l", "x")


def fit_rates(
    members: DataFrame, domains: list[str], targets: dict[str, float], total: float | None = None, low: float = 0.0, high: float = 8.0, rounds: int = 40, tolerance: float = 1e-5
) -> tuple[DataFrame, float]:
    """Adds rate in [low, high]; also the residual: by how much a domain's share misses its target at most.

    members: tokens, p. targets: weights of the domains; total: expected tokens in all, by default the present ones.
    Where the bounds keep the targets out of reach, the fit is the nearest by squared error.

    Each domain's error is divided by its share of the tokens: the scaled Gram matrix then has no eigenvalue above 1,
    and a step of 1 descends. total: by default the present number of tokens.
    """
    n = len(domains)
    sums = lambda df, rate: list(df.agg(*[F.sum(rate * F.col("tokens") * F.get("p", F.lit(k))).alias(f"s{k}") for k in range(n)]).first())
    state = members.withColumn("rate", F.lit(min(max(1.0, low), high)))
    now = [v or 0.0 for v in sums(state, F.lit(1.0))]
    size = sum(now)
    if size <= 0:
        return state, 0.0
    share = [max(v / size, 1e-9) for v in now]
    weight = sum(targets.get(d, 0.0) for d in domains)
    aims = [targets.get(d, 0.0) / weight * (total or size) / size for d in domains] if weight else share
    rate, had = F.col("rate"), sums(state, F.col("rate"))
    for step in range(1, rounds + 1):
        error = [(v or 0.0) / size - a for v, a in zip(had, aims)]
        if max(map(abs, error)) < tolerance:
            break
        slope = sum((F.get("p", F.lit(k)) * F.lit(e / s) for k, (e, s) in enumerate(zip(error, share))), F.lit(0.0))
        rate = F.least(F.greatest(rate - slope, F.lit(low)), F.lit(high))
        if step % 6 == 0:
            state = materialise(state.withColumn("rate", rate))
            rate = F.col("rate")
        had = sums(state, rate)
    got = sum(v or 0.0 for v in had)
    residual = max(abs((v or 0.0) / got - a / sum(aims)) for v, a in zip(had, aims)) if got > 0 else 0.0
    return state.withColumn("rate", rate), residual


def mix_sources(
    docs: DataFrame, labelled: DataFrame, targets: dict[str, float] | None = None, low: float = 0.0, high: float = 8.0, grow: bool = False, rounds: int = 40
) -> DataFrame:
    """doc_id, row, tokens, p_<domain> for each domain, rate, copies, residual; one row for each row of docs.

    labelled: doc_id, domain. copies is the rate's whole part, and one more for a share of documents equal to the
    rest, chosen by the hash of doc_id. residual, the same in all rows, is the largest difference between a domain's
    share of the expected tokens and its target. grow: aim at so many tokens that no domain must shrink. Texts without
    words have no tokens; their rate moves like the others'. Without labelled rows there is one domain and every rate
    is 1. Labelled rows without a domain teach nothing.
    Repeated rows stay; an empty table gives no rows; other columns are ignored.
    """
    targets = targets or TARGETS
    features = materialise(shape_features(docs))
    model = fit_domains(features, labelled) or {"all": (0.0, [0.0] * len(FEATURES), [1.0] * len(FEATURES))}
    names = list(model)
    members = materialise(posteriors(features, model))
    total = None
    if grow:
        have = list(members.agg(*[F.sum(F.col("tokens") * F.get("p", F.lit(k))).alias(f"s{k}") for k in range(len(names))]).first())
        weight = sum(targets.get(d, 0.0) for d in names) or 1.0
        need = [(v or 0.0) * weight / targets[d] for v, d in zip(have, names) if targets.get(d)]
        total = max(need, default=None)
    rated, residual = fit_rates(members, names, targets, total, low, high, rounds)
    share = F.pmod(F.xxhash64("doc_id"), F.lit(1_000_000)) / 1e6
    rate = F.round("rate", 6)
    return rated.select(
        "doc_id",
        "row",
        "tokens",
        *[F.round(F.get("p", F.lit(k)), 6).alias(f"p_{d}") for k, d in enumerate(names)],
        rate.alias("rate"),
        (F.floor(rate) + F.when(share < rate - F.floor(rate), 1).otherwise(0)).cast("int").alias("copies"),
        F.lit(round(residual, 6)).alias("residual"),
    )


def apply_mix(docs: DataFrame, labelled: DataFrame, targets: dict[str, float] | None = None, low: float = 1.0, high: float = 4.0) -> DataFrame:
    """The rows of docs, with all their columns, as often as their fitted number of copies.

    The targets are aimed at within the present number of tokens. With `low` of 1 or more no document is dropped: a
    domain that is short of its weight is repeated, up to `high` times a document, and what the bounds leave open is
    the residual of mix_sources. Columns of any name stay as they are.
    """
    rated = mix_sources(docs, labelled, targets, low, high)
    key, times, again = (f"{n}_{uuid.uuid4().hex}" for n in ("key", "times", "again"))
    copies = rated.groupBy(F.col("doc_id").alias(key)).agg(F.max("copies").alias(times))
    joined = docs.join(copies.hint("merge"), docs["doc_id"].eqNullSafe(copies[key]), "left")
    n = F.coalesce(times, F.lit(1))
    repeat = F.explode(F.when(n > 0, F.sequence(F.lit(1), n)).otherwise(F.array().cast("array<int>")))
    return joined.withColumn(again, repeat).drop(key, times, again)


def op2_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rates of all documents for the target weights of the three domains of `labels`."""
    labelled = table(spark, sf_dir, "labels").select("doc_id", domain_of_labels().alias("domain"))
    return mix_sources(table(spark, sf_dir, "documents"), labelled).drop("row")
