"""Soft-membership mixing. DataFrame functions only.

A classifier fitted on the labels table gives every document a posterior over domains (clean, poor, toxic). Nonnegative
rates, one a document, are then fitted by projected least squares so that the expected tokens of each domain, rate x
tokens x posterior summed over documents, meet the targets. Every document's step is the same function of its
posterior, so a pass over the documents sums one residual per domain, the gradient is scaled by the damped inverse of
the domains' Gram matrix (a handful of numbers), and the rates are stepped and projected to zero or more where they
stand; no rate leaves its row. A step that does not lower the squared residual is taken again with more damping. Rates start from 1, so documents change no more than the targets ask.

The classifier is naive Bayes over the presence of hashed words and of style classes. It is fitted on at most
``sample`` labelled documents, those with the smallest hash of their id (documented parameter). Its table has a row
per telling bucket, at most 2**BITS, which bounds what is broadcast.

Null or empty text: no tokens, the posterior of such texts. Very long texts are read whole. Null labels are not used. Null ids
pass through. Repeated rows get equal rates. No labels: equal priors. A domain without documents cannot meet a
target; the others still do. Empty table: no rows. Other columns are not read by ``document_rates`` and pass through
``draw`` with their values, whatever their names; a kept column named as one of the result raises.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import LOWER, UPPER, materialise, table, unused

DOMAINS = ("clean", "poor", "toxic")
FEATURES = "features of the text"
BITS = 16
#: Marks that are dropped from words, white space that becomes a blank, and ASCII marks that plain prose does without.
MARKS, BLANKS = ".,;:?", "\t\n\x0b\x0c\r"
SYMBOLS = "!#$%&*+/<=>@[\\]^_`{|}~"


#: Documents that the share of a bucket in all domains counts for in each; a domain without documents says nothing.
SMOOTH = 1.0


def _share_class(count: Column, of: Column) -> Column:
    """0 none, then 1 to 4 by tenths of a thing a token."""
    share = count / F.greatest(of, F.lit(1))
    return F.when(count == 0, 0).when(share < 0.02, 1).when(share < 0.1, 2).when(share < 0.4, 3).otherwise(4)


def _words(text: Column) -> Column:
    return F.array_remove(F.split(F.translate(F.coalesce(text, F.lit("")), BLANKS + UPPER + MARKS, " " * len(BLANKS) + LOWER), " ", -1), "")


# Features are never empty; explode_outer keeps the optimizer from computing them once more in a filter on their size.


def with_features(docs: DataFrame, keep: list[str], text_col: str = "text") -> DataFrame:
    """``keep``, n_tokens, and the words and styles that are present."""
    if clash := {c.lower() for c in keep} & {"n_tokens", "rate", *(f"p{k}" for k in range(len(DOMAINS)))}:
        raise ValueError(f"kept columns clash with the result: {sorted(clash)}")
    _text, _list, _set = unused([*keep, "n_tokens", FEATURES], "text", "words", "set")
    d = docs.select(*keep, F.col(text_col).cast("string").alias(_text)).withColumn(_list, _words(F.col(_text))).withColumn("n_tokens", F.size(_list).cast("long")).withColumn(_set, F.array_distinct(_list))
    text, tokens = F.coalesce(_text, F.lit("")), F.greatest(F.col("n_tokens"), F.lit(1))
    style = [F.concat(F.lit(" symbols "), _share_class(F.length(text) - F.length(F.translate(text, SYMBOLS, "")), F.col("n_tokens")).cast("string"))]
    style.append(F.concat(F.lit(" distinct "), F.floor(10 * F.size(_set) / tokens).cast("string")))
    style.append(F.concat(F.lit(" capitals "), F.floor(10 * (F.length(text) - F.length(F.translate(text, UPPER, ""))) / F.greatest(F.length(text), F.lit(1))).cast("string")))
    style.append(F.concat(F.lit(" letters "), F.least(F.floor(F.length(text) / tokens), F.lit(20)).cast("string")))
    return d.select(*keep, "n_tokens", F.concat(_set, F.array(*style)).alias(FEATURES))


def _bucket(feature: Column) -> Column:
    return F.when(F.startswith(feature, F.lit(" ")), -F.abs(F.xxhash64(feature) % 1_000_003) - 1).otherwise(F.pmod(F.xxhash64(feature), F.lit(1 << BITS)))


def fit(docs: DataFrame, labels: DataFrame, sample: int = 12_000, id_col: str = "doc_id", text_col: str = "text", least: int = 5, telling: float = 1.0) -> tuple[DataFrame, list[float]]:
    """(bucket, w1, w2) with log odds against domain 0, and the log priors. ``labels`` has (id, domain int)."""
    spark = docs.sparkSession
    chosen = labels.select(F.col(id_col).alias("_id"), F.col("domain")).where("_id is not null and domain is not null").groupBy("_id").agg(F.max("domain").alias("domain")).orderBy(F.xxhash64("_id"), "_id").limit(sample)
    mine = docs.select(F.col(id_col).alias("_id"), F.col(text_col)).join(F.broadcast(chosen), "_id")
    seen = materialise(with_features(mine, ["domain"], text_col).select("domain", F.explode_outer(FEATURES).alias("f")).groupBy(_bucket(F.col("f")).alias("bucket"), "domain").agg(F.count("*").alias("n")), "buckets")
    sizes = {r[0]: r[1] for r in materialise(mine.groupBy("domain").agg(F.count("*").alias("n")), "domains").collect()}
    n = [sizes.get(k, 0) for k in range(len(DOMAINS))]
    total = sum(n) + len(n)
    priors = [float(np.log((x + 1) / total)) for x in n]
    by = seen.groupBy("bucket").agg(*[F.sum(F.when(F.col("domain") == k, F.col("n")).otherwise(0)).alias(f"n{k}") for k in range(len(DOMAINS))])
    by = by.withColumn("n", sum((F.col(f"n{k}") for k in range(1, len(DOMAINS))), F.col("n0")))
    log_p = [F.log((F.col(f"n{k}") + SMOOTH * F.col("n") / sum(n)) / (n[k] + SMOOTH)) for k in range(len(DOMAINS))]
    weights = by.select("bucket", *[(log_p[k] - log_p[0]).alias(f"w{k}") for k in range(1, len(DOMAINS))], "n")
    telling_now = F.greatest(*[F.abs(F.col(f"w{k}")) for k in range(1, len(DOMAINS))]) >= telling
    return materialise(weights.where((F.col("n") >= least) & telling_now).drop("n"), "weights"), priors


def posteriors(docs: DataFrame, weights: DataFrame, priors: list[float], keep: list[str], text_col: str = "text") -> DataFrame:
    """``keep``, n_tokens, p0, p1, ... One scan; the only exchange has a partial sum a document."""
    row, feature, bucket, *names = unused([*keep, "n_tokens", FEATURES], "row", "feature", "bucket", *[f"w{k}" for k in range(1, len(DOMAINS))])
    features = with_features(docs, keep, text_col).withColumn(row, F.monotonically_increasing_id())
    each = features.select(row, *keep, "n_tokens", F.explode_outer(FEATURES).alias(feature)).select(row, *keep, "n_tokens", _bucket(F.col(feature)).alias(bucket))
    by_bucket = weights.select(F.col("bucket").alias(bucket), *[F.col(f"w{k}").alias(w) for k, w in enumerate(names, 1)])
    sums = each.join(F.broadcast(by_bucket), bucket, "left").groupBy(row).agg(*[F.first(c).alias(c) for c in [*keep, "n_tokens"]], *[F.coalesce(F.sum(w), F.lit(0.0)).alias(w) for w in names])
    logit = [F.lit(priors[0]), *[F.lit(priors[k]) + F.greatest(F.lit(-60.0), F.least(F.lit(60.0), F.col(w))) for k, w in enumerate(names, 1)]]
    top = F.greatest(*logit)
    share = [F.exp(x - top) for x in logit]
    return sums.select(*keep, "n_tokens", *[(x / sum(share[1:], share[0])).alias(f"p{k}") for k, x in enumerate(share)])


def fit_rates(members: DataFrame, targets: list[float], most: int = 40, tolerance: float = 1e-9) -> tuple[Column, dict]:
    """Rate of each row of (n_tokens, p0, p1, ...) as a column, and what it attains.

    ``targets`` are tokens by domain. A pass returns one number a domain to the driver.
    """
    k = range(len(targets))
    p = [F.col(f"p{i}") for i in k]
    tokens = F.col("n_tokens").cast("double")
    total = members.agg(F.sum(tokens)).first()[0] or 0.0
    if not total:
        return F.lit(1.0), {"passes": 0, "attained": [0.0 for _ in k], "converged": not any(targets)}
    goal, n = np.array(targets, float) / total, len(targets)
    rate = best_rate = F.lit(1.0)
    best, attained, residual, gram, damping, passes = np.inf, np.zeros(n), np.zeros(n), np.eye(n), 1e-6, 0
    for passes in range(1, most + 1):
        # The rate is a column of its own, so that a pass has its expression once.
        rated = members.select("n_tokens", *[f"p{i}" for i in k], rate.alias("now"))
        active = F.when(F.col("now") > 0, 1.0).otherwise(0.0)
        got = rated.agg(*[F.sum(tokens * p[i] * F.col("now")) for i in k], *[F.sum(tokens * p[i] * p[j] * active) for i in k for j in k]).first()
        now = np.array(got[:n], float) / total
        value = float(((now - goal) ** 2).sum())
        if value < best:
            settled = value > 0.999999 * best
            best, best_rate, attained, residual, gram, damping = value, rate, now, now - goal, np.array(got[n:], float).reshape(n, n) / total, max(1e-9, damping / 10)
            if settled or np.abs(residual).max() <= tolerance:
                break
        else:  # a shorter step, closer to the plain gradient
            damping *= 10
            if damping > 1e4:
                break
        step = np.linalg.solve(gram + damping * np.eye(n), residual)
        rate = F.greatest(F.lit(0.0), best_rate - sum((p[i] * float(step[i]) for i in k[1:]), p[0] * float(step[0])))
    return best_rate, {"passes": passes, "attained": (attained * total).tolist(), "converged": bool(np.abs(residual).max() <= max(tolerance, 1e-6))}


def domain_labels(labels: DataFrame) -> DataFrame:
    return labels.select("doc_id", F.when(F.col("toxic") == 1, 2).when((F.col("toxic") == 0) & (F.col("quality") == 0), 1).when((F.col("toxic") == 0) & (F.col("quality") == 1), 0).alias("domain"))


def document_rates(docs: DataFrame, labels: DataFrame, weights: list[float], keep: list[str], learn_from: DataFrame | None = None) -> tuple[DataFrame, dict]:
    """``keep``, n_tokens, posteriors and rate. ``weights``: wanted share of tokens by domain.

    The classifier is fitted on labelled documents of ``learn_from`` (``docs`` by default).
    The budget keeps the expected tokens of domain 0 as they are; rates of a domain that has too little rise over 1.
    Also returns wanted and attained tokens and shares.
    """
    model, priors = fit(docs if learn_from is None else learn_from, labels)
    members = materialise(posteriors(docs, model, priors, keep), "members")
    k = range(len(weights))
    have = [x or 0.0 for x in members.agg(*[F.sum(F.col("n_tokens") * F.col(f"p{i}")) for i in k]).first()]
    targets = [have[0] * w / weights[0] for w in weights]
    rate, said = fit_rates(members, targets)
    shares = {name: [x / max(sum(by), 1e-300) for x in by] for name, by in (("wanted", targets), ("attained", said["attained"]), ("before", have))}
    return members.withColumn("rate", rate), said | {"targets": targets, "have": have, "shares": shares}


def draw(docs: DataFrame, rates: DataFrame, id_col: str = "doc_id", text_col: str = "text", seed: int = 11) -> DataFrame:
    """Rows of ``docs``, each as often as its rate: the whole part always, one more with the rest as probability.

    ``rates`` has (id, text_hash, rate); chance is a hash of the id, so a rerun draws alike.
    """
    key, of, hash_, rate, times, copy = unused(docs.columns, "key", "rate_of", "rate_hash", "rate", "times", "copy")
    by = rates.select(F.col(id_col).alias(of), F.col("text_hash").alias(hash_), F.col("rate").alias(rate)).dropDuplicates([of, hash_])
    keyed = docs.withColumn(key, F.xxhash64(text_col))
    chance = F.pmod(F.xxhash64(F.lit(seed), F.col(of), F.col(hash_)), F.lit(1 << 30)) / F.lit(float(1 << 30))
    drawn = keyed.join(by, keyed[id_col].eqNullSafe(by[of]) & (keyed[key] == by[hash_])).withColumn(times, F.floor(F.col(rate) + chance).cast("int"))
    return drawn.where(F.col(times) > 0).withColumn(copy, F.explode(F.sequence(F.lit(1), F.col(times)))).select(*[keyed[c] for c in docs.columns])


SHARES = [0.94, 0.04, 0.02]


def op4_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = table(spark, sf_dir, "documents").select("doc_id", "text"), domain_labels(table(spark, sf_dir, "labels"))
    rates, _ = document_rates(docs, labels, SHARES, ["doc_id"])
    return rates.select("doc_id", "n_tokens", *[F.col(f"p{k}").alias(f"p_{d}") for k, d in enumerate(DOMAINS)], "rate")


QUERIES = {"op4_mixing": op4_mixing}
ORACLES: dict[str, str] = {}
