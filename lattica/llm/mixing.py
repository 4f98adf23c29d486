"""Mixing documents to target domain weights, with DataFrame functions only.

A naive Bayes classifier over hashed words, learned from a labelled table, gives
every document soft memberships in the domains. Nonnegative document rates are then
fitted so that the expected token total of each domain (rate x tokens x membership,
summed over documents) matches its target share of the token budget: projected
gradient steps on least squares, whitened by the domains' second moments so that few
steps suffice. A step is one aggregate of as many sums as there are domains; rates are
recomputed from the steps' multipliers and written every few steps.

The classifier is fitted on at most ``sample`` labelled rows (the smallest hashes of
doc_id) and has ``BUCKETS`` word buckets; everything else covers all documents.

Defined results: texts without words have no tokens, the prior memberships and rate 1;
memberships and rates depend on the text alone, so equal texts get equal rates; a
domain that no document belongs to misses its target and the others still meet theirs;
without labels every document has rate 1 and no memberships; documents with several
labels count once for each; all columns of the documents pass through (but for n_tokens,
memberships, rate and repeats, which are replaced).
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialize, release, table

BUCKETS = 1 << 14
#: Word count to which the evidence of longer texts is scaled down, so that memberships stay soft.
EVIDENCE = 40.0
TARGETS = {"good": 0.85, "junk": 0.14, "toxic": 0.01}


def word_rows(docs: DataFrame, keep: str) -> DataFrame:
    """One row per word: the kept column and the word's bucket."""
    return docs.select(keep, F.explode(F.split(F.lower("text"), r"\s+")).alias("w")).where("w <> ''").select(keep, F.pmod(F.xxhash64("w"), F.lit(BUCKETS)).cast("int").alias("bucket"))


def domains_of(labels: DataFrame) -> DataFrame:
    """(doc_id, domain) of the labelled table: toxic, else good or junk by quality."""
    name = F.when(F.col("toxic") == 1, "toxic").when(F.col("quality") == 1, "good").when(F.col("quality") == 0, "junk")
    return labels.select("doc_id", name.alias("domain")).where("domain is not null and doc_id is not null").distinct()


def fit(docs: DataFrame, labelled: DataFrame, sample: int = 10_000, smooth: float = 0.5):
    """(domains, priors, model): model has a row (bucket, l_0 ... l_k) for every seen bucket."""
    marks = labelled.orderBy(F.xxhash64("doc_id"), "doc_id", "domain").limit(sample)
    rows = docs.select("doc_id", "text").join(F.broadcast(marks), "doc_id")  # at most `sample` short rows
    counts = materialize(word_rows(rows, "domain").groupBy("bucket", "domain").count(), "mix-counts")
    sizes = {r.domain: r.n for r in marks.groupBy("domain").agg(F.count("*").alias("n")).collect()}
    names = sorted(sizes)
    totals = {r.domain: r.n for r in counts.groupBy("domain").agg(F.sum("count").alias("n")).collect()}
    priors = [sizes[d] / sum(sizes.values()) for d in names]
    logs = [F.ln((F.coalesce(F.sum(F.when(F.col("domain") == d, F.col("count"))), F.lit(0)) + smooth) / F.lit(totals.get(d, 0) + smooth * BUCKETS)).alias(f"l_{i}") for i, d in enumerate(names)]
    model = materialize(counts.groupBy("bucket").agg(*logs), "mix-model") if names else None
    release(counts)
    return names, priors, totals, model


def memberships(docs: DataFrame, fitted, smooth: float = 0.5) -> DataFrame:
    """(key, n_rows, n_tokens, p_0 ... p_k) of every distinct text with words; key is xxhash64 of the text."""
    names, priors, totals, model = fitted
    k = len(names)
    unseen = [float(np.log(smooth / (totals.get(d, 0) + smooth * BUCKETS))) for d in names]
    words = word_rows(docs.select(F.xxhash64("text").alias("key"), "text"), "key")
    seen = words.join(F.broadcast(model), "bucket", "left")  # at most BUCKETS rows
    sums = seen.groupBy("key").agg(F.count("*").alias("all_tokens"), *[F.sum(F.coalesce(f"l_{i}", F.lit(unseen[i]))).alias(f"s_{i}") for i in range(k)])
    rows = docs.groupBy(F.xxhash64("text").alias("key")).agg(F.count("*").alias("n_rows"))
    both = sums.join(rows, "key")
    logit = [F.col(f"s_{i}") / F.greatest(F.lit(1.0), F.col("all_tokens") / F.col("n_rows") / EVIDENCE) / F.col("n_rows") + F.lit(float(np.log(priors[i]))) for i in range(k)]
    both = both.select("key", "n_rows", (F.col("all_tokens") / F.col("n_rows")).cast("long").alias("n_tokens"), *[x.alias(f"z_{i}") for i, x in enumerate(logit)])
    top = F.greatest(*[F.col(f"z_{i}") for i in range(k)]) if k > 1 else F.col("z_0")
    both = both.withColumns({f"e_{i}": F.exp(F.col(f"z_{i}") - top) for i in range(k)})
    total = sum((F.col(f"e_{i}") for i in range(1, k)), F.col("e_0"))
    return both.select("key", "n_rows", "n_tokens", *[(F.col(f"e_{i}") / total).alias(f"p_{i}") for i in range(k)])


def fit_rates(members: DataFrame, shares: list[float], budget: float | None = None, steps: int = 64, tolerance: float = 1e-7, keep_every: int = 8):
    """(frame with rate, totals, targets, steps taken) for rows (n_rows, n_tokens, p_0 ...) and the domains' target shares."""
    k = len(shares)
    mass = F.col("n_rows") * F.col("n_tokens")
    moments = members.agg(F.sum(mass).alias("all"), *[F.sum(mass * F.col(f"p_{i}") * F.col(f"p_{j}")).alias(f"m_{i}_{j}") for i in range(k) for j in range(i, k)]).first()
    everything = float(moments["all"] or 0)
    target = np.array(shares, float) * (budget if budget is not None else everything)
    second = np.array([[moments[f"m_{min(i, j)}_{max(i, j)}"] or 0.0 for j in range(k)] for i in range(k)], float)
    white = np.linalg.inv(second + np.eye(k) * max(1e-9 * np.trace(second), 1e-12))
    state, pending, totals, done = members.withColumn("rate", F.lit(1.0)), [], None, 0
    written = None
    while True:
        totals = np.array([x or 0.0 for x in stepped(state, pending, k).agg(*[F.sum(mass * F.col("rate") * F.col(f"p_{i}")) for i in range(k)]).first()])
        gap = totals - target
        if done >= steps or everything == 0 or np.abs(gap).max() <= tolerance * max(1.0, target.sum()):
            break
        pending.append([float(x) for x in white @ gap])
        done += 1
        if len(pending) == keep_every:
            fresh = materialize(stepped(state, pending, k), "mix-rates")
            release(*[written] if written is not None else [])
            state, written, pending = fresh, fresh, []
    return stepped(state, pending, k), totals, target, done


def stepped(state: DataFrame, pending: list, k: int) -> DataFrame:
    """The state after the pending steps: each moves every rate against its gradient and back to zero if below."""
    for u in pending:
        slope = sum((F.col(f"p_{i}") * F.lit(u[i]) for i in range(1, k)), F.col("p_0") * F.lit(u[0]))
        state = state.withColumn("rate", F.greatest(F.lit(0.0), F.col("rate") - slope))
    return state


def mix(docs: DataFrame, labelled: DataFrame, targets: dict[str, float] | None = None) -> DataFrame:
    """The documents with n_tokens, one membership p_<domain> each, rate, and repeats (rate rounded by a hash of the row)."""
    targets = TARGETS if targets is None else targets
    fitted = fit(docs, labelled)
    names = fitted[0]
    own = docs.drop("n_tokens", "rate", "repeats", *[f"p_{d}" for d in names])
    if not names:
        return own.withColumns({"n_tokens": F.size(F.filter(F.split(F.lower(F.coalesce("text", F.lit(""))), r"\s+"), lambda w: w != "")).cast("long"), "rate": F.lit(1.0), "repeats": F.lit(1).cast("long")})
    members = materialize(memberships(docs, fitted), "mix-members")
    shares = np.array([targets.get(d, 0.0) for d in names], float)
    rated, _, _, _ = fit_rates(members, list(shares / (shares.sum() or 1.0)))
    found = materialize(rated.select(F.col("key").alias("__key"), "n_tokens", *[F.col(f"p_{i}").alias(f"p_{d}") for i, d in enumerate(names)], F.round("rate", 9).alias("rate")), "mix-found")
    release(members)
    out = own.withColumn("__key", F.xxhash64("text")).join(found, "__key", "left")
    prior = {f"p_{d}": F.coalesce(f"p_{d}", F.lit(p)) for d, p in zip(names, fitted[1], strict=True)}
    out = out.withColumns({"n_tokens": F.coalesce("n_tokens", F.lit(0).cast("long")), "rate": F.coalesce("rate", F.lit(1.0)), **prior})
    unit = F.pmod(F.xxhash64("doc_id", "__key"), F.lit(1 << 30)) / float(1 << 30)
    return out.withColumn("repeats", F.floor(F.col("rate") + unit).cast("long")).drop("__key")


def op1_mixing(spark, sf_dir) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "text")
    return mix(docs, domains_of(table(spark, sf_dir, "labels", "doc_id", "quality", "toxic"))).drop("text")
