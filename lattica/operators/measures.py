"""Measures over clusterings and over tables of runs."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def mean_modularity_delta(results: DataFrame, base: str, outlier: float = 0.2) -> DataFrame:
    """(variant, delta, graphs, excluded): mean of q minus the base variant's, without failed runs and outliers."""
    ok = results.where("status = 'ok'")
    b = ok.where(F.col("variant") == base).select("graph", F.col("q").alias("q0"))
    rows = ok.join(b, "graph").withColumn("d", F.col("q") - F.col("q0"))
    inside = F.abs("d") <= outlier
    return rows.groupBy("variant").agg(F.avg(F.when(inside, F.col("d"))).alias("delta"), F.count(F.when(inside, 1)).alias("graphs"), F.count(F.when(~inside, 1)).alias("excluded"))


def geomean_ratio(results: DataFrame, base: str) -> DataFrame:
    """(variant, ratio): geometric mean of seconds over the base variant's."""
    ok = results.where("status = 'ok' and seconds > 0")
    b = ok.where(F.col("variant") == base).select("graph", F.col("seconds").alias("s0"))
    return ok.join(b, "graph").groupBy("variant").agg(F.exp(F.avg(F.ln(F.col("seconds") / F.col("s0")))).alias("ratio"))


def repetition_summary(runs: DataFrame) -> DataFrame:
    """(graph, variant): median seconds and q over repetitions, and the standard deviation of q."""
    return runs.where("status = 'ok'").groupBy("graph", "variant").agg(F.percentile("seconds", F.lit(0.5)).alias("seconds"), F.percentile("q", F.lit(0.5)).alias("q"), F.stddev_samp("q").alias("q_stddev"), F.count("*").alias("runs"))


def wins(results: DataFrame, engine: str, reference: str) -> DataFrame:
    """One row: graphs where the engine reaches or beats the reference's q, of all."""
    a = results.where(F.col("variant") == engine).select("graph", F.col("q").alias("qa"))
    b = results.where(F.col("variant") == reference).select("graph", F.col("q").alias("qb"))
    return a.join(b, "graph").agg(F.count_if(F.col("qa") >= F.col("qb")).alias("wins"), F.count("*").alias("graphs"))


def ablation_cube(results: DataFrame) -> DataFrame:
    """Mean q and seconds by graph and variant, by each, and overall."""
    return results.cube("graph", "variant").agg(F.avg("q").alias("q"), F.avg("seconds").alias("seconds"))


def phase_report(seconds: dict[str, float]) -> dict[str, float]:
    """Each phase's share of a run's time."""
    total = sum(seconds.values()) or 1.0
    return {k: v / total for k, v in seconds.items()}


def pair_counts(a: DataFrame, b: DataFrame) -> DataFrame:
    """One row: n, pairs together in both, in a, in b (of clusterings (id, cid))."""
    both = a.select("id", F.col("cid").alias("x")).join(b.select("id", F.col("cid").alias("y")), "id")
    pairs = lambda *k: both.groupBy(*k).count().agg(F.coalesce(F.sum(F.col("count") * (F.col("count") - 1) / 2), F.lit(0.0)).alias("p"))
    one = pairs("x", "y").withColumnRenamed("p", "together").crossJoin(pairs("x").withColumnRenamed("p", "in_a")).crossJoin(pairs("y").withColumnRenamed("p", "in_b"))
    return one.crossJoin(both.agg(F.count("*").alias("n")))


def ari(a: DataFrame, b: DataFrame) -> DataFrame:
    """One row: the adjusted Rand index and its pair counts."""
    p = pair_counts(a, b)
    total = F.col("n") * (F.col("n") - 1) / 2
    expected = F.when(total > 0, F.col("in_a") * F.col("in_b") / total).otherwise(0.0)
    top = (F.col("in_a") + F.col("in_b")) / 2
    return p.select("n", "together", "in_a", "in_b", F.when(top == expected, 1.0).otherwise((F.col("together") - expected) / F.nullif(top - expected, F.lit(0.0))).alias("ari"))


def nmi(a: DataFrame, b: DataFrame) -> DataFrame:
    """One row: mutual information over the mean entropy."""
    both = a.select("id", F.col("cid").alias("x")).join(b.select("id", F.col("cid").alias("y")), "id")
    n = both.agg(F.count("*").alias("n"))
    joint = both.groupBy("x", "y").agg(F.count("*").alias("k"))
    px, py = (joint.groupBy(c).agg(F.sum("k").alias(f"k{c}")) for c in ("x", "y"))
    rows = joint.join(px, "x").join(py, "y").crossJoin(n)
    mi = rows.agg(F.sum(F.col("k") / F.col("n") * F.ln(F.col("k") * F.col("n") / (F.col("kx") * F.col("ky")))).alias("mi"))
    h = lambda p, c: p.crossJoin(n).agg((-F.sum(F.col(f"k{c}") / F.col("n") * F.ln(F.col(f"k{c}") / F.col("n")))).alias(f"h{c}"))
    one = mi.crossJoin(h(px, "x")).crossJoin(h(py, "y"))
    return one.select(F.when(F.col("hx") + F.col("hy") == 0, 1.0).otherwise(2 * F.col("mi") / F.nullif(F.col("hx") + F.col("hy"), F.lit(0.0))).alias("nmi"))
