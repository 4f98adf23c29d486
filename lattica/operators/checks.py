"""Checkers of the quality guarantees: empty results mean the property holds."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import kernel
from .graph import WGraph, components, labelled
from .moves import affinity, destinations, state_of


def violations_separation(g: WGraph, c: DataFrame) -> DataFrame:
    """(a, b, score): pairs of clusters that would gain by merging (only adjacent ones can)."""
    state = state_of(g, c)
    totals = state.where("id = cid").select("cid", F.col("tw").alias("t"))
    cut = labelled(g.edges, state).where("c_src < c_dst").groupBy(F.col("c_src").alias("a"), F.col("c_dst").alias("b")).agg(F.sum("w").alias("w"))
    rows = cut.join(totals.select(F.col("cid").alias("a"), F.col("t").alias("ta")), "a").join(totals.select(F.col("cid").alias("b"), F.col("t").alias("tb")), "b")
    return rows.select("a", "b", (g.long(F.col("w")) * g.den - g.long(F.col("ta")) * g.num * F.col("tb")).alias("score")).where("score > 0")


def violations_node(g: WGraph, c: DataFrame) -> DataFrame:
    """(id, s_own, s_best): vertices that gain by moving to a cluster or alone."""
    state = state_of(g, c)
    dest = destinations(g, state, affinity(g.edges, state))
    best = F.greatest(F.coalesce("s_new", F.lit(0)), F.lit(0))
    return dest.select("id", "s_own", best.alias("s_best")).where("s_best > s_own")


def disconnected_clusters(g: WGraph, c: DataFrame) -> DataFrame:
    """(cid, pieces) of the clusters that fall apart on their own edges."""
    state = state_of(g, c).select("id", "cid")
    inner = labelled(g.edges, state).where("c_src = c_dst").select("src", "dst")
    comp = components(inner) if not inner.isEmpty() else inner.select(F.col("src").alias("id"), F.col("dst").alias("comp"))
    rows = state.join(comp, "id", "left").select("cid", F.coalesce("comp", "id").alias("comp"))
    return rows.groupBy("cid").agg(F.countDistinct("comp").alias("pieces")).where("pieces > 1")


def _subsets(g: WGraph, c: DataFrame, most: int) -> DataFrame:
    """(cid, mask, wx, inx, own): every proper subset of each cluster of at most `most` members."""
    state = state_of(g, c)
    small = state.groupBy("cid").agg(F.sort_array(F.collect_list(F.struct("id", "vw"))).alias("m"), F.sum("vw").alias("w")).where(F.size("m").between(2, most))
    masks = small.select("cid", "m", "w", F.explode(F.expr("sequence(1, shiftleft(1, size(m)) - 2)")).alias("mask"))
    member = masks.select("cid", "mask", "w", F.posexplode("m").alias("i", "v")).select("cid", "mask", "w", "v.id", "v.vw", F.expr("(mask & shiftleft(1, i)) > 0").alias("x"))
    return member


def violations_uniform_small(g: WGraph, c: DataFrame, most: int = 8) -> DataFrame:
    """(cid, mask, score): subsets X of small clusters C with w'(X, C - X) < 0."""
    member = _subsets(g, c, most)
    weights = member.groupBy("cid", "mask").agg(F.sum(F.when(F.col("x"), F.col("vw")).otherwise(0)).alias("wx"), F.first("w").alias("w"))
    cut = g.edges.join(member.select(F.col("id").alias("src"), "cid", "mask", F.col("x").alias("xs")), "src").join(member.select(F.col("id").alias("dst"), "cid", "mask", F.col("x").alias("xd")), ["dst", "cid", "mask"]).where("xs and not xd").groupBy("cid", "mask").agg(F.sum("w").alias("cut"))
    score = F.coalesce("cut", F.lit(0)) * g.den - F.col("wx") * g.num * (F.col("w") - F.col("wx"))
    return weights.join(cut, ["cid", "mask"], "left").select("cid", F.col("mask").cast("long").alias("mask"), score.cast("long").alias("score")).where("score < 0")


def violations_subset_small(g: WGraph, c: DataFrame, most: int = 8) -> DataFrame:
    """(cid, mask, other, gain): subsets of small clusters that would gain by moving to an adjacent cluster."""
    member = _subsets(g, c, most)
    state = state_of(g, c)
    weights = member.groupBy("cid", "mask").agg(F.sum(F.when(F.col("x"), F.col("vw")).otherwise(0)).alias("wx"), F.first("w").alias("w"))
    ins = member.where("x").select(F.col("id").alias("src"), "cid", "mask")
    ends = g.edges.join(ins, "src").join(state.select(F.col("id").alias("dst"), F.col("cid").alias("other"), F.col("tw").alias("to")), "dst")
    inside = member.where("x").select(F.col("id").alias("dst"), "cid", "mask", F.lit(True).alias("both"))
    ends = ends.join(inside, ["dst", "cid", "mask"], "left").where("both is null")
    cut = ends.groupBy("cid", "mask", "other").agg(F.sum("w").alias("k"), F.first("to").alias("to"))
    own = cut.where("other = cid").select("cid", "mask", F.col("k").alias("ko"))
    rows = cut.where("other <> cid").join(weights, ["cid", "mask"]).join(own, ["cid", "mask"], "left")
    there = F.col("k") * g.den - F.col("wx") * g.num * F.col("to")
    here = F.coalesce("ko", F.lit(0)) * g.den - F.col("wx") * g.num * (F.col("w") - F.col("wx"))
    return rows.select("cid", F.col("mask").cast("long").alias("mask"), "other", (there - here).cast("long").alias("gain")).where("gain > 0")


def recorded_merges(record: list):
    """(level, cluster, joined vertex, score with the prefix, score of the prefix with the rest of its cluster) of a refined run.

    record holds (graph, constraint, refined, order) of each level; every sub-cluster was joined in that order.
    """
    np = kernel.np
    for level, (g, b, fine, order) in enumerate(record):
        wb, inside = kernel.totals(g, b), kernel.inside_weight(g, b)
        place = np.empty(g.n, np.int64)
        place[np.lexsort((np.arange(g.n), order))] = np.arange(g.n)
        e = np.flatnonzero((fine[g.src] == fine[g.dst]) & (place[g.src] < place[g.dst]))
        earlier = np.zeros(g.n, np.int64)
        np.add.at(earlier, g.dst[e], g.w[e])
        rows = np.lexsort((place, fine))
        weight = cut = 0
        for i, v in enumerate(rows.tolist()):
            if i == 0 or fine[v] != fine[rows[i - 1]]:
                weight, cut = int(g.vw[v]), int(inside[v])
                continue
            joined = g.den * int(earlier[v]) - g.num * int(g.vw[v]) * weight
            yield level, int(fine[v]), v, joined, g.den * cut - g.num * weight * (int(wb[b[v]]) - weight)
            weight += int(g.vw[v])
            cut += int(inside[v]) - 2 * int(earlier[v])


def certificate_connectivity(record: list) -> list[tuple]:
    """Recorded merges of two parts that lose by meeting: none where every cluster has a tree of harmless merges."""
    return [(level, "merge", c, v) for level, c, v, joined, _ in recorded_merges(record) if joined < 0]


def certificate_density(record: list) -> list[tuple]:
    """Tree nodes (prefixes, and the single vertices that join them) that would rather leave their cluster."""
    bad = [(level, "prefix", c, v) for level, c, v, _, rest in recorded_merges(record) if rest < 0]
    for level, (g, b, fine, _) in enumerate(record):
        wb, inside = kernel.totals(g, b), kernel.inside_weight(g, b)
        alone = g.den * inside - g.num * g.vw * (wb[b] - g.vw) < 0
        size = kernel.np.bincount(fine, minlength=g.n)
        bad += [(level, "vertex", int(fine[v]), int(v)) for v in kernel.np.flatnonzero(alone & (size[fine] > 1))]
    return bad


def certificate(small: kernel.Graph, record: list) -> list[tuple]:
    """All that a refined run recorded against the second and the third property."""
    return certificate_connectivity(record) + certificate_density(record)


def merge_scores(g: WGraph, b: DataFrame, rows: DataFrame, fine: DataFrame) -> DataFrame:
    """(id, cid, joined, rest): both scores of every recorded merge on DataFrames; rows are refine.prefixes, fine what was committed."""
    size = fine.groupBy("cid").agg(F.count("*").alias("size"))
    merges = fine.join(size.where("size > 1"), "cid").join(rows.where("pos > 1").select("id", "joined", "rest"), "id")
    return merges.select("id", "cid", F.col("joined").cast("long").alias("joined"), F.col("rest").cast("long").alias("rest"))


def constraint_floor(small: kernel.Graph, b) -> tuple[int, int]:
    """(objective of the sequential way down inside constraint b, objective of b): the first is never below the second."""
    return kernel.objective(small, kernel.sequential_way_down(small, b)), kernel.objective(small, b)
