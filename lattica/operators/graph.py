"""Weighted graphs as DataFrames, their preparation, objectives and measures of a clustering."""

from __future__ import annotations

from dataclasses import dataclass, replace
from fractions import Fraction

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources import drop, settle

LIMIT = 2**62


@dataclass(frozen=True)
class WGraph:
    """vertices (id, vw[, b]) and edges (src, dst, w) in both directions; lambda = num / den.

    wide: scores can pass 2^62, so they are computed as DECIMAL(38,0).
    """

    vertices: DataFrame
    edges: DataFrame
    num: int
    den: int
    wide: bool = False
    stored: int = -1

    def long(self, col):
        return col.cast("decimal(38,0)") if self.wide else col


def symmetrize(pairs: DataFrame, weighted: bool = False) -> DataFrame:
    """Edges in both directions, one row per ordered pair, without loops; weight 1, or the pair's multiplicity."""
    p = pairs.select(F.least("a", "b").cast("long").alias("a"), F.greatest("a", "b").cast("long").alias("b")).where("a <> b")
    p = p.groupBy("a", "b").agg(F.count("*").alias("w")) if weighted else p.distinct().withColumn("w", F.lit(1).cast("long"))
    ends = F.explode(F.array(F.struct(F.col("a").alias("src"), F.col("b").alias("dst")), F.struct(F.col("b").alias("src"), F.col("a").alias("dst"))))
    return p.select(ends.alias("e"), "w").select("e.src", "e.dst", "w")


def components(edges: DataFrame) -> DataFrame:
    """(id, comp): the smallest vertex that each vertex is connected to (least neighbour, then label of label)."""
    edges = edges.select("src", "dst")
    state = settle(edges.groupBy("src").agg(F.min("dst").alias("m")).select(F.col("src").alias("id"), F.least("src", "m").alias("comp")), "cc")
    while True:
        near = edges.join(state.select(F.col("id").alias("dst"), "comp"), "dst").groupBy("src").agg(F.min("comp").alias("m"))
        lower = settle(state.join(near, state.id == near.src).select("id", "comp", F.least("comp", "m").alias("next")), "cc")
        far = lower.select(F.col("id").alias("next"), F.col("next").alias("far"))
        new = settle(lower.join(far, "next").select("id", F.col("far").alias("comp"), (F.col("far") < F.col("comp")).alias("moved")), "cc")
        ended = new.where("moved").isEmpty()
        drop(state, lower)
        state = new.drop("moved")
        state._scratch = new._scratch
        if ended:
            return state


def largest_component(edges: DataFrame) -> DataFrame:
    """The edges of the component with most vertices (the smallest vertex decides between equals)."""
    comp = components(edges)
    best = comp.groupBy("comp").agg(F.count("*").alias("n")).agg(F.max(F.struct("n", (-F.col("comp")).alias("c"))).alias("t")).first()
    if best.t is None:
        return edges
    return edges.join(comp.where(F.col("comp") == -best.t.c).select(F.col("id").alias("src")), "src", "left_semi")


def profile(edges: DataFrame) -> DataFrame:
    """One row: n, m, max_degree and skew (largest over mean degree)."""
    degree = edges.groupBy("src").agg(F.count("*").alias("d"))
    return degree.agg(F.count("*").alias("n"), (F.sum("d") / 2).cast("long").alias("m"), F.max("d").alias("max_degree"), (F.max("d") / F.avg("d")).alias("skew"))


def degree_buckets(edges: DataFrame, low: int = 8, high: int = 256) -> DataFrame:
    """(id, degree, bucket): low, medium and high degree."""
    d = edges.groupBy(F.col("src").alias("id")).agg(F.count("*").alias("degree"))
    return d.withColumn("bucket", F.when(F.col("degree") < low, "low").when(F.col("degree") < high, "medium").otherwise("high"))


def encode_ids(pairs: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(pairs with dense numbers, map name -> id) for pairs (a, b) of any orderable type."""
    from ..sources.views import _number

    names = settle(_number(pairs.select(F.col("a").alias("name")).unionByName(pairs.select(F.col("b").alias("name")))), "ids")
    left = pairs.join(names.select(F.col("name").alias("a"), F.col("id").alias("x")), "a")
    return left.join(names.select(F.col("name").alias("b"), F.col("id").alias("y")), "b").select(F.col("x").alias("a"), F.col("y").alias("b")), names


def _sums(edges: DataFrame) -> tuple[int, int]:
    """(sum of the weights, number) of the stored edges."""
    e = edges.agg(F.sum(F.col("w").cast("decimal(38,0)")).alias("t"), F.count("*").alias("n")).first()
    return int(e.t or 0), e.n


def _is_wide(edge_weight: int, vertex_weight: int, lam: Fraction) -> bool:
    return 20 * (lam.denominator * edge_weight + lam.numerator * vertex_weight**2) >= LIMIT


def _graph(edges, vertices, lam: Fraction) -> WGraph:
    v = vertices.agg(F.sum(F.col("vw").cast("decimal(38,0)")).alias("t")).first().t or 0
    total, stored = _sums(edges)
    return WGraph(vertices, edges, lam.numerator, lam.denominator, _is_wide(total, int(v), lam), stored)


def modularity_graph(edges: DataFrame, gamma=1) -> WGraph:
    """Vertex weight = degree, lambda = gamma / (sum of degrees). The weights of the vertices are those of the edges: these are read once."""
    per = edges.groupBy(F.col("src").alias("id"))
    vertices = per.agg(F.sum("w").alias("vw"))
    vertices._degrees = per.agg(F.sum("w").alias("vw"), F.count("*").alias("n"))
    total, stored = _sums(edges)
    lam = Fraction(gamma) / total if total else Fraction(0)
    return WGraph(vertices, edges, lam.numerator, lam.denominator, _is_wide(total, total, lam), stored)


def unit_graph(edges: DataFrame, lam) -> WGraph:
    """Vertex weight 1: constant-Potts with resolution lam; label propagation at 0; components at a tiny lam."""
    return _graph(edges, edges.select(F.col("src").alias("id")).distinct().withColumn("vw", F.lit(1).cast("long")), Fraction(lam))


def absolute_potts_graph(edges: DataFrame, gamma) -> WGraph:
    """w'(u,v) = 1 on edges and -gamma off them: edge weight 1 + gamma against lambda gamma, scaled to integers."""
    g = Fraction(gamma)
    scaled = edges.select("src", "dst", (F.col("w") * g.denominator + g.numerator).alias("w"))
    return _graph(scaled, edges.select(F.col("src").alias("id")).distinct().withColumn("vw", F.lit(1).cast("long")), Fraction(g.numerator))


def label_propagation_graph(edges):
    return unit_graph(edges, 0)


def components_graph(edges, eps=Fraction(1, 10**9)):
    return unit_graph(edges, eps)


def sparsest_cut_graph(edges, lam):
    """lam is a candidate ratio cut(S) / (|S| |V - S|); the best two-way split is positive iff a sparser cut exists."""
    return unit_graph(edges, lam)


def cluster_deletion_graph(edges: DataFrame) -> WGraph:
    """lambda = 2m / (2m + 1) per unit pair: a missing edge costs almost as much as all edges gain, so clusters are cliques."""
    stored = edges.count()
    return unit_graph(edges, Fraction(stored, stored + 1))


def presets(edges: DataFrame) -> dict[str, WGraph]:
    return {"modularity": modularity_graph(edges), "modularity_2": modularity_graph(edges, 2), "constant_potts": unit_graph(edges, Fraction(1, 20)), "absolute_potts": absolute_potts_graph(edges, Fraction(1, 2)), "label_propagation": label_propagation_graph(edges), "components": components_graph(edges), "sparsest_cut": sparsest_cut_graph(edges, Fraction(1, 100)), "cluster_deletion": cluster_deletion_graph(edges)}


def singletons(g: WGraph) -> DataFrame:
    return g.vertices.select("id", F.col("id").alias("cid"))


def labelled(edges: DataFrame, c: DataFrame) -> DataFrame:
    """Edges with the clusters of both ends."""
    a = c.select(F.col("id").alias("src"), F.col("cid").alias("c_src"))
    b = c.select(F.col("id").alias("dst"), F.col("cid").alias("c_dst"))
    return edges.join(a, "src").join(b, "dst")


def lambda_cc(g: WGraph, c: DataFrame) -> DataFrame:
    """One row: scaled (den times the objective), value, modularity."""
    inside = labelled(g.edges, c).where("c_src = c_dst").agg(F.coalesce(F.sum(g.long(F.col("w"))), g.long(F.lit(0))).alias("inside"))
    per = c.join(g.vertices, "id").groupBy("cid").agg(F.sum(g.long(F.col("vw"))).alias("t"), F.sum(g.long(F.col("vw")) * g.long(F.col("vw"))).alias("sq"))
    sums = per.agg(F.coalesce(F.sum(F.col("t") * F.col("t")), g.long(F.lit(0))).alias("tt"), F.coalesce(F.sum("sq"), g.long(F.lit(0))).alias("sq"))
    stored = g.edges.agg(F.coalesce(F.sum("w"), F.lit(0)).alias("two_m"))
    scaled = F.lit(g.den) * F.col("inside") - F.lit(g.num) * (F.col("tt") - F.col("sq"))
    value = F.col("scaled").cast("double") / g.den
    q = (F.col("scaled") - F.lit(g.num) * F.col("sq")).cast("double") / (F.lit(float(g.den)) * F.col("two_m"))
    one = inside.crossJoin(sums).crossJoin(stored)  # three one-row aggregates
    return one.withColumn("scaled", scaled).select("scaled", value.alias("value"), F.when(F.col("two_m") > 0, q).otherwise(0.0).alias("modularity"))


def with_constraint(g: WGraph, b: DataFrame) -> WGraph:
    vertices = g.vertices.select("id", "vw").join(b.select("id", F.col("cid").alias("b")), "id")
    vertices._constrained = g.vertices, b
    return replace(g, vertices=vertices)
