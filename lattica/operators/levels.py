"""Contraction and the maps between levels."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..sources import settle
from .graph import WGraph, labelled


def contract(g: WGraph, c: DataFrame, gather: bool = False) -> WGraph:
    """The coarse graph of clusters (id, cid) labelled by their smallest vertex: summed weights, no loops.

    Every edge goes straight to its coarse edge and is summed before the exchange; with
    ``gather`` edges are first brought together by their coarse source (the slower variant).
    """
    rows = labelled(g.edges, c).where("c_src <> c_dst").select(F.col("c_src").alias("src"), F.col("c_dst").alias("dst"), "w")
    if gather:
        rows = rows.repartition("src")
    edges = rows.groupBy("src", "dst").agg(F.sum("w").alias("w"))
    keep = [F.min("b").alias("b")] if "b" in g.vertices.columns else []
    vertices = g.vertices.join(c, "id").groupBy(F.col("cid").alias("id")).agg(F.sum("vw").alias("vw"), *keep)
    edges = settle(edges, "edges")
    return replace(g, vertices=settle(vertices, "vertices"), edges=edges, stored=edges.count())


def contraction_bound(g: WGraph, c: DataFrame) -> DataFrame:
    """(cid, bound): the sum of member degrees, which bounds a coarse vertex's distinct neighbours."""
    d = g.edges.groupBy(F.col("src").alias("id")).agg(F.count("*").alias("d"))
    return c.join(d, "id", "left").groupBy("cid").agg(F.coalesce(F.sum("d"), F.lit(0)).alias("bound"))


def relabel_dense(c: DataFrame) -> DataFrame:
    """(id, cid) with clusters numbered from 0 in the order of their labels: counts per range, then offsets."""
    labels = settle(c.select("cid").distinct().repartitionByRange("cid").sortWithinPartitions("cid").withColumn("p", F.spark_partition_id()), "labels")
    local = labels.withColumn("i", F.row_number().over(W.partitionBy("p").orderBy("cid")))
    sizes = labels.groupBy("p").agg(F.count("*").alias("n"))
    offset = sizes.select("p", F.coalesce(F.sum("n").over(W.orderBy("p").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)).alias("o"))  # one row per partition
    dense = local.join(offset, "p").select("cid", (F.col("i") + F.col("o") - 1).cast("long").alias("dense"))
    return c.join(dense, "cid").select("id", F.col("dense").alias("cid"))


def project(level_map: DataFrame, coarse: DataFrame) -> DataFrame:
    """The coarse clustering on the finer vertices; level_map is (id, cid) with cid the coarse vertex."""
    up = coarse.select(F.col("id").alias("up"), F.col("cid").alias("c"))
    return level_map.join(up, level_map.cid == up.up).select("id", F.col("c").alias("cid"))


def downsample(level_map: DataFrame, c: DataFrame) -> DataFrame:
    """The fine clustering on coarse vertices; all members of a coarse vertex share theirs."""
    return level_map.withColumnRenamed("cid", "up").join(c, "id").groupBy(F.col("up").alias("id")).agg(F.min("cid").alias("cid"))


def level_constant(g: WGraph, c: DataFrame) -> DataFrame:
    """One row: den times (fine objective - coarse objective), the constant that stands in for coarse self-loops."""
    inside = labelled(g.edges, c).where("c_src = c_dst").agg(F.coalesce(F.sum("w"), F.lit(0)).alias("inside"))
    per = c.join(g.vertices, "id").groupBy("cid").agg(F.sum(g.long(F.col("vw"))).alias("t"), F.sum(g.long(F.col("vw")) * g.long(F.col("vw"))).alias("sq"))
    weights = per.agg(F.sum(F.col("t") * F.col("t") - F.col("sq")).alias("pairs"))
    return inside.crossJoin(weights).select((F.lit(g.den) * F.col("inside") - F.lit(g.num) * F.col("pairs")).alias("constant"))


def fine_objective(coarse_scaled: int, constants: list[int]) -> int:
    """den times the objective on the input graph: the coarse one and the constants of the levels between."""
    return coarse_scaled + sum(constants)
