"""Graph views over the given tables: distinct pairs (a, b), one row per undirected edge or more."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from . import read_table


def _width(n: int) -> int:
    """The largest divisor of n not above its square root."""
    return next(d for d in range(int(n**0.5), 0, -1) if n % d == 0)


def _grid(spark, sf_dir, steps) -> DataFrame:
    part = read_table(spark, sf_dir, "part", "p_partkey")
    n = part.count()
    w = _width(n)
    x, y = F.col("p_partkey") % w, F.floor(F.col("p_partkey") / w)
    ends = [F.when((x + dx < w) & (x + dx >= 0) & (y + dy < n // w), F.col("p_partkey") + dx + dy * w) for dx, dy in steps]
    return part.select(F.col("p_partkey").alias("a"), F.explode(F.array(*ends)).alias("b")).where("b is not null")


def lattice2d(spark, sf_dir) -> DataFrame:
    return _grid(spark, sf_dir, ((1, 0), (0, 1)))


def lattice8(spark, sf_dir) -> DataFrame:
    return _grid(spark, sf_dir, ((1, 0), (0, 1), (1, 1), (-1, 1)))


def ring_cliques(spark, sf_dir) -> DataFrame:
    """Blocks of ten part keys, fully joined; first key of each block to the first of the next."""
    part = read_table(spark, sf_dir, "part", "p_partkey")
    n = part.count()
    base = F.col("p_partkey") - F.col("p_partkey") % 10
    inner = part.select(F.col("p_partkey").alias("a"), F.explode(F.sequence(base, base + 9)).alias("b")).where(f"a < b and b < {n}")
    ring = part.where("p_partkey % 10 = 0").select(F.col("p_partkey").alias("a"), ((F.col("p_partkey") + 10) % n).alias("b"))
    return inner.unionByName(ring)


def part_cooc(spark, sf_dir) -> DataFrame:
    items = read_table(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey").distinct()
    other = items.select("l_orderkey", F.col("l_partkey").alias("b"))
    return items.withColumnRenamed("l_partkey", "a").join(other, "l_orderkey").where("a < b").select("a", "b")


def _sided(a, side):
    return (F.col(a) * 4 + side).cast("long")


def order_part(spark, sf_dir) -> DataFrame:
    return read_table(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey").select(_sided("l_orderkey", 0).alias("a"), _sided("l_partkey", 1).alias("b"))


def part_supp(spark, sf_dir) -> DataFrame:
    return read_table(spark, sf_dir, "lineitem", "l_partkey", "l_suppkey").select(_sided("l_partkey", 0).alias("a"), _sided("l_suppkey", 1).alias("b"))


def cust_part(spark, sf_dir) -> DataFrame:
    orders = read_table(spark, sf_dir, "orders", "o_orderkey", "o_custkey")
    items = read_table(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey")
    return orders.join(items, F.col("o_orderkey") == F.col("l_orderkey")).select(_sided("o_custkey", 0).alias("a"), _sided("l_partkey", 1).alias("b"))


def geo_tree(spark, sf_dir) -> DataFrame:
    nation = read_table(spark, sf_dir, "nation", "n_nationkey", "n_regionkey").select(_sided("n_regionkey", 0).alias("a"), _sided("n_nationkey", 1).alias("b"))
    customer = read_table(spark, sf_dir, "customer", "c_custkey", "c_nationkey").select(_sided("c_nationkey", 1).alias("a"), _sided("c_custkey", 2).alias("b"))
    orders = read_table(spark, sf_dir, "orders", "o_orderkey", "o_custkey").select(_sided("o_custkey", 2).alias("a"), _sided("o_orderkey", 3).alias("b"))
    return nation.unionByName(customer).unionByName(orders)


def _next(orders, by, order):
    return orders.select(F.col("o_orderkey").alias("a"), F.lead("o_orderkey").over(W.partitionBy(by).orderBy(*order)).alias("b")).where("b is not null")


def order_chain(spark, sf_dir) -> DataFrame:
    orders = read_table(spark, sf_dir, "orders", "o_orderkey", "o_custkey", "o_orderdate")
    return _next(orders, "o_custkey", ("o_orderdate", "o_orderkey")).unionByName(_next(orders, "o_orderdate", ("o_orderkey",)))


def status_hub(spark, sf_dir) -> DataFrame:
    """Every order to its priority (numbered in binary order) and to its customer's next order."""
    orders = read_table(spark, sf_dir, "orders", "o_orderkey", "o_custkey", "o_orderdate", "o_orderpriority")
    names = orders.groupBy("o_orderpriority").count().select("o_orderpriority")
    ranked = names.select("o_orderpriority", (F.row_number().over(W.orderBy("o_orderpriority")) - 1).cast("long").alias("r"))  # a handful of names
    hubs = orders.join(F.broadcast(ranked), "o_orderpriority").select(_sided("o_orderkey", 0).alias("a"), _sided("r", 1).alias("b"))
    chain = _next(orders, "o_custkey", ("o_orderdate", "o_orderkey")).select(_sided("a", 0).alias("a"), _sided("b", 0).alias("b"))
    return hubs.unionByName(chain)


def user_trans(spark, sf_dir) -> DataFrame:
    """Users of consecutive events. The order is global: events are cut into ranges and only their edges meet."""
    events = read_table(spark, sf_dir, "events", "event_id", "ts", "user_id")
    day = F.date_trunc("day", "ts")
    order = W.partitionBy("day").orderBy("ts", "event_id")
    rows = events.select("ts", "event_id", "user_id", day.alias("day")).withColumn("b", F.lead("user_id").over(order))
    inner = rows.where("b is not null").select(F.col("user_id").alias("a"), "b")
    ends = rows.groupBy("day").agg(F.min(F.struct("ts", "event_id", "user_id")).alias("first"), F.max(F.struct("ts", "event_id", "user_id")).alias("last"))
    seams = ends.select(F.col("last.user_id").alias("a"), F.lead("first.user_id").over(W.orderBy("day")).alias("b")).where("b is not null")  # one row per day
    return inner.unionByName(seams).where("a <> b")


def _number(names: DataFrame, first: int = 0) -> DataFrame:
    """Names with dense numbers in binary order: counts per range partition, then offsets (no single-task sort)."""
    ranged = names.distinct().repartitionByRange("name").sortWithinPartitions("name").withColumn("p", F.spark_partition_id())
    local = ranged.withColumn("i", F.row_number().over(W.partitionBy("p").orderBy("name")))
    sizes = local.groupBy("p").agg(F.count("*").alias("n"))
    offsets = sizes.select("p", (F.sum("n").over(W.orderBy("p").rowsBetween(W.unboundedPreceding, -1))).alias("before"))  # one row per partition
    return local.join(offsets, "p").select("name", (F.col("i") + F.coalesce("before", F.lit(0)) - 1 + first).cast("long").alias("id"))


def _host(url):
    return F.regexp_extract(url, "^[a-z]+://([^/]+)", 1)


def page_nav(spark, sf_dir) -> DataFrame:
    """Pages and the targets of their links, numbered in binary order of the target."""
    pages = read_table(spark, sf_dir, "pages", "page_id", "html")
    links = pages.select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1)).alias("name")).distinct()
    return links.join(_number(links.select("name")), "name").select(_sided("page_id", 0).alias("a"), _sided("id", 1).alias("b"))


def page_host(spark, sf_dir) -> DataFrame:
    pages = read_table(spark, sf_dir, "pages", "page_id", "url").select("page_id", _host("url").alias("name"))
    return pages.join(_number(pages.select("name")), "name").select(_sided("page_id", 0).alias("a"), _sided("id", 1).alias("b"))


def doc_line(spark, sf_dir) -> DataFrame:
    """Documents and, for every line that several have, the first document that has it: a star for each shared line, however common."""
    docs = read_table(spark, sf_dir, "documents", "doc_id", "text")
    lines = docs.select("doc_id", F.explode(F.split("text", "\n")).alias("line")).where("line <> ''").select("doc_id", F.md5("line").alias("line")).distinct()
    first = lines.groupBy("line").agg(F.min("doc_id").alias("b"), F.max("doc_id").alias("last")).where("b < last").select("line", "b")
    return lines.join(first, "line").where("doc_id <> b").select(F.col("doc_id").alias("a"), "b")


#: Vectors in a block: two blocks meet as one matrix.
KNN_BLOCK = 2048


def embed_knn(spark, sf_dir, k: int = 10) -> DataFrame:
    """Each vector and its k nearest by cosine (exact; equal ones by smaller id): blocks of vectors meet blocks, Arrow matrices inside."""
    import numpy as np
    import pandas as pd

    vec = read_table(spark, sf_dir, "embeddings", "vec_id", "embedding").where("embedding is not null")
    blocks = max(1, -(-vec.count() // KNN_BLOCK))
    own = F.pmod(F.xxhash64("vec_id"), F.lit(blocks))
    left = vec.select(own.alias("l"), F.explode(F.sequence(F.lit(0).cast("long"), F.lit(blocks - 1).cast("long"))).alias("r"), "vec_id", "embedding", F.lit(0).alias("side"))
    right = vec.select(F.explode(F.sequence(F.lit(0).cast("long"), F.lit(blocks - 1).cast("long"))).alias("l"), own.alias("r"), "vec_id", "embedding", F.lit(1).alias("side"))
    both = left.unionByName(right)

    def near(pdf: pd.DataFrame) -> pd.DataFrame:
        a, b = pdf[pdf.side == 0].sort_values("vec_id"), pdf[pdf.side == 1].sort_values("vec_id")
        if not len(a) or not len(b):
            return pd.DataFrame({"a": [], "b": [], "s": []}).astype({"a": "int64", "b": "int64", "s": "float64"})
        x, y = (np.stack(t.embedding.to_list()).astype(float) for t in (a, b))
        x, y = x / np.linalg.norm(x, axis=1, keepdims=True), y / np.linalg.norm(y, axis=1, keepdims=True)
        s = np.round(x @ y.T, 12)
        ids = b.vec_id.to_numpy()
        s[a.vec_id.to_numpy()[:, None] == ids[None]] = -9
        top = np.argsort(-s, axis=1, kind="stable")[:, :k]
        return pd.DataFrame({"a": np.repeat(a.vec_id.to_numpy(), top.shape[1]), "b": ids[top].ravel(), "s": np.take_along_axis(s, top, 1).ravel()})

    cand = both.groupBy("l", "r").applyInPandas(near, "a long, b long, s double").where("s > -2")
    rank = F.row_number().over(W.partitionBy("a").orderBy(F.desc("s"), "b"))
    return cand.withColumn("k", rank).where(F.col("k") <= k).select("a", "b")


VIEWS = {f.__name__: f for f in (lattice2d, part_cooc, order_chain, lattice8, order_part, geo_tree, status_hub, part_supp, cust_part, doc_line, page_nav, user_trans, embed_knn, ring_cliques, page_host)}


def pairs(spark: SparkSession, sf_dir: str, view: str) -> DataFrame:
    return VIEWS[view](spark, sf_dir)
