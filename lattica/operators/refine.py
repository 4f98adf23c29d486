"""Refinement by a random spanning forest, and the strict prefix move, in DataFrames."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions import portable_hash, signed_weight
from ..sources import drop, settle
from .graph import WGraph
from .kernel import BIG
from .moves import affinity, destinations, multiple


#: Movers whose running sums one window adds up.
STRETCH = 1 << 14


def _zero():
    return F.lit(0).cast("long")


def eligible(g: WGraph, b: DataFrame) -> DataFrame:
    """(id, vw, b, wb, inside, ok): weight to the rest of the constraint cluster, and whether w'(v, B[v]) >= 0."""
    rows = g.vertices.select("id", "vw").join(b.select("id", F.col("cid").alias("b")), "id")
    rows = rows.join(rows.groupBy("b").agg(F.sum("vw").alias("wb")), "b")
    ends = [rows.select(F.col("id").alias(k), F.col("b").alias(f"b_{k}")) for k in ("src", "dst")]
    inside = g.edges.join(ends[0], "src").join(ends[1], "dst").where("b_src = b_dst").groupBy(F.col("src").alias("id")).agg(F.sum("w").alias("inside"))
    rows = rows.join(inside, "id", "left").withColumn("inside", F.coalesce("inside", _zero()))
    return rows.select("id", "vw", "b", "wb", "inside", (g.long(F.col("inside")) * g.den - g.long(F.col("vw")) * g.num * (F.col("wb") - F.col("vw")) >= 0).alias("ok"))


def chosen_edges(g: WGraph, elig: DataFrame, seed: int, greedy: bool = False) -> DataFrame:
    """(id, choice): uniform (least hash) over itself and the eligible neighbours in its constraint cluster with w' >= 0."""
    ends = [elig.where("ok").select(F.col("id").alias(k), F.col("b").alias(f"b_{k}"), F.col("vw").alias(f"vw_{k}")) for k in ("src", "dst")]
    s = g.long(signed_weight("w", "vw_src", "vw_dst", g.num, g.den))
    near = g.edges.join(ends[0], "src").join(ends[1], "dst").where("b_src = b_dst").withColumn("s", s).where("s >= 0").select(F.col("src").alias("id"), F.col("dst").alias("u"), "s")
    own = elig.where("ok").select("id", F.col("id").alias("u"), g.long(_zero()).alias("s"))
    rank = F.struct(*([(-F.col("s")).alias("s")] if greedy else []), portable_hash("id", "u", seed).alias("h"), "u")
    picked = near.unionByName(own).groupBy("id").agg(F.min(rank)["u"].alias("choice"))
    return elig.select("id").join(picked, "id", "left").select("id", F.coalesce("choice", "id").alias("choice"))


def oriented(choice: DataFrame, seed: int) -> DataFrame:
    """(id, parent, f): choices kept from higher to lower order f; lone vertices go to 2K - f and try again."""
    rows = choice.withColumn("f", portable_hash("id", _zero(), seed + 1))

    def parents(rows):
        target = rows.select(F.col("id").alias("choice"), F.col("f").alias("g"))
        lower = (F.col("g") < F.col("f")) | ((F.col("g") == F.col("f")) & (F.col("choice") < F.col("id")))
        return rows.join(target, "choice").select("id", "choice", "f", F.when(lower, F.col("choice")).otherwise(F.col("id")).alias("parent"))

    first = parents(rows)
    busy = first.where("parent <> id").select(F.explode(F.array("id", "parent")).alias("id")).distinct().withColumn("busy", F.lit(True))
    flipped = first.join(busy, "id", "left").select("id", "choice", F.when(F.col("busy"), F.col("f")).otherwise(2 * BIG - F.col("f")).alias("f"))
    return parents(flipped).select("id", "parent", "f")


def pointer_jump(forest: DataFrame) -> DataFrame:
    """(id, parent, f, root) by doubling."""
    state = settle(forest.withColumn("root", F.col("parent")), "roots")
    while True:
        up = state.select(F.col("id").alias("root"), F.col("root").alias("far"))
        new = settle(state.join(up, "root").select("id", "parent", "f", F.col("far").alias("root"), (F.col("far") != F.col("root")).alias("moved")), "roots")
        ended = new.where("moved").isEmpty()
        drop(state)
        state = new.drop("moved")
        state._scratch = new._scratch
        if ended:
            return state


def _ranged(rows: DataFrame) -> DataFrame:
    """rows (root, f, ...) with part: ranges of the order f of about STRETCH rows of a tree."""
    sizes = rows.groupBy("root").agg(F.ceil(F.count("*") / STRETCH).alias("parts"))
    return rows.join(sizes, "root").withColumn("part", F.floor(F.col("f") * F.col("parts") / F.lit(2 * BIG + 1))).drop("parts")


def prefixes(g: WGraph, forest: DataFrame, elig: DataFrame) -> DataFrame:
    """(id, root, f, pos, ok, joined, rest, good): the two running checks of every vertex at its place in its sorted tree, and their scores."""
    ends = [forest.select(F.col("id").alias(k), F.col("root").alias(f"r_{k}"), F.col("f").alias(f"f_{k}")) for k in ("src", "dst")]
    inner = g.edges.join(ends[0], "src").join(ends[1], "dst").where("r_src = r_dst")
    later = (F.col("f_src") < F.col("f_dst")) | ((F.col("f_src") == F.col("f_dst")) & (F.col("src") < F.col("dst")))
    earlier = inner.where(later).groupBy(F.col("dst").alias("id")).agg(F.sum("w").alias("earlier"))
    rows = forest.join(elig, "id").join(earlier, "id", "left").withColumn("earlier", F.coalesce("earlier", _zero()))
    # a tree is cut into ranges of its random order: sums inside a range, moved by those of the ranges before
    rows = settle(_ranged(rows), "ranges")
    step = F.col("inside") - 2 * F.col("earlier")
    sums = rows.groupBy("root", "part").agg(F.count("*").alias("n"), F.sum("vw").alias("v"), F.sum(step).alias("c"))
    ahead = W.partitionBy("root").orderBy("part").rowsBetween(W.unboundedPreceding, -1)  # one row per range
    before = sums.select("root", "part", *[F.coalesce(F.sum(x).over(ahead), _zero()).alias(f"{x}0") for x in ("n", "v", "c")])
    order = W.partitionBy("root", "part").orderBy("f", "id")
    past = order.rowsBetween(W.unboundedPreceding, -1)
    rows = rows.withColumns({"pos": F.row_number().over(order), "weight": F.coalesce(F.sum("vw").over(past), _zero()), "cut": F.coalesce(F.sum(step).over(past), _zero())}).join(before, ["root", "part"])
    rows = rows.withColumns({"pos": (F.col("pos") + F.col("n0")).cast("int"), "weight": F.col("weight") + F.col("v0"), "cut": F.col("cut") + F.col("c0")})
    joined = g.long(F.col("earlier")) * g.den - g.long(F.col("vw")) * g.num * F.col("weight")
    rest = g.long(F.col("cut")) * g.den - g.long(F.col("weight")) * g.num * (F.col("wb") - F.col("weight"))
    rows = rows.select("id", "root", "f", "pos", "ok", joined.alias("joined"), rest.alias("rest"))
    return rows.withColumn("good", (F.col("pos") == 1) | (F.col("joined") >= 0) & (F.col("rest") >= 0))


def committed(rows: DataFrame, racy: bool = False) -> DataFrame:
    """(id, cid): the valid prefix of a tree is a cluster (labelled by its smallest vertex), all others are alone."""
    if racy:
        part = rows.select("id", F.col("root").alias("raw"))
    else:
        first = rows.where(~F.col("good")).groupBy("root").agg(F.min("pos").alias("failed"))  # where the prefix ends
        held = F.col("failed").isNull() | (F.col("pos") < F.col("failed"))
        part = rows.join(first, "root", "left").select("id", F.when(held & F.col("ok"), F.col("root")).otherwise(-1 - F.col("id")).alias("raw"))
    low = part.groupBy("raw").agg(F.min("id").alias("cid"))
    return part.join(low, "raw").select("id", "cid")


def refine(g: WGraph, b: DataFrame, seed: int, mode: str = "forest") -> DataFrame:
    """(id, cid): sub-clusters of the constraint clustering b (id, cid)."""
    elig = settle(eligible(g, b), "eligible")
    forest = pointer_jump(oriented(settle(chosen_edges(g, elig, seed, mode == "greedy"), "choice"), seed))
    return settle(committed(prefixes(g, forest, elig), mode == "racy"), "refined")


def movers(g: WGraph, state: DataFrame, cap: int | None = None) -> DataFrame:
    """(id, pos, vw, old, new, gain) of all vertices that gain by moving, in hash order; of the first `cap` if given."""
    dest = destinations(g, state, affinity(g.edges, state))
    alone = F.col("s_new").isNull() | (F.col("s_new") < 0)
    zero = g.long(_zero())
    rows = dest.select("id", "vw", F.col("cid").alias("old"), F.when(~alone, F.col("c_new")).alias("new"), (F.when(alone, zero).otherwise(F.col("s_new")) - F.col("s_own")).alias("gain")).where("gain > 0")
    rows = rows.withColumn("h", portable_hash("id", _zero(), 5))
    if cap is not None:
        return rows.orderBy("h", "id").limit(cap).withColumn("pos", F.row_number().over(W.orderBy("h", "id"))).drop("h")
    # ranges of the hash are numbered apart and moved by the counts of the ranges before
    rows = settle(rows.withColumn("range", F.shiftright("h", 21)), "movers")
    sizes = rows.groupBy("range").agg(F.count("*").alias("n"))
    before = sizes.select("range", F.coalesce(F.sum("n").over(W.orderBy("range").rowsBetween(W.unboundedPreceding, -1)), _zero()).alias("before"))  # one row per range
    pos = F.col("before") + F.row_number().over(W.partitionBy("range").orderBy("h", "id"))
    return rows.join(before, "range").withColumn("pos", pos).drop("h", "range", "before")


def strict_pairs(g: WGraph, m: DataFrame) -> DataFrame:
    """(id, pos, old, new, gain, change, run): gains after all earlier movers, pair by pair (for few movers)."""
    u = m.select(F.col("id").alias("src"), F.col("pos").alias("u_pos"), F.col("vw").alias("u_vw"), F.col("old").alias("u_old"), F.col("new").alias("u_new"))
    v = m.select(F.col("id").alias("dst"), F.col("pos").alias("v_pos"), F.col("vw").alias("v_vw"), F.col("old").alias("v_old"), F.col("new").alias("v_new"))
    pairs = u.join(F.broadcast(v), F.col("u_pos") < F.col("v_pos")).join(g.edges, ["src", "dst"], "left")
    s = g.long(signed_weight(F.coalesce("w", _zero()), "u_vw", "v_vw", g.num, g.den))
    change = pairs.groupBy(F.col("dst").alias("id")).agg(F.sum(s * multiple()).alias("change"))
    return _running(g, m.join(change, "id", "left"))


def strict_prefix(g: WGraph, m: DataFrame) -> DataFrame:
    """The same from running sums of the weight that entered or left each cluster before a mover's turn."""
    events = m.select("pos", F.explode(F.array(F.struct(F.col("old").alias("x"), (-F.col("vw")).alias("d")), F.struct(F.col("new").alias("x"), F.col("vw").alias("d")))).alias("e")).select("pos", "e.x", "e.d").where("x is not null")
    asked = m.select("pos", F.explode(F.array(F.struct(F.col("new").alias("x"), F.lit(1).alias("sign")), F.struct(F.col("old").alias("x"), F.lit(-1).alias("sign")))).alias("e"), "id", "vw").select("pos", "e.x", "e.sign", "id", "vw").where("x is not null")
    every = events.select("x", "pos", "d", F.lit(None).cast("long").alias("id"), F.lit(0).alias("sign"), _zero().alias("vw")).unionByName(asked.select("x", "pos", _zero().alias("d"), "id", "sign", "vw"))
    before = F.coalesce(F.sum("d").over(W.partitionBy("x").orderBy("pos").rangeBetween(W.unboundedPreceding, -1)), _zero())
    drift = every.withColumn("drift", before).where("id is not null").groupBy("id").agg(F.sum(-g.long(F.col("vw")) * g.num * F.col("sign") * F.col("drift")).alias("far"))
    u = m.select(F.col("id").alias("src"), F.col("pos").alias("u_pos"), F.col("old").alias("u_old"), F.col("new").alias("u_new"))
    v = m.select(F.col("id").alias("dst"), F.col("pos").alias("v_pos"), F.col("old").alias("v_old"), F.col("new").alias("v_new"))
    near = g.edges.join(u, "src").join(v, "dst").where("u_pos < v_pos").groupBy(F.col("dst").alias("id")).agg(F.sum(g.long(F.col("w")) * g.den * multiple()).alias("near"))
    both = m.join(drift, "id", "left").join(near, "id", "left")
    return _running(g, both.withColumn("change", F.coalesce("far", g.long(_zero())) + F.coalesce("near", g.long(_zero()))).drop("far", "near"))


def _running(g: WGraph, rows: DataFrame) -> DataFrame:
    """Running sums inside stretches of the order, moved by the sums of the stretches before."""
    rows = rows.withColumn("change", F.coalesce("change", g.long(_zero()))).withColumn("part", F.floor(F.col("pos") / STRETCH))
    rows = settle(rows, "changes")
    step = F.col("gain") + F.col("change")
    sums = rows.groupBy("part").agg(F.sum(step).alias("s"))
    before = sums.select("part", F.sum("s").over(W.orderBy("part").rowsBetween(W.unboundedPreceding, -1)).alias("before"))  # one row per stretch
    inner = F.sum(step).over(W.partitionBy("part").orderBy("pos").rowsBetween(W.unboundedPreceding, 0))
    return rows.join(before, "part").withColumn("run", inner + F.coalesce("before", g.long(_zero()))).drop("part", "before")


def strict_move(g: WGraph, state: DataFrame, bound: int = 10_000, method: str = "pairs") -> DataFrame:
    """(id, c_new) of the best prefix of all movers (largest running sum, first of equals); pairs only up to `bound` movers."""
    m = settle(movers(g, state), "movers")
    few = method == "pairs" and m.count() <= bound
    rows = settle((strict_pairs if few else strict_prefix)(g, m), "strict")
    best = rows.orderBy(F.desc("run"), "pos").limit(1).select(F.col("pos").alias("end"))
    return rows.join(F.broadcast(best), F.col("pos") <= F.col("end")).select("id", F.col("new").alias("c_new"))
