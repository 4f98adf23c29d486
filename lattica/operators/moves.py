"""The local move in DataFrames: connection table, destinations, candidates, replay filter, update.

State is (id, vw, cid, tw[, b]): every vertex with its weight, cluster (labelled by its
smallest vertex) and that cluster's weight.
"""

from __future__ import annotations

from fractions import Fraction

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import degree_class, portable_hash, ranks_before, signed_weight
from ..sources import drop, settle
from .graph import WGraph
from .options import Options


def state_of(g: WGraph, c: DataFrame) -> DataFrame:
    """State of a clustering with any labels."""
    rows = g.vertices.join(c.select("id", F.col("cid").alias("raw")), "id")
    per = rows.groupBy("raw").agg(F.min("id").alias("cid"), F.sum("vw").alias("tw"))
    return rows.join(per, "raw").drop("raw")


def singleton_state(g: WGraph) -> DataFrame:
    return g.vertices.withColumns({"cid": F.col("id"), "tw": F.col("vw")})


def inner_edges(g: WGraph, state: DataFrame) -> DataFrame:
    """Edges whose ends share the constraint cluster b."""
    a, b = (state.select(F.col("id").alias(k), F.col("b").alias(f"b_{k}")) for k in ("src", "dst"))
    return g.edges.join(a, "src").join(b, "dst").where("b_src = b_dst").select("src", "dst", "w")


def affinity(edges: DataFrame, state: DataFrame) -> DataFrame:
    """(id, cid, k): weight from every vertex to every adjacent cluster. Symmetric edges let the labelled end be the join key."""
    end = state.select(F.col("id").alias("src"), "cid")
    return edges.join(end, "src").groupBy(F.col("dst").alias("id"), "cid").agg(F.sum("w").alias("k"))


def affinity_salted(edges: DataFrame, state: DataFrame, salt: int = 16) -> DataFrame:
    """The same in two stages for hubs: partial sums under (vertex, cluster, salt), then without the salt."""
    end = state.select(F.col("id").alias("src"), "cid")
    part = edges.join(end, "src").groupBy(F.col("dst").alias("id"), "cid", F.pmod(F.xxhash64("src"), F.lit(salt)).alias("s")).agg(F.sum("w").alias("k"))
    return part.groupBy("id", "cid").agg(F.sum("k").alias("k"))


def affinity_by_degree(edges: DataFrame, state: DataFrame, hubs: DataFrame, salt: int = 16) -> DataFrame:
    """The same by degree bucket: vertices of hubs (id) in two stages, all others in one."""
    own = hubs.withColumnRenamed("id", "dst")
    few = edges.join(own, "dst", "left_semi").select("src", "dst", "w")
    return affinity(edges.join(own, "dst", "left_anti").select("src", "dst", "w"), state).unionByName(affinity_salted(few, state, salt))


def hub_vertices(edges: DataFrame, least: int) -> DataFrame:
    """(id) of the vertices of at least this degree; there are at most 2m / least."""
    return settle(edges.groupBy(F.col("dst").alias("id")).agg(F.count("*").alias("d")).where(F.col("d") >= least).select("id"), "hubs")


def affinity_from_edges(edges: DataFrame) -> DataFrame:
    """The table of the all-singleton clustering: the edges themselves."""
    return edges.select(F.col("src").alias("id"), F.col("dst").alias("cid"), F.col("w").alias("k"))


def patched(aff: DataFrame, edges: DataFrame, before: DataFrame, after: DataFrame) -> DataFrame:
    """The table after moves, from -w and +w on the movers' neighbours only. Labels of unmoved vertices may change too: they count as moved."""
    changed = before.select("id", F.col("cid").alias("old")).join(after.select("id", F.col("cid").alias("new")), "id").where("old <> new")
    rows = edges.join(changed.withColumnRenamed("id", "src"), "src")
    delta = rows.select(F.col("dst").alias("id"), F.explode(F.array(F.struct(F.col("old").alias("cid"), (-F.col("w")).alias("k")), F.struct(F.col("new").alias("cid"), F.col("w").alias("k")))).alias("e")).select("id", "e.cid", "e.k")
    return aff.unionByName(delta).groupBy("id", "cid").agg(F.sum("k").alias("k")).where("k <> 0")


def recomputed(aff: DataFrame, edges: DataFrame, before: DataFrame, after: DataFrame, enumerate_=affinity) -> DataFrame:
    """The table after moves, with the rows of all vertices beside a mover built anew."""
    changed = before.select("id", F.col("cid").alias("old")).join(after.select("id", F.col("cid").alias("new")), "id").where("old <> new").select(F.col("id").alias("src"))
    touched = edges.join(changed, "src", "left_semi").select(F.col("dst").alias("id")).distinct()
    # the touched vertices' edges are found at their own end, where edges may be bucketed, and turned round
    own = edges.join(touched.withColumnRenamed("id", "src"), "src", "left_semi").select(F.col("dst").alias("src"), F.col("src").alias("dst"), "w")
    anew = enumerate_(own, after)
    return aff.join(touched, "id", "left_anti").unionByName(anew)


def destinations(g: WGraph, state: DataFrame, aff: DataFrame) -> DataFrame:
    """(id, vw, cid, tw, k_own, s_own, c_new, s_new): c_new is null with s_new 0 for a fresh singleton, and s_new null without any destination."""
    totals = state.where("id = cid").select("cid", F.col("tw").alias("t"))
    rows = aff.join(totals, "cid").join(state.select("id", "vw", F.col("cid").alias("own")), "id")
    score = g.long(F.col("k")) * g.den - g.long(F.col("vw")) * g.num * F.col("t")
    other = F.when(F.col("cid") != F.col("own"), F.struct(score.alias("s"), (-portable_hash("id", "cid")).alias("h"), (-F.col("cid")).alias("c")))
    best = rows.groupBy("id").agg(F.max(other).alias("best"), F.coalesce(F.sum(F.when(F.col("cid") == F.col("own"), F.col("k"))), F.lit(0)).cast("long").alias("k_own"))
    out = state.join(best, "id", "left").withColumn("k_own", F.coalesce("k_own", F.lit(0).cast("long")))
    out = out.withColumn("s_own", g.long(F.col("k_own")) * g.den - g.long(F.col("vw")) * g.num * (F.col("tw") - F.col("vw")))
    leave = (F.col("s_own") < 0) & (F.col("best").isNull() | (F.col("best.s") < 0))
    return out.select("id", "vw", "cid", "tw", "k_own", "s_own", F.when(~leave, -F.col("best.c")).alias("c_new"), F.when(leave, g.long(F.lit(0).cast("long"))).otherwise(F.col("best.s")).alias("s_new"), *(["b"] if "b" in state.columns else []))


def scaled_objective(g: WGraph, dest: DataFrame) -> int:
    """den times the objective, from own-cluster weights and cluster totals of a destination frame."""
    one = F.sum(g.long(F.col("k_own")) * g.den - g.long(F.col("vw")) * g.num * (F.col("tw") - F.col("vw")))
    return int(dest.agg(one.alias("v")).first().v or 0)


def candidates(g: WGraph, dest: DataFrame, phi) -> DataFrame:
    """(id, c_old, c_new, gain) of the vertices whose best score reaches (1 - phi) of their own."""
    a, b = Fraction(phi).numerator, Fraction(phi).denominator
    keep = F.col("s_new").isNotNull() & (F.col("s_new") * b >= F.col("s_own") * (b - a))
    return dest.where(keep).select("id", F.col("cid").alias("c_old"), "c_new", (F.col("s_new") - F.col("s_own")).alias("gain"), "vw")


def multiple():
    """How often s(u,v) enters v's gain, for columns u_old, u_new, v_old, v_new."""
    gone = F.when(F.col("u_old") == F.col("v_old"), 1).when(F.col("u_old") == F.col("v_new"), -1).otherwise(0)
    come = F.when(F.col("u_new") == F.col("v_old"), -1).when(F.col("u_new") == F.col("v_new"), 1).otherwise(0)
    return gone + come


def replay_filter(g: WGraph, edges: DataFrame, moves: DataFrame, eps=(1, 10)) -> DataFrame:
    """The moves whose gain is not negative once every better-ranked neighbouring candidate has moved."""
    u = moves.select(F.col("id").alias("src"), F.col("c_old").alias("u_old"), F.col("c_new").alias("u_new"), F.col("gain").alias("u_gain"), F.col("vw").alias("u_vw"))
    v = moves.select(F.col("id").alias("dst"), F.col("c_old").alias("v_old"), F.col("c_new").alias("v_new"), F.col("gain").alias("v_gain"), F.col("vw").alias("v_vw"))
    near = edges.join(u, "src").join(v, "dst").where(ranks_before(F.col("u_gain"), F.col("src"), F.col("v_gain"), F.col("dst"), g.den, eps))
    change = near.groupBy(F.col("dst").alias("id")).agg(F.sum(g.long(signed_weight("w", "u_vw", "v_vw", g.num, g.den)) * multiple()).alias("change"))
    return moves.join(change, "id", "left").where(F.col("gain") + F.coalesce("change", g.long(F.lit(0).cast("long"))) >= 0).drop("change")


def min_label_filter(moves: DataFrame, state: DataFrame) -> DataFrame:
    """Improving moves, but a lone vertex joins another lone vertex only under a smaller label."""
    lone = state.groupBy("cid").agg((F.count("*") == 1).alias("lone"))
    rows = moves.where("gain > 0").join(lone.select(F.col("cid").alias("c_old"), F.col("lone").alias("from_lone")), "c_old")
    rows = rows.join(lone.select(F.col("cid").alias("c_new"), F.col("lone").alias("to_lone")), "c_new", "left")
    stop = F.col("from_lone") & F.coalesce("to_lone", F.lit(False)) & (F.col("c_new") > F.col("c_old"))
    return rows.where(~stop).select("id", "c_old", "c_new", "gain", "vw")


def applied(g: WGraph, state: DataFrame, moves: DataFrame) -> DataFrame:
    """The state after moves; a fresh singleton is labelled below every vertex for a moment, then by its vertex."""
    to = moves.select("id", F.coalesce("c_new", -1 - F.col("id")).alias("to"))
    c = state.select("id", "cid").join(to, "id", "left").select("id", F.coalesce("to", "cid").alias("cid"))
    return state_of(g, c)


def coloured(edges: DataFrame, distance: int = 1) -> DataFrame:
    """(id, colour): vertices within the distance differ. Rounds of hashed local minima among the uncoloured.

    The smallest free rank is passed on to neighbours once for each step of the distance, so that
    no pairs at distance two are formed.
    """
    every = edges.select(F.col("src").alias("id")).distinct()
    left = settle(every.withColumn("rank", F.struct(portable_hash("id", F.lit(0).cast("long"), 3).alias("h"), "id")), "colour")
    done, k = None, 0
    while not left.isEmpty():
        low = left.select("id", F.col("rank").alias("r"))
        for _ in range(distance):  # of the vertex itself and its neighbours
            near = edges.join(low.withColumnRenamed("id", "src"), "src").select(F.col("dst").alias("id"), "r")
            low = near.unionByName(low).groupBy("id").agg(F.min("r").alias("r"))
        pick = settle(left.join(low, "id").where("rank = r").select("id", F.lit(k).alias("colour")), "colour")
        rest = settle(left.join(pick, "id", "left_anti"), "colour")
        drop(left)
        left = rest
        done = pick if done is None else done.unionByName(pick)
        k += 1
    return done if done is not None else left.select("id", F.lit(0).alias("colour"))


def batches_of(g: WGraph, o: Options) -> tuple[DataFrame, int]:
    """(id, batch) under the batching in effect, and the number of batches."""
    how = o.batching_in_effect()
    if how in ("color1", "color2"):
        c = coloured(g.edges, 2 if how == "color2" else 1).select("id", F.col("colour").alias("batch"))
    elif how == "degree":
        d = g.edges.groupBy(F.col("src").alias("id")).agg(F.count("*").alias("d"))
        c = d.select("id", degree_class("d", o.batches).alias("batch"))
    else:
        c = g.vertices.select("id", F.pmod(portable_hash("id", F.lit(0).cast("long"), o.seed), F.lit(o.batches)).cast("int").alias("batch"))
    c = settle(c, "batch")
    return c, int(c.agg(F.max("batch")).first()[0] or 0) + 1


def local_move(g: WGraph, state: DataFrame, o: Options, single: bool = False, constrained: bool = False, log: list | None = None, level: int = 0, phase: str = "down"):
    """(state, scaled objective, start objective): passes of simultaneous moves; the best state seen between passes is returned.

    kernel "split" writes the connection table and patches it while few vertices change
    (rebuilding touched rows otherwise); "fused" plans it anew inside each pass. With salt_degree
    the rows of hubs are summed in two stages.
    """
    edges = settle(inner_edges(g, state), "inner") if constrained else g.edges
    hubs = None if o.salt_degree is None else hub_vertices(g.edges, o.salt_degree)
    enumerate_ = affinity if hubs is None else lambda e, x: affinity_by_degree(e, x, hubs, o.salt)
    state = settle(state, "state")
    aff = affinity_from_edges(edges) if single else enumerate_(edges, state)
    if o.kernel == "split" and not single:
        aff = settle(aff, "aff")
    batch, groups = batches_of(g, o) if o.batching_in_effect() else (None, 1)
    n = state.count()
    best = start = best_value = active = stuck = last = None
    for i, phi in [*enumerate(o.phi), (len(o.phi), None)]:
        if phi is not None and stuck == phi:
            continue
        if phi != last:  # another temperature opens every vertex
            drop(*[active] if active is not None else [])
            active, last = None, phi
        movers: list[DataFrame] = []
        total = 0
        for k in range(groups):
            dest = settle(destinations(g, state, aff), "dest")
            if k == 0:  # the state between two passes
                value = scaled_objective(g, dest)
                start = value if start is None else start
                if best_value is None or value > best_value:
                    if best is not None and best is not state:
                        drop(best)
                    best, best_value = state, value
                if phi is None:
                    break
            moves = candidates(g, dest, phi)
            if batch is not None:
                moves = moves.join(batch.where(F.col("batch") == k).select("id"), "id", "left_semi")
            if active is not None:
                moves = moves.join(active, "id", "left_semi")
            if o.symmetry == "replay":
                moves = settle(moves, "moves")
                kept = replay_filter(g, edges, moves, o.eps)
            elif o.symmetry in ("min_label", "async_min_label") and o.mlh_active(i):
                kept = min_label_filter(moves, state)
            else:
                kept = moves if o.symmetry == "none" else moves.where("gain > 0")
            kept = settle(kept.select("id", "c_new"), "kept")
            count = kept.count()
            drop(dest, moves)
            if not count:
                drop(kept)
                continue
            total += count
            movers.append(kept)
            new = settle(applied(g, state, kept), "state")
            few = count <= o.patch_threshold * n
            if o.kernel == "fused" or (o.kernel == "fused_large_moves" and not few):
                nxt = enumerate_(edges, new)
            else:
                nxt = settle(patched(aff, edges, state, new) if few else recomputed(aff, edges, state, new, enumerate_), "aff")
            drop(aff, *([state] if state is not best else []))
            state, aff = new, nxt
        if phi is None:
            break
        if log is not None:
            log.append((level, phase, i, total, value))
        stuck = None if total else phi
        if o.prune:  # movers and their neighbours, from the next pass on
            gone = None
            for m in movers:
                gone = m.select("id") if gone is None else gone.unionByName(m.select("id"))
            gone = state.select("id").limit(0) if gone is None else gone
            near = g.edges.join(gone.withColumnRenamed("id", "src"), "src", "left_semi").select(F.col("dst").alias("id"))
            fresh = settle(near.unionByName(gone).distinct(), "active")
            drop(*[active] if active is not None else [])
            active = fresh
        drop(*movers)
    drop(dest, *([aff] if aff is not None else []), *([state] if state is not best else []), *([batch] if batch is not None else []), *([hubs] if hubs is not None else []), *([edges] if constrained else []))
    return best, best_value, start
