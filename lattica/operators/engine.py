"""The engines over DataFrames: two-way, refined, iteration; small graphs go to the one-task kernel, those of few enough vertices to blocks of edges."""

from __future__ import annotations

import time
from dataclasses import dataclass, field, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources import bucketed, drop, settle
from . import blocks, kernel, levels, moves, refine
from .graph import WGraph, components_graph, label_propagation_graph, lambda_cc, modularity_graph, unit_graph, with_constraint
from .options import Options


@dataclass
class Result:
    clusters: DataFrame
    log: list = field(default_factory=list)
    seconds: dict = field(default_factory=dict)
    levels: int = 0

    def timed(self, phase: str, start: float) -> None:
        self.seconds[phase] = self.seconds.get(phase, 0.0) + time.perf_counter() - start


def local(g: WGraph) -> kernel.Graph:
    """The graph in this process; only for graphs whose stored edges are below the kernel limit."""
    ids, vw, b = blocks.vertices_of(g)
    e = g.edges.select("src", "dst", "w").toArrow()
    src, dst = (np.searchsorted(ids, e[k].to_numpy()) for k in ("src", "dst"))
    return kernel.Graph(ids, vw, src, dst, e["w"].to_numpy(), g.num, g.den, b)


def back(spark, small: kernel.Graph | blocks.Blocks, c: np.ndarray) -> DataFrame:
    ids = small.ids.astype(np.int64, copy=False)
    return spark.createDataFrame(pa.table({"id": ids, "cid": ids[c]}))


def _packed_run(g: WGraph, o: Options, out: Result, depth: int, run) -> DataFrame | None:
    """The clusters of run(graph, log), in one process or over blocks; None where neither may hold the graph."""
    if _fits(g, o):
        small = local(g)
    elif _in_blocks(g, o):
        small = blocks.packed(g)
    else:
        return None
    log = kernel.Log()
    c = run(small, log)
    clusters = settle(back(g.edges.sparkSession, small, c), "clusters")
    if isinstance(small, blocks.Blocks):
        blocks.keep(clusters, small.ids, blocks.canonical(c, small.n))
    out.log += [(depth + r[0], *r[1:4], r[5]) for r in log.rows]
    for k, v in log.seconds.items():
        out.seconds[k] = out.seconds.get(k, 0.0) + v
    return clusters


def _count(state: DataFrame) -> int:
    return state.where("id = cid").count()


def _dealt(g: WGraph, made: list | None = None) -> WGraph:
    """The graph with its edges in buckets by src, for a level that runs on DataFrames; a new table is added to made."""
    if hasattr(g.edges, "_table"):
        return g
    out = replace(g, edges=bucketed(g.edges, "src", "edges"))
    if made is not None:
        made.append(out.edges)
    return out


def _fits(g: WGraph, o: Options) -> bool:
    return not g.wide and 0 <= g.stored <= o.kernel_limit


def _in_blocks(g: WGraph, o: Options) -> bool:
    """Colourings are made on DataFrames only."""
    if g.wide or g.stored < 0 or o.batching_in_effect() in ("color1", "color2"):
        return False
    plain = getattr(g.vertices, "_constrained", (g.vertices,))[0]
    if hasattr(plain, "_arrays"):
        return len(plain._arrays[0]) <= o.state_limit
    known = blocks.degrees(g)
    return (g.vertices if known is None else known).count() <= o.state_limit


def two_way(g: WGraph, o: Options = Options(), constraint: DataFrame | None = None, start: DataFrame | None = None) -> Result:
    """Moves and contraction down to where nothing merges, then moves at every level on the way up (if o.uncoarsen)."""
    out, packed = Result(None), False
    if constraint is not None:
        g = with_constraint(g, constraint)
    stack: list[tuple[WGraph, DataFrame]] = []
    made: list[DataFrame] = []
    while True:
        first = None if stack else start

        def run(small, log, first=first):
            c = None if first is None else blocks.array_of(first, small.ids)
            return kernel.two_way(small, o, small.b, c, log) if isinstance(small, kernel.Graph) else blocks.two_way(small, o, c, log)

        clusters = _packed_run(g, o, out, len(stack), run)
        if clusters is not None:
            packed = True
            break
        single = start is None or bool(stack)
        g = _dealt(g, made)
        state = moves.singleton_state(g) if single else moves.state_of(g, start)
        if single and "b" in g.vertices.columns:
            state = state.select("id", "vw", "cid", "tw", "b")
        t = time.perf_counter()
        state, _, _ = moves.local_move(g, state, o, single, constraint is not None, out.log, len(stack))
        out.timed("move_down", t)
        clusters = state.select("id", "cid")
        if _count(state) == g.vertices.count() or len(stack) >= o.max_levels:
            break
        t = time.perf_counter()
        stack.append((g, clusters))
        g = levels.contract(g, clusters, o.gather)
        made += [g.edges, g.vertices]
        out.timed("contract", t)
    out.levels = len(stack)
    if o.move_at_top and o.uncoarsen and not packed:
        clusters = moves.local_move(g, moves.state_of(g, clusters), o, log=out.log, level=len(stack), phase="up")[0].select("id", "cid")
    for depth in range(len(stack) - 1, -1, -1):
        g, up = stack[depth]
        clusters = levels.project(up, clusters)
        if o.uncoarsen:
            t = time.perf_counter()
            clusters = moves.local_move(g, moves.state_of(g, clusters), o, log=out.log, level=depth, phase="up")[0].select("id", "cid")
            out.timed("move_up", t)
    return _ended(out, g, clusters, stack, made)


def _ended(out: Result, g: WGraph, clusters: DataFrame, stack: list, made: list) -> Result:
    """The result under canonical labels, written, without the scratch of the levels."""
    out.clusters = settle(moves.state_of(g, clusters).select("id", "cid"), "clusters") if stack else clusters
    drop(*made)
    return out


def refined(g: WGraph, o: Options = Options(uncoarsen=False), start: DataFrame | None = None) -> Result:
    """Moves from any clustering, refinement inside clusters, contraction of the refined clusters, projection down."""
    out = Result(None)
    c = start
    stack: list[tuple[WGraph, DataFrame]] = []
    made: list[DataFrame] = []
    while True:

        def run(small, log, c=c, depth=len(stack)):
            engine = kernel if isinstance(small, kernel.Graph) else blocks
            return engine.refined(small, None if c is None else blocks.array_of(c, small.ids), o.but(seed=o.seed + 101 * depth), log)

        clusters = _packed_run(g, o, out, len(stack), run)
        if clusters is not None:
            break
        g = _dealt(g, made)
        state = moves.singleton_state(g) if c is None else moves.state_of(g, c)
        t = time.perf_counter()
        state, value, before = moves.local_move(g, state, o, c is None, log=out.log, level=len(stack))
        out.timed("move_down", t)
        if value == before:
            state = settle(moves.applied(g, state, refine.strict_move(g, state, o.cap, o.strict_method)), "state")
        clusters = state.select("id", "cid")
        n = g.vertices.count()
        if _count(state) == n or len(stack) >= o.max_levels:
            break
        t = time.perf_counter()
        for k in range(o.redraw_limit + 1):
            fine = refine.refine(g, clusters, o.seed + 101 * (len(stack) + 1) + 7919 * k, o.refine_mode)
            if fine.where("id = cid").count() < n:
                break
        else:
            break
        out.timed("refine", t)
        t = time.perf_counter()
        c = settle(levels.downsample(fine, clusters), "start")
        stack.append((g, fine))
        g = levels.contract(g, fine, o.gather)
        made += [g.edges, g.vertices]
        out.timed("contract", t)
    out.levels = len(stack)
    for depth in range(len(stack) - 1, -1, -1):
        g, up = stack[depth]
        clusters = settle(levels.project(up, clusters), "clusters")
        if o.uncoarsen:
            t = time.perf_counter()
            clusters = moves.local_move(g, moves.state_of(g, clusters), o, log=out.log, level=depth, phase="up")[0].select("id", "cid")
            out.timed("move_up", t)
    return _ended(out, g, clusters, stack, made)


def iterate(g: WGraph, o: Options = Options(), rounds: int = 11, scheme: str = "constrained", until_stable: bool = False) -> list[Result]:
    """One result per round; scheme: constrained, seeded, refined or refined_up."""
    out: list[Result] = []
    last = None
    for r in range(rounds):
        if scheme == "constrained":
            res = two_way(g, o, constraint=last)
        elif scheme == "seeded":
            res = two_way(g, o, start=last)
        else:
            res = refined(g, o.but(uncoarsen=scheme == "refined_up", seed=o.seed + 1009 * r), start=last)
        if not hasattr(res.clusters, "_scratch"):
            res.clusters = settle(res.clusters, "round")
        stable = until_stable and last is not None and is_stable(g, last, res.clusters)
        out.append(res)
        last = res.clusters
        if stable:
            break
    return out


def modularity(g: WGraph, c: DataFrame) -> DataFrame:
    """One row: that of lambda_cc, from the blocks if graph and clustering are held there."""
    ids = getattr(g.vertices, "_arrays", (None,))[0]
    if ids is None or not hasattr(g.edges, "_blocks") or getattr(c, "_labels", (None,))[0] is not ids:
        return lambda_cc(g, c).select("modularity")
    small = blocks.packed(g)
    if not hasattr(g.edges, "_total"):
        g.edges._total = g.edges.agg(F.sum("w")).first()[0]
    own = g.num * int(small.vw @ small.vw)
    q = float(blocks.objective(small, c._labels[1]) - own) / (float(g.den) * g.edges._total) if g.edges._total else 0.0
    return g.edges.sparkSession.range(1).select(F.lit(q).alias("modularity"))


def run_log(spark, result: Result, run: str = "run") -> DataFrame:
    """(run, level, phase, pass, movers, objective) of every pass, and (run, phase, seconds) as rows of pass -1."""
    rows = [(run, int(x[0]), str(x[1]), int(x[2]), int(x[3]), str(x[4]), None) for x in result.log]
    rows += [(run, -1, k, -1, None, None, float(v)) for k, v in result.seconds.items()]
    return spark.createDataFrame(rows, "run string, level int, phase string, pass int, movers long, objective string, seconds double")


def is_stable(g: WGraph, before: DataFrame, after: DataFrame) -> bool:
    """An iteration that does not improve the objective."""
    return lambda_cc(g, after).first().scaled <= lambda_cc(g, before).first().scaled


def recombine(g: WGraph, b1: DataFrame, b2: DataFrame, o: Options = Options()) -> Result:
    """Two-way inside both clusterings, free on the way up."""
    both = b1.select("id", F.col("cid").alias("x")).join(b2.select("id", F.col("cid").alias("y")), "id")
    label = both.groupBy("x", "y").agg(F.min("id").alias("cid"))
    return two_way(g, o, constraint=settle(both.join(label, ["x", "y"]).select("id", "cid"), "both"))


def label_propagation(edges: DataFrame, o: Options = Options()) -> Result:
    """One level of moves with lambda 0."""
    g = label_propagation_graph(edges)
    state, _, _ = moves.local_move(g, moves.singleton_state(g), o, True)
    return Result(state.select("id", "cid"))


def layered_order(g: WGraph, gammas) -> DataFrame:
    """(id, place): vertices sorted by their clusters at several resolutions, coarse first (for graph compression)."""
    rows = g.vertices.select("id")
    names = []
    for i, gamma in enumerate(gammas):
        c = two_way(modularity_graph(g.edges, gamma)).clusters
        rows = settle(rows.join(c.withColumnRenamed("cid", f"c{i}"), "id"), "layer")
        names.append(f"c{i}")
    return rows.select("id", F.struct(*names, "id").alias("place")).orderBy("place")


class Engine:
    """A session's entry point: graphs by view, clustering by method, checks and measures."""

    def __init__(self, spark):
        self.spark = spark

    def graph(self, view: str, sf_dir: str, largest: bool = False, gamma=1, lam=None) -> WGraph:
        from ..sources.views import pairs
        from .graph import largest_component, symmetrize

        edges = settle(symmetrize(pairs(self.spark, sf_dir, view)), view)
        if largest:
            edges = settle(largest_component(edges), view)
        return modularity_graph(edges, gamma) if lam is None else unit_graph(edges, lam)

    def cluster(self, g: WGraph, method: str = "two_way", o: Options = Options(), **more) -> Result:
        if method == "two_way":
            return two_way(g, o, **more)
        if method == "one_way":
            return two_way(g, o.but(uncoarsen=False), **more)
        if method in ("refined", "refined_up"):
            return refined(g, o.but(uncoarsen=method == "refined_up"), **more)
        if method == "components":
            return two_way(components_graph(g.edges), o)
        raise ValueError(f"unknown method {method}")

    def sql_cluster(self, view: str, name: str = "clusters", method: str = "two_way", gamma=1) -> DataFrame:
        """Clusters the edges (src, dst, w) of a temp view and publishes the result as another."""
        out = self.cluster(modularity_graph(self.spark.table(view), gamma), method).clusters
        out.createOrReplaceTempView(name)
        return out


__all__ = ["Engine", "Result", "iterate", "label_propagation", "layered_order", "local", "modularity", "recombine", "refined", "replace", "run_log", "two_way"]
