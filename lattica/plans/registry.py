"""Named queries over the given tables and their independent SQL.

Every step query runs the DataFrame path; engine runs use DataFrames on level 0 of
the larger views and the one-task kernel below the kernel limit.
"""

from __future__ import annotations

from fractions import Fraction

from pyspark.sql import functions as F

from ..operators import checks, engine, graph, kernel, levels, measures, moves, refine
from ..operators.options import ABLATIONS, DEFAULT_PHI, Options
from ..sources import drop, scratch_scope, settle
from ..sources.views import VIEWS, pairs
from ..streaming import activity
from . import oracle as sql

STEP = "lattice2d"
PHI75, PHI25 = Fraction(3, 4), Fraction(1, 4)
SIX = [(p.numerator, p.denominator) for p in DEFAULT_PHI]


def _edges(spark, d, view):
    return settle(graph.symmetrize(pairs(spark, d, view)), view)


def _g(spark, d, view=STEP):
    return graph.modularity_graph(_edges(spark, d, view))


def _mod(g, k=10):
    low = F.min("id").alias("cid")
    per = g.vertices.groupBy(F.pmod("id", F.lit(k)).alias("r")).agg(low)
    return g.vertices.select("id", F.pmod("id", F.lit(k)).alias("r")).join(per, "r").select("id", "cid")


def _state(g, k=10):
    return settle(moves.state_of(g, _mod(g, k)), "state")


def _dest(g, state):
    return settle(moves.destinations(g, state, moves.affinity(g.edges, state)), "dest")


def _level0(g, **more):
    """Level 0 on DataFrames; the levels below as they come, in one process only within the usual limit."""
    usual = Options(**more)
    return usual.but(kernel_limit=min(usual.kernel_limit, max(0, g.stored - 1)), state_limit=min(usual.state_limit, g.vertices.count() - 1))


def entry(spark, sf_dir):
    """Two-way clustering of part co-occurrence, level 0 on DataFrames."""
    g = _g(spark, sf_dir, "part_cooc")
    return engine.two_way(g, _level0(g)).clusters


def _graph_query(view):
    return lambda s, d: graph.symmetrize(pairs(s, d, view))


def _profile_query(view):
    return lambda s, d: graph.profile(graph.symmetrize(pairs(s, d, view)))


def components_labels(s, d):
    return graph.components(_edges(s, d, "page_nav"))


def largest_component(s, d):
    return graph.largest_component(_edges(s, d, "page_nav"))


def modularity_of_mod25(s, d):
    g = _g(s, d, "order_chain")
    return graph.lambda_cc(g, _mod(g, 25)).select("modularity")


def lambda_cc_of_mod10(s, d):
    g = _g(s, d)
    return graph.lambda_cc(g, _mod(g)).select(F.col("scaled").cast("long").alias("scaled"), "value")


def objective_presets(s, d):
    out = None
    for name, g in graph.presets(_edges(s, d, STEP)).items():
        row = graph.lambda_cc(g, _mod(g)).select(F.lit(name).alias("preset"), "value")
        out = row if out is None else out.unionByName(row)
    return out


def affinity_mod10(s, d):
    g = _g(s, d)
    return moves.affinity(g.edges, _state(g))


def affinity_salted_mod10(s, d):
    g = _g(s, d, "status_hub")
    return moves.affinity_salted(g.edges, _state(g))


def affinity_singletons(s, d):
    return moves.affinity_from_edges(_g(s, d).edges)


def _moved(g):
    """The table before and the states around a move of every seventh vertex into its right neighbour's cluster."""
    state = _state(g)
    to = g.vertices.select("id", F.when(F.pmod("id", F.lit(7)) == 0, F.pmod(F.col("id") + 1, F.lit(10))).otherwise(F.pmod("id", F.lit(10))).alias("r"))
    low = to.groupBy("r").agg(F.min("id").alias("cid"))
    return state, settle(moves.state_of(g, to.join(low, "r").select("id", "cid")), "state"), settle(moves.affinity(g.edges, state), "aff")


def affinity_patched(s, d):
    g = _g(s, d)
    old, new, aff = _moved(g)
    return moves.patched(aff, g.edges, old, new)


def affinity_recomputed(s, d):
    g = _g(s, d)
    old, new, aff = _moved(g)
    return moves.recomputed(aff, g.edges, old, new)


def best_destination_mod10(s, d):
    g = _g(s, d)
    return _dest(g, _state(g)).select("id", "c_new", "s_own", "s_new")


def new_singleton_cases(s, d):
    g = _g(s, d, "lattice8")
    return _dest(g, _state(g, 3)).where("c_new is null and s_new is not null").select("id", "s_own")


def _cands(phi):
    def run(s, d):
        g = _g(s, d)
        return moves.candidates(g, _dest(g, _state(g)), phi).select("id", "c_old", "c_new", "gain")

    return run


def _first_moves(g):
    state = settle(moves.singleton_state(g), "state")
    dest = settle(moves.destinations(g, state, moves.affinity_from_edges(g.edges)), "dest")
    return state, dest


def replay_filter_pass1(s, d):
    g = _g(s, d)
    _, dest = _first_moves(g)
    return moves.replay_filter(g, g.edges, settle(moves.candidates(g, dest, PHI75), "moves")).select("id", "c_new", "gain")


def mlh_pass1(s, d):
    g = _g(s, d)
    state, dest = _first_moves(g)
    return moves.min_label_filter(moves.candidates(g, dest, 0), state).select("id", "c_new", "gain")


def nosym_pass1(s, d):
    g = _g(s, d)
    return moves.candidates(g, _first_moves(g)[1], 0).select("id", "c_new", "gain")


def _local(n, view=STEP, **more):
    def run(s, d):
        g = _g(s, d, view)
        return moves.local_move(g, moves.singleton_state(g), Options(phi=DEFAULT_PHI[:n], **more), True)[0].select("id", "cid")

    return run


def contract_mod10(s, d):
    g = _g(s, d)
    return levels.contract(g, _mod(g)).edges


def contract_gathered(s, d):
    g = _g(s, d)
    return levels.contract(g, _mod(g), gather=True).edges


def contract_bounds(s, d):
    g = _g(s, d)
    return levels.contraction_bound(g, _mod(g))


def contract_weights(s, d):
    g = _g(s, d)
    return levels.contract(g, _mod(g)).vertices


def relabel_dense(s, d):
    g = _g(s, d)
    return levels.relabel_dense(_mod(g, 37))


def coarse_objective_constant(s, d):
    g = _g(s, d)
    return levels.level_constant(g, _mod(g)).select(F.col("constant").cast("long").alias("constant"))


def project_levels(s, d):
    g = _g(s, d)
    fine = settle(_mod(g, 100), "fine")
    coarse = fine.select("cid").distinct().select(F.col("cid").alias("id"), F.pmod("cid", F.lit(7)).alias("cid"))
    return levels.project(fine, coarse)


def downsample_levels(s, d):
    g = _g(s, d)
    return levels.downsample(settle(_mod(g, 100), "fine"), settle(_mod(g, 10), "coarse"))


def multilevel_ring_cliques(s, d):
    return engine.two_way(graph.unit_graph(_edges(s, d, "ring_cliques"), Fraction(1, 20))).clusters


def _run(view, method, **more):
    def run(s, d):
        g = _g(s, d, view)
        return engine.Engine(s).cluster(g, method, Options(**more)).clusters

    return run


def multilevel_on_frames(s, d):
    """The two-way engine with level 0 on DataFrames, all passes down and up."""
    g = _g(s, d)
    return engine.two_way(g, _level0(g)).clusters


def refined_on_frames(s, d):
    g = _g(s, d)
    return engine.refined(g, _level0(g, uncoarsen=False)).clusters


def _elig(g):
    return settle(refine.eligible(g, _blocks(g)), "eligible")


def _blocks(g):
    """Constraint clusters of 40 consecutive vertices."""
    return g.vertices.select("id", (F.col("id") - F.pmod("id", F.lit(40))).alias("cid"))


def refine_eligible(s, d):
    return _elig(_g(s, d, "lattice8")).select("id", "b", "inside", "ok")


def _choice(g):
    elig = _elig(g)
    return elig, settle(refine.chosen_edges(g, elig, 1), "choice")


def refine_choice(s, d):
    return _choice(_g(s, d, "lattice8"))[1]


def refine_oriented(s, d):
    return refine.oriented(_choice(_g(s, d, "lattice8"))[1], 1)


def refine_roots(s, d):
    return refine.pointer_jump(refine.oriented(_choice(_g(s, d, "lattice8"))[1], 1)).select("id", "root")


def refine_prefixes(s, d):
    g = _g(s, d, "lattice8")
    elig, choice = _choice(g)
    return refine.committed(refine.prefixes(g, refine.pointer_jump(refine.oriented(choice, 1)), elig))


def _strict(method):
    """The strict move over every mover; pairs up to the bound of the engine, prefix sums above."""

    def run(s, d):
        g = _g(s, d)
        m = settle(refine.movers(g, _state(g, 100)), "movers")
        few = method == "pairs" and m.count() <= Options().cap
        return (refine.strict_pairs if few else refine.strict_prefix)(g, m).select("id", "pos", "new", F.col("run").cast("long").alias("run"))

    return run


def refine_merge_scores(s, d):
    """Both scores of every recorded merge: none is negative where the second and third property hold."""
    g = _g(s, d, "lattice8")
    elig, choice = _choice(g)
    rows = settle(refine.prefixes(g, refine.pointer_jump(refine.oriented(choice, 1)), elig), "prefixes")
    return checks.merge_scores(g, _blocks(g), rows, settle(refine.committed(rows), "fine"))


def separation_violations(s, d):
    g = _g(s, d)
    return checks.violations_separation(g, _blocks(g))


def node_violations(s, d):
    g = _g(s, d)
    return checks.violations_node(g, _blocks(g))


def _fives(g):
    return g.vertices.select("id", (F.col("id") - F.pmod("id", F.lit(5))).alias("cid"))


def uniform_density_small(s, d):
    """Clusters of five neighbours, of three and of two that are none, at every size of the table."""
    g = _g(s, d)
    rest = F.pmod("id", F.lit(10))
    part = F.when(rest < 5, 0).otherwise(5 + F.pmod("id", F.lit(2)))
    return checks.violations_uniform_small(g, g.vertices.select("id", (F.col("id") - rest + part).alias("cid")), 6)


def subset_optimality_small(s, d):
    g = _g(s, d)
    return checks.violations_subset_small(g, _fives(g), 6)


def disconnected_pieces(s, d):
    g = _g(s, d)
    return checks.disconnected_clusters(g, g.vertices.select("id", F.pmod("id", F.lit(50)).alias("cid")))


def _rounds(view, scheme, n=11):
    def run(s, d):
        g = _g(s, d, view)
        out = None
        for i, r in enumerate(engine.iterate(g, Options(), n, scheme)):
            row = engine.modularity(g, r.clusters).select(F.lit(i).alias("round"), "modularity")
            out = row if out is None else out.unionByName(row)
        return out

    return run


def recombination(s, d):
    g = _g(s, d)
    a = settle(engine.two_way(g, Options()).clusters, "a")
    b = settle(engine.two_way(g, Options(phi=(PHI25,) * 4)).clusters, "b")
    return engine.recombine(g, a, b).clusters


#: Stand-ins for the ten groups of graphs of the experiments.
STAND_INS = ("lattice2d", "part_cooc", "order_chain", "lattice8", "order_part", "geo_tree", "status_hub", "part_supp", "cust_part", "page_nav")
#: Views of several components, of which the largest is clustered.
SPLIT = ("geo_tree", "page_nav", "doc_line", "page_host")
#: Stored edges up to which a graph is run in one task; larger ones get the status too_large.
TASK_EDGES = 1 << 19
#: Batches in a pass up to which a run is timed; colourings of dense graphs have more, and get the status too_many_batches.
MOST_BATCHES = 64


def _prepared(spark, d, view):
    edges = _edges(spark, d, view)
    return settle(graph.largest_component(edges), view) if view in SPLIT else edges


def _jobs(spark, d, views, jobs):
    """(graphs that fit a task, joined with the jobs (rows of names); graphs that do not)."""
    frames, large = None, []
    for v in views:
        e = _prepared(spark, d, v)
        if e.count() > TASK_EDGES:
            large.append(v)
            continue
        e = e.select(F.lit(v).alias("graph"), "src", "dst", "w")
        frames = e if frames is None else frames.unionByName(e)
    if frames is None:
        frames = spark.createDataFrame([], "graph string, src long, dst long, w long")
    return frames.join(F.broadcast(jobs)), large  # a copy of each graph of checked size for each of the few jobs


def _task_graph(pdf):
    import numpy as np

    ids, where = np.unique(np.concatenate([pdf.src.to_numpy(), pdf.dst.to_numpy()]), return_inverse=True)
    src, dst = where[: len(pdf)], where[len(pdf) :]
    w = pdf.w.to_numpy()
    return kernel.Graph(ids, np.bincount(src, w).astype(np.int64), src, dst, w, 1, int(w.sum()))


def _renumbered(g, repetition):
    """The graph under other vertex numbers, so that every tie falls anew; the first repetition keeps them."""
    import numpy as np

    if not repetition:
        return g
    new = np.random.default_rng(repetition).permutation(g.n)
    order = np.argsort(new)
    return kernel.Graph(np.arange(g.n), g.vw[order], new[g.src], new[g.dst], g.w, g.num, g.den)


RUNS = "graph string, variant string, repetition int, q double, seconds double, contract_seconds double, status string"


def run_table(spark, d, views=tuple(VIEWS), variants=None, repetitions=1):
    """(graph, variant, repetition, q, seconds, contract_seconds, status): one task for each run; a run that fails or does not fit says so."""
    variants = ABLATIONS if variants is None else variants
    import time

    import pandas as pd

    names = spark.createDataFrame([(n, r) for n in variants for r in range(repetitions)], "variant string, repetition int")
    jobs, large = _jobs(spark, d, views, names)

    def work(key, pdf):
        view, variant, repetition = key
        g, o, log = _renumbered(_task_graph(pdf), repetition), variants[variant], kernel.Log()
        start, status, q = time.perf_counter(), "ok", None
        if not isinstance(o, str) and o.batching_in_effect() and kernel.batch_of(g, o).max() >= MOST_BATCHES:
            return pd.DataFrame({"graph": [view], "variant": [variant], "repetition": [repetition], "q": [None], "seconds": [None], "contract_seconds": [None], "status": ["too_many_batches"]})
        try:
            if isinstance(o, str):
                c = kernel.sequential(g, o != "sequential_one_way", o == "sequential_refined", repetition)
            elif variant.startswith("refined"):
                c = kernel.refined(g, None, o.but(seed=repetition), log)
            else:
                c = kernel.two_way(g, o, log=log)
            q = kernel.modularity(g, c)
        except MemoryError:
            status = "out_of_memory"
        took = time.perf_counter() - start
        return pd.DataFrame({"graph": [view], "variant": [variant], "repetition": [repetition], "q": [q], "seconds": [took], "contract_seconds": [log.seconds.get("contract", 0.0)], "status": [status]})

    runs = jobs.groupBy("graph", "variant", "repetition").applyInPandas(work, RUNS)
    if not large:
        return runs
    return runs.unionByName(spark.createDataFrame([(v, n, 0, None, None, None, "too_large") for v in large for n in variants], RUNS))


def trace_table(spark, d, views=STAND_INS, rounds=11, memetic=(4, 6)):
    """(graph, variant, round, q, seconds): quality and running time after every round of the iterated engines, and the memetic run."""
    import time

    import pandas as pd

    names = ("constrained", "refined", "refined_up", "memetic")
    jobs, _ = _jobs(spark, d, views, spark.createDataFrame([(n,) for n in names], "variant string"))

    def work(key, pdf):
        view, variant = key
        g, rows, last, start = _task_graph(pdf), [], None, time.perf_counter()
        if variant == "memetic":
            rows.append((view, variant, 0, kernel.modularity(g, kernel.memetic(g, Options(), *memetic)), time.perf_counter() - start))
        else:
            for r in range(rounds):
                last = kernel.next_round(g, Options(), variant, last, r)
                rows.append((view, variant, r, kernel.modularity(g, last), time.perf_counter() - start))
        return pd.DataFrame(rows, columns=["graph", "variant", "round", "q", "seconds"])

    return jobs.groupBy("graph", "variant").applyInPandas(work, "graph string, variant string, round int, q double, seconds double")


BASELINES = {
    "sequential_two_way": "sequential_two_way",
    "sequential_one_way": "sequential_one_way",
    "sequential_refined": "sequential_refined",
    "batch_degree": Options(symmetry="batch", batching="degree", prune=True, gather=True),
    "batch_color1": Options(symmetry="batch", batching="color1"),
    "batch_color2": Options(symmetry="batch", batching="color2"),
    "batch_partition": Options(symmetry="batch", batching="partition"),
    "async_batches": Options(symmetry="async_batches", batches=16, uncoarsen=False),
    "min_label_gathered": Options(symmetry="async_min_label", mlh_passes=4, batches=16, phi=(Fraction(0),) * 8, gather=True, uncoarsen=False),
    "refined_racy": Options(refine_mode="racy", uncoarsen=False),
    "refined_greedy": Options(refine_mode="greedy", uncoarsen=False),
    "refined_forest": Options(uncoarsen=False),
    "refined_up": Options(),
    "two_way": Options(),
}


def ablation_report(s, d):
    runs = settle(run_table(s, d), "runs")
    return measures.mean_modularity_delta(runs, "default").join(measures.geomean_ratio(runs, "default"), "variant")


def baseline_report(s, d):
    runs = settle(run_table(s, d, variants=BASELINES), "runs")
    return measures.mean_modularity_delta(runs, "two_way", 2.0).join(measures.geomean_ratio(runs, "two_way"), "variant")


def ablation_cube(s, d):
    return measures.ablation_cube(run_table(s, d, variants={k: ABLATIONS[k] for k in ("default", "one_way")})).select("graph", "variant", "q")


def repetition_report(s, d):
    """Median time and quality of 21 repetitions of the default engine, and how far the quality strays."""
    return measures.repetition_summary(run_table(s, d, variants={"default": Options()}, repetitions=21))


def contraction_report(s, d):
    """By variant: contraction's mean and largest share of the run, and its time over the default's."""
    runs = settle(run_table(s, d, variants={k: ABLATIONS[k] for k in ("default", "gathered")}).where("status = 'ok'"), "runs")
    share = F.col("contract_seconds") / F.col("seconds")
    ratio = measures.geomean_ratio(runs.withColumn("seconds", F.col("contract_seconds")), "default")
    return runs.groupBy("variant").agg(F.avg(share).alias("share"), F.max(share).alias("largest_share")).join(ratio, "variant")


def iteration_trace(s, d):
    return trace_table(s, d)


def memetic_vs_iterated(s, d):
    """By iterated engine: graphs on which its last round reaches or beats the memetic run, and the mean difference."""
    runs = settle(trace_table(s, d), "runs")
    last = runs.groupBy("graph", "variant").agg(F.max_by("q", "round").alias("q"))
    out = None
    for name in ("constrained", "refined", "refined_up"):
        row = measures.wins(last, name, "memetic").select(F.lit(name).alias("variant"), "wins", "graphs")
        out = row if out is None else out.unionByName(row)
    base = last.where("variant = 'memetic'").select("graph", F.col("q").alias("q0"))
    delta = last.join(base, "graph").groupBy("variant").agg(F.avg(F.col("q") - F.col("q0")).alias("delta"))
    return out.join(delta, "variant")


def layered_order(s, d):
    g = _g(s, d, "page_nav")
    return engine.layered_order(g, (Fraction(1, 2), 1, 2))


def label_propagation(s, d):
    return engine.label_propagation(_edges(s, d, "page_nav"), Options(phi=(Fraction(0),) * 3)).clusters


def connected_components_objective(s, d):
    return engine.two_way(graph.components_graph(_edges(s, d, "page_host"))).clusters


def cluster_top10(s, d):
    g = _g(s, d)
    return _mod(g, 37).groupBy("cid").agg(F.count("*").alias("size")).orderBy(F.desc("size"), "cid").limit(10)


def cluster_rollup(s, d):
    g = _g(s, d)
    rows = _mod(g, 10).withColumn("half", F.pmod("cid", F.lit(2)))
    return rows.rollup("half", "cid").agg(F.count("*").alias("size"))


def cluster_diff(s, d):
    g = _g(s, d)
    return _mod(g, 10).exceptAll(_mod(g, 20))


def pair_agreement_ari(s, d):
    g = _g(s, d)
    return measures.ari(_mod(g, 10), _mod(g, 15))


def pair_agreement_nmi(s, d):
    g = _g(s, d)
    return measures.nmi(_mod(g, 10), _mod(g, 15))


def stream_edges_windowed(s, d):
    from ..sources import read_table

    return activity(read_table(s, d, "events", "event_id", "ts", "user_id")).select(F.unix_timestamp("window_start").alias("start"), "user_id", "n")


def batching_color1_conflicts(s, d):
    e = _edges(s, d, STEP)
    c = settle(moves.coloured(e), "colours")
    a, b = (c.select(F.col("id").alias(k), F.col("colour").alias(f"c_{k}")) for k in ("src", "dst"))
    return e.join(a, "src").join(b, "dst").agg(F.count_if(F.col("c_src") == F.col("c_dst")).alias("conflicts"))


def degree_buckets(s, d):
    return graph.degree_buckets(_edges(s, d, "status_hub")).groupBy("bucket").agg(F.count("*").alias("n"))


def order_before_event(s, d):
    """Every event with its user's last order (users stand for customers of the same number) at or before it."""
    from ..operators.joins import asof_join
    from ..sources import read_table

    events = read_table(s, d, "events", "event_id", "ts", "user_id").select("event_id", F.col("user_id").alias("k"), F.col("ts").cast("timestamp_ntz").alias("ts"))
    orders = read_table(s, d, "orders", "o_orderkey", "o_custkey", "o_orderdate").select(F.col("o_custkey").alias("k"), F.col("o_orderdate").cast("timestamp_ntz").alias("ts"), "o_orderkey")
    orders = orders.groupBy("k", "ts").agg(F.max("o_orderkey").alias("o_orderkey"))
    return asof_join(events, orders, "k", "ts", "o_orderkey").select("event_id", "o_orderkey")


def users_within_gap(s, d):
    """(a, b, n): how often user b acts within ten seconds after user a."""
    from ..operators.joins import gap_join
    from ..sources import read_table

    e = read_table(s, d, "events", "event_id", "ts", "user_id").select("event_id", "user_id", F.unix_millis(F.col("ts").cast("timestamp")).alias("t"))
    left = e.select(F.col("event_id").alias("ea"), F.col("user_id").alias("a"), F.col("t").alias("ta"))
    right = e.select(F.col("event_id").alias("eb"), F.col("user_id").alias("b"), F.col("t").alias("tb"))
    return gap_join(left, right, "ta", "tb", 10_000).where("ea <> eb").groupBy("a", "b").agg(F.count("*").alias("n"))


def batched_color1(s, d):
    """One pass in colour batches on DataFrames."""
    g = _g(s, d)
    return moves.local_move(g, moves.singleton_state(g), Options(phi=(Fraction(0),), symmetry="batch", batching="color1"), True)[0].select("id", "cid")


def _passes(view=STEP, **more):
    def run(s, d):
        g = _g(s, d, view)
        return moves.local_move(g, moves.singleton_state(g), Options(**more), True)[0].select("id", "cid")

    return run


def _tidy(f):
    """The query with its result written where it left scratch behind, and that scratch gone."""

    def run(s, d):
        with scratch_scope() as made:
            out = f(s, d)
            if not made:
                return out
            out = settle(out, "result")
        drop(*[x for x in made if x is not out])
        return out

    run.__name__ = getattr(f, "__name__", "query")
    run.__doc__ = f.__doc__
    return run


def queries():
    return {name: _tidy(f) for name, f in _queries().items()}


def _queries():
    out = {}
    for v in VIEWS:
        out[f"graph_{v}"] = _graph_query(v)
        out[f"profile_{v}"] = _profile_query(v)
    for f in (components_labels, largest_component, modularity_of_mod25, lambda_cc_of_mod10, objective_presets, affinity_mod10, affinity_salted_mod10, affinity_singletons, affinity_patched, affinity_recomputed, best_destination_mod10, new_singleton_cases, replay_filter_pass1, mlh_pass1, nosym_pass1, contract_mod10, contract_gathered, contract_bounds, contract_weights, relabel_dense, coarse_objective_constant, project_levels, downsample_levels, multilevel_ring_cliques, multilevel_on_frames, refined_on_frames, refine_eligible, refine_choice, refine_oriented, refine_roots, refine_prefixes, refine_merge_scores, separation_violations, node_violations, uniform_density_small, subset_optimality_small, disconnected_pieces, recombination, ablation_report, baseline_report, ablation_cube, repetition_report, contraction_report, iteration_trace, memetic_vs_iterated, layered_order, label_propagation, connected_components_objective, cluster_top10, cluster_rollup, cluster_diff, pair_agreement_ari, pair_agreement_nmi, stream_edges_windowed, batching_color1_conflicts, degree_buckets, order_before_event, users_within_gap, batched_color1):
        out[f.__name__] = f
    out |= {
        "candidates_phi75": _cands(PHI75),
        "candidates_phi25": _cands(PHI25),
        "local_move_1pass": _local(1),
        "local_move_6pass": _local(6),
        "local_move_6pass_fused": _local(6, kernel="fused"),
        "strict_move_pairs": _strict("pairs"),
        "strict_move_prefix": _strict("prefix"),
        "strict_move_all": _strict("prefix"),
        "pruned_passes": _passes(phi=(PHI75,) * 3, prune=True),
        "batched_degree": _passes("status_hub", phi=(Fraction(0),), symmetry="batch", batching="degree"),
        "batched_degree_pruned": _passes(phi=(PHI25,) * 2, symmetry="batch", batching="degree", batches=2, prune=True),
        "batched_partition": _passes(phi=(PHI25,) * 2, symmetry="batch", batching="partition", batches=3),
        "async_passes": _passes("page_nav", phi=(Fraction(0),) * 2, symmetry="async_batches", batches=4),
        "multilevel_lattice2d": _run(STEP, "two_way"),
        "multilevel_cust_part": _run("cust_part", "two_way"),
        "one_way_cust_part": _run("cust_part", "one_way"),
        "refined": _run("cust_part", "refined"),
        "refined_up": _run("cust_part", "refined_up"),
        "constrained_iteration": _rounds(STEP, "constrained"),
        "seeded_iteration": _rounds(STEP, "seeded"),
        "refined_iterated": _rounds(STEP, "refined"),
        "refined_up_iterated": _rounds(STEP, "refined_up"),
    }
    return out


def oracle_sql():
    b, c, step, base = sql.base, sql.clusters, sql.step, sql.base
    out = {f"graph_{v}": sql.graph(v) for v in VIEWS} | {f"profile_{v}": sql.profile(v) for v in VIEWS}
    nav = sql.edges("page_nav")
    comp = f"with recursive {nav}, r(id, x) as (select src, src from edges union select e.dst, r.x from r join edges e on e.src = r.id), cc as (select id, min(x) as comp from r group by id)"
    out["components_labels"] = f"{comp} select id, comp from cc"
    out["largest_component"] = f"{comp}, best as (select comp from cc group by comp order by count(*) desc, comp limit 1) select src, dst, w from edges join cc on cc.id = src join best using (comp)"
    score = "(select sum(w) from edges join c x on x.id = src join c y on y.id = dst where x.cid = y.cid)"
    weights = "t as (select cid, sum(vw) as t, sum(vw * vw) as sq from c join verts using (id) group by cid)"
    scaled = f"(lam.den * coalesce({score}, 0) - lam.num * (select sum(t * t) - sum(sq) from t))"
    out["modularity_of_mod25"] = step("order_chain", f"select ({scaled} - lam.num * (select sum(sq) from t))::double / (lam.den::double * (select sum(w) from edges)) as modularity from lam", c("id % 25"), weights)
    out["lambda_cc_of_mod10"] = step(STEP, f"select {scaled}::bigint as scaled, {scaled}::double / lam.den as value from lam", c("id % 10"), weights)
    pre = [("modularity", "d.n", 0, "1.0 / (select sum(w) from edges)"), ("modularity_2", "d.n", 0, "2.0 / (select sum(w) from edges)"), ("constant_potts", "1", 0, "0.05"), ("absolute_potts", "1", 1, "1.0"), ("label_propagation", "1", 0, "0.0"), ("components", "1", 0, "1e-9"), ("sparsest_cut", "1", 0, "0.01"), ("cluster_deletion", "1", 0, "(select count(*) from edges)::double / ((select count(*) from edges) + 1)")]
    inside = "(select count(*) from edges where src % 10 = dst % 10)"
    rows = " union all ".join(f"select '{n}' as preset, {'3 * ' if scale else ''}{inside} - {lam} * (select sum(t * t - sq) from (select id % 10 as k, sum({vw}) as t, sum({vw} * {vw}) as sq from d group by 1)) as value" for n, vw, scale, lam in pre)
    out["objective_presets"] = f"with {sql.edges(STEP)}, d as (select src as id, count(*)::double as n from edges group by src) select preset, value::double as value from ({rows})"
    pick = sql.choose("p", "c")
    out["affinity_mod10"] = step(STEP, "select id, cid, k from pa", c("id % 10"), pick)
    out["affinity_salted_mod10"] = step("status_hub", "select e.dst as id, c.cid, sum(e.w)::bigint as k from edges e join c on c.id = e.src group by 1, 2", c("id % 10"))
    out["affinity_singletons"] = step(STEP, "select src as id, dst as cid, w as k from edges")
    moved = c("case when id % 7 = 0 then (id + 1) % 10 else id % 10 end")
    out["affinity_patched"] = out["affinity_recomputed"] = step(STEP, "select id, cid, k from pa", moved, pick)
    out["best_destination_mod10"] = step(STEP, "select id, c_new, s_own::bigint as s_own, s_new::bigint as s_new from pd", c("id % 10"), pick)
    out["new_singleton_cases"] = step("lattice8", "select id, s_own::bigint as s_own from pd where c_new is null and s_new is not null", c("id % 3"), pick)
    for name, (x, y) in (("candidates_phi75", (3, 4)), ("candidates_phi25", (1, 4))):
        out[name] = step(STEP, "select id, c_old, c_new, gain from pm", c("id % 10"), pick, sql.candidates("p", x, y))
    first = (c("id"), pick)
    out["replay_filter_pass1"] = step(STEP, "select id, c_new, gain from pf", *first, sql.candidates("p", 3, 4), sql.replay("p"))
    out["nosym_pass1"] = step(STEP, "select id, c_new, gain from pm", *first, sql.candidates("p", 0, 1))
    out["mlh_pass1"] = step(STEP, "select id, c_new, gain from pm where gain > 0 and not c_new > c_old", *first, sql.candidates("p", 0, 1))
    out["local_move_1pass"] = sql.passes(STEP, SIX[:1])
    out["local_move_6pass"] = out["local_move_6pass_fused"] = sql.passes(STEP, SIX)
    cut = "select x.cid as src, y.cid as dst, sum(w)::bigint as w from edges join c x on x.id = src join c y on y.id = dst where x.cid <> y.cid group by 1, 2"
    out["contract_mod10"] = out["contract_gathered"] = step(STEP, cut, c("id % 10"))
    out["contract_bounds"] = step(STEP, "select cid, count(*) as bound from c join edges on src = id group by cid", c("id % 10"))
    out["contract_weights"] = step(STEP, "select cid as id, sum(vw)::bigint as vw from c join verts using (id) group by cid", c("id % 10"))
    out["relabel_dense"] = step(STEP, "select id, dense_rank() over (order by cid) - 1 as cid from c", c("id % 37"))
    out["coarse_objective_constant"] = step(STEP, f"select {scaled}::bigint as constant from lam", c("id % 10"), weights)
    out["project_levels"] = step(STEP, "select id, cid % 7 as cid from c", c("id % 100"))
    out["downsample_levels"] = step(STEP, "select distinct f.cid as id, c.cid from f join c using (id)", c("id % 10"), c("id % 100", "f"))
    out["multilevel_ring_cliques"] = "select p_partkey as id, p_partkey - p_partkey % 10 as cid from part"
    ref = _refine_sql()
    out |= ref
    out["separation_violations"] = step(STEP, "select a.cid as a, b.cid as b, (any_value(lam.den) * sum(w) - any_value(lam.num * ta.t * tb.t))::bigint as score from edges join c a on a.id = src join c b on b.id = dst join t ta on ta.cid = a.cid join t tb on tb.cid = b.cid, lam where a.cid < b.cid group by 1, 2 having any_value(lam.den) * sum(w) - any_value(lam.num * ta.t * tb.t) > 0", c("id // 40"), weights)
    out["node_violations"] = step(STEP, "select id, s_own::bigint as s_own, greatest(coalesce(s_new, 0), 0)::bigint as s_best from pd where greatest(coalesce(s_new, 0), 0) > s_own", c("id // 40"), pick)
    out["disconnected_pieces"] = f"with recursive {sql.edges(STEP)}, v as (select distinct src as id from edges), inn as (select src, dst from edges where src % 50 = dst % 50), r(id, x) as (select id, id from v union select i.dst, r.x from r join inn i on i.src = r.id), cc as (select id, min(x) as comp from r group by id), z as (select id % 50 as k, min(id) as cid, count(distinct comp) as pieces from cc group by 1) select cid, pieces from z where pieces > 1"
    out["connected_components_objective"] = f"with recursive {sql.edges('page_host')}, r(id, x) as (select src, src from edges union select e.dst, r.x from r join edges e on e.src = r.id) select id, min(x) as cid from r group by id"
    out["cluster_top10"] = step(STEP, "select cid, count(*) as size from c group by cid order by size desc, cid limit 10", c("id % 37"))
    out["cluster_rollup"] = step(STEP, "select cid % 2 as half, cid, count(*) as size from c group by rollup (cid % 2, cid)", c("id % 10"))
    out["cluster_diff"] = step(STEP, "select id, cid from c except all select id, cid from f", c("id % 10"), c("id % 20", "f"))
    j = "j as (select c.cid as x, f.cid as y from c join f using (id)), xy as (select sum(k * (k - 1) / 2.0) as p from (select count(*) as k from j group by x, y)), xx as (select sum(k * (k - 1) / 2.0) as p from (select count(*) as k from j group by x)), yy as (select sum(k * (k - 1) / 2.0) as p from (select count(*) as k from j group by y)), nn as (select count(*) as n from j)"
    out["pair_agreement_ari"] = step(STEP, "select n, xy.p::double as together, xx.p::double as in_a, yy.p::double as in_b, ((xy.p - xx.p * yy.p / (n * (n - 1) / 2.0)) / ((xx.p + yy.p) / 2 - xx.p * yy.p / (n * (n - 1) / 2.0)))::double as ari from xy, xx, yy, nn", c("id % 10"), c("id % 15", "f"), j)
    ent = "j as (select c.cid as x, f.cid as y from c join f using (id)), n as (select count(*)::double as n from j), k as (select x, y, count(*)::double as k, sum(count(*)) over (partition by x)::double as kx, sum(count(*)) over (partition by y)::double as ky from j group by x, y), mi as (select sum(k / n * ln(k * n / (kx * ky))) as v from k, n), hx as (select -sum(q / n * ln(q / n)) as v from (select x, count(*)::double as q from j group by x), n), hy as (select -sum(q / n * ln(q / n)) as v from (select y, count(*)::double as q from j group by y), n)"
    out["pair_agreement_nmi"] = step(STEP, "select 2 * mi.v / (hx.v + hy.v) as nmi from mi, hx, hy", c("id % 10"), c("id % 15", "f"), ent)
    out["stream_edges_windowed"] = "select epoch(date_trunc('hour', ts))::bigint as start, user_id, count(*) as n from events group by 1, 2"
    degree = lambda n: f"least((length(bin(vw)) - 1) // 2, {n - 1})"
    hashed = lambda n: f"{sql.hash_sql('id', '0')} % {n}"
    out["pruned_passes"] = sql.batch_passes(STEP, (3, 4), 3, "0", 1, replayed=True, prune=True)
    out["batched_degree"] = sql.batch_passes("status_hub", (0, 1), 1, degree(4), 4)
    out["batched_degree_pruned"] = sql.batch_passes(STEP, (1, 4), 2, degree(2), 2, prune=True)
    out["batched_partition"] = sql.batch_passes(STEP, (1, 4), 2, hashed(3), 3)
    out["async_passes"] = sql.batch_passes("page_nav", (0, 1), 2, hashed(4), 4)
    few = c("id - id % 10 + case when id % 10 < 5 then 0 else 5 + id % 2 end")
    cut_x = "cut as (select a.cid, a.mask, sum(e.w) as cut from edges e join mem a on a.id = e.src and a.x = 1 join mem b on b.id = e.dst and b.x = 0 and b.cid = a.cid and b.mask = a.mask group by 1, 2)"
    out["uniform_density_small"] = step(STEP, "select cid, mask::bigint as mask, (den * coalesce(cut, 0) - num * wx * (w - wx))::bigint as score from wts left join cut using (cid, mask), lam where den * coalesce(cut, 0) - num * wx * (w - wx) < 0", few, sql.SUBSETS, cut_x)
    out_x = "tt as (select c.cid, sum(vw) as t from c join verts using (id) group by c.cid), ends as (select a.cid, a.mask, o.cid as other, sum(e.w) as k from edges e join mem a on a.id = e.src and a.x = 1 join c o on o.id = e.dst left join mem b on b.id = e.dst and b.cid = a.cid and b.mask = a.mask where coalesce(b.x, 0) = 0 group by 1, 2, 3)"
    gain = "(den * n.k - num * wx * tt.t) - (den * coalesce(h.k, 0) - num * wx * (w - wx))"
    out["subset_optimality_small"] = step(STEP, f"select n.cid, n.mask::bigint as mask, n.other, ({gain})::bigint as gain from ends n join wts using (cid, mask) join tt on tt.cid = n.other left join ends h on h.cid = n.cid and h.mask = n.mask and h.other = n.cid, lam where n.other <> n.cid and {gain} > 0", c("id - id % 5"), sql.SUBSETS, out_x)
    out["batching_color1_conflicts"] = "select 0::bigint as conflicts"
    out["order_before_event"] = "with o as (select o_custkey as k, o_orderdate::timestamp as ts, max(o_orderkey) as o_orderkey from orders group by 1, 2) select e.event_id, o.o_orderkey from events e asof left join o on e.user_id = o.k and e.ts::timestamp >= o.ts"
    out["users_within_gap"] = "with e as (select event_id, user_id, epoch_ms(ts::timestamp) as t from events) select x.user_id as a, y.user_id as b, count(*) as n from e x join e y on y.t between x.t and x.t + 10000 and x.event_id <> y.event_id group by 1, 2"
    out["degree_buckets"] = step("status_hub", "select case when vw < 8 then 'low' when vw < 256 then 'medium' else 'high' end as bucket, count(*) as n from verts group by 1")
    return out


def _refine_sql():
    """Refinement on lattice8 in blocks of 40, and the strict move from clusters mod 100."""
    h = sql.hash_sql
    elig = "c as materialized (select id, vw, id - id % 40 as b, sum(vw) over (partition by id // 40) as wb from verts), e0 as materialized (select src as id, sum(w) as inside from edges where src // 40 = dst // 40 group by src), el as materialized (select c.*, coalesce(inside, 0)::bigint as inside, lam.den * coalesce(inside, 0) - lam.num * c.vw * (wb - c.vw) >= 0 as ok from c left join e0 using (id), lam)"
    cand = "x as (select e.src as id, e.dst as u from edges e join el a on a.id = e.src and a.ok join el b on b.id = e.dst and b.ok, lam where a.b = b.b and lam.den * e.w - lam.num * a.vw * b.vw >= 0 union all select id, id from el where ok)"
    pick = f"ch as materialized (select el.id, coalesce(y.u, el.id) as choice from el left join (select id, u from x qualify row_number() over (partition by id order by {h('id', 'u', 1)}, u) = 1) y using (id))"
    f0 = f"f0 as materialized (select id, choice, {h('id', '0', 2)} as f from ch)"
    p0 = "p0 as materialized (select a.id, a.choice, a.f, case when b.f < a.f or (b.f = a.f and b.id < a.id) then b.id else a.id end as parent from f0 a join f0 b on b.id = a.choice)"
    f1 = "f1 as materialized (select id, choice, case when parent = id and id not in (select parent from p0 where parent <> id) then 2 * 2147483648 - f else f end as f from p0)"
    p1 = "p1 as materialized (select a.id, a.f, case when b.f < a.f or (b.f = a.f and b.id < a.id) then b.id else a.id end as parent from f1 a join f1 b on b.id = a.choice)"
    rec = "up(id, hop) as (select id, parent from p1 union select up.id, p1.parent from up join p1 on p1.id = up.hop), rt as (select up.id, up.hop as root from up join p1 on p1.id = up.hop where p1.parent = p1.id)"
    tree = "tr as materialized (select rt.id, rt.root, p1.f, el.* exclude (id) from rt join p1 using (id) join el using (id)), ea as (select e.dst as id, sum(e.w) as earlier from edges e join tr a on a.id = e.src join tr b on b.id = e.dst where a.root = b.root and (a.f < b.f or (a.f = b.f and a.id < b.id)) group by e.dst), pf as (select tr.*, coalesce(earlier, 0) as earlier, row_number() over w as pos, coalesce(sum(vw) over (w rows between unbounded preceding and 1 preceding), 0) as wt, coalesce(sum(inside - 2 * coalesce(earlier, 0)) over (w rows between unbounded preceding and 1 preceding), 0) as cut from tr left join ea using (id) window w as (partition by root order by f, id)), gd as (select *, lam.den * earlier - lam.num * vw * wt as joined, lam.den * cut - lam.num * wt * (wb - wt) as rest, pos = 1 or (lam.den * earlier - lam.num * vw * wt >= 0 and lam.den * cut - lam.num * wt * (wb - wt) >= 0) as good from pf, lam), fl as (select id, pos, joined, rest, case when ok and max((not good)::int) over (partition by root order by f, id) = 0 then root else -1 - id end as raw from gd)"
    base = sql.base("lattice8")
    chain = [base, elig, cand, pick, f0, p0, f1, p1]
    out = {
        "refine_eligible": f"with {base}, {elig} select id, b, inside, ok from el",
        "refine_choice": f"with {', '.join(chain[:4])} select id, choice from ch",
        "refine_oriented": f"with {', '.join(chain)} select id, parent, f from p1",
        "refine_roots": f"with recursive {', '.join(chain)}, {rec} select id, root from rt",
        "refine_prefixes": f"with recursive {', '.join(chain)}, {rec}, {tree} select id, min(id) over (partition by raw) as cid from fl",
        "refine_merge_scores": f"with recursive {', '.join(chain)}, {rec}, {tree}, lb as (select *, min(id) over (partition by raw) as cid, count(*) over (partition by raw) as n from fl) select id, cid, joined::bigint as joined, rest::bigint as rest from lb where n > 1 and pos > 1",
    }
    mv = f"mv as materialized (select id, vw, cid as old, case when s_new is null or s_new < 0 then null else c_new end as new, greatest(coalesce(s_new, 0), 0) - s_own as gain, {h('id', '0', 5)} as h from pd where greatest(coalesce(s_new, 0), 0) > s_own), mp as materialized (select *, row_number() over (order by h, id) as pos from mv)"
    ch = "cg as (select v.id, sum((lam.den * coalesce(e.w, 0) - lam.num * u.vw * v.vw) * (case when u.old = v.old then 1 when u.old = v.new then -1 else 0 end + case when u.new = v.old then -1 when u.new = v.new then 1 else 0 end)) as change from mp u join mp v on u.pos < v.pos left join edges e on e.src = u.id and e.dst = v.id, lam group by v.id)"
    text = sql.step(STEP, "select id, pos, new, sum(gain + coalesce(change, 0)) over (order by pos)::bigint as run from mp left join cg using (id)", sql.clusters("id % 100"), sql.choose("p", "c"), mv, ch)
    out["strict_move_pairs"] = out["strict_move_prefix"] = out["strict_move_all"] = text
    return out
