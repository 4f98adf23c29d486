"""The engines on small graphs with known answers, brute force and each other."""

import itertools
from fractions import Fraction

import numpy as np
import pytest
from pyspark.sql import functions as F

from lattica import sources
from lattica.functions import portable_hash, portable_hash_np
from lattica.operators import blocks, checks, engine, graph, kernel, levels, measures, moves, refine
from lattica.operators.options import ABLATIONS, Options

TRIANGLES = [(0, 1), (0, 2), (1, 2), (2, 3), (3, 4), (3, 5), (4, 5)]


def small(pairs, vw=None, lam=None, w=None):
    e = np.array(pairs)
    ids = np.unique(e)
    src, dst = np.searchsorted(ids, np.concatenate([e, e[:, ::-1]])).T
    weight = np.ones(len(src), np.int64) if w is None else np.concatenate([w, w])
    deg = np.bincount(src, weight).astype(np.int64) if vw is None else np.array(vw)
    lam = Fraction(1, int(weight.sum())) if lam is None else Fraction(lam)
    return kernel.Graph(ids, deg, src, dst, weight, lam.numerator, lam.denominator)


def frames(spark, pairs, **more):
    df = spark.createDataFrame(pairs, "a long, b long")
    return graph.modularity_graph(graph.symmetrize(df), **more)


def as_dict(df):
    return {r.id: r.cid for r in df.collect()}


def random_graph(n, seed, p=0.4):
    rng = np.random.default_rng(seed)
    pairs = [x for x in itertools.combinations(range(n), 2) if rng.random() < p]
    pairs += [(i, i + 1) for i in range(n - 1) if (i, i + 1) not in pairs]
    return pairs, rng.integers(1, 4, len(pairs))


def partitions(n):
    def grow(c, k):
        if len(c) == n:
            yield np.array(c)
            return
        for x in range(k + 1):
            yield from grow([*c, x], max(k, x + 1))

    yield from grow([0], 1)


def test_two_triangles(spark):
    g = small(TRIANGLES)
    c = kernel.two_way(g, Options())
    assert c.tolist() == [0, 0, 0, 3, 3, 3]
    assert kernel.modularity(g, c) == pytest.approx(5 / 14)
    assert kernel.objective(g, c) / g.den == pytest.approx(52 / 7)
    f = frames(spark, TRIANGLES)
    row = graph.lambda_cc(f, spark.createDataFrame([(i, i // 3) for i in range(6)], "id long, cid long")).first()
    assert row.modularity == pytest.approx(5 / 14) and row.value == pytest.approx(52 / 7)


def test_hash_parity(spark):
    rows = spark.range(200).selectExpr("id as v", "id * 7919 as u").select("v", "u", portable_hash("v", "u", 5).alias("h")).collect()
    assert [r.h for r in rows] == portable_hash_np([r.v for r in rows], [r.u for r in rows], 5).tolist()


@pytest.mark.parametrize("seed", range(6))
def test_near_the_optimum(seed):
    pairs, w = random_graph(7, seed)
    g = small(pairs, w=w)
    best = max(kernel.objective(g, kernel.canonical(c)) for c in partitions(g.n))
    for run in (kernel.two_way(g, Options()), kernel.refined(g, None, Options()), kernel.memetic(g, Options(), 3, 3)):
        assert kernel.objective(g, run) <= best
    assert kernel.modularity(g, kernel.memetic(g, Options(), 3, 3)) >= 0.75 * max(0, best - g.num * int((g.vw**2).sum())) / (g.den * int(g.w.sum()))


def test_filter_cases():
    # a swap: two adjacent vertices that each prefer the other's cluster; the filter keeps exactly one
    g = small([(0, 1)], vw=[1, 1], lam=0)
    c, dest, gain = np.array([0, 1]), np.array([1, 0]), np.array([1, 1])
    assert kernel.replay(g, c, dest, gain, np.ones(2, bool), (1, 10)).sum() == 1
    # fresh singletons never meet
    assert kernel.multiple(np.array([0]), np.array([-1]), np.array([0]), np.array([-1])).tolist() == [1]
    # leaving one cluster for another together
    assert kernel.multiple(np.array([0]), np.array([1]), np.array([0]), np.array([1])).tolist() == [2]


@pytest.mark.parametrize("seed", range(8))
def test_strict_move(seed):
    pairs, w = random_graph(14, seed)
    g = small(pairs, w=w)
    c = kernel.canonical(np.random.default_rng(seed).integers(0, 5, g.n))
    a = kernel.strict_move(g, c, Options())
    b = kernel.strict_move(g, c, Options(strict_method="prefix"))
    assert (a == b).all()
    d, s, own = kernel.choose(g, c, kernel.totals(g, c), kernel.affinity(g, c))
    optimal = (np.maximum(np.where(d == -2, 0, s), 0) <= own).all()
    assert kernel.objective(g, a) > kernel.objective(g, c) or optimal


@pytest.mark.parametrize("seed", range(12))
def test_refinement_reaches_what_the_sequential_one_does(seed):
    rng = np.random.default_rng(seed)
    n = 4
    pairs, w = random_graph(n, seed, 0.6)
    g = small(pairs, w=w, vw=rng.integers(1, 3, n), lam=Fraction(int(rng.integers(1, 6)), 8))
    b = kernel.canonical(rng.integers(0, 2, n))
    wb, inside, s = kernel.totals(g, b), kernel.inside_weight(g, b), g.signed()
    ok = g.den * inside - g.num * g.vw * (wb[b] - g.vw) >= 0
    options = [[v] + [int(g.dst[e]) for e in np.flatnonzero(g.src == v) if ok[v] and ok[g.dst[e]] and b[g.dst[e]] == b[v] and s[e] >= 0] for v in range(n)]
    forest = set()
    for choice in itertools.product(*options):
        for order in itertools.permutations(range(n)):
            parent, f = kernel.oriented(g, np.array(choice), 0, np.array(order))
            forest.add(tuple(kernel.commit(g, b, ok, parent, f)))
    reach = set()

    def visit(c, size, order):
        if not order:
            reach.add(tuple(kernel.canonical(np.array(c))))
            return
        v, rest = order[0], order[1:]
        visit(c, size, rest)
        if sum(x == c[v] for x in c) > 1 or not ok[v]:
            return
        for x in set(c):
            members = [u for u in range(n) if c[u] == x]
            if x == c[v] or b[members[0]] != b[v]:
                continue
            k = sum(int(g.w[e]) for e in np.flatnonzero(g.src == v) if c[g.dst[e]] == x)
            weight = int(g.vw[members].sum())
            cut = sum(int(g.w[e]) for e in range(len(g.src)) if c[g.src[e]] == x and c[g.dst[e]] != x and b[g.dst[e]] == b[v])
            if k and g.den * k - g.num * int(g.vw[v]) * weight >= 0 and g.den * cut - g.num * weight * (int(wb[b[v]]) - weight) >= 0:
                new = list(c)
                new[v] = x
                visit(new, size, rest)

    for order in itertools.permutations(range(n)):
        visit(list(range(n)), None, list(order))
    assert forest == reach


def test_guarantees_of_the_refined_engine():
    pairs, w = random_graph(40, 3, 0.15)
    g = small(pairs, w=w)
    record = []
    c = kernel.refined(g, None, Options(uncoarsen=False), record=record)
    t = kernel.totals(g, c)
    reps = np.unique(c)
    for x, y in itertools.combinations(reps, 2):
        between = int(g.w[(c[g.src] == x) & (c[g.dst] == y)].sum())
        assert g.den * between - g.num * int(t[x]) * int(t[y]) <= 0
    assert checks.certificate(g, record) == []


def test_racy_refinement_breaks_them():
    broken = 0
    for seed in range(10):
        pairs, w = random_graph(40, seed, 0.12)
        g = small(pairs, w=w)
        record = []
        kernel.refined(g, None, Options(uncoarsen=False, refine_mode="racy", seed=seed), record=record)
        broken += bool(checks.certificate(g, record))
    assert broken


def test_contraction_keeps_the_objective():
    pairs, w = random_graph(20, 1)
    g = small(pairs, w=w)
    c = kernel.local_move(g, np.arange(g.n), Options())
    coarse, up = kernel.contract(g, c)
    singles = np.arange(coarse.n)
    gap = kernel.objective(g, c) - kernel.objective(coarse, singles)
    merged = singles.copy()
    if coarse.n > 1:
        merged[1] = 0
        assert kernel.objective(g, kernel.canonical(merged[up])) - kernel.objective(coarse, merged) == gap
    assert coarse.vw.sum() == g.vw.sum() and (coarse.src != coarse.dst).all()


def test_ablation_directions():
    rng = np.random.default_rng(0)
    q = {k: [] for k in ABLATIONS}
    for seed in range(4):
        n = 300
        block = rng.integers(0, 12, n)
        pairs = [(i, j) for i, j in itertools.combinations(range(n), 2) if rng.random() < (0.25 if block[i] == block[j] else 0.02)]
        g = small(pairs)
        for name, o in ABLATIONS.items():
            q[name].append(kernel.modularity(g, kernel.two_way(g, o)))
    mean = {k: np.mean(v) for k, v in q.items()}
    assert mean["one_way"] < mean["default"] and mean["no_symmetry"] < mean["default"] - 0.05
    assert mean["fused"] == mean["gathered"] == mean["fused_large_moves"] == mean["default"]
    assert mean["min_label"] <= mean["default"]


def test_iteration_schemes():
    pairs, w = random_graph(60, 5, 0.1)
    g = small(pairs, w=w)
    for scheme in ("constrained", "seeded", "refined", "refined_up"):
        rounds = kernel.iterate(g, Options(), 3, scheme)
        assert kernel.objective(g, rounds[-1]) >= kernel.objective(g, np.arange(g.n))


@pytest.mark.parametrize("seed", range(12))
def test_sequential_way_down_is_as_good_as_its_constraint(seed):
    pairs, w = random_graph(40, seed, 0.12)
    g = small(pairs, w=w)
    rng = np.random.default_rng(seed)
    for b in (kernel.sequential(g), kernel.canonical(rng.integers(0, 6, g.n)), np.zeros(g.n, int), np.arange(g.n)):
        inside, floor = checks.constraint_floor(g, b)
        assert inside >= floor
        c = kernel.sequential_way_down(g, b)
        assert all(len(set(b[c == x])) == 1 for x in np.unique(c))


@pytest.mark.parametrize("symmetry, batching, prune", [("replay", "degree", True), ("none", "degree", False), ("min_label", "degree", False), ("async_batches", "degree", True), ("async_min_label", "degree", True), ("batch", "degree", True), ("batch", "color1", False), ("batch", "color2", True), ("batch", "partition", False)])
def test_frames_equal_kernel_under_every_option(spark, symmetry, batching, prune):
    pairs = [(i, (i + 1) % 14) for i in range(14)] + [(0, 5), (3, 9), (20, 21), (21, 22), (20, 22), (22, 0)]
    g = frames(spark, pairs)
    o = Options(phi=(Fraction(1, 4),) * 2, symmetry=symmetry, batching=batching, batches=2, prune=prune, mlh_passes=2 if prune else "odd")
    got = as_dict(moves.local_move(g, moves.singleton_state(g), o, True)[0])
    small_ = engine.local(g)
    want = kernel.local_move(small_, np.arange(small_.n), o)
    assert [got[int(i)] for i in small_.ids] == small_.ids[want].tolist()


@pytest.mark.parametrize("kind", ["split", "fused", "fused_large_moves"])
def test_ways_to_keep_the_table_agree(kind, monkeypatch):
    pairs, w = random_graph(60, 3, 0.12)
    g = small(pairs, w=w)
    used = set()
    for name in ("patched", "recomputed", "affinity"):
        plain = getattr(kernel, name)
        monkeypatch.setattr(kernel, name, lambda *a, plain=plain, name=name, **k: used.add(name) or plain(*a, **k))
    for threshold in (0.0, 0.1, 1.0):
        o = Options(kernel=kind, patch_threshold=threshold)
        assert (kernel.two_way(g, o) == kernel.two_way(g, Options())).all()
        b = kernel.canonical(np.arange(g.n) % 4)
        assert (kernel.two_way(g, o, b) == kernel.two_way(g, Options(), b)).all()
    assert {"split": {"patched", "recomputed"}, "fused": {"affinity"}, "fused_large_moves": {"patched", "affinity"}}[kind] <= used


def test_hubs_in_two_stages(spark):
    star = [(0, i) for i in range(1, 40)] + [(i, i + 1) for i in range(1, 39)]
    g = frames(spark, star)
    o = Options(phi=(Fraction(1, 4),) * 2)
    plain = as_dict(moves.local_move(g, moves.singleton_state(g), o, True)[0])
    assert as_dict(moves.local_move(g, moves.singleton_state(g), o.but(salt_degree=10, salt=4), True)[0]) == plain
    assert [r.id for r in moves.hub_vertices(g.edges, 10).collect()] == [0]


def test_certificates_on_frames_equal_kernel(spark):
    pairs, _ = random_graph(30, 6, 0.2)
    g = frames(spark, pairs)
    b = spark.createDataFrame([(i, i - i % 10) for i in range(30)], "id long, cid long")
    elig = refine.eligible(g, b)
    forest = refine.pointer_jump(refine.oriented(refine.chosen_edges(g, elig, 4), 4))
    rows = refine.prefixes(g, forest, elig)
    fine = refine.committed(rows)
    got = sorted((r.cid, r.id, r.joined, r.rest) for r in checks.merge_scores(g, b, rows, fine).collect())
    small_ = engine.local(g)
    c, order = kernel.refined_with_order(small_, kernel.canonical(np.arange(30) // 10), 4)
    want = sorted((cid, v, joined, rest) for _, cid, v, joined, rest in checks.recorded_merges([(small_, kernel.canonical(np.arange(30) // 10), c, order)]))
    assert got == want and got and all(r[2] >= 0 and r[3] >= 0 for r in got)


def test_colouring_is_proper():
    pairs, _ = random_graph(30, 2)
    g = small(pairs)
    c = kernel.colouring(g)
    assert (c[g.src] != c[g.dst]).all()
    far = kernel.colouring(g, 2)
    for v in range(g.n):
        near = g.dst[g.src == v]
        assert len(set(far[near])) == len(near)


def test_frames_equal_kernel(spark):
    pairs, _ = random_graph(24, 9, 0.2)
    g = frames(spark, pairs)
    o = Options(phi=(Fraction(3, 4), Fraction(1, 4)))
    for method in ("two_way", "refined"):
        a = engine.Engine(spark).cluster(g, method, o)
        b = engine.Engine(spark).cluster(g, method, o.but(kernel_limit=g.stored - 1))
        assert as_dict(a.clusters) == as_dict(b.clusters)


def test_strict_frames_equal_kernel(spark):
    pairs, _ = random_graph(16, 4, 0.3)
    g = frames(spark, pairs)
    c = spark.createDataFrame([(i, i % 4) for i in range(16)], "id long, cid long")
    state = moves.state_of(g, c)
    k = kernel.strict_move(engine.local(g), kernel.canonical(np.arange(16) % 4), Options())
    for method in ("pairs", "prefix"):
        got = as_dict(moves.applied(g, state, refine.strict_move(g, state, method=method)).select("id", "cid"))
        assert [got[i] for i in range(16)] == k.tolist()


def test_wide_arithmetic(spark):
    pairs = spark.createDataFrame(TRIANGLES, "a long, b long")
    e = graph.symmetrize(pairs).selectExpr("src", "dst", "w * 2000000000 as w")
    g = graph.modularity_graph(e)
    assert g.wide
    c = spark.createDataFrame([(i, i // 3) for i in range(6)], "id long, cid long")
    assert graph.lambda_cc(g, c).first().modularity == pytest.approx(5 / 14)
    assert checks.violations_node(g, c).count() == 0


def test_empty_graph(spark):
    g = graph.modularity_graph(graph.symmetrize(spark.createDataFrame([], "a long, b long")))
    assert engine.two_way(g).clusters.count() == 0


def test_contraction_plan_sums_before_the_exchange(spark):
    g = frames(spark, TRIANGLES)
    c = spark.createDataFrame([(i, i // 3 * 3) for i in range(6)], "id long, cid long")
    rows = graph.labelled(g.edges, c).where("c_src <> c_dst").groupBy("c_src", "c_dst").sum("w")
    plan = rows._jdf.queryExecution().executedPlan().toString()
    assert "partial_sum" in plan and "Cartesian" not in plan
    assert levels.contract(g, c).edges.count() == 2


def test_bucketed_edges_are_not_exchanged(spark):
    from lattica.sources import drop, settle

    g = engine._dealt(frames(spark, TRIANGLES))
    before = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        plan = moves.affinity(g.edges, settle(moves.singleton_state(g)))._jdf.queryExecution().executedPlan().toString()
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", before)
    lines = plan.splitlines()
    scan = next(i for i, x in enumerate(lines) if "Bucketed: true" in x)
    join = next(i for i, x in enumerate(lines) if "SortMergeJoin" in x)
    assert not any("Exchange" in x for x in lines[join:scan]) and "partial_sum" in plan
    drop(g.edges)
    assert spark.sql("show tables").where("not isTemporary").count() == 0


def test_tree_prefixes_in_ranges(spark, monkeypatch):
    monkeypatch.setattr(refine, "STRETCH", 3)
    pairs, _ = random_graph(30, 6, 0.2)
    g = frames(spark, pairs)
    b = spark.createDataFrame([(i, i - i % 15) for i in range(30)], "id long, cid long")
    got = as_dict(refine.refine(g, b, 4))
    small_ = engine.local(g)
    want = kernel.refine(small_, kernel.canonical(np.arange(30) // 15), 4)
    assert [got[int(i)] for i in small_.ids] == small_.ids[want].tolist()


def test_measures(spark):
    a = spark.createDataFrame([(i, i // 3) for i in range(6)], "id long, cid long")
    assert measures.ari(a, a).first().ari == 1.0
    assert measures.nmi(a, a).first().nmi == pytest.approx(1.0)
    runs = spark.createDataFrame([("g", "x", 1.0, 0.5, "ok"), ("g", "y", 2.0, 0.4, "ok"), ("h", "x", 1.0, 0.5, "ok"), ("h", "y", 8.0, 0.1, "ok")], "graph string, variant string, seconds double, q double, status string")
    d = {r.variant: r for r in measures.mean_modularity_delta(runs, "x").collect()}
    assert d["y"].delta == pytest.approx(-0.1) and d["y"].excluded == 1
    assert {r.variant: r.ratio for r in measures.geomean_ratio(runs, "x").collect()}["y"] == pytest.approx(4.0)


def test_sources(spark, tmp_path):
    from lattica.sources import read_edges, write_edges

    e = graph.symmetrize(spark.createDataFrame(TRIANGLES, "a long, b long"))
    for fmt in ("parquet", "orc", "csv", "tsv", "json"):
        write_edges(e, f"{tmp_path}/{fmt}", fmt)
        assert read_edges(spark, f"{tmp_path}/{fmt}", fmt).exceptAll(e).count() == 0
    (tmp_path / "m.mtx").write_text("%%MatrixMarket matrix coordinate pattern symmetric\n% note\n6 6 2\n1 2\n3 4\n")
    assert sorted(map(tuple, read_edges(spark, f"{tmp_path}/m.mtx", "coordinate").collect())) == [(1, 2, 1), (3, 4, 1)]


def test_strict_move_takes_every_mover(spark, monkeypatch):
    monkeypatch.setattr(refine, "STRETCH", 7)
    side = 9
    grid = [(i, i + 1) for i in range(side * side) if i % side < side - 1] + [(i, i + side) for i in range(side * (side - 1))]
    g = frames(spark, grid)
    state = moves.state_of(g, g.vertices.select("id", F.pmod("id", F.lit(5)).alias("cid")))
    m = refine.movers(g, state)
    rows = {r.id: r for r in m.collect()}
    small, c = engine.local(g), kernel.canonical(np.arange(side * side) % 5)
    base, now, want = kernel.objective(small, c), np.array(c), {}
    for r in sorted(rows.values(), key=lambda r: r.pos):  # each mover applied in turn and the whole objective taken anew
        now[r.id] = r.new if r.new is not None else small.n + r.id
        want[r.id] = (kernel.objective(small, now) - base) // 2
    assert len(want) > 60 and sorted(r.pos for r in rows.values()) == list(range(1, len(rows) + 1))
    for judge in (refine.strict_pairs, refine.strict_prefix):
        assert {r.id: int(r.run) for r in judge(g, m).collect()} == want
    best = kernel.strict_move(small, c, Options()).tolist()
    assert kernel.strict_move(small, c, Options(cap=3)).tolist() == best
    for bound in (3, 10_000):
        got = as_dict(moves.applied(g, state, refine.strict_move(g, state, bound)).select("id", "cid"))
        assert [got[i] for i in range(side * side)] == best


@pytest.mark.parametrize("more", [{"symmetry": "min_label", "prune": True}, {"symmetry": "batch", "batches": 2}])
def test_blocks_equal_kernel_under_options(spark, monkeypatch, more):
    monkeypatch.setattr(blocks, "BLOCK", 100)
    pairs, _ = random_graph(40, 11, 0.12)
    g = frames(spark, pairs)
    o, start = Options(phi=(Fraction(3, 4), Fraction(1, 4)), **more), np.arange(40)
    want, got = kernel.Log(), kernel.Log()
    assert (blocks.local_move(blocks.packed(g), start, o, log=got)[0] == kernel.local_move(engine.local(g), start, o, log=want)).all()
    assert got.rows == want.rows and got.rows


def test_blocks_equal_kernel(spark, monkeypatch):
    monkeypatch.setattr(blocks, "BLOCK", 100)
    pairs, _ = random_graph(40, 11, 0.12)
    g = frames(spark, pairs)
    o = Options(phi=(Fraction(3, 4), Fraction(1, 4)))
    b = spark.createDataFrame([(i, i - i % 20) for i in range(40)], "id long, cid long")
    monkeypatch.setattr(moves, "local_move", None)  # above the kernel limit nothing may run on DataFrames
    for run in (lambda o: engine.two_way(g, o, constraint=b), lambda o: engine.refined(g, o, start=b)):
        want, got = run(o), run(o.but(kernel_limit=60))
        assert as_dict(got.clusters) == as_dict(want.clusters)
        assert [r[:2] + r[3:] for r in got.log if r[0] >= 0] == [r[:2] + r[3:] for r in want.log if r[0] >= 0] and got.log
    monkeypatch.undo()
    one = o.but(uncoarsen=False)  # level 0 on DataFrames, then blocks
    assert as_dict(engine.two_way(g, one.but(kernel_limit=20, state_limit=39)).clusters) == as_dict(engine.two_way(g, one).clusters)


@pytest.mark.parametrize("scheme", ["constrained", "seeded", "refined", "refined_up"])
def test_rounds_over_blocks_read_the_vertices_once(spark, monkeypatch, scheme):
    monkeypatch.setattr(blocks, "BLOCK", 100)
    pairs, _ = random_graph(40, 11, 0.12)
    g = frames(spark, pairs)
    o = Options(phi=(Fraction(3, 4), Fraction(1, 4)))
    read = []
    plain = blocks.vertices_of
    monkeypatch.setattr(blocks, "vertices_of", lambda g: read.append(g) or plain(g))
    rounds = engine.iterate(g, o.but(kernel_limit=g.stored - 1), 3, scheme)
    scores = [engine.modularity(g, r.clusters).first().modularity for r in rounds]
    assert sum(x.edges is g.edges for x in read) == 1
    assert scores == [graph.lambda_cc(g, r.clusters).first().modularity for r in rounds]
    small_ = engine.local(g)
    for r, want in zip(rounds, kernel.iterate(small_, o, 3, scheme), strict=True):
        got = as_dict(r.clusters)
        assert [got[int(i)] for i in small_.ids] == small_.ids[want].tolist()


@pytest.mark.parametrize("mode", ["forest", "greedy", "racy"])
def test_refinement_over_blocks_equals_kernel(spark, monkeypatch, mode):
    monkeypatch.setattr(blocks, "BLOCK", 50)
    pairs, _ = random_graph(50, 8, 0.15)
    g = frames(spark, pairs)
    b = kernel.canonical(np.arange(50) % 4)
    assert (blocks.refine(blocks.packed(g), b, 3, mode) == kernel.refine(engine.local(g), b, 3, mode)).all()


def test_smallest_hash_of_a_run():
    rng = np.random.default_rng(4)
    v, h, x = np.sort(rng.integers(0, 50, 400)), rng.integers(0, 4, 400) * (2**29), rng.integers(0, 2**31, 400)
    at = np.flatnonzero(np.append(True, v[1:] != v[:-1]))
    assert blocks._least(h, x, at).tolist() == [min(zip(h[v == k], x[v == k], strict=True))[1] for k in np.unique(v)]


def test_blocks_keep_few_bytes_a_vertex(spark):
    import tracemalloc

    n = 200_000  # a ring with chords
    pairs = spark.range(n).selectExpr("id as a", f"explode(array((id + 1) % {n}, (id + 7) % {n})) as b")
    g = blocks.packed(graph.modularity_graph(graph.symmetrize(pairs)))
    tracemalloc.start()
    blocks.local_move(g, np.arange(n), Options(phi=(Fraction(3, 4),) * 2))
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 64 * n


def test_blocks_without_an_edge(spark, monkeypatch):
    monkeypatch.setattr(blocks, "BLOCK", 2)
    g = frames(spark, TRIANGLES)
    kernels, packed = engine.local(g), blocks.packed(g)
    c = np.array([0, 0, 0, 3, 3, 3])
    one, two = kernel.contract(kernels, c)[0], blocks.contract(packed, c)[0]
    lone, none = (x.contract(y, np.array([0, 0]))[0] for x, y in ((kernel, one), (blocks, two)))
    assert lone.n == none.n == 1 and none.stored == 0
    x = np.array([0])
    assert blocks.objective(none, x) == kernel.objective(lone, x)
    assert (blocks.local_move(none, x, Options())[0] == kernel.local_move(lone, x, Options())[0]).all()


def test_blocks_strict_move_equals_kernel(spark, monkeypatch):
    monkeypatch.setattr(blocks, "BLOCK", 50)
    pairs, w = random_graph(50, 8, 0.15)
    g = graph.modularity_graph(graph.symmetrize(spark.createDataFrame([p for p, k in zip(pairs, w, strict=True) for _ in range(k)], "a long, b long"), weighted=True))
    small_, packed = engine.local(g), blocks.packed(g)
    for k in (3, 10, 50):
        c = kernel.canonical(np.arange(50) % k)
        assert (blocks.strict_move(packed, c) == kernel.strict_move(small_, c, Options())).all()
        assert blocks.objective(packed, c) == kernel.objective(small_, c)
        up, vw = blocks.contract(packed, c)[0], kernel.contract(small_, c)[0]
        a, b = blocks.local(up), vw
        assert sorted(zip(a.src, a.dst, a.w, strict=True)) == sorted(zip(b.src, b.dst, b.w, strict=True)) and (a.vw == b.vw).all() and (a.ids == b.ids).all()


def test_lower_levels_of_frame_runs_keep_the_kernel_limit(spark):
    from dataclasses import replace

    from lattica.plans import registry

    g = frames(spark, TRIANGLES)
    assert registry._level0(g).kernel_limit == g.stored - 1 and registry._level0(g).state_limit == 5
    assert registry._level0(replace(g, stored=10**7)).kernel_limit == Options().kernel_limit


def test_blocks_are_held_until_they_are_dropped(spark, monkeypatch):
    monkeypatch.setattr(blocks, "BLOCK", 100)
    pairs, _ = random_graph(40, 11, 0.12)
    g = blocks.packed(frames(spark, pairs))
    held = blocks.held(g.rows)

    def in_memory():
        return sum(x.numCachedPartitions() for x in spark.sparkContext._jsc.sc().getRDDStorageInfo() if x.id() == held.id())

    assert in_memory() == held.getNumPartitions()
    blocks.local_move(g, np.arange(g.n), Options(phi=(Fraction(3, 4),)))
    assert blocks.held(g.rows) is held  # the passes took the same ones
    sources.drop(g.rows)
    assert in_memory() == 0


def test_modularity_graph_reads_its_edges_once(spark):
    e = sources.settle(graph.symmetrize(spark.createDataFrame([(1, 2), (2, 3), (1, 3), (3, 4)], "a long, b long")))
    spark.sparkContext.setJobGroup("sums", "one aggregate")
    try:
        g = graph.modularity_graph(e)
    finally:
        spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
    stages = [k for j in spark.sparkContext.statusTracker().getJobIdsForGroup("sums") for k in spark.sparkContext.statusTracker().getJobInfo(j).stageIds]
    assert len(set(stages)) <= 3  # the scan with its partial sums, and the last sum (read twice by its name)
    assert (g.num, g.den, g.stored) == (1, 8, 8)
    assert {(r.id, r.vw, r.n) for r in blocks.degrees(g).collect()} == {(1, 2, 2), (2, 2, 2), (3, 3, 3), (4, 1, 1)}


def test_summed_takes_any_weight():
    rng = np.random.default_rng(3)
    x, y = rng.integers(0, 40, 500), rng.integers(0, 30, 500)
    for w in (rng.integers(0, 9, 500), rng.integers(-9, 9, 500), rng.integers(0, 1 << 55, 500)):
        want = {}
        for i, j, k in zip(x.tolist(), y.tolist(), w.tolist(), strict=True):
            want[i, j] = want.get((i, j), 0) + k
        assert [((i, j), k) for i, j, k in zip(*(a.tolist() for a in blocks._summed(x, y, w, 30)), strict=True)] == sorted(want.items())


def test_a_small_graph_is_held_in_few_partitions(spark, monkeypatch):
    monkeypatch.setattr(blocks, "BLOCK", 60)
    g = blocks.packed(frames(spark, random_graph(40, 11, 0.12)[0]))
    many = len(blocks.over(g, lambda a, lo, hi, src, dst, w: (np.full(hi - lo, lo),), ("i4",))[0].tolist())
    made = len({r.lo for r in g.rows.collect()})
    assert many == g.n and 4 <= made < 2 * spark.sparkContext.defaultParallelism
    assert blocks.held(g.rows).getNumPartitions() < made
