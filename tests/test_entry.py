"""The driver contract, the streams and the SQL side on the given tables."""

import os

import pytest

SF = "/root/testdata/sf0.001"
needs_data = pytest.mark.skipif(not os.path.isdir(SF), reason="no test tables")


def test_contract():
    import __spark_entry__ as e

    names = e.queries()
    assert set(e.oracle_sql()) <= set(names)
    assert {"graph_lattice2d", "local_move_6pass", "refine_prefixes", "strict_move_pairs"} <= set(names)


def test_works_without_the_corpus_operators(monkeypatch):
    import __spark_entry__ as e

    monkeypatch.setattr(e, "_llm", lambda: None)
    assert not any(k.startswith("op") or k == "pipeline" for k in e.queries())


@needs_data
def test_entry(spark):
    import __spark_entry__ as e

    out = e.entry(spark)
    assert out.columns == ["id", "cid"] and out.count() == 200


@needs_data
@pytest.mark.parametrize("name", ["graph_geo_tree", "affinity_patched", "replay_filter_pass1", "local_move_1pass", "refine_prefixes", "strict_move_prefix", "contract_gathered", "strict_move_pairs", "graph_doc_line", "uniform_density_small", "subset_optimality_small", "refine_merge_scores", "pruned_passes", "batched_degree_pruned", "async_passes"])
def test_against_sql(spark, name):
    import duckdb

    from lattica.plans import registry

    con = duckdb.connect()
    for t in "region nation customer supplier part orders lineitem events documents embeddings pages".split():
        con.sql(f"create view {t} as select * from '{SF}/{t}.parquet'")
    got = registry.queries()[name](spark, SF)
    want = con.sql(registry.oracle_sql()[name])
    key = lambda rows: sorted(map(str, rows))
    assert key(tuple(r[c] for c in want.columns) for r in got.collect()) == key(want.fetchall())


@needs_data
def test_run_tables(spark, monkeypatch):
    from lattica.operators import measures
    from lattica.operators.options import ABLATIONS
    from lattica.plans import registry

    views = ("ring_cliques", "user_trans", "page_nav")
    runs = registry.run_table(spark, SF, views, {"default": ABLATIONS["default"], "sequential_two_way": "sequential_two_way"}, 3)
    rows = runs.collect()
    assert len(rows) == 18 and all(r.status == "ok" and r.seconds > 0 for r in rows)
    by = {r.graph: r for r in measures.repetition_summary(runs.where("variant = 'default'")).collect()}
    assert all(r.runs == 3 for r in by.values()) and by["ring_cliques"].q > 0.9
    trace = registry.trace_table(spark, SF, ("ring_cliques",), 3, (2, 1)).collect()
    assert {(r.variant, r.round) for r in trace} == {(v, k) for v in ("constrained", "refined", "refined_up") for k in range(3)} | {("memetic", 0)}
    monkeypatch.setattr(registry, "TASK_EDGES", 300)  # a graph that does not fit a task is reported, not run
    status = {r.graph: r.status for r in registry.run_table(spark, SF, views, {"default": ABLATIONS["default"]}).collect()}
    assert status["ring_cliques"] == "too_large" and status["user_trans"] == "ok"


@needs_data
def test_stream_equals_batch(spark, tmp_path):
    from lattica.streaming import EVENTS, activity, read_events, sessions

    events = spark.read.parquet(f"{SF}/events.parquet").select(*EVENTS.fieldNames())
    events.repartition(3).write.parquet(f"{tmp_path}/in")
    q = activity(read_events(spark, f"{tmp_path}/in", 5), late="3650 days").writeStream.format("memory").queryName("act").outputMode("complete").option("checkpointLocation", f"{tmp_path}/cp").start()
    q.processAllAvailable()
    q.stop()
    assert spark.table("act").exceptAll(activity(events)).count() == 0
    assert sessions(events).agg({"n": "sum"}).first()[0] == events.count()


@needs_data
def test_stream_keeps_a_clustering(spark, tmp_path):
    from lattica.streaming import EVENTS, keep_clustered, read_events

    spark.read.parquet(f"{SF}/events.parquet").select(*EVENTS.fieldNames()).repartition(2).write.parquet(f"{tmp_path}/in")
    q = keep_clustered(read_events(spark, f"{tmp_path}/in"), f"{tmp_path}/g", f"{tmp_path}/cp", trigger={"availableNow": True})
    q.awaitTermination(120)
    assert q.exception() is None
    last = spark.read.parquet(f"{tmp_path}/g/clusters/1")
    assert last.count() == spark.read.parquet(f"{tmp_path}/g/edges/1").select("src").distinct().count()
    assert last.select("id").distinct().count() == last.count()


def test_sql_functions(spark):
    from lattica.functions import portable_hash_np, register_functions

    register_functions(spark)
    row = spark.sql("select portable_hash(12L, 34L, 5L) h, signed_weight(3L, 2L, 4L, 1L, 7L) s").first()
    assert row.h == portable_hash_np(12, 34, 5) and row.s == 13


def test_facade(spark):
    from lattica.operators.engine import Engine

    spark.createDataFrame([(a, b, 1) for x, y in [(0, 1), (1, 2), (0, 2), (3, 4), (4, 5), (3, 5), (2, 3)] for a, b in ((x, y), (y, x))], "src long, dst long, w long").createOrReplaceTempView("g")
    Engine(spark).sql_cluster("g", "clusters")
    assert spark.sql("select count(distinct cid) from clusters").first()[0] == 2


def test_table_functions(spark):
    from lattica.functions.tables import register_table_functions

    register_table_functions(spark)
    pairs = [(0, 1), (1, 2), (0, 2), (3, 4), (4, 5), (3, 5), (2, 3)]
    spark.createDataFrame([(a, b, 1) for x, y in pairs for a, b in ((x, y), (y, x))], "src long, dst long, w long").createOrReplaceTempView("edges")
    got = {r.id: r.cid for r in spark.sql("select * from small_graph_cluster(table(edges) with single partition)").collect()}
    assert got == {0: 0, 1: 0, 2: 0, 3: 3, 4: 3, 5: 3}
    q = spark.sql("select modularity_part(src, dst, w, src div 3, dst div 3) q from edges").first().q
    assert q == pytest.approx(5 / 14)


def test_joins(spark):
    from lattica.operators.joins import asof_join, gap_join

    left = spark.createDataFrame([(1, 5, "a"), (1, 1, "b"), (2, 9, "c")], "k int, t int, n string")
    right = spark.createDataFrame([(1, 2, 20), (1, 5, 50), (2, 10, 100)], "k int, t int, v int")
    assert {r.n: r.v for r in asof_join(left, right, "k", "t", "v").collect()} == {"a": 50, "b": None, "c": None}
    x, y = spark.range(0, 40, 3).toDF("a"), spark.range(0, 40, 7).toDF("b")
    got = {(r.a, r.b) for r in gap_join(x, y, "a", "b", 5).collect()}
    assert got == {(i, j) for i in range(0, 40, 3) for j in range(0, 40, 7) if 0 <= j - i <= 5}


def test_log_and_constants(spark):
    from lattica.operators import engine, graph, kernel, levels
    from lattica.operators.options import Options

    pairs = spark.createDataFrame([(0, 1), (1, 2), (0, 2), (3, 4), (4, 5), (3, 5), (2, 3)], "a long, b long")
    g = graph.modularity_graph(graph.symmetrize(pairs))
    r = engine.two_way(g, Options())
    assert engine.run_log(spark, r).where("pass >= 0").count() > 0
    small = engine.local(g)
    c = kernel.local_move(small, kernel.np.arange(6), Options())
    coarse, _ = kernel.contract(small, c)
    constant = kernel.objective(small, c) - kernel.objective(coarse, kernel.np.arange(coarse.n))
    frame = engine.back(spark, small, c)
    assert levels.level_constant(g, frame).first().constant == constant
    assert levels.fine_objective(kernel.objective(coarse, kernel.np.arange(coarse.n)), [constant]) == kernel.objective(small, c)


def test_last_seen_state(spark, tmp_path):
    from lattica.streaming import EVENTS, last_seen, read_events

    rows = spark.sql("select id event_id, timestamp_seconds(1000 + id) ts, id % 3 user_id, 'x' event_type, 1.0D value, '' props from range(30)").select(*EVENTS.fieldNames())
    rows.repartition(2).write.parquet(f"{tmp_path}/in")
    q = last_seen(read_events(spark, f"{tmp_path}/in", 9)).writeStream.format("memory").queryName("seen").outputMode("update").option("checkpointLocation", f"{tmp_path}/cp").start()
    q.processAllAvailable()
    q.stop()
    assert {r.user_id: r.n for r in spark.table("seen").collect()} == {0: 10, 1: 10, 2: 10}
