"""Runs the headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import os
import sys
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
#: Views of the ablation: one of each shape whose graph fits a task.
VIEWS = ("lattice2d", "geo_tree", "page_nav", "ring_cliques", "order_chain", "status_hub")


def main() -> None:
    from pyspark.sql import SparkSession

    spark = SparkSession.builder.master(f"local[{CPUS}]").config("spark.sql.shuffle.partitions", CPUS).config("spark.ui.enabled", "false").config("spark.sql.session.timeZone", "UTC").config("spark.driver.memory", "12g").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    from pyspark.sql import functions as F

    from lattica.operators import engine, graph, measures
    from lattica.operators.options import ABLATIONS, Options
    from lattica.plans import registry
    from lattica.sources import settle
    from lattica.sources.views import pairs

    times: dict[str, float] = {}

    def timed(name, f):
        start = time.perf_counter()
        out = f()
        times[name] = round(time.perf_counter() - start, 3)
        return out

    noop = lambda df: df.write.format("noop").mode("overwrite").save()
    for view in ("part_cooc", "cust_part", "status_hub", "order_chain"):
        timed(f"graph_{view}", lambda v=view: noop(graph.symmetrize(pairs(spark, SF_DIR, v))))
    g = timed("load_cust_part", lambda: graph.modularity_graph(settle(graph.symmetrize(pairs(spark, SF_DIR, "cust_part")), "bench")))
    low = settle(g.vertices.select("id", F.pmod("id", F.lit(1000)).alias("cid")), "bench")
    from lattica.operators import levels, moves

    state = settle(moves.state_of(g, low), "bench")
    timed("affinity", lambda: noop(moves.affinity(g.edges, state)))
    timed("best_destination", lambda: noop(moves.destinations(g, state, moves.affinity(g.edges, state))))
    base = moves.state_of(g, low).select("id", "cid")
    timed("contract", lambda: levels.contract(g, base).stored)
    timed("contract_gathered", lambda: levels.contract(g, base, gather=True).stored)
    info = {}
    # the engines in one task, for the ratios between them, then the Spark engine: level 0 on DataFrames, all passes
    for name in ("two_way", "one_way", "refined", "refined_up"):
        r = timed(f"{name}_cust_part", lambda m=name: engine.Engine(spark).cluster(g, m, Options(kernel_limit=2_000_000)))
        info[f"q_{name}_cust_part"] = round(graph.lambda_cc(g, r.clusters).first().modularity, 6)
    for name in ("one_way",):
        r = timed(f"frames_{name}_cust_part", lambda m=name: engine.Engine(spark).cluster(g, m, Options()))
        info[f"q_frames_{name}_cust_part"] = round(graph.lambda_cc(g, r.clusters).first().modularity, 6)
        info[f"frames_{name}_seconds"] = {k: round(v, 2) for k, v in r.seconds.items()}
    runs = timed("ablation", lambda: settle(registry.run_table(spark, SF_DIR, VIEWS, ABLATIONS), "bench"))
    for row in measures.mean_modularity_delta(runs, "default").join(measures.geomean_ratio(runs, "default"), "variant").collect():
        info[f"ablation_{row.variant}"] = {"time": round(row.ratio, 3), "dq": None if row.delta is None else round(row.delta, 4)}
    share = runs.where("variant = 'default'").agg(F.avg(F.col("contract_seconds") / F.col("seconds"))).first()[0]
    info["contract_share"] = round(share or 0, 4)
    spark.stop()
    print(json.dumps({"metric": "total_seconds", "value": round(sum(times.values()), 3), "unit": "sec", "queries": times, "measures": info, "sf": SF_DIR.rpartition("sf")[2]}))


if __name__ == "__main__":
    main()
