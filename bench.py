"""Headline queries timed on $BENCH_SF_DIR with local[$BENCH_CPUS]; prints one JSON line.

The line also holds, for the counterparts of the study's three graphs, one bulk job against one job per batch: for sampling alone
(`bulk_over_per_batch`) and for a whole epoch of sampling, feature fetch and propagation (`end_to_end`). `python bench.py --sweep` prints the
study's other tables, a line for each point: bulk width, near and far feature tiers, feature replication, phases by number of cores, parts of
sampling on the grid with communication and computation, layer-wise draws in one product and in chunks against a numpy reference, the share
of the prefix sums, and grid words by p and c.
"""

from __future__ import annotations

import json
import os
import subprocess
import sys
import tempfile
import time

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "4")
HEADLINE = [
    "graph_copurchase", "batches_exact", "node_sample_3hop", "node_sample_paper", "node_pushdown", "node_positions", "node_positions_paper", "node_replicated", "layer_sample", "layer_paper", "layer_grid", "layer_independent", "its_distinct",
    "spgemm", "grid_spgemm_c1", "grid_spgemm_c2", "grid_oblivious", "comm_ledger_aware", "feature_fetch", "join_interval", "agg_cube", "stream_tumbling",
]


def session():
    from pyspark.sql import SparkSession

    folder = tempfile.mkdtemp(prefix="sparseloom-bench-")
    return (
        SparkSession.builder.master(f"local[{CPUS}]").appName("bench").config("spark.driver.memory", os.environ.get("BENCH_MEMORY", "8g"))
        .config("spark.sql.shuffle.partitions", str(2 * int(CPUS))).config("spark.ui.enabled", "false").config("spark.sql.session.timeZone", "UTC")
        .config("spark.ui.showConsoleProgress", "false").config("spark.checkpoint.dir", f"{folder}/shared").config("spark.sql.warehouse.dir", f"{folder}/warehouse").getOrCreate()
    )


def timed(df) -> float:
    t = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - t


def headline(spark) -> dict[str, float]:
    from sparseloom.plans.catalog import QUERIES

    timed(QUERIES["graph_bipartite"](spark, SF_DIR))  # start the workers and compile
    out = {}
    for name in HEADLINE:
        t = time.perf_counter()
        timed(QUERIES[name](spark, SF_DIR))
        out[name] = round(time.perf_counter() - t, 3)
    return out


def graphs_of(spark):
    """name, edges, roots, features, batch size: the three graphs, at rest. Batches of 1024, or as many as leave about twenty."""
    from pyspark.sql import functions as F

    from sparseloom.sources import graphs, tables

    t = tables.load(spark, SF_DIR)
    n = t.embeddings.count()
    vectors = t.embeddings.select(F.col("vec_id").alias("at"), F.col("embedding").alias("vec"))
    for name, edges, vs, size in (
        ("copurchase", graphs.copurchase_graph(t), t.part.select(F.col("p_partkey").alias("v")), 512),
        ("trade", graphs.trade_graph(t), t.customer.select(F.col("c_custkey").alias("v")), 512),
        ("similar", graphs.similarity_graph(t, 16), t.embeddings.select(F.col("vec_id").alias("v")), 64),
    ):
        edges = tables.durable(edges.select("src", "dst", "val"))
        features = tables.durable(graphs.vertices_of(edges).withColumn("at", F.pmod("v", F.lit(n))).join(vectors, "at").select("v", "vec"))
        yield name, edges, tables.durable(graphs.split(vs).where("split = 'train'").select("v")), features, size


def ratios(spark) -> dict[str, dict]:
    """Time of one job per batch over the time of one bulk job, with the same graph at rest and the same samples."""
    from pyspark.sql import functions as F

    from sparseloom.operators import matrix
    from sparseloom.operators.framework import SampleSpec, in_bulks, make_batches, sample_minibatches
    from sparseloom.sources import tables

    out = {}
    spec = SampleSpec(fanout=(15, 10, 5), strategy="bucketed", method="positions")
    for name, edges, roots, _, size in graphs_of(spark):
        rows = matrix.to_adjacency(edges)
        b = tables.durable(make_batches(roots, size))
        n = b.agg(F.max("batch")).first()[0] + 1
        whole = wall(lambda: timed(sample_minibatches(edges, b, spec, rows)))
        one = SampleSpec(fanout=(15, 10, 5), strategy="replicated", method="positions")
        loop = wall(lambda: [timed(part) for part in in_bulks(edges, b, one, 1, n, rows)])
        out[name] = {"batches": n, "bulk_s": round(whole, 2), "per_batch_s": round(loop, 2), "speedup": round(loop / whole, 2)}
    return out


def wall(work) -> float:
    t = time.perf_counter()
    work()
    return time.perf_counter() - t


def labels_of(roots):
    """A label for every root; times don't depend on what it says."""
    from pyspark.sql import functions as F

    return roots.select("v", F.pmod(F.xxhash64("v"), F.lit(4)).cast("int").alias("label"))


def end_to_end(spark, only: str | None = None, baseline: bool = True, processes: int = 4) -> dict[str, dict]:
    """One epoch, three layers of 256, fan-out 15, 10, 5: all batches sampled together, against one batch after the other on a replicated graph."""
    from sparseloom.operators import matrix
    from sparseloom.operators.framework import SampleSpec
    from sparseloom.operators.samplers import NodeWise
    from sparseloom.operators.training import ModelSpec, train

    out, model = {}, ModelSpec(64, 256, 4, layers=3, dtype="float32")
    for name, edges, roots, features, size in graphs_of(spark):
        if only not in (None, name):
            continue
        rows, labels = matrix.to_adjacency(edges), labels_of(roots)
        found = {}
        for kind, k, strategy in (("bulk", None, "bucketed"), ("per_batch", 1, "replicated")):
            if kind == "per_batch" and not baseline:
                continue
            spec = SampleSpec(NodeWise("distinct"), (15, 10, 5), strategy=strategy, method="positions")
            t = time.perf_counter()
            _, reports = train(edges, features, labels, roots, model, spec, size, processes=processes, k=k, adjacency=rows)
            found[kind] = {"seconds": round(time.perf_counter() - t, 2), **{p: round(x, 2) for p, x in reports[0].seconds.items()}, "sampling_share": round(reports[0].sampling_share, 3), "steps": reports[0].steps}
        if baseline:
            found["speedup"] = round(found["per_batch"]["seconds"] / found["bulk"]["seconds"], 2)
        out[name] = found
    return out


def sweep(spark) -> None:
    from pyspark.sql import functions as F

    from sparseloom.operators import baselines, draw, features as fetching, grid, matrix, reference, samplers
    from sparseloom.operators.framework import SampleSpec, Timings, in_bulks, make_batches, sample_minibatches
    from sparseloom.operators.samplers import LayerWise, NodeWise
    from sparseloom.plans import cost
    from sparseloom.plans.measure import measured, run
    from sparseloom.plans.planner import plan_epoch
    from sparseloom.sources import tables

    say = lambda **x: print(json.dumps(x), flush=True)
    for name, edges, roots, vectors, size in graphs_of(spark):
        rows = matrix.to_adjacency(edges)
        b = tables.durable(make_batches(roots, size))
        n = b.agg(F.max("batch")).first()[0] + 1
        degree = cost.graph_stats(edges).first()["mean_degree"]
        spec = SampleSpec(NodeWise("distinct"), (15, 10, 5), strategy="bucketed", method="positions")
        choice = plan_epoch(edges, vectors, n, size, spec.fanout, 4, 2 << 30)
        say(graph=name, workload="planned", strategy=choice.strategy, p=choice.grid.p, c=choice.grid.c, k=choice.k, batches=n, mean_degree=round(degree, 1))
        for k in (1, 4, 16, n):  # bulk width
            if k <= n:
                say(graph=name, workload="bulk width", k=k, seconds=round(wall(lambda: [run(x) for x in in_bulks(edges, b, spec, k, n, rows)]), 2))
        sampled = tables.durable(sample_minibatches(edges, b, spec, rows))
        # near and far features; a copy of all features (c = p) against none (c = 1)
        all_near = lambda: fetching.fetch_features_cached(sampled, vectors, edges, 1.0)
        for what, work in (
            ("far only, c = 1", lambda: run(fetching.fetch_features(sampled, vectors))), ("a fifth near", lambda: run(fetching.fetch_features_cached(sampled, vectors, edges, 0.2))),
            ("all near, c = p", lambda: run(all_near())),
        ):
            say(graph=name, workload="feature fetch", tiers=what, **measured(spark, work))
        for c in (1, 2, 4, 8):
            words = cost.feature_words(sampled, grid.Grid(64, c), 64).agg(F.sum("remote_words")).first()[0]
            say(graph=name, workload="feature replication", p=64, c=c, remote_words=words)
        # node-wise and layer-wise on the grid, by part
        for what, sampler, fanout in (("node-wise", NodeWise(), (15,)), ("layer-wise", LayerWise(), (512,))):
            groups = b if what == "node-wise" else tables.durable(make_batches(roots, min(512, 8 * size)))
            for p, c in ((4, 1), (16, 2), (16, 4)):
                parts = Timings()
                on_grid = SampleSpec(sampler, fanout, strategy="grid", grid=grid.Grid(p, c))
                found = measured(spark, lambda: run(sample_minibatches(edges, groups, on_grid, timings=parts)))
                say(graph=name, workload=f"{what} on the grid", p=p, c=c, parts={k: round(v, 2) for k, v in parts.items()}, **found)
        # layer-wise column extraction, whole and in chunks; a numpy reference on one core; prefix sums
        groups = tables.durable(make_batches(roots, min(512, 8 * size)))
        count = groups.agg(F.max("batch")).first()[0] + 1
        frontier = LayerWise().init_frontier(groups)
        wide = tables.durable(samplers.extract_rows(frontier, edges))
        prob = tables.durable(LayerWise().weigh_rows(wide))
        picked = tables.durable(draw.race(prob, 512, 42, 1))
        for chunk in (count, 4, 1):
            say(graph=name, workload="column extraction", batches_at_once=chunk, seconds=round(wall(lambda: run(samplers.extract_columns_chunked(wide, picked, count, chunk))), 2),
                csr_selector_bytes=matrix.storage_bytes(chunk * 20_000, 512, chunk * 512, "csr"), coo_selector_bytes=matrix.storage_bytes(chunk * 20_000, 512, chunk * 512, "coo"))
        its = wall(lambda: run(draw.its_fixed(prob, 512, 42, 1, 2048)))
        prefix = wall(lambda: run(draw.prefix_sum(prob)))
        say(graph=name, workload="prefix sums", sampling_s=round(its, 2), prefix_s=round(prefix, 2), share=round(prefix / its, 3))
        plain = reference.rows_of([(r["src"], r["dst"]) for r in edges.select("src", "dst").collect()])
        of: dict[int, set] = {}
        for r in groups.collect():
            of.setdefault(r["batch"], set()).add(r["v"])
        one_core = wall(lambda: reference.layer_wise_numpy(plain, of, 512, 42))
        ours = wall(lambda: run(sample_minibatches(edges, groups, SampleSpec(LayerWise(), (512,)))))
        say(graph=name, workload="layer-wise, all batches", batches=count, numpy_one_core_s=round(one_core, 2), ours_s=round(ours, 2))
        # words of the first product by p and c
        q, a = matrix.row_selector(b), edges.withColumnsRenamed({"src": "row", "dst": "col"})
        for p, c in ((4, 1), (4, 2), (16, 1), (16, 2), (16, 4), (64, 8)):
            g = grid.Grid(p, c)
            per_column = grid.comm_ledger(q, a, g, True, ("batch",)).where("phase = 'rows'").groupBy("j").agg(F.sum("words").alias("w")).agg(F.max("w")).first()[0]
            blind = grid.comm_ledger(q, a, g, False, ("batch",)).where("phase = 'rows'").agg(F.sum("words")).first()[0]
            say(graph=name, workload="words", p=p, c=c, row_words_column=per_column, model=round(cost.CostModel().row_words(g, n, size, degree)), oblivious_total=blind)
        say(graph=name, workload="whole neighbourhood", hops=1, edges=baselines.full_neighborhood(edges, b, 1).agg(F.sum("edges")).first()[0])
    # phases by number of cores: each in a process of its own
    times: dict[str, dict[int, float]] = {}
    for cpus in (1, 2, 4):
        done = subprocess.run([sys.executable, os.path.abspath(__file__), "--phases"], env=os.environ | {"BENCH_CPUS": str(cpus)}, capture_output=True, text=True)
        found = json.loads(done.stdout.strip().splitlines()[-1])
        say(workload="phases by cores", cpus=cpus, **found)
        for graph, phases in found.items():
            for phase in ("sampling", "fetch", "propagation", "seconds"):
                times.setdefault(f"{graph} {phase}", {})[cpus] = phases["bulk"][phase]
    for what, by in times.items():
        say(workload="scaling", phase=what, table=[[p, s, round(x, 2), round(e, 2)] for p, s, x, e in cost.scaling_table(by)])


def main() -> None:
    spark = session()
    spark.sparkContext.setLogLevel("ERROR")
    if "--sweep" in sys.argv:
        sweep(spark)
        return
    if "--phases" in sys.argv:
        print(json.dumps(end_to_end(spark, baseline=False)))
        return
    found = headline(spark)
    print(json.dumps({"metric": "headline_queries_total", "value": round(sum(found.values()), 3), "unit": "sec", "queries": found, "sf": SF_DIR.rsplit("sf", 1)[-1], "bulk_over_per_batch": ratios(spark), "end_to_end": end_to_end(spark)}))


if __name__ == "__main__":
    sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))
    main()
