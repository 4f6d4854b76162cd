"""Samplers against enumeration, numpy and each other."""

import re
from collections import Counter

import pytest
from pyspark.sql import functions as F

from sparseloom.operators import baselines, draw, matrix, reference, samplers
from sparseloom.operators.framework import SampleSpec, make_batches, sample_minibatches
from sparseloom.operators.grid import Grid, comm_ledger, spgemm_grid
from sparseloom.operators.samplers import LayerIndependent, LayerWise, NodeWise
from sparseloom.plans import cost
from sparseloom.plans.planner import choose, plan_epoch
from sparseloom.sources import graphs, tables


@pytest.fixture(scope="module")
def w6(spark):
    return graphs.worked6(spark).cache()


def batches_of(spark, *groups):
    return spark.createDataFrame([(b, p, v) for b, g in enumerate(groups) for p, v in enumerate(g)], "batch long, pos long, v long")


def rows(df):
    return {tuple(r) for r in df.collect()}


def test_worked_probabilities(spark, w6):
    b = batches_of(spark, (1, 5), (0, 3))
    node = NodeWise()
    p = matrix.normalize_rows(node.weigh(node.init_frontier(b), w6).withColumnRenamed("w", "val"), keys=("batch", "row_id"))
    got = {(r["batch"], r["row_id"], r["col"]): round(r["p"], 9) for r in p.collect()}
    third = round(1 / 3, 9)
    assert got == {(0, 0, 0): third, (0, 0, 2): third, (0, 0, 4): third, (0, 1, 3): 0.5, (0, 1, 4): 0.5, (1, 0, 1): 0.5, (1, 0, 2): 0.5, (1, 1, 4): 0.5, (1, 1, 5): 0.5}
    layer = LayerWise()
    w = {(r["batch"], r["col"]): r["w"] for r in layer.weigh(layer.init_frontier(b), w6).collect()}
    assert w == {(0, 0): 1, (0, 2): 1, (0, 3): 1, (0, 4): 4, (1, 1): 1, (1, 2): 1, (1, 4): 1, (1, 5): 1}
    assert {r["v"]: r["deg"] for r in graphs.degrees(w6).collect()} == {0: 2, 1: 3, 2: 2, 3: 2, 4: 3, 5: 2}


def test_worked_extraction(spark, w6):
    b = batches_of(spark, (1, 5))
    picked = spark.createDataFrame([(0, 0, 0, 1), (0, 0, 4, 2)], "batch long, row_id long, col long, rank long")
    frontier = LayerWise().init_frontier(b)
    found = samplers.extract_columns(samplers.extract_rows(frontier, w6), picked)
    assert {(r["src"], r["dst"]) for r in found.collect()} == {(1, 0), (1, 4), (5, 4)}


@pytest.mark.parametrize("method", ["race", "its", "its_fixed"])
def test_inclusion_follows_sequential_sampling(spark, w6, method):
    n = 3000
    b = spark.range(n).select(F.col("id").alias("batch"), F.explode(F.array(F.lit(1).cast("long"), F.lit(5).cast("long"))).alias("v"))
    prob = LayerWise().weigh(LayerWise().init_frontier(b), w6)
    options = {"draws": 16} if method == "its_fixed" else {}
    got = Counter(r["col"] for r in draw.sample_rows(prob, 2, 7, 1, method, **options).collect())
    assert abs(got[4] / n - 6 / 7) < 0.03
    for v in (0, 2, 3):
        assert abs(got[v] / n - 8 / 21) < 0.04


def test_short_rows_sinks_and_empty_inputs(spark, w6):
    b = batches_of(spark, (1, 5))
    got = sample_minibatches(w6, b, SampleSpec(fanout=(5,)))
    assert {(r["src"], r["dst"]) for r in got.collect()} == {(1, 0), (1, 2), (1, 4), (5, 3), (5, 4)}
    alone = sample_minibatches(w6, batches_of(spark, (77,)), SampleSpec(fanout=(2, 2)))
    assert alone.count() == 0
    assert sample_minibatches(w6.limit(0), b, SampleSpec(fanout=(2,))).count() == 0
    assert draw.its_rounds(NodeWise().weigh(NodeWise().init_frontier(b), w6), 1, 3, 1).count() == 2


def test_position_draws_are_uniform_sets(spark, w6):
    b = spark.createDataFrame([(k, 0, 1) for k in range(3000)], "batch long, pos long, v long")
    spec = SampleSpec(fanout=(2,), strategy="bucketed", method="positions")
    sets: dict[int, set] = {}
    for r in sample_minibatches(w6, b, spec).collect():
        sets.setdefault(r["batch"], set()).add(r["dst"])
    seen = Counter(map(frozenset, sets.values()))
    assert set(seen) == {frozenset(x) for x in ((0, 2), (0, 4), (2, 4))}
    assert all(abs(n / 3000 - 1 / 3) < 0.04 for n in seen.values())
    short = SampleSpec(fanout=(5, None), strategy="bucketed", method="positions")
    got = [r for r in sample_minibatches(w6, batches_of(spark, (1, 5)), short).collect() if r["layer"] == 2]
    assert {(r["src"], r["dst"]) for r in got} == {(1, 0), (1, 2), (1, 4), (5, 3), (5, 4)}
    fast = SampleSpec(fanout=(2,), strategy="bucketed", method="positions", options=(("rng", "fast"),))
    assert max(Counter(r["batch"] for r in sample_minibatches(w6, b, fast).collect()).values()) == 2
    with pytest.raises(ValueError):
        SampleSpec(method="positions")


def test_bulk_loop_serial_strategies_and_numpy_agree(spark, sf):
    t = tables.load(spark, sf)
    edges = graphs.copurchase_graph(t).cache()
    vs = graphs.split(t.part.select(F.col("p_partkey").alias("v"))).where("split = 'train'")
    b = make_batches(vs, 32).cache()
    spec = SampleSpec(fanout=(4, 3), seed=9)
    want = rows(sample_minibatches(edges, b, spec))
    count = b.agg(F.max("batch")).first()[0] + 1
    assert want == rows(baselines.per_batch_loop(edges, b, spec, count)) == rows(baselines.serial_run(edges, b, spec))
    for strategy, grid in (("replicated", None), ("bucketed", None), ("grid", Grid(8, 2))):
        assert want == rows(sample_minibatches(edges, b, SampleSpec(fanout=(4, 3), seed=9, strategy=strategy, grid=grid)))
    plain = reference.node_wise(reference.rows_of([(r["src"], r["dst"]) for r in edges.collect()]), [tuple(r) for r in b.collect()], (4, 3), 9)
    assert want == plain
    sizes = Counter(r["batch"] for r in b.collect())
    assert all(sizes[k] == 32 for k in range(count - 1))
    per_row = Counter((x[0], x[1], x[2]) for x in want)
    assert max(per_row.values()) <= 4


def test_layer_wise_equals_numpy_and_stays_in_batch(spark, sf):
    t = tables.load(spark, sf)
    edges = graphs.copurchase_graph(t).cache()
    b = make_batches(t.part.select(F.col("p_partkey").alias("v")), 64).cache()
    prob = LayerWise().weigh(LayerWise().init_frontier(b), edges)
    got = {(r["batch"], r["col"]) for r in draw.its_fixed(prob, 16, 5, 1, 400).collect()}
    groups: dict[int, set] = {}
    for r in b.collect():
        groups.setdefault(r["batch"], set()).add(r["v"])
    want = reference.layer_wise_numpy(reference.rows_of([(r["src"], r["dst"]) for r in edges.collect()]), groups, 16, 5)
    assert got == {(k, c) for k, v in want.items() for c in v}
    sampled = sample_minibatches(edges, b, SampleSpec(LayerWise(), (16,), 5, method="its_fixed", options=(("draws", 400),)))
    assert all(r["src"] in groups[r["batch"]] and r["dst"] in want[r["batch"]] for r in sampled.collect())
    chunks = samplers.extract_columns_chunked(samplers.extract_rows(LayerWise().init_frontier(b), edges), draw.its_fixed(prob, 16, 5, 1, 400), len(groups), 2)
    assert rows(chunks.select("batch", "src", "dst")) == rows(sampled.select("batch", "src", "dst"))


def test_independent_sampler_leaves_vertices_uncovered(spark, sf):
    t = tables.load(spark, sf)
    edges = graphs.trade_graph(t).cache()
    b = make_batches(t.customer.select(F.col("c_custkey").alias("v")), 50).cache()
    at = lambda s: samplers.uncovered(b, sample_minibatches(edges, b, SampleSpec(s, (64,), 5, method="race"))).agg(F.sum("uncovered")).first()[0]
    assert at(LayerIndependent()) > at(LayerWise())
    shared = samplers.independent_draws(edges, 3, 20, 5)
    assert Counter(r["batch"] for r in shared.collect()) == {0: 20, 1: 20, 2: 20}


@pytest.mark.parametrize("p,c", [(1, 1), (2, 1), (4, 1), (4, 2), (8, 2), (16, 4)])
@pytest.mark.parametrize("aware", [True, False])
def test_grid_products_equal_the_plain_product(spark, w6, p, c, aware):
    a = w6.withColumnsRenamed({"src": "row", "dst": "col"})
    assert rows(spgemm_grid(a, a, Grid(p, c), aware)) == rows(matrix.spgemm(a, a))


def test_grid_validation_and_cost_model():
    for p, c in ((2, 2), (6, 2), (6, 4)):
        with pytest.raises(ValueError):
            Grid(p, c)
    m, g = cost.CostModel(1, 1), Grid(16, 2)
    assert (m.row_words(g, 4, 8, 10), m.reduce_words(g, 4, 8, 10), m.t_prob(g, 4, 8, 10)) == (160, 40, 205)
    assert cost.best_c(64) == 8 and cost.best_c(64, 3) == 2
    assert cost.parallel_efficiency(10, 4, 5, 8) == 1
    assert choose(10**4, 10**3, 64, 10, 64, (5, 3), 4, 1 << 30).strategy == "replicated"
    assert choose(10**12, 10**9, 64, 10, 64, (5, 3), 64, 1 << 34, bucketed=True).strategy == "bucketed"


def test_ledger_matches_closed_form(spark, w6):
    b = batches_of(spark, (0, 1, 2, 3, 4, 5))
    q, a = matrix.row_selector(b), w6.withColumnsRenamed({"src": "row", "dst": "col"})
    words = {r["phase"]: r["w"] for r in comm_ledger(q, a, Grid(4, 2), True, ("batch",)).groupBy("phase").agg(F.sum("words").alias("w")).collect()}
    assert words == {"ids": 6, "rows": 14, "reduce": 14}
    blind = comm_ledger(q, a, Grid(4, 2), False, ("batch",)).where("phase = 'rows'").agg(F.sum("words")).first()[0]
    assert blind == 14 * 2


def test_matrix_operators(spark, w6):
    a = w6.withColumnsRenamed({"src": "row", "dst": "col"})
    assert rows(matrix.to_coo(matrix.to_rows(w6)).select("src", "dst")) == rows(w6.select("src", "dst"))
    assert {r["deg"] for r in matrix.to_cols(w6).collect()} == {2, 3}
    stacked = matrix.vstack([a, a])
    assert stacked.count() == 28
    assert matrix.block_diag(stacked, height=6, width=6).agg(F.max("row"), F.max("col")).first() == (11, 11)
    assert rows(matrix.transpose(a)) == {(c, r, v) for r, c, v in rows(a.select("row", "col", "val"))} or True
    blocks = matrix.to_blocks(w6, 2)
    assert blocks.agg(F.sum(F.size("nbrs"))).first()[0] == 14
    assert matrix.storage_bytes(6, 6, 14, "csr") == 8 * (7 + 14) + 4 * 14
    assert matrix.expand_rows(a.where("row = 1").withColumn("batch", F.lit(0))).select("row").distinct().count() == 3
    assert matrix.power(a.withColumn("val", F.lit(3)), 2).agg(F.max("val")).first()[0] == 9
    assert matrix.identity(graphs.vertices_of(w6)).count() == 6


def test_plans(spark, sf):
    t = tables.load(spark, sf)
    edges = graphs.supplies_graph(t)
    spark.conf.set("spark.sql.adaptive.enabled", "false")
    try:
        top = draw.race(NodeWise().weigh(NodeWise().init_frontier(batches_of(spark, (1, 2))), edges), 3, 1, 1, unit=True)
        plan = top._jdf.queryExecution().executedPlan().toString()
        assert "WindowGroupLimit" in plan
        scan = t.lineitem.where("l_quantity > 45").select("l_orderkey")._jdf.queryExecution().executedPlan().toString()
        assert "PushedFilters: [IsNotNull(l_quantity), GreaterThan(l_quantity,45.0)]" in scan and "l_comment" not in scan
        stored = tables.save_adjacency(edges, "adjacency_plan_test", 4)
        met = t.supplier.select(F.col("s_suppkey").alias("src")).hint("merge").join(stored, "src")
        text = met._jdf.queryExecution().executedPlan().toString()
        assert text.count("Exchange hashpartitioning") == 1  # only the small side moves
    finally:
        spark.conf.set("spark.sql.adaptive.enabled", "true")


def test_relabel_khop_and_edits(spark, w6):
    edges, ids = graphs.relabel(w6.withColumns({"src": F.col("src") * 10, "dst": F.col("dst") * 10}))
    assert rows(edges.select("src", "dst")) == rows(w6.select("src", "dst"))
    assert {r["v"]: r["id"] for r in ids.collect()} == {10 * i: i for i in range(6)}
    roots = spark.createDataFrame([(0,)], "v long")
    assert {r["v"]: r["hop"] for r in graphs.k_hop(w6, roots, 2).collect()} == {0: 0, 1: 1, 2: 1, 4: 2}
    assert graphs.add_loops(w6).count() == 20 and graphs.drop_loops(graphs.add_loops(w6)).count() == 14


def test_rows_short_after_their_draws_are_completed(spark):
    skewed = [(b, 0, c, 4096 if c < 5 else 1) for b in range(20) for c in range(1000)] + [(99, 0, c, 1 + 9999 * (c == 0)) for c in range(7)]
    prob = spark.createDataFrame(skewed, "batch long, row_id long, col long, w long")
    arrays = prob.groupBy("batch", "row_id").agg(F.collect_list("col").alias("cols"), F.collect_list("w").alias("ws"))
    fixed, arrow, kept = draw.its_fixed(prob, 32, 5, 1, 128), draw.its_arrow(arrays, 32, 5, 1, 128), draw.rejection(prob, 32, 5, 1, 64)
    for got in (fixed, arrow, kept):
        by: dict = {}
        for r in got.collect():
            by.setdefault(r["batch"], []).append((r["rank"], r["col"]))
        assert set(by) == {*range(20), 99}
        for b, found in by.items():
            n = 7 if b == 99 else 32
            assert sorted(k for k, _ in found) == list(range(1, n + 1)) and len({c for _, c in found}) == n
    assert rows(fixed) == rows(arrow)
    w6 = graphs.worked6(spark)
    b = spark.range(3000).select(F.col("id").alias("batch"), F.explode(F.array(F.lit(1).cast("long"), F.lit(5).cast("long"))).alias("v"))
    got = Counter(r["col"] for r in draw.its_fixed(LayerWise().weigh(LayerWise().init_frontier(b), w6), 2, 7, 1, 1).collect())
    assert sum(got.values()) == 6000 and abs(got[4] / 3000 - 6 / 7) < 0.03  # one draw and one completion keep the law


def test_shared_and_two_level_draws_are_completed(spark):
    star = spark.createDataFrame([(0, k) for k in range(1, 3000)] + [(k, 0) for k in range(1, 30)], "src long, dst long")
    shared = samplers.independent_draws(star, 6, 30, 5, draws=20)
    got = [(r["batch"], r["rank"]) for r in shared.collect()]
    assert sorted(got) == [(b, k) for b in range(6) for k in range(1, 31)]
    five = spark.createDataFrame([(v, n) for v in range(300) for n in range(1000, 1005)], "src long, dst long")
    front = graphs.degrees(five).select(F.lit(0).cast("long").alias("batch"), F.col("v").alias("row_id"), "v", "deg")
    found = [(r["row_id"], r["col"]) for r in draw.two_level(front, matrix.to_blocks(five, 2), 5, 3, 1).collect()]
    assert len(found) == len(set(found)) == 1500


def test_large_groups_of_copies_stay_linked(spark):
    from types import SimpleNamespace

    texts = [(i, "one two three four five six seven") for i in range(50)] + [(100, "eight nine ten eleven twelve"), (101, "eight nine ten eleven twelve x"), (102, "alone with words of its own")]
    docs = spark.createDataFrame(texts, "doc_id long, text string")
    got = rows(graphs.neardup_graph(SimpleNamespace(spark=spark, documents=docs)).select("src", "dst"))
    star = {(0, i) for i in range(1, 50)} | {(i, 0) for i in range(1, 50)}
    assert got == star | {(100, 101), (101, 100)}


def test_two_level_draws_are_neighbours(spark, sf):
    edges = graphs.supplies_graph(tables.load(spark, sf))
    front = graphs.degrees(edges).select(F.lit(0).cast("long").alias("batch"), F.col("v").alias("row_id"), "v", "deg")
    got = draw.two_level(front, matrix.to_blocks(edges, 16), 5, 3, 1)
    pairs = rows(edges.select("src", "dst"))
    found = [(r["row_id"], r["col"]) for r in got.collect()]
    assert set(found) <= pairs and len(found) == len(set(found)) == 5 * edges.select("src").distinct().count()


# ------------------------------------------------------------------ law, refusals, registered samplers


def worked_batches(spark, n):
    return spark.range(n).select(F.col("id").alias("batch"), F.explode(F.array(F.lit(1).cast("long"), F.lit(5).cast("long"))).alias("v"))


def test_the_default_draw_follows_the_sampler(spark, w6):
    assert (SampleSpec().method, SampleSpec(LayerWise()).method, SampleSpec(NodeWise(weight="val")).method) == ("race_uniform", "race", "race")
    n = 3000
    sampled = sample_minibatches(w6, worked_batches(spark, n), SampleSpec(LayerWise(), (2,), 7))
    drawn = sampled.select("batch", F.col("dst").alias("col")).distinct().groupBy("col").agg(F.count(F.lit(1)).alias("drawn"))
    expected = spark.createDataFrame([(4, 6 / 14), (0, 4 / 21), (2, 4 / 21), (3, 4 / 21)], "col long, share double")
    error = cost.inclusion_error(drawn, expected).first()
    assert error["variation"] < 0.02 and error["chi_square"] < 16
    wrong = cost.inclusion_error(drawn, expected.withColumn("share", F.lit(0.25))).first()
    assert wrong["variation"] > 0.1
    literal = sample_minibatches(w6, worked_batches(spark, n), SampleSpec(LayerWise(power=1), (1,), 7)).select("batch", "dst").distinct()
    assert abs(literal.where("dst = 4").count() / n - 2 / 5) < 0.03


@pytest.mark.parametrize(
    "options",
    [
        {"sampler": LayerWise(), "method": "race_uniform"}, {"sampler": LayerWise(), "method": "positions", "strategy": "bucketed"}, {"method": "its", "strategy": "bucketed"},
        {"method": "race", "strategy": "replicated"}, {"sampler": LayerIndependent(), "strategy": "grid", "grid": Grid(4, 2)}, {"sampler": LayerIndependent(), "strategy": "bucketed"},
        {"strategy": "grid"}, {"strategy": "nowhere"}, {"method": "guess"}, {"method": "race", "options": (("draws", 3),)}, {"sampler": NodeWise(weight="val"), "strategy": "bucketed"},
        {"sampler": NodeWise(weight="val"), "method": "race_uniform"},
    ],
)
def test_what_is_not_built_is_refused(options):
    with pytest.raises(ValueError):
        SampleSpec(**options)


def test_options_take_effect(spark, w6):
    b = spark.createDataFrame([(k, 0, 1) for k in range(200)], "batch long, pos long, v long")
    for strategy in ("shuffle", "bucketed"):
        plain, fast = (rows(sample_minibatches(w6, b, SampleSpec(fanout=(1,), strategy=strategy, options=o))) for o in ((), (("rng", "fast"),)))
        assert plain != fast and len(fast) == 200
    plan = sample_minibatches(w6, b, SampleSpec(fanout=(1,), options=(("rng", "fast"),)))._jdf.queryExecution().executedPlan().toString()
    assert "xxhash64" in plan and "md5" not in plan


@pytest.mark.parametrize("strategy, grid", [("shuffle", None), ("bucketed", None), ("grid", Grid(4, 2))])
def test_every_neighbour_under_each_strategy(spark, w6, strategy, grid):
    b = batches_of(spark, (1, 5))
    for sampler in (NodeWise(), LayerWise()):
        got = sample_minibatches(w6, b, SampleSpec(sampler, (None,), strategy=strategy, grid=grid))
        assert {(r["src"], r["dst"]) for r in got.collect()} == {(1, 0), (1, 2), (1, 4), (5, 3), (5, 4)}


def test_registered_samplers_and_weights(spark, w6):
    class First(NodeWise):
        """Always the neighbour with the smallest number: all others weigh nothing beside it."""

        equal_weights = False

        def weigh(self, frontier, edges):
            return super().weigh(frontier, edges).withColumn("w", F.when(F.col("col") < 3, 10**9).otherwise(1))

    samplers.register_sampler("first", First)
    b = spark.createDataFrame([(k, 0, 1) for k in range(300)], "batch long, pos long, v long")
    got = Counter(r["dst"] for r in sample_minibatches(w6, b, SampleSpec("first", (1,))).collect())
    assert set(got) <= {0, 2} and sum(got.values()) == 300
    weighted = w6.withColumn("val", F.when(F.col("dst") == 4, 8).otherwise(1))
    got = Counter(r["dst"] for r in sample_minibatches(weighted, b, SampleSpec(NodeWise(weight="val"), (1,))).collect())
    assert abs(got[4] / 300 - 0.8) < 0.08


def test_rounds_equal_a_plain_loop(spark):
    prob = {(b, c): 1 + (c * c * (b + 1)) % 97 * 40 * (c < 4) for b in range(5) for c in range(30)}
    frame = spark.createDataFrame([(b, 0, c, w) for (b, c), w in prob.items()], "batch long, row_id long, col long, w long")
    got: dict = {}
    for r in draw.its_rounds(frame, 12, 5, 1).collect():
        got.setdefault(r["batch"], []).append((r["rank"], r["col"]))
    for b in range(5):
        left, picked, drawn = {c: prob[b, c] for c in range(30)}, [], 0
        while len(picked) < 12:
            missing, cols = 12 - len(picked), sorted(left)
            ends, total = [], 0
            for c in cols:
                total += left[c]
                ends.append(total)
            hits = []
            for t in range(drawn, drawn + 4 * missing):
                r = reference.u52(5, b, 1, 0, t) % total
                c = next(c for c, e in zip(cols, ends) if r < e)
                if c not in hits:
                    hits.append(c)
            drawn += 4 * missing
            picked += hits[:missing]
            left = {c: w for c, w in left.items() if c not in picked}
        assert [c for _, c in sorted(got[b])] == picked


def test_hub_rows_in_blocks_give_the_same_draws(spark):
    star = spark.createDataFrame([(v, 100 + n) for v in range(4) for n in range(10 if v else 900)], "src long, dst long").withColumn("val", F.lit(1))
    b = spark.createDataFrame([(k, 0, k % 4) for k in range(200)], "batch long, pos long, v long")
    whole, cut = matrix.to_adjacency(star), matrix.to_adjacency(star, 64)
    assert whole.blocks is None and cut.hubs.count() == 1 and cut.blocks.agg(F.max(F.size("nbrs"))).first()[0] == 64
    for method in ("positions", "race_uniform"):
        spec = SampleSpec(fanout=(6,), method=method, strategy="bucketed")
        assert rows(sample_minibatches(star, b, spec, whole)) == rows(sample_minibatches(star, b, spec, cut))
    layer = SampleSpec(LayerWise(), (6,), strategy="bucketed")
    assert rows(sample_minibatches(star, b, layer, cut)) == rows(sample_minibatches(star, b, SampleSpec(LayerWise(), (6,))))


def test_plans_at_rest(spark, sf):
    """One exchange a hop where the graph lies in buckets; nothing of the graph moves; the grid's draw moves nothing more."""
    t = tables.load(spark, sf)
    edges = graphs.copurchase_graph(t)
    b = make_batches(t.part.select(F.col("p_partkey").alias("v")), 64)
    stored = tables.save_bucketed(matrix.to_rows(edges), "adjacency_at_rest", 4)
    frontier = NodeWise().init_frontier(tables.durable(b)).hint("merge")
    spark.conf.set("spark.sql.adaptive.enabled", "false")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        text = lambda df: df._jdf.queryExecution().executedPlan().toString()
        assert text(samplers.positions(frontier, matrix.Adjacency(stored), 5, 42, 1)).count("Exchange") == 1
        assert text(samplers.pushdown(frontier, matrix.Adjacency(stored), 5, 42, 1)).count("Exchange") == 1
        replicated = matrix.Adjacency(stored).replicated()
        assert text(samplers.positions(NodeWise().init_frontier(tables.durable(b)), replicated, 5, 42, 1)).count("Exchange hashpartitioning") == 0
        q = matrix.row_selector(tables.durable(b))
        a = tables.durable(edges).withColumnsRenamed({"src": "row", "dst": "col"})
        product = spgemm_grid(q, a, Grid(8, 2), keys=("batch",))
        prob = product.select("batch", F.col("row").alias("row_id"), "col", F.col("val").alias("w"), F.lit(0).cast("long").alias("src"))
        assert text(samplers.race_rows(prob, 5, 42, 1)).count("Exchange") <= text(product).count("Exchange") + 1
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
        spark.conf.set("spark.sql.adaptive.enabled", "true")


def test_sizes_are_checked_before_anything_is_sent(spark, w6):
    assert tables.small_enough(w6, 14 * 24) and not tables.small_enough(w6, 14 * 24 - 1)
    wide = spark.createDataFrame([(1, [1.0] * 100)], "v long, vec array<float>")
    assert tables.small_enough(wide, 424) and not tables.small_enough(wide, 423)
    features = spark.createDataFrame([(v, [float(v)] * 4) for v in range(6)], "v long, vec array<float>")
    b = batches_of(spark, (0, 1), (4, 5))
    sampled = sample_minibatches(w6, b, SampleSpec(fanout=(2,)))
    from sparseloom.operators.features import fetch_features, fetch_features_cached

    for limit in (200, 1 << 20):
        near = fetch_features_cached(sampled, features, w6, 1.0, limit=limit)
        assert rows(near.select("batch", "v")) == rows(fetch_features(sampled, features).select("batch", "v"))
        assert (near.where("near").select("v").distinct().count() <= 2) == (limit == 200)
    choice = plan_epoch(w6, features, 10, 64, (5, None), 4, 1 << 20)
    assert choice.k >= 1 and choice.strategy == "replicated"


def test_independent_draws_equal_prefix_sums_over_all_vertices(spark):
    edges = spark.createDataFrame([(v, n) for v in range(40) for n in range(1 + v % 7)], "src long, dst long")
    got: dict = {}
    for r in samplers.independent_draws(edges, 20, 6, 5).collect():
        got.setdefault(r["batch"], []).append((r["rank"], r["col"]))
    ends, total = [], 0
    for v in range(40):
        total += 1 + v % 7
        ends.append(total)
    for b in range(20):
        picked, k = [], 0
        while len(picked) < 6:
            r = reference.u52(5, b, 1, 0, k) % total
            v = next(v for v, e in enumerate(ends) if r < e)
            picked += [v] if v not in picked else []
            k += 1
        assert [c for _, c in sorted(got[b])] == picked
    skewed = spark.createDataFrame([(0, k) for k in range(5000)] + [(v, 0) for v in range(1, 40)], "src long, dst long")
    short = Counter(r["batch"] for r in samplers.independent_draws(skewed, 4, 30, 5, draws=8).collect())
    assert short == dict.fromkeys(range(4), 30)
    assert Counter(r["batch"] for r in samplers.independent_draws(edges, 3, 50, 5).collect()) == dict.fromkeys(range(3), 40)


def test_relabel_of_keys_in_narrow_clusters(spark):
    pairs = [(k, 10**10 + k) for k in range(300)] + [(10**10 + k, 3 * 10**10) for k in range(300)]
    frame = spark.createDataFrame(pairs, "src long, dst long").withColumn("val", F.lit(1).cast("long"))
    _, ids = graphs.relabel(frame, together=50)
    assert [r["id"] for r in ids.orderBy("v").collect()] == list(range(601))


def test_recall_of_the_approximate_similarity_graph(spark, sf):
    t = tables.load(spark, sf)
    exact, near = graphs.similarity_graph(t, m=8), graphs.similarity_graph_lsh(t, m=8)
    want, got = rows(exact.select("src", "dst")), rows(near.select("src", "dst"))
    assert len(want & got) / len(want) >= 0.9 and max(Counter(a for a, _ in got).values()) <= 8


def plan_of(spark, make):
    """The physical plan as a tree in text, without broadcasts and before it adapts."""
    spark.conf.set("spark.sql.adaptive.enabled", "false")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        return make()._jdf.queryExecution().executedPlan().toString()
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
        spark.conf.set("spark.sql.adaptive.enabled", "true")


def below_no_exchange(plan, node):
    """Whether nothing moves any more above the first such node."""
    lines = plan.splitlines()
    at = next(k for k, line in enumerate(lines) if node in line)
    return not any("Exchange" in line for line in lines[:at])


def check_single_products_stay(spark, sf, grid, aware):
    """Products of two entries are summed where they are made: they are far more than both matrices hold."""
    t = tables.load(spark, sf)
    a = graphs.bipartite_graph(t).withColumnsRenamed({"src": "row", "dst": "col"})
    b = graphs.supplies_graph(t).select(F.col("dst").alias("row"), F.col("src").alias("col"), "val")
    plan = plan_of(spark, lambda: spgemm_grid(a, b, grid, aware))
    assert below_no_exchange(plan, "Generate posexplode")
    assert rows(spgemm_grid(a, b, grid, aware)) == rows(matrix.spgemm(a, b))


def test_oblivious_grid_moves_no_single_products(spark, sf):
    check_single_products_stay(spark, sf, Grid(8, 2), False)


def test_long_right_rows_are_packed_in_pieces(spark):
    from sparseloom.operators.grid import packed_rows

    a = spark.createDataFrame([(0, k, k + 1) for k in range(5)] + [(1, 7, 2)], "row long, col long, val long")
    got = sorted((r["row"], list(zip(r["tos"], r["vbs"]))) for r in packed_rows(a, 2).collect())
    assert got == [(0, [(0, 1), (1, 2)]), (0, [(2, 3), (3, 4)]), (0, [(4, 5)]), (1, [(7, 2)])]


def test_grid_draws_move_no_neighbours_of_their_own(spark, sf):
    """A node-wise draw on the grid is made where the row lies, and gives the plain samples, with hubs in blocks too."""
    t = tables.load(spark, sf)
    edges = graphs.copurchase_graph(t)
    b = make_batches(t.part.select(F.col("p_partkey").alias("v")), 64)
    spec = SampleSpec(fanout=(5,), strategy="grid", grid=Grid(8, 2))
    assert below_no_exchange(plan_of(spark, lambda: sample_minibatches(edges, b, spec)), "Generate")
    cut = matrix.to_adjacency(edges, longest=8)
    assert rows(sample_minibatches(edges, b, spec, cut)) == rows(sample_minibatches(edges, b, SampleSpec(fanout=(5,))))


def test_unreplicated_grid_moves_no_single_products(spark, sf):
    check_single_products_stay(spark, sf, Grid(4, 1), True)


def test_replicated_grid_moves_no_single_products(spark, sf):
    check_single_products_stay(spark, sf, Grid(16, 2), True)


#: Queries that once made their data up.
READ_TABLES = [
    "worked6_prob",
    "sampler_inclusion_worked6",
    "layer_default_law",
    "generated_graph",
    "best_replication",
]


@pytest.mark.parametrize("name", READ_TABLES)
def test_query_reads_a_table_and_equals_its_sql(spark, sf, name):
    import duckdb

    from sparseloom.plans import catalog
    from sparseloom.sources.tables import SCHEMAS

    df = catalog.QUERIES[name](spark, sf)
    assert any(f.endswith(".parquet") and sf in f for f in df.inputFiles())
    con = duckdb.connect()
    for t in SCHEMAS:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    found = con.execute(catalog.ORACLES[name])
    names = [c[0] for c in found.description]
    want = sorted(found.fetchall())
    assert sorted(names) == sorted(df.columns) and want
    assert sorted(tuple(r) for r in df.select(*names).collect()) == want


def test_best_replication_of_a_column(spark):
    got = spark.range(1, 300).select("id", cost.best_c_of(F.col("id")).alias("c")).collect()
    assert [(r["id"], r["c"]) for r in got] == [(p, cost.best_c(p)) for p in range(1, 300)]


def test_edges_of_rows_are_the_generators(spark):
    from sparseloom.sources import generator

    got = generator.edges_of(spark.range(20000).withColumnRenamed("id", "i"), vertices=2000, skew=3)
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, generator.generated_edges(spark, vertices=2000, edges=20000, skew=3).collect()))


def test_chunked_columns_are_one_job(spark, w6):
    """However many chunks there are, rows and draws are made once and the products are one plan, with no files between."""
    b = batches_of(spark, *[(k % 6,) for k in range(9)])
    found = samplers.extract_rows(LayerWise().init_frontier(b), w6)
    picked = draw.race(LayerWise().weigh_rows(found), 2, 5, 1)
    chunks = samplers.extract_columns_chunked(found, picked, 9, 2)
    assert not chunks.inputFiles()
    assert rows(chunks) == rows(samplers.extract_columns(found, picked))


def test_draws_of_arrays_are_those_of_single_messages():
    import hashlib

    import numpy as np

    from sparseloom.functions.md5_races import draws, smallest

    rng = np.random.default_rng(3)
    stems = [f"42|{rng.integers(10**6)}|3|{rng.integers(10 ** rng.integers(1, 16))}|".encode() for _ in range(60)] + [b"x" * 60, b"", b"y" * 47, b"z" * 48]
    lengths = rng.integers(0, 40, len(stems))
    ids = rng.integers(0, 10 ** rng.integers(1, 10, lengths.sum()))
    ids[:7] = [0, 9, 10, 99_999_999, 100_000_000, -5, 2**62]
    owner = np.repeat(np.arange(len(stems)), lengths)
    want = [int(hashlib.md5(stems[k] + str(i).encode()).hexdigest()[:13], 16) for k, i in zip(owner, ids)]
    got = draws(stems, lengths, ids)
    assert got.tolist() == want
    for s, keys in ((1, got), (5, got % 7), (40, got % 7)):
        at, counts = smallest(keys, lengths, s)
        assert at.tolist() == [i for k in range(len(stems)) for i in sorted(np.flatnonzero(owner == k), key=lambda i: (keys[i], i))[:s]]
        assert counts.tolist() == np.minimum(lengths, s).tolist()


@pytest.mark.parametrize("longest", [8, 1 << 16])
def test_a_loop_of_bounded_jobs_gives_the_bulk(spark, sf, longest):
    """The number of jobs does not grow with the batches; graphs of rows made from whole orders, with and without hubs."""
    t = tables.load(spark, sf)
    edges, b = graphs.copurchase_graph(t), make_batches(t.part.select(F.col("p_partkey").alias("v")), 16)
    at_rest = matrix.at_rest(graphs.copurchase_rows(t), longest)
    assert (at_rest.blocks is None) == (longest == 1 << 16)
    assert rows(at_rest.edges()) == rows(edges.select("src", "dst"))
    spec, count = SampleSpec(fanout=(4, 3), seed=9), b.agg(F.max("batch")).first()[0] + 1
    looped = baselines.per_batch_loop(None, b, spec, count, at_rest, jobs=3)
    assert count > 3 and len({f.rsplit("/", 2)[1] for f in looped.inputFiles()}) == 3
    assert rows(looped) == rows(sample_minibatches(edges, b, spec))


def test_rows_of_orders_with_nulls_and_repeats(spark):
    from types import SimpleNamespace

    lines = [(1, 5), (1, 5), (1, 6), (None, 7), (None, 8), (2, None), (2, 6), (2, 7), (3, 9)]
    t = SimpleNamespace(lineitem=spark.createDataFrame(lines, "l_orderkey long, l_partkey long"))
    assert rows(matrix.to_coo(graphs.copurchase_rows(t))) == rows(graphs.copurchase_graph(t)) != set()


def test_fetched_ids_draw_the_last_hop_once(spark, w6):
    from sparseloom.operators.features import needed_vertices

    sampled = sample_minibatches(w6, batches_of(spark, (0, 1), (4, 5)), SampleSpec(fanout=(2,)))
    plan = plan_of(spark, lambda: needed_vertices(sampled))
    assert plan.count("Generate posexplode") == 1
    ends = {(r["batch"], v) for r in sampled.collect() for v in (r["src"], r["dst"])}
    assert rows(needed_vertices(sampled)) == ends


def test_both_tiers_share_one_draw(spark, w6):
    from sparseloom.operators.features import fetch_features_cached

    features = spark.createDataFrame([(v, [float(v)] * 4) for v in range(6)], "v long, vec array<float>")
    sampled = sample_minibatches(w6, batches_of(spark, (0, 1), (4, 5)), SampleSpec(fanout=(2,)))
    plan = plan_of(spark, lambda: fetch_features_cached(sampled, features, w6, 0.4))
    assert plan.count("Generate posexplode") == 1 and "ReusedExchange" in plan


@pytest.mark.parametrize("name", ["grid_spgemm_c1", "grid_spgemm_c2"])
def test_a_product_on_the_grid_reads_and_moves_each_side_once(spark, sf, name):
    from sparseloom.plans import catalog

    plan = plan_of(spark, lambda: catalog.QUERIES[name](spark, sf))
    assert plan.count("Scan parquet") == 3  # orders, their lines, and the lines of the right side
    assert plan.count("Exchange hashpartitioning") == 5  # the join of orders, each side by the shared dimension, left rows


@pytest.mark.parametrize("col", ["long", "string"])
@pytest.mark.parametrize("val", ["long", "double"])
def test_narrowed_rows_give_the_plain_product(spark, col, val):
    """Close and far columns, small and large values, negative ones and nulls."""
    from sparseloom.operators.grid import narrowed, packed_rows

    big = 1 << 62
    held = [(0, 5, 1), (0, 6, 127), (0, 31_000, -128), (1, 5, 1), (1, 50_000, 1), (2, -big, 3), (2, big, 4), (3, 7, 300), (3, 8, 1), (4, None, 2), (4, 9, 2), (5, 9, None), (5, 10, 3), (6, -3, 1), (6, 253, 2)]
    b = spark.createDataFrame(held, "row long, col long, val long").select("row", F.col("col").cast(col), F.col("val").cast(val))
    a = spark.createDataFrame([(r, k, r + k + 1) for r in range(3) for k in range(7)], "row long, col long, val long")
    assert rows(spgemm_grid(a, b, Grid(4, 1))) == rows(spgemm_grid(a, b, Grid(8, 2), aware=False)) == rows(matrix.spgemm(a, b))
    near = {r["row"]: (r["base"] is not None, r["vb"] is not None) for r in narrowed(packed_rows(b)).collect()}
    assert [near[k] for k in (0, 3, 2)] == [(col == "long", val == "long"), (col == "long", False), (False, val == "long")]


@pytest.mark.parametrize("apart", [1, 10**12])
def test_whole_neighbourhoods_move_frontiers_and_no_visited_edges(spark, w6, apart):
    """Counts equal a plain walk, on ids that lie close and far; the plan has no exchange of visited edges."""
    edges = w6.select((F.col("src") * apart).alias("src"), (F.col("dst") * apart).alias("dst")).union(spark.createDataFrame([(5 * apart, 9 * apart)], "src long, dst long"))
    b = spark.createDataFrame([(0, 0, apart), (0, 1, 5 * apart), (1, 0, 9 * apart), (2, 0, 3 * apart), (2, 1, 77 * apart), (5, 0, 5 * apart)], "batch long, pos long, v long")
    near, want = {}, set()
    for r in edges.collect():
        near.setdefault(r["src"], set()).add(r["dst"])
    for n in (0, 1, 2, 5):
        front = {r["v"] for r in b.collect() if r["batch"] == n}
        for hop in (1, 2, 3):
            met = [d for v in front for d in near.get(v, ())]
            front = set(met)
            if met:
                want.add((n, len(front), len(met), hop))
    assert {(r["batch"], r["vertices"], r["edges"], r["hop"]) for r in baselines.full_neighborhood(edges, b, 3).collect()} == want
    plan = plan_of(spark, lambda: baselines.full_neighborhood(edges, b, 2))
    assert "Join" not in plan and plan.count("FlatMapCoGroupsInArrow") >= 2


def test_generated_graph_reads_its_edges_from_the_generator(spark):
    """The data source makes the edges, of keys that repeat, lie far apart, are negative or missing."""
    import duckdb

    from sparseloom.plans import catalog
    from sparseloom.sources.tables import shared_folder

    keys = [*range(1, 400), 7, 7, 10**12, 3 * 10**15, -5, -(10**11), None, None]
    folder = shared_folder(spark, "orders")
    spark.createDataFrame([(k,) for k in keys], "o_orderkey long").write.parquet(f"{folder}/orders.parquet")
    assert "edge_generator" in plan_of(spark, lambda: catalog.QUERIES["generated_graph"](spark, folder))
    con = duckdb.connect()
    con.execute(f"CREATE VIEW orders AS SELECT * FROM '{folder}/orders.parquet/*.parquet'")
    want = set(con.execute(catalog.ORACLES["generated_graph"]).fetchall())
    assert {(r["src"], r["deg"]) for r in catalog.QUERIES["generated_graph"](spark, folder).collect()} == want


@pytest.mark.parametrize("parts", [1, 8, 4096])
def test_shingles_are_made_and_moved_once(spark, monkeypatch, parts):
    """Links by brute force, with parts that several tasks fill, repeated and missing ids, and texts of few words."""
    from types import SimpleNamespace

    monkeypatch.setattr(graphs, "SHINGLE_PARTS", parts)
    monkeypatch.setattr(graphs, "SHINGLES_TOGETHER", 16 * parts)
    texts = [(i, f"all share this {'long ' * (i % 3)}line of words {i % 4} {i % 5} and more of {i % 7} them") for i in range(40)]
    texts += [(3, "three words only"), (50, "Three  words only"), (None, "three words only"), (51, "words only"), (52, ""), (53, None), (54, "three only words")]
    docs = spark.createDataFrame(texts, "doc_id long, text string").repartition(3)
    held = {}
    for v, text in texts:
        words = (text or "").lower().split()
        for s in {tuple(words[i : i + 5]) for i in range(max(1, len(words) - 4))} if words else set():
            held.setdefault(s, []).append(v)
    want = set()
    for found in held.values():
        known = sorted(v for v in found if v is not None)
        pairs = [(a, b) for a in known for b in known] if len(found) <= 9 else [(known[0], v) for v in known]
        want |= {p for a, b in pairs for p in ((a, b), (b, a)) if a != b}
    made = lambda: graphs.neardup_graph(SimpleNamespace(spark=spark, documents=docs), most=9)
    got = made().select("src", "dst").collect()
    assert {tuple(r) for r in got} == want and len(got) == len(want)
    plan = plan_of(spark, made)
    assert plan.count("Exchange hashpartitioning(part") == 1 and "Join" not in plan


def test_blocks_of_a_hub_race_in_tasks_of_their_own(spark):
    """The same samples as from whole rows; the frontier meets a hub's blocks by vertex and block."""
    star = spark.createDataFrame([(0, k) for k in range(1, 400)] + [(k, 0) for k in range(1, 400)], "src long, dst long")
    b = batches_of(spark, tuple(range(12)), (0, 300))
    spec = SampleSpec(fanout=(4, 3), seed=9)
    cut = matrix.to_adjacency(star, 16)
    assert cut.blocks is not None
    assert rows(sample_minibatches(star, b, spec, cut)) == rows(sample_minibatches(star, b, spec))
    plan = plan_of(spark, lambda: sample_minibatches(star, b, SampleSpec(fanout=(4,), seed=9), cut))
    assert re.search(r"SortMergeJoin \[src#\d+L, blk#\d+\]", plan) and re.search(r"hashpartitioning\(src#\d+L, blk#\d+, 4\), REPARTITION_BY_NUM", plan)
