import math
import random
from dataclasses import replace
from itertools import combinations

import pytest
from pyspark.sql import functions as F

from binflow import queries, workloads
from binflow.baselines import runs as baselines
from binflow.baselines import serial
from binflow.operators import graphs as utilities
from binflow.operators import relational
from binflow.plans import engine, layout, misses, modes, program
from binflow.programs import local, runs
from binflow.sources import datasource, generators, views
from binflow.streaming import edges as streams

TOY = [(0, 1), (0, 2), (0, 3), (0, 6), (1, 2), (2, 4), (2, 5), (3, 0), (4, 6), (4, 7), (5, 1), (6, 7)]


@pytest.fixture(scope="module")
def toy(spark):
    return layout.build(spark.createDataFrame([(a, b, 1) for a, b in TOY], "src bigint, dst bigint, weight bigint"), 8, 4)


SMALL = "/root/testdata/sf0.001"


def rows(df):
    return sorted(map(tuple, df.collect()))


def test_toy_costs_and_modes(toy):
    plan = modes.mode_plan(toy.vertices, toy.part_stats, toy.k).orderBy("part").collect()
    assert [(r.n_e, r.n_msg, round(r.cost_sc), round(r.cost_pc), r["mode"]) for r in plan] == [(5, 4, 100, 84, "pc"), (3, 2, 60, 52, "pc"), (3, 2, 60, 52, "pc"), (1, 1, 28, 32, "pc")]
    only1 = modes.mode_plan(toy.vertices.where("vid = 1"), toy.part_stats, toy.k).first()
    assert (round(only1.cost_sc, 1), only1["mode"]) == (22.4, "sc")
    exact = modes.mode_plan(toy.vertices.where("vid = 1"), toy.part_stats, toy.k, exact=True).first()
    assert exact.cost_sc == 24
    only0 = modes.mode_plan(toy.vertices.where("vid = 0"), toy.part_stats, toy.k).first()
    assert (round(only0.cost_sc, 1), only0["mode"]) == (77.6, "pc")
    assert layout.inter_partition_edges(toy.edges, 8, 4).first().crossing == 10


def test_a_list_in_chunks_is_one_message(spark, toy, monkeypatch):
    edges = spark.createDataFrame([(a, b, 1) for a, b in TOY], "src bigint, dst bigint, weight bigint")
    monkeypatch.setattr(layout, "CHUNK", 1)
    chunked = layout.build(edges, 8, 4)
    assert chunked.bins.count() > toy.bins.count()
    found = []
    for g in (toy, chunked):
        monkeypatch.setattr(queries, "graph", lambda *_, g=g: g)
        found.append(rows(queries.bins_summary(spark, "")))
    assert found[0] == found[1] and sum(r[2] for r in found[0]) == 9


def _rows_read(spark):
    jsc, jvm = spark.sparkContext._jsc.sc(), spark.sparkContext._jvm
    jsc.listenerBus().waitUntilEmpty(10_000)
    stages = jsc.statusStore().stageList(None, False, False, spark.sparkContext._gateway.new_array(jvm.double, 0), jvm.java.util.ArrayList())
    return sum(stages.apply(i).inputRecords() for i in range(stages.size()))


def _rmat_sql(scale: int, degree: int, seed: int = 42) -> str:
    """The generator's arithmetic, one row a draw and level."""
    prime, (a, b, c, _) = generators.PRIME, generators.QUADRANTS
    steps = "".join(f", d{k + 1} as (select id, level, (x * x + x * (16807 + level) + {12345 + k}) % {prime} as x from d{k})" for k in range(3))
    return f"""with d0 as (select id, level, (id % {prime} * 48271 + (level + 1) * 69621 + {seed}) % {prime} as x from range({degree << scale}) i(id), range({scale}) l(level)){steps},
    u as (select id, level, x / {prime}.0::double as u from d3),
    g as (select id, sum((u >= {a + b}::double)::bigint << ({scale - 1} - level)) as src, sum(((u >= {a}::double and u < {a + b}::double) or u >= {a + b + c}::double)::bigint << ({scale - 1} - level)) as dst from u group by id),
    e as (select distinct src, dst from g where src <> dst), o as (select src as vid, count(*) as out_deg from e group by src), i as (select distinct dst as vid from e)
    select coalesce(out_deg, 0) as out_deg, count(*) as n from o full join i using (vid) group by 1"""


def test_generator_equals_its_sql(spark):
    import duckdb

    made = relational.degrees(generators.rmat(spark, 6, 16)).groupBy("out_deg").agg(F.count(F.lit(1)).alias("n"))
    assert rows(made) == sorted(duckdb.sql(_rmat_sql(6, 16)).fetchall())


def test_degree_histogram_reads_the_lines(spark):
    found = queries.rmat_degree_hist(spark, SMALL)
    assert any("lineitem" in f for f in found.inputFiles())
    assert sum(r.out_deg * r.n for r in found.collect()) == views.g_line_chain(spark, SMALL).count()


def test_statistics_are_taken_from_the_table(spark):
    g = queries.graph(spark, SMALL, "line_chain")
    kept = rows(g.part_stats.select("part", "n_v", "n_e", "n_msg", F.round("r", 9)))
    before = _rows_read(spark)
    assert rows(queries.part_stats_r(spark, SMALL)) == kept
    assert _rows_read(spark) - before >= spark.read.parquet(f"{SMALL}/lineitem.parquet").count()


def test_bfs_modes_agree(toy):
    want = [(0, 0, 0), (1, 0, 1), (2, 0, 1), (3, 0, 1), (4, 2, 2), (5, 2, 2), (6, 0, 1), (7, 6, 2)]
    for mode in ("auto", "sc", "pc"):
        assert rows(runs.bfs(toy, 0, mode=mode)) == want
    assert rows(baselines.bfs_switching(toy, 0)[0]) == want
    with pytest.raises(ValueError):
        runs.bfs(toy, 0, waves=2)


def test_pagerank_of_a_cycle(spark):
    g = layout.build(generators.cycle_graph(spark, 6), 6, 2)
    assert all(abs(r.rank - 1 / 6) < 1e-12 for r in runs.pagerank(g, 3).collect())


def test_waves_and_delta_agree(spark):
    g = layout.build(views.edge_weights(generators.grid_graph(spark, 4, 5), 128), 20, 4)
    want = rows(runs.sssp(g, 0, waves=1))
    assert len(want) == 20
    assert rows(runs.sssp(g, 0, waves=2)) == want
    assert rows(baselines.sssp_delta(g, 0)[0]) == want


def test_selective_continuity(spark):
    """With a high threshold only the seed stays active, by its own rule, though nothing reaches it."""
    g = layout.build(generators.star_graph(spark, 10), 11, 2)
    sparse = {r.vid: r.p for r in runs.nibble(g, [0], 0.06, 1).collect()}
    assert abs(sparse[0] - 0.5) < 1e-12 and abs(sum(sparse.values()) - 1) < 1e-12
    dense = engine.run(g, program.nibble(0, 0.06), max_rounds=1).state.where("x > 0").select("vid", "x").collect()
    assert {r.vid: r.x for r in dense} == pytest.approx(sparse)


def test_missing_root_and_empty_graph(spark, toy):
    assert rows(runs.bfs(toy, 99)) == []
    g = layout.build(spark.createDataFrame([], "src bigint, dst bigint, weight bigint"), 3, 2)
    assert rows(runs.connected_components(g)) == [(0, 0), (1, 1), (2, 2)]


def test_csr_round_trip(toy):
    back = layout.from_csr(layout.to_csr(toy.edges))
    assert rows(back) == rows(toy.edges)


def test_dense_ids(spark):
    ids = layout.dense_ids(spark.range(0, 1000, 7).withColumn("k", F.xxhash64("id")), ["k"]).orderBy("k").select("vid")
    assert [r.vid for r in ids.collect()] == list(range(143))


def test_edge_limit():
    assert baselines.check_edge_limit(10)
    with pytest.raises(OverflowError):
        baselines.check_edge_limit(2**31)


def test_asof(spark):
    left = spark.createDataFrame([(1, 5), (1, 1), (2, 9)], "k int, t int")
    right = spark.createDataFrame([(1, 2, "a"), (1, 4, "b")], "k int, t int, v string")
    assert rows(relational.asof_join(left, right, "k", "t", ["v"]).select("k", "t", F.coalesce("last_v", F.lit("-")))) == [(1, 1, "-"), (1, 5, "b"), (2, 9, "-")]


def test_local_settling_agrees(spark):
    """Partitions settle at once, or a step at a time; the distances are those of the plain rounds, in fewer rounds."""
    g = layout.build(views.edge_weights(generators.grid_graph(spark, 4, 5), 128), 20, 2)
    want = rows(runs.sssp(g, 0, waves=1))
    whole, few = local.sssp_local(g, 0)
    stepped, many = local.sssp_local(g, 0, most=1)
    assert rows(whole) == want and rows(stepped) == want and few <= many
    path = layout.build(views.symmetrise(generators.path_graph(spark, 40)), 40, 4)
    labels, n = local.components_local(path)
    assert {r.label for r in labels.collect()} == {0} and n <= 5
    assert rows(local.sssp_local(path, 99)[0]) == []


def test_modelled_misses_of_toy(toy):
    """All values fit one line: first touches only, plus the streams (12 edges, 9 messages)."""
    got = {r.paradigm: r.misses for r in misses.model_misses(toy).collect()}
    assert got == {"sc": 2 + (8 * 9 + 12 * 12) / 64, "pc": 2 + (8 * 9 + 4 * 21) / 64, "push": 1 + 48 / 64, "pull": 1 + 48 / 64}


def test_graph_utilities(spark, toy):
    assert rows(utilities.reverse(utilities.reverse(toy.edges))) == rows(toy.edges)
    linked = {tuple(sorted(e)) for e in TOY}
    assert utilities.triangles(toy.edges).first().triangles == sum(linked.issuperset(combinations(t, 2)) for t in combinations(range(8), 3)) == 3
    assert rows(utilities.induced_subgraph(toy.edges, spark.createDataFrame([(0,), (1,), (2,)], "vid bigint")).select("src", "dst")) == [(0, 1), (0, 2), (1, 2)]
    cut = utilities.conductance(toy.edges, F.col("vid") < 4).first()
    assert (cut.cut, cut.volume) == (3, 8)
    assert rows(utilities.dangling(toy.vertices)) == [(7,)]
    ring = generators.cycle_graph(spark, 30).union(spark.createDataFrame([(100, 101, 1), (7, 7, 1), (200, 200, 1)], "src bigint, dst bigint, weight bigint"))
    found = {r.vid: r.label for r in utilities.alternating_stars(ring).collect()}
    assert found == {i: 0 for i in range(30)} | {100: 100, 101: 100, 200: 200}
    assert utilities.alternating_stars(ring.limit(0)).count() == 0


def test_incremental_labels(spark):
    first = streams.add_edges(None, spark.createDataFrame([(1, 2), (3, 4)], "src bigint, dst bigint"))
    second = streams.add_edges(first, spark.createDataFrame([(4, 2), (9, 8)], "src bigint, dst bigint"))
    assert rows(second) == [(1, 1), (2, 1), (3, 1), (4, 1), (8, 8), (9, 8)]


@pytest.mark.parametrize("leaves", [9, 20_000])
def test_residual_query_converges_at_any_size(spark, monkeypatch, leaves):
    g = layout.build(generators.star_graph(spark, leaves).where("src = 0"), leaves + 1, 4)
    monkeypatch.setattr(queries, "graph", lambda *_: g)
    want = {r.vid: r["rank"] for r in runs.pagerank(g, 3).collect()}
    got = {r.vid: r["rank"] for r in queries.pagerank_residual(spark, "").collect()}
    assert got == pytest.approx(want, rel=1e-4) and min(got.values()) > 0


def random_edges(n, m, seed):
    draw = random.Random(seed)
    return sorted({(draw.randrange(n), draw.randrange(n), draw.randint(1, 9)) for _ in range(m)})


@pytest.fixture(scope="module")
def wild(spark):
    """Self loops, parallel edges of other weights, isolated vertices; 4 partitions and a short last one."""
    edges = random_edges(45, 120, 3)
    return edges, layout.build(spark.createDataFrame(edges, "src bigint, dst bigint, weight bigint"), 50, 4)


@pytest.mark.parametrize("how", [{"mode": "sc"}, {"mode": "pc"}, {"mode": "auto"}, {"paradigm": "push"}, {"paradigm": "pull"}, {"paradigm": "edge"}, {"paradigm": "blocked"}], ids=str)
def test_programs_equal_the_serial_reference(wild, how):
    edges, g = wild
    assert {r.vid: (r.parent, r.level) for r in runs.bfs(g, 0, **how).collect()} == serial.bfs(edges, 0)
    assert {r.vid: r.dist for r in runs.sssp(g, 0, **how).collect()} == serial.sssp(edges, 0)
    ranks = engine.run(g, program.pagerank(), max_rounds=3, **how).state.collect()
    assert {r.vid: r.x for r in ranks} == pytest.approx(serial.pagerank(edges, 50, 3))


def test_walks_and_components_equal_the_serial_reference(spark, wild):
    edges, g = wild
    assert {r.vid: r["rank"] for r in runs.pagerank(g, 10).collect()} == pytest.approx(serial.pagerank(edges, 50))
    for eps in (1e-9, 1e-2):
        got = {r.vid: r.p for r in runs.nibble(g, [0, 99], eps, 4).collect()}
        assert got == pytest.approx(serial.nibble(edges, 0, eps, 4))
    both = layout.build(views.symmetrise(g.edges), 50, 4)
    want = serial.components(edges, 50)
    for waves in (1, 3):
        assert {r.vid: r.label for r in runs.connected_components(both, waves=waves).collect()} == want
    assert {r.vid: r.dist for r in runs.sssp(g, 0, waves=4).collect()} == serial.sssp(edges, 0)
    with pytest.raises(ValueError):
        runs.pagerank(g, 1, mode="best")


def test_heat_kernel_sums_the_series(spark):
    g = layout.build(generators.complete_graph(spark, 5), 5, 2)
    got = {r.vid: r.score for r in runs.heat_kernel(g, [0], terms=30).collect()}
    assert sum(got.values()) == pytest.approx(1.0, abs=1e-9)
    assert got[0] == pytest.approx((1 + 4 * math.exp(-6.25)) / 5)


def test_ties_of_the_model_go_to_pc():
    stats = {0: {"n_e": 10, "r": 0.5, "n_msg": 5, "lo": 0, "hi": 0}}
    pc = float(modes.cost_pc(10, 0.5, 4))
    front = {0: (2, 3, 2)}
    sc = float(modes.cost_sc(2, 3, 1.5))
    assert modes.choose(front, stats, 4, ratio=pc / sc)[0]["mode"] == "pc"
    assert modes.choose(front, stats, 4, ratio=pc / sc * 0.999)[0]["mode"] == "sc"


def nodes(df):
    """Names and short texts of the physical plan's nodes, kept tables not opened."""
    out = []

    def walk(p):
        if p.nodeName() == "AdaptiveSparkPlan":
            return walk(p.initialPlan())
        out.append((p.nodeName(), p.simpleString(1000)))
        for i in range(p.children().size()):
            walk(p.children().apply(i))

    walk(df._jdf.queryExecution().executedPlan())
    return out


@pytest.mark.parametrize("mode", ["sc", "pc"])
def test_a_round_is_one_exchange(spark, wild, mode):
    """The bins and the state stay where they lie; PC sends (dst_part, src_part, src, chunk, val) and no lists."""
    _, g = wild
    before = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        with engine.fixed_dealing(spark):
            one = program.sssp(0)
            state = engine.State(g, engine.cut(engine.start(g, one)))
            arrived = engine.combined(g, state.rows(), one, () if mode == "sc" else None, () if mode == "pc" else None)
            new = engine.gather(g, state.rows(), arrived, one, 1, F.col("active"))
            found = nodes(new)
            moved = [text for name, text in found if name == "Exchange"]
            assert len(moved) == 1 and "dst_part" in moved[0]
            again = nodes(engine.State(g, engine.cut(new.drop("touched"))).rows().groupBy("part").count())
            assert not [n for n, _ in again if n == "Exchange"]
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", before)


def test_sparse_rounds_read_listed_partitions(spark):
    """The scan of the kept bins has the listed partitions as its predicate, and SC reads no other block."""
    g = layout.build(generators.path_graph(spark, 64), 64, 16)
    rows = engine.listed(g.by_source, "src_part", [3, 4, 9], g.k)
    scan = next(text for name, text in nodes(rows) if name == "InMemoryTableScan")
    assert ">= 3" in scan and "<= 4" in scan and "= 9" in scan or "(src_part" in scan
    assert sorted({r.src_part for r in rows.collect()}) == [3, 4, 9]
    many = list(range(0, 16, 2))
    assert sorted({r.src_part for r in engine.listed(g.by_source, "src_part", many, 16).collect()}) == many
    log = engine.run(g, program.bfs(0), max_rounds=6, trace=True).log
    assert all(r["touched_parts"] == 1 and r["touched_bins"] == 1 and r["frontier"] == 1 for r in log)


def test_gaps_are_bridged_and_tested(spark, monkeypatch):
    monkeypatch.setattr(engine, "MOST_RANGES", 2)
    rows = spark.range(100).select(F.col("id").cast("int").alias("p"))
    parts = [1, 3, 4, 40, 43, 90]
    assert sorted(r.p for r in engine.listed(rows, "p", parts, 100).collect()) == parts


def test_work_follows_the_active_edges(spark):
    """Modelled bytes of every round are within a constant of those of the active vertices and edges, in all modes the model chooses."""
    g = layout.build(generators.rmat(spark, 8, 8), 256, 16)
    for made in (program.bfs(0), program.sssp(0), program.nibble(0, 1e-4)):
        log = engine.run(g, made, max_rounds=6).log
        assert engine.check_work_bound(log, g.k) <= 10 and all(r["model_bytes"] == r["best_bytes"] for r in log)
    with pytest.raises(AssertionError):
        engine.check_work_bound(engine.run(layout.build(generators.path_graph(spark, 64), 64, 16), program.bfs(0), mode="pc", max_rounds=1).log, 16)


def test_bins_move_fewer_bytes_than_edges(spark):
    g = layout.build(generators.rmat(spark, 11, 16), 2048, 8)
    moved = {r.system: r.shuffle_bytes for r in workloads.shuffle_contrast(g, 1).collect()}
    assert 0 < moved["pc"] < moved["sc"] and moved["pc"] < moved["push"] and moved["pc"] < moved["edge"]


def test_saved_graph_opens(spark, wild, tmp_path):
    edges, g = wild
    layout.save_graph(g, f"file://{tmp_path}/g")
    again = layout.open_graph(spark, f"file://{tmp_path}/g")
    assert rows(again.edges) == rows(g.edges) and rows(again.part_stats) == rows(g.part_stats)
    assert {r.vid: r.dist for r in runs.sssp(again, 0).collect()} == serial.sssp(edges, 0)
    assert layout.build(spark.createDataFrame([(0, 0, 1)], "src bigint, dst bigint, weight bigint")).n_vertices == 1
    assert (layout.choose_k(0, slots=2), layout.choose_k(10**9, 24, 128 << 20, 8)) == (8, 179)


def test_damaged_tree_fails_the_checks(spark, wild):
    _, g = wild
    tree = runs.bfs(g, 0)
    assert {r.failures for r in runs.validate_bfs(g, 0, tree).collect()} == {0}
    bad = tree.where("vid <> 5").withColumn("level", F.when(F.col("vid") == 0, 0).otherwise(F.col("level") + (F.col("vid") % 3 == 0).cast("int")))
    assert sum(r.failures for r in runs.validate_bfs(g, 0, bad).collect()) > 0


def test_data_source_draws_what_the_generator_draws(spark):
    datasource.register(spark)
    made = spark.read.format("binflow_rmat").option("scale", 6).option("degree", 4).load()
    assert made.count() == 256
    assert rows(made.where("src <> dst").distinct()) == rows(generators.rmat(spark, 6, 4).select("src", "dst"))


def test_python_message(spark, wild):
    """A program whose message is a Python function gives what the column expression gives."""
    edges, g = wild
    ranks = program.pagerank()
    one = replace(program.spmv(), message=program.python_function(lambda x: x * 2, "double"))
    got = {r.vid: r.x for r in engine.run(g, one, max_rounds=1).state.collect()}
    want = {v: 0.0 for v in range(50)}
    for _, b, w in edges:
        want[b] += 2.0 * w
    assert got == pytest.approx(want) and ranks.combine == "sum"


def test_a_stream_goes_on_where_it_stopped(spark, tmp_path):
    """The second run of a query in the same folder reads new files only and keeps the state."""
    (tmp_path / "in").mkdir()
    for k in range(2):
        batch = spark.range(k * 10, k * 10 + 10).selectExpr("id as event_id", "timestamp_ntz'2024-01-01 00:00:00' as ts", "id % 3 as user_id", "'view' as event_type", "1.0D as value", "'' as props")
        batch.toPandas().to_parquet(tmp_path / "in" / ("events.parquet" if k == 0 else "events_1.parquet"), coerce_timestamps="us")
        got = rows(streams.vertex_activity(spark, f"file://{tmp_path}/in", at=f"file://{tmp_path}/at").select("user_id", "n"))
        assert sum(n for _, n in got) == 10 * (k + 1)


def test_small_relational_operators(spark):
    texts = spark.createDataFrame([(1, "a b c d"), (2, "B C  d e"), (3, None), (4, "")], "id bigint, text string")
    other = spark.createDataFrame([(9, "x b c d")], "id bigint, text string")
    assert rows(relational.shingle_join(texts, "id", other, "id", "text", 3)) == [(1, 9, 1), (2, 9, 1)]
    vectors = spark.createDataFrame([(1, [1.0, 0.0], 0), (2, [2.0, 0.1], 0), (3, [0.0, 1.0], 0), (4, [1.0, 0.0], 1), (5, [0.0, 0.0], 0)], "id bigint, v array<double>, block int")
    assert [(a, b) for a, b, _ in rows(relational.similarity_join(vectors, "id", "v", "block", 0.9))] == [(1, 2)]
    ids = spark.range(1000)
    assert 50 < relational.hash_sample(ids, "id", 0.1).count() < 150 and relational.except_ids(ids, ids).count() == 0
    names = views.register_views(spark, "/root/testdata/sf0.001")
    assert "g_doc_bench" in names and spark.sql("select count(*) as n from g_embed_sim").first().n >= 0
