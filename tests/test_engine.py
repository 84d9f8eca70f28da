"""The engine on small graphs and the smallest tables."""

import time

import numpy as np
import pytest
from pyspark.sql import Window

from factorgraph_spark.operators import baselines, block_bp, exact, partition, sync_bp
from factorgraph_spark.operators.kernel import BPConfig
from factorgraph_spark.operators.model import Clause, potts
from factorgraph_spark.plans import gallery, planner

SMALL = "/root/testdata/sf0.001"


def table(df):
    return {(r["vid"], r["state"]): r["belief"] for r in df.collect()}


def close(a, b, by=1e-6):
    a, b = table(a), table(b)
    return a.keys() == b.keys() and max(abs(a[k] - b[k]) for k in a) < by


@pytest.fixture(scope="module")
def loop(spark):
    return gallery.literal(spark, [[0.0, 1.0], [0.3, 0.0], [0.0, 0.0]], [([0, 1], potts(2, 0.2)), ([1, 2], potts(2, 0.2)), ([2, 0], potts(2, 0.2))])


def test_chain_converges_to_enumeration(spark):
    g = gallery.literal(spark, [[0.0, 1.0], [0.0, 0.0], [0.5, 0.0]], [([0, 1], potts(2, 0.7)), ([1, 2], potts(2, 0.7))])
    assert {r["violations"] for r in g.validate().collect()} == {0}
    want = exact.enumerate_all(g)
    assert close(sync_bp.run(g, 8, 1e-12).beliefs, want)
    assign = partition.hash_parts(g, 3)
    assert close(block_bp.run(g, assign, BPConfig(damping=0.0, beta=1e-10)).beliefs, want)


def test_three_slots_in_columns_and_in_the_kernel(spark):
    clause = Clause("a & b -> c", 1.3, ((0, 0), (1, 0), (2, 1)))
    assert clause.potential()[1] == [1.3] * 6 + [0.0, 1.3]
    g = gallery.literal(spark, [[0.0, 2.0], [0.0, 0.5], [0.0, 0.0]], [([0, 1, 2], clause.potential()[1])])
    want = exact.enumerate_all(g)
    assert close(sync_bp.run(g, 4, 1e-12, every=2).beliefs, want)
    assert close(baselines.block_beliefs(spark, baselines.shared_queue_sweep(g, damping=0.0, beta=1e-12)), want)


def test_a_loop_is_close_to_exact_but_need_not_be(spark, loop):
    got, want = table(sync_bp.run(loop, 12, 1e-10, every=6).beliefs), table(exact.enumerate_all(loop))
    assert max(abs(got[k] - want[k]) for k in got) < 0.01


def test_unary_factors_are_absorbed_and_parallel_ones_merged(spark):
    g = gallery.literal(spark, [[0.0, 0.0], [0.0, 0.0]], [([0], [0.0, 1.0]), ([0, 1], potts(2, 0.3)), ([0, 1], potts(2, 0.4))])
    want = exact.enumerate_all(g)
    a = planner.merge_parallel(planner.absorb_unary(g))
    assert a.edges.count() == 2
    assert close(exact.enumerate_all(a), want)
    assert close(sync_bp.run(a, 6, 1e-12, every=3).beliefs, want)


def test_isolated_variables_and_empty_graphs(spark):
    g = gallery.literal(spark, [[0.0, 0.0], [0.0, 0.0], [0.0, 0.0]], [([0, 1], potts(2, 1.0))])
    assert {round(x, 9) for x in table(sync_bp.run(g, 4, 1e-9).beliefs).values()} == {0.5}
    r = block_bp.run(g, partition.hash_parts(g, 2), BPConfig(damping=0.0))
    assert r.converged and {round(x, 9) for x in table(r.beliefs).values()} == {0.5}


def test_messages_sent_are_messages_received(spark):
    g = gallery.conversation_chains(spark, SMALL)
    r = block_bp.run(g, partition.hash_parts(g, 4), BPConfig(damping=0.0, beta=1e-8, send_every=0))
    assert r.converged
    assert sum(x["sent"] for x in r.rounds) == sum(x["received"] for x in r.rounds) > 0
    assert not block_bp.audit(g, r, 1e-6).count()


def test_pieces_are_dealt_evenly_and_a_cut_beats_hashing(spark):
    deal = partition.deal(spark, 40, 8, 1).groupBy("block").count().collect()
    assert {r["count"] for r in deal} == {5}
    g = gallery.grid_synthetic(spark, 12, 12, 3)
    costs, work = partition.edge_cost(g), partition.vertex_work(g)
    cut = partition.multilevel(g, 4).withColumnRenamed("piece", "block")
    assert partition.cut_cost(costs, cut).first()[0] < 0.4 * partition.cut_cost(costs, partition.hash_parts(g, 4)).first()[0]
    assert partition.work_balance(work, cut, 4).first()[0] < 1.3


def test_gibbs_chains_agree_with_exact(spark):
    g = gallery.literal(spark, [[0.0, 1.0], [0.0, 0.0], [0.5, 0.0]], [([0, 1], potts(2, 0.7)), ([1, 2], potts(2, 0.7))])
    want = table(exact.enumerate_all(g))
    for draw in (baselines.gibbs, baselines.gibbs_binary):
        s = draw(g, 6000, 500, 2)
        assert max(r["mean_l1"] for r in baselines.agreement(s).collect()) < 0.08
        got = table(s.where("chain = 0"))
        assert max(abs(got[k] - want[k]) for k in want) < 0.04


def test_only_mail_is_shuffled(spark):
    g = gallery.conversation_chains(spark, SMALL)
    cfg = BPConfig(damping=0.0, beta=1e-8, send_every=1, pass_share=0.0)
    r = block_bp.resume(block_bp.Result(g, block_bp.place(g, partition.hash_parts(g, 6), cfg)), cfg, max_rounds=2)
    assert r.mail_bytes and not r.converged
    plan = block_bp.superstep(r.state, r.mail, r.mail_bytes, cfg)._jdf.queryExecution().executedPlan().toString()
    # One exchange, of the mail; states are scanned where they are and joined by a broadcast.
    assert plan.count("Exchange hashpartitioning(") == 1 and "BroadcastHashJoin" in plan and "kind=state" not in plan.split("Exchange hashpartitioning(")[1].split("FileScan")[0]
    assert plan.count("FileScan parquet") == 2 and "SortMergeJoin" not in plan


def test_rounds_take_even_time_and_mail_beyond_the_bound_is_shuffled(spark, monkeypatch):
    g = gallery.conversation_chains(spark, SMALL)
    cfg = BPConfig(damping=0.0, beta=1e-9, send_every=1, pass_share=0.0)
    run = lambda: block_bp.resume(block_bp.Result(g, block_bp.place(g, partition.hash_parts(g, 3), cfg)), cfg, max_rounds=24)
    r = run()
    ends = sorted({x["seconds"] for x in r.rounds})
    took = np.diff([0.0, *ends])
    assert len(took) == 24 and np.median(took[-6:]) < 2.5 * np.median(took[2:8])
    monkeypatch.setattr(block_bp, "BROADCAST_MAIL", -1)
    counts = lambda x: sorted((y["round"], y["block"], y["vertex_updates"], y["sent"], y["received"]) for y in x.rounds if y["round"] < 5)
    cfg2 = cfg
    other = block_bp.resume(block_bp.Result(g, block_bp.place(g, partition.hash_parts(g, 3), cfg2)), cfg2, max_rounds=5)
    assert counts(other) == counts(r)


def test_reduced_evidence_equals_clamped(spark):
    g = gallery.literal(spark, [[0.0, 0.3], [0.0, 0.0], [0.2, 0.0, 0.1], [0.0, 0.4]], [([0, 1], potts(2, 0.7)), ([1, 2, 3], [0.1 * k for k in range(12)]), ([2, 0], [0.3, 0.0, 0.1, 0.5, 0.0, 0.2]), ([1], [0.0, 0.3])])
    seen = spark.createDataFrame([(2, 1), (4, 2), (6, None)], "vid long, state int")
    left = g.with_evidence(seen, "reduce")
    assert not [r for r in left.validate().collect() if r["violations"]]
    clamped, reduced = (table(exact.enumerate_all(x)) for x in (g.with_evidence(seen), left))
    assert {k[0] for k in reduced} == {0, 6} and all(abs(reduced[k] - clamped[k]) < 1e-9 for k in reduced)
    with pytest.raises(ValueError):
        g.with_evidence(seen, "drop")


def test_coarsening_goes_on_until_the_driver_can_take_it(spark):
    g = gallery.literal(spark, [[0.0, 0.0]] * 120, [([0, k], potts(2, 0.1)) for k in range(1, 60)])  # a star, and variables without a factor
    placed = partition.multilevel(g, 2, driver_vertices=30).collect()
    assert len({r["vid"] for r in placed}) == len(placed) == g.variables.count() + g.edges.select("fid").distinct().count()
    assert {r["piece"] for r in placed} <= {0, 1}


def test_streams_equal_their_batch_twins(spark, tmp_path):
    from pyspark.sql import functions as F

    from factorgraph_spark.streaming import evidence

    e = spark.read.parquet(f"{SMALL}/events.parquet").orderBy("ts").withColumn("part", F.floor(F.percent_rank().over(Window.orderBy("ts")) * 3.999))
    for k in range(4):
        e.where(F.col("part") == k).drop("part").coalesce(1).write.mode("append").parquet(f"{tmp_path}/events")
        time.sleep(1.1)  # files are taken in order of their time
    batch = spark.read.parquet(f"{tmp_path}/events").withColumn("ts", F.col("ts").cast("timestamp"))
    key = lambda df: sorted(map(str, df.collect()))
    for f in (evidence.tumbling_counts, evidence.sliding_counts, evidence.session_counts):
        assert key(evidence.drained(f(evidence.read_events(spark, f"{tmp_path}/events")), "complete")) == key(f(batch))
    # Appended windows are those that the watermark has passed, each once and final.
    final = key(evidence.drained(evidence.tumbling_counts(evidence.read_events(spark, f"{tmp_path}/events")), "append"))
    assert 0 < len(final) == len(set(final)) and set(final) <= set(key(evidence.tumbling_counts(batch)))
    twice = evidence.read_events(spark, f"{tmp_path}/events")
    assert evidence.drained(evidence.first_seen(twice.unionByName(twice)).select("event_id")).count() == batch.count()
    assert evidence.late_rows(batch, "2024-01-02 00:00:00").agg(F.sum("late")).first()[0] == batch.where("ts < '2024-01-02'").count()


def test_forward_filter_equals_recursion(spark, tmp_path):
    from factorgraph_spark.streaming import evidence

    e = spark.read.parquet(f"{SMALL}/events.parquet")
    e.coalesce(1).write.parquet(f"{tmp_path}/events")
    got = {(r["event_id"], r["state"]): r["belief"] for r in evidence.drained(evidence.forward_filter(evidence.read_events(spark, f"{tmp_path}/events"))).collect()}
    like, pair = np.array(gallery.emission()), np.exp(np.array(potts(3, gallery.STICKY)).reshape(3, 3))
    state = {}
    for r in sorted(e.collect(), key=lambda r: (r["ts"], r["event_id"])):
        p = state.get(r["user_id"], np.ones(3)) * like[:, gallery.EVENT_TYPES.index(r["event_type"])]
        p /= p.sum()
        assert all(abs(got[r["event_id"], k] - p[k]) < 1e-9 for k in range(3))
        state[r["user_id"]] = p @ pair
    assert len(got) == 3 * e.count()


def test_functions_of_the_sql_surface(spark):
    from factorgraph_spark.functions import surface

    surface.register(spark)
    r = spark.sql("SELECT bp_lse(array(0.0D, 0.0D)) AS a, bp_norm(array(1.0D, 1.0D)) AS b, bp_l1(array(0.0D, -700.0D), array(-700.0D, 0.0D)) AS c").first()
    assert abs(r["a"] - np.log(2)) < 1e-12 and np.allclose(r["b"], -np.log(2)) and abs(r["c"] - 2) < 1e-12
    p = spark.sql("SELECT bp_product(m) AS p FROM VALUES (array(0.0D, 1.0D)), (array(1.0D, 0.5D)) AS t(m)").first()["p"]
    assert np.allclose(p, np.exp([1.0, 1.5]) / np.exp([1.0, 1.5]).sum())


def test_workloads_are_sound(spark):
    for g in (gallery.docs_mln(spark, SMALL), gallery.page_hosts(spark, SMALL), gallery.events_chains(spark, SMALL)):
        assert {r["rule"]: r["violations"] for r in g.validate().collect() if r["violations"]} == {}
    assert np.allclose([sum(r) for r in gallery.emission()], 1)


def test_equal_texts_are_linked_however_many(spark, tmp_path):
    texts = {k: "The same twenty-four characters, then " + (f"another end {k}" if k % 5 else "a copy") for k in range(30)} | {40: None, 41: None, 42: "", 43: ""}
    spark.createDataFrame([(k, t, "en", "web") for k, t in texts.items()], "doc_id long, text string, lang string, source string").write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(1, 1, 0)], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    g = gallery.docs_mln(spark, str(tmp_path))
    assert not [r for r in g.validate().collect() if r["violations"]]
    prior = {r["vid"]: r["prior"][1] for r in g.variables.collect()}
    factors = {}
    for r in g.edges.collect():
        factors.setdefault(r["fid"], {})[r["slot"]] = r["vid"]
    same = [(f[1] // 16, f[2] // 16) for f in factors.values() if len(f) == 3 and prior[f[0]] == 3.0 and f[1] // 2 % 8 == f[2] // 2 % 8 == gallery.ORDER]
    klass = {k: k for k in texts}
    for _ in texts:
        for a, b in same:
            klass[a] = klass[b] = min(klass[a], klass[b])
    for a in texts:
        for b in texts:
            assert (klass[a] == klass[b]) == (a == b or (texts[a] is not None and texts[a] == texts[b]))


def test_ablation_runs_to_convergence(spark):
    from factorgraph_spark.plans import catalogue

    rows = catalogue.queries()["exp_ablation_docs"](spark, SMALL).collect()
    assert len({(r["residual"], r["sweep"]) for r in rows}) == 4
    assert len([r for r in rows if r["converged"]]) == 4


def test_the_ablation_runs_in_tasks(spark, monkeypatch):
    from factorgraph_spark.plans import experiments, gallery

    def refuse(*a):
        raise AssertionError("the driver holds the graph")

    monkeypatch.setattr(baselines, "whole_block", refuse)
    g = gallery.docs_mln(spark, SMALL)
    rows = experiments.ablate(g, BPConfig(beta=1e-2)).collect()
    assert sorted((r["residual"], r["sweep"]) for r in rows if r["converged"]) == [(a, b) for a in ("belief", "message") for b in ("volume", "work")]
    none = type(g)(g.variables.where("false"), g.edges.where("false"), g.potentials)
    assert [(r["vertex_updates"], r["converged"]) for r in experiments.ablate(none).collect()] == [(0, True)] * 4


def test_runs_of_an_experiment_leave_no_states(spark):
    import os

    from factorgraph_spark.plans import experiments
    from factorgraph_spark.sources.tables import shared_dir

    held = lambda: {x for x in os.listdir(shared_dir(spark).removeprefix("file:")) if x.startswith(("round-", "blocks-", "placed-"))}
    before, g = held(), experiments.settled(gallery.grid_synthetic(spark, 6, 6, 2))
    rows = experiments.scaling(g, (1, 2), (1, 2), BPConfig(beta=1e-3)).collect()
    assert len(rows) == 3 and all(r["converged"] for r in rows) and held() == before
    r = block_bp.run(g, cfg=BPConfig(beta=1e-3, workers=2, over=2))
    assert r.beliefs.count() == 72 and len(held() - before) == 1


def test_update_counts_come_from_blocks(spark, monkeypatch):
    from factorgraph_spark.plans import experiments

    def refuse(*a):
        raise AssertionError("the driver holds the graph")

    monkeypatch.setattr(baselines, "whole_block", refuse)
    seen, run = [], block_bp.run_converged
    monkeypatch.setattr(block_bp, "run_converged", lambda g, assign, cfg: seen.append(assign.select("block").distinct().count()) or run(g, assign, cfg))
    g = experiments.settled(gallery.grid_synthetic(spark, 8, 8, 2))
    for most in (40_000, 32):  # 176 vertices: blocks of the first cut, and smaller ones
        monkeypatch.setattr(experiments, "BLOCK_VERTICES", most)
        got = experiments.table1(g, 3, BPConfig(beta=1e-3), None)
        assert got["parts"] == 3 and got["rel_com_cost"] > 0 and 1 <= got["rel_work_balance"] <= 3
    assert seen == [3, 6]


def test_experiments_are_registered_on_the_tables_in_full(spark, monkeypatch):
    from factorgraph_spark.plans import catalogue, experiments

    q, seen = catalogue.queries(), []
    names = ("parts", "rel_com_cost", "rel_work_balance", "informed_balance", "partition_seconds")
    monkeypatch.setattr(experiments, "table1", lambda g, parts, cfg, bound: seen.append((g.variables.count(), parts, bound)) or dict(zip(names, (parts, 1.0, 1.0, 1.0, 1.0))))
    monkeypatch.setattr(experiments, "scaling", lambda g, *a: seen.append((g.variables.count(), *a[:2])) or spark.createDataFrame([(1,)], "workers int"))
    monkeypatch.setattr(experiments, "overpartition_trials", lambda g, *a: seen.append((g.variables.count(), *a)) or spark.createDataFrame([(1,)], "over int"))
    monkeypatch.setattr(block_bp, "run", lambda g, cfg: seen.append((g.variables.count(), cfg.workers, cfg.max_rounds)) or block_bp.Result(g, g.variables))
    grid, returns, docs = (g(spark, SMALL).variables.count() for g in (gallery.grid_lineitem, gallery.returns_mln, gallery.docs_mln))
    assert [r["graph"] for r in q["exp_table1_grid"](spark, SMALL).collect()] == ["grid_lineitem", "returns_mln", "docs_mln"]
    assert [r["graph"] for r in q["exp_scaling_grid"](spark, SMALL).collect()] == ["grid_lineitem", "returns_mln"]
    q["exp_overpartition_trials"](spark, SMALL), q["block_bp_round_log"](spark, SMALL)
    workers = (1, 2, 4, 8, 20, 60, 120)
    assert seen[:3] == [(grid, 120, None), (returns, 120, None), (docs, 120, None)]
    assert seen[3:] == [(grid, workers, (1, 5)), (returns, workers, (1, 5)), (grid, 60, (1, 2, 5, 10), 30), (grid, 4, 500)]


def test_gibbs_accuracy_draws_every_sample(spark, monkeypatch):
    from factorgraph_spark.plans import catalogue

    drawn, draw = [], baselines.gibbs_binary
    monkeypatch.setattr(baselines, "gibbs_binary", lambda g, samples=125_000, burn_in=25_000, chains=4: drawn.append((samples, burn_in, chains)) or draw(g, samples, burn_in, chains))
    rows = catalogue.queries()["gibbs_accuracy"](spark, SMALL).collect()
    assert drawn == [(125_000, 25_000, 4)] and len(rows) == 6 and max(r["mean_l1"] for r in rows) < 0.05


def test_incremental_takes_all_evidence(spark):
    from pyspark.sql import functions as F

    from factorgraph_spark.streaming import evidence

    g = gallery.literal(spark, [[0.0, 0.0]] * 6, [([k, k + 1], potts(2, 0.7)) for k in range(5)])
    cfg = BPConfig(damping=0.0, beta=1e-9, workers=2, over=1)
    news = [(0, 1, 0.4), (0, 1, 0.5), (0, 0, 0.2), (10, 0, 1.5)]
    many = spark.range(120_000).select((F.col("id") % 2 * 6).alias("vid"), F.lit(1).alias("state"), F.lit(1e-5).alias("strength"))  # 0.6 each on 0 and 3
    e = many.unionByName(spark.createDataFrame(news, "vid long, state int, strength double"))
    first = block_bp.run(g, cfg=cfg)
    second = evidence.incremental(g, first, e, cfg)
    want = gallery.literal(spark, [[0.2, 1.5], [0.0, 0.0], [0.0, 0.0], [0.0, 0.6], [0.0, 0.0], [1.5, 0.0]], [([k, k + 1], potts(2, 0.7)) for k in range(5)])
    assert second.converged and close(second.beliefs, exact.enumerate_all(want))
    again = evidence.incremental(g, second, spark.createDataFrame([], e.schema), cfg)
    assert again.converged and close(again.beliefs, second.beliefs)


def test_blocks_of_the_flagship_grow_in_number_not_in_size(spark, monkeypatch):
    from factorgraph_spark.plans import catalogue

    g = gallery.snowflake_tree(spark, SMALL)
    sizes = []
    place = block_bp.place
    monkeypatch.setattr(catalogue, "BLOCK_VERTICES", 500)
    monkeypatch.setattr(block_bp, "place", lambda fg, assign, cfg: sizes.extend(r["count"] for r in assign.groupBy("block").count().collect()) or place(fg, assign, cfg))
    n, got = g.variables.count(), catalogue.flagship(spark, SMALL).count()
    assert got == n and len(sizes) > 8 and max(sizes) < 2 * n / 8
