"""The equations on ends of factors against those on tables of edges, and what the queries on them shuffle."""

import pytest
from pyspark.sql import functions as F

import __spark_entry__
from factorgraph_spark.operators import messages, pairwise
from factorgraph_spark.operators.model import linear_penalty, potts
from factorgraph_spark.plans import gallery

SMALL = "/root/testdata/sf0.001"


def mixed(spark):
    """Two and three states, a unary factor, parallel factors, a loop, an impossible pair and a variable on its own."""
    skew = [0.3, -0.2, 0.9, 0.0, -700.0, 0.4]
    factors = [([0, 1], skew), ([1, 2], linear_penalty(3, 0.5)), ([2, 0], [0.1, 0.5, 0.2, 0.0, 1.0, -1.0]), ([0], [0.0, 1.5]), ([0, 1], skew), ([3, 0], potts(2, 0.8))]
    return gallery.literal(spark, [[0.0, 0.4], [0.1, 0.0, -0.3], [0.0, 0.2, 0.9], [0.0, -1.0], [0.0, 2.0, 1.0]], factors)


def held(df):
    return {(r["fid"], r["slot"]): (list(r["f2v"]), r["delta"]) for r in df.select("fid", "slot", "f2v", "delta").collect()}


@pytest.mark.parametrize("damping, space", [(0.0, "prob"), (0.6, "prob"), (0.6, "log")])
def test_ends_repeat_the_equations_on_edges(spark, damping, space):
    g = mixed(spark)
    state, values = messages.uniform(g), pairwise.tables(g, 3)
    rows = pairwise.start(g, 3, fids=True).withColumns({"q1": F.lit(0.0), "q2": F.lit(0.0)})
    for _ in range(3):
        state = messages.step(g, state.drop("delta"), 3, 2, damping, space).localCheckpoint()
        rows = pairwise.step(rows, values, 3, True, damping, space).localCheckpoint()
        got, want = held(pairwise.edges(rows, g, 3)), held(state)
        assert got.keys() == want.keys()
        for k in want:
            assert got[k][0] == pytest.approx(want[k][0], abs=1e-9) and got[k][1] == pytest.approx(want[k][1], abs=1e-9)
        rows = pairwise.gathered(rows)
        a, b = ({(r["vid"], r["state"]): r["belief"] for r in df.collect()} for df in (pairwise.beliefs(rows, 3), messages.beliefs(g, state, 3)))
        assert a == pytest.approx(b, abs=1e-9)


@pytest.mark.parametrize("name", ["msg_factor_to_var_step", "msg_binary_logodds_step", "residual_message", "beliefs_variable"])
def test_a_step_shuffles_little(spark, name):
    # Grounding takes 13 shuffles, the step 2; by tables of edges all was 33 to 52.
    plan = __spark_entry__.queries()[name](spark, SMALL)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning") <= 20


def test_landing_every_iteration_changes_nothing(spark, monkeypatch):
    from factorgraph_spark.operators import sync_bp

    g = mixed(spark)
    runs = []
    for rows in (0, 10**9):
        monkeypatch.setattr(sync_bp, "LANDED_ROWS", rows)
        runs.append(sync_bp.run(g, 12, 1e-3, 0.3, every=5))
    a, b = ({(r["vid"], r["state"]): r["belief"] for r in x.beliefs.collect()} for x in runs)
    assert a == pytest.approx(b, abs=1e-12) and [t for t, _ in runs[0].log] == [t for t, _ in runs[1].log] and runs[0].converged == runs[1].converged
    assert {t % 5 for t, _ in runs[0].log[:-1]} <= {0} and held(runs[0].state).keys() == held(messages.step(g, messages.uniform(g), 3, 2)).keys()


@pytest.mark.parametrize("name", ["sync_bp_convergence_log", "sync_bp_returns_t3", "sync_bp_snowflake"])
def test_a_run_holds_one_iteration(spark, name):
    # Before, checkpoints of the graph's tables and of every state were left in the shared folder.
    from pathlib import Path

    shared = Path(spark.conf.get("spark.checkpoint.dir"))
    there = lambda: {p for pattern in ("iteration-*", "*/rdd-*") for p in shared.glob(pattern)}
    before = there()
    __spark_entry__.queries()[name](spark, SMALL).collect()
    assert len(there() - before) == 1
