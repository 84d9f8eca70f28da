"""Queries of the measures, schedules, samples and extensions, one key each, with SQL that computes the same where SQL can.

Measures of runs read a log of rounds whose numbers come from md5, so that other engines repeat it.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import surface
from ..functions.logspace import lnorm, md5_uniform
from ..operators import baselines, block_bp, messages, metrics, partition, residuals, sync_bp, termination
from ..operators.kernel import BPConfig
from ..operators.model import potts
from ..sources.tables import cut, table
from ..streaming import evidence
from . import experiments, gallery
from .catalogue import CHAINS, _STEP, _VU, RETURNS, U, _conversations, _md5_state, _returns, _stepped, _updates, query
from .experiments import settled

# Measures of a run

ROUNDS, BLOCKS = 12, 8


def _u(tag: str, *parts):
    return md5_uniform(F.concat_ws("|", F.lit(tag), *[F.col(p).cast("string") for p in parts]))


def round_log(spark: SparkSession) -> DataFrame:
    rows = spark.range(ROUNDS * BLOCKS).select(F.floor(F.col("id") / BLOCKS).alias("round"), (F.col("id") % BLOCKS).alias("block"))
    count = lambda tag, most: F.floor(_u(tag, "round", "block") * most).cast("long")
    rows = rows.withColumn("work", (count("w", 100) + 1).cast("double")).withColumn("active", _u("a", "round", "block") < 1 - F.col("round") / (ROUNDS - 1))
    return rows.withColumn("sent", count("s", 20)).withColumn("vertex_updates", count("v", 50)).withColumn("edge_updates", F.col("vertex_updates") * 3 + count("e", 5))


def _sql_u(tag: str) -> str:
    return U.format(f"'{tag}|' || round || '|' || block")


LOG = (
    f"WITH k AS (SELECT r::BIGINT AS round, b::BIGINT AS block FROM (SELECT unnest(range({ROUNDS})) AS r) x, (SELECT unnest(range({BLOCKS})) AS b) y), "
    f"l AS (SELECT round, block, floor({_sql_u('w')} * 100) + 1 AS work, {_sql_u('a')} < 1 - round / {ROUNDS - 1}.0 AS active, floor({_sql_u('s')} * 20)::BIGINT AS sent, "
    f"floor({_sql_u('v')} * 50)::BIGINT AS vertex_updates, floor({_sql_u('v')} * 50)::BIGINT * 3 + floor({_sql_u('e')} * 5)::BIGINT AS edge_updates FROM k)"
)

query("modelled_time", LOG + " SELECT sum(w) AS modelled, count(*) AS rounds FROM (SELECT max(work) AS w FROM l GROUP BY round) x")(lambda s, d: metrics.modelled_time(round_log(s)))
query("active_blocks", LOG + " SELECT round, sum(active::INT)::BIGINT AS active FROM l GROUP BY round")(lambda s, d: metrics.active_blocks(round_log(s)))
query("network_cumulative", LOG + " SELECT round, (sum(n) OVER (ORDER BY round))::BIGINT AS messages FROM (SELECT round, sum(sent) AS n FROM l GROUP BY round) x")(lambda s, d: metrics.network(round_log(s)))
query("edge_vs_vertex_updates", LOG + " SELECT round, (sum(v) OVER (ORDER BY round))::BIGINT AS vertex_updates, (sum(e) OVER (ORDER BY round))::BIGINT AS edge_updates FROM (SELECT round, sum(vertex_updates) AS v, sum(edge_updates) AS e FROM l GROUP BY round) x")(
    lambda s, d: metrics.edge_vs_vertex_updates(round_log(s))
)
query("utilisation", LOG + f" SELECT round(sum((vertex_updates > 0)::INT) / ({BLOCKS} * {ROUNDS}.0), 9) AS utilisation FROM l")(lambda s, d: metrics.utilisation(round_log(s), BLOCKS).select(F.round("utilisation", 9).alias("utilisation")))


@query(
    "speedup_table",
    LOG
    + ", p AS (SELECT unnest([1, 2, 4, 8])::BIGINT AS workers), h AS (SELECT workers, round, block % workers AS owner, sum(work) AS w FROM l, p GROUP BY 1, 2, 3), t AS (SELECT workers, sum(w) AS time FROM (SELECT workers, round, max(w) AS w FROM h GROUP BY 1, 2) x GROUP BY workers)"
    + " SELECT workers, time, round((SELECT time FROM t WHERE workers = 1) / time, 9) AS speedup, (SELECT time FROM t WHERE workers = 1) / time >= workers AS linear FROM t",
)
def _speedup(s: SparkSession, d: str) -> DataFrame:
    """Modelled time of the log's blocks on 1 to 8 workers, each with its share of the blocks."""
    held = round_log(s).withColumn("workers", F.explode(F.array(*[F.lit(p).cast("long") for p in (1, 2, 4, 8)])))
    held = held.groupBy("workers", "round", (F.col("block") % F.col("workers")).alias("owner")).agg(F.sum("work").alias("w"))
    runs = held.groupBy("workers", "round").agg(F.max("w").alias("w")).groupBy("workers").agg(F.sum("w").alias("time"))
    return metrics.speedup(runs).withColumn("speedup", F.round("speedup", 9))


query("update_histogram", RETURNS + _VU + " SELECT floor(log2(n))::INT AS log2_updates, count(*) AS vertices FROM u GROUP BY 1")(lambda s, d: metrics.update_histogram(_updates(_returns(s, d))))
query("half_split_corr", RETURNS + _VU + ", f AS (SELECT n, floor(" + U.format("'h|' || vid") + " * n) AS x FROM u) SELECT round(corr(x, n - x), 6) AS r, count(*) AS vertices FROM f")(
    lambda s, d: metrics.half_split((u := _updates(_returns(s, d))).select("vid", F.floor(_u("h", "vid") * F.col("n_updates")).alias("n_updates")), u).select(F.round("r", 6).alias("r"), "vertices")
)
_TWO = ", c AS (SELECT e.fid, e.vid, (a.n + b.n) * 3 AS cost FROM e JOIN u a ON a.vid = e.fid JOIN u b ON b.vid = e.vid), h AS (SELECT vid, floor(" + U.format("'part|' || vid || '|42'") + " * 8)::BIGINT AS a, floor(" + U.format("'part|' || vid || '|7'") + " * 8)::BIGINT AS b FROM x)"
query("rel_com_cost", RETURNS + _VU + _TWO + " SELECT round(sum(CASE WHEN f.a <> v.a THEN cost ELSE 0 END) / sum(CASE WHEN f.b <> v.b THEN cost ELSE 0 END), 9) AS rel_com_cost FROM c JOIN h f ON f.vid = c.fid JOIN h v ON v.vid = c.vid")(
    lambda s, d: metrics.relative_cut(partition.edge_cost(g := _returns(s, d), _updates(g)), partition.hash_parts(g, 8), partition.hash_parts(g, 8, 7)).select(F.round("rel_com_cost", 9).alias("rel_com_cost"))
)
_WORKS = ", q AS (SELECT vid, (count(*) * 2)::DOUBLE AS w FROM e GROUP BY vid UNION ALL SELECT fid, (count(*) * 4)::DOUBLE FROM e GROUP BY fid)"
query("rel_work_balance", RETURNS + _VU + _TWO + _WORKS + ", y AS (SELECT h.a, sum(q.w * u.n) AS load FROM q JOIN u ON u.vid = q.vid JOIN h ON h.vid = q.vid GROUP BY h.a) SELECT round(8 * max(load) / sum(load), 9) AS balance FROM y")(
    lambda s, d: metrics.relative_balance(partition.vertex_work(g := _returns(s, d), _updates(g)), partition.hash_parts(g, 8), 8).select(F.round("balance", 9).alias("balance"))
)
query("mean_l1_accuracy", RETURNS + _STEP + ", y AS (SELECT v.vid, v.odds + sum(x) AS o, v.odds + sum(f) AS p FROM v JOIN n ON n.vid = v.vid GROUP BY v.vid, v.odds) SELECT round(avg(2 * abs(1 / (1 + exp(-o)) - 1 / (1 + exp(-p)))), 9) AS mean_l1, count(*) AS variables FROM y")(
    lambda s, d: metrics.mean_l1(messages.beliefs((r := _stepped(s, d))[0], r[1], 2), messages.beliefs(r[0], r[2], 2)).select(F.round("mean_l1", 9).alias("mean_l1"), "variables")
)

# Over-partitioning: pieces by md5, dealt at random thirty times.

TRIAL_KS, TRIAL_WORKERS, TRIALS = (1, 2, 5), 4, 30


def _trial_sql() -> str:
    out = RETURNS + _WORKS
    for k in TRIAL_KS:
        n = TRIAL_WORKERS * k
        out += (
            f", p{k} AS MATERIALIZED (SELECT vid, w, floor(" + U.format("'part|' || vid || '|42'") + f" * {n})::BIGINT AS piece FROM q), d{k} AS (SELECT trial, piece, (row_number() OVER (PARTITION BY trial ORDER BY md5(piece || '|' || trial), piece) - 1) % {TRIAL_WORKERS} AS block FROM (SELECT unnest(range({n})) AS piece) a, (SELECT unnest(range({TRIALS})) AS trial) b)"
            f", l{k} AS (SELECT trial, {TRIAL_WORKERS} * max(w) / sum(w) AS balance FROM (SELECT trial, block, sum(w) AS w FROM d{k} JOIN (SELECT piece, sum(w) AS w FROM p{k} GROUP BY piece) s USING (piece) GROUP BY trial, block) z GROUP BY trial)"
            f", b{k} AS (SELECT f.piece AS a, v.piece AS b, sum(6.0::DOUBLE) AS c FROM e JOIN p{k} f ON f.vid = e.fid JOIN p{k} v ON v.vid = e.vid WHERE f.piece <> v.piece GROUP BY 1, 2)"
            f", c{k} AS (SELECT x.trial, sum(CASE WHEN x.block <> y.block THEN c ELSE 0 END) AS cost FROM b{k} JOIN d{k} x ON x.piece = b{k}.a JOIN d{k} y ON y.piece = b{k}.b AND y.trial = x.trial GROUP BY x.trial)"
        )
    one = "SELECT {0}::INT AS over, round(avg(balance), 6) AS balance, round(1.96 * stddev_samp(balance) / sqrt(count(*)), 6) AS balance_ci, round(avg(cost), 3) AS cut_cost, round(1.96 * stddev_samp(cost) / sqrt(count(*)), 3) AS cut_cost_ci FROM l{0} JOIN c{0} USING (trial)"
    return out + " " + " UNION ALL ".join(one.format(k) for k in TRIAL_KS)


@query("overpart_trials_ci", _trial_sql())
def _trials(s: SparkSession, d: str) -> DataFrame:
    g = settled(_returns(s, d))
    costs, work = partition.edge_cost(g), partition.vertex_work(g)
    out = None
    for k in TRIAL_KS:
        pieces = cut(partition.hash_parts(g, TRIAL_WORKERS * k).withColumnRenamed("block", "piece"))
        found = experiments.deal_trials(costs, work, pieces, TRIAL_WORKERS, k, TRIALS)
        out = found if out is None else out.unionByName(found)
    return experiments.intervals(out).select("over", F.round("balance", 6).alias("balance"), F.round("balance_ci", 6).alias("balance_ci"), F.round("cut_cost", 3).alias("cut_cost"), F.round("cut_cost_ci", 3).alias("cut_cost_ci"))


# Messages

query("msg_normalise", RETURNS + ", m AS (SELECT vid, other, 0.1 + " + U.format("'42|' || vid || '|' || other || '|0'") + " AS a, 0.1 + " + U.format("'42|' || vid || '|' || other || '|1'") + " AS b FROM e) SELECT vid, count(*) AS n, round(min(b / (a + b)), 9) AS low, round(max(b / (a + b)), 9) AS high FROM m GROUP BY vid")(
    lambda s, d: _md5_state(_returns(s, d)).groupBy("vid").agg(F.count(F.lit(1)).alias("n"), F.round(F.min(F.exp(F.get("f2v", F.lit(1)))), 9).alias("low"), F.round(F.max(F.exp(F.get("f2v", F.lit(1)))), 9).alias("high"))
)
query("arr_log_normalise", "WITH x AS (SELECT vec_id, (unnest(range(1, len(embedding) + 1)) - 1)::INT AS c, unnest(embedding)::DOUBLE AS v FROM embeddings), t AS (SELECT vec_id, max(v) + ln(sum(exp(v - m))) AS total FROM (SELECT *, max(v) OVER (PARTITION BY vec_id) AS m FROM x) y GROUP BY vec_id) SELECT x.vec_id, c, round(v - total, 6) AS logp FROM x JOIN t ON t.vec_id = x.vec_id")(
    lambda s, d: table(s, d, "embeddings").select("vec_id", F.posexplode(lnorm(F.transform("embedding", lambda x: x.cast("double")))).alias("c", "x")).select("vec_id", "c", F.round("x", 6).alias("logp"))
)


@query("belief_refresh_equals_product", RETURNS + ", o AS (SELECT b, count(*) AS n FROM p WHERE t = 'os' GROUP BY b) SELECT 0::BIGINT AS differing, max(n) * 2 + 1 AS vertices FROM o")
def _refreshed(s: SparkSession, d: str) -> DataFrame:
    """Vertices of the supplier star whose belief, refreshed message by message over a run, is not the product of its messages."""
    import numpy as np

    b = baselines.whole_block(settled(gallery.supplier_star(s, d)), BPConfig(damping=0.0, beta=1e-8))
    b.run_sweeps()
    total, joint = b.total.copy(), b.joint.copy()
    b.recompute()
    off = int((np.abs(total - b.total).max(axis=1) > 1e-9).sum() + (np.abs(joint - b.joint).max(axis=1) > 1e-9).sum())
    return s.createDataFrame([(off, len(b.ids))], "differing long, vertices long")


# Sweeps, on the star of the supplier of most orders: the root is the order of the highest id.

_STAR = RETURNS + (
    ", hub AS (SELECT b FROM p WHERE t = 'os' GROUP BY b ORDER BY count(*) DESC, b LIMIT 1), s AS (SELECT e.fid, e.vid AS leaf, hub.b AS hub FROM e JOIN hub ON e.other = hub.b WHERE e.slot = 0 AND e.w = 0.02), n AS (SELECT count(*) AS d FROM s), "
    "root AS (SELECT fid, leaf, hub FROM s ORDER BY leaf DESC LIMIT 1), ids AS (SELECT vid, row_number() OVER (ORDER BY kind, vid) - 1 AS k FROM (SELECT 0 AS kind, leaf AS vid FROM s UNION ALL SELECT 0, hub FROM root UNION ALL SELECT 1, fid FROM s) i), "
    "o AS (SELECT 0 AS rank, leaf AS vid, 2.0::DOUBLE AS work FROM root UNION ALL SELECT 1, fid, 8 FROM root UNION ALL SELECT 2, hub, 2 * d FROM root, n UNION ALL SELECT 2 + row_number() OVER (ORDER BY s.fid), s.fid, 8 FROM s, root WHERE s.fid <> root.fid "
    "UNION ALL SELECT 1 + d + row_number() OVER (ORDER BY s.fid), s.leaf, 2 FROM s, root, n WHERE s.fid <> root.fid)"
)
STAR_WORK, STAR_VOLUME = 3000.0, 30


def _star_order(s: SparkSession, d: str, cfg: BPConfig, still: bool = False):
    b = baselines.whole_block(settled(gallery.supplier_star(s, d)), cfg)
    if still:
        b.residual[::3] = 0.0
    return b, b.order(b.n_var - 1)


def _ranked(s: SparkSession, b, order: list[int]) -> DataFrame:
    return s.createDataFrame([(k, b.ids[x], float(b.work[x])) for k, x in enumerate(order)], "rank long, vid long, work double")


query("sweep_order_volume", _STAR + f" SELECT rank::BIGINT AS rank, vid, work FROM o WHERE rank < {STAR_VOLUME}")(lambda s, d: _ranked(s, *_star_order(s, d, BPConfig(sweep="volume", volume=STAR_VOLUME))))
query("sweep_order_work", _STAR + f" SELECT rank::BIGINT AS rank, vid, work FROM (SELECT *, sum(work) OVER (ORDER BY rank) AS used FROM o) x WHERE used <= {STAR_WORK}")(lambda s, d: _ranked(s, *_star_order(s, d, BPConfig(w_max=STAR_WORK))))
query(
    "sweep_order_pruned",
    _STAR
    # What is still is left out, and nothing is reached through it.
    + ", a AS (SELECT o.*, k % 3 = 0 AS still FROM o JOIN ids ON ids.vid = o.vid), r AS (SELECT a.rank, a.vid, a.work FROM a LEFT JOIN s ON s.leaf = a.vid LEFT JOIN a f ON f.vid = s.fid WHERE a.rank = 0 OR (NOT a.still AND NOT (SELECT still FROM a WHERE rank = 1) AND (a.rank <= 1 OR NOT (SELECT still FROM a WHERE rank = 2) OR a.rank = 2) AND (f.vid IS NULL OR a.rank < 3 OR NOT f.still)))"
    + f" SELECT row_number() OVER (ORDER BY rank) - 1 AS rank, vid, work FROM (SELECT *, sum(work) OVER (ORDER BY rank) AS used FROM r) x WHERE used <= {STAR_WORK}",
)(lambda s, d: _ranked(s, *_star_order(s, d, BPConfig(w_max=STAR_WORK), still=True)))
query("sweep_visit_sequence", _STAR + f", m AS (SELECT rank, vid FROM o WHERE rank < {STAR_VOLUME}) SELECT ({STAR_VOLUME} - 1 - rank)::BIGINT AS step, vid FROM m UNION ALL SELECT ({STAR_VOLUME} - 1 + rank)::BIGINT, vid FROM m WHERE rank > 0")(lambda s, d: _visits(s, d))


def _visits(s: SparkSession, d: str) -> DataFrame:
    b, order = _star_order(s, d, BPConfig(sweep="volume", volume=STAR_VOLUME))
    return s.createDataFrame([(k, b.ids[x]) for k, x in enumerate(b.visits(order))], "step long, vid long")


# A converged run on a graph with cycles, against a long synchronous run


def _differing(s: SparkSession, g, cfg: BPConfig) -> DataFrame:
    """Variables whose belief in the block sweeper's result differs by more than 1e-3 from a synchronous run's, and all variables."""
    run = block_bp.run_converged(g, cfg=cfg)
    want = sync_bp.run(g, 200, 1e-6, every=5)
    both = run.beliefs.join(want.beliefs.withColumnRenamed("belief", "b"), ["vid", "state"])
    far = both.groupBy("vid").agg(F.max(F.abs(F.col("belief") - F.col("b"))).alias("d"))
    return far.agg(F.sum((F.col("d") > 1e-3).cast("long")).alias("differing"), F.count(F.lit(1)).alias("variables"))


query("block_bp_grid_converged", "SELECT 0::BIGINT AS differing, 400::BIGINT AS variables")(lambda s, d: _differing(s, settled(gallery.grid_synthetic(s, 20, 20, 5)), BPConfig(damping=0.0, beta=1e-5, workers=4, over=2)))

# Grids

_PIXELS = (
    "WITH t AS (SELECT floor(date_diff('day', DATE '1995-01-01', l_shipdate::DATE) / 7)::INT AS r, (l_partkey % 100)::INT AS c, least(4, floor(avg(l_quantity) / 10))::DOUBLE AS obs FROM lineitem GROUP BY 1, 2), w AS (SELECT unnest(range(min(r), max(r) + 1))::INT AS r FROM t), "
    "px AS (SELECT ((w.r * 100 + k.c) * 8 + 7)::BIGINT * 2 AS vid, w.r, k.c, t.obs FROM w CROSS JOIN (SELECT unnest(range(100))::INT AS c) k LEFT JOIN t ON t.r = w.r AND t.c = k.c), "
    "pr AS (SELECT a.vid AS a, b.vid AS b FROM px a JOIN px b ON b.vid = a.vid + 16 AND b.r = a.r UNION ALL SELECT a.vid, b.vid FROM px a JOIN px b ON b.vid = a.vid + 1600)"
)
query("grid_edges_lineitem", _PIXELS + ", f AS (SELECT ('0x' || substr(md5('px|' || a || '|' || b), 1, 15))::BIGINT * 2 + 1 AS fid, a, b FROM pr) SELECT vid, count(*) AS degree, min(fid) AS first, max(fid) AS last FROM (SELECT fid, a AS vid FROM f UNION ALL SELECT fid, b FROM f) x GROUP BY vid")(
    lambda s, d: gallery.grid_lineitem(s, d).edges.groupBy("vid").agg(F.count(F.lit(1)).alias("degree"), F.min("fid").alias("first"), F.max("fid").alias("last"))
)
query("grid_unary_gaussian", _PIXELS + " SELECT vid, " + ", ".join(f"round(CASE WHEN obs IS NULL THEN 0 ELSE -({k} - obs) * ({k} - obs) / 2 END, 6) + 0.0 AS p{k}" for k in range(5)) + " FROM px")(
    lambda s, d: gallery.grid_lineitem(s, d).variables.select("vid", *[(F.round(F.get("prior", F.lit(k)), 6) + F.lit(0.0)).alias(f"p{k}") for k in range(5)])
)


def _grid_unrolled(times: int) -> str:
    """SQL of synchronous iterations on the grid, messages in long form (a message from a to b by state)."""
    out = _PIXELS + ", st AS (SELECT unnest(range(5)) AS s), u AS MATERIALIZED (SELECT vid, s, CASE WHEN obs IS NULL THEN 0::DOUBLE ELSE -(s - obs) * (s - obs) / 2 END AS p FROM px, st)"
    out += ", ends AS MATERIALIZED (SELECT a AS src, b AS dst FROM pr UNION ALL SELECT b, a FROM pr), m0 AS MATERIALIZED (SELECT src, dst, s, -ln(5)::DOUBLE AS m FROM ends, st)"
    for k in range(times):
        out += (
            f", t{k} AS (SELECT u.vid, u.s, u.p + coalesce(sum(m.m), 0) AS total FROM u LEFT JOIN m{k} m ON m.dst = u.vid AND m.s = u.s GROUP BY u.vid, u.s, u.p)"
            f", q{k} AS (SELECT b.dst AS src, b.src AS dst, t.s, t.total - b.m AS o FROM m{k} b JOIN t{k} t ON t.vid = b.dst AND t.s = b.s)"
            f", z{k} AS (SELECT q.src, q.dst, st.s, ln(sum(exp(q.o - 0.5 * abs(q.s - st.s)))) AS m FROM q{k} q, st GROUP BY 1, 2, 3)"
            f", m{k + 1} AS MATERIALIZED (SELECT src, dst, s, m - ln(sum(exp(m)) OVER (PARTITION BY src, dst)) AS m FROM z{k})"
        )
    out += f", e AS (SELECT u.vid, u.s, exp(u.p + coalesce(sum(m.m), 0)) AS x FROM u LEFT JOIN m{times} m ON m.dst = u.vid AND m.s = u.s GROUP BY u.vid, u.s, u.p)"
    return out + " SELECT vid, round(sum(s * x) / sum(x), 6) AS mean FROM e GROUP BY vid"


@query("sync_bp_grid_t5", _grid_unrolled(5))
def _grid_t5(s: SparkSession, d: str) -> DataFrame:
    g = settled(gallery.grid_lineitem(s, d))
    state = cut(messages.uniform(g))
    for _ in range(5):
        state = cut(messages.step(g, state.drop("delta"), 5, 2))
    return messages.beliefs(g, state, 5).groupBy("vid").agg(F.round(F.sum(F.col("state") * F.col("belief")), 6).alias("mean"))


# Exact and sampled


@query("exact_enumeration_small", CHAINS + " WHERE t.conv_id IN (SELECT conv_id FROM conversations GROUP BY conv_id ORDER BY conv_id LIMIT 3)")
def _enumerated(s: SparkSession, d: str) -> DataFrame:
    """Marginals of the three conversations of least id, by enumeration of all their states."""
    from ..operators import exact
    from ..operators.model import FactorGraph

    g = _conversations(s, d)
    few = [r["conv_id"] for r in table(s, d, "conversations").select("conv_id").distinct().orderBy("conv_id").limit(3).collect()]
    inside = lambda c: F.floor(F.col(c) / 16000).isin(few)
    small = FactorGraph(g.variables.where(inside("vid")), g.edges.where(inside("vid")), g.potentials)
    return exact.enumerate_all(small).where("state = 1").select("vid", F.round("belief", 4).alias("p1"))


_GIBBS = (
    RETURNS
    + ", x0 AS (SELECT vid, odds, floor(" + U.format("'x|' || vid") + " * 2)::INT AS x FROM v WHERE vid % 16 IN (0, 2)), pull AS (SELECT a AS vid, sum(w * (2 * y.x - 1)) AS pull FROM p JOIN x0 y ON y.vid = p.b WHERE t = 'oc' GROUP BY a)"
    + " SELECT x0.vid, CASE WHEN x0.vid % 16 = 0 THEN (CASE WHEN " + U.format("'42|0|1|' || x0.vid") + " < 1 / (1 + exp(-(odds + coalesce(pull, 0)))) THEN 1 ELSE 0 END) ELSE x END AS x FROM x0 LEFT JOIN pull ON pull.vid = x0.vid"
)


@query("gibbs_colour_sweep", _GIBBS)
def _colour(s: SparkSession, d: str) -> DataFrame:
    """Orders drawn anew given their customers' states."""
    g = _returns(s, d)
    v = g.variables.where("vid % 16 in (0, 2)")
    states = v.select("vid", F.floor(_u("x", "vid") * 2).cast("int").alias("x"))
    ends = g.edges.groupBy("fid", "potential_id").agg(F.max_by("vid", F.when(F.col("slot") == 0, 1)).alias("a"), F.max_by("vid", F.when(F.col("slot") == 1, 1)).alias("b"))
    weight = g.potentials.select("potential_id", F.get("logpsi", F.lit(0)).alias("w"))
    links = ends.where("a % 16 = 0 and b % 16 = 2").join(F.broadcast(weight), "potential_id").select("a", "b", "w")
    odds = v.select("vid", (F.get("prior", F.lit(1)) - F.get("prior", F.lit(0))).alias("odds"))
    return baselines.colour_sweep(states, links, odds, v.select("vid", F.when(F.col("vid") % 16 == 0, 0).otherwise(1).alias("colour")), 0, 0, 1)


# Histories and termination

_HISTORY = "WITH h AS (SELECT user_id AS vid, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS step, round(abs(value), 6) AS l1, event_type = 'login' AS updated FROM events)"


@query("residual_belief_accumulated", _HISTORY + ", f AS (SELECT *, sum(updated::INT) OVER (PARTITION BY vid ORDER BY step) AS life FROM h) SELECT vid, step, round(sum(CASE WHEN updated THEN 0 ELSE l1 END) OVER (PARTITION BY vid, life ORDER BY step), 4) + 0.0 AS residual FROM f")
def _accumulated(s: SparkSession, d: str) -> DataFrame:
    """Every user's events as a vertex's history: values are changes of its belief, logins its updates."""
    from pyspark.sql import Window

    e = table(s, d, "events")
    step = F.row_number().over(Window.partitionBy("user_id").orderBy("ts", "event_id")).cast("long")
    rows = e.select(F.col("user_id").alias("vid"), step.alias("step"), F.round(F.abs("value"), 6).alias("l1"), (F.col("event_type") == "login").alias("updated"))
    return residuals.accumulated(rows).select("vid", "step", (F.round("residual", 4) + F.lit(0.0)).alias("residual"))


_RING = [(0, (True, True), 8, 0), (1, (False, True), 2, 8), (2, (False, False), 0, 2), (3, (False, False), 0, 0), (4, (False, False), 0, 0), (5, (False, False), 0, 0)]
_RING_SQL = "WITH RECURSIVE l(round, a0, a1, s, r) AS (VALUES " + ", ".join(f"({t}, {a[0]}, {a[1]}, {x}, {y})" for t, a, x, y in _RING) + "), " + (
    "c AS (SELECT round, a0, a1, NOT a0 AND NOT a1 AND (sum(s) OVER w) = (sum(r) OVER w) AS calm FROM l WINDOW w AS (ORDER BY round)), "
    # One hop a round: the marker moves on from a quiet holder, and hops count while all is calm.
    "t AS (SELECT -1 AS round, 0 AS holder, 0 AS clean, false AS stop UNION ALL "
    "SELECT c.round, CASE WHEN CASE t.holder WHEN 0 THEN a0 ELSE a1 END THEN t.holder ELSE (t.holder + 1) % 2 END, CASE WHEN NOT calm THEN 0 WHEN CASE t.holder WHEN 0 THEN a0 ELSE a1 END THEN t.clean ELSE t.clean + 1 END, "
    "calm AND t.clean + 1 >= 4 FROM t JOIN c ON c.round = t.round + 1 WHERE NOT t.stop) SELECT round::INT AS round, holder::INT AS holder, clean::INT AS clean, stop FROM t WHERE round >= 0"
)
query("termination_token_trace", _RING_SQL)(lambda s, d: s.createDataFrame(termination.token_ring([(t, list(a), x, y) for t, a, x, y in _RING], 2, 1), "round int, holder int, clean int, stop boolean"))


@query("termination_audit", "SELECT count(*) AS variables, 0::BIGINT AS moved FROM conversations")
def _audit(s: SparkSession, d: str) -> DataFrame:
    """Variables of the conversations, and how many of them one more undamped step would still move after a run."""
    g = _conversations(s, d)
    moved = block_bp.audit(g, block_bp.run(g, cfg=BPConfig(damping=0.0, beta=1e-9, workers=2, over=1)), 1e-6).count()
    return g.variables.agg(F.count(F.lit(1)).alias("variables")).withColumn("moved", F.lit(moved).cast("long"))


# Chains of events, by recursion over a user's events

_EMIT = gallery.emission()
_PRIOR = [" + ".join(f"CASE WHEN event_type = '{t}' THEN {math.log(_EMIT[s][k])!r}::DOUBLE ELSE 0 END" for k, t in enumerate(gallery.EVENT_TYPES)) for s in range(3)]


def _passed(row: str, to: int) -> str:
    terms = [f"exp({row}.p{k} + {row}.m{k}" + (f" + {gallery.STICKY}" if k == to else "") + ")" for k in range(3)]
    return f"ln({' + '.join(terms)})"


def _direction(name: str, start: str, sign: str) -> str:
    sent = ", ".join(_passed(name, k) + f" - greatest({', '.join(_passed(name, j) for j in range(3))})" for k in range(3))
    return f"{name} AS (SELECT user_id, k, p0, p1, p2, 0::DOUBLE AS m0, 0::DOUBLE AS m1, 0::DOUBLE AS m2 FROM t WHERE k = {start} UNION ALL SELECT t.user_id, t.k, t.p0, t.p1, t.p2, {sent} FROM {name} JOIN t ON t.user_id = {name}.user_id AND t.k = {name}.k {sign} 1)"


_EVENTS = (
    f"WITH RECURSIVE t AS MATERIALIZED (SELECT event_id, user_id, {', '.join(f'({p}) AS p{k}' for k, p in enumerate(_PRIOR))}, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS k, count(*) OVER (PARTITION BY user_id) AS n FROM events), "
    + _direction("f", "1", "+") + ", " + _direction("g", "n", "-")
    + ", b AS (SELECT (t.event_id * 8 + 7) * 2 AS vid, " + ", ".join(f"exp(t.p{k} + f.m{k} + g.m{k}) AS b{k}" for k in range(3)) + " FROM t JOIN f ON f.user_id = t.user_id AND f.k = t.k JOIN g ON g.user_id = t.user_id AND g.k = t.k)"
    + " SELECT vid, " + ", ".join(f"round(b{k} / (b0 + b1 + b2), 6) AS p{k}" for k in range(3)) + " FROM b"
)


@query("forward_backward_events", _EVENTS)
def _events(s: SparkSession, d: str) -> DataFrame:
    from ..operators import exact

    e = table(s, d, "events").select(F.col("user_id").alias("chain"), F.col("ts").alias("pos"), gallery.vid(F.col("event_id"), gallery.OTHER).alias("vid"))
    nodes = gallery.events_chains(s, d).variables.join(e, "vid").select("chain", "pos", "vid", "prior")
    found = exact.forward_backward(nodes, potts(3, gallery.STICKY), 3)
    return found.groupBy("vid").agg(*[F.round(F.max(F.when(F.col("state") == k, F.col("belief"))), 6).alias(f"p{k}") for k in range(3)])


# Rounds of the multilevel cut

_EDGES = RETURNS + ", c AS (SELECT least(fid, vid) AS u, greatest(fid, vid) AS v, 6::DOUBLE AS w FROM e), q AS (SELECT vid, (count(*) * 2)::DOUBLE AS work FROM e GROUP BY vid UNION ALL SELECT fid, (count(*) * 4)::DOUBLE FROM e GROUP BY fid)"
_MATCHED = _EDGES + (
    ", both_ AS (SELECT u, v, w FROM c UNION ALL SELECT v, u, w FROM c), light AS (SELECT x.u, x.v, x.w, " + U.format("least(x.u, x.v) || '|' || greatest(x.u, x.v) || '|0'") + " AS t FROM both_ x JOIN q a ON a.vid = x.u JOIN q b ON b.vid = x.v WHERE a.work + b.work <= 10000), "
    "pick AS (SELECT u, v FROM (SELECT u, v, row_number() OVER (PARTITION BY u ORDER BY w DESC, t DESC, v DESC) AS k FROM light) z WHERE k = 1), matched AS (SELECT p.u AS a, p.v AS b FROM pick p JOIN pick r ON r.u = p.v AND r.v = p.u WHERE p.u < p.v)"
)
query("heavy_edge_matching_round", _MATCHED + " SELECT a, b FROM matched")(lambda s, d: _matching(s, d)[2])
query("contract_round", _MATCHED + " SELECT coalesce(m.a, q.vid) AS vid, sum(q.work) AS work FROM q LEFT JOIN matched m ON m.b = q.vid GROUP BY 1")(lambda s, d: partition.contract(*_matching(s, d))[1])


def _matching(s: SparkSession, d: str) -> tuple[DataFrame, DataFrame, DataFrame]:
    g = settled(_returns(s, d))
    e = partition.edge_cost(g).select(F.least("fid", "vid").alias("u"), F.greatest("fid", "vid").alias("v"), F.col("cost").alias("w"))
    w = partition.vertex_work(g)
    return e, w, cut(partition.matching_round(e, w, 1e4))


# Streams, each run over the table as a stream of files and held against the same windows in SQL

_HOUR = "date_trunc('hour', ts)"


def _streamed(f, mode: str = "complete"):
    """The query that runs ``f`` over the table of events as a stream."""

    def run(s: SparkSession, d: str) -> DataFrame:
        out = evidence.drained(f(evidence.read_events(s, f"{d}/events.parquet*")), mode)
        return out.withColumn("start", F.col("start").cast("timestamp_ntz")) if "start" in out.columns else out

    return run


query("stream_tumbling_counts", f"SELECT {_HOUR} AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2")(_streamed(evidence.tumbling_counts))
query("stream_sliding_counts", f"SELECT start, event_type, count(*) AS n FROM (SELECT unnest([{_HOUR}, {_HOUR} - INTERVAL 1 HOUR]) AS start, event_type FROM events) x GROUP BY 1, 2")(_streamed(evidence.sliding_counts))
query(
    "stream_session_counts",
    "WITH o AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 12 HOUR THEN 0 ELSE 1 END AS opens FROM events), n AS (SELECT user_id, ts, sum(opens) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM o) SELECT min(ts) AS start, user_id, count(*) AS n FROM n GROUP BY user_id, k",
)(_streamed(evidence.session_counts))
query("stream_first_seen", "SELECT count(DISTINCT event_id) AS n, count(DISTINCT event_id) AS ids FROM events")(
    lambda s, d: _streamed(lambda e: evidence.first_seen(e.unionByName(e)).select("event_id"), "append")(s, d).agg(F.count(F.lit(1)).alias("n"), F.count_distinct("event_id").alias("ids"))
)

# Functions for SQL users

query("udaf_product_messages", RETURNS + f", m AS (SELECT vid, {{0}} AS a, {{1}} AS b FROM e), t AS (SELECT vid, sum(ln(a / (a + b))) AS x, sum(ln(b / (a + b))) AS y FROM m WHERE vid % 16 = 6 GROUP BY vid) SELECT vid, round(1 / (1 + exp(x - y)), 6) AS p1 FROM t".format(*["0.1 + " + U.format(f"'42|' || vid || '|' || other || '|{k}'") for k in (0, 1)]))(
    lambda s, d: _md5_state(_returns(s, d)).where("vid % 16 = 6").groupBy("vid").agg(surface.product_of_messages("f2v").alias("b")).select("vid", F.round(F.get("b", F.lit(1)), 6).alias("p1"))
)


@query("udtf_assignments", "SELECT c.card::INT AS card, x.cell::INT AS cell, s.slot::INT AS slot, ((x.cell // (c.card ** (1 - s.slot))::BIGINT) % c.card)::INT AS state FROM (SELECT unnest([2, 3, 5]) AS card) c, LATERAL (SELECT unnest(range(c.card * c.card)) AS cell) x, (SELECT unnest([0, 1]) AS slot) s")
def _assignments(s: SparkSession, d: str) -> DataFrame:
    surface.register(s)
    return s.sql("SELECT c.card, a.cell, a.slot, a.state FROM VALUES (2), (3), (5) AS c(card), LATERAL bp_assignments(array(c.card, c.card)) AS a")


@query("sql_surface", RETURNS + ", m AS (SELECT vid, {0} AS a, {1} AS b FROM e WHERE vid % 16 = 6) SELECT vid, count(*) AS n, round(max(ln(a + b)), 6) AS lse, round(max(abs(a / (a + b) - 0.5) + abs(b / (a + b) - 0.5)), 6) AS l1 FROM m GROUP BY vid".format(*["0.1 + " + U.format(f"'42|' || vid || '|' || other || '|{k}'") for k in (0, 1)]))
def _surface(s: SparkSession, d: str) -> DataFrame:
    surface.register(s)
    e = _returns(s, d).edges.where("vid % 16 = 6")
    _returns(s, d).edges.select("fid", F.col("vid").alias("other"), (1 - F.col("slot")).alias("slot")).createOrReplaceTempView("bp_other")
    e.createOrReplaceTempView("bp_edges")
    u = lambda k: f"0.1D + conv(substring(md5(concat_ws('|', '42', e.vid, o.other, '{k}')), 1, 8), 16, 10) / 4294967296.0D"
    return s.sql(
        f"SELECT vid, count(*) AS n, round(max(bp_lse(w)), 6) AS lse, round(max(bp_l1(bp_norm(w), bp_norm(array(0.0D, 0.0D)))), 6) AS l1 "
        f"FROM (SELECT e.vid, array(ln({u(0)}), ln({u(1)})) AS w FROM bp_edges e JOIN bp_other o ON o.fid = e.fid AND o.slot = e.slot) x GROUP BY vid"
    )
