"""Queries that run the methods, one key each, with SQL that computes the same where SQL can."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.logspace import lnorm, md5_uniform
from ..operators import baselines, block_bp, exact, messages, metrics, pairwise, partition, residuals, sync_bp, termination, theory
from ..operators.kernel import BPConfig
from ..operators.model import FactorGraph, potts
from ..sources.tables import cut, table
from . import experiments, gallery, planner
from .experiments import settled

Query = Callable[[SparkSession, str], DataFrame]
_queries: dict[str, Query] = {}
_sql: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f: Query) -> Query:
        _queries[name] = f
        if sql:
            _sql[name] = sql
        return f

    return add


# SQL that the oracles share: the grounded graphs, by their definitions.

RETURNS = """
WITH ord AS (SELECT o_orderkey, o_custkey, o_orderstatus, o_orderpriority FROM orders WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem)),
cus AS (SELECT c_custkey, c_nationkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM ord)),
v AS (SELECT o_orderkey * 16 AS vid, (CASE o_orderstatus WHEN 'F' THEN -1.0 WHEN 'P' THEN 1.0 ELSE 0.0 END + CASE WHEN o_orderpriority = '1-URGENT' THEN 0.4 ELSE 0.0 END)::DOUBLE AS odds FROM ord
  UNION ALL SELECT (c_custkey * 8 + 1) * 2, 0 FROM cus UNION ALL SELECT DISTINCT (l_suppkey * 8 + 2) * 2, 0 FROM lineitem
  UNION ALL SELECT DISTINCT (l_partkey * 8 + 3) * 2, 0 FROM lineitem UNION ALL SELECT DISTINCT (c_nationkey::BIGINT * 8 + 4) * 2, 0 FROM cus),
p AS (SELECT DISTINCT 'os' AS t, l_orderkey * 16 AS a, (l_suppkey * 8 + 2) * 2 AS b, 0.02::DOUBLE AS w FROM lineitem
  UNION ALL SELECT DISTINCT 'op', l_orderkey * 16, (l_partkey * 8 + 3) * 2, 0.05 FROM lineitem
  UNION ALL SELECT 'oc', o_orderkey * 16, (o_custkey * 8 + 1) * 2, 0.3 FROM ord
  UNION ALL SELECT 'cn', (c_custkey * 8 + 1) * 2, (c_nationkey::BIGINT * 8 + 4) * 2, 0.3 FROM cus),
e AS (SELECT ('0x' || substr(md5(t || '|' || a || '|' || b), 1, 15))::BIGINT * 2 + 1 AS fid, a AS vid, b AS other, 0 AS slot, w FROM p
  UNION ALL SELECT ('0x' || substr(md5(t || '|' || a || '|' || b), 1, 15))::BIGINT * 2 + 1, b, a, 1, w FROM p)
"""

U = "(('0x' || substr(md5({}), 1, 8))::BIGINT / 4294967296.0)"
# Message to vid from its other end, valued by md5: log-odds of state 1.
MD5_ODDS = "ln(0.1 + " + U.format("'42|' || vid || '|' || other || '|1'") + ") - ln(0.1 + " + U.format("'42|' || vid || '|' || other || '|0'") + ")"


def _returns(spark: SparkSession, sf_dir: str) -> FactorGraph:
    return gallery.returns_mln(spark, sf_dir)


def _md5_state(fg: FactorGraph) -> DataFrame:
    """The edges with messages valued by md5 of both ends (binary pairwise graphs)."""
    e = fg.edges
    ends = e.select("fid", F.col("vid").alias("other"), (1 - F.col("slot")).alias("slot"))
    u = lambda s: F.ln(0.1 + md5_uniform(F.concat_ws("|", F.lit("42"), F.col("vid").cast("string"), F.col("other").cast("string"), F.lit(s))))
    return e.join(ends, ["fid", "slot"]).withColumn("f2v", lnorm(F.array(u("0"), u("1")))).select("fid", "vid", "slot", "card", "potential_id", "f2v")


def _odds(column: str):
    return F.get(column, F.lit(1)) - F.get(column, F.lit(0))


# All messages of a step, as a row per variable: how many, the least, the greatest and their sum.
_DIGEST = " SELECT vid, count(*) AS n, round(min(x), 6) + 0.0 AS low, round(max(x), 6) + 0.0 AS high, round(sum(x), 4) + 0.0 AS total FROM n GROUP BY vid"


def _digest(rows: DataFrame, *more: Column) -> DataFrame:
    return rows.groupBy("vid").agg(F.count("odds").alias("n"), *more, *[(F.round(f("odds"), k) + F.lit(0.0)).alias(name) for f, k, name in ((F.min, 6, "low"), (F.max, 6, "high"), (F.sum, 4, "total"))])


query("fg_variables_returns", RETURNS + "SELECT vid, odds FROM v")(lambda s, d: _returns(s, d).variables.select("vid", F.get("prior", F.lit(1)).alias("odds")))
query("fg_edges_returns", RETURNS + "SELECT fid, vid, slot, 2 AS card FROM e")(lambda s, d: _returns(s, d).edges.select("fid", "vid", "slot", "card"))
query("fg_factors_returns", RETURNS + "SELECT fid, count(*) AS arity, max(w) AS weight FROM e GROUP BY fid")(
    lambda s, d: (g := _returns(s, d)).edges.join(F.broadcast(g.potentials), "potential_id").groupBy("fid").agg(F.count(F.lit(1)).alias("arity"), F.max(F.get("logpsi", F.lit(0))).alias("weight"))
)
query("fg_validate_returns", "SELECT unnest(['card_of_edge_and_variable','card_of_edge_and_template','slots_complete','one_template','template_length','finite','prior_length','duplicate_variable']) AS rule, 0::BIGINT AS violations")(lambda s, d: _returns(s, d).validate())
query("fg_degree_distribution", RETURNS + "SELECT kind, degree, count(*) AS n FROM (SELECT 'variable' AS kind, count(*) AS degree FROM e GROUP BY vid UNION ALL SELECT 'factor', count(*) FROM e GROUP BY fid) x GROUP BY kind, degree")(lambda s, d: _returns(s, d).degrees())
query("msg_var_to_factor_step", RETURNS + f", m AS (SELECT *, {MD5_ODDS} AS f FROM e), t AS (SELECT v.vid, v.odds + sum(m.f) AS total FROM v JOIN m ON m.vid = v.vid GROUP BY v.vid, v.odds), n AS (SELECT m.vid, t.total - m.f AS x FROM m JOIN t ON t.vid = m.vid)" + _DIGEST)(
    lambda s, d: _digest(messages.var_to_factor(g := _returns(s, d), _md5_state(g), 2).select("vid", _odds("v2f").alias("odds")))
)
_STEP = f", m AS (SELECT *, {MD5_ODDS} AS f FROM e), t AS (SELECT v.vid, v.odds + sum(m.f) AS total FROM v JOIN m ON m.vid = v.vid GROUP BY v.vid, v.odds), q AS (SELECT m.*, t.total - m.f AS o FROM m JOIN t ON t.vid = m.vid), n AS (SELECT a.fid, a.vid, a.f, 2 * atanh(tanh(a.w / 2) * tanh(b.o / 2)) AS x FROM q a JOIN q b ON a.fid = b.fid AND a.slot <> b.slot)"


def _md5_ends(s: SparkSession, d: str, both: bool = False) -> tuple[FactorGraph, DataFrame]:
    """The returns graph, and its ends with messages valued by md5 (both: with those to the other ends)."""
    g = _returns(s, d)
    u = lambda a, b, s: F.ln(0.1 + md5_uniform(F.concat_ws("|", F.lit("42"), F.col(a).cast("string"), F.col(b).cast("string"), F.lit(s))))
    sent = lambda a, b: F.when(F.col("code") >= 0, u(a, b, "1") - u(a, b, "0")).otherwise(F.col("r1"))
    rows = pairwise.start(g, 2).withColumn("q1", sent("other", "vid")) if both else pairwise.start(g, 2)
    return g, rows.withColumn("r1", sent("vid", "other"))


def _answered(s: SparkSession, d: str, both: bool = False) -> DataFrame:
    """The rows after a step from those, by variable."""
    g, rows = _md5_ends(s, d, both)
    return pairwise.gathered(pairwise.step(rows, pairwise.tables(g, 2), 2, both))


def _end_digest(rows: DataFrame) -> DataFrame:
    """_digest of what gathered ends hold in r1."""
    x = F.when(F.col("code") >= 0, F.col("r1"))
    found = _digest(rows.select("vid", x.alias("odds"), "code"), F.min("code").alias("least"))
    return found.where("least < 0 and n > 0").drop("least")


def _stepped(s: SparkSession, d: str, damping: float = 0.0) -> tuple[FactorGraph, DataFrame, DataFrame]:
    g = _returns(s, d)
    old = _md5_state(g)
    return g, old, messages.step(g, old, 2, 2, damping)


query("msg_factor_to_var_step", RETURNS + _STEP + _DIGEST)(lambda s, d: _end_digest(_answered(s, d)))
query("msg_binary_logodds_step", RETURNS + _STEP + _DIGEST)(
    # The shortcut on log-odds: one number per message.
    lambda s, d: _end_digest(_binary_step(s, d))
)


def _binary_step(s: SparkSession, d: str) -> DataFrame:
    from ..functions.logspace import binary_message

    g, rows = _md5_ends(s, d)
    w = F.broadcast(g.potentials.select((2 * F.col("potential_id")).cast("int").alias("even"), F.get("logpsi", F.lit(0)).alias("w")))
    sent = pairwise.others(rows, 2).join(w, F.col("code") - F.col("code") % 2 == F.col("even"), "left")
    prior = F.col("code") < 0
    return pairwise.gathered(sent.select(F.coalesce("other", "vid").alias("vid"), "code", F.when(~prior, binary_message(F.col("w"), F.col("v1"))).alias("r1")))


_DAMPED = ", r AS (SELECT vid, 0.4 / (1 + exp(-x)) + 0.6 / (1 + exp(-f)) AS x FROM n)" + _DIGEST.replace("FROM n", "FROM r")
query("msg_damped_step", RETURNS + _STEP + _DAMPED)(lambda s, d: _digest(_stepped(s, d, 0.6)[2].select("vid", F.exp(F.get("f2v", F.lit(1))).alias("odds"))))
query("residual_message", RETURNS + _STEP + " SELECT vid, round(max(2 * abs(1 / (1 + exp(-x)) - 1 / (1 + exp(-f)))), 6) AS residual FROM n GROUP BY vid")(
    lambda s, d: residuals.inbound(_answered(s, d, True)).select("vid", F.round("residual", 6).alias("residual"))
)
query("sync_bp_convergence_test", RETURNS + _STEP + " SELECT round(max(2 * abs(1 / (1 + exp(-x)) - 1 / (1 + exp(-f)))), 6) AS max_delta FROM n")(
    lambda s, d: residuals.largest_change((r := _stepped(s, d))[1], r[2]).select(F.round("max_delta", 6).alias("max_delta"))
)
_BELIEF = ", y AS (SELECT v.vid, v.odds + sum({0}) AS o FROM v JOIN n ON n.vid = v.vid GROUP BY v.vid, v.odds)"
query("beliefs_variable", RETURNS + _STEP + _BELIEF.format("x") + " SELECT vid, 0 AS state, round(1 / (1 + exp(o)), 6) AS belief FROM y UNION ALL SELECT vid, 1, round(1 / (1 + exp(-o)), 6) FROM y")(
    lambda s, d: pairwise.beliefs(_answered(s, d), 2).select("vid", "state", F.round("belief", 6).alias("belief"))
)
query("residual_belief_naive", RETURNS + _STEP + ", y AS (SELECT v.vid, v.odds + sum(x) AS o, v.odds + sum(f) AS p FROM v JOIN n ON n.vid = v.vid GROUP BY v.vid, v.odds) SELECT vid, round(2 * abs(1 / (1 + exp(-o)) - 1 / (1 + exp(-p))), 6) AS residual FROM y")(
    lambda s, d: residuals.naive(messages.beliefs((r := _stepped(s, d))[0], r[1], 2), messages.beliefs(r[0], r[2], 2)).select("vid", F.round("residual", 6).alias("residual"))
)
query("beliefs_factor", RETURNS + f", m AS (SELECT *, {MD5_ODDS} AS f FROM e), t AS (SELECT v.vid, v.odds + sum(m.f) AS total FROM v JOIN m ON m.vid = v.vid GROUP BY v.vid, v.odds), q AS (SELECT m.*, t.total - m.f AS o FROM m JOIN t ON t.vid = m.vid), n AS (SELECT a.fid % 4096 AS vid, exp(a.w) * (1 + exp(a.o + b.o)) / (exp(a.w) * (1 + exp(a.o + b.o)) + exp(a.o) + exp(b.o)) AS x FROM q a JOIN q b ON a.fid = b.fid AND a.slot = 0 AND b.slot = 1)" + _DIGEST)(
    # Of a factor, the probability that its ends are equal; factors in 2,048 groups by id.
    lambda s, d: _digest(messages.factor_beliefs(g := _returns(s, d), messages.var_to_factor(g, _md5_state(g), 2), 2).select((F.col("fid") % 4096).alias("vid"), (F.exp(F.get("logb", F.lit(0))) + F.exp(F.get("logb", F.lit(3)))).alias("odds")))
)


def _unrolled(times: int, every: int = 0, beta: float = 0.0) -> str:
    """SQL of a number of synchronous iterations from uniform messages; every: of the log of changes instead of the beliefs."""
    out = RETURNS + ", n0 AS MATERIALIZED (SELECT fid, vid, slot, w, 0::DOUBLE AS x FROM e)"
    for k in range(times):
        out += f", t{k} AS (SELECT v.vid, v.odds + sum(n.x) AS total FROM v JOIN n{k} n ON n.vid = v.vid GROUP BY v.vid, v.odds), q{k} AS (SELECT n.*, t.total - n.x AS o FROM n{k} n JOIN t{k} t ON t.vid = n.vid), n{k + 1} AS MATERIALIZED (SELECT a.fid, a.vid, a.slot, a.w, 2 * atanh(tanh(a.w / 2) * tanh(b.o / 2)) AS x FROM q{k} a JOIN q{k} b ON a.fid = b.fid AND a.slot <> b.slot)"
    if every:
        sent = "1 / (1 + exp(-{0}.x))".format
        out += "".join(f", d{t} AS (SELECT max(2 * abs({sent('a')} - {sent('b')})) AS d FROM n{t} a JOIN n{t - 1} b ON b.fid = a.fid AND b.vid = a.vid)" for t in range(every, times + 1, every))
        rows = [f"SELECT {t} AS iteration, round(d, 7) AS max_delta FROM d{t}" + (f" WHERE (SELECT d FROM d{t - every}) > {beta}" if t > every else "") for t in range(every, times + 1, every)]
        return out + " " + " UNION ALL ".join(rows)
    return out + f" SELECT v.vid, round(1 / (1 + exp(-(v.odds + sum(n.x)))), 6) AS p1 FROM v JOIN n{times} n ON n.vid = v.vid GROUP BY v.vid, v.odds"


query("sync_bp_returns_t3", _unrolled(3))(lambda s, d: sync_bp.run(_returns(s, d), 3, None, width=2, keep=False).beliefs.where("state = 1").select("vid", F.round("belief", 6).alias("p1")))
query("sync_bp_convergence_log", _unrolled(12, 3, 1e-4))(lambda s, d: s.createDataFrame([(t, round(x, 7)) for t, x in sync_bp.run(_returns(s, d), 12, 1e-4, every=3, width=2, keep=False).log], "iteration int, max_delta double"))

# The snowflake: exact marginals by group-bys up and down the tree.

SNOW = """
WITH line AS (SELECT l_orderkey, l_linenumber, ((l_orderkey * 8 + l_linenumber) * 8 + 5) * 2 AS vid, avg(CASE l_returnflag WHEN 'R' THEN 1.0::DOUBLE WHEN 'A' THEN -0.3::DOUBLE ELSE 0::DOUBLE END) AS o FROM lineitem GROUP BY 1, 2, 3),
l AS (SELECT *, 2 * atanh(tanh(0.4::DOUBLE) * tanh(o / 2)) AS m FROM line),
o1 AS (SELECT orders.o_orderkey AS k, orders.o_custkey AS p, coalesce(sum(m), 0) AS o FROM orders LEFT JOIN l ON l_orderkey = o_orderkey GROUP BY 1, 2), o AS (SELECT *, 2 * atanh(tanh(0.3::DOUBLE) * tanh(o / 2)) AS m FROM o1),
c1 AS (SELECT c_custkey AS k, c_nationkey AS p, coalesce(sum(m), 0) AS o FROM customer LEFT JOIN o ON o.p = c_custkey GROUP BY 1, 2), c AS (SELECT *, 2 * atanh(tanh(0.1::DOUBLE) * tanh(o / 2)) AS m FROM c1),
n1 AS (SELECT n_nationkey AS k, n_regionkey AS p, coalesce(sum(m), 0) AS o FROM nation LEFT JOIN c ON c.p = n_nationkey GROUP BY 1, 2), n AS (SELECT *, 2 * atanh(tanh(0.05::DOUBLE) * tanh(o / 2)) AS m FROM n1),
r AS (SELECT r_regionkey AS k, coalesce(sum(m), 0) AS t FROM region LEFT JOIN n ON n.p = r_regionkey GROUP BY 1),
nt AS (SELECT n.*, n.o + 2 * atanh(tanh(0.05::DOUBLE) * tanh((r.t - n.m) / 2)) AS t FROM n JOIN r ON r.k = n.p),
ct AS (SELECT c.*, c.o + 2 * atanh(tanh(0.1::DOUBLE) * tanh((nt.t - c.m) / 2)) AS t FROM c JOIN nt ON nt.k = c.p),
ot AS (SELECT o.*, o.o + 2 * atanh(tanh(0.3::DOUBLE) * tanh((ct.t - o.m) / 2)) AS t FROM o JOIN ct ON ct.k = o.p),
lt AS (SELECT l.*, l.o + 2 * atanh(tanh(0.4::DOUBLE) * tanh((ot.t - l.m) / 2)) AS t FROM l JOIN ot ON ot.k = l.l_orderkey),
b AS (SELECT vid, t FROM lt UNION ALL SELECT k * 16, t FROM ot UNION ALL SELECT (k * 8 + 1) * 2, t FROM ct UNION ALL SELECT (k::BIGINT * 8 + 4) * 2, t FROM nt UNION ALL SELECT (k::BIGINT * 8 + 6) * 2, t FROM r)
"""
SNOW_P = SNOW + "SELECT vid, round(1 / (1 + exp(-t)), 4) AS p1 FROM b"


def _p1(beliefs: DataFrame, digits: int = 4) -> DataFrame:
    return beliefs.where("state = 1").select("vid", F.round("belief", digits).alias("p1"))


def _components_snowflake(s: SparkSession, d: str) -> DataFrame:
    return partition.components(settled(gallery.snowflake_tree(s, d))).groupBy("component").agg(F.count(F.lit(1)).alias("n")).select("n")


def snow_exact(s: SparkSession, d: str) -> DataFrame:
    """vid and log-odds t, by exact.snowflake_marginals."""
    g = gallery
    score = F.when(F.col("l_returnflag") == "R", 1.0).when(F.col("l_returnflag") == "A", -0.3).otherwise(0.0)
    lines = table(s, d, "lineitem").groupBy("l_orderkey", "l_linenumber").agg(F.avg(score).alias("odds")).withColumn("id", g.vid(F.col("l_orderkey") * 8 + F.col("l_linenumber"), g.LINE))
    pair = lambda t, a, ka, b, kb: table(s, d, t).select(g.vid(F.col(a), ka).alias("child"), g.vid(F.col(b), kb).alias("parent"))
    edges = [
        (lines.select(F.col("id").alias("child"), g.vid(F.col("l_orderkey"), g.ORDER).alias("parent")), g.SNOWFLAKE[0]),
        (pair("orders", "o_orderkey", g.ORDER, "o_custkey", g.CUSTOMER), g.SNOWFLAKE[1]),
        (pair("customer", "c_custkey", g.CUSTOMER, "c_nationkey", g.NATION), g.SNOWFLAKE[2]),
        (pair("nation", "n_nationkey", g.NATION, "n_regionkey", g.REGION), g.SNOWFLAKE[3]),
    ]
    levels = exact.snowflake_marginals(edges, lines)
    out = levels[0]
    for x in levels[1:]:
        out = out.unionByName(x)
    return out.select(F.col("id").alias("vid"), F.col("odds").alias("t"))


query("exact_snowflake", SNOW_P)(lambda s, d: snow_exact(s, d).select("vid", F.round(1 / (1 + F.exp(-F.col("t"))), 4).alias("p1")))
query("sync_bp_snowflake", SNOW_P)(lambda s, d: _p1(sync_bp.run(gallery.snowflake_tree(s, d), 16, 1e-9, every=4, width=2, keep=False).beliefs))
query("block_bp_snowflake", SNOW_P)(lambda s, d: flagship(s, d))
query("fg_components", "SELECT 1 + count(DISTINCT n_nationkey) + count(DISTINCT c_custkey) + count(DISTINCT o_orderkey) + count(DISTINCT (l_orderkey * 8 + l_linenumber)) AS n FROM region LEFT JOIN nation ON n_regionkey = r_regionkey LEFT JOIN customer ON c_nationkey = n_nationkey LEFT JOIN orders ON o_custkey = c_custkey LEFT JOIN lineitem ON l_orderkey = o_orderkey GROUP BY r_regionkey")(_components_snowflake)
query("map_states", SNOW + "SELECT vid, CASE WHEN t > 0 THEN 1 ELSE 0 END AS state FROM b WHERE abs(t) > 1e-9")(lambda s, d: snow_exact(s, d).where(F.abs("t") > 1e-9).select("vid", F.when(F.col("t") > 0, 1).otherwise(0).alias("state")))
query("topk_uncertain", SNOW + "SELECT vid, round(abs(t), 6) AS margin FROM b WHERE vid % 16 = 2 ORDER BY round(abs(t), 6), vid LIMIT 20")(lambda s, d: snow_exact(s, d).where("vid % 16 = 2").select("vid", F.round(F.abs("t"), 6).alias("margin")).orderBy("margin", "vid").limit(20))


#: Vertices of a block of the flagship, which a Python worker holds as one: blocks grow in number with the tables, not in size.
BLOCK_VERTICES = 40_000


def snowflake_blocks(g: FactorGraph) -> int:
    """How many blocks the snowflake g is dealt over: a tree has about as many factors as variables."""
    return max(8, -(-2 * g.variables.count() // BLOCK_VERTICES))


def flagship(s: SparkSession, d: str, blocks: int | None = None) -> DataFrame:
    """The block sweeper on the snowflake. A customer's orders and lines stay in its block, so only edges to nations are cut."""
    g = settled(gallery.snowflake_tree(s, d))
    blocks = blocks or snowflake_blocks(g)
    k, orders = gallery, table(s, d, "orders").select("o_orderkey", "o_custkey")
    block = lambda c: F.pmod(F.xxhash64(c), F.lit(blocks)).alias("block")
    lines = table(s, d, "lineitem").select("l_orderkey", "l_linenumber").distinct().join(orders, F.col("l_orderkey") == F.col("o_orderkey"))
    v = lines.select(k.vid(F.col("l_orderkey") * 8 + F.col("l_linenumber"), k.LINE).alias("vid"), block("o_custkey"))
    v = v.unionByName(orders.select(k.vid(F.col("o_orderkey"), k.ORDER).alias("vid"), block("o_custkey")))
    v = v.unionByName(table(s, d, "customer").select(k.vid(F.col("c_custkey"), k.CUSTOMER).alias("vid"), block("c_custkey")))
    v = cut(g.variables.select("vid").join(v, "vid", "left").select("vid", F.coalesce("block", F.lit(0)).cast("long").alias("block")))
    f = g.edges.where("slot = 0").join(v, "vid").select(F.col("fid").alias("vid"), "block")
    return _p1(block_bp.run_converged(g, v.unionByName(f), BPConfig(damping=0.0, beta=1e-8, send_every=0)).beliefs)


# Chains of conversations: forward-backward in log-odds.

CHAINS = """
WITH RECURSIVE t AS (SELECT conv_id, turn, ((conv_id * 1000 + turn) * 8 + 7) * 2 AS vid, CASE WHEN contains(text, '?') THEN 0.8::DOUBLE ELSE -0.2::DOUBLE END AS o, row_number() OVER (PARTITION BY conv_id ORDER BY turn) AS k, count(*) OVER (PARTITION BY conv_id) AS n FROM conversations),
f AS (SELECT conv_id, k, o, 0::DOUBLE AS m FROM t WHERE k = 1 UNION ALL SELECT t.conv_id, t.k, t.o, 2 * atanh(tanh(0.35::DOUBLE) * tanh((f.o + f.m) / 2)) FROM f JOIN t ON t.conv_id = f.conv_id AND t.k = f.k + 1),
g AS (SELECT conv_id, k, o, 0::DOUBLE AS m FROM t WHERE k = n UNION ALL SELECT t.conv_id, t.k, t.o, 2 * atanh(tanh(0.35::DOUBLE) * tanh((g.o + g.m) / 2)) FROM g JOIN t ON t.conv_id = g.conv_id AND t.k = g.k - 1)
SELECT t.vid, round(1 / (1 + exp(-(t.o + f.m + g.m))), 4) AS p1 FROM t JOIN f ON f.conv_id = t.conv_id AND f.k = t.k JOIN g ON g.conv_id = t.conv_id AND g.k = t.k
"""


def _conversations(s: SparkSession, d: str) -> FactorGraph:
    return settled(gallery.conversation_chains(s, d))


@query("forward_backward_conversations", CHAINS)
def _fb(s: SparkSession, d: str) -> DataFrame:
    c = table(s, d, "conversations")
    nodes = _conversations(s, d).variables.join(c.select(F.col("conv_id").alias("chain"), F.col("turn").alias("pos"), gallery.vid(F.col("conv_id") * 1000 + F.col("turn"), gallery.OTHER).alias("vid")), "vid")
    return _p1(exact.forward_backward(nodes.select("chain", "pos", "vid", "prior"), potts(2, 0.7), 2))


query("async_bp_chain", CHAINS)(lambda s, d: _p1(baselines.block_beliefs(s, baselines.round_robin(_conversations(s, d), 1e-9))))
query("shared_queue_chain", CHAINS)(lambda s, d: _p1(baselines.block_beliefs(s, baselines.shared_queue_sweep(_conversations(s, d), 20, 1e-9, damping=0.0))))
query("block_bp_chain", CHAINS)(lambda s, d: _p1(block_bp.run_converged(_conversations(s, d), cfg=BPConfig(damping=0.0, beta=1e-9, workers=3, over=2)).beliefs))


@query("block_bp_modes_agree", "SELECT 0::BIGINT AS differing")
def _modes(s: SparkSession, d: str) -> DataFrame:
    """Variables whose belief differs by more than 1e-4 between the four combinations of residual and sweep, on chains."""
    g = _conversations(s, d)
    found = [dict((v, p[1]) for v, p in b.beliefs()) for b in (_swept(g, r, w) for r in ("message", "belief") for w in ("volume", "work"))]
    return s.createDataFrame([(int(sum(max(f[v] for f in found) - min(f[v] for f in found) > 1e-4 for v in found[0])),)], "differing long")


def _swept(g: FactorGraph, residual: str, sweep: str):
    b = baselines.whole_block(g, BPConfig(damping=0.0, beta=1e-8, residual=residual, sweep=sweep))
    b.run_sweeps()
    return b


# Placement

query("edge_cost_uninformed", RETURNS + "SELECT fid, vid, 6::DOUBLE AS cost FROM e")(lambda s, d: partition.edge_cost(_returns(s, d)))
query("vertex_work_uninformed", RETURNS + "SELECT vid, (count(*) * 2)::DOUBLE AS work FROM e GROUP BY vid UNION ALL SELECT fid, (count(*) * 4)::DOUBLE FROM e GROUP BY fid")(lambda s, d: partition.vertex_work(_returns(s, d)))
_INFORMED = "(1 + floor(" + U.format("'u|' || {}") + " * 20))"
_VU = ", x AS (SELECT vid FROM e UNION SELECT fid FROM e), u AS (SELECT vid, " + _INFORMED.format("vid") + "::DOUBLE AS n FROM x)"


def _updates(fg: FactorGraph) -> DataFrame:
    u = md5_uniform(F.concat_ws("|", F.lit("u"), F.col("vid").cast("string")))
    return partition.vertices(fg).select("vid", (1 + F.floor(u * 20)).alias("n_updates"))


query("edge_cost_informed", RETURNS + _VU + " SELECT e.fid, e.vid, (a.n + b.n) * 3 AS cost FROM e JOIN u a ON a.vid = e.fid JOIN u b ON b.vid = e.vid")(lambda s, d: partition.edge_cost(g := _returns(s, d), _updates(g)))
query("vertex_work_informed", RETURNS + _VU + ", w AS (SELECT vid, (count(*) * 2)::DOUBLE AS w FROM e GROUP BY vid UNION ALL SELECT fid, (count(*) * 4)::DOUBLE FROM e GROUP BY fid) SELECT w.vid, w.w * u.n AS work FROM w JOIN u ON u.vid = w.vid")(lambda s, d: partition.vertex_work(g := _returns(s, d), _updates(g)))
_HASH = ", x AS (SELECT vid, (count(*) * 2)::DOUBLE AS w FROM e GROUP BY vid UNION ALL SELECT fid, (count(*) * 4)::DOUBLE FROM e GROUP BY fid), h AS (SELECT vid, w, floor(" + U.format("'part|' || vid || '|42'") + " * 8)::BIGINT AS block FROM x)"
query("cut_cost_hash", RETURNS + _HASH + " SELECT (count(*) * 6)::DOUBLE AS cut_cost, count(*) AS cut_edges FROM e JOIN h a ON a.vid = e.fid JOIN h b ON b.vid = e.vid WHERE a.block <> b.block")(lambda s, d: partition.cut_cost(partition.edge_cost(g := _returns(s, d)), partition.hash_parts(g, 8)))
_LOADS = ", y AS (SELECT block, sum(w) AS load FROM h GROUP BY block)"
query("cut_balance_hash", RETURNS + _HASH + _LOADS + " SELECT round(8 * max(load) / sum(load), 6) AS balance FROM y")(lambda s, d: partition.work_balance(partition.vertex_work(g := _returns(s, d)), partition.hash_parts(g, 8), 8).select(F.round("balance", 6).alias("balance")))
query("cut_feasible_gamma", RETURNS + _HASH + _LOADS + " SELECT 1.03::DOUBLE AS gamma, 8 * max(load) / sum(load) <= 1.03 AS feasible FROM y")(lambda s, d: partition.feasible(partition.vertex_work(g := _returns(s, d)), partition.hash_parts(g, 8), 8, 1.03))
query("overpart_assign", "SELECT piece, ((row_number() OVER (ORDER BY md5(piece || '|42'), piece) - 1) % 12)::BIGINT AS block FROM (SELECT unnest(range(60)) AS piece) p")(lambda s, d: partition.deal(s, 60, 12, 42))
query("overpart_bound", "SELECT p, sigma, round(pow(p, 1 / log2(1 / (sigma + 0.5))), 6) AS k FROM (SELECT unnest([2.0, 8, 60, 120]::DOUBLE[]) AS p) a, (SELECT unnest([0.0, 0.1, 0.2, 0.3]::DOUBLE[]) AS sigma) b")(
    lambda s, d: s.createDataFrame([(p, x, round(theory.over_partition_bound(p, x), 6)) for p in (2.0, 8.0, 60.0, 120.0) for x in (0.0, 0.1, 0.2, 0.3)], "p double, sigma double, k double")
)


@query("multilevel_cut_quality")
def _quality(s: SparkSession, d: str) -> DataFrame:
    g = _grid(s, d)
    costs, work = partition.edge_cost(g), partition.vertex_work(g)
    rows = []
    for name, a in (("multilevel", partition.multilevel(g, PARTS).withColumnRenamed("piece", "block")), ("hash", partition.hash_parts(g, PARTS)), ("range", partition.range_parts(g, PARTS))):
        a = cut(a)
        rows.append((name, partition.cut_cost(costs, a).first()["cut_cost"], partition.work_balance(work, a, PARTS).first()["balance"]))
    return s.createDataFrame(rows, "method string, cut_cost double, balance double")


# Laws and schedules

query("premature_chain_trace")(lambda s, d: s.createDataFrame([(t, v, round(a, 6), round(n, 6), round(b, 6)) for t, v, a, n, b in gallery.premature_trace()], "stage int, vertex int, accumulated double, naive double, belief double"))
query("degree_amplification_star", "SELECT d::INT AS d, 1e-4::DOUBLE AS eps, round(0.5 - 1 / (1 + exp(d * (ln(0.5 + 1e-4) - ln(0.5 - 1e-4)))), 10) AS change, round(d * 1e-4, 10) AS linear FROM (SELECT unnest([1, 10, 100, 1000]) AS d) x")(
    lambda s, d: s.createDataFrame([(k, 1e-4, round(theory.degree_amplification(k, 1e-4), 10), round(k * 1e-4, 10)) for k in (1, 10, 100, 1000)], "d int, eps double, change double, linear double")
)
query("chain_bound", "SELECT n::INT AS n, p::INT AS p, t::INT AS tau, 2 * n / p * ceil(t * p / n) AS steps, 2 * n / p + 2.0 * t AS bound FROM (SELECT 1000.0::DOUBLE AS n, unnest([1, 4, 20, 100]) AS p) x, (SELECT unnest([5, 50, 300]) AS t) y")(
    lambda s, d: s.createDataFrame([(1000, p, t, *map(float, theory.chain_bound(1000, p, t))) for p in (1, 4, 20, 100) for t in (5, 50, 300)], "n int, p int, tau int, steps double, bound double")
)
_LOG = [(0, 0, 5, 0, True), (0, 1, 3, 0, True), (1, 0, 2, 3, False), (1, 1, 0, 5, True), (2, 0, 0, 0, False), (2, 1, 0, 2, False), (3, 0, 0, 0, False), (3, 1, 0, 0, False)]
_LOG_SQL = "WITH l(round, block, sent, received, active) AS (VALUES " + ", ".join(f"({a}, {b}, {c}, {e}, {f})" for a, b, c, e, f in _LOG) + ")"
query("termination_quiescent", _LOG_SQL + ", p AS (SELECT round::BIGINT AS round, sum(active::INT)::BIGINT AS active, sum(sent) AS s, sum(received) AS r FROM l GROUP BY 1) SELECT round, active, (sum(s) OVER w)::BIGINT AS sent, (sum(r) OVER w)::BIGINT AS received, active = 0 AND sum(s) OVER w = sum(r) OVER w AS stop FROM p WINDOW w AS (ORDER BY round)")(
    lambda s, d: termination.quiescent(s.createDataFrame(_LOG, "round long, block long, sent long, received long, active boolean"))
)


@query("tau_eps_chain")
def _tau(s: SparkSession, d: str) -> DataFrame:
    import numpy as np

    n = 200
    u = [[float(r["a"]), float(r["b"])] for r in s.range(n).select(md5_uniform(F.concat(F.lit("a"), F.col("id").cast("string"))).alias("a"), md5_uniform(F.concat(F.lit("b"), F.col("id").cast("string"))).alias("b")).collect()]
    pair = np.array(potts(2, 1.0)).reshape(2, 2)
    return s.createDataFrame([(e, theory.tau_eps(np.array(u), pair, e)) for e in (0.1, 0.01, 0.001, 0.0001)], "eps double, tau int")


# Images

query("grid_pixels_lineitem", "WITH s AS (SELECT floor(date_diff('day', DATE '1995-01-01', l_shipdate::DATE) / 7)::INT AS r, (l_partkey % 100)::INT AS c, least(4, floor(avg(l_quantity) / 10))::DOUBLE AS obs FROM lineitem GROUP BY 1, 2), w AS (SELECT unnest(range(min(r), max(r) + 1))::INT AS r FROM s) SELECT w.r, k.c, s.obs FROM w CROSS JOIN (SELECT unnest(range(100))::INT AS c) k LEFT JOIN s ON s.r = w.r AND s.c = k.c")(lambda s, d: gallery.lineitem_pixels(s, d).select("r", "c", "obs"))
query("grid_embeddings_pixels", "SELECT vec_id AS r, (i - 1)::INT AS c, CASE WHEN x < -0.15 THEN 0.0 WHEN x < -0.05 THEN 1.0 WHEN x < 0.05 THEN 2.0 WHEN x < 0.15 THEN 3.0 ELSE 4.0 END::DOUBLE AS obs FROM (SELECT vec_id, unnest(range(1, 65)) AS i, unnest(embedding)::DOUBLE AS x FROM embeddings) t")(lambda s, d: gallery.embedding_pixels(s, d))
query("grid_edges_synthetic", "SELECT count(*) AS n, 2 * 40 * 39 AS expected FROM (SELECT r, c FROM (SELECT unnest(range(40)) AS r) a, (SELECT unnest(range(39)) AS c) b UNION ALL SELECT r, c FROM (SELECT unnest(range(39)) AS r) a, (SELECT unnest(range(40)) AS c) b) e")(lambda s, d: gallery.grid_synthetic(s, 40, 40).edges.where("slot = 0").agg(F.count(F.lit(1)).alias("n")).withColumn("expected", F.lit(2 * 40 * 39)))


# Experiments, on graphs grounded from the tables and in the settings of the survey

PARTS, WORKERS, OVERS, TRIALS = 120, (1, 2, 4, 8, 20, 60, 120), (1, 2, 5, 10), 30
_EXACT = BPConfig(damping=0.0, beta=1e-3, send_every=0)


def _grid(s: SparkSession, d: str) -> FactorGraph:
    return settled(gallery.grid_lineitem(s, d))


@query("exp_table1_grid")
def _table1(s: SparkSession, d: str) -> DataFrame:
    """The cuts of the grid, the returns and the documents; update counts come from a run to convergence, damped where cycles ask for it."""
    out = []
    for name, ground, cfg in (("grid_lineitem", gallery.grid_lineitem, _EXACT), ("returns_mln", gallery.returns_mln, _EXACT), ("docs_mln", gallery.docs_mln, BPConfig(beta=1e-3))):
        out.append((name, *experiments.table1(settled(ground(s, d)), PARTS, cfg, None).values()))
    return s.createDataFrame(out, "graph string, parts int, rel_com_cost double, rel_work_balance double, informed_balance double, partition_seconds double")


@query("exp_scaling_grid")
def _scaling(s: SparkSession, d: str) -> DataFrame:
    """Runs of the grid and of the returns on logical workers."""
    runs = [experiments.scaling(settled(ground(s, d)), WORKERS, (1, 5), _EXACT).select(F.lit(name).alias("graph"), "*") for name, ground in (("grid_lineitem", gallery.grid_lineitem), ("returns_mln", gallery.returns_mln))]
    return runs[0].unionByName(runs[1])


query("exp_overpartition_trials")(lambda s, d: experiments.overpartition_trials(_grid(s, d), 60, OVERS, TRIALS))
query("exp_ablation_docs")(lambda s, d: experiments.ablate(settled(gallery.docs_mln(s, d)), BPConfig(beta=1e-3)))
query("gibbs_accuracy")(lambda s, d: _gibbs(s, d))


def _gibbs(s: SparkSession, d: str) -> DataFrame:
    """mean_l1 of the shared queue's beliefs against Gibbs chains, and how far the chains agree, on the supplier star."""
    g = settled(gallery.supplier_star(s, d))
    draws = cut(baselines.gibbs_binary(g))
    mean = draws.groupBy("vid", "state").agg(F.avg("belief").alias("belief"))
    b = baselines.block_beliefs(s, baselines.shared_queue_sweep(g, beta=1e-6, damping=0.0))
    return metrics.mean_l1(b, mean).crossJoin(baselines.agreement(draws).select(F.col("mean_l1").alias("chains")))  # one row each


@query("block_bp_round_log")
def _round_log(s: SparkSession, d: str) -> DataFrame:
    return block_bp.run(_grid(s, d), cfg=_EXACT).round_log()


@query("planner_rewrites", RETURNS + ", o AS (SELECT b, count(*) AS n FROM p WHERE t = 'os' GROUP BY b) SELECT 2 * max(n) AS edges, 2 * max(n) AS merged_edges, 1::BIGINT AS potentials FROM o")
def _rewrites(s: SparkSession, d: str) -> DataFrame:
    g = settled(gallery.supplier_star(s, d))
    m = planner.merge_parallel(planner.absorb_unary(g))
    return s.createDataFrame([(g.edges.count(), m.edges.count(), m.potentials.count())], "edges long, merged_edges long, potentials long")


def queries() -> dict[str, Query]:
    from . import measures  # noqa: F401  registers its own

    return dict(_queries)


def oracle_sql() -> dict[str, str]:
    queries()
    return dict(_sql)
