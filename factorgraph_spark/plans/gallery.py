"""Models grounded from the given tables, and small literal ones.

Variable ids are 2 * (8 * key + kind), so that every table's keys have room of their own.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.logspace import md5_uniform
from ..operators.model import Clause, FactorGraph, ground, linear_penalty, potentials_frame, potts
from ..sources.tables import table

ORDER, CUSTOMER, SUPPLIER, PART, NATION, LINE, REGION, OTHER = range(8)


def vid(key: Column, kind: int) -> Column:
    return (key.cast("long") * 8 + kind) * 2


def _binary(odds: Column) -> Column:
    """Prior of a binary variable with these log-odds of state 1."""
    return F.array(F.lit(0.0), odds.cast("double"))


def _variables(*parts: DataFrame) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out.select("vid", F.size("prior").alias("card"), "prior")


def _pairs(df: DataFrame, name: str, a: Column, b: Column) -> DataFrame:
    key = F.concat_ws("|", F.lit(name), a.cast("string"), b.cast("string"))
    return df.select(key.alias("key"), a.alias("v0"), b.alias("v1"))


def order_odds(status: Column, priority: Column) -> Column:
    base = F.when(status == "F", -1.0).when(status == "P", 1.0).otherwise(0.0)
    return base + F.when(priority == "1-URGENT", 0.4).otherwise(0.0)


def returns_mln(spark: SparkSession, sf_dir: str, weights=(0.02, 0.05, 0.3, 0.3), frustrated: float | None = None) -> FactorGraph:
    """Risk bits of orders, customers, suppliers, parts and nations, linked by equality clauses.

    weights: supplier, part, customer, nation. frustrated: log-weight of supplier links whose sign is drawn by md5.
    """
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey", "l_partkey")
    used = lines.select("l_orderkey").distinct()
    orders = table(spark, sf_dir, "orders").join(used, F.col("o_orderkey") == F.col("l_orderkey"), "left_semi")
    customers = table(spark, sf_dir, "customer").join(orders.select("o_custkey").distinct(), F.col("c_custkey") == F.col("o_custkey"), "left_semi")
    flat = lambda df, key, kind: df.select(vid(F.col(key), kind).alias("vid"), _binary(F.lit(0.0)).alias("prior"))
    variables = _variables(
        orders.select(vid(F.col("o_orderkey"), ORDER).alias("vid"), _binary(order_odds(F.col("o_orderstatus"), F.col("o_orderpriority"))).alias("prior")),
        flat(customers, "c_custkey", CUSTOMER),
        flat(lines.select("l_suppkey").distinct(), "l_suppkey", SUPPLIER),
        flat(lines.select("l_partkey").distinct(), "l_partkey", PART),
        flat(customers.select("c_nationkey").distinct(), "c_nationkey", NATION),
    )
    ws, wp, wc, wn = weights
    links = lambda w: ([2, 2], potts(2, w))
    supplied = lines.select("l_orderkey", "l_suppkey").distinct()
    pair = lambda df: _pairs(df, "os", vid(F.col("l_orderkey"), ORDER), vid(F.col("l_suppkey"), SUPPLIER))
    clauses = []
    if frustrated is None:
        clauses.append((pair(supplied), links(ws)))
    else:
        sign = md5_uniform(F.concat_ws("|", F.col("l_orderkey").cast("string"), F.col("l_suppkey").cast("string"))) < 0.5
        clauses += [(pair(supplied.where(sign)), links(frustrated)), (pair(supplied.where(~sign)), links(-frustrated))]
    parts = lines.select("l_orderkey", "l_partkey").distinct()
    clauses += [
        (_pairs(parts, "op", vid(F.col("l_orderkey"), ORDER), vid(F.col("l_partkey"), PART)), links(wp)),
        (_pairs(orders, "oc", vid(F.col("o_orderkey"), ORDER), vid(F.col("o_custkey"), CUSTOMER)), links(wc)),
        (_pairs(customers, "cn", vid(F.col("c_custkey"), CUSTOMER), vid(F.col("c_nationkey"), NATION)), links(wn)),
    ]
    return ground(spark, variables, clauses)


#: Equality weights of the snowflake: line-order, order-customer, customer-nation, nation-region.
SNOWFLAKE = (0.8, 0.6, 0.2, 0.1)


def snowflake_tree(spark: SparkSession, sf_dir: str, weights=SNOWFLAKE) -> FactorGraph:
    """Lines, orders, customers, nations and regions: a forest of one tree per region. Evidence: return flags of a line group, averaged."""
    score = F.when(F.col("l_returnflag") == "R", 1.0).when(F.col("l_returnflag") == "A", -0.3).otherwise(0.0)
    lines = table(spark, sf_dir, "lineitem").groupBy("l_orderkey", "l_linenumber").agg(F.avg(score).alias("odds")).withColumn("key", F.col("l_orderkey") * 8 + F.col("l_linenumber"))
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    customers, nations = table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey"), table(spark, sf_dir, "nation").select("n_nationkey", "n_regionkey")
    regions = table(spark, sf_dir, "region").select("r_regionkey")
    flat = lambda df, key, kind: df.select(vid(F.col(key), kind).alias("vid"), _binary(F.lit(0.0)).alias("prior"))
    variables = _variables(
        lines.select(vid(F.col("key"), LINE).alias("vid"), _binary(F.col("odds")).alias("prior")),
        flat(orders, "o_orderkey", ORDER),
        flat(customers, "c_custkey", CUSTOMER),
        flat(nations, "n_nationkey", NATION),
        flat(regions, "r_regionkey", REGION),
    )
    w = [([2, 2], potts(2, x)) for x in weights]
    return ground(
        spark,
        variables,
        [
            (_pairs(lines, "lo", vid(F.col("key"), LINE), vid(F.col("l_orderkey"), ORDER)), w[0]),
            (_pairs(orders, "oc", vid(F.col("o_orderkey"), ORDER), vid(F.col("o_custkey"), CUSTOMER)), w[1]),
            (_pairs(customers, "cn", vid(F.col("c_custkey"), CUSTOMER), vid(F.col("c_nationkey"), NATION)), w[2]),
            (_pairs(nations, "nr", vid(F.col("n_nationkey"), NATION), vid(F.col("n_regionkey"), REGION)), w[3]),
        ],
    )


#: Event types in the order of the emission table's columns.
EVENT_TYPES = ("click", "error", "login", "purchase", "view")
STICKY = 1.5


def emission(states: int = 3, types=EVENT_TYPES) -> list[list[float]]:
    """Rows: hidden states; md5-valued, normalised."""
    import hashlib

    u = [[0.1 + int(hashlib.md5(f"emission|{s}|{t}".encode()).hexdigest()[:8], 16) / 2**32 for t in range(len(types))] for s in range(states)]
    return [[x / sum(row) for x in row] for row in u]


def _chain(spark: SparkSession, nodes: DataFrame, group: list[Column], order: list[Column], table_: tuple[list[int], list[float]], name: str) -> FactorGraph:
    """nodes: vid, prior. Neighbours in order within group are linked."""
    w = Window.partitionBy(*group).orderBy(*order)
    linked = nodes.withColumn("next", F.lead("vid").over(w)).where("next is not null")
    return ground(spark, _variables(nodes.select("vid", "prior")), [(_pairs(linked, name, F.col("vid"), F.col("next")), table_)])


def events_chains(spark: SparkSession, sf_dir: str, single: bool = False) -> FactorGraph:
    """A hidden mood per event, a chain per user in order of time (single: one chain of all events)."""
    rows = emission()
    e = table(spark, sf_dir, "events").select("event_id", "user_id", "ts", "event_type")
    cases = [[F.when(F.col("event_type") == t, F.lit(math.log(rows[s][k]))) for k, t in enumerate(EVENT_TYPES)] for s in range(3)]
    nodes = e.withColumn("vid", vid(F.col("event_id"), OTHER)).withColumn("prior", F.array(*[F.coalesce(*c, F.lit(0.0)) for c in cases]))
    return _chain(spark, nodes, [F.lit(1) if single else F.col("user_id")], [F.col("ts"), F.col("event_id")], ([3, 3], potts(3, STICKY)), "ev")


def conversation_chains(spark: SparkSession, sf_dir: str) -> FactorGraph:
    """A bit per turn, evidence from a question mark, a chain per conversation."""
    c = table(spark, sf_dir, "conversations").select("conv_id", "turn", "text")
    nodes = c.withColumn("vid", vid(F.col("conv_id") * 1000 + F.col("turn"), OTHER)).withColumn("prior", _binary(F.when(F.contains("text", F.lit("?")), 0.8).otherwise(-0.2)))
    return _chain(spark, nodes, [F.col("conv_id")], [F.col("turn")], ([2, 2], potts(2, 0.7)), "cv")


COLOURS, SIGMA, SMOOTH = 5, 1.0, 0.5


def gaussian_unary(observed: Column, levels: int = COLOURS, sigma: float = SIGMA) -> Column:
    """Log likelihood of every level; flat where nothing is observed."""
    known = F.array(*[-((F.lit(float(x)) - observed) * (F.lit(float(x)) - observed)) / (2 * sigma * sigma) for x in range(levels)])
    return F.when(observed.isNull(), F.array(*[F.lit(0.0)] * levels)).otherwise(known)


def grid(spark: SparkSession, pixels: DataFrame, columns: int, levels: int = COLOURS, sigma: float = SIGMA, smooth: float = SMOOTH) -> FactorGraph:
    """A 4-neighbour grid from pixels (r, c, obs); a null obs is latent. Every pixel of the table is a variable."""
    at = F.col("r").cast("long") * columns + F.col("c")
    p = pixels.withColumn("vid", vid(at, OTHER))
    nodes = p.select("vid", gaussian_unary(F.col("obs"), levels, sigma).alias("prior"))
    ids = p.select("vid", "r", "c")
    right = ids.select((F.col("vid") - 16).alias("vid"), F.col("vid").alias("to"), (F.col("c") - 1).alias("nc"))
    down = ids.select((F.col("vid") - 16 * columns).alias("vid"), F.col("vid").alias("to"))
    across = ids.join(right, "vid").where("nc = c").select("vid", "to")
    along = ids.join(down, "vid").select("vid", "to")
    return ground(spark, _variables(nodes), [(_pairs(across.unionByName(along), "px", F.col("vid"), F.col("to")), ([levels, levels], linear_penalty(levels, smooth)))])


def lineitem_pixels(spark: SparkSession, sf_dir: str, buckets: int = 100) -> DataFrame:
    """r (ship week), c (part bucket), obs (0 to 4, null where no line fell) of the whole rectangle."""
    week = F.floor(F.datediff(F.col("l_shipdate").cast("date"), F.lit("1995-01-01").cast("date")) / 7).cast("int")
    seen = table(spark, sf_dir, "lineitem").groupBy(week.alias("r"), (F.col("l_partkey") % buckets).cast("int").alias("c")).agg(F.least(F.lit(4.0), F.floor(F.avg("l_quantity") / 10).cast("double")).alias("obs"))
    rows = seen.agg(F.min("r").alias("lo"), F.max("r").alias("hi")).select(F.explode(F.sequence("lo", "hi")).alias("r"))
    return rows.select("r", F.explode(F.sequence(F.lit(0), F.lit(buckets - 1))).alias("c")).join(seen, ["r", "c"], "left")


def grid_lineitem(spark: SparkSession, sf_dir: str) -> FactorGraph:
    return grid(spark, lineitem_pixels(spark, sf_dir), 100)


def embedding_pixels(spark: SparkSession, sf_dir: str) -> DataFrame:
    """r (vector), c (dimension), obs: the value cut into five levels at -0.15, -0.05, 0.05, 0.15."""
    e = table(spark, sf_dir, "embeddings").select("vec_id", F.posexplode("embedding").alias("c", "x"))
    x = F.col("x").cast("double")
    level = F.when(x < -0.15, 0.0).when(x < -0.05, 1.0).when(x < 0.05, 2.0).when(x < 0.15, 3.0).otherwise(4.0)
    return e.select(F.col("vec_id").alias("r"), "c", level.alias("obs"))


def synthetic_pixels(spark: SparkSession, rows: int, columns: int, levels: int = COLOURS, sigma: float = 1.0, seed: int = 42) -> DataFrame:
    """A noisy image, busier in its top half (rings) than below (one slow ramp); noise from two md5 numbers per pixel."""
    p = spark.range(rows * columns).select(F.floor(F.col("id") / columns).cast("int").alias("r"), (F.col("id") % columns).cast("int").alias("c"))
    dist = F.sqrt(F.pow(F.col("r") - rows / 4, F.lit(2.0)) + F.pow(F.col("c") - columns / 2, F.lit(2.0)))
    rings, ramp = F.floor(dist * levels / 12) % levels, F.floor(F.col("c") * levels / columns)
    u = lambda k: md5_uniform(F.concat_ws("|", F.lit(str(seed)), F.col("r").cast("string"), F.col("c").cast("string"), F.lit(k)))
    noise = F.sqrt(-2 * F.ln(u("a") + 1e-12)) * F.cos(2 * math.pi * u("b"))
    true = F.when(F.col("r") < rows / 2, rings).otherwise(ramp).cast("double")
    return p.select("r", "c", true.alias("true"), (true + sigma * noise).alias("obs"))


def grid_synthetic(spark: SparkSession, rows: int = 500, columns: int = 500, levels: int = COLOURS, sigma: float = 1.0, seed: int = 42) -> FactorGraph:
    return grid(spark, synthetic_pixels(spark, rows, columns, levels, sigma, seed), columns, levels, sigma)


def docs_mln(spark: SparkSession, sf_dir: str) -> FactorGraph:
    """Quality and toxicity bits of documents, trust of sources, a hub per language, and match bits of documents that begin alike.

    Every document is linked to the least id of its text, so equal texts are all linked through their class, however many copies there
    are. These representatives, where they share their first 24 characters, are linked in order of id: match bits of neighbours and of
    next neighbours, closed by transitivity clauses of three literals. Labels clamp what they know.
    """
    d = table(spark, sf_dir, "documents").select("doc_id", "text", "lang", "source")
    labels = table(spark, sf_dir, "labels")
    n = d.join(labels, "doc_id", "left")
    clamp = lambda c: F.when(F.col(c) == 1, 3.0).when(F.col(c) == 0, -3.0).otherwise(0.0)
    named = lambda c, kind: vid(F.pmod(F.xxhash64(c), F.lit(1 << 50)), kind)
    # A null text is a class of its own.
    c = d.select("doc_id", F.lower(F.substring("text", 1, 24)).alias("start"), F.coalesce(F.sha2("text", 256), F.col("doc_id").cast("string")).alias("digest"))
    first = c.groupBy("digest").agg(F.min("doc_id").alias("first"), F.first("start").alias("start"))
    w = Window.partitionBy("start").orderBy("first")
    lead = first.select(F.col("first").alias("doc_id"), *[F.lead("first", k).over(w).alias(f"doc_id{k}") for k in (1, 2)])
    pair = lambda a, b: vid(F.pmod(F.xxhash64(F.col(a), F.col(b)), F.lit(1 << 50)), LINE)
    match = lambda df, a, b, odds: df.where(F.col(b).isNotNull()).select(pair(a, b).alias("vid"), _binary(F.lit(odds)).alias("prior"), F.col(a).alias("a"), F.col(b).alias("b"))
    copies = match(first.join(c, "digest").where("doc_id > first"), "first", "doc_id", 3.0)
    both = copies.unionByName(match(lead, "doc_id", "doc_id1", -0.5)).unionByName(match(lead, "doc_id", "doc_id2", -0.5))
    variables = _variables(
        n.select(vid(F.col("doc_id"), ORDER).alias("vid"), _binary(clamp("quality")).alias("prior")),
        n.select(vid(F.col("doc_id"), CUSTOMER).alias("vid"), _binary(clamp("toxic")).alias("prior")),
        d.select(named("source", SUPPLIER).alias("vid")).distinct().select("vid", _binary(F.lit(0.0)).alias("prior")),
        d.select(named("lang", NATION).alias("vid")).distinct().select("vid", _binary(F.lit(0.0)).alias("prior")),
        both.select("vid", "prior"),
    )
    quality, toxic = vid(F.col("doc_id"), ORDER), vid(F.col("doc_id"), CUSTOMER)
    implies = Clause("match & quality -> quality", 0.8, ((0, 0), (1, 0), (2, 1)))
    closes = Clause("match & match -> match", 1.0, ((0, 0), (1, 0), (2, 1)))
    three = lambda df, name, a, b, c: df.select(F.concat_ws("|", F.lit(name), a.cast("string"), b.cast("string"), c.cast("string")).alias("key"), a.alias("v0"), b.alias("v1"), c.alias("v2"))
    triple = lead.where("doc_id2 is not null")
    return ground(
        spark,
        variables,
        [
            (_pairs(d, "qs", quality, named("source", SUPPLIER)), ([2, 2], potts(2, 0.4))),
            (_pairs(d, "ql", quality, named("lang", NATION)), ([2, 2], potts(2, 0.02))),
            (_pairs(d, "tq", toxic, quality), ([2, 2], [0.0, 0.5, 0.5, 0.0])),
            (three(both, "mq", F.col("vid"), vid(F.col("a"), ORDER), vid(F.col("b"), ORDER)), implies.potential()),
            (three(triple, "mm", pair("doc_id", "doc_id1"), pair("doc_id1", "doc_id2"), pair("doc_id", "doc_id2")), closes.potential()),
        ],
    )


def supplier_star(spark: SparkSession, sf_dir: str, weight: float = 0.02) -> FactorGraph:
    """The supplier of most orders and those orders."""
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey").distinct()
    hub = lines.groupBy("l_suppkey").count().orderBy(F.desc("count"), "l_suppkey").limit(1).select("l_suppkey")
    own = lines.join(F.broadcast(hub), "l_suppkey")
    o = table(spark, sf_dir, "orders").join(own, F.col("o_orderkey") == F.col("l_orderkey"))
    variables = _variables(
        o.select(vid(F.col("o_orderkey"), ORDER).alias("vid"), _binary(order_odds(F.col("o_orderstatus"), F.col("o_orderpriority"))).alias("prior")),
        hub.select(vid(F.col("l_suppkey"), SUPPLIER).alias("vid"), _binary(F.lit(0.0)).alias("prior")),
    )
    return ground(spark, variables, [(_pairs(own, "os", vid(F.col("l_orderkey"), ORDER), vid(F.col("l_suppkey"), SUPPLIER)), ([2, 2], potts(2, weight)))])


def page_hosts(spark: SparkSession, sf_dir: str) -> FactorGraph:
    """Spam bits of pages and of their hosts. Evidence: the share of symbols in the page's text."""
    p = table(spark, sf_dir, "pages").select("page_id", "html", F.regexp_extract("url", "://([^/?#]*)", 1).alias("host"))
    odds = F.least(F.lit(2.0), 200.0 * (F.length("html") - F.length(F.translate("html", "#*$%", ""))) / F.greatest(F.length("html"), F.lit(1)) - 0.5)
    host = vid(F.pmod(F.xxhash64("host"), F.lit(1 << 50)), SUPPLIER)
    variables = _variables(p.select(vid(F.col("page_id"), ORDER).alias("vid"), _binary(odds).alias("prior")), p.select(host.alias("vid")).distinct().select("vid", _binary(F.lit(0.0)).alias("prior")))
    return ground(spark, variables, [(_pairs(p, "ph", vid(F.col("page_id"), ORDER), host), ([2, 2], potts(2, 0.5)))])


def literal(spark: SparkSession, priors: list[list[float]], factors: list[tuple[list[int], list[float]]]) -> FactorGraph:
    """A small graph: variable k has id 2k and factor k id 2k + 1; factors are (variables, log table)."""
    variables = [(2 * k, len(p), [float(x) for x in p]) for k, p in enumerate(priors)]
    edges = [(2 * k + 1, 2 * v, s, len(priors[v]), k) for k, (vs, _) in enumerate(factors) for s, v in enumerate(vs)]
    from ..operators.model import EDGES, VARIABLES

    tables = {k: ([len(priors[v]) for v in vs], t) for k, (vs, t) in enumerate(factors)}
    return FactorGraph(spark.createDataFrame(variables, VARIABLES), spark.createDataFrame(edges, EDGES), potentials_frame(spark, tables))


#: Unary tables and update stages of the chain on which a belief residual without accumulation stops too early.
PREMATURE_UNARY = ((1 / 9, 9), (9 / 10, 1 / 10), (1 / 2, 1 / 2), (1 / 10, 9 / 10), (9, 1 / 9))
PREMATURE_STAGES = ((2, 4), (3,), (1, 5), (2, 4), (1, 5))


def premature_chain(spark: SparkSession) -> FactorGraph:
    from ..functions.logspace import LOG_ZERO

    equal = [0.0, LOG_ZERO, LOG_ZERO, 0.0]
    return literal(spark, [[math.log(x) for x in u] for u in PREMATURE_UNARY], [([k, k + 1], equal) for k in range(4)])


def premature_trace() -> list[tuple[int, int, float, float, float]]:
    """stage, vertex, accumulated residual, naive residual (-1 stands for infinite) and belief in state 0, in the pairwise form.

    A vertex update sends psi * (product of the other inbound messages) to each neighbour; equality factors pass it on as it is.
    """
    n = 5
    psi = [[x / sum(u) for x in u] for u in PREMATURE_UNARY]
    msg = {(i, j): [0.5, 0.5] for i in range(n) for j in (i - 1, i + 1) if 0 <= j < n}

    def belief(j: int) -> list[float]:
        b = list(psi[j])
        for i in (j - 1, j + 1):
            if 0 <= i < n:
                b = [x * y for x, y in zip(b, msg[(i, j)])]
        return [x / sum(b) for x in b]

    acc, seen, out = [math.inf] * n, [None] * n, []
    for t, stage in enumerate(PREMATURE_STAGES):
        for v in stage:
            i = v - 1
            acc[i], seen[i] = 0.0, belief(i)
            for j in (i - 1, i + 1):
                if 0 <= j < n:
                    m = list(psi[i])
                    for k in (i - 1, i + 1):
                        if 0 <= k < n and k != j:
                            m = [x * y for x, y in zip(m, msg[(k, i)])]
                    old = belief(j)
                    msg[(i, j)] = [x / sum(m) for x in m]
                    acc[j] += sum(abs(x - y) for x, y in zip(old, belief(j)))
        for j in range(n):
            naive = -1.0 if seen[j] is None else sum(abs(x - y) for x, y in zip(seen[j], belief(j)))
            out.append((t, j + 1, -1.0 if math.isinf(acc[j]) else acc[j], naive, belief(j)[0]))
    return out
