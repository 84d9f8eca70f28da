"""The message equations on factors of at most two variables: a row per end of a factor, kept with the variable at that end.

rows: vid, other (the variable at the other end; null: none), code, r1, r2, ... (what the factor sends to vid, log values by state less that of
state 0). ``code`` is 2 * potential_id + slot. A variable's prior is a row too, whose code is the variable's number of states, negative. So all that a variable
needs comes in one shuffle, and what it answers is addressed to the other ends: an iteration is one shuffle, and no row looks for its
partner. States are unrolled into columns, which Spark compiles; absent states of narrow variables hold 0.

Changes and damping need what the factor sends to the other end at the same time (``q1``, ...). That is not sent but found again: a tracked row
brings what its variable received before (``o1``, ...; damped, also what the other end had, ``b1``, ...), from which the variable
repeats its last answer.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.logspace import LOG_ZERO
from .model import FactorGraph

#: States up to which the equations are unrolled; wider graphs go by ``messages``.
WIDEST = 8


def fits(width: int, arity: int) -> bool:
    return arity <= 2 and 2 <= width <= WIDEST


def named(prefix: str, width: int) -> list[str]:
    return [f"{prefix}{k}" for k in range(1, width)]


def _relative(values: str, width: int) -> list[Column]:
    return [F.coalesce(F.get(values, F.lit(k)) - F.get(values, F.lit(0)), F.lit(0.0)) for k in range(1, width)]


def start(fg: FactorGraph, width: int, fids: bool = False) -> DataFrame:
    """rows of uniform messages, with fid on request, brought together by variable."""
    nothing, flat = F.lit(None).cast("long"), [F.lit(0.0).alias(c) for c in named("r", width)]
    fid = lambda c: [c.alias("fid")] if fids else []
    ends = fg.ends().select("vid", "other", (2 * F.col("potential_id") + F.col("slot")).cast("int").alias("code"), *flat, *fid(F.col("fid")))
    prior = [c.alias(n) for c, n in zip(_relative("prior", width), named("r", width))]
    own = fg.variables.select("vid", nothing.alias("other"), (-F.col("card")).alias("code"), *prior, *fid(nothing))
    return gathered(ends.unionByName(own))


def gathered(rows: DataFrame) -> DataFrame:
    return rows.repartition("vid")


def tables(fg: FactorGraph, width: int) -> DataFrame:
    """code, to (states at the receiving end) and p_x_y: the template's values, x at the sending end. A unary template answers its own variable."""
    out = []
    for k, (cards, logpsi) in sorted(fg.templates().items()):
        for slot in range(len(cards)):
            own, to = cards[slot], cards[1 - slot] if len(cards) == 2 else cards[0]
            at = (lambda x, y: y) if len(cards) == 1 else (lambda x, y: x * to + y) if slot == 0 else (lambda x, y: y * own + x)  # noqa: B023
            out.append((2 * k + slot, to, *[float(logpsi[at(x, y)]) if x < own and y < to else None for x in range(width) for y in range(width)]))
    cells = [f"p_{x}_{y}" for x in range(width) for y in range(width)]
    found = fg.spark.createDataFrame(out, "code int, to int, " + ", ".join(f"{c} double" for c in cells))
    return F.broadcast(found.select("code", "to", *[F.coalesce(F.exp(c), F.lit(0.0)).alias(c) for c in cells]))


def others(rows: DataFrame, width: int, of: tuple[tuple[str, str], ...] = (("r", "v"),)) -> DataFrame:
    """rows (gathered) with v1, ...: prior and messages of all other factors. Rows of what is no variable of the graph are dropped. of: prefixes of what is summed and of what comes out."""
    at = Window.partitionBy("vid")
    pairs = [(a, b) for x, y in of for a, b in zip(named(x, width), named(y, width))]
    sums = rows.select("*", F.min("code").over(at).alias("least"), *[F.sum(a).over(at).alias(f"_{a}") for a, _ in pairs])
    return sums.where("least < 0").select(*rows.columns, *[(F.col(f"_{a}") - F.col(a)).alias(b) for a, b in pairs])


def _answer(rows: DataFrame, width: int, into: str, v: str = "v") -> DataFrame:
    """rows (with the templates' values) with into1, ...: what the factor sends to its other end, given v."""
    keep, states = rows.columns, range(width)
    v = [F.lit(0.0), *[F.col(c) for c in named(v, width)]]
    rows = rows.withColumn("_top", F.greatest(*v))
    # The largest term is 1 and templates are bounded, so sums need no further shift.
    rows = rows.select(*keep, *[F.exp(F.greatest(v[x] - F.col("_top"), F.lit(LOG_ZERO))).alias(f"_e{x}") for x in states])
    total = lambda y: sum((F.col(f"_e{x}") * F.col(f"p_{x}_{y}") for x in states[1:]), F.col("_e0") * F.col(f"p_0_{y}"))
    rows = rows.select(*keep, *[F.ln(total(y)).alias(f"_s{y}") for y in states])
    rows = rows.withColumn("_hi", F.greatest(*[F.col(f"_s{y}") for y in states]))
    floor = lambda y: F.greatest(F.col(f"_s{y}") - F.col("_hi"), F.lit(LOG_ZERO))
    return rows.select(*keep, *[F.when(F.col(f"_s{y}").isNotNull(), floor(y) - floor(0)).otherwise(0.0).alias(f"{into}{y}") for y in states[1:]])


def probabilities(r: list[Column], card: Column) -> list[Column]:
    """Probabilities of the states from relative log values; 0 for absent states."""
    r = [F.lit(0.0), *r]
    top = F.greatest(*r)
    e = [F.exp(F.greatest(x - top, F.lit(LOG_ZERO))) for x in r]
    e[1:] = [F.when(F.lit(k) < card, x).otherwise(0.0) for k, x in enumerate(e[1:], 1)]
    return [x / sum(e[1:], e[0]) for x in e]


def _mixed(rows: DataFrame, width: int, new: str, old: str, damping: float, space: str) -> DataFrame:
    if not damping:
        return rows
    n, o = ([F.col(c) for c in named(p, width)] for p in (new, old))
    if space == "log":
        mixed = [(1 - damping) * a + damping * b for a, b in zip(n, o)]
    else:
        logs = [F.ln((1 - damping) * a + damping * b) for a, b in zip(probabilities(n, F.col("to")), probabilities(o, F.col("to")))]
        mixed = [F.coalesce(x - logs[0], F.lit(0.0)) for x in logs[1:]]
    return rows.withColumns(dict(zip(named(new, width), mixed)))


def step(rows: DataFrame, values: DataFrame, width: int, tracked: bool = False, damping: float = 0.0, space: str = "prob") -> DataFrame:
    """What the variables of gathered rows answer: the rows of the next iteration, not yet gathered. values: ``tables``.

    tracked: with delta, the L1 change of the message (null for a prior), and with o1, ... for a further tracked step. rows then hold q1, ... or o1, ... . Damping needs tracked rows.
    """
    if damping and not tracked:
        raise ValueError("damping needs tracked rows")
    r, q, o, b, n = (named(p, width) for p in "rqobn")
    fid = ["fid"] if "fid" in rows.columns else []
    if tracked and "q1" not in rows.columns:
        rows = others(rows, width, (("r", "v"), ("o", "w"))).join(values, "code", "left")
        rows = _mixed(_answer(rows, width, "q", "w"), width, "q", "b", damping, space)
    else:
        rows = others(rows, width).join(values, "code", "left")
    rows = _mixed(_answer(rows, width, "n"), width, "n", "q", damping, space)
    prior = F.col("code") < 0
    of = lambda was, now: [F.when(prior, F.col(a)).otherwise(F.col(x)).alias(c) for a, x, c in zip(r, was, now)]
    flip = F.when(F.col("other").isNull(), F.col("code")).otherwise(F.col("code") + 1 - 2 * (F.col("code") % 2)).cast("int")
    more = []
    if tracked:
        change = [F.abs(x - y) for x, y in zip(*(probabilities([F.col(c) for c in p], F.col("to")) for p in (n, q)))]
        more = [*of(q, o), *([F.col(a).alias(c) for a, c in zip(r, b)] if damping else []), F.when(~prior, sum(change[1:], change[0])).alias("delta")]
    back = F.when(F.col("other").isNotNull(), F.col("vid")).alias("other")
    return rows.select(F.coalesce("other", "vid").alias("vid"), back, flip.alias("code"), *of(n, r), *more, *fid)


def totals(rows: DataFrame, width: int) -> DataFrame:
    """vid, card and t1, ...: prior plus all messages of every variable (gathered rows)."""
    sums = rows.groupBy("vid").agg((-F.min("code")).alias("card"), *[F.sum(a).alias(b) for a, b in zip(named("r", width), named("t", width))])
    return sums.where("card > 0")


def beliefs(rows: DataFrame, width: int) -> DataFrame:
    """vid, state, belief of gathered rows."""
    p = F.array(*probabilities([F.col(c) for c in named("t", width)], F.col("card")))
    return totals(rows, width).select("vid", F.posexplode(F.slice(p, F.lit(1), F.col("card"))).alias("state", "belief"))


def edges(rows: DataFrame, fg: FactorGraph, width: int) -> DataFrame:
    """The state as ``messages`` has it: fid, vid, slot, card, potential_id, f2v and, of tracked rows, delta. Rows with fid."""
    cards = F.broadcast(fg.potentials.select(F.col("potential_id"), F.posexplode("cards").alias("slot", "card")))
    held = rows.where("code >= 0").withColumn("potential_id", F.floor(F.col("code") / 2).cast("long")).withColumn("slot", F.col("code") % 2).join(cards, ["potential_id", "slot"])
    f2v = F.slice(F.array(*[F.ln(p) for p in probabilities([F.col(c) for c in named("r", width)], F.col("card"))]), F.lit(1), F.col("card"))
    return held.select("fid", "vid", "slot", "card", "potential_id", f2v.alias("f2v"), *(["delta"] if "delta" in rows.columns else []))
