"""Factor graphs as three tables.

variables: vid, card, prior (log weights by state; unary factors may be folded into it)
edges: fid, vid, slot, card, potential_id (a row per factor and variable)
factors: fid, potential_id, vids by slot (a row per factor; the same as edges, where a graph comes with it)
potentials: potential_id, cards, logpsi (row-major, last slot fastest). Templates are shared by many factors and stay few.

Ids: even for variables, odd for factors, so one long keys both.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce
from operator import mul

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.logspace import LOG_ZERO

VARIABLES = "vid long, card int, prior array<double>"
EDGES = "fid long, vid long, slot int, card int, potential_id long"
POTENTIALS = "potential_id long, cards array<int>, logpsi array<double>"


@dataclass
class FactorGraph:
    variables: DataFrame
    edges: DataFrame
    potentials: DataFrame
    factors: DataFrame | None = None

    @property
    def spark(self) -> SparkSession:
        return self.variables.sparkSession

    def templates(self) -> dict[int, tuple[list[int], list[float]]]:
        """The potentials on the driver."""
        return {r["potential_id"]: (r["cards"], r["logpsi"]) for r in self.potentials.collect()}

    def ends(self) -> DataFrame:
        """fid, vid, slot, potential_id and other, the variable on the factor's other slot (null: none): the edges of factors of at most two variables."""
        f = self.factors
        if f is None:
            on = lambda s: F.max(F.when(F.col("slot") == s, F.col("vid")))
            f = self.edges.groupBy("fid", "potential_id").agg(F.filter(F.array(on(0), on(1)), lambda v: v.isNotNull()).alias("vids"))
        a, b = F.get("vids", F.lit(0)), F.get("vids", F.lit(1))
        end = lambda s, own, other: F.struct(F.lit(s).alias("slot"), own.alias("vid"), other.alias("other"))
        both = f.select("fid", "potential_id", F.explode(F.array(end(0, a, b), end(1, b, a))).alias("e"))
        return both.select("fid", "e.vid", "e.slot", "potential_id", "e.other").where("vid is not null")

    def validate(self) -> DataFrame:
        """rule and violations: a row per rule, zeros for a sound graph."""
        e, v, p = self.edges, self.variables, self.potentials
        size = F.aggregate("cards", F.lit(1), lambda a, c: a * c)
        factor = e.groupBy("fid").agg(F.count(F.lit(1)).alias("n"), F.count_distinct("slot").alias("d"), F.max("slot").alias("top"), F.count_distinct("potential_id").alias("ps"))
        on_slot = e.join(F.broadcast(p), "potential_id").where(F.get("cards", F.col("slot")).isNull() | (F.get("cards", F.col("slot")) != F.col("card")))
        rules = {
            "card_of_edge_and_variable": e.join(v.select("vid", F.col("card").alias("c")), "vid", "left").where(F.col("c").isNull() | (F.col("c") != F.col("card"))),
            "card_of_edge_and_template": on_slot,
            "slots_complete": factor.where((F.col("n") != F.col("d")) | (F.col("top") + 1 != F.col("n"))),
            "one_template": factor.where("ps != 1"),
            "template_length": p.where(F.size("logpsi") != size),
            "finite": p.where(F.exists("logpsi", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) > -LOG_ZERO))),
            "prior_length": v.where(F.size("prior") != F.col("card")),
            "duplicate_variable": v.groupBy("vid").count().where("count > 1"),
        }
        return reduce(DataFrame.unionByName, [d.agg(F.count(F.lit(1)).alias("violations")).select(F.lit(name).alias("rule"), "violations") for name, d in rules.items()])

    def degrees(self) -> DataFrame:
        """kind, degree and n: how many variables and factors have so many neighbours."""
        e = self.edges
        by = [e.groupBy(F.col(c).alias("x")).count().select(F.lit(k).alias("kind"), F.col("count").alias("degree")) for c, k in (("vid", "variable"), ("fid", "factor"))]
        return by[0].unionByName(by[1]).groupBy("kind", "degree").agg(F.count(F.lit(1)).alias("n"))

    def with_evidence(self, evidence: DataFrame, mode: str = "clamp", strength: float = -LOG_ZERO) -> FactorGraph:
        """evidence: vid, state (null: nothing known). "clamp" sets the other states' prior to -strength. "reduce" takes the known variables out
        of the graph and their states into the factors: a factor keeps the part of its table that agrees with them, and none of
        its known slots. The reduced templates, one for each template and combination of known states, are made on the driver."""
        if mode not in ("clamp", "reduce"):
            raise ValueError(f"unknown mode {mode!r}")
        known = evidence.where("state is not null").select("vid", F.col("state").alias("s"))
        if mode == "reduce":
            return self._reduced(known)
        fixed = F.transform("prior", lambda x, i: F.when(i == F.col("s"), F.lit(0.0)).otherwise(F.lit(-abs(strength))))
        v = self.variables.join(known, "vid", "left").withColumn("prior", F.when(F.col("s").isNull(), F.col("prior")).otherwise(fixed)).drop("s")
        return FactorGraph(v, self.edges, self.potentials, self.factors)

    def _reduced(self, known: DataFrame) -> FactorGraph:
        fixed = F.sort_array(F.collect_list(F.when(F.col("s").isNotNull(), F.struct("slot", "s"))))
        held = self.edges.join(known, "vid", "left")
        held = held.join(held.groupBy("fid").agg(fixed.alias("fixed")), "fid")
        kinds = sorted((r["potential_id"], tuple((x["slot"], x["s"]) for x in r["fixed"])) for r in held.select("potential_id", "fixed").distinct().collect())
        templates, tables, numbers = self.templates(), {}, []
        for k, (p, fixed_slots) in enumerate(kinds):
            cards, logpsi = templates[p]
            at = dict(fixed_slots)
            index = tuple(at.get(slot, slice(None)) for slot in range(len(cards)))
            part = np.array(logpsi).reshape(cards)[index]
            if part.ndim:
                tables[k] = (list(part.shape), part.ravel().tolist())
                numbers.append((p, [list(x) for x in fixed_slots], k))
        numbered = F.broadcast(self.spark.createDataFrame(numbers, "potential_id long, known array<array<int>>, number long"))
        same = F.transform("fixed", lambda x: F.array(x["slot"].cast("int"), x["s"].cast("int")))
        edges = held.where("s is null").withColumn("known", same).join(numbered, ["potential_id", "known"])
        before = F.size(F.filter("fixed", lambda x: x["slot"] < F.col("slot")))
        edges = edges.select("fid", "vid", (F.col("slot") - before).cast("int").alias("slot"), "card", F.col("number").alias("potential_id"))
        return FactorGraph(self.variables.join(known, "vid", "left_anti"), edges, potentials_frame(self.spark, tables))


def potts(card: int, weight: float) -> list[float]:
    """Log weight on equal states."""
    return [weight if a == b else 0.0 for a in range(card) for b in range(card)]


def linear_penalty(card: int, weight: float) -> list[float]:
    return [-weight * abs(a - b) for a in range(card) for b in range(card)]


@dataclass(frozen=True)
class Clause:
    """A weighted disjunction over binary atoms; a literal is (slot, wanted value)."""

    name: str
    weight: float
    literals: tuple[tuple[int, int], ...]

    def potential(self) -> tuple[list[int], list[float]]:
        """cards and log table: the weight for every assignment that satisfies the clause, else 0."""
        n = len(self.literals)
        rows = [[(k >> (n - 1 - s)) & 1 for s in range(n)] for k in range(2**n)]
        return [2] * n, [self.weight if any(r[s] == want for s, want in self.literals) else 0.0 for r in rows]


def potentials_frame(spark: SparkSession, tables: dict[int, tuple[list[int], list[float]]]) -> DataFrame:
    rows = []
    for k, (cards, logpsi) in sorted(tables.items()):
        if len(logpsi) != reduce(mul, cards, 1) or len(logpsi) > 2**20:
            raise ValueError(f"potential {k}: {len(logpsi)} entries for domains {cards}")
        rows.append((k, list(map(int, cards)), [max(float(x), LOG_ZERO) for x in logpsi]))
    return spark.createDataFrame(rows, POTENTIALS)


def ground(spark: SparkSession, variables: DataFrame, clauses: list[tuple[DataFrame, tuple[list[int], list[float]]]]) -> FactorGraph:
    """A graph from variables and, per clause, a table with one row per grounding (columns key, v0, v1, ...) and a shared potential.

    key (string) must be unique over all clauses; it names the factor, whose id is odd and made of the first 60 bits of its md5, so that other engines repeat it.
    """
    parts, factors, tables = [], [], {}
    for k, (rows, potential) in enumerate(clauses):
        tables[k] = potential
        slots = [F.struct(F.lit(s).alias("slot"), F.col(f"v{s}").alias("vid"), F.lit(c).alias("card")) for s, c in enumerate(potential[0])]
        fid = F.conv(F.substring(F.md5(F.col("key").cast("binary")), 1, 15), 16, 10).cast("long") * 2 + 1
        vids = F.array(*[F.col(f"v{s}") for s in range(len(potential[0]))])
        factors.append(rows.select(fid.alias("fid"), F.lit(k).cast("long").alias("potential_id"), vids.alias("vids")))
        made = rows.select(fid.alias("fid"), F.explode(F.array(*slots)).alias("e"))
        parts.append(made.select("fid", "e.vid", "e.slot", "e.card", F.lit(k).cast("long").alias("potential_id")))
    return FactorGraph(variables, reduce(DataFrame.unionByName, parts), potentials_frame(spark, tables), reduce(DataFrame.unionByName, factors))
