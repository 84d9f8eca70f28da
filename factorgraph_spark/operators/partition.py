"""Placing a graph: costs, cuts, over-segmentation, baselines.

Vertices are variables and factors; assignments are tables (vid, piece or block).
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.logspace import md5_uniform
from ..sources.tables import cut
from .model import FactorGraph

#: Vertices that the driver cuts itself; larger graphs are coarsened on the cluster first.
DRIVER_VERTICES = 50_000
#: Edges that the driver cuts itself, unless there are hardly more vertices than parts.
DRIVER_EDGES = 5_000_000


def _updates(updates: DataFrame | None, df: DataFrame, key: str, name: str) -> DataFrame:
    if updates is None:
        return df.withColumn(name, F.lit(1.0))
    u = updates.select(F.col("vid").alias(key), F.col("n_updates").cast("double").alias(name))
    return df.join(u, key, "left").withColumn(name, F.coalesce(name, F.lit(0.0)))


def edge_cost(fg: FactorGraph, updates: DataFrame | None = None, c_comm: float = 1.0) -> DataFrame:
    """fid, vid, cost: updates of both ends, times message size plus header."""
    e = _updates(updates, _updates(updates, fg.edges.select("fid", "vid", "card"), "fid", "uf"), "vid", "uv")
    return e.select("fid", "vid", ((F.col("uf") + F.col("uv")) * (F.col("card") + c_comm)).alias("cost"))


def vertex_work(fg: FactorGraph, updates: DataFrame | None = None) -> DataFrame:
    """vid, work: updates, times degree, times states (of a factor: cells of its table)."""
    size = fg.potentials.select("potential_id", F.size("logpsi").alias("cells"))
    f = fg.edges.groupBy("fid", "potential_id").agg(F.count(F.lit(1)).alias("d")).join(F.broadcast(size), "potential_id").select(F.col("fid").alias("vid"), (F.col("d") * F.col("cells")).cast("double").alias("w"))
    v = fg.variables.select("vid", "card").join(fg.edges.groupBy("vid").agg(F.count(F.lit(1)).alias("d")), "vid", "left")
    v = v.select("vid", (F.coalesce("d", F.lit(0)) * F.col("card")).cast("double").alias("w"))
    both = _updates(updates, f.unionByName(v), "vid", "u")
    return both.select("vid", (F.col("w") * F.col("u")).alias("work"))


def cut_cost(costs: DataFrame, assign: DataFrame, column: str = "block") -> DataFrame:
    """cost of the edges between parts, each counted once, and how many there are."""
    a = assign.select("vid", F.col(column).alias("b"))
    e = costs.join(a.toDF("fid", "bf"), "fid").join(a.toDF("vid", "bv"), "vid").where("bf != bv")
    return e.agg(F.coalesce(F.sum("cost"), F.lit(0.0)).alias("cut_cost"), F.count(F.lit(1)).alias("cut_edges"))


def loads(work: DataFrame, assign: DataFrame, column: str = "block") -> DataFrame:
    return work.join(assign.select("vid", F.col(column).alias("block")), "vid").groupBy("block").agg(F.sum("work").alias("load"), F.count(F.lit(1)).alias("vertices"))


def work_balance(work: DataFrame, assign: DataFrame, parts: int, column: str = "block") -> DataFrame:
    """The heaviest part over the even share."""
    by = loads(work, assign, column)
    return by.agg((parts * F.max("load") / F.sum("load")).alias("balance"))


def feasible(work: DataFrame, assign: DataFrame, parts: int, gamma: float) -> DataFrame:
    return work_balance(work, assign, parts).select(F.lit(gamma).alias("gamma"), (F.col("balance") <= gamma).alias("feasible"))


# Baselines of placement


def vertices(fg: FactorGraph) -> DataFrame:
    return fg.variables.select("vid").unionByName(fg.edges.select(F.col("fid").alias("vid")).distinct())


def hash_parts(fg: FactorGraph, parts: int, seed: int = 42) -> DataFrame:
    """By md5 of the id, which other engines repeat."""
    u = md5_uniform(F.concat_ws("|", F.lit("part"), F.col("vid").cast("string"), F.lit(str(seed))))
    return vertices(fg).select("vid", F.floor(u * parts).cast("long").alias("block"))


def range_parts(fg: FactorGraph, parts: int) -> DataFrame:
    """Even stretches of variable ids; a factor goes with its first variable."""
    v = fg.variables.agg(F.min("vid").alias("lo"), F.max("vid").alias("hi"))
    share = lambda c: F.least(F.lit(parts - 1), F.floor((F.col(c) - F.col("lo")) * parts / (F.col("hi") - F.col("lo") + 1))).cast("long")
    f = fg.edges.groupBy("fid").agg(F.min("vid").alias("first"))
    rows = fg.variables.select("vid", F.col("vid").alias("first")).unionByName(f.select(F.col("fid").alias("vid"), "first"))
    return rows.crossJoin(F.broadcast(v)).select("vid", share("first").alias("block"))  # v has one row


def components(fg: FactorGraph) -> DataFrame:
    """vid and component (least variable id it is connected to), by least labels with pointer jumps."""
    label = cut(fg.variables.select("vid", F.col("vid").alias("c")))
    while True:
        f = fg.edges.join(label, "vid").groupBy("fid").agg(F.min("c").alias("fc"))
        near = fg.edges.join(f, "fid").groupBy("vid").agg(F.min("fc").alias("nc"))
        new = label.join(near, "vid", "left").select("vid", "c", F.least("c", F.coalesce("nc", "c")).alias("m"))
        jump = new.select(F.col("vid").alias("m"), F.col("m").alias("mm"))
        new = cut(new.join(jump, "m").select("vid", "c", F.col("mm").alias("n")))
        if not new.where("n != c").limit(1).count():
            return new.select("vid", F.col("n").alias("component"))
        label = new.select("vid", F.col("n").alias("c"))


# Multilevel cut


def matching_round(edges: DataFrame, work: DataFrame, cap: float, salt: int = 0) -> DataFrame:
    """a, b of one round of heavy-edge matching: vertices that propose to each other.

    edges: u, v, w (u < v); every vertex proposes to its heaviest neighbour whose merged work stays below cap, ties by md5.
    """
    w = work.select("vid", "work")
    both = edges.select("u", "v", "w").unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v"), "w"))
    light = both.join(w.toDF("u", "wu"), "u").join(w.toDF("v", "wv"), "v").where(F.col("wu") + F.col("wv") <= cap)
    tie = md5_uniform(F.concat_ws("|", F.least("u", "v").cast("string"), F.greatest("u", "v").cast("string"), F.lit(str(salt))))
    pick = light.groupBy("u").agg(F.max_by("v", F.struct("w", tie.alias("t"), "v")).alias("v"))
    back = pick.select(F.col("u").alias("v"), F.col("v").alias("u"))
    return pick.join(back, ["u", "v"]).where("u < v").select(F.col("u").alias("a"), F.col("v").alias("b"))


def paired(near: DataFrame, work: DataFrame, cap: float, vertices: int) -> DataFrame:
    """a, b: light vertices (at most half of cap) that have the same hub in near (leaf, hub), in pairs of like work; hubs are dealt over buckets
    of about a thousand vertices."""
    rows = near.join(work.toDF("leaf", "w"), "leaf").where(F.col("w") <= cap / 2)
    rows = rows.withColumn("s", F.pmod(F.xxhash64("leaf"), F.lit(1 + vertices // 1000)))
    place = F.row_number().over(Window.partitionBy("hub", "s").orderBy("w", "leaf"))
    pairs = rows.withColumn("k", F.floor((place - 1) / 2)).groupBy("hub", "s", "k").agg(F.min("leaf").alias("a"), F.max("leaf").alias("b"))
    return pairs.where("a < b").select("a", "b")


def contract(edges: DataFrame, work: DataFrame, matched: DataFrame) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Coarse edges and work, and the map vid -> coarse id (the lower of a pair)."""
    m = work.select("vid").join(matched.select(F.col("b").alias("vid"), F.col("a").alias("to")), "vid", "left").select("vid", F.coalesce("to", "vid").alias("coarse"))
    e = edges.join(m.toDF("u", "cu"), "u").join(m.toDF("v", "cv"), "v").where("cu != cv")
    e = e.groupBy(F.least("cu", "cv").alias("u"), F.greatest("cu", "cv").alias("v")).agg(F.sum("w").alias("w"))
    return e, work.join(m, "vid").groupBy(F.col("coarse").alias("vid")).agg(F.sum("work").alias("work")), m


def _grow(start: np.ndarray, nbr: np.ndarray, wt: np.ndarray, work: np.ndarray, members: np.ndarray, share: float, rng) -> np.ndarray:
    """Members of one side of a bisection, grown from a far vertex by strongest connection."""
    import heapq

    inside = np.zeros(len(work), dtype=bool)
    inside[members] = True
    goal, have = share * work[members].sum(), 0.0
    taken = np.zeros(len(work), dtype=bool)
    gain = np.zeros(len(work))
    order = members.tolist()
    seed = order[int(rng.integers(len(order)))]
    for _ in range(2):  # a far vertex
        seen, line = {seed}, [seed]
        for k in line:
            for j in nbr[start[k] : start[k + 1]].tolist():
                if inside[j] and j not in seen:
                    seen.add(j)
                    line.append(j)
        seed = line[-1]
    heap, spare = [(0.0, seed)], iter(order)
    while have < goal:
        if heap:
            g, k = heapq.heappop(heap)
            if taken[k] or -g < gain[k]:
                continue
        else:
            k = next((x for x in spare if not taken[x]), None)
            if k is None:
                break
        if have and have + work[k] - goal > goal - have:
            if not heap:
                break
            taken[k] = False
            gain[k] = np.inf  # too heavy here: not offered again
            continue
        taken[k] = True
        have += work[k]
        for j, w in zip(nbr[start[k] : start[k + 1]].tolist(), wt[start[k] : start[k + 1]].tolist()):
            if inside[j] and not taken[j] and gain[j] < np.inf:
                gain[j] += w
                heapq.heappush(heap, (-gain[j], j))
    return taken


def _refine(start, nbr, wt, work, part, parts: int, gamma: float, passes: int) -> None:
    """Moves of positive gain that keep every part within gamma times the even share."""
    load = np.bincount(part, weights=work, minlength=parts)
    limit = gamma * work.sum() / parts
    for _ in range(passes):
        moved = 0
        for k in range(len(work)):
            a, b = start[k], start[k + 1]
            if a == b:
                continue
            own = part[k]
            near = part[nbr[a:b]]
            if (near == own).all():
                continue
            pull = np.bincount(near, weights=wt[a:b], minlength=parts)
            pull_own = pull[own]
            pull[load + work[k] > limit] = -1
            pull[own] = pull_own
            to = int(pull.argmax())
            over = load[own] > limit
            if to != own and (pull[to] > pull_own or over):
                part[k] = to
                load[own] -= work[k]
                load[to] += work[k]
                moved += 1
        if not moved:
            return


def cut_arrays(n: int, u: np.ndarray, v: np.ndarray, w: np.ndarray, work: np.ndarray, parts: int, gamma: float = 1.03, seed: int = 42, passes: int = 4) -> np.ndarray:
    """Part of every vertex by recursive bisection and refinement, on arrays."""
    order = np.argsort(np.concatenate([u, v]), kind="stable")
    src = np.concatenate([u, v])[order]
    nbr, wt = np.concatenate([v, u])[order], np.concatenate([w, w])[order]
    start = np.searchsorted(src, np.arange(n + 1))
    rng = np.random.default_rng(seed)
    part = np.zeros(n, dtype=np.int64)
    todo = [(np.arange(n), 0, parts)]
    while todo:
        members, first, k = todo.pop()
        if k == 1 or not len(members):
            part[members] = first
            continue
        left = k // 2
        side = _grow(start, nbr, wt, work, members, left / k, rng)
        todo += [(members[side[members]], first, left), (members[~side[members]], first + left, k - left)]
    _refine(start, nbr, wt, work, part, parts, gamma, passes)
    return part


def multilevel(fg: FactorGraph, parts: int, updates: DataFrame | None = None, gamma: float = 1.03, seed: int = 42, c_comm: float = 1.0, driver_vertices: int = DRIVER_VERTICES) -> DataFrame:
    """vid, piece of a weighted k-way cut: coarsen on the cluster, cut the coarse graph on the driver, project back, refine.

    Only a graph of at most ``driver_vertices`` vertices (or 20 a part) comes to the driver: coarsening goes on until it is that small, which it
    gets, as less than two vertices a part are too heavy to be paired. Edges between so many vertices are counted before they are fetched
    and the lightest-matched graph is coarsened on while there are more than ``DRIVER_EDGES``. updates makes the cut an informed one.
    """
    edges = cut(edge_cost(fg, updates, c_comm).select(F.least("fid", "vid").alias("u"), F.greatest("fid", "vid").alias("v"), F.col("cost").alias("w")))
    work = cut(vertex_work(fg, updates).withColumn("work", F.greatest("work", F.lit(1e-9))))
    total = work.agg(F.sum("work")).first()[0] or 0.0
    cap, maps, levels = 1.5 * total / max(1, parts), [], []
    n = work.count()
    while n > max(driver_vertices, 20 * parts) or (n > 20 * parts and edges.count() > DRIVER_EDGES):
        coarse_edges, coarse_work, to = contract(edges, work, cut(matching_round(edges, work, cap, len(maps))))
        maps.append(cut(to))
        levels.append((edges, work))
        edges, work = cut(coarse_edges), cut(coarse_work)
        m = work.count()
        if m > 0.97 * n:  # hubs: leaves that share a neighbour, or have none, pair up instead; where that does not help either, any light vertices
            two_hop = edges.select(F.col("u").alias("hub"), F.col("v").alias("leaf")).unionByName(edges.select(F.col("v").alias("hub"), F.col("u").alias("leaf")))
            every = work.select(F.col("vid").alias("leaf"))
            least = every.join(two_hop.groupBy("leaf").agg(F.min("hub").alias("hub")), "leaf", "left").select("leaf", F.coalesce("hub", F.lit(-1)).alias("hub"))
            for near in (least, every.withColumn("hub", F.lit(-1))):
                coarse_edges, coarse_work, to = contract(edges, work, cut(paired(near, work, cap, m)))
                maps.append(cut(to))
                levels.append((edges, work))
                edges, work = cut(coarse_edges), cut(coarse_work)
                k = work.count()
                if k <= 0.97 * m:
                    break
        n = work.count()
    vs, es = work.orderBy("vid").toArrow(), edges.toArrow()
    ids = vs.column("vid").to_numpy()
    u, v = (np.searchsorted(ids, es.column(c).to_numpy()) for c in ("u", "v"))
    part = cut_arrays(len(ids), u, v, es.column("w").to_numpy(), vs.column("work").to_numpy(), parts, gamma, seed)
    spark = fg.spark
    import pyarrow as pa

    placed = spark.createDataFrame(pa.table({"vid": pa.array(ids, pa.int64()), "piece": pa.array(part, pa.int64())}))
    for to, (e, w) in zip(reversed(maps), reversed(levels)):
        placed = to.join(placed.withColumnRenamed("vid", "coarse"), "coarse").select("vid", "piece")
        placed = cut(refine_round(e, w, placed, parts, gamma))
    return placed


def refine_round(edges: DataFrame, work: DataFrame, placed: DataFrame, parts: int, gamma: float) -> DataFrame:
    """One sweep of positive-gain moves: a part admits movers in order of gain while its free capacity lasts. Moves go up only, so pairs don't swap."""
    both = edges.select("u", "v", "w").unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v"), "w"))
    pull = both.join(placed.toDF("v", "p"), "v").groupBy("u", "p").agg(F.sum("w").alias("w"))
    own = pull.join(placed.toDF("u", "own"), "u")
    best = own.groupBy("u", "own").agg(F.max(F.when(F.col("p") == F.col("own"), F.col("w"))).alias("stay"), F.max(F.when(F.col("p") > F.col("own"), F.struct("w", "p"))).alias("go"))
    want = best.where(F.col("go.w") > F.coalesce("stay", F.lit(0.0))).select(F.col("u").alias("vid"), F.col("go.p").alias("to"), (F.col("go.w") - F.coalesce("stay", F.lit(0.0))).alias("gain")).join(work, "vid")
    load = work.join(placed, "vid").groupBy(F.col("piece").alias("to")).agg(F.sum("work").alias("load"))
    total = work.agg(F.sum("work").alias("all"))
    order = Window.partitionBy("to").orderBy(F.desc("gain"), "vid")
    fits = want.join(load, "to").crossJoin(F.broadcast(total)).withColumn("after", F.sum("work").over(order) + F.col("load"))
    moves = fits.where(F.col("after") <= gamma * F.col("all") / parts).select("vid", "to")
    return placed.join(moves, "vid", "left").select("vid", F.coalesce("to", "piece").alias("piece"))


# Over-partitioning


def deal(spark, pieces: int, workers: int, seed: int) -> DataFrame:
    """piece, block: exactly pieces / workers random pieces to each worker, in order of md5."""
    p = spark.range(pieces).withColumnRenamed("id", "piece")
    order = Window.orderBy(F.md5(F.concat_ws("|", F.col("piece").cast("string"), F.lit(str(seed))).cast("binary")), "piece")
    return p.select("piece", ((F.row_number().over(order) - 1) % workers).cast("long").alias("block"))


def over_segment(fg: FactorGraph, workers: int, over: int = 5, seed: int = 42, gamma: float = 1.03, updates: DataFrame | None = None, pieces: DataFrame | None = None) -> DataFrame:
    """vid, piece, block: ``over`` pieces per worker, dealt at random."""
    pieces = multilevel(fg, workers * over, updates, gamma, seed) if pieces is None else pieces
    return pieces.join(F.broadcast(deal(fg.spark, workers * over, workers, seed)), "piece").select("vid", "piece", "block")
