"""Approximate nearest neighbours by a permutation index.

A bounded sample of the vectors serves as pivots, for every dimension its own. Every vector is represented by the order of its ``ORDER``
nearest pivots, worked out once. Rows are dealt into blocks; a block posts its vectors in pivot inverted files: for every pivot the rows that
have it among their ORDER nearest, with its rank. A query reads the files of its own ORDER nearest pivots only and adds up the footrule
distance of the rows that it meets there (a pivot missing on one side counts as rank ORDER): of PIVOTS files it reads ORDER, each with a share
of ORDER / PIVOTS of the block. The closest ``PART`` of the block, at least ``LEAST``, are ranked again by exact cosine, and the best of all
blocks are merged. Every row is indexed.

Equal vectors are one entry with its smallest ids, so copies of any number neither crowd a block nor displace each other. Queries and rows
meet block by block: a task holds BLOCK_ROWS rows and BLOCK_QUERIES queries on average, whatever the table.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import cut, ship, tidy

PIVOTS, ORDER = 512, 64
#: Entries that pivots are chosen from, and the cosine up to which they count as apart.
SAMPLE, APART = 4096, 0.7
PART, LEAST = 0.09, 45
BLOCK_ROWS, BLOCK_QUERIES = 16_384, 8_192


def _usable(vector: Column) -> Column:
    fine = F.forall(vector, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) != float("inf")))
    return vector.isNotNull() & (F.size(vector) > 0) & fine & F.exists(vector, lambda x: x != 0)


def _rows(vectors: DataFrame, vec_id: str, embedding: str) -> DataFrame:
    """id and vec (doubles) of the usable rows, each once."""
    rows = vectors.select(F.col(vec_id).cast("long").alias("id"), F.transform(F.col(embedding), lambda x: x.cast("double")).alias("vec"))
    rows = rows.where(F.col("id").isNotNull() & F.coalesce(_usable(F.col("vec")), F.lit(False)))
    return rows.withColumn("vec", F.transform("vec", lambda x: x + F.lit(0.0))).distinct()  # -0.0 is 0.0


def distinct_vectors(rows: DataFrame, most: int) -> DataFrame:
    """rep (least id), ids (the ``most`` smallest, ascending) and vec of every distinct vector of rows (id, vec).

    Each task first keeps the smallest ids of a vector it holds, so copies are not gathered.
    """
    first = F.row_number().over(Window.partitionBy("vec").orderBy("id"))
    few = rows.withColumn("k", first).where(F.col("k") <= most)
    return few.groupBy("vec").agg(F.min("id").alias("rep"), F.sort_array(F.collect_list("id")).alias("ids"))


def fit_pivots(entries: DataFrame, pivots: int = PIVOTS) -> dict[int, np.ndarray]:
    """By dimension: at most ``pivots`` unit vectors, spread over the SAMPLE entries of lowest hashes.

    A cluster of near copies, however large a part of the rows, gives a pivot or few, so the orders of the others stay telling.
    """
    place = F.row_number().over(Window.partitionBy("d").orderBy(F.xxhash64("rep"), "rep"))
    some = entries.select(F.size("vec").alias("d"), "rep", "vec").withColumn("k", place).where(F.col("k") <= SAMPLE)
    samples: dict[int, list] = {}
    for r in some.orderBy("d", "k").select("d", "vec").toLocalIterator():
        samples.setdefault(r["d"], []).append(r["vec"])
    return {d: _spread(_unit(np.array(vecs)), pivots) for d, vecs in samples.items()}


def _spread(sample: np.ndarray, pivots: int) -> np.ndarray:
    chosen, near = [], np.full(len(sample), -2.0)
    while len(chosen) < min(pivots, len(sample)):
        apart = np.flatnonzero(near < APART)
        # The next of the sample that is no near copy of a pivot; when there is none, the farthest from all pivots.
        chosen.append(int(apart[0]) if len(apart) else int(near.argmin()))
        near = np.maximum(near, sample @ sample[chosen[-1]])
        near[chosen[-1]] = 9
    return sample[chosen]


def _unit(x: np.ndarray) -> np.ndarray:
    x = x / np.abs(x).max(axis=1, keepdims=True)
    return x / np.sqrt((x * x).sum(axis=1, keepdims=True))


def permutations(vectors: np.ndarray, pivots: np.ndarray, order: int = ORDER) -> np.ndarray:
    """The ``order`` nearest pivots of each vector, nearest first, ties to the lower pivot."""
    return np.argsort(-(_unit(vectors) @ pivots.T), axis=1, kind="stable")[:, : min(order, len(pivots))].astype(np.int16)


class Block:
    """Pivot inverted files of some rows."""

    def __init__(self, perms: np.ndarray, pivots: int):
        self.n, self.order = perms.shape
        rows, ranks = np.divmod(np.arange(perms.size), max(1, self.order))
        by = np.argsort(perms.ravel(), kind="stable")
        self.rows, self.ranks = rows[by], ranks[by].astype(np.int32)
        self.starts = np.searchsorted(perms.ravel()[by], np.arange(pivots + 1))

    def footrule(self, perm: np.ndarray) -> np.ndarray:
        """Footrule distance of a query's order to every row's; pivots that neither has add nothing."""
        m = self.order
        # As if nothing were shared, every row is sum(m - rank) over both orders away; each shared pivot takes off what it has in common.
        off = np.zeros(self.n, dtype=np.int32)
        for rank, pivot in enumerate(perm.tolist()):
            a, b = self.starts[pivot], self.starts[pivot + 1]
            off[self.rows[a:b]] += 2 * (m - np.maximum(self.ranks[a:b], rank))
        return m * (m + 1) - off


def _ordered(rows: DataFrame, shared) -> DataFrame:
    """rows (with vec) with d, the dimension, and perm: the vector's order of pivots, as int16."""
    fields = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in rows.schema)

    @tidy
    def order(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pivots = shared.value
        for batch in batches:
            vec = batch.column("vec")
            sizes = np.diff(vec.offsets.to_numpy())
            flat, starts = vec.flatten().to_numpy(zero_copy_only=False), np.cumsum(sizes) - sizes
            perms: list = [None] * len(sizes)
            for d in np.unique(sizes).tolist():
                at = np.flatnonzero(sizes == d)
                found = permutations(flat[starts[at][:, None] + np.arange(d)], pivots[d])
                for k, perm in zip(at.tolist(), found):
                    perms[k] = perm.tobytes()
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(sizes, pa.int32()), pa.array(perms, pa.binary())], [*batch.schema.names, "d", "perm"])

    return rows.mapInArrow(order, f"{fields}, d int, perm binary")


def search(vectors: DataFrame, queries: Column, *, k: int = 5, vec_id: str = "vec_id", embedding: str = "embedding", part: float = PART, least: int = LEAST) -> DataFrame:
    """query_id, rank (from 1), vec_id and score of the ``k`` nearest rows found for every row of vectors where ``queries`` holds.

    Nearness is cosine in double precision on the original vectors, ties go to the smaller id, and a query never finds its own id. Vectors
    that are null, empty, zero or hold null or non-finite components take no part; vectors are compared with those of their dimension. Rows
    of one id and vector count once, as rows and as queries; rows of one id with different vectors are separate rows and separate queries.
    An empty table gives an empty result. Other columns, whatever their names, are seen by ``queries`` only.
    """
    ship(vectors.sparkSession)
    entries = cut(distinct_vectors(_rows(vectors, vec_id, embedding), k + 1))
    pivots = fit_pivots(entries)
    shared = vectors.sparkSession.sparkContext.broadcast(pivots)  # at most PIVOTS vectors of each dimension
    entries = cut(_ordered(entries, shared))
    asked = cut(_ordered(_rows(vectors.where(queries), vec_id, embedding), shared).withColumn("ask", F.monotonically_increasing_id()))
    # Blocks by dimension.
    held, asking = ({r["d"]: r["count"] for r in t.groupBy("d").count().collect()} for t in (entries, asked))
    counts = [(d, max(1, -(-n // BLOCK_ROWS)), max(1, -(-asking.get(d, 0) // BLOCK_QUERIES))) for d, n in sorted(held.items())]
    blocks = F.broadcast(vectors.sparkSession.createDataFrame(counts, "d int, nr int, nq int"))
    deal = lambda c, n: F.pmod(F.xxhash64(c), F.col(n)).cast("int")
    every = lambda n: F.explode(F.sequence(F.lit(0), F.col(n) - 1))
    left = entries.join(blocks, "d").withColumn("r", deal("rep", "nr")).withColumn("q", every("nq")).drop("nr", "nq")
    right = asked.join(blocks, "d").withColumn("q", deal("ask", "nq")).withColumn("r", every("nr")).drop("nr", "nq")

    def meet(rows: pa.Table, asks: pa.Table) -> pa.Table:
        names = ("ask", "query_id", "ids", "score")
        kinds = (pa.int64(), pa.int64(), pa.list_(pa.int64()), pa.float64())
        if not rows.num_rows or not asks.num_rows:
            return pa.table([pa.array([], t) for t in kinds], names=list(names))
        width = rows.column("d")[0].as_py()
        flat = lambda t: t.column("vec").combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(-1, width)
        perms = lambda t: np.frombuffer(b"".join(t.column("perm").to_pylist()), dtype=np.int16).reshape(t.num_rows, -1)
        rows = rows.take(pa.array(np.argsort(rows.column("rep").to_numpy(), kind="stable")))
        x, y = flat(rows), flat(asks)
        block = Block(perms(rows), len(shared.value[width]))
        take = min(len(x), max(least, int(part * len(x))))
        norms = np.sqrt((x * x).sum(axis=1))
        numbers, qid, at, score = [], [], [], []
        for perm, v, number, ident in zip(perms(asks), y, asks.column("ask").to_pylist(), asks.column("id").to_pylist()):
            far = block.footrule(perm)
            near = np.flatnonzero(far <= np.partition(far, take - 1)[take - 1])  # ties at the edge stay
            cosine = np.array((x[near] * v).sum(axis=1) / (norms[near] * np.sqrt((v * v).sum())))
            best = near_best(cosine, k + 1)
            numbers += [number] * len(best)
            qid += [ident] * len(best)
            at += near[best].tolist()
            score += cosine[best].tolist()
        ids = rows.column("ids").take(pa.array(at, pa.int64())).combine_chunks()
        return pa.table([pa.array(numbers, kinds[0]), pa.array(qid, kinds[1]), ids, pa.array(score, kinds[3])], names=list(names)).cast(pa.schema(list(zip(names, kinds))))

    found = left.groupBy("d", "r", "q").cogroup(right.groupBy("d", "r", "q")).applyInArrow(meet, "ask long, query_id long, ids array<long>, score double")
    spread = found.select("ask", "query_id", "score", F.explode("ids").alias("vec_id")).where("vec_id != query_id")
    rank = F.row_number().over(Window.partitionBy("ask").orderBy(F.desc("score"), "vec_id"))
    return spread.withColumn("rank", rank.cast("int")).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def near_best(score: np.ndarray, most: int) -> np.ndarray:
    """Positions of the ``most`` highest scores and of all that tie with the last of them."""
    if len(score) <= most:
        return np.arange(len(score))
    edge = np.partition(score, len(score) - most)[len(score) - most]
    return np.flatnonzero(score >= edge)


def op4(vectors: DataFrame) -> DataFrame:
    return search(vectors, F.col("vec_id") % 50 == 0)
