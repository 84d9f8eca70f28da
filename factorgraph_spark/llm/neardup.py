"""Near-duplicate detection: minhash signatures, a multi-index Hamming join, and confirmation on whole shingle sets.

1. ``sketch``: every document's set of hashed word shingles becomes a digest of the set and a signature of ``SYMBOLS`` b-bit minhash values.
   Documents with equal sets are one class from here on, so that a group of exact copies of any size is a single row.
2. Two signatures are near if at most ``INDEX_ERRORS`` of their first ``INDEXED`` symbols differ and at least ``least_matches`` of all symbols
   agree. The indexed symbols are split into chunks of ``CHUNK``; within that many errors there is, by pigeonhole, a chunk with at most one
   of them, so posting every chunk with each of its symbols left out in turn brings every near pair under a common key. At a similarity of 0.8 a
   pair is not near with a probability of about 1e-5.
3. Every member of a bucket is paired with the bucket's least member (linear, never all pairs; buckets of the same members name the same
   pair), every member's best near pair is confirmed on whole sets, and confirmed links give components.
4. Completeness: a bucket that still spans several components is compared across them, in blocks of bounded size dealt over tasks. Components
   with a near pair form a cell. Within a cell, whole sets meet in blocks of bounded size, every near pair whose components are still apart is
   confirmed, and what leaves a task is the links that join components: fewer than its members. No candidate is capped or left out.

Components use alternating star contractions on distributed edge tables; edges, sets and fingerprints never come to the driver.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import cut, forget, landed, strings, tidy, utf8

SYMBOLS, INDEXED, CHUNK = 128, 48, 4
INDEX_ERRORS = 2 * (INDEXED // CHUNK) - 1
#: Members of a bucket that one task compares with as many others.
BLOCK = 1024
#: Edges that a task of the star contractions holds on average.
TASK_EDGES = 50_000
#: Ids up to which a side is broadcast; beyond, the join shuffles.
BROADCAST_IDS = 1_000_000
#: Bytes of text that are hashed together.
TOGETHER = 300_000

_rng = np.random.default_rng(20240101)
_BYTE = _rng.integers(0, 2**64, 256, dtype=np.uint64)
_PLACE = _rng.integers(0, 2**64, 8, dtype=np.uint64) | np.uint64(1)
_MASK = _rng.integers(0, 2**32, SYMBOLS, dtype=np.uint32)
_TIMES = _rng.integers(0, 2**32, SYMBOLS, dtype=np.uint32) | np.uint32(1)
_SPACES = np.zeros(256, dtype=bool)
_SPACES[[32, *range(9, 14)]] = True
_GROW = np.uint64(0x9E3779B97F4A7C15)


def _mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def _powers(n: int) -> np.ndarray:
    out = np.full(n, _GROW, dtype=np.uint64)
    out[:1] = 1
    return np.cumprod(out, dtype=np.uint64)


def shingle_sets(texts: list[bytes], width: int) -> list[np.ndarray]:
    """Sorted distinct 64-bit shingle hashes of each text. A text of fewer than ``width`` words has its whole sequence as one shingle."""
    joined = np.frombuffer(b" ".join(t.lower() for t in texts) + b" ", dtype=np.uint8)
    bounds = np.cumsum([0, *(len(t) + 1 for t in texts)])
    solid = ~_SPACES[joined]
    edges = np.flatnonzero(np.diff(np.concatenate(([False], solid)).astype(np.int8)))
    starts, ends = edges[::2], edges[1::2]
    if not len(starts):
        return [np.zeros(0, dtype=np.uint64) for _ in texts]
    lengths = ends - starts
    first = np.cumsum(lengths) - lengths
    inside = np.arange(lengths.sum()) - np.repeat(first, lengths)
    words = _mix(np.add.reduceat(_BYTE[joined[solid]] * _powers(int(lengths.max()))[inside], first) + lengths.astype(np.uint64))
    at = np.searchsorted(starts, bounds)
    count = max(0, len(words) - width + 1)
    whole = np.zeros(count, dtype=np.uint64)
    for k in range(width):
        whole += words[k : k + count] * _PLACE[k % 8] * _powers(k // 8 + 1)[-1]
    whole = _mix(whole)
    out = []
    for a, b in zip(at[:-1].tolist(), at[1:].tolist()):
        if b - a >= width:
            out.append(np.unique(whole[a : b - width + 1]))
        elif b > a:
            out.append(_mix(np.array([(words[a:b] * _PLACE[np.arange(b - a) % 8]).sum() + np.uint64(b - a)], dtype=np.uint64)))
        else:
            out.append(np.zeros(0, dtype=np.uint64))
    return out


def signature(hashes: np.ndarray) -> np.ndarray:
    """SYMBOLS minhash values of 16 bits."""
    low = np.full(SYMBOLS, 0xFFFFFFFF, dtype=np.uint32)
    top = (hashes >> np.uint64(32)).astype(np.uint32)
    for k in range(0, len(top), 4096):
        low = np.minimum(low, ((top[k : k + 4096, None] ^ _MASK) * _TIMES).min(axis=0))
    return ((low * np.uint32(0x9E3779B1)) >> np.uint32(16)).astype("<u2")


def _grouped(texts) -> Iterator[list[bytes]]:
    held, size = [], 0
    for t in texts:
        held.append(utf8(t))
        size += len(held[-1])
        if size > TOGETHER:
            yield held
            held, size = [], 0
    if held:
        yield held


def sketch(docs: DataFrame, width: int) -> DataFrame:
    """id, n_shingles, digest and sig of every row of docs (id, t); the last two are null for an empty set."""

    @tidy
    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n, digest, sig = [], [], []
            for held in _grouped(strings(batch.column("t"))):
                for s in shingle_sets(held, width):
                    n.append(len(s))
                    digest.append(hashlib.md5(s.tobytes(), usedforsecurity=False).digest() if len(s) else None)
                    sig.append(signature(s).tobytes() if len(s) else None)
            yield pa.RecordBatch.from_arrays([batch.column("id"), pa.array(n, pa.int64()), pa.array(digest, pa.binary()), pa.array(sig, pa.binary())], ["id", "n_shingles", "digest", "sig"])

    return docs.mapInArrow(make, "id long, n_shingles long, digest binary, sig binary")


def index_keys(sig) -> list:
    """The keys of a signature: each chunk with each of its symbols left out."""
    out = []
    for chunk in range(INDEXED // CHUNK):
        symbols = [F.substring(sig, 1 + 2 * (chunk * CHUNK + k), 2) for k in range(CHUNK)]
        out += [F.xxhash64(F.lit(chunk * CHUNK + k), *[s for j, s in enumerate(symbols) if j != k]) for k in range(CHUNK)]
    return out


def least_matches(percent: int) -> int:
    """Equal symbols that a pair at the threshold has with a probability of about 1 - 1e-5."""
    j = percent / 100
    return max(0, int(SYMBOLS * j - 4.2 * (SYMBOLS * j * (1 - j)) ** 0.5))


@F.arrow_udf(T.IntegerType())
def _matches(a: pa.Array, b: pa.Array) -> pa.Array:
    x, y = (np.frombuffer(b"".join(v.to_pylist()), dtype="<u2").reshape(-1, SYMBOLS) for v in (a, b))
    return pa.array((x == y).sum(axis=1).astype(np.int32))


def _overlap(a: bytes, b: bytes) -> int:
    both = np.concatenate([np.frombuffer(a, dtype="<u8"), np.frombuffer(b, dtype="<u8")])
    both.sort()
    return int((both[1:] == both[:-1]).sum())


def _confirm(percent: int):
    @F.arrow_udf(T.BooleanType())
    def confirm(a: pa.Array, b: pa.Array) -> pa.Array:
        out = []
        for x, y in zip(a, b):
            x, y = x.as_buffer(), y.as_buffer()
            shared = _overlap(x, y)
            out.append(100 * shared >= percent * ((len(x) + len(y)) // 8 - shared))
        return pa.array(out, pa.bool_())

    return confirm


def restrict(docs: DataFrame, ids: DataFrame, how: str, column: str) -> DataFrame:
    """docs joined with ids by column: without a shuffle of docs as long as the ids are few."""
    few = ids.limit(BROADCAST_IDS + 1).count() <= BROADCAST_IDS
    return docs.join(F.broadcast(ids) if few else ids, column, how)


def _sets(docs: DataFrame, classes: DataFrame, cids: DataFrame, width: int) -> DataFrame:
    """cid and set (sorted hashes as bytes) of the classes with these numbers, from the rows with their least id and their digest."""
    wanted = classes.join(cids, "cid").select("id", "digest", "cid")

    @tidy
    def make(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            at = 0
            for held in _grouped(strings(batch.column("t"))):
                part = batch.slice(at, len(held))
                sets = [s.tobytes() for s in shingle_sets(held, width)]
                same = [hashlib.md5(s, usedforsecurity=False).digest() == d for s, d in zip(sets, part.column("digest").to_pylist())]
                yield pa.RecordBatch.from_arrays([part.column("cid"), pa.array(sets, pa.binary())], ["cid", "set"]).filter(pa.array(same, pa.bool_()))
                at += len(held)

    return restrict(docs, wanted, "inner", "id").select("t", "digest", "cid").mapInArrow(make, "cid long, set binary")


class _Joined:
    """Components that a task has joined so far."""

    def __init__(self):
        self.up: dict[int, int] = {}

    def root(self, x: int) -> int:
        while (y := self.up.get(x, x)) != x:
            self.up[x] = x = self.up.get(y, y)
        return x

    def join(self, x: int, y: int) -> bool:
        x, y = self.root(x), self.root(y)
        self.up[max(x, y)] = min(x, y)
        return x != y


def _forest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """node and component of all nodes of one task's edges (u, v)."""
    joined, nodes = _Joined(), set()
    for batch in batches:
        for x, y in zip(batch.column("u").to_pylist(), batch.column("v").to_pylist()):
            joined.join(x, y)
            nodes.update((x, y))
    found = sorted(nodes)
    yield pa.RecordBatch.from_arrays([pa.array(found, pa.int64()), pa.array([joined.root(x) for x in found], pa.int64())], ["node", "component"])


def components(edges: DataFrame) -> DataFrame:
    """node and component (its least node) for every node of the edges (a, b): alternating star contractions, from forests that tasks have
    made of their own edges.

    Tasks hold TASK_EDGES edges each on average, so their number grows with the edges. A table of least neighbours is broadcast while it has
    at most BROADCAST_IDS rows and joined by a shuffle beyond. What a round has replaced is removed from the shared folder.
    """
    spark = edges.sparkSession
    edges = cut(edges.where("a != b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")))
    n = edges.count()
    tasks = lambda: 1 + n // TASK_EDGES
    edges = edges.coalesce(tasks()).mapInArrow(_forest, "node long, component long").where("node != component").toDF("u", "v").distinct()
    edges, path = landed(edges.coalesce(tasks()), "links")
    state = None
    while True:
        now = edges.agg(F.count(F.lit(1)), F.expr("bit_xor(xxhash64(u, v))")).first()
        if now == state or not now[0]:
            own = edges.select("v").distinct().select(F.col("v").alias("node"), F.col("v").alias("component"))
            return edges.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(own)
        state, n = now, now[0]
        least = lambda e: e.groupBy("u").agg(F.min("v").alias("m")).coalesce(tasks())
        near = lambda e: F.broadcast(least(e)) if 2 * n <= BROADCAST_IDS else least(e)
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        # Every larger neighbour is linked to the least of a node and its neighbours.
        large = both.where("v > u").join(near(both), "u").select(F.col("v").alias("u"), F.least("u", "m").alias("v"))
        # Every smaller neighbour, and the node itself, is linked to the least of them.
        small = large.join(near(large), "u").select(F.when(F.col("v") == F.col("m"), F.col("u")).otherwise(F.col("v")).alias("u"), F.col("m").alias("v"))
        last = path
        edges, path = landed(small.distinct().coalesce(tasks()), "links")
        forget(spark, last)


def _signs(column) -> np.ndarray:
    return np.frombuffer(b"".join(column.to_pylist()), dtype="<u2").reshape(-1, SYMBOLS)


def _across(members: DataFrame, least: int) -> DataFrame:
    """a, b: components that are to be compared, as far as they connect what a bucket's members (key, cid, comp, sig, n) span."""
    blocks = F.ceil(F.col("n") / BLOCK).cast("int")
    own = F.pmod(F.xxhash64("cid"), F.col("blocks")).cast("int")
    dealt = members.withColumn("blocks", blocks).withColumn("own", own)
    dealt = dealt.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    dealt = dealt.select("key", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), "comp", "sig")

    def compare(group: pa.Table) -> pa.Table:
        comp, sig = group.column("comp").to_numpy(), _signs(group.column("sig"))
        _, of, sizes = np.unique(comp, return_inverse=True, return_counts=True)
        joined, a, b = _Joined(), [], []
        for k in np.flatnonzero(of != sizes.argmax()).tolist():  # every pair across components has a member outside the largest one
            near = np.flatnonzero(of != of[k])
            for other in set(comp[near[(sig[near] == sig[k]).sum(axis=1) >= least]].tolist()):
                if joined.join(int(comp[k]), other):
                    a.append(int(comp[k]))
                    b.append(other)
        return pa.table({"a": pa.array(a, pa.int64()), "b": pa.array(b, pa.int64())})

    return dealt.groupBy("key", "i", "j").applyInArrow(compare, "a long, b long").distinct()


def _within(members: DataFrame, least: int, percent: int) -> DataFrame:
    """a, b: confirmed links that join the components of each cell. members: cell, cid, comp, sig, set.

    Every pair across components has a member outside the cell's largest one: those outside ("left") meet all members ("right").
    """
    sizes = members.groupBy("cell", "comp").agg(F.count(F.lit(1)).alias("n"))
    cells = sizes.groupBy("cell").agg(F.max_by("comp", F.struct("n", "comp")).alias("largest"), F.sum("n").alias("all"), F.max("n").alias("most"))
    blocks = lambda c: F.greatest(F.lit(1), F.ceil(c / (BLOCK // 2))).cast("int")
    cells = cells.select(F.col("cell"), "largest", blocks(F.col("all") - F.col("most")).alias("ni"), blocks(F.col("all")).alias("nj"))
    rows = members.join(cells, "cell")
    every = lambda n: F.sequence(F.lit(0), F.col(n) - 1)
    own = lambda n: F.array(F.pmod(F.xxhash64("cid"), F.col(n)).cast("int"))
    outside = F.col("comp") != F.col("largest")
    sides = F.array(F.struct(F.lit(False).alias("left"), every("ni").alias("i"), own("nj").alias("j")), F.when(outside, F.struct(F.lit(True).alias("left"), own("ni").alias("i"), every("nj").alias("j"))))
    dealt = rows.withColumn("side", F.explode(F.filter(sides, lambda x: x.isNotNull())))
    dealt = dealt.withColumn("i", F.explode("side.i")).withColumn("j", F.explode("side.j"))
    dealt = dealt.select("cell", "i", "j", F.col("side.left").alias("left"), "cid", "comp", "sig", "set")
    dealt = dealt.repartition("cell", "i", "j")  # else the blocks of a cell stay together, where the join by cell has put them

    def confirm(group: pa.Table) -> pa.Table:
        cid, comp, left = (group.column(c).to_numpy() for c in ("cid", "comp", "left"))
        sig, sets = _signs(group.column("sig")), [x.as_buffer() for x in group.column("set")]
        right = np.flatnonzero(~left)
        joined, a, b = _Joined(), [], []
        for k in np.flatnonzero(left).tolist():
            near = right[comp[right] != comp[k]]
            m = (sig[near] == sig[k]).sum(axis=1)
            good = m >= least
            near = near[good][np.argsort(-m[good], kind="stable")]
            for other in near.tolist():
                if joined.root(int(comp[k])) == joined.root(int(comp[other])):
                    continue
                shared, x, y = _overlap(sets[k], sets[other]), len(sets[k]) // 8, len(sets[other]) // 8
                if 100 * shared >= percent * (x + y - shared):
                    joined.join(int(comp[k]), int(comp[other]))
                    a.append(int(cid[k]))
                    b.append(int(cid[other]))
        return pa.table({"a": pa.array(a, pa.int64()), "b": pa.array(b, pa.int64())})

    return dealt.groupBy("cell", "i", "j").applyInArrow(confirm, "a long, b long")


def link(docs: DataFrame, *, doc_id: str = "doc_id", text: str = "text", width: int = 5, percent: int = 80) -> DataFrame:
    """One row per input row: id, n_shingles, component_id (least id reachable over links) and kept (the row has that id).

    Two documents are linked if 100 * |A & B| >= percent * |A | B| for their sets of ``width``-word shingles (words: runs without ASCII
    white space, A-Z lower-cased). Null and empty texts have an empty set and no links. Rows that share an id count as one document. Rows
    with a null id have no component and are not kept. An empty table gives an empty result. Ids are integers.
    """
    source = docs.select(F.col(doc_id).cast("long").alias("id"), F.col(text).alias("t"))
    least = least_matches(percent)
    sketches = cut(sketch(source, width))
    classes = sketches.where("digest is not null and id is not null").groupBy("digest").agg(F.min("id").alias("id"), F.first("sig").alias("sig"))
    classes = cut(classes.withColumn("cid", F.monotonically_increasing_id()))  # fixed by the checkpoint
    signs = classes.select("cid", "sig")
    keys = signs.select("cid", F.explode(F.array(*index_keys(F.col("sig")))).alias("key"))
    buckets = keys.groupBy("key").agg(F.count(F.lit(1)).alias("n"), F.min("cid").alias("pivot")).where("n > 1")
    members = cut(keys.join(buckets, "key").select("key", "cid", "n", "pivot"))
    pairs = members.where("cid != pivot").select("cid", "pivot").distinct()
    scored = pairs.join(signs.toDF("cid", "x"), "cid").join(signs.toDF("pivot", "y"), "pivot").select("cid", "pivot", _matches("x", "y").alias("m"))
    best = scored.where(F.col("m") >= least).groupBy("cid").agg(F.max(F.struct("m", (-F.col("pivot")).alias("p"))).alias("best"))
    tried = cut(best.select(F.col("cid").alias("a"), (-F.col("best.p")).alias("b")))

    # Rows that share an id count as one document, whatever their texts; a class that they hold twice has its set made twice.
    valid = sketches.where("digest is not null and id is not null")
    again = cut(valid.groupBy("id").count().where("count > 1").select("id"))
    repeats = again.limit(1).count() > 0
    once = lambda sets: cut(sets.dropDuplicates(["cid"]) if repeats else sets)

    sets = once(_sets(source, classes, tried.select("a").union(tried.select("b")).distinct().toDF("cid"), width))
    both = tried.join(sets.toDF("a", "x"), "a").join(sets.toDF("b", "y"), "b")
    links = both.select("a", "b", _confirm(percent)("x", "y").alias("ok")).where("ok").select("a", "b")
    if repeats:
        held = valid.join(again, "id").select("id", "digest").distinct().join(classes.select("digest", "cid"), "digest").select("id", "cid")
        links = links.unionByName(held.join(held.groupBy("id").agg(F.min("cid").alias("b")), "id").where("cid != b").select(F.col("cid").alias("a"), "b").distinct())
    links = cut(links)
    comp = components(links)

    spans = members.select("key", "cid", "n").join(comp.toDF("cid", "comp"), "cid", "left").withColumn("comp", F.coalesce("comp", "cid"))
    mixed = spans.groupBy("key").agg(F.min("comp").alias("x"), F.max("comp").alias("y")).where("x != y").select("key")
    across = cut(_across(spans.join(mixed, "key").join(signs, "cid").select("key", "comp", "cid", "n", "sig"), least))
    if across.limit(1).count():
        cells = components(across).toDF("comp", "cell")
        named = signs.join(comp.toDF("cid", "comp"), "cid", "left").withColumn("comp", F.coalesce("comp", "cid"))
        inside = cut(named.join(cells, "comp").select("cell", "cid", "comp", "sig"))
        sets = once(_sets(source, classes, inside.select("cid"), width))
        more = _within(inside.join(sets, "cid"), least, percent)
        comp = components(links.unionByName(more))

    of_class = classes.join(comp.toDF("cid", "component"), "cid", "left").select("digest", "id", F.coalesce("component", "cid").alias("component"))
    of_class = cut(of_class)
    lowest = of_class.groupBy("component").agg(F.min("id").alias("component_id"))
    of_class = of_class.join(lowest, "component").select("digest", "component_id")
    out = sketches.select("id", "n_shingles", "digest").join(of_class, "digest", "left")
    component = F.when(F.col("id").isNotNull(), F.coalesce("component_id", "id"))
    out = out.select(F.col("id").alias(doc_id), "n_shingles", component.alias("component_id"))
    return out.withColumn("kept", F.coalesce(F.col(doc_id) == F.col("component_id"), F.lit(False)))


def op9(docs: DataFrame) -> DataFrame:
    return link(docs, width=4)
