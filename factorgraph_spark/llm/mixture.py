"""Mixing sources to target weights by entropy balancing.

Every source has a token target, and a mean that its tokens' tilts are to come near: tilts are the logarithms of document lengths unless
given, and the mean lies ``PULL`` of the way from the source's own to the corpus's, so that the mix evens out lengths between sources.
Among all document rates of 0 to a cap below ``most`` that meet the token targets, entropy balancing takes those closest to the given prior rates in
Kullback-Leibler divergence, every document counted by its tokens, plus a quadratic penalty (``RIDGE``) on missing the mean. The minimiser
is an exponential tilt, ``rate = min(cap, prior * exp(level[source] + slope[source] * tilt))``, where the cap is ``most`` less a
quarter of what the source's mean rate leaves to it, so that rounding can move every document either way; level and slope minimise a convex dual that
splits by source. Documents enter it only by their (source, prior, tilt) cell and its tokens. Each Newton iteration is one aggregation of
the cells, with partial sums: it evaluates the dual, its gradient and its Hessian at several lengths of the last step, and every source goes on
from the best. Iterations end when all sources meet their conditions to within ``EXACT``.

Rates become whole copies: the integer part, and one more for documents whose hash, divided by the rest of the rate, lies below a cut. The
cut of a source (near 1) is the one at which its tokens come nearest to the target. It is found by narrowing: each level sums tokens per source and one of ``FAN`` hash intervals and keeps
the interval in which the target falls. No window or task holds more than FAN rows of a source.

All of it is DataFrame operations.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import SPACE
from .common import cut_plan as cut

#: Weights that sources get in turn.
WEIGHTS = (3, 1, 2)
#: Tokens of the mix over tokens of the corpus; and the most that a source's target, or a document's copies, can be of what it has.
SHARE, MOST = 1.5, 2.0
#: How far a source's mean tilt is to go to the corpus's, and the penalty on missing that.
PULL, RIDGE = 0.25, 0.05
#: Newton iterations at most, the error (by the target) at which they end, and the lengths tried of each step.
NEWTON_ROUNDS, EXACT = 60, 1e-9
STEPS = (1.0, 0.5, 0.125, 1 / 64)
#: Hash intervals per level of the narrowing, and levels.
FAN_BITS, LEVELS = 10, 4
#: Sources up to which a table of them is broadcast.
FEW_SOURCES = 100_000
#: Tilts are rounded to this step, which bounds the cells of a source.
TILT_STEP = 1 / 64


def token_count(text: Column) -> Column:
    """Runs of characters other than ASCII white space; null has none."""
    return F.coalesce(F.regexp_count(text, F.lit(f"[^{SPACE}]+")), F.lit(0)).cast("long")


def water_fill(sizes: DataFrame, *, weights=WEIGHTS, share: float = SHARE, most: float = MOST) -> DataFrame:
    """target of each row (source, source_size): ``share`` of all sizes dealt by weight, no source above ``most`` times its size.

    Sources are ordered by code point (null last) and weigh ``weights`` in turn. What a source can't take is dealt again by weight among
    the others until none is above its bound. Bounds bind in order of bound per weight: with ``left`` dealt over the ``open`` weight, those
    bind whose bound per weight is at most left / open, so running sums in that order give the level at once. The table has a row per
    source; its windows hold source names only, never documents.
    """
    in_order = Window.orderBy(F.col("source").isNull(), F.col("source"))
    numbered = sizes.withColumn("k", F.row_number().over(in_order) - 1)
    weight = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (F.col("k") % len(weights) + 1).cast("int"))
    rows = numbered.withColumn("weight", weight).withColumn("bound", most * F.col("source_size"))
    by_bound = Window.orderBy(F.col("bound") / F.col("weight"), "k")
    before = by_bound.rowsBetween(Window.unboundedPreceding, -1)
    everything = Window.orderBy(F.lit(0)).rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    rows = rows.withColumn("left", share * F.sum("source_size").over(everything) - F.coalesce(F.sum("bound").over(before), F.lit(0.0)))
    rows = rows.withColumn("open", F.sum("weight").over(everything) - F.coalesce(F.sum("weight").over(before), F.lit(0.0)))
    rows = rows.withColumn("level", F.col("left") / F.col("open"))
    free = F.when(F.col("bound") > F.col("level") * F.col("weight"), F.col("level"))  # the first source that isn't bound sets it
    level = F.first(free, ignorenulls=True).over(by_bound.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))
    return rows.withColumn("target", F.least("bound", F.coalesce(level * F.col("weight"), F.col("bound")))).select("source", "source_size", "target")


def _sums(step: float) -> list[Column]:
    """Dual, gradient and Hessian sums of a source's cells at this length of its step."""
    level, slope = F.col("level") + step * F.col("d_level"), F.col("slope") + step * F.col("d_slope")
    eta, top = F.ln("prior") + level + slope * F.col("z"), F.ln("cap")
    rate = F.exp(F.least(eta, top))
    free = F.when(eta < top, F.col("tokens") * rate).otherwise(F.lit(0.0))
    met = F.col("tokens") * rate
    potential = F.col("tokens") * (rate + F.greatest(eta - top, F.lit(0.0)) * F.col("cap"))
    z = F.col("z")
    return [F.sum(c) for c in (potential, met, met * z, free, free * z, free * z * z)]


def multipliers(cells: DataFrame, targets: DataFrame, *, most: float = MOST, pull: float = PULL, ridge: float = RIDGE) -> DataFrame:
    """The dual's solution by source: level, slope, cap, center and scale (of tilts) and error (what its conditions are missed by, over the target).

    cells: source, prior, tilt, tokens; targets: source, target. A source whose target is all that it can give has every rate at ``most``.
    """
    used = cells.where("tokens > 0 and prior > 0")
    whole = used.agg(F.sum("tokens").alias("n"), (F.sum(F.col("tokens") * F.col("tilt")) / F.sum("tokens")).alias("m"), F.sqrt(F.sum(F.col("tokens") * F.col("tilt") * F.col("tilt")) / F.sum("tokens") - F.pow(F.sum(F.col("tokens") * F.col("tilt")) / F.sum("tokens"), F.lit(2.0))).alias("sd")).first()
    center, scale = whole["m"] or 0.0, whole["sd"] if whole["sd"] and whole["sd"] > 1e-9 else 1.0
    used = used.withColumn("z", (F.col("tilt") - center) / scale)
    own = used.groupBy("source").agg(F.sum(F.col("tokens") * F.col("prior")).alias("mass"), (F.sum(F.col("tokens") * F.col("z")) / F.sum("tokens")).alias("mean"), F.sum("tokens").alias("held"))
    state = own.join(targets.select(F.col("source").alias("ts"), "target"), F.col("ts").eqNullSafe(F.col("source"))).drop("ts")
    bound = F.col("target") >= most * F.col("held") * (1 - 1e-12)
    zero = F.lit(0.0)
    cap = F.when(bound, F.lit(float(most))).otherwise(most - (most - F.col("target") / F.col("held")) / 4)
    state = state.withColumn("solved", bound | (F.col("target") <= 0)).withColumn("level", F.when(bound, F.lit(700.0)).when(F.col("target") <= 0, F.lit(-700.0)).otherwise(F.log(F.col("target") / F.col("mass"))))
    state = cut(state.select("source", "target", cap.alias("cap"), ((1 - pull) * F.col("mean")).alias("goal"), "solved", "level", *[zero.alias(c) for c in ("slope", "d_level", "d_slope")], F.lit(float("inf")).alias("error")))
    few = state.count() <= FEW_SOURCES
    for _ in range(NEWTON_ROUNDS):
        if not state.where(~F.col("solved") & (F.col("error") > EXACT)).limit(1).count():
            break
        open_ = state.where(~F.col("solved")).withColumnRenamed("source", "of")
        names = ("dual", "met", "moment", "h", "hz", "hzz")
        sums = [c.alias(f"{n}{k}") for k, step in enumerate(STEPS) for n, c in zip(names, _sums(step))]
        keys = ("target", "cap", "goal", "level", "slope", "d_level", "d_slope")
        found = _with_sources(used.withColumnRenamed("source", "cs"), open_.withColumnRenamed("of", "source"), "cs", few).groupBy("source", *keys).agg(*sums)
        tried = []
        for k, step in enumerate(STEPS):
            level, slope = F.col("level") + step * F.col("d_level"), F.col("slope") + step * F.col("d_slope")
            value = F.col(f"dual{k}") - F.col("target") * (level + slope * F.col("goal")) + 0.5 * ridge * F.col("target") * slope * slope
            tried.append(F.struct(value.alias("value"), level.alias("level"), slope.alias("slope"), *[F.col(f"{n}{k}").alias(n) for n in names[1:]]))
        best = found.select("source", "target", "cap", "goal", F.array_min(F.array(*tried)).alias("b")).select("source", "target", "cap", "goal", "b.*")
        # The gradient, and a Hessian that stays invertible where nearly all rates are at their bound.
        t = F.col("target")
        g1, g2 = F.col("met") - t, F.col("moment") - t * F.col("goal") + ridge * t * F.col("slope")
        h11, h12, h22 = F.col("h") + 1e-9 * t, F.col("hz"), F.col("hzz") + ridge * t
        det = h11 * h22 - h12 * h12
        short = lambda c: F.greatest(F.lit(-2.0), F.least(F.lit(2.0), c))
        after = best.select(
            "source", "target", "cap", "goal", F.lit(False).alias("solved"), "level", "slope",
            short((h12 * g2 - h22 * g1) / det).alias("d_level"), short((h12 * g1 - h11 * g2) / det).alias("d_slope"),
            (F.greatest(F.abs(g1), F.abs(g2)) / t).alias("error"),
        )
        state = cut(state.where("solved").unionByName(after))
    return state.select("source", "level", "slope", "cap", F.lit(center).alias("center"), F.lit(scale).alias("scale"), F.when(F.col("solved"), zero).otherwise(F.col("error")).alias("error"))


def _with_sources(docs: DataFrame, sources: DataFrame, key: str, few: bool | None = None) -> DataFrame:
    """docs joined with one row per source: broadcast while sources are few (counted unless the caller knows)."""
    few = few if few is not None else sources.limit(FEW_SOURCES + 1).count() <= FEW_SOURCES
    return docs.join(F.broadcast(sources) if few else sources, F.col(key).eqNullSafe(F.col("source"))).drop(key)


def _nearest_cuts(docs: DataFrame, targets: DataFrame) -> DataFrame:
    """By source: the place below which documents get one more copy (cut), and place and size of one beyond that does (p) and one below that doesn't (q). docs: source, size, base, part (0 to 1), u (place of LEVELS * FAN_BITS bits)."""
    gain = docs.where("size > 0 and part > 0")
    taken = docs.groupBy("source").agg(F.sum(F.col("base") * F.col("size")).alias("sure"))
    same = lambda a, b: a.eqNullSafe(b)
    state = targets.join(taken.withColumnRenamed("source", "s"), same(F.col("s"), F.col("source"))).select(
        F.col("source").alias("cs"), (F.col("target") - F.col("sure")).alias("need"), F.lit(0).cast("long").alias("low")
    )
    for level in range(LEVELS):
        shift = (LEVELS - 1 - level) * FAN_BITS
        inside = _with_sources(gain, state.withColumn("of", F.col("cs")), "of")
        inside = inside.where(F.shiftright("u", shift + FAN_BITS) == F.shiftright("low", shift + FAN_BITS)) if level else inside
        sums = inside.groupBy("cs", "need", "low", F.shiftright("u", shift).alias("slot")).agg(F.sum("size").alias("size"))
        upto = F.sum("size").over(Window.partitionBy("cs").orderBy("slot"))
        sums = sums.withColumn("before", upto - F.col("size"))
        last = level == LEVELS - 1
        # The slot in which the need is met; on the last level a slot is taken if all of it fits.
        fits = F.col("before") + F.col("size") <= F.col("need") if last else F.col("before") < F.col("need")
        best = sums.where(fits).groupBy("cs").agg(F.max_by(F.struct("slot", (F.col("before") + (F.col("size") if last else F.lit(0))).alias("before"), "need"), F.col("slot")).alias("b"))
        after = F.shiftleft(F.col("b.slot") + (1 if last else 0), shift)
        found = best.select(F.col("cs").alias("bs"), after.alias("at"), (F.col("b.need") - F.col("b.before")).alias("rest"))
        state = cut(
            state.join(found, same(F.col("bs"), F.col("cs")), "left").select(
                "cs", F.when(F.col("bs").isNull(), F.col("need")).otherwise(F.col("rest")).alias("need"), F.coalesce("at", "low").alias("low")
            )
        )
    # What is still missing is less than the next document has. Either the document beyond the cut whose size comes nearest closes the
    # gap, or the next one is taken and, of those taken, the one whose size comes nearest to the excess is left out.
    open_ = cut(_with_sources(gain, state.withColumn("of", F.col("cs")), "of"))
    beyond = open_.where(F.col("u") >= F.col("low"))
    added = _nearest(beyond, F.col("need"), "a")
    first = beyond.groupBy("cs").agg(F.min("u").alias("nu"))
    size = _with_cs(beyond, first).where("u = nu").groupBy("cs").agg(F.min("nu").alias("nu"), F.min("size").alias("ns"))
    excess = _with_cs(open_.where(F.col("u") < F.col("low")), size).withColumn("over", F.col("ns") - F.col("need"))
    dropped = _nearest(excess, F.col("over"), "d")
    both = state
    for part in (added, size, dropped):
        own = part.columns[0]
        both = both.join(part.withColumnRenamed(own, "of"), same(F.col("of"), F.col("cs")), "left").drop("of")
    swap = F.coalesce(F.col("d_off") < F.coalesce("a_off", "need"), F.lit(False))
    plain = ~swap & (F.col("a_off") < F.col("need"))
    return cut(
        both.select(
            "cs",
            F.col("low").alias("cut"),
            F.when(swap, F.col("nu")).when(plain, F.col("a_u")).alias("pu"),
            F.when(swap, F.col("ns")).when(plain, F.col("a_size")).alias("psize"),
            F.when(swap, F.col("d_u")).alias("qu"),
            F.when(swap, F.col("d_size")).alias("qsize"),
        )
    )


def _with_cs(rows: DataFrame, sources: DataFrame) -> DataFrame:
    """rows joined with a table of sources, both by cs."""
    few = sources.limit(FEW_SOURCES + 1).count() <= FEW_SOURCES
    right = sources.withColumnRenamed("cs", "of")
    return rows.join(F.broadcast(right) if few else right, F.col("of").eqNullSafe(F.col("cs"))).drop("of")


def _nearest(rows: DataFrame, goal: Column, name: str) -> DataFrame:
    """cs and, of the row whose size comes nearest to goal: its distance, place and size; ties to the lower place, then size."""
    off = F.abs(F.col("size") - goal)
    least = cut(rows.groupBy("cs").agg(F.min(off).alias("off")))
    at = _with_cs(rows, least).where(off == F.col("off"))
    place = cut(at.groupBy("cs").agg(F.min("u").alias("pu"), F.min("off").alias("o")))
    found = _with_cs(at, place).where(F.col("u") == F.col("pu")).groupBy("cs").agg(F.min("o").alias(f"{name}_off"), F.min("pu").alias(f"{name}_u"), F.min("size").alias(f"{name}_size"))
    return cut(found.withColumnRenamed("cs", f"{name}_cs"))


def _measured(docs: DataFrame, doc_id: str, text: str, source: str, prior: Column | None, tilt: Column | None) -> DataFrame:
    """docs with the struct m: source, size, prior, tilt and uniform (a number in [0, 1) from the id)."""
    one = F.lit(1.0)
    return docs.withColumn(
        MADE,
        F.struct(
            F.col(source).alias("source"),
            token_count(F.col(text)).alias("size"),
            (one if prior is None else prior.cast("double")).alias("prior"),
            (F.round((F.log2(1.0 + token_count(F.col(text))) if tilt is None else tilt.cast("double")) / TILT_STEP) * TILT_STEP).alias("tilt"),
            (F.shiftrightunsigned(F.xxhash64(F.col(doc_id).cast("string")), 12) / F.lit(2.0**52)).alias("uniform"),
        ),
    )


#: The one column that is added to a caller's table on the way.
MADE = "_mixture"


def _dealt(rows: DataFrame, solved: DataFrame) -> DataFrame:
    """rows (source, size, prior, tilt, uniform) with rate, base, part and u. solved: a row per source with its level, slope, cap, center and scale."""
    tilted = _with_sources(rows, solved.withColumnRenamed("source", "of"), "of")
    tilt = (F.col("tilt") - F.col("center")) / F.col("scale")
    rate = F.least(F.when(F.col("prior") > 0, F.exp(F.least(F.ln("prior") + F.col("level") + F.col("slope") * tilt, F.lit(50.0)))).otherwise(F.lit(0.0)), F.col("cap"))
    near = F.round(rate)  # a rate that misses a whole number by rounding error is that number
    rate = F.when(F.abs(rate - near) < 1e-9, near).otherwise(rate)
    dealt = tilted.withColumn("rate", F.when(F.col("size") > 0, rate).otherwise(F.lit(0.0)))
    dealt = dealt.withColumn("base", F.floor("rate")).withColumn("part", F.col("rate") - F.col("base"))
    ratio = F.col("uniform") / F.col("part")
    return dealt.withColumn("u", F.when(F.col("part") > 0, F.floor(ratio / (1 + ratio) * 2 ** (LEVELS * FAN_BITS))))


def _copies(dealt: DataFrame, most: float) -> DataFrame:
    this = lambda k: F.col("u").eqNullSafe(F.col(f"{k}u")) & F.col("size").eqNullSafe(F.col(f"{k}size"))
    more = ((F.col("u") < F.col("cut")) & ~this("q")) | this("p")
    copies = F.col("base") + F.when((F.col("part") > 0) & more, 1).otherwise(0)
    return dealt.withColumn("copies", F.least(copies, F.lit(int(most))).cast("int"))


def solve(rows: DataFrame, *, weights=WEIGHTS, share: float = SHARE, most: float = MOST) -> DataFrame:
    """A row per source: source_size, target, level, slope, error and the place of its cut. rows: source, size, prior, tilt, uniform."""
    cells = cut(rows.groupBy("source", "prior", "tilt").agg(F.sum("size").alias("tokens")))
    targets = cut(water_fill(cells.groupBy("source").agg(F.sum("tokens").alias("source_size")), weights=weights, share=share, most=most))
    by_source = multipliers(cells, targets, most=most).withColumnRenamed("source", "ms")
    solved = targets.join(by_source, F.col("ms").eqNullSafe(F.col("source")), "left").drop("ms")
    solved = cut(solved.fillna({"level": -700.0, "slope": 0.0, "cap": float(most), "center": 0.0, "scale": 1.0, "error": 0.0}))
    dealt = _dealt(rows, solved.select("source", "level", "slope", "cap", "center", "scale"))
    cuts = _nearest_cuts(dealt.select("source", "size", "base", "part", "u"), targets)
    return cut(solved.join(cuts, F.col("cs").eqNullSafe(F.col("source")), "left").drop("cs"))


def balance(docs: DataFrame, *, doc_id: str = "doc_id", text: str = "text", source: str = "source", prior: Column | None = None, tilt: Column | None = None, weights=WEIGHTS, share: float = SHARE, most: float = MOST) -> DataFrame:
    """One row per input row: doc_id, size, source_size, target, rate, copies (0 to ``most``) and taken (copies times size).

    prior and tilt are columns of docs (default: 1 for every document, and log2 of 1 + size). Null text has size 0 and is never taken; null
    is a source of its own; an empty table gives an empty result. Rows of equal id and size lie at one place, so equal rows get equal copies;
    reruns agree. Other columns of docs, whatever their names, are not read.
    """
    rows = cut(_measured(docs, doc_id, text, source, prior, tilt).select(F.col(doc_id).alias("id"), f"{MADE}.*"))
    rows = _copies(_dealt(rows, solve(rows, weights=weights, share=share, most=most)), most)
    return rows.select(F.col("id").alias(doc_id), "size", "source_size", "target", "rate", "copies", (F.col("copies") * F.col("size")).cast("long").alias("taken"))


def mix(docs: DataFrame, *, doc_id: str = "doc_id", text: str = "text", source: str = "source", weights=WEIGHTS, share: float = SHARE, most: float = MOST) -> DataFrame:
    """The mix itself: every row of docs as often as ``balance`` takes it. Texts are not shuffled; other columns stay as they are."""
    measured = _measured(docs, doc_id, text, source, None, None)
    solved = solve(cut(measured.select(f"{MADE}.*")), weights=weights, share=share, most=most)
    packed = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("row"))
    rows = _measured(packed, f"row.{doc_id}", f"row.{text}", f"row.{source}", None, None).select("row", f"{MADE}.*")
    taken = _copies(_dealt(rows, solved), most).where("copies > 0")
    return taken.select("row", F.explode(F.sequence(F.lit(1), F.col("copies")))).select("row.*")


def op2(docs: DataFrame) -> DataFrame:
    return balance(docs).select("doc_id", "size", "source_size", "target", "taken")
