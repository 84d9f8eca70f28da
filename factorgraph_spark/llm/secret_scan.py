r"""Secret scan: Boolean trigram queries, derived from each rule's regular expression, over segment-wise trigram postings.

``trigram_query`` walks Python's parse tree of a pattern and returns what a matching text must hold: an AND/OR tree of trigrams, or
``ANY`` where nothing is certain. Documents of a task up to SEGMENT, or SEGMENT_CHARS characters, are one index segment. For the trigrams that the rules ask for, the
segment keeps a posting list (the sorted numbers of the rows that hold it); queries are evaluated by intersecting and uniting
postings, and only the rows that remain are run through the regular expression. A rule without a mandatory trigram scans every row.
The index folds A-Z to a-z, so that it serves rules of either kind; what else a rule that is not ASCII may fold counts as uncertain. Nothing is shuffled and a lost task rebuilds its own segments.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import ship, strings, tidy

try:
    from re import _constants as C
    from re import _parser as parser
except ImportError:  # before Python 3.11
    import sre_constants as C
    import sre_parse as parser


@dataclass(frozen=True)
class Rule:
    """A kind of secret. Matches are leftmost and do not overlap; one is kept if ``group`` has at least ``least`` characters."""

    kind: str
    pattern: str
    least: int = 1
    group: int = 0
    flags: int = re.ASCII


# The three base rules.
BASE = (
    Rule("assign", r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 6, 2, re.ASCII | re.IGNORECASE),
    Rule("access", r"AKIA[A-Z0-9]+", 20),
    Rule("hex", r"[0-9a-f]+", 24),
)
# Public formats of keys and tokens.
MORE = (
    Rule("private_key", r"-----BEGIN (?:RSA |EC |DSA |OPENSSH )?PRIVATE KEY-----"),
    Rule("github", r"gh[pousr]_[A-Za-z0-9]{36,255}"),
    Rule("slack", r"xox[abprs]-[A-Za-z0-9-]{10,250}"),
    Rule("google_key", r"AIza[A-Za-z0-9_-]{35}"),
    Rule("stripe", r"[sr]k_live_[A-Za-z0-9]{16,99}"),
    Rule("jwt", r"eyJ[A-Za-z0-9_-]{10,}\.eyJ[A-Za-z0-9_-]{10,}\.[A-Za-z0-9_-]{10,}"),
)

SPANS = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64())]))
#: Documents, and characters, of an index segment; a longer document is a segment of its own.
SEGMENT, SEGMENT_CHARS = 2_000, 1_000_000
ANY = ("any",)
#: Alternatives that a pattern's exact strings may have before only their trigrams are kept.
MOST_STRINGS = 64


def _all(kind: str, parts: list) -> tuple:
    """parts joined by "and" or "or", with ANY absorbed."""
    flat = []
    for p in parts:
        flat += p[1] if p[0] == kind else [p]
    if kind == "and":
        flat = [p for p in dict.fromkeys(map(_frozen, flat)) if p != ANY]
        return ANY if not flat else flat[0] if len(flat) == 1 else ("and", tuple(flat))
    if ANY in flat:
        return ANY
    flat = list(dict.fromkeys(map(_frozen, flat)))
    return flat[0] if len(flat) == 1 else ("or", tuple(flat))


def _frozen(q):
    return tuple(map(_frozen, q)) if isinstance(q, (list, tuple)) else q


def _grams(strings: set[str]) -> tuple:
    """What a text must hold that holds one of strings."""
    one = [_all("and", [("has", s[k : k + 3]) for k in range(len(s) - 2)] or [ANY]) for s in sorted(strings)]
    return _all("or", one) if one else ANY


#: Letters with a case variant beyond A-Z.
_FOLDED = frozenset("iksIKS")


def _walk(items, ascii_only: bool = True) -> tuple[set[str] | None, tuple]:
    """The exact strings that a sequence can match, if they are few; and its query."""
    exact: set[str] | None = {""}
    run: set[str] = {""}  # strings that end at the current place without a gap
    need: list[tuple] = []

    def flush() -> None:
        need.append(_grams(run))

    for op, arg in items:
        strings, query = _node(op, arg, ascii_only)
        if strings is not None and len(run) * len(strings) <= MOST_STRINGS:
            run = {a + b for a in run for b in strings}
            exact = exact if exact is None else {a + b for a in exact for b in strings}
        else:
            flush()
            need.append(query)
            run, exact = ({""} if strings is None else strings), None
    flush()
    return exact, _all("and", need)


def _node(op, arg, ascii_only: bool) -> tuple[set[str] | None, tuple]:
    if op is C.LITERAL:
        if not ascii_only and (arg >= 128 or chr(arg) in _FOLDED):
            return None, ANY
        return {chr(arg).lower() if arg < 128 else chr(arg)}, ANY
    if op is C.AT:
        return {""}, ANY
    if op is C.SUBPATTERN:
        return _walk(arg[-1], ascii_only)
    if op is C.BRANCH:
        parts = [_walk(p, ascii_only) for p in arg[1]]
        strings = set().union(*(p[0] for p in parts)) if all(p[0] is not None for p in parts) else None
        return (strings if strings and len(strings) <= MOST_STRINGS else None), _all("or", [_all("and", [p[1], _grams(p[0]) if p[0] else ANY]) for p in parts])
    if op is C.IN:
        if all(o is C.LITERAL and (ascii_only or (a < 128 and chr(a) not in _FOLDED)) for o, a in arg) and len(arg) <= 8:
            return {chr(a).lower() if a < 128 else chr(a) for _, a in arg}, ANY
        return None, ANY
    if op in (C.MAX_REPEAT, C.MIN_REPEAT):
        low, high, inner = arg
        strings, query = _walk(inner, ascii_only)
        if strings is not None and (low, high) == (0, 1):
            return strings | {""}, ANY
        if strings is not None and low == high and len(strings) ** low <= MOST_STRINGS:
            out = {""}
            for _ in range(low):
                out = {a + b for a in out for b in strings}
            return out, ANY
        return None, (_all("and", [query, _grams(strings) if strings else ANY]) if low else ANY)
    return None, ANY


def trigram_query(pattern: str, flags: int = 0) -> tuple:
    """("has", trigram), ("and", parts), ("or", parts) or ANY: what every text with a match holds, after A-Z to a-z."""
    exact, query = _walk(parser.parse(pattern, flags), bool(flags & re.ASCII))
    return _all("and", [query, _grams(exact) if exact else ANY])


def grams_in(query: tuple) -> set[str]:
    return {query[1]} if query[0] == "has" else set() if query == ANY else set().union(*map(grams_in, query[1]))


def candidates(query: tuple, postings: dict[str, np.ndarray], every: np.ndarray) -> np.ndarray:
    """Row numbers that satisfy the query."""
    if query == ANY:
        return every
    if query[0] == "has":
        return postings[query[1]]
    parts = sorted((candidates(q, postings, every) for q in query[1]), key=len)
    out = parts[0]
    for p in parts[1:]:
        out = np.intersect1d(out, p, assume_unique=True) if query[0] == "and" else np.union1d(out, p)
    return out



def fold(text: str) -> str:
    return text.lower() if text.isascii() else text.encode("utf-8", "surrogatepass").lower().decode("utf-8", "surrogatepass")


def index_segment(texts: list[str], grams: list[str]) -> dict[str, np.ndarray]:
    """Posting lists of one segment for the given trigrams."""
    folded = [fold(t) for t in texts]
    return {g: np.fromiter((k for k, t in enumerate(folded) if g in t), dtype=np.int64) for g in grams}


class Finder:
    """The rules, compiled once for a task."""

    def __init__(self, rules):
        self.kinds = [r.kind for r in rules]
        self.queries = [trigram_query(r.pattern, r.flags) for r in rules]
        self.grams = sorted(set().union(*map(grams_in, self.queries)))
        self.rules = [(r, re.compile(self._long(r), r.flags)) for r in rules]

    @staticmethod
    def _long(rule: Rule) -> str:
        """Of a run of one class that must be long enough, shorter runs need not be reported to Python one by one."""
        if rule.group == 0 and rule.least > 1 and re.fullmatch(r"\[[^\]\\^]+\]\+", rule.pattern):
            return f"{rule.pattern[:-1]}{{{rule.least},}}"
        return rule.pattern

    def __call__(self, texts: list[str]) -> list[list[tuple[str, int, int]]]:
        """kind, start and end of every match, for each text of a segment in order of start and then of the rules."""
        postings = index_segment(texts, self.grams)
        out: list[list] = [[] for _ in texts]
        every = np.arange(len(texts))
        for k, ((rule, search), query) in enumerate(zip(self.rules, self.queries)):
            for row in candidates(query, postings, every).tolist():
                for m in search.finditer(texts[row]):
                    if m.end(rule.group) - m.start(rule.group) >= rule.least:
                        out[row].append((m.start(), k, m.end()))
        return [[(self.kinds[k], s, e) for s, k, e in sorted(found)] for found in out]


def find_all(texts: list[str], rules) -> list[list[tuple[str, int, int]]]:
    """kind, start and end of every match, for each text in order of start and then of the rules."""
    return Finder(rules)(texts)


def segments(column: pa.Array) -> Iterator[list[str]]:
    """The texts of an Arrow column, null as empty, in index segments."""
    held, size = [], 0
    for t in strings(column):
        if held and (len(held) == SEGMENT or size + len(t) > SEGMENT_CHARS):
            yield held
            held, size = [], 0
        held.append(t)
        size += len(t)
    if held:
        yield held


def scan(docs: DataFrame, *, doc_id: str = "doc_id", text: str = "text", rules=BASE + MORE) -> DataFrame:
    """One row per input row: its id and ``spans`` (array of kind, start, end; code points, end exclusive).

    Null and empty texts have no spans, repeated rows are scanned each, and an empty table gives an empty result. Columns other than the two
    named are not read, whatever their names.
    """
    ship(docs.sparkSession)

    @tidy
    def search(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        find = Finder(rules)
        for batch in batches:
            at = 0
            for texts in segments(batch.column("t")):
                spans = pa.array([[{"kind": k, "start": s, "end": e} for k, s, e in x] for x in find(texts)], SPANS)
                yield pa.RecordBatch.from_arrays([batch.column("id").slice(at, len(texts)), spans], ["id", "spans"])
                at += len(texts)

    kind = dict(docs.select(doc_id).dtypes)[doc_id]
    rows = docs.select(F.col(doc_id).alias("id"), F.col(text).alias("t"))
    return rows.mapInArrow(search, f"id {kind}, spans array<struct<kind: string, start: long, end: long>>").withColumnRenamed("id", doc_id)


def _marked(text: str, spans, mark: str) -> str:
    parts, at = [], 0
    for _, s, e in spans:
        if s > at or not parts:
            parts += [text[at:s], mark]
        at = max(at, e)
    return "".join([*parts, text[at:]])


def redact(docs: DataFrame, *, text: str = "text", rules=BASE + MORE, mark: str = "<secret>") -> DataFrame:
    """docs with every span replaced by ``mark`` (spans that touch or overlap become one mark); null stays null, other columns stay."""
    ship(docs.sparkSession)

    @tidy
    def clean(columns: Iterator[pa.Array]) -> Iterator[pa.Array]:
        find = Finder(rules)
        for column in columns:
            done, at = [], 0
            for texts in segments(column):
                same = column.slice(at, len(texts))
                at += len(texts)
                found = find(texts)
                if any(found):
                    same = pa.array([_marked(t, spans, mark) if spans else t for t, spans in zip(texts, found)], pa.string(), mask=same.is_null().to_numpy(zero_copy_only=False))
                done.append(same.cast(pa.string()))
            yield pa.concat_arrays(done) if done else pa.array([], pa.string())

    return docs.withColumn(text, F.arrow_udf(clean, T.StringType())(F.col(text)))


def op6(docs: DataFrame) -> DataFrame:
    base = [r.kind for r in BASE]
    joined = lambda spans: F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"], s["end"])), ",")
    of = lambda *kinds: F.filter("spans", lambda s: s["kind"].isin(*kinds))
    return scan(docs).select(
        "doc_id",
        *[F.size(of(k)).cast("long").alias(f"n_{k}") for k in base],
        F.sha2(joined(of(*base)), 256).alias("base_sha256"),
        joined(F.col("spans")).alias("spans"),
    )
