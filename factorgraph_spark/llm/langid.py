"""Language identification by unigram piece models whose segmentations are summed out.

The pieces are those of a fixed public vocabulary. Every language has a probability for every piece, fitted by expectation maximisation on
the words of a bounded sample of labelled documents. A text's likelihood is the product over its chunks (runs of letters, lower-cased) of the sum, over all
ways to cut the chunk into pieces, of the product of piece probabilities; the forward recursion computes it for all languages and all new
chunks of a batch at once. Chunks recur, so each worker keeps a bounded table of their scores. No shuffle: texts are scored where they are.

Sums are scaled by language every few characters, so that chunks of any length stay within double precision; only the last places are held,
as many as the longest piece has characters. Training, on its bounded sample, cuts chunks of more than ``LONGEST`` characters.
"""

from __future__ import annotations

import functools
import re
import sys
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import ship, strings, tidy

#: Characters of a chunk in training.
LONGEST = 32
#: Labelled documents of the training sample, shared evenly among the languages.
SAMPLE_DOCS = 800
EM_ROUNDS = 3
#: Probability of a character that is no piece; share of the pooled model in every language's.
UNKNOWN, POOLED = 1e-7, 0.02
#: Chunks that a worker remembers; the table is emptied when it is full.
REMEMBERED = 250_000
TOGETHER = 300_000
#: Longer chunks are not remembered.
SHORT = 64
#: Places whose pieces are looked up at a time, places between scalings, and characters of the words that are scored at once.
STRETCH, SCALED, AT_ONCE = 2_048, 16, 200_000
UNDETERMINED = "und"


_WORD = re.compile(r"[^\W\d_]+")


@functools.cache
def _signs() -> re.Pattern:
    """Number signs such as ½, which Python counts as parts of words."""
    return re.compile("[" + "".join(c for c in map(chr, range(sys.maxunicode + 1)) if c.isnumeric() and not c.isalpha() and not c.isdecimal()) + "]")


def chunks_of(text: str) -> list[str]:
    """The runs of letters of a text, lower-cased."""
    found = _WORD.findall(text.lower())
    if not text.isascii() and found and not "".join(found).isalpha():
        found = [c for chunk in found for c in _signs().split(chunk) if c]
    return found


_ODD = np.uint64(0x9E3779B97F4A7C15)
_STEP = np.uint64(0xD1342543DE82EF95)


def default_vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("piece_bpe_32k.model")


def read_pieces(path: str) -> list[str]:
    """Ordinary pieces of a sentencepiece model, of letters and the sign of a chunk's start: no control, byte or unknown pieces."""
    import sentencepiece

    m = sentencepiece.SentencePieceProcessor(model_file=path)
    pieces = [m.id_to_piece(k) for k in range(m.get_piece_size()) if not (m.is_control(k) or m.is_byte(k) or m.is_unknown(k))]
    return [p for p in pieces if p == "▁" or p.removeprefix("▁").isalpha()]  # chunks hold no others


class PieceIndex:
    """Finds all pieces in all chunks of a batch by rolling hashes of code points."""

    BITS = 20

    def __init__(self, pieces: list[str]):
        self.size, self.longest = len(pieces), max(map(len, pieces), default=1)
        keys = np.array([self._hash(p) for p in pieces], dtype=np.uint64)
        self.keys = np.append(keys, np.uint64(0))
        self.tables, rest, bits = [], np.arange(self.size, dtype=np.int32), self.BITS
        while len(rest):  # what finds its slot taken goes to a further, smaller table
            table, odd = np.full(1 << bits, self.size, dtype=np.int32), _ODD + np.uint64(2 * len(self.tables))
            slots = self._slot(keys[rest], odd, bits)
            table[slots] = rest
            self.tables.append((odd, bits, table))
            rest, bits = rest[table[slots] != rest], 16

    @staticmethod
    def _slot(keys: np.ndarray, odd: np.uint64, bits: int) -> np.ndarray:
        return ((keys * odd) >> np.uint64(64 - bits)).view(np.int64)

    @staticmethod
    def _hash(piece: str) -> int:
        h = 0
        for c in piece:
            h = (h * int(_STEP) + ord(c) + 1) & 0xFFFFFFFFFFFFFFFF
        return h

    def find(self, codes: np.ndarray) -> Iterator[np.ndarray]:
        """codes: words by characters, 0 after a word's end. For each piece length, the piece that starts at each place (size: none)."""
        n, width = codes.shape
        hashes = np.zeros((n, width), dtype=np.uint64)
        for length in range(1, min(self.longest, width) + 1):
            hashes = hashes[:, : width - length + 1] * _STEP + codes[:, length - 1 :] + np.uint64(1)
            ids = np.full(hashes.shape, self.size, dtype=np.int32)
            for odd, bits, table in self.tables:
                maybe = table[self._slot(hashes, odd, bits)]
                np.copyto(ids, maybe, where=self.keys[maybe] == hashes)
            ids[codes[:, length - 1 :] == 0] = self.size
            yield ids


def _codes(words: list[str]) -> tuple[np.ndarray, np.ndarray]:
    """Code points of the words, padded with 0, and the words' lengths."""
    lengths = np.fromiter(map(len, words), dtype=np.int64, count=len(words))
    flat = np.frombuffer("".join(words).encode("utf-32-le", "surrogatepass"), dtype="<u4")
    codes = np.zeros((len(words), int(lengths.max())), dtype=np.uint64)
    codes[np.arange(codes.shape[1]) < lengths[:, None]] = flat
    return codes, lengths


def forward(index: PieceIndex, probs: np.ndarray, words: list[str]) -> tuple[np.ndarray, list[np.ndarray], np.ndarray]:
    """alpha (place, word, language), the pieces by length, and lengths; words have 1 to LONGEST + 1 characters.

    probs: piece by language with a last row of zeros for "no piece"; a single character that is no piece has UNKNOWN.
    """
    codes, lengths = _codes(words)
    found = list(index.find(codes))
    n, width = codes.shape
    alpha = np.zeros((width + 1, n, probs.shape[1]))
    alpha[0] = 1
    single = found[0] == index.size
    for end in range(1, width + 1):
        live = np.flatnonzero(lengths >= end)
        for length in range(1, min(end, len(found)) + 1):
            ids = found[length - 1][live, end - length]
            hit = ids < index.size
            if hit.any():
                rows = live[hit]
                alpha[end, rows] += alpha[end - length, rows] * probs[ids[hit]]
        rows = live[single[live, end - 1]]
        alpha[end, rows] += alpha[end - 1, rows] * UNKNOWN
    return alpha, found, lengths


def log_likelihoods(index: PieceIndex, probs: np.ndarray, words: list[str]) -> np.ndarray:
    """Word by language: log of the sum over all segmentations. words: of any length, the shortest first."""
    lengths = np.fromiter(map(len, words), dtype=np.int64, count=len(words))
    n, width, slots = len(words), int(lengths[-1]), index.longest + 1
    ring = np.zeros((slots, n, probs.shape[1]))  # sums up to the places from the current one on
    ring[0] = 1
    scale, out = np.zeros(ring.shape[1:]), np.zeros(ring.shape[1:])
    ended = 0
    for begin in range(0, width, STRETCH):
        codes, _ = _codes([w[begin : begin + STRETCH + index.longest] for w in words])
        found = list(index.find(codes))
        single = found[0] == index.size
        for at in range(begin, min(width, begin + STRETCH)):
            here, place = ring[at % slots], at - begin
            live = int(np.searchsorted(lengths, at, side="right"))
            out[ended:live] = np.log(np.maximum(here[ended:live], 1e-300)) + scale[ended:live]
            ended = live
            if at and at % SCALED == 0:
                by = np.maximum(here[live:], 1e-300).copy()
                ring[:, live:] /= by
                scale[live:] += np.log(by)
            for length, ids in enumerate(found, 1):
                if place >= ids.shape[1]:
                    break
                ids = ids[live:, place]
                rows = np.flatnonzero(ids < index.size)
                if len(rows):
                    ring[(at + length) % slots, live + rows] += here[live + rows] * probs[ids[rows]]
            rows = live + np.flatnonzero(single[live:, place])
            ring[(at + 1) % slots, rows] += here[rows] * UNKNOWN
            here[:] = 0
    out[ended:] = np.log(np.maximum(ring[width % slots, ended:], 1e-300)) + scale[ended:]
    return out


def expected_counts(index: PieceIndex, probs: np.ndarray, words: list[str], counts: np.ndarray) -> np.ndarray:
    """Expected uses of each piece in the words' segmentations, for one language (probs has one column)."""
    alpha, found, lengths = forward(index, probs, words)
    width, n = alpha.shape[0] - 1, len(words)
    beta = np.zeros((width + 1, n))
    beta[lengths, np.arange(n)] = 1
    total = alpha[lengths, np.arange(n), 0]
    weight = counts / np.maximum(total, 1e-300)
    out, p = np.zeros(index.size + 1), probs[:, 0]
    single = found[0] == index.size
    for start in range(width - 1, -1, -1):
        live = np.flatnonzero(lengths > start)
        for length in range(1, min(width - start, len(found)) + 1):
            ids = found[length - 1][live, start]
            hit = ids < index.size
            rows, ids = live[hit], ids[hit]
            gain = p[ids] * beta[start + length, rows]
            beta[start, rows] += gain
            np.add.at(out, ids, alpha[start, rows, 0] * gain * weight[rows])
        rows = live[single[live, start]]
        beta[start, rows] += UNKNOWN * beta[start + 1, rows]
    return out[:-1]


def stretches(chunk: str) -> list[str]:
    """A chunk as training takes it."""
    marked = "▁" + chunk
    return [marked[k : k + LONGEST] for k in range(0, len(marked), LONGEST)]


@dataclass
class Model:
    languages: list[str]
    pieces: list[str]
    probs: np.ndarray  # piece by language, a row of zeros last


def fit(word_counts: dict[str, dict[str, int]], pieces: list[str], rounds: int = EM_ROUNDS) -> Model:
    """Piece probabilities of every language from its word counts."""
    index = PieceIndex(pieces)
    languages, columns = sorted(word_counts), []
    for language in languages:
        counts: dict[str, int] = {}
        for chunk, n in word_counts[language].items():
            for s in stretches(chunk):
                counts[s] = counts.get(s, 0) + n
        words = sorted(counts, key=lambda w: (len(w), w))
        p = np.full((index.size + 1, 1), 1 / index.size)
        for _ in range(rounds):
            p[-1] = 0
            total = np.zeros(index.size)
            for k in range(0, len(words), 5_000):
                part = words[k : k + 5_000]
                total += expected_counts(index, p, part, np.array([counts[w] for w in part], dtype=float))
            p = np.append(total / max(total.sum(), 1e-300), 0)[:, None]
        columns.append(p[:-1, 0])
    own = np.stack(columns, axis=1) if columns else np.zeros((index.size, 0))
    pooled = own.mean(axis=1, keepdims=True) * 0.9 + 0.1 / index.size if columns else 0
    probs = (1 - POOLED) * own + POOLED * pooled
    return Model(languages, pieces, np.vstack([probs, np.zeros((1, probs.shape[1]))]))


class Scorer:
    """Scores of chunks and texts under a model, with a bounded table of chunks."""

    def __init__(self, model: Model):
        self.model, self.index = model, PieceIndex(model.pieces)
        self._forget()

    def _forget(self) -> None:
        self.known: dict[str, int] = {}
        self.used = 0
        self.rows = np.zeros((1024, len(self.model.languages)))

    def _scored(self, chunks: set[str]) -> Iterator[tuple[list[str], np.ndarray]]:
        """chunks in parts, the shortest first, with their scores."""
        held, size = [], 0
        for c in sorted(chunks, key=len):
            if held and (size + len(c) > AT_ONCE or len(held) == 4_000):
                yield held, log_likelihoods(self.index, self.model.probs, ["▁" + x for x in held])
                held, size = [], 0
            held.append(c)
            size += len(c)
        if held:
            yield held, log_likelihoods(self.index, self.model.probs, ["▁" + x for x in held])

    def _learn(self, chunks: set[str]) -> None:
        for part, logs in self._scored(chunks):
            first, self.used = self.used, self.used + len(part)
            while self.used > len(self.rows):
                self.rows = np.vstack([self.rows, np.zeros_like(self.rows)])
            self.rows[first : self.used] = logs
            self.known.update(zip(part, range(first, self.used)))

    def texts(self, texts) -> Iterator[tuple[bool, np.ndarray]]:
        """Whether the text has a word, and its log-likelihood by language."""
        held, size = [], 0
        for t in texts:
            held.append(chunks_of(t))
            size += len(t)
            if size > TOGETHER:
                yield from self._held(held)
                held, size = [], 0
        yield from self._held(held)

    def _held(self, held: list[list[str]]) -> Iterator[tuple[bool, np.ndarray]]:
        if self.used > REMEMBERED:
            self._forget()
        new = set().union(*held).difference(self.known) if self.model.languages else set()
        if new:
            self._learn(new)
        for chunks in held:
            known = map(self.known.__getitem__, chunks) if self.model.languages else ()
            yield bool(chunks), self.rows[np.fromiter(known, dtype=np.int64)].sum(axis=0)
        for c in [c for c in new if len(c) > SHORT]:
            del self.known[c]


def held_out(doc_id: Column) -> Column:
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 4 == 2, F.lit(False))


def train(docs: DataFrame, *, doc_id: str = "doc_id", text: str = "text", lang: str = "lang", vocabulary: str | None = None, sample_docs: int = SAMPLE_DOCS) -> Model:
    """A model from at most ``sample_docs`` labelled documents that are not held out; the sample is the one of lowest hashes of the id."""
    ship(docs.sparkSession)
    labelled = docs.select(F.col(doc_id).alias("id"), F.col(text).alias("t"), F.col(lang).alias("l")).where(F.col("l").isNotNull() & F.col("t").isNotNull() & ~held_out(F.col("id")))
    languages = max(1, labelled.select(F.count_distinct("l")).first()[0])
    order = Window.partitionBy("l").orderBy(F.xxhash64("id"), "id")
    chosen = labelled.select("id", "l").withColumn("k", F.row_number().over(order)).where(F.col("k") <= max(1, sample_docs // languages)).select("id").distinct()

    @tidy
    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = Counter((label, w) for label, t in zip(batch.column("l").to_pylist(), strings(batch.column("t"))) for w in chunks_of(t))
            yield pa.RecordBatch.from_arrays([pa.array([x for x, _ in found], pa.string()), pa.array([w for _, w in found], pa.string()), pa.array(list(found.values()), pa.int64())], ["l", "w", "n"])

    words = labelled.join(F.broadcast(chosen), "id").select("l", "t").mapInArrow(count, "l string, w string, n long")
    counts: dict[str, dict[str, int]] = {}
    for r in words.groupBy("l", "w").agg(F.sum("n").alias("n")).toLocalIterator():  # the words of the sample
        counts.setdefault(r["l"], {})[r["w"]] = r["n"]
    return fit(counts, read_pieces(vocabulary or default_vocabulary()))


def predict(docs: DataFrame, model: Model, *, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, lang_pred and score (posterior under equal priors) of every row.

    Texts that are null or hold no letter are undetermined, score 0, and so are all if the model has no language. Ties go to the first
    language by name. Columns other than the two named are not read, whatever their names; an empty table gives an empty result.
    """
    ship(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast(model)  # as large as vocabulary times languages

    @tidy
    def guess(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scorer = Scorer(shared.value)
        names = scorer.model.languages
        for batch in batches:
            best, score = [], []
            for worded, logs in scorer.texts(strings(batch.column("t"))):
                if not names or not worded:
                    best.append(UNDETERMINED)
                    score.append(0.0)
                    continue
                k = int(np.argmax(logs))
                best.append(names[k])
                score.append(float(1 / np.exp(logs - logs[k]).sum()))
            yield pa.RecordBatch.from_arrays([batch.column("id"), pa.array(best, pa.string()), pa.array(score, pa.float64())], ["id", "lang_pred", "score"])

    kind = dict(docs.select(doc_id).dtypes)[doc_id]
    rows = docs.select(F.col(doc_id).alias("id"), F.col(text).alias("t"))
    return rows.mapInArrow(guess, f"id {kind}, lang_pred string, score double").withColumnRenamed("id", doc_id)


def accept(docs: DataFrame, model: Model, *, text: str = "text", least: float = 0.5) -> DataFrame:
    """The rows of docs whose language is determined with a score of at least ``least``; all columns stay, nothing is shuffled.

    A model without a language (no labelled document to learn from) can't tell, so only texts without a letter are rejected.
    """
    ship(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast(model)

    @tidy
    def sure(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        scorer = Scorer(shared.value)
        for batch in batches:
            found = scorer.texts(strings(batch))
            yield pa.array([bool(worded) and (not len(logs) or bool(1 / np.exp(logs - logs.max()).sum() >= least)) for worded, logs in found], pa.bool_())

    return docs.where(F.arrow_udf(sure, T.BooleanType())(F.col(text)))


def op3(docs: DataFrame) -> DataFrame:
    return predict(docs, train(docs)).select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "lang_pred", "score")
