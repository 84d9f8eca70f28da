"""Licence scan: an exact set-similarity join of text blocks with licence templates.

A block is a line of a document, or a window: ``WINDOW`` times a template's length of words in a row, across line breaks, so that
wrapped notices are found. A template matches a block if at least ``threshold`` of the template's distinct words are in the
block. The join is exact: a first pass counts in how many blocks each template word stands (all blocks of all documents), which
orders every template's words from rare to frequent; a block can only reach the threshold if it holds one of the template's
``|T| - need + 1`` rarest words (prefix filter), has at least ``need`` distinct words (length filter), and if the words that remain
after its first shared prefix word are still enough (position filter). The filters run on the document's words first, which hold
every block's, and again on each line; windows slide over the places of the template's words, all of them. What passes is verified
on the full sets. Neither pass
shuffles text: the first sends one row per template word and task, the second nothing.

The prefix words of all templates form an inverted index, so that a document or line meets only templates that share a rare word with it.

Templates are a literal table, sent with the tasks in groups of at most ``MAX_TEMPLATE_WORDS`` words (a single longer template is a group of
its own). Every group is one more step over the same rows, which adds its matches to those before: results do not depend on the groups.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass
from math import ceil

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import ship, strings, tidy, utf8

# Phrases whose places are always reported, with their labels.
PHRASES = {"mit license": "mit", "apache license": "apache", "general public license": "gpl"}

# Wordings by which works state a licence, label first.
TEMPLATES = (
    ("mit", "released under the mit license"),
    ("mit", "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files"),
    ("apache", "licensed under the apache license version 2 0"),
    ("gpl", "this work is licensed under the gnu general public license version 3"),
    ("gpl", "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license"),
    ("cc-by-nc", "licensed under cc by nc 4 0"),
    ("cc-by-sa", "this work is licensed under a creative commons attribution sharealike 4 0 international license"),
    ("bsd", "redistribution and use in source and binary forms with or without modification are permitted"),
    ("mpl", "this source code form is subject to the terms of the mozilla public license v 2 0"),
)

PLACES = pa.list_(pa.struct([("word", pa.int64()), ("label", pa.string())]))
BLOCKS = pa.list_(pa.struct([("line", pa.int64()), ("label", pa.string()), ("containment", pa.float64())]))
WINDOWS = pa.list_(pa.struct([("word", pa.int64()), ("label", pa.string()), ("containment", pa.float64())]))

#: Words of a window for each word of a template: room for words that a notice adds.
WINDOW = 1.25

#: Words in the templates of one step.
MAX_TEMPLATE_WORDS = 50_000

#: A-Z to a-z, and every byte that is no part of a word to a space; bytes from 0x80 belong to words.
_WORD_BYTES = bytes(b if 48 <= b <= 57 or 97 <= b <= 122 or b >= 128 else b + 32 if 65 <= b <= 90 else 32 for b in range(256))


def words_of(text: str | None) -> list[bytes]:
    return utf8(text).translate(_WORD_BYTES).split()


@dataclass(frozen=True)
class Template:
    label: str
    ordered: tuple[bytes, ...]  # rare to frequent
    need: int
    width: int  # words of a window

    @property
    def prefix(self) -> tuple[bytes, ...]:
        return self.ordered[: len(self.ordered) - self.need + 1]


def _lines(text: str | None) -> list[bytes]:
    return utf8(text).split(b"\n")


def block_frequencies(docs: DataFrame, words: set[bytes], text: str = "text") -> dict[bytes, int]:
    """In how many lines of all documents each of ``words`` stands."""

    @tidy
    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found: Counter[bytes] = Counter()
        for batch in batches:
            for t in strings(batch.column("t")):
                if words.isdisjoint(words_of(t)):
                    continue
                for line in _lines(t):
                    found.update(words.intersection(line.translate(_WORD_BYTES).split()))
        yield pa.RecordBatch.from_arrays([pa.array([w.decode() for w in found], pa.string()), pa.array(list(found.values()), pa.int64())], ["w", "n"])

    rows = docs.select(F.col(text).alias("t")).mapInArrow(count, "w string, n long").groupBy("w").agg(F.sum("n").alias("n")).collect()
    return {r["w"].encode(): r["n"] for r in rows}


def compile_templates(templates, frequency: dict[bytes, int], threshold: float) -> list[Template]:
    out = []
    for label, wording in templates:
        words = set(words_of(wording))
        if words:
            width = ceil(WINDOW * len(words_of(wording)))
            out.append(Template(label, tuple(sorted(words, key=lambda w: (frequency.get(w, 0), w))), max(1, ceil(threshold * len(words) - 1e-9)), width))
    return out


def shared_words(words: set[bytes], t: Template) -> int:
    """How many of the template's words are among ``words``; 0 where they are fewer than it needs."""
    if len(words) < t.need:
        return 0
    first = next((k for k, w in enumerate(t.prefix) if w in words), None)
    if first is None or len(t.ordered) - first < t.need:
        return 0
    shared = sum(w in words for w in t.ordered[first:])
    return shared if shared >= t.need else 0


class Prefixes:
    """Templates by the words of their prefixes."""

    def __init__(self, templates: list[Template]):
        self.templates, self.by_word = templates, {}
        for k, t in enumerate(templates):
            for w in t.prefix:
                self.by_word.setdefault(w, []).append(k)
        self.rare = frozenset(self.by_word)

    def reached(self, words: set[bytes], among: set[int] | None = None) -> list[tuple[int, int]]:
        """Number and shared words of every template (of ``among``) that the words reach."""
        met = {k for w in self.rare.intersection(words) for k in self.by_word[w]}
        if among is not None:
            met &= among
        return [(k, shared) for k in sorted(met) if (shared := shared_words(words, self.templates[k]))]


def match_windows(words: list[bytes], t: Template) -> Iterator[tuple[int, float]]:
    """First word and containment of the best window (the first of equals) in each run of overlapping windows that reach the template."""
    sought = set(t.ordered)
    hits = [k for k, w in enumerate(words) if w in sought]
    held: Counter[bytes] = Counter()
    left, best, last = 0, None, -1
    for k in hits:
        held[words[k]] += 1
        while hits[left] <= k - t.width:
            w = words[hits[left]]
            held[w] -= 1
            if not held[w]:
                del held[w]
            left += 1
        if len(held) < t.need:
            continue
        if best and hits[left] > last:
            yield best[0], best[1] / len(t.ordered)
            best = None
        if not best or len(held) > best[1]:
            best = (hits[left], len(held))
        last = k
    if best:
        yield best[0], best[1] / len(t.ordered)


def phrase_places(words: list[bytes], phrases: dict[str, str]) -> Iterator[tuple[int, str]]:
    """Index of the first word, and label, of every place of every phrase."""
    joined = b" " + b" ".join(words) + b" "
    for phrase, label in phrases.items():
        sought = b" " + phrase.encode() + b" "
        at = joined.find(sought)
        while at >= 0:
            yield joined.count(b" ", 0, at), label
            at = joined.find(sought, at + 1)


def scan(docs: DataFrame, *, doc_id: str = "doc_id", text: str = "text", templates=TEMPLATES, phrases=PHRASES, threshold: float = 0.8) -> DataFrame:
    """One row per input row: its id, n_words, ``phrases`` (array of word and label), ``blocks`` (lines that match: array of line, label,
    containment) and ``windows`` (the same across line breaks: array of first word, label, containment).

    Null and empty texts have no words and no matches; repeated rows are scanned each; an empty table gives an empty result. Other
    columns of the input are not read.
    """
    ship(docs.sparkSession)
    groups, size = [[]], 0
    for t in templates:
        size += len(words_of(t[1]))
        if groups[-1] and size > MAX_TEMPLATE_WORDS:
            groups, size = [*groups, []], len(words_of(t[1]))
        groups[-1].append(t)
    compiled: list[list[Template]] = []
    for group in groups:
        words = {w for _, wording in group for w in words_of(wording)}
        compiled.append(compile_templates(group, block_frequencies(docs, words, text), threshold) if words else [])

    kind = dict(docs.select(doc_id).dtypes)[doc_id]
    schema = f"id {kind}, n_words long, phrases array<struct<word: long, label: string>>, blocks array<struct<line: long, label: string, containment: double>>, windows array<struct<word: long, label: string, containment: double>>"
    out = docs.select(F.col(doc_id).alias("id"), F.col(text).alias("t"))
    for k, part in enumerate(compiled):
        last = k == len(compiled) - 1
        out = out.mapInArrow(_step(part, phrases if k == 0 else None, not last), schema + ("" if last else ", t string"))
    return out.withColumnRenamed("id", doc_id)


def _step(part: list[Template], phrases: dict[str, str] | None, onward: bool):
    """Adds one group's matches to the rows; the first step (with phrases) starts them. onward: the text goes on to the next step."""

    @tidy
    def match(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        index = Prefixes(part)
        for batch in batches:
            counts, places, blocks, windows = [], [], [], []
            for t in strings(batch.column("t")):
                words = words_of(t)
                if phrases is not None:
                    counts.append(len(words))
                    places.append([{"word": w, "label": x} for w, x in sorted(phrase_places(words, phrases))] if words else [])
                found, across = [], []
                if not index.rare.isdisjoint(words):
                    possible = {k for k, _ in index.reached(set(words))}
                    for n, line in enumerate(_lines(t) if possible else []):
                        reached = index.reached(set(line.translate(_WORD_BYTES).split()), possible)
                        found += [{"line": n, "label": part[k].label, "containment": shared / len(part[k].ordered)} for k, shared in reached]
                    for k in sorted(possible):
                        across += [{"word": at, "label": part[k].label, "containment": c} for at, c in match_windows(words, part[k])]
                blocks.append(found)
                windows.append(across)
            if phrases is not None:
                columns = [pa.array(counts, pa.int64()), pa.array(places, PLACES)]
            else:
                columns = [batch.column("n_words"), batch.column("phrases")]
                blocks = [a + b for a, b in zip(batch.column("blocks").to_pylist(), blocks)]
                windows = [a + b for a, b in zip(batch.column("windows").to_pylist(), windows)]
            columns = [batch.column("id"), *columns, pa.array(blocks, BLOCKS), pa.array(windows, WINDOWS)]
            names = ["id", "n_words", "phrases", "blocks", "windows"]
            yield pa.RecordBatch.from_arrays([*columns, batch.column("t")] if onward else columns, [*names, "t"] if onward else names)

    return match


def op1(docs: DataFrame) -> DataFrame:
    """The digest columns of a scan: places and labels of phrases, and the labels and best score of the join."""
    base = F.array_sort(F.array_distinct(F.col("phrases.label")))
    every = F.array_sort(F.array_distinct(F.concat("phrases.label", "blocks.label", "windows.label")))
    return scan(docs).select(
        "doc_id",
        "n_words",
        F.size("phrases").cast("long").alias("n_base"),
        F.array_min("phrases.word").alias("first_word"),
        F.array_max("phrases.word").alias("last_word"),
        F.array_join(base, ",").alias("base_labels"),
        F.array_join(every, ",").alias("labels"),
        F.when(F.size("phrases") > 0, F.lit(1.0)).otherwise(F.coalesce(F.array_max(F.concat("blocks.containment", "windows.containment")), F.lit(0.0))).alias("score"),
    )
