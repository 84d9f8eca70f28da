"""Helpers that the operators of this subpackage share."""

from __future__ import annotations

import ctypes
import functools
import gc
from collections.abc import Iterator

import pyarrow as pa

from pyspark.sql import Column
from pyspark.sql import functions as F

from ..shipping import ship
from ..sources.tables import checkpointed as cut
from ..sources.tables import cut as cut_plan
from ..sources.tables import forget, fresh_path, landed, table

__all__ = ["SPACE", "cut", "cut_plan", "forget", "fresh_path", "landed", "lower_ascii", "ship", "strings", "table", "tidy", "utf8"]

#: White space that separates words, as a character class for Java and Python patterns.
SPACE = r"\x20\x09-\x0D"


def lower_ascii(text: Column) -> Column:
    """A-Z to a-z and nothing else, unlike lower()."""
    return F.translate(text, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def utf8(text: str | None) -> bytes:
    return b"" if text is None else text.encode("utf-8", "surrogatepass")


#: Rows of an Arrow batch that are turned into Python strings at a time.
SLICE = 128


def strings(column: pa.Array) -> Iterator[str]:
    """The texts of an Arrow column, null as empty, without a second copy of the whole batch."""
    for k in range(0, len(column), SLICE):
        for t in column.slice(k, SLICE).to_pylist():
            yield t or ""


def tidy(f):
    """A function over Arrow batches that gives its task's memory back to the system, so that idle Python workers stay small."""

    @functools.wraps(f)
    def run(batches):
        try:
            yield from f(batches)
        finally:
            gc.collect()
            pa.default_memory_pool().release_unused()
            try:
                ctypes.CDLL(None).malloc_trim(0)
            except (OSError, AttributeError):  # another C library
                pass

    return run
