"""Helpers shared by the corpus operators: scratch tables, word rules and batch iteration."""

from __future__ import annotations

import ctypes
from collections.abc import Iterator

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column
from pyspark.sql import functions as F

from ..sources.scratch import materialise, scratch_root

#: A word is a run of bytes outside the six ASCII white space characters.
WORD = r"[^\x20\x09-\x0D]+"
BLANKS = " \t\n\x0b\x0c\r"

__all__ = ["BLANKS", "WORD", "in_fold", "materialise", "rows_of", "scratch_root", "slices", "trim", "utf8", "word_count"]


def word_count(text: str | Column) -> Column:
    """Number of words; 0 for a null."""
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def in_fold(doc_id: str | Column, modulus: int, remainder: int) -> Column:
    """True where crc32 of the id as text leaves ``remainder``; a null id counts as the empty text."""
    text = (F.col(doc_id) if isinstance(doc_id, str) else doc_id).cast("string")
    return F.crc32(F.coalesce(text, F.lit("")).cast("binary")) % modulus == remainder


def trim() -> None:
    """Give memory that earlier tasks of this Python worker have freed back to the machine."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library: it keeps the memory for later tasks
        return


def slices(batches: Iterator[pa.RecordBatch], column: str, most_bytes: int) -> Iterator[pa.RecordBatch]:
    """Cut Arrow batches so that ``column`` holds about ``most_bytes`` at most (one row at least)."""
    trim()
    for batch in batches:
        if not batch.num_rows:
            continue
        sizes = pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False)
        begin, held = 0, 0
        for i, n in enumerate(sizes.tolist()):
            if i > begin and held + n > most_bytes:
                yield batch.slice(begin, i - begin)
                begin, held = i, 0
            held += n
        yield batch.slice(begin)


def utf8(column: pa.Array) -> list[bytes]:
    """The UTF-8 bytes of a string column, a null as the empty string."""
    return column.cast(pa.binary()).fill_null(b"").to_pylist()


def rows_of(batch: pa.RecordBatch) -> Iterator[dict]:
    """The rows of a batch of few but large rows, one Python copy at a time."""
    for i in range(batch.num_rows):
        trim()
        yield batch.slice(i, 1).to_pylist()[0]
