"""Column helpers that the text operators share."""

from __future__ import annotations

import zlib

from pyspark.sql import Column
from pyspark.sql import functions as F

#: The separators of the word rule `[^\x20\x09-\x0D]+`, as Java and RE2 patterns read them.
GAPS = r"[\x20\x09-\x0D]+"
WORD = r"[^\x20\x09-\x0D]+"


def free_name(taken: list[str], name: str) -> str:
    """``name``, or a longer one that none of ``taken`` is, whatever its case."""
    used = {c.lower() for c in taken}
    while name.lower() in used:
        name += "_"
    return name


def named(name: str) -> Column:
    """The column with exactly this name, dots and all."""
    return F.col("`" + name.replace("`", "``") + "`")


def text_or_empty(name: str = "text") -> Column:
    return F.coalesce(F.col(name).cast("string"), F.lit(""))


def text_bytes(name: str = "text") -> Column:
    """UTF-8 bytes of a text column, null as empty, for Arrow consumers."""
    return text_or_empty(name).cast("binary")


def word_array(text: Column) -> Column:
    return F.array_remove(F.split(text, GAPS), "")


def word_count(text: Column) -> Column:
    return F.regexp_count(text, F.lit(WORD)).cast("long")


def fold_of(doc_id: Column, folds: int) -> Column:
    """crc32 of the decimal id modulo ``folds``; a null id counts as the empty string."""
    return F.pmod(F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")), F.lit(folds))


def fold_of_id(doc_id: int | None, folds: int) -> int:
    return zlib.crc32(b"" if doc_id is None else str(doc_id).encode()) % folds


def release() -> None:
    """Hands a worker's freed memory back to the system; called where a task ends, as workers stay for later stages."""
    import ctypes

    import pyarrow as pa

    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # another C library
        pass
