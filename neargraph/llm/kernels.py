"""Shared pieces of the Arrow kernels: words, batches of bounded size."""

from __future__ import annotations

import contextlib
import ctypes
import gc
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from neargraph.runtime import Scratch


def ascii_words(text: str | None, *, lower: bool = False) -> list[bytes]:
    r"""Maximal runs of ``[^\x20\x09-\x0D]``, as UTF-8; ``lower`` changes A-Z only. No text: no words."""
    if not text:
        return []
    raw = text.encode("utf-8", "surrogatepass")
    return (raw.lower() if lower else raw).split()


def documents_of(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Only the two columns that text operators read, under fixed names, so other columns cannot clash."""
    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))


def pieces(batches: Iterator[pa.RecordBatch], max_chars: int = 4_000_000) -> Iterator[tuple[pa.Array, list[str | None]]]:
    """(ids, texts) in pieces of a bounded number of characters; a longer text is a piece of its own."""
    for batch in batches:
        ids, texts = batch.column(0), batch.column(1).to_pylist()
        at = held = 0
        for i, text in enumerate(texts):
            held += len(text or "")
            if held >= max_chars:
                yield ids.slice(at, i + 1 - at), texts[at : i + 1]
                at, held = i + 1, 0
        if at < len(texts):
            yield ids.slice(at), texts[at:]


def numbered(rows: DataFrame, order: list, scratch: Scratch, name: str = "number") -> DataFrame:
    """The rows with numbers 0, 1, ... in an order. Equal tables get equal numbers whatever their partitions, as rows that tie in the
    whole order should be alike. A sorted table is written, and only its row count by partition is collected.
    """
    tied = rows.withColumn("_tie", F.monotonically_increasing_id())  # equal rows need not go to one task
    placed = scratch.keep(tied.orderBy(*order, "_tie").drop("_tie").withColumn("_place", F.monotonically_increasing_id()))
    part, spot = F.shiftright("_place", 33), F.col("_place").bitwiseAND((1 << 33) - 1)
    counts = sorted((r.part, r.n) for r in placed.groupBy(part.alias("part")).agg(F.count("*").alias("n")).collect())
    offsets, before = [], 0
    for p, n in counts:
        offsets.append((p, before))
        before += n
    first = scratch.spark.createDataFrame(offsets, "_part long, _first long")
    joined = placed.join(F.broadcast(first), part == F.col("_part"))  # one row for each partition
    return joined.select(*rows.columns, (F.col("_first") + spot).alias(name))


_RESIDENT: dict = {}


def resident(kind: str, key=None, make=lambda: None):
    """The one large object that a Python worker keeps between tasks; one of another kind or key takes its place.

    Workers are used again by later stages, so what a stage has learned must not stay beside what the next one needs.
    """
    if _RESIDENT.get("is") != (kind, key):
        release()
        _RESIDENT["object"] = make()
        _RESIDENT["is"] = (kind, key)
    return _RESIDENT["object"]


def release() -> None:
    """Drops the object that is kept, and gives memory that is free back to the system, where the C library can."""
    _RESIDENT.clear()
    gc.collect()
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):
        ctypes.CDLL(None).malloc_trim(0)


def tidy(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The results of a kernel that keeps nothing for the next task: its memory goes back to the system when it is done."""
    try:
        yield from batches
    finally:
        release()


def record(schema: pa.Schema, *columns) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([c if isinstance(c, pa.Array) else pa.array(c, f.type) for c, f in zip(columns, schema, strict=True)], schema=schema)
