"""Helpers shared by the operators: tables, shared scratch tables, Arrow slicing."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
import pyarrow.compute  # noqa: F401
from pyspark.sql import Column
from pyspark.sql import functions as F

from ..sources.tables import shared_dir, table  # noqa: F401
from ..sources.tables import stored as settle  # noqa: F401


def slices(batches: Iterator[pa.RecordBatch], text: str, limit: int = 4 << 20) -> Iterator[pa.RecordBatch]:
    """Cut Arrow batches where their texts reach ``limit`` bytes; a longer text comes alone."""
    for batch in batches:
        sizes = pa.compute.fill_null(pa.compute.binary_length(batch.column(text)), 0).to_pylist()
        start = total = 0
        for i, n in enumerate(sizes):
            if total and total + n > limit:
                yield batch.slice(start, i - start)
                start, total = i, 0
            total += n
        if start < len(sizes):
            yield batch.slice(start)


def with_columns(batch: pa.RecordBatch, extra: dict[str, pa.Array], drop: tuple[str, ...] = ()) -> pa.RecordBatch:
    """The batch without ``drop`` and with ``extra``, which replace columns of the same name."""
    kept = [n for n in batch.schema.names if n not in drop and n not in extra]
    return pa.RecordBatch.from_arrays([*(batch.column(n) for n in kept), *extra.values()], [*kept, *extra])


def texts_of(batch: pa.RecordBatch, name: str) -> list[str]:
    """Texts of a column; null is the empty text."""
    return ["" if x is None else x for x in batch.column(name).to_pylist()]


def held_out(doc_id) -> Column:
    """Rows no classifier learns from: crc32 of the id as text leaves 2 modulo 4."""
    return F.coalesce(F.crc32(F.col(doc_id).cast("string").cast("binary")) % 4 == 2, F.lit(False))
