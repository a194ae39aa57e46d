"""Arrow plumbing shared by the document operators."""

from __future__ import annotations

import gc
from collections.abc import Callable, Iterator
from contextlib import contextmanager

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema

SLICE_ROWS = 128
SLICE_BYTES = 8 << 20


def slices(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Cut Arrow batches into pieces of few rows and few bytes (one huge text may exceed the latter alone)."""
    for batch in batches:
        step = SLICE_ROWS
        if batch.num_rows:
            step = max(1, min(SLICE_ROWS, int(SLICE_BYTES * batch.num_rows / max(1, batch.nbytes))))
        for at in range(0, batch.num_rows, step):
            yield batch.slice(at, step)


@contextmanager
def no_cycle_search():
    """Row functions keep large tables without reference cycles; searching those for cycles again and again is wasted time."""
    gc.disable()
    try:
        yield
    finally:
        gc.enable()


def map_text(df: DataFrame, start: Callable[[], Callable], columns: str, id_col: str = "doc_id", text_col: str = "text", together: bool = False) -> DataFrame:
    """Row-wise text operator: ``start()`` runs once per task and gives a function of one whole text, or if ``together`` of a list of whole texts (a slice).

    The result has the id column and the given columns (DDL), in row order; other input columns are not
    read. Ids may be null or repeat: rows are never joined or grouped here.
    """
    out = T.StructType([T.StructField("doc_id", df.schema[id_col].dataType), *T.StructType.fromDDL(columns).fields])
    arrow = to_arrow_schema(out)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        with no_cycle_search():
            one = start()
            for piece in slices(batches):
                texts = piece.column(1).to_pylist()
                made = one(texts) if together else [one(t) for t in texts]
                cols = [piece.column(0).cast(arrow.field(0).type)]
                cols += [pa.array(c, type=arrow.field(k + 1).type) for k, c in enumerate(zip(*made, strict=True))]
                yield pa.RecordBatch.from_arrays(cols, schema=arrow)

    return df.select(df[id_col], df[text_col].cast("string")).mapInArrow(run, out)


def replace_text(df: DataFrame, start: Callable[[], Callable[[str | None], str | None]], text_col: str = "text", length_col: str | None = None) -> DataFrame:
    """Rewrite the text column row by row; every other column passes through as Arrow data.

    ``length_col`` may name a column that gets the length of a text that has changed.
    """
    arrow = to_arrow_schema(df.schema)
    at = df.columns.index(text_col)
    size = df.columns.index(length_col) if length_col else None

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        with no_cycle_search():
            one = start()
            for piece in slices(batches):
                cols = [c.cast(f.type) for c, f in zip(piece.columns, arrow, strict=True)]
                before = piece.column(at).to_pylist()
                after = [one(t) for t in before]
                cols[at] = pa.array(after, type=arrow.field(at).type)
                if size is not None:
                    stated = [n if a == b else len(b) for n, a, b in zip(cols[size].to_pylist(), before, after, strict=True)]
                    cols[size] = pa.array(stated, type=arrow.field(size).type)
                yield pa.RecordBatch.from_arrays(cols, schema=arrow)

    return df.mapInArrow(run, df.schema)
