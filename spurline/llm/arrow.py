"""Small helpers around mapInArrow."""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame

#: Rows of output put into one Arrow batch at most; bounds what a worker holds besides its input batch.
OUT_ROWS = 512


def map_rows(df: DataFrame, columns: list[str], make: Callable[[], Callable[..., Iterable[tuple]]], schema: str) -> DataFrame:
    """``df.select(columns)`` row by row through ``make()(*values)``, which yields output tuples.

    ``make`` runs once per task, on the executor. Other columns of ``df`` are never sent to Python.
    """
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        step, out = make(), []
        for batch in batches:
            for at in range(0, batch.num_rows, OUT_ROWS):
                part = batch.slice(at, OUT_ROWS)
                for row in zip(*(c.to_pylist() for c in part.columns), strict=True):
                    out.extend(step(*row))
                if len(out) >= OUT_ROWS:
                    yield _batch(out, fields)
                    out = []
        if out:
            yield _batch(out, fields)

    fields = _arrow_schema(df, schema)
    return df.select(*columns).mapInArrow(run, schema)


def _batch(rows: list[tuple], fields: pa.Schema) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, type=f.type) for c, f in zip(zip(*rows, strict=True), fields, strict=True)], schema=fields)


def _arrow_schema(df: DataFrame, ddl: str) -> pa.Schema:
    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import StructType

    return to_arrow_schema(StructType.fromDDL(ddl))
