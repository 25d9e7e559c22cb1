"""Running a kernel over the strings of Arrow batches, in output pieces of bounded size."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame

from phrasework.schemas import names

#: Rows of one output batch.
OUT_ROWS = 1 << 16

ARROW = {"string": pa.string(), "bigint": pa.int64(), "int": pa.int32(), "double": pa.float64(), "boolean": pa.bool_()}


def arrow_schema(schema: str) -> pa.Schema:
    return pa.schema([(part.split()[0], ARROW[part.split()[1]]) for part in schema.split(", ")])


def map_strings(S: DataFrame, schema: str, kernel: Callable[[str, str], Iterator[tuple]]) -> DataFrame:
    """Rows that ``kernel(string_id, text)`` yields for every string; null texts give none."""
    fields = names(schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out_schema = arrow_schema(schema)
        held: list[tuple] = []

        def flush() -> pa.RecordBatch:
            columns = list(zip(*held)) if held else [[] for _ in fields]
            batch = pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(columns, out_schema)], schema=out_schema)
            held.clear()
            return batch

        for batch in batches:
            for key, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                if text is None:
                    continue
                for row in kernel(key, text):
                    held.append(row)
                    if len(held) >= OUT_ROWS:
                        yield flush()
        if held:
            yield flush()

    return S.select("string_id", "text").mapInArrow(run, schema)
