"""Adds a struct column that is computed from one text column, batch by batch, with all other columns passed through."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_schema


def with_struct(df: DataFrame, column: str, output: str, ddl: str, make: Callable[[], Callable[[list], list]], rows: int = 256) -> DataFrame:
    """`make` runs once in each task and gives the function from values of `column` to one tuple each, or to one Arrow array for each field.

    A column that is named like the output is replaced. At most `rows` rows are held as Python objects at a time. If the function has
    an attribute `done`, that is called when the task ends, so that an idle worker holds nothing.
    """
    df = df.drop(output)
    out = T.StructType([*df.schema.fields, T.StructField(output, T._parse_datatype_string(ddl))])
    schema = to_arrow_schema(out)
    kind = schema.field(output).type
    names = [f.name for f in kind]

    def run(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        work = make()
        try:
            for whole in it:
                at = whole.schema.get_field_index(column)
                for i in range(0, whole.num_rows, rows):
                    batch = whole.slice(i, rows)
                    made = work(batch.column(at).to_pylist())
                    fields = made if isinstance(made[0], pa.Array) else [pa.array(list(x), f.type) for x, f in zip(zip(*made, strict=True), kind, strict=True)]
                    yield pa.RecordBatch.from_arrays([*batch.columns, pa.StructArray.from_arrays(fields, names=names)], schema=schema)
        finally:
            getattr(work, "done", lambda: None)()

    return df.mapInArrow(run, out)
