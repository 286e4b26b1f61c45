"""Row-wise additions to a table by functions over Arrow batches."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StructField, StructType, _parse_datatype_string

from navgraph.session import ship


def fresh(columns: list[str], *names: str) -> list[str]:
    """These names, changed where a table with `columns` has them already."""
    taken, out = {c.lower() for c in columns}, []
    for name in names:
        while name.lower() in taken:
            name = f"_{name}"
        taken.add(name.lower())
        out.append(name)
    return out


def named(column: str) -> Column:
    """A column by its name as it is, dots and all."""
    return F.col("`" + column.replace("`", "``") + "`")


def fields(ddl: str) -> list[StructField]:
    return _parse_datatype_string(ddl).fields


def add_columns(df: DataFrame, ddl: str, make: Callable[[], Callable[[pa.RecordBatch], dict]]) -> DataFrame:
    """`df` with the columns of `ddl`, which replace columns of those names.

    make() runs once in each task and returns a function from a batch to the new columns, as lists or Arrow arrays.
    """
    ship(df.sparkSession)
    new = fields(ddl)
    names = {f.name for f in new}
    keep = [f for f in df.schema.fields if f.name not in names]
    schema = StructType([*keep, *new])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark.sql.pandas.types import to_arrow_schema

        columns, work = to_arrow_schema(StructType(new)), make()
        for batch in batches:
            made = work(batch)
            arrays = [batch.column(batch.schema.get_field_index(f.name)) for f in keep] + [x if isinstance(x := made[f.name], pa.Array) else pa.array(x, f.type) for f in columns]
            yield pa.RecordBatch.from_arrays(arrays, names=[f.name for f in schema])

    return df.mapInArrow(run, schema)
