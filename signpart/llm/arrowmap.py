"""Building the output batches of Arrow map stages."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T


#: Rows and bytes of the batches that Python workers take; the least of these and the session's own values holds.
BATCH_ROWS, BATCH_BYTES = 2000, 4 << 20


def arrow_map(df: DataFrame, run: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]], schema: T.StructType | str) -> DataFrame:
    """mapInArrow with batches small enough for whole texts: long rows otherwise make batches of any size."""
    conf = df.sparkSession.conf
    for key, most in (("spark.sql.execution.arrow.maxRecordsPerBatch", BATCH_ROWS), ("spark.sql.execution.arrow.maxBytesPerBatch", BATCH_BYTES)):
        now = int(conf.get(key).rstrip("b"))
        if now <= 0 or now > most:
            conf.set(key, str(most))
    return df.mapInArrow(run, schema)


def with_columns(df: DataFrame, columns: dict[str, T.DataType], make: Callable[[pa.RecordBatch], dict], keep: list[str] | None = None) -> DataFrame:
    """df with columns that ``make`` computes for each batch; columns of the same names (in any case) are replaced in place."""
    names = keep if keep is not None else df.columns
    lower = {c.lower() for c in columns}
    rest = [f for f in df.schema.fields if f.name in names and f.name.lower() not in lower]
    schema = T.StructType([*rest, *(T.StructField(k, v) for k, v in columns.items())])
    out_names = [f.name for f in schema.fields]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                made = make(batch)
                at = {n: i for i, n in enumerate(batch.schema.names)}
                yield pa.RecordBatch.from_arrays([made[n] if n in made else batch.column(at[n]) for n in out_names], names=out_names)

    return arrow_map(df, run, schema)
