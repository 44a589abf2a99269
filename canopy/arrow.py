"""Helpers for functions that run over Arrow batches."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark import cloudpickle
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import StructType

#: Rows of one output batch, and rows taken as Python objects at a time: whole texts can be long.
ROWS, STEP = 2048, 128


def arrow_map(df: DataFrame, make: Callable[[], Callable], schema: str | StructType) -> DataFrame:
    """``mapInArrow`` whose function gets a list for each input column.

    ``make`` runs once per task and returns a function from lists to an
    iterator of output rows (tuples).
    """
    schema = StructType.fromDDL(schema) if isinstance(schema, str) else schema
    fields = to_arrow_schema(schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        step = make()
        for batch in batches:
            rows: list[tuple] = []
            for part in parts(batch):
                for row in step(*(c.to_pylist() for c in part.columns)):
                    rows.append(row)
                    if len(rows) >= ROWS:
                        yield to_batch(rows, fields)
                        rows = []
            if rows:
                yield to_batch(rows, fields)

    return df.mapInArrow(run, schema)


def parts(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
    return (batch.slice(k, STEP) for k in range(0, batch.num_rows, STEP))


def to_batch(rows: list[tuple], fields: pa.Schema) -> pa.RecordBatch:
    columns = list(zip(*rows)) if rows else [()] * len(fields)
    return pa.RecordBatch.from_arrays([pa.array(list(c), type=f.type) for c, f in zip(columns, fields)], schema=fields)


class Shared:
    """A broadcast of any object of this package; workers need no copy of the package."""

    def __init__(self, spark: SparkSession, value: object):
        self.packed, self.kept = spark.sparkContext.broadcast(cloudpickle.dumps(value)), None

    def __getstate__(self) -> dict:
        return {"packed": self.packed, "kept": None}

    @property
    def value(self):
        if self.kept is None:
            self.kept = (cloudpickle.loads(self.packed.value),)
        return self.kept[0]
