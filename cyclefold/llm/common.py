"""What the corpus operators share: reading tables, Arrow row loops and lineage cuts.

Rules that hold for every operator here:

* only the named input columns are read, so extra columns, also ones whose names equal an
  operator's outputs, never clash;
* a null text counts as the empty text; a null id stays null in the result;
* an empty table gives an empty result with the same schema;
* repeated rows are separate rows unless the operator's docstring says otherwise.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from ..plans.storage import exists, forget, materialise, new_folder, shared_dir

__all__ = ["exists", "forget", "materialise", "new_folder", "per_row", "shared_dir", "slices", "table"]

#: Rows that are turned into Python objects at a time inside one Arrow batch.
SLICE_ROWS = 256


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def slices(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
    for at in range(0, batch.num_rows, SLICE_ROWS):
        yield batch.slice(at, SLICE_ROWS)


def per_row(
    columns: Iterable[str],
    schema: pa.Schema,
    make: Callable[[], Callable[..., Iterable[tuple]]],
) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """A ``mapInArrow`` function: ``make()`` runs once per task and gives ``f(*columns) -> rows``.

    Memory is bounded by one slice of rows and what they yield.
    """
    columns = list(columns)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        f = make()
        for batch in batches:
            for part in slices(batch):
                values = [part.column(part.schema.get_field_index(c)).to_pylist() for c in columns]
                rows = [row for args in zip(*values, strict=True) for row in f(*args)]
                arrays = list(zip(*rows, strict=True)) if rows else [[] for _ in schema]
                yield pa.RecordBatch.from_arrays(
                    [pa.array(a, type=field.type) for a, field in zip(arrays, schema, strict=True)],
                    schema=schema,
                )

    return run
