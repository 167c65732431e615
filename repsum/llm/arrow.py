"""Small helpers for operators that work on Arrow batches.

Edge cases: null values are handed over as None and count no bytes; a single row longer than a
slice is a slice of its own; an empty batch or table yields nothing; repeated rows are rows of
their own. Column names are compared as Spark compares them, without regard to case.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator

import pyarrow as pa
import pyarrow.compute  # noqa: F401  (makes pa.compute available)
from pyspark.sql import DataFrame, types as T

#: Text bytes handled at once inside a worker, however many rows a batch holds.
SLICE_BYTES = 4 << 20


def slices(batch: pa.RecordBatch, column: str, limit: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Cut a batch so that each part holds about ``limit`` bytes of ``column``; a longer single row stays whole."""
    sizes = pa.compute.fill_null(pa.compute.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False)
    begin, held = 0, 0
    for i, n in enumerate(sizes.tolist()):
        if held and held + n > limit:
            yield batch.slice(begin, i - begin)
            begin, held = i, 0
        held += n
    if begin < batch.num_rows:
        yield batch.slice(begin)


def add_columns(df: DataFrame, text: str, fields: list[T.StructField], work: Callable[[], Callable[..., dict]], also: str | None = None) -> DataFrame:
    """Append columns computed from one text column, row by row, keeping every other column.

    ``work()`` is called once per task and returns a function from a list of texts (None
    for null) to a dict of equally long value lists. ``also`` names a second column whose
    values are handed over as a second list. A clashing name of the input is overwritten,
    whatever its case; see columns.carry() for a way to keep it.
    """
    names = [f.name for f in fields]
    taken = {n.lower() for n in names}
    kept = [f for f in df.schema.fields if f.name.lower() not in taken]
    schema = T.StructType(kept + fields)
    from pyspark.sql.pandas.types import to_arrow_schema

    arrow = to_arrow_schema(T.StructType(fields))
    keep_names = [f.name for f in kept]

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        step = work()
        for whole in batches:
            for part in slices(whole, text):
                made = step(*(part.column(c).to_pylist() for c in (text, also) if c))
                columns = [part.column(n) for n in keep_names] + [pa.array(made[f.name], type=f.type) for f in arrow]
                yield pa.RecordBatch.from_arrays(columns, names=keep_names + names)
            pa.default_memory_pool().release_unused()

    return df.mapInArrow(run, schema)
