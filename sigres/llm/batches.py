"""Arrow batches cut by bytes, so a worker's memory does not depend on how long texts are."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame

#: Bytes of text that a worker handles at once; one longer text makes a slice of its own.
SLICE_BYTES = 1 << 20


def slices(batches: Iterator[pa.RecordBatch], text: str, most: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Cut each batch where the bytes of its ``text`` column pass multiples of ``most``."""
    for batch in batches:
        if not batch.num_rows:
            continue
        sizes = pc.fill_null(pc.binary_length(batch.column(text)), 0).to_numpy(zero_copy_only=False)
        block = np.cumsum(sizes, dtype=np.int64) // most
        cuts = [0, *(np.flatnonzero(np.diff(block)) + 1).tolist(), batch.num_rows]
        for a, b in zip(cuts, cuts[1:]):
            if b > a:
                yield batch.slice(a, b - a)


def map_text(df: DataFrame, fn: Callable[[pa.RecordBatch], dict], schema: str, text: str = "text",
             setup: Callable[[], object] | None = None) -> DataFrame:
    """Apply ``fn(slice)`` or, with ``setup``, ``fn(slice, state)``; state is made once a task.

    ``fn`` returns a dict of columns in the order of ``schema``.
    """
    from pyspark.sql.types import _parse_datatype_string
    from pyspark.sql.pandas.types import to_arrow_schema

    arrow = to_arrow_schema(_parse_datatype_string(schema))

    def run(batches):
        state = (setup(),) if setup else ()
        for part in slices(batches, text):
            out = fn(part, *state)
            yield pa.RecordBatch.from_arrays([pa.array(out[f.name], f.type) for f in arrow], schema=arrow)
        # workers stay for later tasks: what this one needed goes back to the machine
        del state
        pa.default_memory_pool().release_unused()

    return df.mapInArrow(run, schema)


def row_counter() -> list[int]:
    """A counter of a task's rows that no other task's counter meets; the same in every rerun."""
    return [TaskContext.get().partitionId() << 40]
