"""Keys with a large share of all rows, found without moving the rows.

Each task counts the keys of runs of its rows and reports those with a share of 1 / ``SHARES`` of the
run or more.  A key whose reports add up to that share of all rows is heavy.  Reports never exceed
the rows there are, so at most ``SHARES`` keys are heavy at any size of input and their list may be
broadcast; a key with twice that share of all rows is always among them, unless it has one row in each
run only.  Heavy keys take a way without an exchange by key, all others the plain way: nothing is dropped.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

SHARES = 5000
#: Rows that a task counts at once.
RUN = 1 << 20


def heavy_keys(table: DataFrame, key: str, rows: int, shares: int = SHARES) -> DataFrame:
    """The heavy keys of a table of so many rows, one column, at most ``shares`` rows."""

    def report(held: list[pa.Array]) -> pa.RecordBatch:
        column = pa.chunked_array(held).combine_chunks()
        counted = column.value_counts()
        often = pc.greater_equal(counted.field("counts"), max(2, -(-len(column) // shares)))
        counted = counted.filter(often)
        return pa.RecordBatch.from_arrays([counted.field("values"), counted.field("counts").cast(pa.int64())], names=[key, "n"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, n = [], 0
        for batch in batches:
            held.append(batch.column(0))
            n += len(batch)
            if n >= RUN:
                yield report(held)
                held, n = [], 0
        if n:
            yield report(held)

    kind = dict(table.dtypes)[key]
    reported = table.select(key).where(F.col(key).isNotNull()).mapInArrow(run, f"{key} {'long' if kind == 'bigint' else kind}, n long")
    return reported.groupBy(key).agg(F.sum("n").alias("n")).where(F.col("n") >= max(2, -(-rows // shares))).select(key)
