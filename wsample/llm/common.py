"""Helpers shared by the corpus operators."""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator

import pyarrow as pa
import pyarrow.compute
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from wsample.plans.shared import new_path, shared_dir, written

__all__ = ["by_batch", "fitting", "new_path", "release", "shared_dir", "small_enough", "text_of", "unused", "written"]


def release(*tables: DataFrame) -> None:
    """Remove tables that :func:`written` made and nothing reads any more, and let Spark drop shuffle files of plans that are gone."""
    for table in tables:
        jvm = table.sparkSession._jvm
        for file in table.inputFiles()[:1]:
            folder = jvm.org.apache.hadoop.fs.Path(file).getParent()
            folder.getFileSystem(table.sparkSession._jsc.hadoopConfiguration()).delete(folder, True)
    if tables:
        tables[0].sparkSession._jvm.System.gc()


def unused(name: str, taken: Iterable[str]) -> str:
    """The name, with underscores until no column has it (Spark compares without case)."""
    low = {t.lower() for t in taken}
    while name.lower() in low:
        name += "_"
    return name


def text_of(column: str = "text") -> Column:
    """The text, a null being empty."""
    return F.coalesce(F.col(column).cast("string"), F.lit(""))


def fitting(batch: pa.RecordBatch, column: str, limit: int = 8_000_000) -> Iterator[pa.RecordBatch]:
    """Slices of a batch of at most about ``limit`` bytes in a binary or string column (one row at least)."""
    lengths = pa.compute.binary_length(batch.column(column)).fill_null(0).to_numpy(zero_copy_only=False)
    start, total = 0, 0
    for i, n in enumerate(lengths):
        if total and total + n > limit:
            yield batch.slice(start, i - start)
            start, total = i, 0
        total += int(n)
    if start < batch.num_rows:
        yield batch.slice(start)


def by_batch(df: DataFrame, f: Callable[[pa.RecordBatch], Iterator[pa.RecordBatch] | pa.RecordBatch], schema: str, *, size_by: str | None = None) -> DataFrame:
    """mapInArrow with one function a batch, batches being cut by bytes so that long texts stay bounded."""

    def run(batches):
        for batch in batches:
            for part in fitting(batch, size_by) if size_by else [batch]:
                if part.num_rows:
                    made = f(part)
                    if isinstance(made, pa.RecordBatch):
                        yield made
                    else:
                        yield from made

    return df.mapInArrow(run, schema)


def small_enough(df: DataFrame, limit_rows: int) -> bool:
    """Whether a frame has at most that many rows, found without counting beyond them."""
    return df.limit(limit_rows + 1).count() <= limit_rows
