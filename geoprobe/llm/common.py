"""Helpers shared by the corpus operators: Arrow batch mapping, shared-folder checkpoints, hashing."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import checkpointed, shared_folder, spread, swept, tables_written, workers_can_import

__all__ = ["as_binary", "checkpointed", "digest_of", "held_out", "load", "map_text", "shared_folder", "slices", "spread", "swept", "tables_written", "unused", "workers_can_import"]

#: A Python worker handles about this many text bytes at a time, whatever the Arrow batch size.
SLICE_BYTES = 2 << 20


def as_binary(column: pa.Array) -> list[bytes]:
    """The UTF-8 bytes of a string or binary column; null is empty."""
    kind = pa.large_binary() if pa.types.is_large_string(column.type) else pa.binary()
    return [x or b"" for x in column.cast(kind).to_pylist()]


def slices(batch: pa.RecordBatch, column: str, limit: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Cut a batch into runs of rows of about `limit` bytes in `column` (a longer single row stays whole)."""
    sizes = pc.binary_length(batch.column(column)).fill_null(0).to_pylist()
    start = held = 0
    for i, size in enumerate(sizes):
        if i > start and held + size > limit:
            yield batch.slice(start, i - start)
            start, held = i, 0
        held += size
    if batch.num_rows > start:
        yield batch.slice(start)


def map_text(df: DataFrame, fn: Callable[[pa.RecordBatch], dict], schema: str, column: str = "text", limit: int = SLICE_BYTES) -> DataFrame:
    """Apply `fn` (batch -> columns by name) to runs of rows; narrow, no shuffle, memory bounded by `limit`."""
    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import _parse_datatype_string

    workers_can_import(df.sparkSession)
    arrow = to_arrow_schema(_parse_datatype_string(schema))

    def run(batches):
        for batch in batches:
            for part in slices(batch, column, limit):
                made = fn(part)
                yield pa.RecordBatch.from_arrays([pa.array(made[f.name], type=f.type) for f in arrow], schema=arrow)

    return df.mapInArrow(run, schema)


def load(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    """Columns of a given table; wide rows of a small file are dealt to all cores."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    df = df.select(*columns) if columns else df
    return spread(df) if {"text", "html"} & set(columns) and name in ("documents", "pages") else df


def unused(df: DataFrame, *names: str) -> list[str]:
    """The names, lengthened until no column of `df` has them."""
    taken = {c.lower() for c in df.columns}
    out = []
    for name in names:
        while name.lower() in taken:
            name += "_"
        taken.add(name.lower())
        out.append(name)
    return out


def digest_of(ids) -> F.Column:
    """Lowercase SHA-256 of an array of strings joined by commas."""
    return F.sha2(F.concat_ws(",", ids), 256)


def held_out(doc_id) -> F.Column:
    """The fixed test fold: CRC-32 of the id as text leaves 2 modulo 4."""
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit("")).cast("binary")) % 4 == 2
