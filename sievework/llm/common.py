"""Shared plumbing of the training-data operators: staged tables, table readers, Arrow batch loops."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..plans.staging import shared_dir, stage
from ..sources.tables import load as table

__all__ = ["held_out", "map_arrow", "shared_dir", "stage", "table", "unused", "with_score"]

#: Rows of one inner batch; bounds what a Python worker holds beside the Arrow batch that Spark sends.
INNER_ROWS = 512


def unused(df: DataFrame, *names: str) -> list[str]:
    """``names``, each with underscores in front until no column of ``df`` is called so."""
    taken, out = {c.lower() for c in df.columns}, []
    for name in names:
        while name.lower() in taken:
            name = f"_{name}"
        out.append(name)
    return out


def map_arrow(
    df: DataFrame, make: Callable[[], Callable[[pa.RecordBatch], pa.RecordBatch]], schema
) -> DataFrame:
    """``mapInArrow`` in inner batches of ``INNER_ROWS``; ``make()`` builds the row-wise function once per task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fn = make()
        for batch in batches:
            for at in range(0, batch.num_rows, INNER_ROWS):
                yield fn(batch.slice(at, INNER_ROWS))

    return df.mapInArrow(run, schema)


def with_score(df: DataFrame, text_col: str, make: Callable, name: str) -> DataFrame:
    """Append a double column from a text column; all other columns pass through Python untouched.

    ``make()`` returns list-of-texts -> list-of-floats. A column already called ``name`` is replaced.
    """
    df = df.drop(name)
    schema = T.StructType([*df.schema.fields, T.StructField(name, T.DoubleType())])

    def build():
        fn = make()

        def one(batch: pa.RecordBatch) -> pa.RecordBatch:
            texts = batch.column(batch.schema.get_field_index(text_col)).to_pylist()
            return pa.RecordBatch.from_arrays(
                [*batch.columns, pa.array(fn(texts), pa.float64())], [*batch.schema.names, name]
            )

        return one

    return map_arrow(df, build, schema)


def held_out(id_col: str, mod: int, rest: int):
    """Whether crc32 of the id as text leaves ``rest`` modulo ``mod``; a null id is never held out."""
    return F.coalesce(F.crc32(F.col(id_col).cast("string")) % mod == rest, F.lit(False))
