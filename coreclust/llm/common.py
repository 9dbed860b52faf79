"""Helpers shared by the corpus operators: reading, shared intermediate tables, text bytes."""

from __future__ import annotations

import os
import tempfile
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from ..sources.tables import spread
from ..storage import Scratch, shared_dir

__all__ = ["Scratch", "shared_dir"]

#: ASCII A-Z to a-z on UTF-8 bytes; every other byte stays.
LOWER = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))
#: Keeps the bytes of words made of digits, letters a-z and non-ASCII characters; all else becomes a space.
ALNUM_WORDS = bytes(LOWER[c] if 48 <= c <= 57 or 97 <= LOWER[c] <= 122 or c >= 128 else 32 for c in range(256))
#: Rows that are turned into Python objects at a time.
SLICE = 256


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return spread(df) if name in ("documents", "pages") else df


def encode(text: str | None) -> bytes:
    return b"" if text is None else text.encode("utf-8", "surrogatepass")


def slices(batches: Iterator[pa.RecordBatch], rows: int = SLICE) -> Iterator[list[list]]:
    """The batches' columns as Python lists, a bounded number of rows at a time."""
    for batch in batches:
        for at in range(0, batch.num_rows, rows):
            yield [c.to_pylist() for c in batch.slice(at, rows).columns]


def map_rows(df: DataFrame, make: Callable[[], Callable[..., dict]], schema: str) -> DataFrame:
    """mapInArrow around a function from column lists to a dict of output columns.

    `make` runs once per task and returns that function, so tables it needs are set up once.
    """
    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import _parse_datatype_string

    arrow = to_arrow_schema(_parse_datatype_string(schema))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        f = make()
        for cols in slices(batches):
            yield pa.RecordBatch.from_pydict(f(*cols), schema=arrow)

    return df.mapInArrow(run, schema)


def extend_rows(df: DataFrame, columns: list[str], make: Callable[[], Callable[..., dict]], extra: str) -> DataFrame:
    """Like `map_rows`, but every column of `df` stays and those of `extra` are added."""
    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import StructType, _parse_datatype_string

    more = _parse_datatype_string(extra)
    added = to_arrow_schema(more)
    where = [df.columns.index(c) for c in columns]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        f = make()
        for batch in batches:
            for at in range(0, batch.num_rows, SLICE):
                part = batch.slice(at, SLICE)
                got = f(*(part.column(k).to_pylist() for k in where))
                new = [pa.array(got[x.name], x.type) for x in added]
                yield pa.RecordBatch.from_arrays([*part.columns, *new], [*part.schema.names, *added.names])

    return df.mapInArrow(run, StructType([*df.schema.fields, *more.fields]))


def ragged(starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """Positions start, start+1, ... for each (start, length), one after the other."""
    total = int(lengths.sum())
    if not total:
        return np.zeros(0, np.int64)
    ends = np.cumsum(lengths)
    return np.repeat(starts - (ends - lengths), lengths) + np.arange(total)


def tokenizer_path(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def default_parallelism(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def ensure_file_dir() -> str:
    """A folder of this task's own for memory-mapped arrays; removed by its user before the task ends."""
    return tempfile.mkdtemp(prefix="map-", dir=os.environ.get("TMPDIR") or None)
