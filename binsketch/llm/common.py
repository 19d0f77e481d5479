"""Helpers that all operators of this folder share."""

from __future__ import annotations

import contextlib
import ctypes
from collections.abc import Callable, Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from ..tables import fresh_path, scratch, shared_dir, written

__all__ = ["as_array", "claim", "free_name", "fresh_path", "map_batches", "parts_for", "scratch", "shared_dir", "table", "texts_of", "tidy", "written"]

MOST_BYTES = 8_000_000  # of a batch that is worked on at once; a longer text is alone in it


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A given table, read by Spark only, so that any store works."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def free_name(name: str, taken: list[str]) -> str:
    """``name``, or a longer one, that no column bears in whatever letters."""
    low = {t.lower() for t in taken}
    while name.lower() in low:
        name = f"_{name}"
    return name


def parts_for(df: DataFrame, times: float = 1.0, each: int = 128 << 20) -> int:
    """How many partitions a shuffle of about ``times`` the bytes of ``df`` needs (by the scan's size; where that is unknown, and
    as the least, the session's number)."""
    size = int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    least = max(int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")), 1)
    return least if size >= 1 << 60 else max(least, min(int(size * times) // each + 1, 1_000_000))


def map_batches(df: DataFrame, f: Callable[[pa.RecordBatch], Iterable[dict]], schema: str) -> DataFrame:
    """``f`` gives column dictionaries for each Arrow batch, cut to some rows and bytes; nothing is held between batches."""
    from pyspark.sql.pandas.types import to_arrow_schema
    from pyspark.sql.types import _parse_datatype_string

    out = to_arrow_schema(_parse_datatype_string(schema))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = max(1, min(1024, batch.num_rows * MOST_BYTES // max(batch.nbytes, 1)))
            for part in (batch.slice(i, rows) for i in range(0, batch.num_rows, rows)):
                for cols in f(part):
                    yield pa.RecordBatch.from_arrays([as_array(cols[x.name], x.type) for x in out], schema=out)

    return df.mapInArrow(tidy(run), schema)


def as_array(values, kind: pa.DataType) -> pa.Array:
    if isinstance(values, pa.Array):
        return values if values.type == kind else values.cast(kind)
    return pa.array(values, type=kind)


def texts_of(batch: pa.RecordBatch, name: str = "text") -> list[str]:
    """Texts of a batch; null counts as empty."""
    return ["" if t is None else t for t in batch.column(name).to_pylist()]


_memos: dict[str, Callable[[], None]] = {}
_owner: str | None = None


def claim(owner: str, forget: Callable[[], None] | None = None) -> None:
    """What an operator remembers in a worker goes (``forget``) when another one starts there: workers serve many stages."""
    global _owner
    if owner == _owner:
        return
    for name, f in _memos.items():
        if name != owner:
            f()
    trim()
    _owner = owner
    if forget:
        _memos[owner] = forget


def trim() -> None:
    """Give memory that is free within the process back to the machine: idle workers stay beside busy ones."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):  # where the C library has it
        ctypes.CDLL(None).malloc_trim(0)


def tidy(f: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """``f``, with memory given back at the end of the task."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from f(batches)
        trim()

    return run
