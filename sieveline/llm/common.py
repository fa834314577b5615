"""Small helpers shared by the training-data operators.

Words are maximal runs of characters other than U+0020 and U+0009 to U+000D, which
is what ``bytes.split()`` cuts out in Python and what :func:`words` does in Catalyst.
"""

from __future__ import annotations

from collections.abc import Callable

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..store import cut, scratch  # noqa: F401

#: ASCII white space beside the blank.
WHITE = ["\t", "\n", "\x0b", "\x0c", "\r"]
#: Most rows that an Arrow function gets, and so returns, at once.
STEP_ROWS = 1_000


def release() -> None:
    """Hand memory that the allocators hold back to the system."""
    for pool in (pa.default_memory_pool(), pa.system_memory_pool()):
        pool.release_unused()


def small_batches(spark: SparkSession) -> None:
    """Have the session send batches of at most :data:`STEP_ROWS` rows to Arrow functions.

    Several Arrow stages that follow each other on the same executors otherwise leave
    buffers of whole default batches behind. A smaller setting of the session stays.
    """
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(spark.conf.get(key)) <= STEP_ROWS:
        spark.conf.set(key, str(STEP_ROWS))


def stepwise(run: Callable) -> Callable:
    """An Arrow function that works in small steps and keeps no freed memory.

    Workers stay with their executor between stages, so that what one of them still holds
    adds to the memory of the stages that follow.
    """

    def steps(batches):
        def parts():
            for batch in batches:
                for at in range(0, batch.num_rows, STEP_ROWS):
                    yield batch.slice(at, STEP_ROWS)
                del batch
                release()

        yield from run(parts())
        release()

    return steps


def packed(text: Column) -> Column:
    """A text compressed by itself, its length in bytes before it; null stays null."""

    @F.arrow_udf("binary")
    def pack(texts: pa.Array) -> pa.Array:
        codec = pa.Codec("zstd")
        out = [None if t is None else len(t).to_bytes(8, "little") + codec.compress(t, asbytes=True) for t in texts.cast(pa.large_binary()).to_pylist()]
        release()
        return pa.array(out, pa.binary())

    return pack(text)


def unpacked(data: Column) -> Column:
    """The text that :func:`packed` has compressed."""

    @F.arrow_udf("string")
    def unpack(data: pa.Array) -> pa.Array:
        codec = pa.Codec("zstd")
        out = [None if x is None else codec.decompress(x[8:], int.from_bytes(x[:8], "little"), asbytes=True) for x in data.to_pylist()]
        release()
        return pa.array(out, pa.binary()).cast(pa.string())

    return unpack(data)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def blanks(text: Column) -> Column:
    """Text whose white space is all U+0020 (null: empty)."""
    out = F.coalesce(text, F.lit(""))
    for c in WHITE:
        out = F.replace(out, F.lit(c), F.lit(" "))
    return out


def words(text: Column) -> Column:
    """Array of the words of a text; empty for null."""
    return F.array_remove(F.split(blanks(text), " "), "")
