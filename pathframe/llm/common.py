"""Helpers shared by the operators: table access, in-row bindings, byte-bounded Arrow chunks, checkpoints."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterable, Iterator
from contextlib import contextmanager
from contextvars import ContextVar

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.shared import checkpointed, shared_top

#: A-Z and a-z, the only letters that the contracts fold.
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """body(value) with value computed once for the row, however often body uses it."""
    return F.transform(F.array(value), body)[0]


def running(values: Column, how: str, block: int = 512) -> Column:
    """Running sum, max or min of an int array, in blocks: a fold that appends copies what it has, so it is kept short."""
    put = {"sum": lambda a, v: a + v, "max": F.greatest, "min": F.least}[how]

    def folded(own: Column) -> Column:
        start = own[0] if how != "sum" else F.lit(0)
        step = lambda s, v: F.struct(put(s["at"], v).alias("at"), F.concat(s["out"], F.array(put(s["at"], v))).alias("out"))
        return F.aggregate(own, F.struct(start.cast("int").alias("at"), F.array().cast("array<int>").alias("out")), step, lambda s: s["out"])

    def joined(blocks: Column) -> Column:
        last = folded(F.transform(blocks, lambda b: F.element_at(b, -1)))
        return F.when(F.size(blocks) == 1, blocks[0]).otherwise(let(last, lambda ends: F.flatten(F.transform(blocks, lambda b, k: F.transform(b, lambda v: F.when(k > 0, put(F.get(ends, k - 1), v)).otherwise(v))))))

    cut = lambda own: F.transform(F.sequence(F.lit(0), F.floor((F.size(own) - 1) / block).cast("int")), lambda k: folded(F.slice(own, k * block + 1, F.lit(block))))
    return let(values, lambda own: F.when(F.size(own) == 0, F.array().cast("array<int>")).otherwise(let(cut(own), joined)))


def quoted(column: str) -> str:
    return "`" + column.replace("`", "``") + "`"


def free_name(df: DataFrame, stem: str) -> str:
    """A column name that df doesn't have, in any case of letters."""
    taken = {c.lower() for c in df.columns}
    while stem in taken:
        stem += "_"
    return stem


def ascii_lower(text: Column) -> Column:
    """A-Z only; lower() would also fold letters such as the Kelvin sign into a-z."""
    return F.translate(text, UPPER, LOWER)


def arrow_bounded(df: DataFrame, most_bytes: int = 8 << 20) -> DataFrame:
    """df as it is, with Arrow batches of its session bounded in bytes, not rows alone, so that long texts don't add up.
    The bound is a setting that sessions may change at any time; a session that has set one keeps it, whatever it is."""
    key = "spark.sql.execution.arrow.maxBytesPerBatch"
    if not df.sparkSession._jsparkSession.sessionState().conf().contains(key):
        df.sparkSession.conf.set(key, str(most_bytes))
    return df


def chunks(batch: pa.RecordBatch, column: str, most_bytes: int = 4 << 20) -> Iterator[pa.RecordBatch]:
    """Slices of a batch whose text takes about most_bytes, one row at least, so memory follows the bytes of text."""
    sizes = pc.binary_length(batch.column(column)).fill_null(0).to_numpy(zero_copy_only=False)
    start = total = 0
    for i, n in enumerate(sizes):
        if i > start and total + n > most_bytes:
            yield batch.slice(start, i - start)
            start, total = i, 0
        total += int(n)
    if start < len(sizes):
        yield batch.slice(start)
    pa.default_memory_pool().release_unused()  # a worker that waits for its next batch holds no spare memory


settle = checkpointed
#: Folders written inside `writing()`, by nesting; none outside of it.
_WRITTEN: ContextVar[list[str] | None] = ContextVar("written", default=None)


def shared_folder(spark: SparkSession, name: str) -> str:
    """A new folder beside the session's checkpoints, for tables that executors write and read."""
    path = f"{shared_top(spark)}/{name}-{uuid.uuid4().hex}"
    if (held := _WRITTEN.get()) is not None:
        held.append(path)
    return path


def stored(df: DataFrame, name: str) -> DataFrame:
    """df written as Parquet in the shared folder and read again: lineage is cut and later reads take only their columns."""
    path = shared_folder(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


@contextmanager
def writing() -> Iterator[list[str]]:
    """The folders that are written inside, for removed() when what is read from them is written elsewhere."""
    held: list[str] = []
    before = _WRITTEN.set(held)
    try:
        yield held
    finally:
        _WRITTEN.reset(before)


def removed(spark: SparkSession, folders: Iterable[str]) -> None:
    jvm, conf = spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration()
    for folder in folders:
        path = jvm.org.apache.hadoop.fs.Path(folder)
        path.getFileSystem(conf).delete(path, True)
