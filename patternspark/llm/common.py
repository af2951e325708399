"""Helpers that the corpus operators share."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable, Iterator
from contextlib import contextmanager

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
_own_dir: list[str] = []


def shared_dir(spark: SparkSession) -> str:
    """Folder that driver and executors share: ``spark.checkpoint.dir``, or one of our own if unset (local runs)."""
    at = spark.conf.get("spark.checkpoint.dir", None)
    if at:
        return at.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("spark.checkpoint.dir must name a folder that driver and executors share")
    if not _own_dir:
        _own_dir.append("file://" + tempfile.mkdtemp(prefix="patternspark-"))
    return _own_dir[0]


def cut(df: DataFrame, tag: str, within: str | None = None) -> DataFrame:
    """Write ``df`` to the shared folder (or a folder of ``scratch``) and read it back: ends the lineage, survives lost executors."""
    spark = df.sparkSession
    path = f"{within or shared_dir(spark) + '/patternspark'}/{tag}-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


@contextmanager
def scratch(spark: SparkSession) -> Iterator[str]:
    """A folder in the shared one for tables that nothing needs after the block; it is removed at its end."""
    path = f"{shared_dir(spark)}/patternspark/scratch-{uuid.uuid4().hex}"
    try:
        yield path
    finally:
        at = spark._jvm.org.apache.hadoop.fs.Path(path)
        at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)


def ascii_lower(c: Column) -> Column:
    """Lower-case A-Z only. Pure ASCII takes the fast built-in; other texts keep their accented capitals."""
    return F.when(F.octet_length(c) == F.char_length(c), F.lower(c)).otherwise(F.translate(c, UPPER, UPPER.lower()))


def ascii_lower_py(text: str) -> str:
    return text.lower() if text.isascii() else text.translate(_LOWER)


_LOWER = {ord(a): a.lower() for a in UPPER}


#: Rows and bytes of text that Python code takes at a time; one row may be longer.
SLICE_ROWS, SLICE_BYTES = 1024, 1 << 20


def slices(batch: pa.RecordBatch, at: int, rows: int = SLICE_ROWS, size: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Parts of a batch whose texts (column ``at``) take a bounded part of memory, in order; no row is cut."""
    ends = np.cumsum(pc.fill_null(pc.binary_length(batch.column(at)), 0).to_numpy(zero_copy_only=False).astype(np.int64))
    lo, done = 0, 0
    while lo < batch.num_rows:
        hi = min(max(lo + 1, int(np.searchsorted(ends, done + size, side="right"))), lo + rows, batch.num_rows)
        yield batch.slice(lo, hi - lo)
        lo, done = hi, int(ends[hi - 1])


def quoted(name: str) -> Column:
    """A column by its plain name, dots and back-ticks included."""
    return F.col("`" + name.replace("`", "``") + "`")


def add_columns(docs: DataFrame, make: Callable[[], Callable[[list], list[pa.Array]]], fields: list[tuple[str, T.DataType]], *, text_col: str, keep: list[str]) -> DataFrame:
    """The columns ``keep`` and what ``make()`` (called once a task) gives for slices of the texts.

    Names of the input cannot clash on the way: columns travel by position, and the text only once.
    """
    inner = [f"c{i}" for i in range(len(keep))]
    at = keep.index(text_col) if text_col in keep else len(keep)
    plain = docs.select(*[quoted(c).alias(i) for c, i in zip(keep, inner)], *([quoted(text_col).alias("text")] if at == len(keep) else []))
    names = [*inner, *[f"n{i}" for i in range(len(fields))]]
    schema = T.StructType([*plain.schema.fields[:len(keep)], *[T.StructField(f"n{i}", kind) for i, (_, kind) in enumerate(fields)]])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        work = make()
        for whole in batches:
            for b in slices(whole, at):
                yield pa.RecordBatch.from_arrays([*b.columns[:len(inner)], *work(b.column(at).to_pylist())], names=names)

    return plain.mapInArrow(run, schema).toDF(*keep, *[name for name, _ in fields])
