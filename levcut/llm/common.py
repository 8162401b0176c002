"""Shared pieces of the training-data operators."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from levcut.runtime import checkpoint_folder, cut_lineage, ship  # noqa: F401

#: Rows of an Arrow batch that holds whole texts: some MB at usual lengths.
TEXT_ROWS = 1000

#: Byte table: A-Z become a-z, other ASCII that is no digit or letter a space.
WORD_BYTES = bytes(
    (b + 32 if 65 <= b <= 90 else b if b >= 128 or 48 <= b <= 57 or 97 <= b <= 122 else 32) for b in range(256)
)
#: Byte table: A-Z become a-z, nothing else changes.
LOWER_BYTES = bytes((b + 32 if 65 <= b <= 90 else b) for b in range(256))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


_written: list[str] = []


def stored(df: DataFrame) -> DataFrame:
    """The rows, written to the shared checkpoint folder and read again.

    Not checkpoint(): what the optimizer keeps of a checkpoint's plan makes
    unions over several of them fail with columns that are not found.
    drop_stored() deletes what has been written so.
    """
    path = f"{checkpoint_folder(df.sparkSession).rstrip('/')}/stored-{uuid.uuid4().hex}"
    df.write.parquet(path)
    _written.append(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def drop_folder(spark: SparkSession, path: str) -> None:
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)


def drop_stored(spark: SparkSession) -> None:
    """Deletes all stored() tables of this process, once no frame over them is needed."""
    while _written:
        drop_folder(spark, _written.pop())


def text_column(name: str = "text") -> Column:
    """The text as a string; null counts as empty."""
    return F.coalesce(F.col(name).cast("string"), F.lit(""))


def map_arrow(df: DataFrame, function: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]], schema: str | StructType) -> DataFrame:
    """mapInArrow with batches small enough for whole texts."""
    df.sparkSession.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(TEXT_ROWS))
    return df.mapInArrow(function, schema)
