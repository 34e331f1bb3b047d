"""What the operators of this package share: reading, cutting lineage, sizes."""

from __future__ import annotations

from collections.abc import Iterator
from contextlib import contextmanager

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from huecount.session import cut, fresh_dir, made, release, remove, settle  # noqa: F401 (the operators take them from here)

#: A word is a run of anything but these six ASCII white-space characters.
WORD = r"[^\x20\x09-\x0D]+"
#: What a Python worker takes on at a time. An Arrow batch holds up to 64 MB, by Spark's own bound.
SLICE_ROWS, SLICE_CHARS = 256, 1 << 21


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


@contextmanager
def small_batches(spark: SparkSession) -> Iterator[None]:
    """Arrow batches of SLICE_ROWS rows for what is written meanwhile; the session's own setting comes back."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(name)
    spark.conf.set(name, str(SLICE_ROWS))
    try:
        yield
    finally:
        spark.conf.set(name, before)


def cut_texts(df: DataFrame, name: str, compression: str = "snappy") -> DataFrame:
    """``cut`` for what Python workers make of whole texts: a worker and its feeder hold few of them at a time."""
    with small_batches(df.sparkSession):
        return cut(df, name, compression=compression)


def slices(batches: Iterator[pd.DataFrame], column: str = "text") -> Iterator[pd.DataFrame]:
    """The rows of all batches in frames of SLICE_ROWS rows and about SLICE_CHARS characters of the column at
    most; a longer text is a frame of its own."""
    for batch in batches:
        size = batch[column].str.len().fillna(0).to_numpy() if len(batch) else ()
        at = held = 0
        for i, n in enumerate(size):
            if i > at and (i - at == SLICE_ROWS or held + n > SLICE_CHARS):
                yield batch.iloc[at:i].reset_index(drop=True)
                at, held = i, 0
            held += n
        if at < len(batch):
            yield batch.iloc[at:].reset_index(drop=True)


def n_words(text: Column) -> Column:
    """Number of words of a text; 0 for null."""
    return F.coalesce(F.size(F.regexp_extract_all(text, F.lit(WORD), F.lit(0))), F.lit(0)).cast("long")


def hash_hex(*parts: Column | str) -> Column:
    """An order that any SQL engine can repeat: md5 of the parts as text."""
    cols = [F.coalesce((F.lit(p) if isinstance(p, str) else p).cast("string"), F.lit("~")) for p in parts]
    return F.md5(F.concat_ws("|", *cols).cast("binary"))
