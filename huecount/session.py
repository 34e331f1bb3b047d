"""Sessions, and cutting lineage through tables in a folder that the whole cluster shares."""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession


def local_session(cores: int | str = 8, name: str = "huecount") -> SparkSession:
    """A session for tests and benchmarks on one machine."""
    return (
        SparkSession.builder.master(f"local[{cores}]")
        .appName(name)
        .config("spark.sql.shuffle.partitions", str(cores) if str(cores).isdigit() else "8")
        .config("spark.sql.adaptive.enabled", "true")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.driver.memory", "8g")
        .getOrCreate()
    )


def shared_dir(spark: SparkSession) -> str:
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    if spark.sparkContext.master.startswith("local"):
        return "file:///tmp/checkpoints"
    raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")


#: Folders that this process has made, in order, for release() to remove.
_MADE: list[str] = []


def fresh_dir(spark: SparkSession, name: str) -> str:
    """A new name in the shared folder. Whoever reads what is written there last may release it."""
    path = f"{shared_dir(spark)}/huecount-{name}-{uuid.uuid4().hex}"
    _MADE.append(path)
    return path


#: Spark removes the shuffle files of a query once it has run.
SWEEP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


@contextmanager
def swept(spark: SparkSession) -> Iterator[None]:
    """Shuffle files of what is run inside are removed when it has run, not when the driver collects garbage. For results that are
    written or told: a frame that is run a second time shuffles again."""
    before = spark.conf.get(SWEEP, None)
    spark.conf.set(SWEEP, "true")
    try:
        yield
    finally:
        spark.conf.unset(SWEEP) if before is None else spark.conf.set(SWEEP, before)


def cut(df: DataFrame, name: str = "table", partition_by: tuple[str, ...] = (), compression: str = "snappy") -> DataFrame:
    """Write df to the shared folder and read it again: later stages neither recompute it nor depend on the
    executors that made it. partition_by: hash-partition rows for the join that reads them next."""
    spark, path = df.sparkSession, fresh_dir(df.sparkSession, name)
    with swept(spark):
        (df.repartition(*partition_by) if partition_by else df).write.option("compression", compression).parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def made() -> int:
    """How many folders have been made so far: a mark for release()."""
    return len(_MADE)


def release(spark: SparkSession, since: int = 0, keep: tuple[str, ...] = ()) -> int:
    """Remove the folders made since a mark, but for some; return their number. For results that are read no
    more: a table that still depends on them can be read no longer."""
    gone = [p for p in _MADE[since:] if p not in keep]
    _MADE[since:] = [p for p in _MADE[since:] if p in keep]
    for p in gone:
        remove(spark, p)
    return len(gone)


def remove(spark: SparkSession, path: str) -> None:
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)


def settle(df: DataFrame, name: str, since: int) -> DataFrame:
    """Write df, then remove all that has been made since a mark: the result needs nothing else."""
    out = cut(df, name)
    release(df.sparkSession, since, (_MADE[-1],))
    return out
