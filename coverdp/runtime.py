"""What every operator needs from the session: shared folders, table readers, code on executors."""

from __future__ import annotations

import gc
import tempfile
import uuid
import zipfile
from collections.abc import Callable, Iterator
from contextlib import contextmanager
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

_SHIPPED: set[str] = set()
#: The tables written within each scratch() that is open, and the folders of all.
_OPEN: list[list[str]] = []


def ship(spark: SparkSession) -> None:
    """Send this package to the executors once per application, for clusters where it isn't installed."""
    sc = spark.sparkContext
    if sc.applicationId in _SHIPPED:
        return
    root = Path(__file__).resolve().parent
    target = Path(tempfile.mkdtemp(prefix="coverdp-")) / "coverdp_code.zip"
    with zipfile.ZipFile(target, "w") as z:
        for p in sorted(root.rglob("*.py")):
            z.write(p, p.relative_to(root.parent))
    sc.addPyFile(str(target))
    _SHIPPED.add(sc.applicationId)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables, by any path that Spark's readers open."""
    ship(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_folder(spark: SparkSession) -> str:
    """The folder that the driver and all executors share: spark.checkpoint.dir, or one of our own where it's unset."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if found:
        return found.rstrip("/")
    context = spark.sparkContext._jsc.sc()
    if not context.getCheckpointDir().isDefined():
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="coverdp-checkpoints-"))
    return context.getCheckpointDir().get()


def materialise(df: DataFrame) -> DataFrame:
    """Write a table into the shared folder and read it back: lineage ends here, and lost executors cost nothing."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/coverdp-{uuid.uuid4().hex}"
    df.write.parquet(path)
    if _OPEN:
        _OPEN[-1].append(path)
    out = spark.read.schema(df.schema).parquet(path)
    out.written_to = path
    return out


def remove(spark: SparkSession, *paths: str) -> None:
    """Delete folders that nothing reads any more."""
    for path in paths:
        p = spark._jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


def tidy(any_table: DataFrame) -> None:
    """Let Spark drop the shuffle files that nothing refers to any more: its cleaner follows the driver's collector, which may not run for half an hour."""
    gc.collect()
    any_table.sparkSession._jvm.System.gc()


def release(*tables: DataFrame) -> None:
    """Delete tables that materialise() wrote, once nothing reads them any more."""
    remove(tables[0].sparkSession, *{f.rpartition("/")[0] for t in tables for f in t.inputFiles()})
    tidy(tables[0])


@contextmanager
def scratch(spark: SparkSession) -> Iterator[Callable[[DataFrame], DataFrame]]:
    """Tables that materialise() writes within are deleted at its end, but for those that went through the function it gives."""
    kept: set[str] = set()

    def keep(written: DataFrame) -> DataFrame:
        kept.add(written.written_to)
        return written

    _OPEN.append([])
    try:
        yield keep
    finally:
        own = _OPEN.pop()
        if _OPEN:
            _OPEN[-1].extend(x for x in own if x in kept)
        remove(spark, *(x for x in own if x not in kept))
        tidy(spark.range(1))


def is_empty(df: DataFrame) -> bool:
    return not df.take(1)
