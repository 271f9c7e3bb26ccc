"""Tables in the folder that driver and executors share."""

from __future__ import annotations

import os
import re
import shutil
import site
import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

_written: list[str] = []
_tables: list[str] = []
_folders: dict[str, str] = {}


def shared_dir(spark: SparkSession) -> str:
    """The cluster's spark.checkpoint.dir; only where it is unset on a single machine (tests) a local folder."""
    held = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not held:
        if re.fullmatch(r"local(\[.*\])?", spark.sparkContext.master) is None:
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        app = spark.sparkContext.applicationId
        if app not in _folders:
            _folders[app] = tempfile.mkdtemp(prefix="wingcount-")
        held = _folders[app]
    return held.rstrip("/")


def new_path(spark: SparkSession, name: str) -> str:
    _written.append(path := f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}")
    return path


def written(df: DataFrame, name: str, compression: str = "zstd") -> DataFrame:
    """`df` as a Parquet table in the shared folder: lineage ends there, and a lost executor loses nothing."""
    spark = df.sparkSession
    path = new_path(spark, name)
    df.write.option("compression", compression).parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def settled(df: DataFrame, name: str = "settled") -> DataFrame:
    """A frame that several passes read: a plain scan of files stays as it is, anything else (a view with joins, hashes or JSON) is written once."""
    return df if is_settled(df) else written(df, name)


def is_settled(df: DataFrame) -> bool:
    """Whether `df` is a plain scan of files."""
    plan = df._jdf.queryExecution().optimizedPlan()
    return plan.children().isEmpty() and plan.nodeName().startswith("LogicalRelation")


def bucketed(df: DataFrame, name: str, key: str) -> DataFrame:
    """Like `written`, but in buckets of `key`: a later join or grouping on it leaves these rows where they are."""
    spark = df.sparkSession
    path = new_path(spark, name)
    table = f"{name}_{path.rpartition('-')[2]}"
    _tables.append(table)
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    df.write.option("compression", "zstd").option("path", path).bucketBy(n, key).saveAsTable(table)
    return spark.table(table)


@contextmanager
def shuffles_dropped(spark: SparkSession) -> Iterator[None]:
    """Shuffle files of what is planned and run within go as soon as it has run, instead of when the driver happens to collect its garbage. A frame planned here is for one run."""
    name = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    before = spark.conf.get(name, None)
    spark.conf.set(name, "true")
    try:
        yield
    finally:
        spark.conf.unset(name) if before is None else spark.conf.set(name, before)


def size_of(df: DataFrame) -> int:
    """Bytes of the files that `df` reads, as its plan knows them; a source of unknown size counts nothing."""
    leaves = df._jdf.queryExecution().optimizedPlan().collectLeaves()
    sizes = [int(leaves.apply(k).stats().sizeInBytes()) for k in range(leaves.size())]
    return sum(x for x in sizes if x < 1 << 60)


def drop_written(spark: SparkSession) -> None:
    """Deletes every table that this process wrote; call it once results have been consumed."""
    hadoop = spark.sparkContext._jvm.org.apache.hadoop.fs.Path
    while _tables:
        spark.sql(f"DROP TABLE IF EXISTS {_tables.pop()}")
    while _written:
        path = hadoop(_written.pop())
        path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


_shipped: set[str] = set()


def ship(spark: SparkSession) -> None:
    """Sends this package to the Python workers, unless they find it as the driver does: over PYTHONPATH, an installed package or the working folder."""
    root = Path(__file__).resolve().parent.parent
    seen = [*os.environ.get("PYTHONPATH", "").split(os.pathsep), os.getcwd(), *site.getsitepackages()]
    app = spark.sparkContext.applicationId
    if app in _shipped or root in {Path(p).resolve() for p in seen if p}:
        return
    _shipped.add(app)
    folder = tempfile.mkdtemp(prefix="wingcount-")
    spark.sparkContext.addPyFile(shutil.make_archive(f"{folder}/wingcount", "zip", root, "wingcount"))
