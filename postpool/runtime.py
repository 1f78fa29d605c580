"""Where intermediate tables go, and how large a broadcast side may be."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

SHARED_DIR = "spark.checkpoint.dir"


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: the cluster's own setting. Where it is unset, a temp folder serves a
    local master (tests); on a cluster it is an error."""
    base = spark.conf.get(SHARED_DIR, None) or spark.sparkContext._jsc.sc().getCheckpointDir().getOrElse(None)
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError(f"set {SHARED_DIR} to a folder that driver and executors share")
        base = tempfile.mkdtemp(prefix="postpool-")
        spark.sparkContext.setCheckpointDir(base)
    return str(base).rstrip("/")


def scratch_path(spark: SparkSession, tag: str) -> str:
    """A new path in this application's part of the shared folder; `clear_scratch` deletes all of them."""
    return f"{shared_dir(spark)}/postpool/{spark.sparkContext.applicationId}/{tag}-{uuid.uuid4().hex}"


def clear_scratch(spark: SparkSession) -> None:
    """Delete what this application wrote to the shared folder. Frames that still read from it fail afterwards, so call
    it when their results are written."""
    sc = spark.sparkContext
    path = sc._jvm.org.apache.hadoop.fs.Path(f"{shared_dir(spark)}/postpool/{sc.applicationId}")
    path.getFileSystem(sc._jsc.hadoopConfiguration()).delete(path, True)


def materialise(df: DataFrame, tag: str, **options) -> DataFrame:
    """Write df as Parquet to the shared folder and read it back: cuts the lineage and survives lost executors."""
    spark = df.sparkSession
    path = scratch_path(spark, tag)
    df.write.options(**options).parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def materialise_buckets(df: DataFrame, tag: str, key: str, buckets: int, order: list[str]) -> DataFrame:
    """The same as a table of one file a bucket of `key`, sorted within: grouping by the key needs no shuffle then."""
    spark = df.sparkSession
    name = f"postpool_{tag}_{uuid.uuid4().hex}"
    rows = df.repartition(buckets, key).sortWithinPartitions(key, *order)
    rows.write.bucketBy(buckets, key).sortBy(key, *order).format("parquet").option("path", scratch_path(spark, tag)).saveAsTable(name)
    return spark.table(name)


def shuffle_partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


_SHIPPED: set[str] = set()


def ship(spark: SparkSession) -> None:
    """Send this package to the executors, once an application, for sessions whose workers don't have it on their path."""
    import shutil
    from pathlib import Path

    app = spark.sparkContext.applicationId
    if app in _SHIPPED:
        return
    package = Path(__file__).resolve().parent
    if package.is_dir():  # else the package itself came in an archive
        folder = Path(tempfile.mkdtemp(prefix="postpool-ship-"))
        shutil.copytree(package, folder / "src" / package.name, ignore=shutil.ignore_patterns("__pycache__"))
        spark.sparkContext.addPyFile(shutil.make_archive(str(folder / package.name), "zip", folder / "src"))
    _SHIPPED.add(app)
