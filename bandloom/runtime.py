"""Session plumbing shared by the whole package: tables, shared folders, shipping code."""

from __future__ import annotations

import atexit
import os
import shutil
import tempfile
import uuid
import zipfile
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

PACKAGE = Path(__file__).resolve().parent
_shipped: set[str] = set()
_own_dirs: list[str] = []
_scratch: list[str] = []


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given parquet tables; works for every store Spark can read."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def spread(df: DataFrame) -> DataFrame:
    """df, dealt out over all cores if its scan has few splits; for costly work on each row.

    A file of one row group is one task, whatever its size. Inputs of at least twice as many splits as cores (all large ones)
    stay where they are and cost no shuffle; no row is dropped either way. Plans with exchanges of their own, whose
    partitions only running them would tell, are left alone.
    """
    execution = df._jdf.queryExecution()
    if execution.executedPlan().getClass().getSimpleName() == "AdaptiveSparkPlanExec":
        return df
    cores = df.sparkSession.sparkContext.defaultParallelism
    return df if execution.toRdd().getNumPartitions() >= 2 * cores else df.repartition(2 * cores)


def read_table(spark: SparkSession, folder: str, name: str, kind: str = "parquet", schema: str | None = None) -> DataFrame:
    """A table as parquet, csv (with a header) or json; the last two need a schema, so that no pass infers one."""
    if kind == "parquet":
        return spark.read.parquet(f"{folder}/{name}.parquet") if schema is None else spark.read.schema(schema).parquet(f"{folder}/{name}.parquet")
    if kind not in ("csv", "json") or schema is None:
        raise ValueError("kind is parquet, csv or json; csv and json need a schema")
    reader = spark.read.schema(schema).option("mode", "FAILFAST")
    return reader.option("header", True).csv(f"{folder}/{name}.csv") if kind == "csv" else reader.json(f"{folder}/{name}.json")


def ship(spark: SparkSession) -> None:
    """Give executors this package once per application (they share no local disk with the driver)."""
    app = spark.sparkContext.applicationId
    if app in _shipped:
        return
    folder = tempfile.mkdtemp(prefix="bandloom-ship-")
    target = os.path.join(folder, "bandloom_code.zip")
    with zipfile.ZipFile(target, "w", zipfile.ZIP_DEFLATED) as z:
        for p in sorted(PACKAGE.rglob("*.py")):
            z.write(p, p.relative_to(PACKAGE.parent))
    spark.sparkContext.addPyFile(target)
    _shipped.add(app)
    atexit.register(shutil.rmtree, folder, True)


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, or one of ours where it is unset and all is one machine."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if found:
        return found.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    if not _own_dirs:
        _own_dirs.append(tempfile.mkdtemp(prefix="bandloom-shared-"))
        atexit.register(shutil.rmtree, _own_dirs[0], True)
    return "file://" + _own_dirs[0]


def scratch(spark: SparkSession, label: str) -> str:
    """A fresh path under the shared folder."""
    path = f"{shared_dir(spark)}/bandloom-{label}-{uuid.uuid4().hex}"
    _scratch.append(path)
    return path


def scratch_paths() -> list[str]:
    """Paths handed out and not deleted yet, oldest first."""
    return list(_scratch)


def clean(spark: SparkSession, keep: list[str] = ()) -> None:
    """Delete all scratch paths but those to keep: for callers that are done with the frames which read them."""
    for path in scratch_paths():
        if path not in keep:
            delete(spark, path)


def delete(spark: SparkSession, path: str) -> None:
    """Remove a scratch path through Hadoop's file system, whatever its scheme."""
    jpath = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    jpath.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(jpath, True)
    if path in _scratch:
        _scratch.remove(path)


def exists(spark: SparkSession, path: str) -> bool:
    jpath = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return jpath.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(jpath)


def written(df: DataFrame, label: str) -> tuple[DataFrame, str]:
    """Cut lineage: write df as Parquet in the shared folder and read it back; survives lost executors."""
    spark = df.sparkSession
    path = scratch(spark, label)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path), path
