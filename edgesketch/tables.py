"""Tables, scratch tables in the shared folder, and star contraction over link tables."""

from __future__ import annotations

import atexit
import contextlib
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share; a private one only where none is set."""
    told = spark.conf.get("spark.checkpoint.dir", None)
    if told:
        return told.rstrip("/")
    before = spark.sparkContext._jsc.sc().getCheckpointDir()
    if before.isDefined():
        return before.get().rstrip("/")
    master = spark.sparkContext.master
    if master != "local" and not master.startswith("local["):
        raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    own = "file://" + tempfile.mkdtemp(prefix="edgesketch-")
    spark.sparkContext.setCheckpointDir(own)
    return own


def delete_path(spark: SparkSession, path: str) -> None:
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)


_WRITTEN: list[tuple[SparkSession, str]] = []
_SCOPES: list[list[str]] = []


def _sweep() -> None:
    for spark, path in _WRITTEN:
        try:
            delete_path(spark, path)
        except Exception:  # noqa: BLE001 - the session may be gone at exit
            return


atexit.register(_sweep)


@contextlib.contextmanager
def scratch_scope(spark: SparkSession):
    """Scratch tables made inside go when it ends, but for those made with ``outer``."""
    _SCOPES.append([])
    try:
        yield
    finally:
        for path in _SCOPES.pop():
            delete_path(spark, path)


def scratch_path(spark: SparkSession, tag: str, outer: int = 0) -> str:
    """A fresh path in the shared folder, removed with its scope (or the one ``outer`` further out), else when this process ends."""
    path = f"{shared_dir(spark)}/edgesketch/{tag}-{uuid.uuid4().hex}"
    scopes = _SCOPES[: max(0, len(_SCOPES) - outer)]
    if scopes:
        scopes[-1].append(path)
    else:
        _WRITTEN.append((spark, path))
    return path


@contextlib.contextmanager
def shuffles_released(spark: SparkSession):
    """Shuffle files of what is written inside go as each write ends; else they stay until the driver's old objects are collected."""
    name = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    before = spark.conf.get(name, None)
    spark.conf.set(name, "true")
    try:
        yield
    finally:
        if before is None:
            spark.conf.unset(name)
        else:
            spark.conf.set(name, before)


def materialize(df: DataFrame, tag: str, outer: int = 0) -> DataFrame:
    """Cuts the lineage with a table in the shared folder: any executor can be lost later."""
    spark, path = df.sparkSession, scratch_path(df.sparkSession, tag, outer)
    with shuffles_released(spark):
        df.write.option("compression", "zstd").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def parts(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def star_components(edges: DataFrame, most_rounds: int = 60) -> tuple[DataFrame, int]:
    """((vertex, component) of all endpoints by alternating star contraction, rounds).

    The minimum per vertex is a partial aggregate, so a hub costs one row per task; the joins have a
    unique side, which AQE splits where the other is skewed.
    """
    with scratch_scope(edges.sparkSession):
        now = materialize(edges.where("u <> v").select(F.least("u", "v").alias("lo"), F.greatest("u", "v").alias("hi")).distinct(), "stars")
        last, rounds = None, 0
        while rounds < most_rounds:
            rounds += 1
            both = now.select(F.col("lo").alias("x"), F.col("hi").alias("y")).union(now.select("hi", "lo"))
            least = both.groupBy("x").agg(F.min("y").alias("m")).select("x", F.least("x", "m").alias("m"))
            large = both.where("y > x").join(least, "x").select(F.col("m").alias("lo"), F.col("y").alias("hi")).distinct()
            # small star: a vertex's smaller neighbours, and itself, meet at the least of them
            least = large.groupBy("hi").agg(F.min("lo").alias("m"))
            small = large.join(least, "hi").select(F.explode(F.array("lo", "hi")).alias("x"), "m").where("x <> m")
            now = materialize(small.select(F.least("x", "m").alias("lo"), F.greatest("x", "m").alias("hi")).distinct(), "stars")
            told = now.agg(F.count(F.lit(1)).alias("n"), F.bit_xor(F.xxhash64("lo", "hi")).alias("x")).first()
            if tuple(told) == last:
                break
            last = tuple(told)
        else:
            raise RuntimeError("star contraction did not settle")
        now = materialize(now, "stars", outer=True)
    roots = now.select(F.col("hi").alias("vertex"), F.col("lo").alias("component"))
    return roots.union(now.select("lo", "lo").distinct()), rounds
