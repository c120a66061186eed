"""Session settings for tests and benches, and the shared folder for cut lineage."""

from __future__ import annotations

import re
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def local_session(cores: int | str = "*", shuffle_partitions: int = 8, memory: str = "8g") -> SparkSession:
    """A local session for tests and benches; clusters bring their own."""
    return (
        SparkSession.builder.master(f"local[{cores}]")
        .appName("pairmatch")
        .config("spark.sql.shuffle.partitions", str(shuffle_partitions))
        .config("spark.driver.memory", memory)
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .getOrCreate()
    )


def checkpoint_root(spark: SparkSession) -> str:
    """The shared folder named in spark.checkpoint.dir; a local one only where none is set and all runs on one machine."""
    sc = spark.sparkContext
    shared = spark.conf.get("spark.checkpoint.dir", None)
    if shared is None:
        shared = sc._jsc.sc().getCheckpointDir()
        shared = shared.get() if shared.isDefined() else None
    if shared is None:
        if not re.fullmatch(r"local(\[.*\])?", sc.master):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all machines share")
        shared = "file://" + tempfile.mkdtemp(prefix="pairmatch-ck-")
        sc.setCheckpointDir(shared)
    elif not sc._jsc.sc().getCheckpointDir().isDefined():
        sc.setCheckpointDir(shared)
    return shared


def cut(df: DataFrame, eager: bool = True) -> DataFrame:
    """Materialise in the shared folder and forget the lineage."""
    checkpoint_root(df.sparkSession)
    return df.checkpoint(eager)


CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def put_down(df: DataFrame, name: str) -> DataFrame:
    """Written to the shared folder as compressed Parquet and read again; what was shuffled to make it goes once it is written, where Spark can do that (from 4.1 on)."""
    spark, path = df.sparkSession, f"{checkpoint_root(df.sparkSession).rstrip('/')}/{name}-{uuid.uuid4().hex}"
    was = spark.conf.get(CLEANUP, None)
    if was is not None:
        spark.conf.set(CLEANUP, "true")
    try:
        df.write.option("compression", "zstd").parquet(path)
    finally:
        if was is not None:
            spark.conf.set(CLEANUP, was)
    return spark.read.schema(df.schema).parquet(path)
