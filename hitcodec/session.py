"""Session helpers that leave settings fixed at start alone."""

from __future__ import annotations

import os
import tempfile
import uuid
import zipfile

from pyspark.sql import SparkSession

SHIPPED = "hitcodec.shipped"


def local_session(cpus: int | str = "*", partitions: int = 8, name: str = "hitcodec") -> SparkSession:
    """A session for tests and the bench; a cluster brings its own."""
    return (
        SparkSession.builder.master(f"local[{cpus}]")
        .appName(name)
        .config("spark.sql.shuffle.partitions", str(partitions))
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.ui.enabled", "false")
        .config("spark.driver.memory", "8g")
        .config("spark.sql.adaptive.enabled", "true")
        .config("spark.sql.execution.arrow.pyspark.enabled", "true")
        .getOrCreate()
    )


def ship_package(spark: SparkSession) -> None:
    """Send this package to the executors' Python workers, once a Spark application."""
    context = spark.sparkContext
    if getattr(context, "_hitcodec_shipped", False):
        return
    root = os.path.dirname(os.path.abspath(__file__))
    folder = tempfile.mkdtemp(prefix="hitcodec-")
    target = os.path.join(folder, f"hitcodec_{uuid.uuid4().hex[:8]}.zip")
    with zipfile.ZipFile(target, "w", zipfile.ZIP_DEFLATED) as out:
        for top, _, names in os.walk(root):
            for name in names:
                if name.endswith(".py"):
                    path = os.path.join(top, name)
                    out.write(path, os.path.join("hitcodec", os.path.relpath(path, root)))
    context.addPyFile(target)
    context._hitcodec_shipped = True


def shared_dir(spark: SparkSession) -> str:
    """The shared folder for written intermediate tables: spark.checkpoint.dir, or (in tests only) a local one set here."""
    place = spark.conf.get("spark.checkpoint.dir", None)
    if not place:
        found = spark.sparkContext._jsc.sc().getCheckpointDir()
        if found.isDefined():
            return found.get()
        if not spark.sparkContext.master.startswith("local") or spark.sparkContext.master.startswith("local-cluster"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        place = "file://" + tempfile.mkdtemp(prefix="hitcodec-checkpoint-")
        spark.sparkContext.setCheckpointDir(place)
        return place
    return place


def scratch(spark: SparkSession, name: str) -> str:
    """A new path under the shared folder."""
    return f"{shared_dir(spark).rstrip('/')}/{name}-{uuid.uuid4().hex}"


def materialise(df, name: str):
    """Write a table to the shared folder and read it again: cuts lineage, survives lost executors."""
    path = scratch(df.sparkSession, name)
    df.write.option("compression", "zstd").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
