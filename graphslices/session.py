"""Sessions for scripts and tests, and the package's code for Python workers."""

from __future__ import annotations

import tempfile
import uuid
import zipfile
from pathlib import Path

from pyspark.sql import SparkSession

PACKAGE = Path(__file__).resolve().parent


def local_session(cores: int | str = "*", partitions: int = 8, memory: str = "4g") -> SparkSession:
    """A local session. On a cluster the session comes from outside; nothing in the package needs these settings."""
    build = SparkSession.builder.master(f"local[{cores}]").appName("graphslices")
    settings = {
        "spark.sql.shuffle.partitions": str(partitions), "spark.driver.memory": memory, "spark.sql.session.timeZone": "UTC",
        "spark.sql.adaptive.enabled": "true", "spark.ui.enabled": "false", "spark.ui.showConsoleProgress": "false",
    }
    for k, v in settings.items():
        build = build.config(k, v)
    return build.getOrCreate()


def ship(spark: SparkSession) -> None:
    """Sends the package to the Python workers of the session, once for each context, so that they need not find it on their own path."""
    sc = spark.sparkContext
    if getattr(sc, "_graphslices_shipped", False):
        return
    path = Path(tempfile.mkdtemp(prefix="graphslices-code-")) / "graphslices_code.zip"
    with zipfile.ZipFile(path, "w") as out:
        for f in sorted(PACKAGE.rglob("*.py")):
            out.write(f, f"{PACKAGE.name}/{f.relative_to(PACKAGE)}")
    sc.addPyFile(str(path))  # served by the driver to every executor
    sc._graphslices_shipped = True


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir. Only on one machine (a local master, as in tests) one is made where the session names none."""
    sc = spark.sparkContext
    found = spark.conf.get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if not found:
        if not sc.master.startswith("local") or sc.master.startswith("local-cluster"):
            raise ValueError("the session names no shared folder: set spark.checkpoint.dir")
        found = tempfile.mkdtemp(prefix="graphslices-")
        sc.setCheckpointDir(found)
    return found


def cut(df):
    """df with its lineage cut by a reliable checkpoint in the shared folder."""
    shared_dir(df.sparkSession)
    return df.checkpoint()


def stored(df):
    """df as Parquet in the shared folder: computed once (a checkpoint computes its last stage twice) and smaller than checkpointed rows. Its partitions are not kept, and a task holds a row group of 16 MB at most."""
    path = f"{shared_dir(df.sparkSession)}/graphslices-{uuid.uuid4().hex}"
    df.write.option("parquet.block.size", 16 << 20).parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
