"""Session defaults for stand-alone use, and the shared folder for checkpoints."""

from __future__ import annotations

import gc
import tempfile

from pyspark.sql import DataFrame, SparkSession


def session(cores: str = "*", shuffle_partitions: int = 8) -> SparkSession:
    """A session with adaptive execution, UTC and Arrow; on a cluster use the one that is given."""
    return (
        SparkSession.builder.master(f"local[{cores}]")
        .appName("boxmdl")
        .config("spark.sql.shuffle.partitions", str(shuffle_partitions))
        .config("spark.sql.adaptive.enabled", "true")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.ui.enabled", "false")
        .getOrCreate()
    )


def fixed(df: DataFrame) -> DataFrame:
    """A reliable checkpoint of `df` in the folder that spark.checkpoint.dir names: cuts lineage between mining rounds."""
    sc = df.sparkSession.sparkContext
    if sc.getCheckpointDir() is None:
        sc.setCheckpointDir(df.sparkSession.conf.get("spark.checkpoint.dir", None) or local_folder(sc.master))
    return df.checkpoint(eager=True)


def released(spark: SparkSession) -> None:
    """Lets the driver give up broadcasts, shuffles, checkpoints and plans that nothing refers to any longer; Spark itself waits for the JVM to run short of memory."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def local_folder(master: str) -> str:
    """A temporary folder, where driver and tasks are one process; on a cluster the session has to name a shared one."""
    if master != "local" and not master.startswith("local["):
        raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
    return "file://" + tempfile.mkdtemp(prefix="boxmdl-checkpoint-")
