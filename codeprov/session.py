"""Session helpers: nothing here changes a setting that is fixed when Spark starts."""

from __future__ import annotations

import tempfile

from pyspark.sql import DataFrame, SparkSession


def local_session(cores: int = 8, name: str = "codeprov", memory: str = "8g") -> SparkSession:
    """A session for tests and benches on one machine."""
    return (
        SparkSession.builder.master(f"local[{cores}]")
        .appName(name)
        .config("spark.driver.memory", memory)
        .config("spark.sql.shuffle.partitions", str(cores))
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.sql.execution.arrow.pyspark.enabled", "true")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .getOrCreate()
    )


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given Parquet tables."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``, or the checkpoint folder already set.

    Where neither is set, a temporary folder on one machine (tests), and an error on a cluster, whose executors
    would not see it.
    """
    context = spark.sparkContext
    at = context._jsc.sc().getCheckpointDir()
    place = spark.conf.get("spark.checkpoint.dir", None) or (at.get() if at.isDefined() else None)
    if place is None:
        if not context.master.startswith("local") or context.master.startswith("local-cluster"):
            raise RuntimeError("spark.checkpoint.dir names no folder shared by driver and executors")
        place = tempfile.mkdtemp(prefix="codeprov-")
    return place.rstrip("/")


def cut_lineage(df: DataFrame) -> DataFrame:
    """``df`` written once and read back, so that losing an executor costs no recomputation.

    The files go to ``shared_folder``.
    """
    context = df.sparkSession.sparkContext
    if not context._jsc.sc().getCheckpointDir().isDefined():
        context.setCheckpointDir(shared_folder(df.sparkSession))
    return df.checkpoint(eager=True)
