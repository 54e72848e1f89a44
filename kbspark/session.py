"""Session helpers. Nothing here changes a setting that is fixed when Spark starts."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def build_session(name: str = "kbspark", cpus: str = "*", partitions: int = 8) -> SparkSession:
    """A local session for tests and the bench; production sessions are given by the caller."""
    return (
        SparkSession.builder.master(f"local[{cpus}]")
        .appName(name)
        .config("spark.sql.shuffle.partitions", str(partitions))
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.sql.adaptive.enabled", "true")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.driver.memory", "8g")
        .getOrCreate()
    )


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, else (local tests only) a temp folder."""
    sc = spark.sparkContext
    if sc._jsc.sc().getCheckpointDir().isEmpty():
        configured = sc.getConf().get("spark.checkpoint.dir")
        sc.setCheckpointDir(configured or tempfile.mkdtemp(prefix="kbspark-ckpt-"))
    return sc._jsc.sc().getCheckpointDir().get()


def keep(df: DataFrame, name: str = "kept") -> DataFrame:
    """Write df as Parquet in the shared folder and read it again: like cut, but compressed and by columns."""
    path = f"{shared_folder(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.parquet(path)


def cut(df: DataFrame) -> DataFrame:
    """Materialise df in the shared folder and drop its lineage; survives the loss of executors."""
    shared_folder(df.sparkSession)
    return df.checkpoint(eager=True)


def rest(spark: SparkSession) -> None:
    """Have the executors' JVMs collect their garbage and give free heap back to the system, which Python workers beside
    them need next. One short task for each core."""
    n = spark.sparkContext.defaultParallelism
    spark.range(0, n, 1, n).select(F.java_method(F.lit("java.lang.System"), F.lit("gc"))).write.format("noop").mode("overwrite").save()
