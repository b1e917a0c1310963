"""Session for local use and the shared folder for stages; a given session is used as it is."""

from __future__ import annotations

import atexit
import shutil
import tempfile

from pyspark.sql import DataFrame, SparkSession


def local_session(cores: int | str = "*", partitions: int = 8, memory: str = "6g") -> SparkSession:
    return (
        SparkSession.builder.master(f"local[{cores}]")
        .config("spark.sql.shuffle.partitions", str(partitions))
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.driver.memory", memory)
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .getOrCreate()
    )


def shared_dir(spark: SparkSession) -> str:
    """The checkpoint folder that the session names; one of its own only where none is set."""
    jsc = spark.sparkContext._jsc.sc()
    if not jsc.getCheckpointDir().isDefined():
        named = spark.conf.get("spark.checkpoint.dir", None)
        if not named:
            if not spark.sparkContext.master.startswith("local"):
                raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
            named = tempfile.mkdtemp(prefix="fimspark-stages-")
            atexit.register(shutil.rmtree, named, ignore_errors=True)
        spark.sparkContext.setCheckpointDir(named)
    return jsc.getCheckpointDir().get()


def stage(df: DataFrame) -> DataFrame:
    """Write a level's rows to the shared folder: later steps read them and the plan starts anew."""
    shared_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def release(*stages: DataFrame) -> None:
    """Remove the files of stages that nothing reads any more. Tables that are no stages are left alone."""
    for df in stages:
        plan = df._jdf.queryExecution().logical()
        if plan.getClass().getSimpleName() != "LogicalRDD":
            continue
        path = plan.rdd().getCheckpointFile()
        if path.isDefined():
            sc = df.sparkSession.sparkContext
            where = sc._jvm.org.apache.hadoop.fs.Path(path.get())
            where.getFileSystem(sc._jsc.hadoopConfiguration()).delete(where, True)
