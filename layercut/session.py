"""Session helpers shared by the whole package."""

from __future__ import annotations

from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession

#: Used only in one process (local[...]) that names no shared folder, as in tests.
LOCAL_CHECKPOINT_DIR = "/tmp/checkpoints/layercut"


def local_session(cores: int = 8, shuffle_partitions: int = 8, name: str = "layercut") -> SparkSession:
    """A session for tests and the bench; queries themselves take the session as given."""
    return (
        SparkSession.builder.master(f"local[{cores}]")
        .appName(name)
        .config("spark.sql.shuffle.partitions", str(shuffle_partitions))
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.driver.memory", "12g")
        .config("spark.driver.host", "127.0.0.1")
        .getOrCreate()
    )


def shared_folder(spark: SparkSession) -> str:
    """The folder that all executors share: the checkpoint folder in use, or the one that spark.checkpoint.dir names. A cluster must name one."""
    used = spark.sparkContext._jsc.sc().getCheckpointDir()
    if used.isDefined():
        return used.get()
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named is None and not spark.sparkContext.master.startswith("local[") and spark.sparkContext.master != "local":
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    spark.sparkContext.setCheckpointDir(named or LOCAL_CHECKPOINT_DIR)
    return spark.sparkContext._jsc.sc().getCheckpointDir().get()


def cut_lineage(df: DataFrame) -> DataFrame:
    """Reliable checkpoint in the shared folder."""
    shared_folder(df.sparkSession)
    return df.checkpoint(eager=True)


@contextmanager
def keeping_placement(spark: SparkSession, tasks: int | None = None):
    """Plans made inside keep how their rows are partitioned: adaptive execution, which may coalesce partitions and thus reports none, is
    off, and as it was before afterwards. tasks: partitions of the exchanges made inside."""
    names = {"spark.sql.adaptive.enabled": "false"} | ({"spark.sql.shuffle.partitions": str(tasks)} if tasks else {})
    before = {name: spark.conf.get(name) for name in names}
    for name, value in names.items():
        spark.conf.set(name, value)
    try:
        yield
    finally:
        for name, value in before.items():
            spark.conf.set(name, value)


def cut_placed(df: DataFrame) -> DataFrame:
    """cut_lineage() that keeps how df is partitioned, so that later joins on the placement add no exchange."""
    with keeping_placement(df.sparkSession):
        return cut_lineage(df)
