"""Session helpers shared by every module: shared folder, materialised steps, table loading."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T

#: Used only where the session names no checkpoint folder (tests, laptops).
LOCAL_CHECKPOINTS = "/tmp/checkpoints/ctxloom"


def local_session(cores: int = 8, **conf) -> SparkSession:
    """A session for tests and benches; clusters bring their own."""
    builder = (
        SparkSession.builder.master(f"local[{cores}]")
        .appName("ctxloom")
        .config("spark.sql.shuffle.partitions", "8")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.driver.memory", "8g")
    )
    for key, value in conf.items():
        builder = builder.config(key, value)
    spark = builder.getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir; where that is unset, a local one for a local session, and
    a folder of the warehouse for a cluster."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    set_by_code = spark.sparkContext.getCheckpointDir()
    if set_by_code:
        return set_by_code.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        return spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/ctxloom-steps"
    spark.sparkContext.setCheckpointDir(LOCAL_CHECKPOINTS)
    return LOCAL_CHECKPOINTS


def materialise(df: DataFrame, name: str = "step") -> DataFrame:
    """Write ``df`` once to the shared folder and read it back: lineage is cut and any executor may be lost."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/ctxloom-{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    _steps.append(path)
    return spark.read.schema(df.schema).parquet(path)


_steps: list[str] = []


def drop_steps(spark: SparkSession) -> int:
    """Deletes the steps that this process has written, once nothing reads them any more; returns how many there were."""
    hadoop, paths = spark.sparkContext._jsc.hadoopConfiguration(), list(_steps)
    for path in paths:
        where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(hadoop).delete(where, True)
        _steps.remove(path)
    return len(paths)


def load(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def schema_with(base: T.StructType, ddl: str) -> T.StructType:
    """A schema with more fields, given as DDL."""
    return T.StructType([*base.fields, *T.StructType.fromDDL(ddl).fields])
