"""Session helpers: test session, table loading, shared scratch space.

Nothing here changes settings of a session that already runs for longer than a write.
"""

from __future__ import annotations

import atexit
import os
import shutil
import tempfile
import uuid
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

REPO = str(Path(__file__).resolve().parent.parent)
_own_dirs: dict[str, str] = {}
_TIDY = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def local_session(cores: int = 8, partitions: int = 8) -> SparkSession:
    """A local session for tests and the bench; clusters bring their own."""
    os.environ["PYTHONPATH"] = os.pathsep.join(x for x in (REPO, os.environ.get("PYTHONPATH", "")) if x)
    return (
        SparkSession.builder.master(f"local[{cores}]")
        .appName("catalogflow")
        .config("spark.sql.shuffle.partitions", str(partitions))
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.driver.memory", os.environ.get("BENCH_DRIVER_MEMORY", "6g"))
        .config("spark.sql.files.maxPartitionBytes", "16m")
        .getOrCreate()
    )


def ship(spark: SparkSession) -> None:
    """Let Python workers of this session import the package from its source folder."""
    env = spark.sparkContext.environment
    if REPO not in env.get("PYTHONPATH", "").split(os.pathsep):
        env["PYTHONPATH"] = os.pathsep.join(x for x in (REPO, env.get("PYTHONPATH", "")) if x)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _delete(spark: SparkSession, path: str) -> None:
    try:
        jvm = spark.sparkContext._jvm
        p = jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)
    except Exception:  # the session may be gone; the folder is the application's own
        pass


def shared_root(spark: SparkSession) -> str:
    """This application's own folder below ``spark.checkpoint.dir``, which all executors share.

    Where the setting is missing (tests), a folder is made once, for a local master only.
    """
    app = spark.sparkContext.applicationId
    if app not in _own_dirs:
        base = spark.conf.get("spark.checkpoint.dir", None)
        if not base:
            if not spark.sparkContext.master.startswith("local"):
                raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
            folder = tempfile.mkdtemp(prefix="catalogflow-")
            atexit.register(shutil.rmtree, folder, True)
            base = "file://" + folder
        _own_dirs[app] = f"{base.rstrip('/')}/catalogflow-{app}"
        atexit.register(_delete, spark, _own_dirs[app])
    return _own_dirs[app]


def fresh_path(spark: SparkSession, tag: str) -> str:
    return f"{shared_root(spark)}/{tag}-{uuid.uuid4().hex[:12]}"


def staged(df: DataFrame, tag: str, tidy: bool = False) -> DataFrame:
    """Write ``df`` to the shared folder and read it back: lineage is cut and no executor holds the only copy.

    tidy: shuffle files of the write are removed when it ends, not when the driver happens to collect its garbage; the setting
    for it holds for the time of the write.
    """
    spark = df.sparkSession
    path = fresh_path(spark, tag)
    before = spark.conf.get(_TIDY, None)
    if tidy:
        spark.conf.set(_TIDY, "true")
    try:
        df.write.parquet(path)
    finally:
        if tidy:
            spark.conf.unset(_TIDY) if before is None else spark.conf.set(_TIDY, before)
    return spark.read.schema(df.schema).parquet(path)


def broadcast_small(df: DataFrame, rows: int = 200_000) -> DataFrame:
    """``df`` with a broadcast hint if it has at most ``rows`` rows, else as it is, so that its join is shuffled. Counts ``df``, which should be staged."""
    return F.broadcast(df) if df.count() <= rows else df
