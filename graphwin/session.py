"""Session helpers: sessions for tests, shared intermediate tables, package shipping."""

from __future__ import annotations

import atexit
import os
import shutil
import tempfile
import uuid
import zipfile
from contextlib import contextmanager
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Used only where the session names no shared folder (tests, notebooks).
DEFAULT_SHARED_DIR = "/tmp/checkpoints"
#: The most rows of a few numbers each that are sent whole to every task; larger sides are joined by shuffles.
BROADCAST_ROWS = 2_000_000
CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
ROOT = Path(__file__).resolve().parent.parent
_own_local: list[str] = []


def local_session(cores: int | str = "*", shuffle_partitions: int = 8, **conf: str) -> SparkSession:
    """A session for tests and benches; clusters bring their own."""
    builder = SparkSession.builder.master(f"local[{cores}]").config("spark.sql.shuffle.partitions", str(shuffle_partitions))
    builder = builder.config("spark.sql.session.timeZone", "UTC").config("spark.ui.enabled", "false")
    builder = builder.config("spark.ui.showConsoleProgress", "false").config("spark.sql.adaptive.enabled", "true")
    for key, value in conf.items():
        builder = builder.config(key, value)
    return builder.getOrCreate()


def shared_dir(spark: SparkSession) -> str:
    """The folder that the driver and all executors see: spark.checkpoint.dir, or a default where it is unset."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    return f"{(named or DEFAULT_SHARED_DIR).rstrip('/')}/graphwin"


def small(df: DataFrame) -> DataFrame:
    """df, sent whole to every task if it has few rows. df should be a table, as it is counted first."""
    return F.broadcast(df) if df.limit(BROADCAST_ROWS + 1).count() <= BROADCAST_ROWS else df


@contextmanager
def dropping_shuffles(spark: SparkSession):
    """What runs inside deletes its shuffle files when it ends, not when the driver happens to collect garbage."""
    before = spark.conf.get(CLEANUP, None)
    spark.conf.set(CLEANUP, "true")
    try:
        yield
    finally:
        spark.conf.unset(CLEANUP) if before is None else spark.conf.set(CLEANUP, before)


def materialize(df: DataFrame, label: str, codec: str | None = None) -> DataFrame:
    """Write df to the shared folder and read it back: cuts lineage, survives lost executors, and is computed once."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"
    with dropping_shuffles(spark):
        (df.write.option("compression", codec) if codec else df.write).parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out.shared_path = path
    if spark.conf.get("spark.checkpoint.dir", None) is None:
        if not _own_local:
            atexit.register(lambda: [shutil.rmtree(p, ignore_errors=True) for p in _own_local])
        _own_local.append(path)
    return out


def discard(*frames: DataFrame) -> None:
    """Delete tables that materialize() wrote, once nothing lazy reads them any more."""
    for df in frames:
        path = getattr(df, "shared_path", None)
        if path:
            jvm = df.sparkSession._jvm
            where = jvm.org.apache.hadoop.fs.Path(path)
            where.getFileSystem(df.sparkSession._jsparkSession.sessionState().newHadoopConf()).delete(where, True)


def ship(spark: SparkSession) -> None:
    """Make this package importable in Python workers that don't have the repository on their path."""
    sc = spark.sparkContext
    on_path = str(ROOT) in os.environ.get("PYTHONPATH", "").split(":") or (os.getcwd() == str(ROOT) and sc.master.startswith("local["))
    if on_path or getattr(sc, "_graphwin_shipped", False):
        return
    target = os.path.join(tempfile.mkdtemp(), "graphwin.zip")
    with zipfile.ZipFile(target, "w") as z:
        for f in (ROOT / "graphwin").rglob("*.py"):
            z.write(f, f.relative_to(ROOT))
    sc.addPyFile(target)
    sc._graphwin_shipped = True
