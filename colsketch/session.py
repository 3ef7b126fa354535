"""Session helpers: a tuned local session for tests and benches, and shipping of this package to executors."""

from __future__ import annotations

import atexit
import gc
import io
import tempfile
import uuid
import zipfile
from pathlib import Path

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

#: Bytes of a batch that goes to Python; Spark's own bound of 64 MB takes several times as much in the JVM and in the worker.
BATCH_BYTES = 4 << 20
_BATCH = "spark.sql.execution.arrow.maxBytesPerBatch"
_shipped: set[str] = set()


def ship(spark: SparkSession) -> SparkSession:
    """Makes this package importable in Python workers, once for each application; executors fetch it from the driver."""
    context = spark.sparkContext
    if context.applicationId not in _shipped:
        home = Path(__file__).resolve().parent
        data = io.BytesIO()
        with zipfile.ZipFile(data, "w") as z:
            for p in sorted(home.rglob("*.py")):
                z.writestr(str(Path(home.name) / p.relative_to(home)), p.read_text())
        out = Path(tempfile.mkdtemp(prefix="colsketch-")) / "colsketch_package.zip"
        out.write_bytes(data.getvalue())
        context.addPyFile(str(out))
        _shipped.add(context.applicationId)
    return spark


def small_batches(spark: SparkSession) -> SparkSession:
    """Batches that go to Python get BATCH_BYTES at most from now on, or what the session sets if that is less; no result depends on it."""
    most = spark._jsparkSession.sessionState().conf().arrowMaxBytesPerBatch()
    if not 0 < most <= BATCH_BYTES:
        spark.conf.set(_BATCH, str(BATCH_BYTES))
    return spark


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, or the context's own checkpoint folder.

    Only a session that runs in one process (local[...]) gets a folder of this machine where none is set.
    """
    context = spark.sparkContext
    named = spark.conf.get("spark.checkpoint.dir", None) or context.getCheckpointDir()
    if not named:
        if not context.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        named = tempfile.mkdtemp(prefix="colsketch-")
    if not context.getCheckpointDir():
        context.setCheckpointDir(named)
    return named


def cut(df: DataFrame) -> DataFrame:
    """Reliable checkpoint in the shared folder, so that a lost executor costs no earlier pass."""
    shared_dir(df.sparkSession)
    return df.checkpoint()


def kept(df: DataFrame) -> DataFrame:
    """As cut(), in Parquet: the last stage runs once and numbers take few bytes, but the partitioning is not known any more.

    The table stays until drop() or until the process ends.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/kept-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    atexit.register(_delete, spark, path)
    out = spark.read.schema(df.schema).parquet(path)
    out._kept_at = path
    return out


def _delete(spark: SparkSession, path: str) -> None:
    try:
        at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
        at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)
    except Exception:  # noqa: BLE001, the session may have ended before the process
        return


def drop(*tables: DataFrame) -> None:
    """Deletes the files of results of kept() and cut() that nothing reads any more."""
    for df in tables:
        path = getattr(df, "_kept_at", None)
        if path is None:
            plan = df._jdf.queryExecution().logical()
            found = plan.rdd().getCheckpointFile() if plan.nodeName() == "LogicalRDD" or "LogicalRDD" in plan.getClass().getName() else None
            path = found.get() if found is not None and found.isDefined() else None
        if path:
            _delete(df.sparkSession, path)


def free(spark: SparkSession) -> None:
    """Lets Spark delete the shuffle files of tables that are out of reach, which it does when the driver collects garbage."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    spark.sparkContext._jvm.System.gc()


def local_session(cores: int | str = 8, partitions: int = 8, memory: str = "8g") -> SparkSession:
    spark = (
        SparkSession.builder.master(f"local[{cores}]")
        .appName("colsketch")
        .config("spark.driver.memory", memory)
        .config("spark.sql.shuffle.partitions", str(partitions))
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.sql.adaptive.enabled", "true")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    return spark
