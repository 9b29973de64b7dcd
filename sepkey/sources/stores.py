"""Tables, durable intermediate results, and stored samples and sketches."""

from __future__ import annotations

import atexit
import ctypes
import gc
import tempfile
import uuid
import zipfile
from contextlib import contextmanager
from pathlib import Path

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

import sepkey


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


BATCH_BYTES = 8 << 20


def ship(spark: SparkSession) -> None:
    """Sends the package to the executors, once for each Spark application: they need no copy on their own disks. Arrow batches of this
    session become at most BATCH_BYTES: both sides of the pipe hold a few of them for each task."""
    sc = spark.sparkContext
    if spark.conf.get("spark.sql.execution.arrow.maxBytesPerBatch") == "67108864b":  # the default; a value of the user's own stays
        spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", f"{BATCH_BYTES}b")
    if getattr(sc, "_sepkey_sent", False):
        return
    top = Path(sepkey.__file__).parent
    where = Path(tempfile.mkdtemp(prefix="sepkey-")) / "sepkey_package.zip"
    with zipfile.ZipFile(where, "w") as z:
        for p in sorted(top.rglob("*.py")):
            z.write(p, str(p.relative_to(top.parent)))
    sc.addPyFile(str(where))
    sc._sepkey_sent = True


def map_arrow(df: DataFrame, run, schema) -> DataFrame:
    """``mapInArrow`` whose workers give memory back when a task ends: they stay for later tasks, beside stages that need none of them."""
    ship(df.sparkSession)

    def tidy(batches):
        try:
            yield from run(batches)
        finally:
            give_back()

    return df.mapInArrow(tidy, schema)


def give_back() -> None:
    """Returns freed memory of Arrow's pool and of the C library to the system."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # only the GNU library has it
        return


def shared_folder(spark: SparkSession) -> str:
    """The folder named by ``spark.checkpoint.dir``. Where none is set, a local master gets a temporary folder and any other
    the warehouse, which all executors see."""
    sc = spark.sparkContext
    found = sc._jsc.sc().getCheckpointDir()
    if not found.isDefined():
        if sc.master.startswith("local[") or sc.master == "local":
            sc.setCheckpointDir(tempfile.mkdtemp(prefix="sepkey-"))
        else:
            sc.setCheckpointDir(spark.conf.get("spark.checkpoint.dir", None) or spark.conf.get("spark.sql.warehouse.dir") + "/checkpoints")
        found = sc._jsc.sc().getCheckpointDir()
    return found.get()


_scopes: list[list[tuple[SparkSession, str]]] = []


@contextmanager
def scratch():
    """Files that ``durable`` writes inside go at the end, but for those written with ``keep``: they stay as long as those around."""
    _scopes.append([])
    try:
        yield
    finally:
        for spark, path in _scopes.pop():
            _remove(spark, path)


#: Spark's own switch: shuffle files of a query go when it ends, not when the driver's garbage is collected.
_TIDY = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def durable(df: DataFrame, name: str = "step", keep: bool = False, codec: str = "snappy", tidy: bool = False) -> DataFrame:
    """``df`` written as Parquet in the shared folder and read back: cut lineage that outlives a lost executor. The files go when the
    ``scratch`` around ends (with ``keep``: the one around that), else with the driver. With ``tidy`` the shuffle files go at once."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"
    before = spark.conf.get(_TIDY, "false")
    if tidy:
        spark.conf.set(_TIDY, "true")
        df = df.select("*")  # planned anew under the switch
    try:
        df.write.option("compression", codec).parquet(path)
    finally:
        if tidy:
            spark.conf.set(_TIDY, before)
    around = _scopes[:-1] if keep else _scopes
    if around:
        around[-1].append((spark, path))
    else:
        atexit.register(_remove, spark, path)
    return spark.read.schema(df.schema).parquet(path)


def _remove(spark: SparkSession, path: str) -> None:
    try:
        hadoop = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
        hadoop.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(hadoop, True)
    except Exception:  # the session may be gone at exit; the folder is then the cluster's to clear
        return


def save(df: DataFrame, path: str, about: dict) -> None:
    """Rows of a sample or sketch, and one row of what is needed to answer from them."""
    df.write.mode("overwrite").parquet(f"{path}/rows")
    spark = df.sparkSession
    spark.range(1).select(*[F.lit(v).alias(k) for k, v in about.items()]).write.mode("overwrite").parquet(f"{path}/about")


def load(spark: SparkSession, path: str) -> tuple[DataFrame, dict]:
    return spark.read.parquet(f"{path}/rows"), spark.read.parquet(f"{path}/about").first().asDict()
