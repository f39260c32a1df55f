"""Places that every executor can reach, and tables that cut lineage.

``spark.checkpoint.dir`` names the folder shared by the driver and the executors. Where a session
lacks it and runs in one process (unit tests, a laptop) it is filled in once with a folder under the
warehouse; on a cluster that is an error.
"""

from __future__ import annotations

import atexit
import gc
import os
import shutil
import tempfile
import uuid
import zipfile
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

_KEY = "spark.checkpoint.dir"
_ROOT = Path(__file__).resolve().parent
_SHIPPED: set[str] = set()


def ship(spark: SparkSession) -> None:
    """Makes this package importable in Python workers, unless their path already has it.

    Spark's own file server hands the archive to executors, so no shared folder is needed. Call it
    before an operator that runs Python.
    """
    app = spark.sparkContext.applicationId
    on_path = [os.path.abspath(p) for p in os.environ.get("PYTHONPATH", "").split(os.pathsep) if p]
    if app in _SHIPPED or str(_ROOT.parent) in on_path:
        return
    folder = tempfile.mkdtemp(prefix="strel-")
    atexit.register(shutil.rmtree, folder, ignore_errors=True)
    archive = f"{folder}/strel_package.zip"
    with zipfile.ZipFile(archive, "w") as z:
        for f in sorted(_ROOT.rglob("*.py")):
            z.write(f, f.relative_to(_ROOT.parent))
    spark.sparkContext.addPyFile(archive)
    _SHIPPED.add(app)


def shared_dir(spark: SparkSession) -> str:
    """The shared folder for intermediate tables."""
    found = spark.sparkContext.getConf().get(_KEY) or spark.conf.get(_KEY, None)
    if not found:
        found = spark.sparkContext._jsc.sc().getCheckpointDir()
        found = found.get() if found.isDefined() else None
    if not found:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        found = spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_checkpoints"
        spark.sparkContext.setCheckpointDir(found)
    return found.rstrip("/")


def materialize(df: DataFrame, tag: str, *spent: DataFrame | None) -> DataFrame:
    """Writes ``df`` as a table in the shared folder and reads it again.

    The result has no lineage: a lost executor costs a re-read, not a re-computation, and two
    consumers of the result share one evaluation. ``spent`` are earlier such tables that only ``df``
    still read; they are deleted.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/strel/{tag}-{uuid.uuid4().hex}"
    df.write.mode("overwrite").parquet(path)
    found = spark.read.schema(df.schema).parquet(path)
    found._strel_path = path
    discard(*(t for t in spent if t is not None))
    return found


def discard(*tables: DataFrame) -> None:
    """Deletes tables that ``materialize`` wrote, once nothing reads them any more.

    Also lets the JVM notice that the shuffles of finished steps are unreachable, so that long
    iterative operators do not hold the disk of every step.
    """
    for t in tables:
        jvm = t.sparkSession.sparkContext._jvm
        path = jvm.org.apache.hadoop.fs.Path(t._strel_path)
        path.getFileSystem(t.sparkSession.sparkContext._jsc.hadoopConfiguration()).delete(path, True)
    if tables:
        gc.collect()
        tables[0].sparkSession.sparkContext._jvm.System.gc()


def give_back(spark: SparkSession) -> None:
    """Lets the JVMs of the driver and of all executors collect their garbage and shrink their heaps.

    A heap that one step has filled stays in use else, and leaves no room for the Python workers of
    the next. One task for each core, dealt over the executors while they are idle; costs less than
    a second.
    """
    gc.collect()
    n = spark.sparkContext.defaultParallelism
    asked = spark.range(0, n, 1, n).select(F.expr("reflect('java.lang.System', 'gc')").alias("done"))
    asked.write.format("noop").mode("overwrite").save()
    spark.sparkContext._jvm.System.gc()


def ranked(rows: DataFrame, by: list, to: str, tag: str = "ranked") -> DataFrame:
    """``rows`` with a dense number from 0 in the order of ``by`` (columns or expressions).

    Rows are dealt by ranges; each range numbers its own and starts behind those before it, so no
    task holds all rows (one row a range is summed up by one task).
    """
    dealt = materialize(rows.repartitionByRange(*by).withColumn("__part", F.spark_partition_id()), tag)
    before = dealt.groupBy("__part").agg(F.count(F.lit(1)).alias("__n"))
    up = Window.orderBy("__part").rowsBetween(Window.unboundedPreceding, -1)
    before = before.select("__part", F.coalesce(F.sum("__n").over(up), F.lit(0)).alias("__before"))
    own = F.row_number().over(Window.partitionBy("__part").orderBy(*by))
    return dealt.join(before, "__part").withColumn(to, F.col("__before") + own - 1).drop("__part", "__before")


def release(spark: SparkSession) -> None:
    """Deletes the intermediate tables; call it once the results that read them are stored."""
    jvm = spark.sparkContext._jvm
    path = jvm.org.apache.hadoop.fs.Path(f"{shared_dir(spark)}/strel")
    fs = path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())
    if fs.exists(path):
        fs.delete(path, True)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")
