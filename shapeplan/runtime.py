"""Session plumbing shared by everything that runs on a cluster."""

from __future__ import annotations

import os
import tempfile
import uuid
import zipfile
from pathlib import Path

from pyspark.sql import DataFrame, Observation, SparkSession
from pyspark.sql import functions as F

ROOT = Path(__file__).resolve().parent.parent
_SHIPPED = "shapeplan.shipped"

#: Bytes of files, and rows, up to which Spark may choose by itself to broadcast a table.
SMALL_FILES, SMALL_ROWS = 1 << 20, 100_000


def ship(spark: SparkSession) -> None:
    """Make this package importable in Python workers.

    Workers on the driver's machine get the package folder on their path; on a real
    cluster the package travels once as a zip. Settings of the session stay as they are.
    """
    sc = spark.sparkContext
    path = sc.environment.get("PYTHONPATH", "")
    if str(ROOT) not in path.split(os.pathsep):
        sc.environment["PYTHONPATH"] = os.pathsep.join(p for p in (str(ROOT), path) if p)
    if sc.master.startswith("local") or getattr(sc, "_shapeplan_shipped", False):
        return
    target = Path(tempfile.mkdtemp()) / "shapeplan.zip"
    with zipfile.ZipFile(target, "w") as z:
        for f in (ROOT / "shapeplan").rglob("*"):
            if f.suffix in {".py", ".json"}:
                z.write(f, f.relative_to(ROOT))
    sc.addPyFile(str(target))
    sc._shapeplan_shipped = True


def scratch_root(spark: SparkSession) -> str:
    """Shared folder for written intermediate tables.

    The cluster names it in ``spark.checkpoint.dir``. Only on a single machine (tests, local runs) it may be
    unset, and a folder under the warehouse is used instead; on a cluster that could be the driver's own disk.
    """
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if spark.sparkContext.master.split("[")[0] != "local":
            raise ValueError("set spark.checkpoint.dir to a folder that all machines share")
        base = spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_scratch"
    return base.rstrip("/")


def _own_folder(spark: SparkSession) -> str:
    return f"{scratch_root(spark)}/shapeplan/{spark.sparkContext.applicationId}"


def scratch_path(spark: SparkSession, name: str) -> str:
    return f"{_own_folder(spark)}/{name}-{uuid.uuid4().hex}"


def clear_scratch(spark: SparkSession) -> None:
    """Delete this application's intermediate tables; results that were not written elsewhere can't be read afterwards."""
    remove(spark, _own_folder(spark))


def written(df: DataFrame, name: str) -> DataFrame:
    """Cut lineage: write ``df`` as Parquet in the shared folder and read it back.

    A lost executor then costs a re-read and never the plan above the cut.
    """
    spark = df.sparkSession
    path = scratch_path(spark, name)
    df.write.option("compression", "zstd").parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def shuffled(df: DataFrame) -> DataFrame:
    """``df``, but joins with it are shuffled unless a broadcast is asked for.

    Spark takes a table's size from its compressed files, of which a hash table is a multiple, and builds that on the driver.
    """
    return df.hint("merge")


def settled(df: DataFrame, name: str) -> DataFrame:
    """Like ``written``; the rows are counted on the way, and many of them are never broadcast."""
    seen = Observation()
    out = written(df.observe(seen, F.count(F.lit(1)).alias("n")), name)
    return out if seen.get["n"] <= SMALL_ROWS else shuffled(out)


def bucketed(df: DataFrame, name: str, key: str, n: int) -> DataFrame:
    """Like ``written``, dealt out to ``n`` buckets by a key: later joins and groups by it don't shuffle this side again."""
    spark, label = df.sparkSession, f"{name}_{uuid.uuid4().hex}"
    df.write.format("parquet").option("compression", "zstd").option("path", scratch_path(spark, name)).bucketBy(n, key).saveAsTable(label)
    out = spark.table(label)
    spark.sql(f"DROP TABLE {label}")  # the catalog's entry only: the files lie outside the warehouse's tables
    return out


def remove(spark: SparkSession, path: str) -> None:
    """Delete a folder through Hadoop's file system, whatever the store is."""
    jvm = spark.sparkContext._jvm
    p = jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir.rstrip('/')}/{name}.parquet")


def joinable(df: DataFrame) -> DataFrame:
    """A side of a join, ``shuffled`` unless the files it comes from are small. A hint holds up to the next join, so what joins give needs one anew."""
    size = df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()
    return df if int(str(size)) <= SMALL_FILES else shuffled(df)
