"""Tables written to the cluster's shared folder, to cut lineage and to survive lost executors."""

from __future__ import annotations

import contextlib
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_folder(spark: SparkSession) -> str:
    """A folder of this application in that of ``spark.checkpoint.dir``; where that is unset, in the warehouse, or in local mode a temporary folder."""
    own = f"rankflow-{spark.sparkContext.applicationId}"
    found = spark.conf.get("spark.checkpoint.dir", None)
    if found:
        return f"{found}/{own}"
    if spark.sparkContext.master.startswith("local[") or spark.sparkContext.master == "local":
        return f"file://{tempfile.gettempdir()}/{own}"
    return f"{spark.conf.get('spark.sql.warehouse.dir')}/{own}"


def written(df: DataFrame, name: str) -> DataFrame:
    """``df`` as a table in the shared folder; it stays until :func:`discard`."""
    path = f"{shared_folder(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out.scratch_path = path
    return out


def bucketed(df: DataFrame, name: str, key: str, buckets: int) -> DataFrame:
    """As :func:`written`, in buckets by ``key``, each sorted by it: joins on the key don't move it, and few keys read few buckets."""
    path = f"{shared_folder(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    table = f"rankflow_{path.rsplit('/', 1)[1].replace('-', '_')}"
    df.repartition(buckets, key).write.bucketBy(buckets, key).sortBy(key).option("path", path).saveAsTable(table)
    out = df.sparkSession.table(table)
    out.scratch_path, out.scratch_name = path, table
    return out


def appended(tables: list[DataFrame]) -> DataFrame:
    """Tables of one schema made by :func:`written`, as one scan."""
    return tables[0].sparkSession.read.schema(tables[0].schema).parquet(*[t.scratch_path for t in tables])


def held(df: DataFrame, *tables: DataFrame | None) -> DataFrame:
    """``df``, which still reads tables made by :func:`written`: they go with it when it is discarded."""
    df.scratch_tables = [*getattr(df, "scratch_tables", []), *(t for t in tables if t is not None and t is not df)]
    return df


def discard(*tables: DataFrame | None) -> None:
    """Delete tables made by :func:`written`, and those that a result was :func:`held` with, once nothing will read them again."""
    for df in tables:
        if df is None:
            continue
        discard(*getattr(df, "scratch_tables", []))
        path = getattr(df, "scratch_path", None)
        if path:
            if name := getattr(df, "scratch_name", None):
                df.sparkSession.sql(f"DROP TABLE IF EXISTS {name}")
            _delete(df.sparkSession, path)


def discard_all(spark: SparkSession) -> None:
    """Delete all that this application has left in the shared folder; its results can't be read any more."""
    _delete(spark, shared_folder(spark))


def _delete(spark: SparkSession, path: str) -> None:
    hadoop = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    with contextlib.suppress(Exception):
        hadoop.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(hadoop, True)
