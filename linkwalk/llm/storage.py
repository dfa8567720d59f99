"""Shared-folder tables: lineage is cut by writing Parquet where every executor can read it."""

from __future__ import annotations

import gc
import re
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def names_out(given: list[str], added: list[str]) -> list[str]:
    """Names under which input columns come back: their own, or with ``_in`` appended (again while that is taken too) where an
    operator adds a column of that name. Case does not tell names apart."""
    taken, out = {c.lower() for c in [*given, *added]}, []
    for c in given:
        name = c
        if c.lower() in {a.lower() for a in added}:
            while name.lower() in taken:
                name += "_in"
            taken.add(name.lower())
        out.append(name)
    return out


def shared_dir(spark: SparkSession) -> str:
    """The folder named by ``spark.checkpoint.dir``; a temporary one only where that setting is absent and Spark runs in this
    one process (local tests). On a cluster without the setting this raises: no local folder is shared there."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    held = spark.sparkContext._jsc.sc().getCheckpointDir()
    if held.isDefined():
        return held.get().rstrip("/")
    if not re.match(r"local(\[|$)", spark.sparkContext.master):
        raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="linkwalk-"))
    return spark.sparkContext._jsc.sc().getCheckpointDir().get().rstrip("/")


def cut(df: DataFrame) -> DataFrame:
    """Writes ``df`` once and returns a reader of it: later plans start at the files, whatever executors are lost."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/linkwalk-{uuid.uuid4().hex}"
    df.write.parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._linkwalk_path = path
    return out


def discard(df: DataFrame) -> None:
    """Deletes the files behind a table made by :func:`cut` once nothing reads it any more."""
    path = getattr(df, "_linkwalk_path", None)
    if path:
        jvm, conf = df.sparkSession._jvm, df.sparkSession._jsc.hadoopConfiguration()
        target = jvm.org.apache.hadoop.fs.Path(path)
        target.getFileSystem(conf).delete(target, True)


def release(spark: SparkSession) -> None:
    """Has the driver collect its garbage, upon which Spark removes shuffle files that only finished plans used. Between large
    steps this bounds the disk that executors hold; otherwise the files stay until the driver happens to collect. Spark holds on
    to the plan that ran last, so an empty one runs first."""
    spark.range(0).count()
    gc.collect()
    spark._jvm.System.gc()


def with_uid(df: DataFrame, id_col: str, *ties: str, name: str = "uid") -> DataFrame:
    """Adds a unique non-null long that sorts as ``id_col`` does.

    Where ids are unique and not null, it is the id. Otherwise a copy of the rows is written in id order (nulls last, then
    ``ties``) and numbered, so repeated rows stay apart and null ids come after all others.
    """
    held = df.select(F.count(F.lit(1)).alias("n"), F.count_distinct(id_col).alias("d")).first()
    if held["n"] == held["d"] and dict(df.dtypes)[id_col] in ("bigint", "int", "smallint", "tinyint"):
        return df.withColumn(name, F.col(id_col).cast("long"))
    keys = [F.col(id_col).asc_nulls_last(), *[F.xxhash64(F.col(t)) for t in ties]]
    ranged = df.repartitionByRange(*keys).sortWithinPartitions(*keys)
    return cut(ranged.withColumn(name, F.monotonically_increasing_id()))
