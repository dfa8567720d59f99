"""Secret scans over an incremental blob ledger. Built-in functions only.

A *blob* is a text, named by its SHA-256. The ledger holds (blob, rule version, spans) for all that was scanned; a run
scans each blob that the ledger lacks for the version at hand once, writes the new rows to the ledger, and joins findings to
every path that holds the blob. A ledger is a folder that every executor can reach; each run adds files to it.
"""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .spans import SPAN, find, has
from .storage import names_out, shared_dir

BASE = ["assign", "access", "hex"]
ADDED = ["pem", "jwt"]
RULE_VERSION = "2"
LEDGER = f"blob string, rule_version string, spans {SPAN}"


def secret_spans(text: Column) -> Column:
    """All spans of a text, kind by kind in the order of ``BASE + ADDED``, each kind by start; null counts as empty."""
    t = F.coalesce(text, F.lit(""))
    low = F.lower(t)
    head = r"""(?i:password|passwd|secret|token|api_?key)["']?\x20*+[:=]\x20*+["']?"""
    value = r"[A-Za-z0-9+/_.=-]++"
    return F.concat(
        find(t, "assign", head + value, has(low, "passw", "secret", "token", "api"), lambda v: F.length(F.regexp_extract(v, f"^{head}({value})", 1)) >= 6),
        find(t, "access", r"AKIA[A-Z0-9]{16,}+", has(t, "AKIA")),
        find(t, "hex", r"[0-9a-f]{24,}+", t.rlike("[0-9a-f]{24}")),
        find(t, "pem", r"-----BEGIN [A-Z ]{0,40}PRIVATE KEY-----", has(t, "PRIVATE KEY-----")),
        find(t, "jwt", r"eyJ[A-Za-z0-9_-]{8,}+\.eyJ[A-Za-z0-9_-]{8,}+\.[A-Za-z0-9_-]{8,}+", has(t, "eyJ")),
    )


def blob_name(text: Column) -> Column:
    return F.sha2(F.coalesce(text, F.lit("")).cast("binary"), 256)


def scan_unseen(blobs: DataFrame, ledger: DataFrame | None = None, rule_version: str = RULE_VERSION) -> DataFrame:
    """``blobs(blob, text)``, repeats allowed → new ledger rows, one for each blob that ``ledger`` lacks at this version."""
    # Copies are combined before they move, then what is known goes.
    once = blobs.groupBy("blob").agg(F.first("text").alias("text"))
    if ledger is not None:
        once = once.join(ledger.where(F.col("rule_version") == rule_version).select("blob").distinct(), "blob", "left_anti")
    return once.select("blob", F.lit(rule_version).alias("rule_version"), secret_spans(F.col("text")).alias("spans"))


def new_ledger(spark: SparkSession) -> str:
    """A place for a ledger in the shared folder."""
    return f"{shared_dir(spark)}/secret-ledger-{uuid.uuid4().hex}"


def read_ledger(spark: SparkSession, path: str) -> DataFrame:
    """The ledger's rows; none where nothing was written yet."""
    target = spark._jvm.org.apache.hadoop.fs.Path(path)
    if not target.getFileSystem(spark._jsc.hadoopConfiguration()).exists(target):
        return spark.createDataFrame([], LEDGER)
    return spark.read.schema(LEDGER).parquet(path)


def scan_secrets(paths: DataFrame, ledger: str, text_col: str = "text", rule_version: str = RULE_VERSION) -> DataFrame:
    """``paths`` plus ``blob`` and ``spans``; what the ledger in the folder ``ledger`` lacks is scanned once and added to it.

    Every version of a file is a row of ``paths``. A null text is the empty blob; equal texts are scanned once; rows that
    repeat each get the findings; an empty table gives an empty result. Input columns named ``blob`` or ``spans`` come back with
    ``_in`` appended. A run that is broken off and started again finds what it has committed.
    """
    spark, given = paths.sparkSession, paths.columns
    own = paths.select(*[F.col(f"`{c}`").alias(f"in_{i}") for i, c in enumerate(given)])
    text = F.col(f"in_{given.index(text_col)}")
    named = own.withColumn("blob", blob_name(text))
    scan_unseen(named.select("blob", text.alias("text")), read_ledger(spark, ledger), rule_version).write.mode("append").parquet(ledger)
    found = read_ledger(spark, ledger).where(F.col("rule_version") == rule_version).where(F.size("spans") > 0).select("blob", "spans")
    out = named.join(found, "blob", "left").withColumn("spans", F.coalesce("spans", F.array().cast(SPAN)))
    return out.select(*[F.col(f"in_{i}").alias(c) for i, c in enumerate(names_out(given, ["blob", "spans"]))], "blob", "spans")
