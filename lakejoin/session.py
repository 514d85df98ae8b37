"""What the engine needs of a running session."""

from __future__ import annotations

import os
import re
import tempfile
import uuid
import zipfile
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

_NAME = "lakejoin-package.zip"


#: Rows and bytes of an Arrow batch: a row may be a long text, and a batch is held on both sides at once.
BATCH_ROWS, BATCH_BYTES = 2_000, 8 << 20


def ship(spark: SparkSession) -> None:
    """Send this package to the executors once a context, so that Python workers can import it anywhere; and lower the session's
    limits of Arrow batches to ours, where they are above."""
    for name, most in (("maxRecordsPerBatch", BATCH_ROWS), ("maxBytesPerBatch", BATCH_BYTES)):
        key = f"spark.sql.execution.arrow.{name}"
        now = re.fullmatch(r"(-?\d+)b?", spark.conf.get(key))
        if now is None or not 0 < int(now[1]) <= most:
            spark.conf.set(key, str(most))
    sc = spark.sparkContext
    if _NAME in sc._python_includes:
        return
    root = Path(__file__).resolve().parent
    path = os.path.join(tempfile.mkdtemp(prefix="lakejoin-"), _NAME)
    with zipfile.ZipFile(path, "w") as z:
        for file in sorted(root.rglob("*.py")):
            z.write(file, f"{root.name}/{file.relative_to(root)}")
    sc.addPyFile(path)


def shared_dir(spark: SparkSession) -> str:
    """The checkpoint folder of the session. Where none is set, a temporary one serves a local master (tests, one machine); on a
    cluster that folder would be seen by the driver alone, so a missing setting is an error there."""
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        named = spark.conf.get("spark.checkpoint.dir", None)
        if named is None and not re.fullmatch(r"local(\[.*\])?", sc.master):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        sc.setCheckpointDir(named or tempfile.mkdtemp(prefix="lakejoin-"))
    return sc.getCheckpointDir()


def stored(df: DataFrame) -> DataFrame:
    """End the lineage of a frame: compressed Parquet in the shared folder, read back with its size known."""
    path = f"{shared_dir(df.sparkSession)}/table-{uuid.uuid4().hex}"
    df.write.parquet(path)
    out = df.sparkSession.read.parquet(path)
    out.stored_in = path
    return out


def dropped(*tables: DataFrame) -> None:
    """Delete tables of ``stored`` that nothing reads any more; disk then holds no more than the step at hand needs."""
    for t in tables:
        spark = t.sparkSession
        path = spark._jvm.org.apache.hadoop.fs.Path(t.stored_in)
        path.getFileSystem(spark._jsparkSession.sessionState().newHadoopConf()).delete(path, True)


def swept(spark: SparkSession) -> None:
    """Shuffle files go once the driver's JVM has collected the plans they belong to, which it may not do for long: have it do so now."""
    spark._jvm.System.gc()
