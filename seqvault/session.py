"""Sessions for tests and benches, the shared work folder, and shipping this package to executors."""

from __future__ import annotations

import os
import tempfile
import zipfile
from pathlib import Path

from pyspark.sql import SparkSession

#: Used only by local masters that name no spark.checkpoint.dir (tests, a laptop).
LOCAL_SHARED = "/tmp/checkpoints/seqvault"
#: Bytes of an Arrow batch between Spark and a Python worker, unless the session names another number: rows are whole texts.
BATCH_BYTES, BATCH_SETTING = 8 << 20, "spark.sql.execution.arrow.maxBytesPerBatch"


def local_session(cpus: int = 8, memory: str = "8g", partitions: int = 8, **conf: str) -> SparkSession:
    """A local session with the settings that tests and bench use."""
    builder = SparkSession.builder.master(f"local[{cpus}]").appName("seqvault")
    settings = {
        "spark.sql.shuffle.partitions": str(partitions),
        "spark.driver.memory": memory,
        "spark.ui.enabled": "false",
        "spark.ui.showConsoleProgress": "false",
        "spark.sql.session.timeZone": "UTC",
        "spark.sql.execution.arrow.pyspark.enabled": "true",
    }
    for key, value in (settings | conf).items():
        builder = builder.config(key, value)
    spark = builder.getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, or a local one where a local master has none."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    os.makedirs(LOCAL_SHARED, exist_ok=True)
    return f"file://{LOCAL_SHARED}"


def ship_package(spark: SparkSession) -> None:
    """Send this package to the executors once per application, so that Python workers can import it anywhere.

    Batches for workers are kept small too: Spark's default of 64 MB a batch counts several times in a task.
    """
    context = spark.sparkContext
    if spark.conf.get(BATCH_SETTING) in ("64MB", "67108864", "67108864b"):
        spark.conf.set(BATCH_SETTING, str(BATCH_BYTES))
    if getattr(context, "_seqvault_shipped", False):
        return
    root = Path(__file__).resolve().parent
    target = Path(tempfile.mkdtemp(prefix="seqvault-")) / "seqvault.zip"
    with zipfile.ZipFile(target, "w", zipfile.ZIP_DEFLATED) as out:
        for path in sorted(root.rglob("*.py")):
            out.write(path, path.relative_to(root.parent))
    context.addPyFile(str(target))
    context._seqvault_shipped = True
