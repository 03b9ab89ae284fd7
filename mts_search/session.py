"""Makes the package's code reachable for Python workers of a running session."""

from __future__ import annotations

import tempfile
import uuid
import zipfile
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

_SHIPPED: set[str] = set()


def ship(spark: SparkSession) -> None:
    """Send this package to the executors once per application, through Spark's own file server."""
    app = spark.sparkContext.applicationId
    if app in _SHIPPED:
        return
    root = Path(__file__).resolve().parent
    target = Path(tempfile.mkdtemp(prefix="pkg_")) / f"{root.name}.zip"
    with zipfile.ZipFile(target, "w") as z:
        for f in sorted(root.rglob("*.py")):
            z.write(f, f.relative_to(root.parent))
    spark.sparkContext.addPyFile(str(target))
    _SHIPPED.add(app)


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``; a local one only where it is unset, as in tests."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not found:
        found = "file://" + tempfile.mkdtemp(prefix="shared_")
        spark.sparkContext.setCheckpointDir(found)
    return found.rstrip("/")


def written(df: DataFrame, tag: str, group_bytes: int | None = None) -> DataFrame:
    """``df`` as a Parquet table in the shared folder, read back: its lineage ends there.

    ``group_bytes``: size of row groups; a reader's batch lies within one, so small ones bound its memory for long rows.
    """
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/{tag}_{uuid.uuid4().hex}"
    (df.write.option("parquet.block.size", group_bytes) if group_bytes else df.write).parquet(path)
    return spark.read.schema(df.schema).parquet(path)
