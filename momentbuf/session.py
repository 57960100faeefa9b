"""Making the package known to executors, and a session for local use."""

from __future__ import annotations

import os
import tempfile
import zipfile

from pyspark.sql import SparkSession

ROOT = os.path.dirname(os.path.dirname(os.path.abspath(__file__)))


def ship(spark: SparkSession) -> None:
    """Give executors this package, unless their Python path has it already."""
    on_path = {os.path.abspath(p) for p in [*os.environ.get("PYTHONPATH", "").split(":"), os.getcwd()] if p}
    if ROOT in on_path or getattr(spark.sparkContext, "_momentbuf_shipped", False):
        return
    out = os.path.join(tempfile.mkdtemp(prefix="momentbuf"), "momentbuf.zip")
    with zipfile.ZipFile(out, "w") as z:
        for d, _, names in os.walk(os.path.join(ROOT, "momentbuf")):
            for n in names:
                if n.endswith(".py"):
                    z.write(p := os.path.join(d, n), os.path.relpath(p, ROOT))
    spark.sparkContext.addPyFile(out)
    spark.sparkContext._momentbuf_shipped = True


def local_session(cores: str = "*", partitions: int = 8) -> SparkSession:
    return SparkSession.builder.master(f"local[{cores}]").config("spark.sql.shuffle.partitions", partitions).config("spark.sql.session.timeZone", "UTC").config("spark.ui.enabled", "false").getOrCreate()
