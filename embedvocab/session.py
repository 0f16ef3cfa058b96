"""Sessions, and the package for executors that do not have it installed."""

from __future__ import annotations

import tempfile
import zipfile
from pathlib import Path

from pyspark.sql import SparkSession


def build(app: str = "embedvocab", cores: int = 8, partitions: int = 8) -> SparkSession:
    """A local session for tests and benchmarks; on a cluster the driver brings its own."""
    spark = (
        SparkSession.builder.master(f"local[{cores}]").appName(app)
        .config("spark.sql.shuffle.partitions", str(partitions)).config("spark.sql.session.timeZone", "UTC")
        .config("spark.sql.adaptive.enabled", "true").config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false").config("spark.driver.memory", "8g").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    ship(spark)
    return spark


def ship(spark: SparkSession) -> None:
    """Sends the package's source to the executors, once a context."""
    context = spark.sparkContext
    if getattr(context, "_embedvocab_shipped", False):
        return
    package = Path(__file__).resolve().parent
    at = Path(tempfile.mkdtemp(prefix="embedvocab-")) / "embedvocab_source.zip"
    with zipfile.ZipFile(at, "w") as z:
        for f in sorted(package.rglob("*.py")):
            z.write(f, f"embedvocab/{f.relative_to(package)}")
    context.addPyFile(str(at))
    context._embedvocab_shipped = True
