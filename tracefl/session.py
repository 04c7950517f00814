"""Sessions for tests and benches, and the package on the executors."""

from __future__ import annotations

import os
import tempfile
import zipfile
from pathlib import Path

from pyspark.sql import SparkSession

ROOT = Path(__file__).resolve().parent.parent
_shipped: set[str] = set()


def local(cores: int | str = "*", partitions: int = 8, memory: str = "8g") -> SparkSession:
    return (
        SparkSession.builder.master(f"local[{cores}]")
        .config("spark.sql.shuffle.partitions", partitions)
        .config("spark.driver.memory", memory)
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.executorEnv.PYTHONPATH", str(ROOT))
        .getOrCreate()
    )


def ensure_importable(spark: SparkSession) -> None:
    """Sends the package to the executors unless the environment they inherit already has it."""
    context = spark.sparkContext
    paths = [os.getcwd(), *os.environ.get("PYTHONPATH", "").split(os.pathsep)]
    if context.applicationId in _shipped or any(p and os.path.realpath(p) == str(ROOT) for p in paths):
        return
    archive = Path(tempfile.mkdtemp(prefix="tracefl-")) / "tracefl_package.zip"
    with zipfile.ZipFile(archive, "w") as z:
        for p in ROOT.joinpath("tracefl").rglob("*.py"):
            z.write(p, p.relative_to(ROOT))
        if (pipeline := ROOT / "corpus_pipeline.py").exists():
            z.write(pipeline, pipeline.name)
    context.addPyFile(str(archive))
    _shipped.add(context.applicationId)
