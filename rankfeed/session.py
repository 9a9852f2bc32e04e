"""What a session needs before Python workers on other machines can run functions of this package."""

from __future__ import annotations

import pathlib
import tempfile
import zipfile

from pyspark.sql import SparkSession


def ship(spark: SparkSession) -> SparkSession:
    """Send the package's source to the executors, once for each session; workers need not have it on their path."""
    context = spark.sparkContext
    if not getattr(context, "_rankfeed_shipped", False):
        package = pathlib.Path(__file__).resolve().parent
        archive = pathlib.Path(tempfile.mkdtemp(prefix="rankfeed-code-")) / "rankfeed.zip"
        with zipfile.ZipFile(archive, "w") as z:
            for source in sorted(package.rglob("*.py")):
                z.write(source, source.relative_to(package.parent))
        context.addPyFile(str(archive))
        context._rankfeed_shipped = True
    return spark
