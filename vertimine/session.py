"""A local session with the settings the engine is tested under; on a cluster the caller's session is used as it is."""

import pathlib
import tempfile
import zipfile

from pyspark.sql import SparkSession


def local_session(cores: int = 8, shuffle_partitions: int = 8, memory: str = "8g") -> SparkSession:
    spark = (
        SparkSession.builder.master(f"local[{cores}]")
        .config("spark.sql.shuffle.partitions", shuffle_partitions)
        .config("spark.driver.memory", memory)
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.ui.enabled", "false")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    return spark


_shipped: set[str] = set()


def ship(spark: SparkSession) -> None:
    """Give this package to the executors' Python, once per application: they need not have it installed or on their path."""
    context = spark.sparkContext
    if context.applicationId in _shipped:
        return
    top = pathlib.Path(__file__).parent
    path = pathlib.Path(tempfile.mkdtemp()) / f"{top.name}-{context.applicationId}.zip"  # read by Spark on the driver only
    with zipfile.ZipFile(path, "w") as z:
        for f in sorted(top.rglob("*.py")):
            z.write(f, f.relative_to(top.parent))
    context.addPyFile(str(path))
    _shipped.add(context.applicationId)
