"""Session defaults, and shipping of this package to the Python workers."""

from __future__ import annotations

import gc
import io
import os
import tempfile
import zipfile
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession

_SHIPPED: set[str] = set()


def local(cores: str = "*", partitions: int = 8, memory: str = "8g") -> SparkSession:
    """A local session for tests and benches; on a cluster use the session that is given."""
    spark = (
        SparkSession.builder.master(f"local[{cores}]")
        .config("spark.driver.memory", memory)
        .config("spark.sql.shuffle.partitions", str(partitions))
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.ui.enabled", "false")
        .config("spark.sql.adaptive.enabled", "true")
        .config("spark.sql.warehouse.dir", tempfile.mkdtemp(prefix="gridmin-warehouse-"))
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    return spark


def shared_base(spark: SparkSession) -> str:
    """The folder named by spark.checkpoint.dir. Where that is unset, a local session uses one below its warehouse; on a cluster
    this raises, as no other folder is known to be shared."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if base:
        return base.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
    return spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_stage"


def ship(spark: SparkSession) -> None:
    """Send this package to the executors, once an application, so that their Python workers can import it."""
    app = spark.sparkContext.applicationId
    if app in _SHIPPED:
        return
    root = Path(__file__).resolve().parent
    data = io.BytesIO()
    with zipfile.ZipFile(data, "w", zipfile.ZIP_DEFLATED) as z:
        for f in sorted(root.rglob("*.py")):
            z.write(f, f.relative_to(root.parent))
    path = os.path.join(tempfile.mkdtemp(prefix="gridmin-"), "gridmin.zip")  # read by the driver's own file server only
    Path(path).write_bytes(data.getvalue())
    spark.sparkContext.addPyFile(path)
    _SHIPPED.add(app)


def map_arrow(df: DataFrame, fn, schema) -> DataFrame:
    """``df.mapInArrow`` with this package importable on the workers."""
    ship(df.sparkSession)
    return df.mapInArrow(fn, schema)


def tidy(spark: SparkSession) -> None:
    """Have Spark remove the shuffles and broadcasts that nothing refers to any more; else they stay until the driver collects its garbage."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()
