"""Sessions for tests and benches, table loading and shipping of the package to executors."""

from __future__ import annotations

import os
import tempfile
import uuid
import zipfile
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

ROOT = Path(__file__).resolve().parent


def local_session(cpus: int | str = 8, shuffle_partitions: int = 8, **conf: str) -> SparkSession:
    """A local session; a session that is given from outside is used as it is."""
    os.environ["PYTHONPATH"] = f"{ROOT.parent}:{os.environ.get('PYTHONPATH', '')}"
    builder = SparkSession.builder.master(f"local[{cpus}]").config("spark.sql.shuffle.partitions", str(shuffle_partitions))
    builder = builder.config("spark.sql.session.timeZone", "UTC").config("spark.ui.enabled", "false").config("spark.driver.memory", "8g")
    for key, value in conf.items():
        builder = builder.config(key, value)
    return builder.getOrCreate()


_SHIPPED: set[str] = set()


def ship(spark: SparkSession) -> None:
    """Give executors the package once a session, in case they do not share the driver's Python path."""
    key = spark.sparkContext.applicationId
    if key in _SHIPPED:
        return
    _SHIPPED.add(key)
    path = Path(tempfile.mkdtemp(prefix="hubgraph-")) / "hubgraph.zip"
    with zipfile.ZipFile(path, "w") as z:
        for f in ROOT.rglob("*.py"):
            z.write(f, f.relative_to(ROOT.parent))
    spark.sparkContext.addPyFile(str(path))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A given table; timestamps without a zone are read as UTC."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    for field in df.schema:
        if field.dataType.typeName() == "timestamp_ntz":
            df = df.withColumn(field.name, F.col(field.name).cast("timestamp"))
    return df


def shared_dir(spark: SparkSession) -> str:
    """The folder that all executors share: spark.checkpoint.dir, or a temporary one where it is unset (tests)."""
    path = spark.conf.get("spark.checkpoint.dir", None)
    if not path:
        path = "file://" + os.path.join(tempfile.gettempdir(), "checkpoints")
    return path.rstrip("/")


ARROW_BYTES = "spark.sql.execution.arrow.maxBytesPerBatch"


def small_batches(spark: SparkSession, most: int = 4 << 20) -> None:
    """Arrow batches of no more than `most` bytes: a runtime setting of the session, only ever lowered."""
    held = spark.conf.get(ARROW_BYTES).lower().removesuffix("b")
    if not held.isdigit() or not 0 < int(held) <= most:
        spark.conf.set(ARROW_BYTES, f"{most}b")


def stage(df: DataFrame, by: str | None = None, **options: str) -> DataFrame:
    """Write df to the shared folder, with options of Parquet, and read it back, which cuts lineage and survives lost executors."""
    path = f"{shared_dir(df.sparkSession)}/hubgraph-{uuid.uuid4().hex}"
    (df.write.partitionBy(by) if by else df.write).options(**options).parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
