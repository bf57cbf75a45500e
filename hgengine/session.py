"""Session helpers: a local profile for tests, and the package's own code for Python workers."""

from __future__ import annotations

import tempfile
import uuid
import zipfile
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Most rows that a broadcast side may have; counted before the hint is given.
BROADCAST_ROWS = 200_000

HERE = Path(__file__).resolve().parent


def local(cores: str = "*", partitions: int = 8, memory: str = "8g", **conf: str) -> SparkSession:
    """A local session; on a cluster use the session that is given."""
    builder = SparkSession.builder.master(f"local[{cores}]").appName("hgengine")
    settings = {"spark.sql.shuffle.partitions": str(partitions), "spark.driver.memory": memory, "spark.ui.enabled": "false", "spark.ui.showConsoleProgress": "false", "spark.sql.session.timeZone": "UTC"}
    return builder.config(map=settings | conf).getOrCreate()


def ship(spark: SparkSession) -> None:
    """Give Python workers this package through Spark's file server, once for each context."""
    context = spark.sparkContext
    if getattr(ship, "to", None) == context.applicationId:
        return
    # stays as long as the driver: executors that start later fetch it too
    path = Path(tempfile.mkdtemp(prefix="hgengine-")) / "hgengine_code.zip"
    with zipfile.ZipFile(path, "w") as out:
        for p in sorted(HERE.rglob("*.py")):
            out.write(p, p.relative_to(HERE.parent))
    context.addPyFile(str(path))
    ship.to = context.applicationId


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir. On one machine, where it is unset, one made here;
    a cluster without it is an error, as each machine would write into a folder of its own."""
    path = spark.conf.get("spark.checkpoint.dir", None)
    if not path:
        if not spark.sparkContext.master.startswith("local["):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        path = getattr(shared_dir, "made", None) or tempfile.mkdtemp(prefix="shared-")
        shared_dir.made = path
    if spark.sparkContext._jsc.sc().getCheckpointDir().isEmpty():
        spark.sparkContext.setCheckpointDir(path)
    return path


def scratch(spark: SparkSession, label: str) -> str:
    return f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"


def cut(df: DataFrame) -> DataFrame:
    """Write df to the shared folder and read it back: the lineage ends there, and a lost executor loses nothing."""
    spark = df.sparkSession
    path = scratch(spark, "cut")
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def small(df: DataFrame, rows: int = BROADCAST_ROWS) -> DataFrame:
    """Hint a broadcast of df (cut before) if its counted rows are within the bound; else leave it to a shuffled join."""
    return F.broadcast(df) if df.count() <= rows else df
