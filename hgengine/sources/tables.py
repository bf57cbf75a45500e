"""Tables of a scale directory, membership files, and layouts to save a hypergraph in."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from hgengine.model import HyperFrame
from hgengine.session import ship


def load(spark: SparkSession, sf_dir: str, name: str, columns: list[str] | None = None, where: str | Column | None = None) -> DataFrame:
    """A Parquet table; columns and predicate reach the scan."""
    ship(spark)
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    df = df if where is None else df.where(where)
    return df.select(*columns) if columns else df


def read_membership(spark: SparkSession, path: str, fmt: str = "csv", layout: str = "pairs", sep: str = "\t") -> HyperFrame:
    """pairs: a vertex id and a hyperedge id in each row (csv, json, orc, parquet). lines: a text line is a hyperedge,
    its words are members, and its id counts lines (not in order)."""
    if layout == "lines":
        rows = spark.read.text(path).select(F.monotonically_increasing_id().alias("hid"), F.explode(F.split("value", r"\s+")).alias("v")).where("v <> ''")
        return HyperFrame.from_table(rows.select(F.col("v").cast("long").alias("vid"), "hid"), "vid", "hid")
    reader = spark.read.schema("vid long, hid long")
    df = reader.csv(path, sep=sep) if fmt == "csv" else reader.format(fmt).load(path)
    return HyperFrame.from_table(df, "vid", "hid")


def save(hf: HyperFrame, path: str, by_part: bool = False) -> None:
    """Three Parquet tables under path; memberships in a folder of each part if they are placed and parts are few."""
    hf.vertices.write.mode("overwrite").parquet(f"{path}/vertices")
    hf.hyperedges.write.mode("overwrite").parquet(f"{path}/hyperedges")
    writer = hf.incidence.write.mode("overwrite")
    (writer.partitionBy("part") if by_part else writer).parquet(f"{path}/incidence")


def save_bucketed(hf: HyperFrame, name: str, buckets: int) -> None:
    """Memberships as two tables bucketed and sorted by either id: joins on them need no shuffle."""
    for side in ("vid", "hid"):
        hf.incidence.write.mode("overwrite").bucketBy(buckets, side).sortBy(side).saveAsTable(f"{name}_by_{side}")


def restore(spark: SparkSession, path: str) -> HyperFrame:
    return HyperFrame(*(spark.read.parquet(f"{path}/{t}") for t in ("vertices", "hyperedges", "incidence")))
