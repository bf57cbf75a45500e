"""The hypergraph value: vertices, hyperedges and their incidence, each a DataFrame.

Vertex and hyperedge ids are separate spaces and are never put into one column.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class HyperFrame:
    """vertices (vid, attributes), hyperedges (hid, weight, attributes), incidence (vid, hid, multiplicity, attributes).

    Isolated vertices and empty hyperedges are legal."""

    vertices: DataFrame
    hyperedges: DataFrame
    incidence: DataFrame

    @staticmethod
    def from_table(df: DataFrame, vertex: str | Column, hyperedge: str | Column, weight: Column | None = None, incidence: dict[str, Column] | None = None, vertices: DataFrame | None = None, hyperedges: DataFrame | None = None) -> HyperFrame:
        """Distinct memberships of two key columns; repeats add to multiplicity. incidence: aggregates by name.

        vertices and hyperedges give attributes and members without a membership; else they are the keys that occur."""
        v, h = (F.col(c) if isinstance(c, str) else c for c in (vertex, hyperedge))
        rows = df.where(v.isNotNull() & h.isNotNull()).groupBy(v.alias("vid"), h.alias("hid"))
        inc = rows.agg(F.count("*").cast("int").alias("multiplicity"), *(c.alias(n) for n, c in (incidence or {}).items()))
        vs = inc.select("vid").distinct() if vertices is None else vertices
        hs = inc.select("hid").distinct() if hyperedges is None else hyperedges
        if weight is not None or "weight" not in hs.columns:
            hs = hs.withColumn("weight", (F.lit(1.0) if weight is None else weight).cast("double"))
        return HyperFrame(vs, hs, inc)

    @staticmethod
    def from_rows(spark, memberships: list[tuple[int, int]], weights: dict[int, float] | None = None, vertices: list[int] = (), hyperedges: list[int] = ()) -> HyperFrame:
        """From (vid, hid) pairs in memory; vertices and hyperedges add some without a membership."""
        inc = spark.createDataFrame(memberships, "vid long, hid long").groupBy("vid", "hid").agg(F.count("*").cast("int").alias("multiplicity"))
        vs = spark.createDataFrame([(v,) for v in sorted({v for v, _ in memberships} | set(vertices))], "vid long")
        hs = spark.createDataFrame([(h, float((weights or {}).get(h, 1.0))) for h in sorted({h for _, h in memberships} | set(hyperedges))], "hid long, weight double")
        return HyperFrame(vs, hs, inc)

    @staticmethod
    def from_arrays(df: DataFrame, hyperedge: str, members: str) -> HyperFrame:
        """A row is a hyperedge, an array column its members."""
        return HyperFrame.from_table(df.select(F.col(hyperedge).alias("_h"), F.explode(members).alias("_v")), "_v", "_h")

    @staticmethod
    def from_tokens(df: DataFrame, hyperedge: str, text: str, ids: bool = True) -> HyperFrame:
        """Lower-case words between single blanks are vertices: their hash, or with ids=False the words themselves."""
        word = F.explode(F.split(F.lower(F.col(text)), " "))
        rows = df.select(F.col(hyperedge).alias("_h"), word.alias("_w")).where("_w <> ''")
        return HyperFrame.from_table(rows, F.xxhash64("_w") if ids else F.col("_w"), "_h")

    @staticmethod
    def from_links(df: DataFrame, hyperedge: str, html: str) -> HyperFrame:
        """The targets of href="..." are vertices, by hash."""
        link = F.explode(F.regexp_extract_all(html, F.lit('href="([^"]*)"'), F.lit(1)))
        return HyperFrame.from_table(df.select(F.col(hyperedge).alias("_h"), link.alias("_l")), F.xxhash64("_l"), "_h")

    @staticmethod
    def from_windows(df: DataFrame, vertex: str, time: str, unit: str = "hour", incidence: dict[str, Column] | None = None) -> HyperFrame:
        """Those seen in one unit of time are a hyperedge, named by the epoch seconds of its begin."""
        begin = F.unix_timestamp(F.date_trunc(unit, F.col(time).cast("timestamp")))
        return HyperFrame.from_table(df, F.col(vertex), begin, incidence=incidence)

    def with_vertex_columns(self, **columns: Column) -> HyperFrame:
        return replace(self, vertices=self.vertices.withColumns(columns))

    def with_hyperedge_columns(self, **columns: Column) -> HyperFrame:
        return replace(self, hyperedges=self.hyperedges.withColumns(columns))

    def restrict(self, vertex: Column | str | None = None, hyperedge: Column | str | None = None, incidence: Column | str | None = None, drop_empty: bool = False, drop_isolated: bool = False) -> HyperFrame:
        """The part whose members satisfy the predicates; memberships go with either end."""
        vs, hs, inc = self.vertices, self.hyperedges, self.incidence
        if incidence is not None:
            inc = inc.where(incidence)
        if vertex is not None:
            vs = vs.where(vertex)
            inc = inc.join(vs.select("vid"), "vid", "left_semi")
        if hyperedge is not None:
            hs = hs.where(hyperedge)
            inc = inc.join(hs.select("hid"), "hid", "left_semi")
        if drop_empty:
            hs = hs.join(inc.select("hid"), "hid", "left_semi")
        if drop_isolated:
            vs = vs.join(inc.select("vid"), "vid", "left_semi")
        return HyperFrame(vs, hs, inc)

    def dual(self) -> HyperFrame:
        """Vertices and hyperedges change places; vertices without a weight get 1."""
        hs = self.vertices.withColumnRenamed("vid", "hid")
        hs = hs if "weight" in hs.columns else hs.withColumn("weight", F.lit(1.0))
        inc = self.incidence.select(F.col("hid").alias("vid"), F.col("vid").alias("hid"), *(c for c in self.incidence.columns if c not in ("vid", "hid")))
        return HyperFrame(self.hyperedges.withColumnRenamed("hid", "vid"), hs, inc)

    def isolated_hyperedges(self) -> DataFrame:
        return self.hyperedges.select("hid").join(self.incidence, "hid", "left_anti")

    def isolated_vertices(self) -> DataFrame:
        return self.vertices.select("vid").join(self.incidence, "vid", "left_anti")

    def validate(self) -> dict[str, int]:
        """Counts of broken rules: repeated ids and memberships, memberships without an end, null keys."""
        inc = self.incidence
        checks = {
            "repeated_vertices": self.vertices.groupBy("vid").count().where("count > 1"),
            "repeated_hyperedges": self.hyperedges.groupBy("hid").count().where("count > 1"),
            "repeated_memberships": inc.groupBy("vid", "hid").count().where("count > 1"),
            "dangling_vertices": inc.join(self.vertices.select("vid"), "vid", "left_anti"),
            "dangling_hyperedges": inc.join(self.hyperedges.select("hid"), "hid", "left_anti"),
            "null_keys": inc.where("vid is null or hid is null"),
        }
        return {name: df.count() for name, df in checks.items()}

    def persist(self) -> HyperFrame:
        return HyperFrame(self.vertices.persist(), self.hyperedges.persist(), self.incidence.persist())
