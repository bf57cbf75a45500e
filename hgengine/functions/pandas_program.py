"""Programs as Python procedures over batches of nodes, for what columns cannot say. Messages still combine in SQL."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from hgengine.model import HyperFrame
from hgengine.session import cut, ship


@dataclass(frozen=True)
class PandasProgram:
    """fn(batch with id, the state column and message, step) -> id, state, sent, send; combine: an SQL aggregate."""

    fn: Callable[[pd.DataFrame, int], pd.DataFrame]
    combine: Callable[[Column], Column]


def _stepped(nodes: DataFrame, messages: DataFrame, program: PandasProgram, key: str, state: str, step: int) -> DataFrame:
    fn = program.fn

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            yield fn(pdf, step)

    kind = nodes.schema[state].dataType.simpleString()
    joined = nodes.select(F.col(key).alias("id"), state).join(messages, F.col("id") == F.col("_to"), "left").select("id", state, "message")
    return cut(joined.mapInPandas(run, f"id long, {state} {kind}, sent {kind}, send boolean"))


def iterate_pandas(hf: HyperFrame, vertices: DataFrame, hyperedges: DataFrame, vertex: PandasProgram, hyperedge: PandasProgram, max_rounds: int, state: str = "hops") -> DataFrame:
    """The vertices after rounds of both sides, until no vertex sends. Vertices with a state send it first."""
    ship(hf.incidence.sparkSession)
    inc = hf.incidence.select("vid", "hid").persist()
    first = vertices.select(F.col("vid").alias("id"), state, F.col(state).alias("message"))
    kind = vertices.schema[state].dataType.simpleString()

    def start(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            out = vertex.fn(pdf.assign(**{state: None if kind == "string" else float("nan")}), 0)
            yield out

    vs = cut(first.mapInPandas(start, f"id long, {state} {kind}, sent {kind}, send boolean"))
    hs = hyperedges
    for r in range(1, max_rounds + 1):
        told = vs.where("send").join(inc, F.col("id") == F.col("vid")).groupBy(F.col("hid").alias("_to")).agg(vertex.combine(F.col("sent")).alias("message"))
        hs = _stepped(hs, told, hyperedge, "hid", state, r)
        heard = hs.where("send").join(inc, F.col("id") == F.col("hid")).groupBy(F.col("vid").alias("_to")).agg(hyperedge.combine(F.col("sent")).alias("message"))
        vs = _stepped(vs.withColumnRenamed("id", "vid"), heard, vertex, "vid", state, r)
        hs = hs.select(F.col("id").alias("hid"), state)
        if not vs.where("send").limit(1).count():
            break
    return vs.select(F.col("id").alias("vid"), state)
