"""Programs of the two sides: what a node keeps, what it sends, when, and how messages to one node combine.

Expressions are columns, so a superstep is one plan of joins and aggregates:
state("x") is the node's attribute, msg("y") its combined message (null without one), nid() its id, step() the round,
dst_id() the receiver's id and edge("w") an attribute of the membership, for messages that depend on the receiver.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field
from enum import Enum

from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql import types as T


def state(name: str) -> Column:
    return F.col(name)


def msg(name: str) -> Column:
    return F.col(f"_msg_{name}")


def nid() -> Column:
    return F.col("_id")


def step() -> Column:
    return F.col("_step")


def dst_id() -> Column:
    return F.col("_dst")


def edge(name: str) -> Column:
    return F.col(f"_edge_{name}")


class Combiner(Enum):
    SUM = "sum"
    MIN = "min"
    MAX = "max"
    COUNT = "count"
    BOOL_AND = "bool_and"
    BOOL_OR = "bool_or"
    CONCAT = "concat"
    SET_UNION = "set_union"
    MAP_SUM = "map_sum"

    @property
    def again(self) -> Combiner:
        """What combines combined messages."""
        return Combiner.SUM if self is Combiner.COUNT else self

    def of(self, column: Column) -> Column:
        if self is Combiner.CONCAT:
            return F.flatten(F.collect_list(column))
        if self is Combiner.SET_UNION:
            return F.array_distinct(F.flatten(F.collect_set(column)))
        if self is Combiner.MAP_SUM:
            entries = F.flatten(F.collect_list(F.map_entries(column)))
            keys = F.array_distinct(F.transform(entries, lambda e: e["key"]))
            return F.map_from_entries(F.transform(keys, lambda k: F.struct(k, F.aggregate(F.filter(entries, lambda e: e["key"] == k), F.lit(0.0), lambda s, e: s + e["value"]))))
        return {"sum": F.sum, "min": F.min, "max": F.max, "count": F.count, "bool_and": F.bool_and, "bool_or": F.bool_or}[self.value](column)


@dataclass(frozen=True)
class Custom:
    """A combiner given as an aggregate function of a column, and one that combines its results (itself if left out)."""

    aggregate: Callable[[Column], Column]
    merge: Callable[[Column], Column] | None = None

    @property
    def again(self) -> Custom:
        return Custom(self.merge or self.aggregate)

    def of(self, column: Column) -> Column:
        return self.aggregate(column)


def first_by(order: str) -> Custom:
    """Of struct messages, the one with the smallest field."""
    return Custom(lambda c: F.min_by(c, c[order]))


def infer_combiners(schema: T.StructType, hints: dict[str, Combiner | Custom] | None = None) -> dict[str, Combiner | Custom]:
    """The combiner of each field of a message by its type: numbers add, arrays concatenate, maps add by key, booleans
    hold if any does, structs go field by field. Others need a hint."""
    found: dict[str, Combiner | Custom] = {}
    for f in schema.fields:
        kind = f.dataType
        if hints and f.name in hints:
            found[f.name] = hints[f.name]
        elif isinstance(kind, T.NumericType):
            found[f.name] = Combiner.SUM
        elif isinstance(kind, T.BooleanType):
            found[f.name] = Combiner.BOOL_OR
        elif isinstance(kind, T.ArrayType):
            found[f.name] = Combiner.CONCAT
        elif isinstance(kind, T.MapType):
            found[f.name] = Combiner.MAP_SUM
        elif isinstance(kind, T.StructType):
            inner = infer_combiners(kind)
            found[f.name] = Custom(lambda c, inner=inner: F.struct(*(k.of(c[n]).alias(n) for n, k in inner.items())))
        else:
            raise TypeError(f"no combiner for {f.name} of type {kind.simpleString()}: give a hint")
    return found


@dataclass(frozen=True)
class Program:
    """state: new attributes; emit: message fields; when: whether the node sends after this step (true if left out);
    to: a predicate over receivers; combine: a combiner for each field, else inferred from its type."""

    emit: dict[str, Column]
    state: dict[str, Column] = field(default_factory=dict)
    when: Column | None = None
    to: Column | None = None
    combine: dict[str, Combiner | Custom] | None = None

    @property
    def by_receiver(self) -> bool:
        """Whether messages must be computed for each membership rather than once for each node."""
        return self.to is not None or any(mark in str(c) for c in self.emit.values() for mark in ("_dst", "_edge_"))
