"""Vertex programs as Column expressions: nothing of a round runs row by row in Python."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class VertexProgram:
    """A synchronous program over one attribute (any type, structs included).

    ``message`` gives what a source sends along an edge, from its columns ``attr`` and
    ``out_deg``; ``fold`` combines messages and partial results alike, so it must be
    commutative and associative; ``apply(attr, inc)`` is the new attribute, ``inc`` null
    where nothing came.  ``monotone`` says that what an unchanged source once sent stays in
    its destinations, so that cells of inactive bands may be skipped.
    """

    name: str
    init: Callable[[DataFrame], DataFrame]  # vertices -> vid, band, out_deg, attr, active
    message: Callable[[Column, Column], Column]
    fold: Callable[[Column], Column]
    apply: Callable[[Column, Column], Column]
    monotone: bool
    sends: Callable[[Column], Column] | None = None  # which sources send at all
    changed: Callable[[Column, Column], Column] | None = None  # (old, new)
    extra: Callable[[DataFrame], DataFrame] | None = None  # one row of globals for ``apply_extra``
    apply_extra: Callable[[Column, Column], Column] | None = None
    kind: str = "targeted"  # global: every band is active in every round, so none is looked for or skipped
    pair: Callable[[Column, Column], Column] | None = None  # ``fold`` of two values, where it isn't a known one

    def combine(self, a: Column, b: Column) -> Column | None:
        """The fold of two increments, either of them null; None if the program can't say."""
        both = self.pair or {F.sum: lambda x, y: x + y, F.min: F.least, F.max: F.greatest, F.bool_or: lambda x, y: x | y}.get(self.fold)
        return both and F.coalesce(both(a, b), a, b)

    def differs(self, old: Column, new: Column) -> Column:
        return self.changed(old, new) if self.changed else ~old.eqNullSafe(new)


def with_attr(vertices: DataFrame, attr: Column, active: Column | None = None) -> DataFrame:
    return vertices.select("vid", "band", "out_deg", attr.alias("attr"), (F.lit(True) if active is None else active).alias("changed"))


def started_from(program: VertexProgram, values: DataFrame, key: str = "vid") -> VertexProgram:
    """``program`` with start values from outside: ``values`` has ``key`` (vid or raw_key), ``attr``
    and perhaps ``active``.  Vertices it doesn't name start as the program says."""
    has_active = "active" in values.columns
    given = values.select(F.col(key).alias("_key"), F.col("attr").alias("_attr"), (F.coalesce(F.col("active"), F.lit(True)) if has_active else F.lit(True)).alias("_active"))

    def init(vertices: DataFrame) -> DataFrame:
        own = program.init(vertices)
        named = own if key == "vid" else own.join(vertices.select("vid", key), "vid")
        met = named.join(given, F.col(key) == F.col("_key"), "left")
        known = F.col("_key").isNotNull()
        return met.select("vid", "band", "out_deg", F.when(known, F.col("_attr")).otherwise(F.col("attr")).cast(own.schema["attr"].dataType).alias("attr"), F.when(known, F.col("_active")).otherwise(F.col("changed")).alias("changed"))

    return replace(program, name=f"{program.name}-from", init=init)
