"""Entity profiles and matching tasks.

A profile is (source, pid, text): all values of a record joined by a space, attribute names ignored, null values left out.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T


def as_text(column: Column, kind: T.DataType) -> Column:
    """A value as text: structs and arrays by their parts, maps by their values."""
    if isinstance(kind, T.StructType):
        return F.concat_ws(" ", *[as_text(column[f.name], f.dataType) for f in kind.fields])
    if isinstance(kind, T.ArrayType):
        return F.array_join(F.transform(column, lambda x: as_text(x, kind.elementType)), " ")
    if isinstance(kind, T.MapType):
        return as_text(F.map_values(column), T.ArrayType(kind.valueType))
    if isinstance(kind, T.BinaryType):
        raise ValueError("binary values have no text")
    return column.cast("string")


def to_profiles(df: DataFrame, id_col: str, cols: list[str] | None = None, source: str = "L") -> DataFrame:
    """Profiles of any table; without cols, of all columns but the id. Only the columns named are read."""
    kinds = {f.name: f.dataType for f in df.schema.fields}
    cols = [c for c in df.columns if c != id_col] if cols is None else cols
    if missing := [c for c in (id_col, *cols) if c not in kinds]:
        raise ValueError(f"no such column: {missing}")
    return df.select(F.lit(source).alias("source"), F.col(id_col).cast("long").alias("pid"), F.concat_ws(" ", *[as_text(F.col(c), kinds[c]) for c in cols]).alias("text"))


@dataclass(frozen=True)
class Task:
    """Profiles to match. kind: dedup (pairs of one source, l < r) or linkage (l from source L, r from source R)."""

    profiles: DataFrame
    kind: str

    def __post_init__(self) -> None:
        if self.kind not in ("dedup", "linkage"):
            raise ValueError(f"unknown kind: {self.kind}")

    @property
    def linkage(self) -> bool:
        return self.kind == "linkage"

    def checked(self) -> Task:
        """Raises if an id occurs twice in a source."""
        twice = self.profiles.groupBy("source", "pid").count().where("count > 1").first()
        if twice:
            raise ValueError(f"duplicate pid: {twice['source']} {twice['pid']}")
        return self

    def sizes(self) -> dict[str, int]:
        return {r["source"]: r["count"] for r in self.profiles.groupBy("source").count().collect()}


def Dedup(df: DataFrame) -> Task:  # noqa: N802
    return Task(df, "dedup")


def Linkage(left: DataFrame, right: DataFrame) -> Task:  # noqa: N802
    return Task(left.withColumn("source", F.lit("L")).unionByName(right.withColumn("source", F.lit("R"))), "linkage")


@dataclass(frozen=True)
class MultiSource:
    """More than two clean sources. single: one task over all, pairs inside a source dropped; series: a linkage of each pair of sources."""

    profiles: DataFrame
    strategy: str = "single"

    def tasks(self) -> list[Task]:
        if self.strategy == "single":
            return [Dedup(self.profiles)]
        names = sorted(r[0] for r in self.profiles.select("source").distinct().collect())
        of = lambda s: self.profiles.where(F.col("source") == s)
        return [Linkage(of(a), of(b)) for i, a in enumerate(names) for b in names[i + 1 :]]

    def across(self, edges: DataFrame) -> DataFrame:
        """Edges between different sources."""
        home = self.profiles.select("pid", "source")
        return (
            edges.join(home.withColumnsRenamed({"pid": "l", "source": "sl"}), "l").join(home.withColumnsRenamed({"pid": "r", "source": "sr"}), "r").where("sl <> sr").select(*edges.columns)
        )

    def edges(self, candidates) -> DataFrame:
        """candidates: task -> edges."""
        parts = [candidates(t) for t in self.tasks()]
        return self.across(parts[0]) if self.strategy == "single" else reduce(DataFrame.unionByName, parts)
