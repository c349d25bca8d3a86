"""Graphs, windows and window queries."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from graphwin.functions.aggregates import Agg


class CycleError(ValueError):
    """A topological window needs an acyclic graph."""


class HolisticAggregateError(ValueError):
    """An index keeps partial aggregates, so it can't serve aggregates that have none."""


@dataclass(frozen=True)
class KHop:
    """Vertices within k hops. `out`: reached from the owner, `in`: reaching it, `both`: directions ignored."""

    k: int
    direction: str = "out"
    include_self: bool = True

    def __post_init__(self):
        if self.k < 0 or self.direction not in ("out", "in", "both"):
            raise ValueError(f"bad window: k={self.k}, direction={self.direction}")


@dataclass(frozen=True)
class Topological:
    """All ancestors (or descendants) in a DAG."""

    direction: str = "ancestors"
    include_self: bool = True

    def __post_init__(self):
        if self.direction not in ("ancestors", "descendants"):
            raise ValueError(f"bad window direction {self.direction}")


@dataclass
class PropertyGraph:
    """vertices (id LONG, attributes...), edges (src LONG, dst LONG, attributes...). Undirected edges are stored once."""

    vertices: DataFrame
    edges: DataFrame
    directed: bool = False
    name: str = "graph"
    part: str | None = None  # a whole-number column of vertices and edges, if no edge joins vertices of different values
    twins: DataFrame | None = None  # (id, rep): vertices of one rep are neighbours and have the same other neighbours
    between: DataFrame | None = None  # with twins: (src, dst), the edges between reps
    repeated: DataFrame | None = None  # (src, dst), the edges of a directed graph or the steps both ways of another, some repeatedly, without the shuffle that makes edges distinct

    def arcs(self, direction: str = "out") -> DataFrame:
        """Steps (src, dst) that a window walks from its owner."""
        e = self.edges.select("src", "dst")
        if not self.directed or direction == "both":
            return e.union(e.select(F.col("dst"), F.col("src"))).toDF("src", "dst").distinct()
        return e if direction == "out" else e.select(F.col("dst").alias("src"), F.col("src").alias("dst"))

    def arcs_with_self(self, direction: str = "out") -> DataFrame:
        return self.arcs(direction).union(self.vertices.select("id", "id")).toDF("src", "dst")

    def loose_steps(self, direction: str = "out") -> DataFrame:
        """arcs_with_self, some perhaps repeatedly, for work that repeats don't change."""
        if self.directed and direction != "both":
            return self.arcs_with_self(direction)
        e = self.edges.select("src", "dst") if self.repeated is None else self.repeated
        steps = e if self.repeated is not None and not self.directed else e.union(e.select(F.col("dst"), F.col("src")))
        return steps.union(self.vertices.select("id", "id")).toDF("src", "dst")

    def induced(self, keep: Column) -> "PropertyGraph":
        """The subgraph of the vertices for which keep holds."""
        v = self.vertices.where(keep)
        e = self.edges.join(v.select(F.col("id").alias("src")), "src", "left_semi").join(v.select(F.col("id").alias("dst")), "dst", "left_semi")
        return PropertyGraph(v, e.select(self.edges.columns), self.directed, f"{self.name}_induced", self.part)

    def quotient(self) -> "PropertyGraph":
        """The graph of the reps of twins. From one hop on, a window that includes its owner is that of the owner's rep with
        every member's twins, so cliques need no edges."""
        return PropertyGraph(self.twins.where("id = rep").select("id"), self.between, self.directed, f"{self.name}_quotient")

    def by_twins(self, window) -> bool:
        return self.twins is not None and isinstance(window, KHop) and window.k >= 1 and window.include_self

    def reversed(self) -> "PropertyGraph":
        return PropertyGraph(self.vertices, self.edges.withColumnsRenamed({"src": "_s"}).withColumnsRenamed({"dst": "src"}).withColumnsRenamed({"_s": "dst"}).select(self.edges.columns), self.directed, f"{self.name}_reversed", self.part)

    def validate(self, acyclic: bool = False) -> DataFrame:
        """(check, n): loops, repeated edges, edges and vertices out of order, and on request cycles."""
        e, v = self.edges.select("src", "dst"), self.vertices
        ids = v.select("id").distinct()
        ends = e.select(F.col("src").alias("id")).union(e.select("dst"))
        checks = [
            ("loops", e.where("src = dst").agg(F.count("*").alias("n"))),
            ("repeated_edges", e.groupBy("src", "dst").count().agg(F.coalesce(F.sum(F.col("count") - 1), F.lit(0)).cast("long").alias("n"))),
            ("repeated_vertices", v.groupBy("id").count().agg(F.coalesce(F.sum(F.col("count") - 1), F.lit(0)).cast("long").alias("n"))),
            ("dangling_ends", ends.join(ids, "id", "left_anti").agg(F.count("*").alias("n"))),
            ("null_ids", v.where("id IS NULL").agg(F.count("*").alias("n"))),
        ]
        out = None
        for name, df in checks:
            row = df.select(F.lit(name).alias("check"), "n")
            out = row if out is None else out.union(row)
        if acyclic:
            from graphwin.operators.reach import ancestor_pairs

            ancestor_pairs(self)  # raises CycleError
        return out


@dataclass(frozen=True)
class VertexWindowFunction:
    window: KHop | Topological
    agg: Agg


@dataclass
class VertexWindowQuery:
    """Window functions over one graph; see graphwin.plans.query.run for strategies."""

    graph: PropertyGraph
    functions: list[VertexWindowFunction] = field(default_factory=list)

    def run(self, strategy: str = "auto", **options) -> DataFrame:
        from graphwin.plans.query import run

        return run(self, strategy, **options)

    def explain(self, **options) -> str:
        from graphwin.plans.query import explain

        return explain(self, **options)
