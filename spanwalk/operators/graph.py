"""Temporal graphs, vertex and edge sets, and the maps over them."""

from __future__ import annotations

from dataclasses import dataclass, field, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from ..functions.predicates import Ordering, Window

COLUMNS = ("src", "dst", "t_start", "t_end", "weight")


class InvalidEdges(ValueError):
    """Edges with null ends, an end before the start, or a negative weight."""


@dataclass(frozen=True)
class VertexSet:
    """Distinct vertices as a one-column frame `v`."""

    df: DataFrame

    @classmethod
    def of(cls, df: DataFrame, column: str = "v") -> VertexSet:
        return cls(df.select(F.col(column).alias("v")).where("v is not null").distinct())

    def union(self, other: VertexSet) -> VertexSet:
        return VertexSet(self.df.union(other.df).distinct())

    def intersect(self, other: VertexSet) -> VertexSet:
        return VertexSet(self.df.join(other.df, "v", "left_semi"))

    def minus(self, other: VertexSet) -> VertexSet:
        return VertexSet(self.df.join(other.df, "v", "left_anti"))

    def filter(self, condition: Column) -> VertexSet:
        return VertexSet(self.df.where(condition))

    def size(self) -> int:
        return self.df.count()


@dataclass(frozen=True)
class TemporalEdgeSet:
    """A multiset of edges."""

    df: DataFrame

    def filter(self, condition: Column) -> TemporalEdgeSet:
        return TemporalEdgeSet(self.df.where(condition))

    def union(self, other: TemporalEdgeSet) -> TemporalEdgeSet:
        return TemporalEdgeSet(self.df.unionByName(other.df))

    def intersect(self, other: TemporalEdgeSet) -> TemporalEdgeSet:
        return TemporalEdgeSet(self.df.intersectAll(other.df.select(self.df.columns)))

    def minus(self, other: TemporalEdgeSet) -> TemporalEdgeSet:
        return TemporalEdgeSet(self.df.exceptAll(other.df.select(self.df.columns)))

    def endpoints(self) -> VertexSet:
        return VertexSet(self.df.select(F.col("src").alias("v")).union(self.df.select(F.col("dst").alias("v"))).distinct())

    def size(self) -> int:
        return self.df.count()


@dataclass(frozen=True)
class TemporalGraph:
    """Edges bound to an ordering predicate; vertices default to the ends of the edges."""

    edges: DataFrame
    predicate: Ordering = Ordering.STRICTLY_SUCCEEDS
    directed: bool = True
    given: DataFrame | None = field(default=None)

    @property
    def vertices(self) -> VertexSet:
        return VertexSet.of(self.given) if self.given is not None else TemporalEdgeSet(self.edges).endpoints()

    def checked(self) -> TemporalGraph:
        """Fails early on edges that no method is defined for."""
        bad = self.edges.where("src is null or dst is null or t_start is null or t_end is null or t_end < t_start or coalesce(weight, 0) < 0")
        if not bad.isEmpty():
            raise InvalidEdges(f"first of them: {bad.first()}")
        return self

    def restrict(self, window: Window, mode: str = "contained") -> TemporalGraph:
        """Edges inside the window, or active at some time of it."""
        return replace(self, edges=self.edges.where(window.contains() if mode == "contained" else window.intersects()))

    def create_views(self, prefix: str) -> None:
        """Views <prefix>_edges and <prefix>_vertices for SQL."""
        self.edges.createOrReplaceTempView(f"{prefix}_edges")
        self.vertices.df.createOrReplaceTempView(f"{prefix}_vertices")

    def both_ways(self) -> DataFrame:
        """Every edge in both directions (twice for a self-loop)."""
        back = self.edges.withColumns({"src": F.col("dst"), "dst": F.col("src")})
        return self.edges.unionByName(back)

    def walkable(self) -> DataFrame:
        return self.edges if self.directed else self.both_ways()


def with_edge_ids(edges: DataFrame) -> DataFrame:
    """A content-derived id of two hashes (128 bits) and the edge's number among equal ones."""
    content = [c for c in COLUMNS if c in edges.columns]
    nth = F.row_number().over(W.partitionBy(*content).orderBy(F.lit(0)))
    return edges.withColumn("edge_id", F.struct(F.xxhash64(*content).alias("h1"), F.xxhash64(F.lit("second"), *content).alias("h2"), nth.alias("nth")))


def vertex_map(vertices: VertexSet, properties: DataFrame, keep: Column, updates: dict[str, Column] | None = None) -> DataFrame:
    """Vertices of the set (with properties, updated) for which `keep` holds."""
    rows = properties.join(vertices.df, "v", "left_semi")
    return (rows.withColumns(updates) if updates else rows).where(keep)


def edge_map(edges: TemporalEdgeSet, keep: Column) -> TemporalEdgeSet:
    """The set form: edges of the set for which `keep` holds."""
    return edges.filter(keep)


def edge_map_static(graph: TemporalGraph, frontier: VertexSet, keep: Column | None = None) -> DataFrame:
    """Edges that leave the frontier, whatever their time."""
    out = graph.walkable().join(frontier.df, F.col("src") == F.col("v"), "left_semi")
    return out if keep is None else out.where(keep)


def degrees(edges: DataFrame, orientation: str = "out") -> DataFrame:
    return edges.groupBy(F.col("src" if orientation == "out" else "dst").alias("v")).agg(F.count("*").alias("m"))


def top_sources(edges: DataFrame, k: int) -> list[int]:
    """The k vertices of largest out-degree, ties by least id; k numbers reach the driver."""
    return [r.v for r in degrees(edges).orderBy(F.desc("m"), "v").limit(k).collect()]

