"""A blocked priority-search index for the edges of high-degree vertices.

One axis (start or end) is the heap: a node holds up to `block_rows` edges with the best heap
keys among those of its range. The other axis is the tree: the remaining edges are divided by
rank, so the tree is balanced whatever the data. A query bounds the heap axis on one side and
the tree axis on both; a node can hold results only if its best key meets the heap bound and
its range meets the tree bounds, and if it can't, neither can any node below it.

The build has no recursion: ranks on the tree axis give every edge its path, and each level
takes the best edges of every prefix. Edges are laid out by (v, shard) once, which serves all
levels. Vertices with more than `shard_rows` edges are divided by quantiles of the tree axis
first, so a hub is never one task.

Nodes are kept in order of their best heap key. A query narrows them by headers (best key and
range of the tree axis) with literal bounds that reach the file scan, so edges are read of nodes
that may hold results only.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from ..functions.predicates import ThreeSided
from ..operators.graph import degrees
from ..session import release, settle, settle_laid, settle_partitioned, settle_sorted
from .shards import SHARD_ROWS, with_shards

CUTOFF, BLOCK_ROWS = 2000, 64


def select_indexed_vertices(edges: DataFrame, cutoff: int = CUTOFF, orientation: str = "out") -> DataFrame:
    """(v, m) of the vertices whose degree meets the cutoff."""
    return degrees(edges, orientation).where(F.col("m") >= cutoff)


@dataclass(frozen=True)
class DualAxisIndex:
    """Node table and catalog of one orientation and axis setting."""

    nodes: DataFrame | None  # None where only the choice is asked for: v, shard, node, level, heap_best, tree_lo, tree_hi, n, edges
    catalog: DataFrame  # v, m
    orientation: str
    heap_axis: str
    heap_mode: str

    @property
    def tree_axis(self) -> str:
        return "t_end" if self.heap_axis == "t_start" else "t_start"

    def beats(self, key: Column, bound: Column) -> Column:
        """Does a heap key meet the bound (at least it for mode max, at most it for mode min)?"""
        return key >= bound if self.heap_mode == "max" else key <= bound

    def save(self, path: str) -> None:
        """Node rows in order of their best heap key, so that bounds prune files and pages; a hub's nodes are spread over many files."""
        self.nodes.repartitionByRange("heap_best", "v").sortWithinPartitions("heap_best", "v").write.mode("overwrite").parquet(path + "/nodes")
        self.catalog.write.mode("overwrite").parquet(path + "/catalog")


def load_index(spark, path: str, orientation: str, heap_axis: str, heap_mode: str) -> DualAxisIndex:
    return DualAxisIndex(spark.read.parquet(path + "/nodes"), spark.read.parquet(path + "/catalog"), orientation, heap_axis, heap_mode)


def build_index(edges: DataFrame, cutoff: int = CUTOFF, heap_axis: str = "t_start", heap_mode: str = "max", block_rows: int = BLOCK_ROWS, orientation: str = "out", shard_rows: int = SHARD_ROWS) -> DualAxisIndex:
    v, nbr = ("src", "dst") if orientation == "out" else ("dst", "src")
    tree_axis = "t_end" if heap_axis == "t_start" else "t_start"
    sign = -1 if heap_mode == "max" else 1  # one code path: the smaller signed key is the better
    catalog = settle(select_indexed_vertices(edges, cutoff, orientation))
    weight = F.col("weight") if "weight" in edges.columns else F.lit(1.0)
    own = edges.select(F.col(v).alias("v"), F.col(nbr).alias("nbr"), "t_start", "t_end", weight.alias("weight")).join(catalog, "v")
    own = with_shards(own, tree_axis, shard_rows).withColumn("key", sign * F.col(heap_axis))
    own = settle_partitioned(own, int(edges.sparkSession.conf.get("spark.sql.shuffle.partitions")), "v", "shard")
    group = W.partitionBy("v", "shard")
    content = ["nbr", "weight"]
    ranked = own.withColumns({"size": F.count("*").over(group), "rank": F.row_number().over(group.orderBy(tree_axis, "key", *content)) - 1})
    depth = F.greatest(F.lit(0), F.ceil(F.log2(F.col("size") / float(block_rows)))).cast("int")
    left = ranked.withColumn("depth", depth).withColumn("path", F.floor(F.col("rank") * F.pow(F.lit(2.0), F.col("depth")) / F.col("size")).cast("long"))
    left = settle_laid(left)
    release(own)
    deepest = left.agg(F.max("depth")).head()[0]
    placed = []
    for level in range((deepest if deepest is not None else -1) + 1):
        prefix = F.floor(F.col("path") / F.pow(F.lit(2.0), F.col("depth") - level)).cast("long")
        here = left.where(F.col("depth") >= level).withColumn("prefix", prefix)
        place = F.row_number().over(W.partitionBy("v", "shard", "prefix").orderBy("key", "rank"))
        here = here.withColumn("place", place)
        takes = (F.col("place") <= block_rows) | (F.col("depth") == level)
        tagged = settle_laid(here.withColumn("taken", takes))
        placed.append(tagged.where("taken").withColumns({"level": F.lit(level), "node": (F.lit(1 << level) + F.col("prefix")).cast("long")}).drop("prefix", "place", "taken"))
        left = tagged.where("not taken").drop("prefix", "place", "taken")
    if not placed:
        placed = [left.withColumns({"level": F.lit(0), "node": F.lit(1).cast("long")})]
    rows = placed[0]
    for p in placed[1:]:
        rows = rows.unionByName(p)
    # a node's tree range covers its own edges; its subtree's range is checked node by node
    nodes = rows.groupBy("v", "shard", "node", "level").agg(
        F.min("key").alias("best"), F.max("key").alias("worst"), F.min(tree_axis).alias("tree_lo"), F.max(tree_axis).alias("tree_hi"), F.count("*").alias("n"),
        F.array_sort(F.collect_list(F.struct("key", "nbr", "t_start", "t_end", "weight"))).alias("edges"),
    ).select("v", "shard", "node", "level", (sign * F.col("best")).alias("heap_best"), (sign * F.col("worst")).alias("heap_worst"), "tree_lo", "tree_hi", "n", "edges")
    return DualAxisIndex(settle_sorted(nodes, "heap_best", "v"), catalog, orientation, heap_axis, heap_mode)


def query_window(index: DualAxisIndex, vertices: DataFrame, start: int, end: int) -> DataFrame:
    """(v, nbr, t_start, t_end, weight): edges of the asked vertices inside [start, end].

    The bounds are literals: headers are filtered in the file scan, and edges are unpacked of the
    nodes that are left.
    """
    heap, low, high = (start, start, end) if index.heap_axis == "t_start" and index.heap_mode == "max" else (end, start, end) if index.heap_axis == "t_end" and index.heap_mode == "min" else (None, start, end)
    hit = index.nodes.where((F.col("tree_hi") >= low) & (F.col("tree_lo") <= high))
    if heap is not None:
        hit = hit.where(index.beats(F.col("heap_best"), F.lit(heap)))
    rows = hit.join(vertices.select("v"), "v", "left_semi").select("v", F.explode("edges").alias("e")).select("v", "e.nbr", "e.t_start", "e.t_end", "e.weight")
    return rows.where((F.col("t_start") >= start) & (F.col("t_end") <= end))


def query_index(index: DualAxisIndex, asked: DataFrame, bounds: ThreeSided, extra: Column | None = None) -> DataFrame:
    """Rows of `asked` (with column v) joined with the edges of v that meet the bounds.

    Columns of `asked` plus nbr, t_start, t_end, weight. The bounds may use columns of `asked`:
    the widest of them narrow the headers first, then each row is met with headers alone, and
    edges are fetched for the nodes that some row opens.
    """
    worst = F.min if index.heap_mode == "max" else F.max
    widest = asked.agg(worst(bounds.heap_bound).alias("heap"), F.min(bounds.tree_lo).alias("low"), F.max(bounds.tree_hi).alias("high")).head()
    nodes = index.nodes.withColumnsRenamed({"v": "__v", "shard": "__shard", "node": "__node"})
    if widest.heap is not None:
        nodes = nodes.where(index.beats(F.col("heap_best"), F.lit(widest.heap)) & (F.col("tree_hi") >= widest.low) & (F.col("tree_lo") <= widest.high))
    meets = (F.col("v") == F.col("__v")) & index.beats(F.col("heap_best"), bounds.heap_bound) & (F.col("tree_hi") >= bounds.tree_lo) & (F.col("tree_lo") <= bounds.tree_hi)
    opened = asked.join(nodes.select("__v", "__shard", "__node", "heap_best", "tree_lo", "tree_hi"), meets).select(*asked.columns, "__v", "__shard", "__node")
    blocks = nodes.select("__v", "__shard", "__node", F.col("edges").alias("__edges"))
    hit = opened.join(blocks, ["__v", "__shard", "__node"])
    out = hit.select(*asked.columns, F.explode("__edges").alias("__e")).select(*asked.columns, "__e.nbr", "__e.t_start", "__e.t_end", "__e.weight")
    keep = index.beats(F.col(index.heap_axis), bounds.heap_bound) & F.col(index.tree_axis).between(bounds.tree_lo, bounds.tree_hi)
    return out.where(keep if extra is None else keep & extra)


def nodes_read(index: DualAxisIndex, asked: DataFrame, bounds: ThreeSided) -> DataFrame:
    """(v, nodes, examined): index nodes that a query opens and the edges in them."""
    meets = (F.col("v") == F.col("__v")) & index.beats(F.col("heap_best"), bounds.heap_bound) & (F.col("tree_hi") >= bounds.tree_lo) & (F.col("tree_lo") <= bounds.tree_hi)
    hit = asked.join(index.nodes.withColumnRenamed("v", "__v").select("__v", "heap_best", "tree_lo", "tree_hi", "n"), meets)
    return hit.groupBy("v").agg(F.count("*").alias("nodes"), F.sum("n").alias("examined"))


def descend(index: DualAxisIndex, asked: DataFrame, bounds: ThreeSided) -> DataFrame:
    """(v, shard, node) opened by a descent from the root: a node is opened if its best heap key meets the bound.

    The tree bounds only decide which opened nodes are read, since a node's own range does not
    cover its children's. Serves to check `query_index` and to count rounds.
    """
    slim = settle(index.nodes.select(F.col("v").alias("__v"), "shard", "node", "heap_best", "tree_lo", "tree_hi"))
    frontier = settle(asked.join(slim.where("node = 1"), F.col("v") == F.col("__v")).where(index.beats(F.col("heap_best"), bounds.heap_bound)).select(*asked.columns, "shard", "node", "tree_lo", "tree_hi"))
    opened = [frontier]
    while not frontier.isEmpty():
        children = frontier.select(*asked.columns, "shard", F.explode(F.array(F.col("node") * 2, F.col("node") * 2 + 1)).alias("child"))
        frontier = settle(children.join(slim.withColumnRenamed("shard", "__s"), (F.col("v") == F.col("__v")) & (F.col("shard") == F.col("__s")) & (F.col("child") == F.col("node"))).where(index.beats(F.col("heap_best"), bounds.heap_bound)).select(*asked.columns, "shard", "node", "tree_lo", "tree_hi"))
        opened.append(frontier)
    out = opened[0]
    for o in opened[1:]:
        out = out.unionByName(o)
    return out.where((F.col("tree_hi") >= bounds.tree_lo) & (F.col("tree_lo") <= bounds.tree_hi)).select("v", "shard", "node").distinct()
