"""Building graphs: symmetrise, merge, drop, renumber."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from graphmoves.model import WeightedGraph, require
from graphmoves.session import bucketed, buckets_for, drop, snapshot


def from_pairs(df: DataFrame, a: str = "a", b: str = "b", w: str | None = "w", keep: bool = True) -> WeightedGraph:
    """Undirected pairs (any order, repeated, loops allowed) as a graph; null ends are dropped, negative and zero weights rejected."""
    own = df.select(F.col(a).cast("long").alias("a"), F.col(b).cast("long").alias("b"), (F.col(w) if w else F.lit(1).cast("long")).alias("w")).where("a is not null and b is not null")
    own = own.withColumn("w", F.when(F.col("w") > 0, F.col("w")).otherwise(F.raise_error(F.lit("weights must be positive")).cast(own.schema["w"].dataType)))
    merged = own.groupBy(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).agg(F.sum("w").alias("w"))
    merged = snapshot(merged) if keep else merged
    plain = merged.where("a <> b")
    edges = plain.selectExpr("a as src", "b as dst", "w").union(plain.selectExpr("b", "a", "w"))
    g = from_edges(edges, merged.where("a = b").selectExpr("a as id", "w as loop"), keep, 2 * plain.count() if keep else None)
    drop(merged if keep else None)
    return g


def from_edges(edges: DataFrame, loops: DataFrame | None = None, keep: bool = True, rows: int | None = None) -> WeightedGraph:
    """Symmetric edges and loops (id, loop); nodes without any edge don't occur. Kept edges are bucketed by src, nodes by id.

    rows: how many edges a written table has; others are written first, to be counted.
    """
    edges = require(edges, ("src", "dst", "w"))
    n = 0
    if keep:
        plain = snapshot(edges) if rows is None else edges
        n = buckets_for(edges.sparkSession, plain.count() if rows is None else rows)
        edges = bucketed(plain, "src", n)
        drop(plain)
    out = edges.groupBy(F.col("src").alias("id")).agg(F.sum("w").alias("out"))
    zero = F.lit(0).cast(edges.schema["w"].dataType)
    nodes = out.join(loops, "id", "full") if loops is not None else out.withColumn("loop", zero)
    nodes = nodes.select("id", F.coalesce("loop", zero).alias("loop"), (F.coalesce("out", zero) + 2 * F.coalesce("loop", zero)).alias("deg"), F.lit(1).cast("long").alias("mass"))
    nodes = bucketed(nodes, "id", n) if keep else nodes
    return WeightedGraph(edges, nodes, nodes.agg(F.sum("deg")).first()[0] or 0, n)


def dense_ids(ids: DataFrame, column: str = "id", order: str | None = None) -> DataFrame:
    """(column, dense): consecutive numbers from 0 in the order of `order` or the ids.

    A range sort, and the sizes of the ranges before; never one window over all rows.
    """
    key = F.expr(order) if order else F.col(column)
    own = ids.select(column).distinct().select(column, key.alias("_k"))
    ranged = snapshot(own.repartitionByRange("_k", column).select(column, "_k", F.spark_partition_id().alias("_p")))
    sizes = ranged.groupBy("_p").agg(F.count("*").alias("_n"))  # a row for each partition
    starts = sizes.select("_p", F.coalesce(F.sum("_n").over(Window.orderBy("_p").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("_s"))
    rank = F.row_number().over(Window.partitionBy("_p").orderBy("_k", column)) - 1
    return ranged.withColumn("_r", rank).join(F.broadcast(starts), "_p").select(column, (F.col("_s") + F.col("_r")).alias("dense"))


def relabel(g: WeightedGraph, ids: DataFrame) -> WeightedGraph:
    """The graph under new ids (id, dense)."""
    e = g.edges.join(ids.selectExpr("id as src", "dense as s"), "src").join(ids.selectExpr("id as dst", "dense as d"), "dst")
    nodes = g.nodes.join(ids, "id").select(F.col("dense").alias("id"), "loop", "deg", "mass")
    n = g.buckets or buckets_for(e.sparkSession, g.edges.count())
    return WeightedGraph(bucketed(e.selectExpr("s as src", "d as dst", "w"), "src", n), bucketed(nodes, "id", n), g.total, n)


def prepare(g: WeightedGraph, seed: int = 0, randomise: bool = True) -> tuple[WeightedGraph, DataFrame]:
    """Nodes without edges or loops go; ids become consecutive, in random order if asked. Also the mapping (id, dense)."""
    kept = g.nodes.where("deg > 0")
    ids = snapshot(dense_ids(kept, "id", f"xxhash64(id, {seed})" if randomise else None))
    return relabel(g, ids), ids


def to_adjacency(g: WeightedGraph) -> DataFrame:
    return g.edges.groupBy(F.col("src").alias("id")).agg(F.sort_array(F.collect_list(F.struct("dst", "w"))).alias("nbrs"))


def to_edges(adjacency: DataFrame) -> DataFrame:
    return adjacency.select(F.col("id").alias("src"), F.inline("nbrs"))
