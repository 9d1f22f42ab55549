"""Contraction, unpacking and the multi-level driver."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphmoves.model import Config, Result, WeightedGraph
from graphmoves.plans.moving import local_moving
from graphmoves.session import bucketed, buckets_for, drop, kept_by, snapshot
from graphmoves.sources.build import dense_ids


def contract(g: WeightedGraph, labels: DataFrame, dense: bool = True) -> tuple[WeightedGraph, DataFrame]:
    """One node per cluster, and members (fine_id, coarse_id). Edges are summed per (cluster, far node) before the far end is replaced."""
    own = labels.select("id", "c")
    if dense:
        ids = dense_ids(own.select("c"), "c")
        own = own.join(ids, "c").select("id", F.col("dense").alias("c"))
    own = snapshot(own)
    half = g.edges.join(own.select(F.col("id").alias("src"), F.col("c").alias("a")), "src").groupBy("a", "dst").agg(F.sum("w").alias("w"))
    both = half.join(own.select(F.col("id").alias("dst"), F.col("c").alias("b")), "dst").groupBy("a", "b").agg(F.sum("w").alias("w"))
    both = snapshot(both)
    n = buckets_for(both.sparkSession, both.count())
    edges = bucketed(both.where("a <> b").selectExpr("a as src", "b as dst", "w"), "src", n)
    inner = both.where("a = b").selectExpr("a as id", "w as i")
    kept = g.nodes.join(own, "id").groupBy(F.col("c").alias("id")).agg(F.sum("loop").alias("loop"), F.sum("deg").alias("deg"), F.sum("mass").alias("mass"))
    kind = g.nodes.schema["loop"].dataType
    nodes = kept.join(inner, "id", "left").select("id", (F.col("loop") + (F.coalesce("i", F.lit(0)) / 2).cast(kind)).alias("loop"), "deg", "mass")
    nodes = bucketed(nodes, "id", n)
    drop(both)
    return WeightedGraph(edges, nodes, g.total, n), kept_by(own.select(F.col("id").alias("fine_id"), F.col("c").alias("coarse_id")), own)


def unpack(coarse: DataFrame, members: DataFrame) -> DataFrame:
    """Labels of coarse nodes brought back to their members."""
    return members.join(coarse.select(F.col("id").alias("coarse_id"), "c"), "coarse_id").select(F.col("fine_id").alias("id"), "c")


def cluster(g: WeightedGraph, objective: str = "modularity", cfg: Config | None = None, initial_labels: DataFrame | None = None) -> Result:
    """Local moving and contraction in turn, until a level leaves every node alone."""
    cfg = cfg or Config()
    graph, labels, members, trace, level = g, initial_labels, [], [], 0
    while True:
        labels, own = local_moving(graph, labels, replace(cfg, seed=cfg.seed + level), objective, level)
        trace += own
        level += 1
        if level >= cfg.max_levels or graph.nodes.count() == (own[-1][4] if own else 0):
            break
        coarse, m = contract(graph, labels)
        members.append(m)
        drop(labels, *((graph.edges, graph.nodes) if graph is not g else ()))
        graph, labels = coarse, None
    last = labels
    for m in reversed(members):
        labels = unpack(labels, m)
    labels = snapshot(labels)
    drop(last, *((graph.edges, graph.nodes) if graph is not g else ()))
    return Result(labels, level, trace, members)


def sync_modularity(g: WeightedGraph, cfg: Config | None = None, **kw) -> Result:
    return cluster(g, "modularity", cfg, **kw)


def sync_modularity_flat(g: WeightedGraph, cfg: Config | None = None, **kw) -> Result:
    return cluster(g, "modularity", replace(cfg or Config(), max_levels=1), **kw)


def sync_map(g: WeightedGraph, cfg: Config | None = None, **kw) -> Result:
    return cluster(g, "map", cfg, **kw)


def sync_map_flat(g: WeightedGraph, cfg: Config | None = None, **kw) -> Result:
    return cluster(g, "map", replace(cfg or Config(), max_levels=1), **kw)
