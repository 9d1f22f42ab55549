"""Scores of clusterings and likeness of two clusterings, each a few aggregates and one final row."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphmoves.functions.columns import plogp
from graphmoves.model import WeightedGraph
from graphmoves.plans.moving import cluster_stats, state_of


def measures(g: WeightedGraph, labels: DataFrame) -> DataFrame:
    """c, vol, inner, cut, members (nodes), size (their mass)."""
    return cluster_stats(g, state_of(g, labels), True)


def modularity_frame(g: WeightedGraph, labels: DataFrame, gamma: float = 1.0) -> DataFrame:
    w = float(g.total)
    return measures(g, labels).agg(F.sum(F.col("inner") / w - gamma * (F.col("vol") / w) * (F.col("vol") / w)).alias("q"))


def modularity(g: WeightedGraph, labels: DataFrame, gamma: float = 1.0) -> float:
    return modularity_frame(g, labels, gamma).first()[0]


def constant_size_frame(g: WeightedGraph, labels: DataFrame) -> DataFrame:
    """Share of weight inside clusters against a null model in which all pairs of nodes are equally likely: sum of inner / W - (size / N) ** 2."""
    n = g.nodes.agg(F.sum("mass").cast("double").alias("n"))
    return measures(g, labels).crossJoin(F.broadcast(n)).agg(F.sum(F.col("inner") / float(g.total) - (F.col("size") / F.col("n")) * (F.col("size") / F.col("n"))).alias("q"))


def constant_size(g: WeightedGraph, labels: DataFrame) -> float:
    return constant_size_frame(g, labels).first()[0]


def node_term(g: WeightedGraph, base: float = math.e) -> DataFrame:
    return g.nodes.agg(F.sum(plogp(F.col("deg") / float(g.total), base)).alias("h"))


def map_equation_frame(g: WeightedGraph, labels: DataFrame, base: float = math.e, with_nodes: bool = True) -> DataFrame:
    """l: description length per step; without the node term it is what moving minimises."""
    w = float(g.total)
    s = measures(g, labels).agg(F.sum("cut").alias("s"), F.sum(plogp(F.col("cut") / w, base)).alias("a"), F.sum(plogp((F.col("cut") + F.col("vol")) / w, base)).alias("b"))
    own = s.select((plogp(F.col("s") / w, base) - 2 * F.col("a") + F.col("b")).alias("l"))
    return own.crossJoin(F.broadcast(node_term(g, base))).select((F.col("l") - F.col("h")).alias("l")) if with_nodes else own


def map_equation(g: WeightedGraph, labels: DataFrame, base: float = math.e, with_nodes: bool = True) -> float:
    return map_equation_frame(g, labels, base, with_nodes).first()[0]


def scores(g: WeightedGraph, labels: DataFrame) -> tuple[float, float, int]:
    """Modularity, map equation (base e) and number of clusters by one pass over the edges."""
    w = float(g.total)
    part = lambda c: plogp(c / w, math.e)
    q = F.sum(F.col("inner") / w - (F.col("vol") / w) * (F.col("vol") / w)).alias("q")
    m = measures(g, labels).agg(q, F.sum("cut").alias("s"), F.sum(part(F.col("cut"))).alias("a"), F.sum(part(F.col("cut") + F.col("vol"))).alias("b"), F.count("*").alias("n"))
    own = m.crossJoin(F.broadcast(node_term(g)))
    return tuple(own.select("q", (part(F.col("s")) - 2 * F.col("a") + F.col("b") - F.col("h")).alias("l"), "n").first())


def map_equation_directed(flow: DataFrame, visit: DataFrame, labels: DataFrame, base: float = math.e) -> float:
    """flow (src, dst, f) of a stationary walk and visit (id, p): exits are the flow that leaves a cluster."""
    at = labels.select("id", "c")
    out = flow.join(at.selectExpr("id as src", "c as a"), "src").join(at.selectExpr("id as dst", "c as b"), "dst").where("a <> b").groupBy(F.col("a").alias("c")).agg(F.sum("f").alias("q"))
    per = visit.join(at, "id").groupBy("c").agg(F.sum("p").alias("p")).join(out, "c", "left").select(F.coalesce("q", F.lit(0.0)).alias("q"), "p")
    r = per.agg(F.sum("q").alias("s"), F.sum(plogp(F.col("q"), base)).alias("a"), F.sum(plogp(F.col("q") + F.col("p"), base)).alias("b")).crossJoin(visit.agg(F.sum(plogp(F.col("p"), base)).alias("h")))
    return r.select(plogp(F.col("s"), base) - 2 * F.col("a") + F.col("b") - F.col("h")).first()[0]


def ari_frame(one: DataFrame, two: DataFrame) -> DataFrame:
    """Adjusted Rand index over ids that both label: one shuffle of ids, then sums over the contingency cells."""
    cells = one.select("id", F.col("c").alias("x")).join(two.select("id", F.col("c").alias("y")), "id").groupBy("x", "y").agg(F.count("*").alias("n"))
    two_of = lambda n: n.cast("decimal(38,0)") * (n - 1) / 2
    rows, cols = cells.groupBy("x").agg(F.sum("n").alias("n")), cells.groupBy("y").agg(F.sum("n").alias("n"))
    total = lambda d, name: d.agg(F.sum(two_of(F.col("n"))).cast("double").alias(name))
    all_ = cells.agg(two_of(F.sum("n")).cast("double").alias("t"))
    r = total(cells, "s").crossJoin(total(rows, "a")).crossJoin(total(cols, "b")).crossJoin(all_)
    expected = F.col("a") * F.col("b") / F.greatest(F.col("t"), F.lit(1.0))
    spread = (F.col("a") + F.col("b")) / 2 - expected
    return r.select(F.when(spread == 0, F.lit(1.0)).otherwise((F.col("s") - expected) / F.when(spread == 0, 1.0).otherwise(spread)).alias("ari"))


def adjusted_rand(one: DataFrame, two: DataFrame) -> float:
    return ari_frame(one, two).first()[0]


def describe_clusters(g: WeightedGraph, labels: DataFrame) -> DataFrame:
    w = float(g.total)
    m = measures(g, labels)
    return m.select("c", F.col("members").alias("size"), "vol", "cut", (F.col("cut") / F.greatest(F.lit(1), F.least("vol", F.lit(g.total) - F.col("vol")))).alias("conductance"), (F.col("inner") / w).alias("coverage_part"))


def describe_graph(g: WeightedGraph) -> DataFrame:
    n = g.nodes.agg(F.count("*").alias("nodes"), F.avg("deg").alias("mean_degree"), F.max("deg").alias("max_degree"))
    m = g.edges.agg((F.count("*") / 2).cast("long").alias("edges"))
    return n.crossJoin(m).withColumn("density", 2 * F.col("edges") / (F.col("nodes") * F.greatest(F.lit(1), F.col("nodes") - 1)))


def sampled_modularity(g: WeightedGraph, labels: DataFrame, share: float, seed: int = 0) -> tuple[float, float]:
    """Estimate of the score from a Bernoulli sample of undirected edges, with its standard error (volumes are exact)."""
    w = float(g.total)
    at = labels.select("id", "c")
    pick = F.pmod(F.xxhash64(F.least("src", "dst"), F.greatest("src", "dst"), F.lit(seed)), F.lit(1 << 30)) < share * (1 << 30)
    own = g.edges.where(pick).join(at.selectExpr("id as src", "c as a"), "src").join(at.selectExpr("id as dst", "c as b"), "dst").where("a = b and src < dst")
    r = own.agg(F.coalesce(F.sum("w"), F.lit(0)).alias("s"), F.coalesce(F.sum(F.col("w") * F.col("w")), F.lit(0)).alias("s2")).first()
    null = state_of(g, labels).groupBy("c").agg(F.sum("deg").alias("v"), F.sum(2 * F.col("loop")).alias("l")).agg(F.sum((F.col("v") / w) * (F.col("v") / w)), F.sum("l")).first()
    return (2 * r.s / share + null[1]) / w - null[0], 2 * math.sqrt(r.s2 * (1 - share)) / share / w


def resolution_probe(g: WeightedGraph, truth: DataFrame, seed: int = 0) -> dict:
    """Does merging true clusters raise modularity, and how far does that lead from the truth?"""
    from graphmoves.baselines.sequential import sequential_cluster
    from graphmoves.plans.levels import contract, unpack

    coarse, members = contract(g, truth)
    merged = unpack(sequential_cluster(coarse, "modularity", seed), members)
    return {"truth": modularity(g, truth), "merged": modularity(g, merged), "ari": adjusted_rand(truth, merged), "clusters": merged.select("c").distinct().count()}
