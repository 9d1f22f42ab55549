"""Partition-local, chunked and propagating contestants, and the walk for directed flows. Analogues of schemes that are only named in publications."""

from __future__ import annotations

import random
from collections.abc import Iterator
from dataclasses import replace

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphmoves.baselines.sequential import MAX_EDGES, Flow, _local, multilevel, sequential_cluster, sweep
from graphmoves.model import Config, Result, WeightedGraph
from graphmoves.plans.levels import cluster, contract, unpack
from graphmoves.plans.moving import _kept as kept_state
from graphmoves.plans.moving import with_measures
from graphmoves.session import drop, kept_by, snapshot
from graphmoves.sources.build import dense_ids


def pagerank(edges: DataFrame, nodes: DataFrame, damping: float = 0.85, iters: int = 20, tol: float = 0.0) -> DataFrame:
    """id, p on directed weighted edges (src, dst, w); what dangling nodes hold is dealt to all. Two exchanges an iteration."""
    n = nodes.count()
    out = edges.groupBy(F.col("src").alias("id")).agg(F.sum("w").alias("out"))
    base = snapshot(nodes.select("id").join(out, "id", "left"))
    rank = base.select("id", "out", F.lit(1.0 / max(1, n)).alias("p"))
    for i in range(iters):
        share = edges.join(rank.where("out > 0").select(F.col("id").alias("src"), (F.col("p") / F.col("out")).alias("r")), "src").groupBy(F.col("dst").alias("id")).agg(F.sum(F.col("w") * F.col("r")).alias("got"))
        lost = rank.where("out is null").agg(F.coalesce(F.sum("p"), F.lit(0.0)).alias("lost"))
        new = base.join(share, "id", "left").crossJoin(F.broadcast(lost))
        new = new.select("id", "out", ((1 - damping) / n + damping * (F.coalesce("got", F.lit(0.0)) + F.col("lost") / n)).alias("p"))
        if tol or i % 5 == 4:
            old, rank = rank, snapshot(new)
            if tol and rank.join(old.withColumnRenamed("p", "q"), "id").agg(F.sum(F.abs(F.col("p") - F.col("q")))).first()[0] < tol:
                break
        else:
            rank = new
    return rank.select("id", "p")


def walk(edges: DataFrame, nodes: DataFrame, **options) -> tuple[DataFrame, DataFrame]:
    """Recorded flow along edges (teleports not recorded) of a PageRank walk, and visit shares, both scaled to one."""
    p = snapshot(pagerank(edges, nodes, **options))
    out = edges.groupBy("src").agg(F.sum("w").alias("out"))
    flow = edges.join(out, "src").join(p.select(F.col("id").alias("src"), "p"), "src").select("src", "dst", (F.col("p") * F.col("w") / F.col("out")).alias("f"))
    flow = snapshot(flow)
    total = flow.agg(F.sum("f")).first()[0] or 1.0
    flow = flow.select("src", "dst", (F.col("f") / total).alias("f"))
    visit = flow.groupBy(F.col("dst").alias("id")).agg(F.sum("f").alias("v"))
    return flow, nodes.select("id").join(visit, "id", "left").select("id", F.coalesce("v", F.lit(0.0)).alias("p"))


def seq_map_directed(g: WeightedGraph, seed: int = 0, edges: DataFrame | None = None) -> DataFrame:
    return sequential_cluster(g, "map_directed", seed, flow=walk(edges if edges is not None else g.edges, g.nodes))


def parallel_cluster(g: WeightedGraph, objective: str = "modularity", seed: int = 0, parts: int = 4, sweeps: int = 8, levels: int = 20, flow: tuple[DataFrame, DataFrame] | None = None) -> DataFrame:
    """Each part moves its own nodes sequentially against labels of other parts that are as old as the sweep; merged after each.

    A part holds its nodes' edges and the labels around them; sums over whole clusters are joined to them.
    """
    kind = "modularity" if objective == "modularity" else "map"
    if g.edges.count() > MAX_EDGES * (parts if kind == "modularity" else 1):
        raise MemoryError("out of memory for one worker: a part holds its nodes' edges, with the map objective the whole graph")
    graph, members, level = g, [], 0
    while True:
        labels = _parallel_map(graph, seed, parts, sweeps, flow) if kind == "map" else _parallel_modularity(graph, seed, parts, sweeps)
        level += 1
        n, c = graph.nodes.count(), labels.select("c").distinct().count()
        if n == c or level >= levels:
            break
        graph, m = contract(graph, labels)
        members.append(m)
        flow = flow and contract_flow(*flow, m)
    for m in reversed(members):
        labels = unpack(labels, m)
    return snapshot(labels)


def part_rows(g: WeightedGraph, state: DataFrame, s: int, parts: int) -> DataFrame:
    """part, v, u, w, c, vol of sweep s: a row for each node (u null, w its degree, c its own cluster), those first, and one for each edge into it (c is of u).

    Edges are joined where they lie, since the state is bucketed as they are; the one exchange takes them to the part of v.
    """
    w = float(g.total)
    far = g.edges.join(state.selectExpr("id AS src", "c", "vol"), "src").selectExpr("dst AS v", "src AS u", f"w / {w!r}D AS w", "c", f"vol / {w!r}D AS vol")
    own = state.selectExpr("id AS v", "cast(NULL AS long) AS u", f"deg / {w!r}D AS w", "c", f"vol / {w!r}D AS vol")
    rows = far.union(own).selectExpr(f"cast(pmod(xxhash64(v, {s}), {parts}) AS int) AS part", "*")
    return rows.repartitionById(parts, "part").sortWithinPartitions(F.col("u").isNotNull())  # one key, a radix sort


def _part_sweep(batches: Iterator[pa.RecordBatch], rng: random.Random) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Nodes of a part, their clusters before and after each has moved once, in random order. About 40 bytes an edge."""
    nodes, edges, ids = [], [], None
    for b in batches:
        k = b.column(1).null_count
        x = [b.column(i).slice(0, k).to_numpy(zero_copy_only=False) for i in (0, 2, 3, 4)]
        if k:
            nodes.append(x)
        if k == b.num_rows:
            continue
        if ids is None:  # nodes come first
            ids = np.sort(np.concatenate([y[0] for y in nodes]))
        v, u, f, c, vol = (b.column(i).slice(k).to_numpy(zero_copy_only=False) for i in range(5))
        at = np.searchsorted(ids, u)
        at[at == len(ids)] = 0
        edges.append((np.searchsorted(ids, v).astype(np.int32), u, np.where(ids[at] == u, at, -1).astype(np.int32), f, c, vol))
    if not nodes:
        return (np.empty(0, np.int64),) * 3
    ids, p, before, own_vol = (np.concatenate(x) for x in zip(*nodes, strict=True))
    order = np.argsort(ids)
    ids, p, before, own_vol = ids[order], p[order], before[order], own_vol[order]
    n = len(ids)
    if not edges:
        return ids, before, before
    v, u, slot, f, c, vol = (np.concatenate(x) for x in zip(*edges, strict=True))
    del edges
    order = np.lexsort((u, v))
    del u
    v, slot, f, c, vol = v[order], slot[order], f[order], c[order], vol[order]
    names, first, index = np.unique(np.concatenate((c, before)), return_index=True, return_inverse=True)
    vols = np.concatenate((vol, own_vol))[first].tolist()
    # an end in another part keeps its cluster for the whole sweep: its slot is that cluster's
    slot = np.where(slot < 0, n + index[: len(c)], slot).astype(np.int32)
    start = np.concatenate(([0], np.cumsum(np.bincount(v, minlength=n)))).tolist()
    del v, c, vol
    label, p = index[len(f) :].tolist() + list(range(len(names))), p.tolist()
    order = list(range(n))
    rng.shuffle(order)
    for i in order:
        lo, hi, a, own = start[i], start[i + 1], label[i], p[i]
        to = {a: 0.0}
        for j, x in zip(slot[lo:hi].tolist(), f[lo:hi].tolist()):  # noqa: B905
            k = label[j]
            to[k] = to.get(k, 0.0) + x
        base = to.pop(a) - own * (vols[a] - own)
        best, most = a, base
        for k, x in to.items():
            gain = x - own * vols[k]
            if gain > most or gain == most and best != a and k > best:
                best, most = k, gain
        if most > base + 1e-13:
            vols[a] -= own
            vols[best] += own
            label[i] = best
    return ids, before, names[np.array(label[:n], np.int64)]


def _parallel_modularity(g: WeightedGraph, seed: int, parts: int, sweeps: int) -> DataFrame:
    """Sweeps until none moves a node; sums over whole clusters come with the rows."""
    labels = None
    for s in range(sweeps):
        state = kept_state(g, with_measures(g, labels, ("vol",)))

        def run(batches: Iterator[pa.RecordBatch], s: int = s) -> Iterator[pa.RecordBatch]:
            out = _part_sweep(batches, random.Random(seed * 1000 + s))
            for i in range(0, len(out[0]), 1 << 16):
                yield pa.RecordBatch.from_arrays([pa.array(x[i : i + (1 << 16)], pa.int64()) for x in out], ["id", "o", "c"])

        old, labels = labels, snapshot(part_rows(g, state, s, parts).select("v", "u", "w", "c", "vol").mapInArrow(run, "id long, o long, c long"))
        drop(old, state)
        if not labels.where("c <> o").limit(1).count():
            break
    return kept_by(labels.select("id", "c"), labels)


def contract_flow(flow: DataFrame, visit: DataFrame, members: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Flow between and visits of coarse nodes; what stays inside one is its loop."""
    at = members.select(F.col("fine_id").alias("id"), F.col("coarse_id").alias("c"))
    half = flow.join(at.selectExpr("id as src", "c as a"), "src").groupBy("a", "dst").agg(F.sum("f").alias("f"))
    both = half.join(at.selectExpr("id as dst", "c as b"), "dst").groupBy(F.col("a").alias("src"), F.col("b").alias("dst")).agg(F.sum("f").alias("f"))
    return snapshot(both), snapshot(visit.join(at, "id").groupBy(F.col("c").alias("id")).agg(F.sum("p").alias("p")))


def _parallel_map(g: WeightedGraph, seed: int, parts: int, sweeps: int, flow) -> DataFrame:
    """Map objective: parts move in turn their own share of nodes, each on the whole flow with labels of the last sweep."""
    from graphmoves.baselines.sequential import _frame

    own = _frame(g)
    if flow:
        own = flow[0].select("src", "dst", "f", F.lit(None).cast("double").alias("p")).union(flow[1].select(F.col("id"), F.col("id"), F.lit(0.0), "p"))
    copies = own.withColumn("part", F.explode(F.sequence(F.lit(0), F.lit(parts - 1))))
    labels = g.nodes.select("id", F.col("id").alias("c"))
    for s in range(sweeps):
        lab = labels.select(F.col("id").alias("src"), F.lit(None).cast("long").alias("dst"), F.lit(0.0).alias("f"), F.lit(-1.0).alias("p"), F.explode(F.sequence(F.lit(0), F.lit(parts - 1))).alias("part"), "c")

        def run(pdf: pd.DataFrame) -> pd.DataFrame:
            is_label = pdf.p == -1.0
            now = dict(zip(pdf.src[is_label], pdf.c[is_label], strict=True))
            local, ids = _local(pdf[~is_label])
            at = {v: i for i, v in enumerate(ids)}
            c = [at[now[v]] for v in ids]
            mine = [i for i, v in enumerate(ids) if (hash((v, s)) % parts) == pdf.part.iloc[0]]
            sweep(local, "map", random.Random(seed * 1000 + s), c, mine, 1)
            return pd.DataFrame({"id": [ids[i] for i in mine], "c": [ids[c[i]] for i in mine]})

        new = snapshot(copies.withColumn("c", F.lit(None).cast("long")).unionByName(lab).groupBy("part").applyInPandas(run, "id long, c long"))
        stay = new.join(labels.withColumnRenamed("c", "o"), "id").where("c <> o").limit(1).count() == 0
        labels = new
        if stay:
            break
    return labels


def stale_map_standin(g: WeightedGraph, cfg: Config | None = None) -> Result:
    """A stand-in, not a reconstruction, for a distributed map-equation scheme that is only named: cluster measures refreshed once a round."""
    return cluster(g, "map", replace(cfg or Config(), stats="per_round"))


def label_propagation(g: WeightedGraph, iters: int = 5, labels: DataFrame | None = None, cap: int | None = None) -> DataFrame:
    """Every node takes the label of largest weight around it, the smaller label at ties; with `cap` about so many nodes of a label that has grown beyond keep it, the others their former one."""
    labels = labels if labels is not None else g.nodes.select("id", F.col("id").alias("c"))
    for it in range(iters):
        seen = g.edges.join(labels.withColumnRenamed("id", "src"), "src").groupBy("dst", "c").agg(F.sum("w").alias("w"))
        best = seen.groupBy(F.col("dst").alias("id")).agg(F.max(F.struct("w", (-F.col("c")).alias("k"))).alias("b"))
        new = labels.withColumnRenamed("c", "o").join(best, "id", "left").select("id", F.coalesce(-F.col("b.k"), "o").alias("c"))
        if cap:  # the share of a label's nodes that fits keeps it, by hash; others stay where they are
            size = new.groupBy("c").agg(F.count("*").alias("n")).where(F.col("n") > cap)
            mark = F.pmod(F.xxhash64("id", F.lit(it)), F.lit(1 << 30)) / float(1 << 30)
            new = new.join(size, "c", "left").join(labels.withColumnRenamed("c", "o"), "id")
            new = new.select("id", F.when(F.col("n").isNull() | (mark * F.col("n") < cap), F.col("c")).otherwise(F.col("o")).alias("c"))
        labels = snapshot(new)
    return labels


def chunk_merge(g: WeightedGraph, parts: int = 4, by: str = "range", objective: str = "modularity", seed: int = 0) -> DataFrame:
    """Each part of the nodes is clustered alone on its own edges, then the merged graph by one worker. by: "range" of ids or "lp", size-capped label propagation."""
    if by == "range":
        ids = dense_ids(g.nodes.select("id"))
        n = g.nodes.count()
        home = ids.select("id", F.floor(F.col("dense") * parts / n).alias("part"))
    else:
        lp = label_propagation(g, 4, cap=max(1, g.nodes.count() // parts))
        home = lp.select("id", F.pmod(F.xxhash64("c"), F.lit(parts)).alias("part"))
    home = snapshot(home)
    w = float(g.total)
    e = g.edges.join(home.selectExpr("id as src", "part"), "src").join(home.selectExpr("id as dst", "part as q"), "dst").where("part = q").select("part", "src", "dst", (F.col("w") / w).alias("f"), F.lit(None).cast("double").alias("p"))
    own = g.nodes.join(home, "id").select("part", F.col("id").alias("src"), F.col("id").alias("dst"), (F.col("loop") * 2 / w).alias("f"), (F.col("deg") / w).alias("p"))

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        local, ids = _local(pdf)
        return pd.DataFrame({"id": ids, "c": [ids[x] for x in multilevel(local, "modularity" if objective == "modularity" else "map", seed)]})

    first = snapshot(e.union(own).groupBy("part").applyInPandas(run, "id long, c long"))
    coarse, members = contract(g, first)
    return unpack(sequential_cluster(coarse, objective, seed), members)


__all__ = ["Flow", "chunk_merge", "drop", "label_propagation", "pagerank", "parallel_cluster", "seq_map_directed", "stale_map_standin", "walk"]
