"""Synchronous local moving: activation, cluster measures, bids, comparison, labels carried over.

State is one table (id, c, deg, loop, mass and the measures of c), bucketed by id as edges are by src, so
attaching the far end's cluster and its measures moves no edge; of each sub-round only the active share of the edges,
1 / k, is shuffled, to the node that is free to move. Measures are kept up to date by what movers change: volumes
and masses by the movers themselves, cuts by their folded bids, corrected for edges both ends of which moved.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Observation
from pyspark.sql import functions as F

from graphmoves.functions.columns import DEC, activation_sql, plogp_sql, tie_sql
from graphmoves.model import Config, WeightedGraph
from graphmoves.session import bucketed, drop, kept_by, snapshot

#: Cluster measures that an objective's bids hold, and the node's own part in each.
MEASURES = {"modularity": ("vol",), "resolution": ("vol",), "map": ("vol", "cut"), "constant_size": ("size",)}
OWN = {"vol": "deg", "size": "mass"}
#: Bytes of a row of labels with measures in a broadcast table.
LABEL_BYTES = 64


def measures_of(objective: str) -> tuple[str, ...]:
    """The measures of "modularity", "map", "constant_size" or "resolution:<number>"."""
    kind, _, gamma = objective.partition(":")
    if kind not in MEASURES or (kind == "resolution") != bool(gamma):
        raise ValueError(f"unknown objective {objective!r}")
    return MEASURES[kind]


def singleton_labels(g: WeightedGraph) -> DataFrame:
    return g.nodes.select("id", F.col("id").alias("c"))


def state_of(g: WeightedGraph, labels: DataFrame) -> DataFrame:
    return g.nodes.join(labels.select("id", "c"), "id").select("id", "c", "deg", "loop", "mass")


def cluster_stats(g: WeightedGraph, state: DataFrame, need_cut: bool) -> DataFrame:
    """c, vol, mass, size and, if needed, inner and cut = vol - inner, from scratch; loops count twice."""
    vol = state.groupBy("c").agg(F.sum("deg").alias("vol"), F.sum(2 * F.col("loop")).alias("loops"), F.count("*").alias("members"), F.sum("mass").alias("size"))
    if not need_cut:
        return vol.select("c", "vol", "members", "size")
    at = state.select("id", "c")
    same = g.edges.join(at.withColumnRenamed("id", "src"), "src").groupBy("dst", "c").agg(F.sum("w").alias("w"))
    inner = same.join(at.select(F.col("id").alias("dst"), "c"), ["dst", "c"]).groupBy("c").agg(F.sum("w").alias("i"))
    out = vol.join(inner, "c", "left").withColumn("inner", F.coalesce("i", F.lit(0)) + F.col("loops"))
    return out.select("c", "vol", "inner", (F.col("vol") - F.col("inner")).alias("cut"), "members", "size")


def total_cut(stats: DataFrame) -> DataFrame:
    return stats.agg(F.sum("cut").alias("s"))


def _active(v: str, rnd: int, i: int, cfg: Config) -> str:
    return f"{activation_sql(v, rnd, cfg.seed, cfg.sub_rounds, cfg.hash_kind)} = {i}"


def _attach(g: WeightedGraph, enriched: DataFrame, active: str, cfg: Config, measures: tuple[str, ...]) -> DataFrame:
    """v, c, x and the far end's cluster measures, for edges into active nodes."""
    far = enriched.selectExpr("id AS src", "c", *measures)
    if cfg.strategy == "broadcast_labels" and g.nodes.count() * LABEL_BYTES <= cfg.broadcast_bytes:
        far = F.broadcast(far)
    return g.edges.where(active).join(far, "src").selectExpr("dst AS v", "c", "w AS x", *measures)


def make_bids(g: WeightedGraph, state: DataFrame, stats: DataFrame | None, rnd: int, i: int, cfg: Config, measures: tuple[str, ...] = ("vol",)) -> DataFrame:
    """A row per active node and cluster that bids for it: v, a (its own cluster), c, x, the measures with and without the node, is_own, own_x (x of its own cluster), deg, loop, mass.

    The own cluster always bids, if only with x = 0, so that staying competes. Without stats the state holds the measures.
    """
    enriched = state if stats is None else state.join(stats.select("c", *measures), "c")
    kind = g.edges.schema["w"].dataType.simpleString()
    own = enriched.where(_active("id", rnd, i, cfg)).selectExpr("id AS v", "c", f"cast(0 AS {kind}) AS x", *measures, "1 AS is_own", "deg", "loop", "mass")
    if cfg.strategy == "cluster_local":
        every = _cluster_local_links(g, enriched, _active("dst", rnd, i, cfg), measures).unionByName(own, allowMissingColumns=True).repartition("v")
    else:
        every = _attach(g, enriched, _active("dst", rnd, i, cfg), cfg, measures).unionByName(own, allowMissingColumns=True)
        every = every.repartition(g.buckets, "v") if g.buckets else every.repartition("v")
    fold = every.groupBy("v", "c").agg(F.expr("sum(x) AS x"), *[F.expr(f"max({m}) AS {m}") for m in (*measures, "is_own", "deg", "loop", "mass")])
    # what only the own cluster's row has, spread over the node's bids, which are already together; the only window of a sub-round
    mine = "max(CASE WHEN is_own = 1 THEN named_struct('a', c, 'own_x', x, 'deg', deg, 'loop', loop, 'mass', mass) END) OVER (PARTITION BY v) AS mine"
    return exclude_self(fold.selectExpr("v", "c", "x", *measures, mine).selectExpr("v", "c", "x", *measures, "mine.*"), measures)


def exclude_self(fold: DataFrame, measures: tuple[str, ...]) -> DataFrame:
    """Measures of each bidding cluster without the node."""
    less = {"cut": "cut - deg + 2 * loop + 2 * x"} | {m: f"{m} - {own}" for m, own in OWN.items()}
    return fold.selectExpr("v", "a", "c", "x", *measures, *[f"CASE WHEN c = a THEN {less[m]} ELSE {m} END AS {m}_wo" for m in measures], "cast(c = a AS int) AS is_own", "own_x", "deg", "loop", "mass")


def _cluster_local_links(g: WeightedGraph, enriched: DataFrame, active: str, measures: tuple[str, ...]) -> DataFrame:
    """Links as whole clusters see them: each with all its edges in one worker, bounded by the largest cluster's edges; for comparison only."""
    import pandas as pd

    kind = g.edges.schema["w"].dataType.simpleString()
    elements = g.edges.where(active).join(enriched.selectExpr("id AS src", "c", *measures), "src")

    def bid(pdf: pd.DataFrame) -> pd.DataFrame:
        x = pdf.groupby("v", as_index=False).w.sum()
        return pd.DataFrame({"v": x.v, "c": pdf.c.iloc[0], "x": x.w, **{m: pdf[m].iloc[0] for m in measures}})

    schema = f"v long, c long, x {kind}, " + ", ".join(f"{m} {enriched.schema[m].dataType.simpleString()}" for m in measures)
    return elements.select("c", F.col("dst").alias("v"), "w", *measures).groupBy("c").applyInPandas(bid, schema)


def modularity_gain(g: WeightedGraph) -> Column:
    """Order-free exact gain: x W - deg vol; times 2 / W^2 it is the change of the score."""
    return F.expr(gain_sql(g, "modularity"))


def gain_sql(g: WeightedGraph, objective: str) -> str:
    """The gain of a bid by an objective that needs nothing but the bid."""
    if objective == "constant_size":
        n = g.nodes.agg(F.sum("mass")).first()[0] or 0
        return f"x * {float(n) * n / float(g.total or 1)!r}D - mass * size_wo"
    if objective.startswith("resolution:"):
        return f"x * {float(g.total)!r}D - {float(objective[11:])!r}D * deg * vol_wo"
    if isinstance(g.total, float):
        return f"x * {g.total!r}D - deg * vol_wo"
    if g.exact:
        return f"x * {int(g.total)}L - deg * vol_wo"
    d = lambda c: f"cast({c} AS decimal(19,0))"
    return f"cast({d('x')} * {d(f'{int(g.total)}L')} AS {DEC}) - cast({d('deg')} * {d('vol_wo')} AS {DEC})"


def _best(bids: DataFrame, score: str, measures: tuple[str, ...], cfg: Config) -> DataFrame:
    """v, c (chosen), a (before), x and own_x (weight to either), the chosen cluster's measures, deg, loop, mass. A pairwise reduction, no list per node; the own cluster wins ties."""
    tie = tie_sql("c", "v", cfg.seed, cfg.hash_kind)
    taken = ("c", "a", "x", "own_x", *measures, "deg", "loop", "mass")
    best = f"max(named_struct('g', {score}, 'o', is_own, 't', {tie}, {', '.join(f"'{k}', {k}" for k in taken)})) AS b"
    return bids.groupBy("v").agg(F.expr(best)).selectExpr("v", *[f"b.{k} AS {k}" for k in taken])


def choose_modularity(bids: DataFrame, g: WeightedGraph, cfg: Config) -> DataFrame:
    return _best(bids, gain_sql(g, "modularity"), ("vol",), cfg)


def map_delta_sql(total: float) -> str:
    """Change of the map equation against a partition without the node, up to a constant of the node."""
    p = lambda z: f"({plogp_sql(f'(({z}) / {float(total or 1)!r}D)')})"
    return f"{p('s0 - cut_wo + cu')} - 2 * ({p('cu')} - {p('cut_wo')}) + ({p('cu + vol_wo + deg')} - {p('cut_wo + vol_wo')})"


def choose_map(bids: DataFrame, g: WeightedGraph, cut: DataFrame | int | float, cfg: Config) -> DataFrame:
    """The bid of least map equation; s0 is the sum of cuts once the node has left its cluster. cut: all clusters', or a frame (s) of one row.

    Whole units of the last digit compared are ranked: `round` to digits goes through texts of decimals, row by row.
    """
    own = bids.crossJoin(F.broadcast(cut)) if isinstance(cut, DataFrame) else bids.withColumn("s", F.lit(cut))
    own = own.selectExpr("*", "s - deg + 2 * loop + 2 * own_x AS s0", "cut_wo + (deg - 2 * loop) - 2 * x AS cu")
    return _best(own, f"-rint(({map_delta_sql(g.total)}) * 1e{cfg.min_gain_digits}D)", ("vol", "cut"), cfg)


def choose(bids: DataFrame, g: WeightedGraph, objective: str, cfg: Config, cut: DataFrame | int | float | None = None, gain: str | None = None) -> DataFrame:
    """The chosen bid of every active node, by the objective."""
    if objective == "map":
        return choose_map(bids, g, cut, cfg)
    return _best(bids, gain or gain_sql(g, objective), measures_of(objective), cfg)


def apply_moves(state: DataFrame, moves: DataFrame) -> DataFrame:
    """Nodes without a move keep their cluster."""
    m = moves.select(F.col("v").alias("id"), F.col("c").alias("to"))
    return state.join(m, "id", "left").select("id", F.coalesce("to", "c").alias("c"), "deg", "loop", "mass")


def sub_round(g: WeightedGraph, state: DataFrame, rnd: int, i: int, cfg: Config, objective: str) -> DataFrame:
    """One sub-round on a state without measures, as a plan: measures from scratch, bids, choice, labels carried over."""
    measures = measures_of(objective)
    stats = cluster_stats(g, state, "cut" in measures)
    bids = make_bids(g, state, stats, rnd, i, cfg, measures)
    return apply_moves(state, choose(bids, g, objective, cfg, total_cut(stats) if "cut" in measures else None))


def with_measures(g: WeightedGraph, labels: DataFrame | None, measures: tuple[str, ...]) -> DataFrame:
    """State with the measures of every node's cluster; singletons have them in their own columns."""
    if labels is None:
        alone = {"vol": F.col("deg"), "cut": F.col("deg") - 2 * F.col("loop"), "size": F.col("mass")}
        return g.nodes.select("id", F.col("id").alias("c"), "deg", "loop", "mass", *[alone[m].alias(m) for m in measures])
    state = state_of(g, labels)
    return state.join(cluster_stats(g, state, "cut" in measures).select("c", *measures), "c").select(*state.columns, *measures)


def _kept(g: WeightedGraph, state: DataFrame) -> DataFrame:
    """A written state, bucketed as the graph is."""
    return bucketed(state, "id", g.buckets) if g.buckets else snapshot(state)


def _all_cuts(g: WeightedGraph, state: DataFrame) -> int | float:
    """Sum of all clusters' cuts, each once: clusters of a written state."""
    return state.groupBy("c").agg(F.max("cut").alias("cut")).agg(F.sum("cut")).first()[0] or 0


def _both_moved(g: WeightedGraph, movers: DataFrame, active: tuple[str, str]) -> DataFrame:
    """c, d_inner: what one-sided updates of two neighbours that both moved have got wrong. Only edges with both ends active are read on."""
    e = g.edges.where(" AND ".join(active)).join(movers.selectExpr("v AS src", "a AS au", "c AS bu"), "src").join(movers.selectExpr("v AS dst", "a AS av", "c AS bv"), "dst")
    fix = lambda c, same, times: f"named_struct('c', {c}, 'd_inner', CASE WHEN {same} THEN {times} * w END)"
    return e.selectExpr(f"inline(array({fix('av', 'au = av', 1)}, {fix('bv', 'au = bv', -2)}, {fix('bv', 'bu = bv', 1)}))").where("d_inner IS NOT NULL")


def changes(g: WeightedGraph, movers: DataFrame, measures: tuple[str, ...], active: tuple[str, str]) -> DataFrame:
    """c and d_<measure>: how the movers change the measures of clusters. Rows only for clusters that nodes leave or enter."""
    kinds = {f"d_{m}": OWN[m] for m in measures if m in OWN}
    inner = "cut" in measures
    row = lambda c, sign, x: f"named_struct('c', {c}, {', '.join(f"'{d}', {sign} * {k}" for d, k in kinds.items())}{f", 'd_inner', {sign} * 2 * ({x} + loop)" * inner})"
    booked = movers.selectExpr(f"inline(array({row('a', -1, 'own_x')}, {row('c', 1, 'x')}))")
    if not inner:
        return booked.groupBy("c").agg(*[F.expr(f"sum({d}) AS {d}") for d in kinds])
    every = booked.unionByName(_both_moved(g, movers, active), allowMissingColumns=True)
    return every.groupBy("c").agg(F.expr("coalesce(sum(d_vol), 0) AS d_vol"), F.expr("coalesce(sum(d_vol), 0) - coalesce(sum(d_inner), 0) AS d_cut"))


def _step(g: WeightedGraph, state: DataFrame, cut, rnd: int, i: int, cfg: Config, objective: str, gain: str | None = None) -> tuple[DataFrame, int | float | None, int]:
    """State, sum of cuts and number of movers after a sub-round. One shuffle of the active edges; all else is of nodes or movers."""
    measures = measures_of(objective)
    seen = Observation()
    moves = choose(make_bids(g, state, None, rnd, i, cfg, measures), g, objective, cfg, cut, gain)
    moves = snapshot(moves.where("c <> a").observe(seen, F.count(F.lit(1)).alias("n")))
    moved = seen.get["n"]
    if not moved:
        drop(moves)
        return state, cut, 0
    to = moves.selectExpr("v AS id", "c AS _c", *[f"{m} AS _{m}" for m in measures])
    kept = ["id", "deg", "loop", "mass"]
    new = state.join(to, "id", "left").selectExpr(*kept, "coalesce(_c, c) AS c", *[f"coalesce(_{m}, {m}) AS {m}" for m in measures])
    delta = None
    if cfg.stats != "per_round":
        delta = changes(g, moves, measures, (_active("src", rnd, i, cfg), _active("dst", rnd, i, cfg)))
        if "cut" in measures:
            summed = Observation()
            delta = snapshot(delta.observe(summed, F.sum("d_cut").alias("s")))
            cut += summed.get["s"] or 0
        new = new.join(delta, "c", "left").selectExpr(*kept, "c", *[f"{m} + coalesce(d_{m}, 0) AS {m}" for m in measures])
    new = _kept(g, new)
    drop(moves, delta, state)
    return new, cut, moved


def score_of(g: WeightedGraph, labels: DataFrame, objective: str) -> float:
    from graphmoves import quality as Q

    if objective == "map":
        return Q.map_equation(g, labels, with_nodes=False)
    if objective == "constant_size":
        return Q.constant_size(g, labels)
    return Q.modularity(g, labels, gamma=float(objective[11:]) if objective.startswith("resolution:") else 1.0)


def local_moving(g: WeightedGraph, labels: DataFrame | None, cfg: Config, objective: str, level: int = 0) -> tuple[DataFrame, list[tuple]]:
    """Rounds until nobody moves or the cap; state is written after every sub-round in which anybody moved.

    The trace has a row (level, round, sub_round, moved, clusters, score) a round, sub_round being their number; with
    cfg.trace "sub_rounds" also one for each of these. Clusters and scores of those are of the state then.
    """
    measures = measures_of(objective)
    if cfg.strategy not in ("edge_join", "broadcast_labels", "cluster_local"):
        raise ValueError(f"unknown strategy {cfg.strategy!r}")
    state = _kept(g, with_measures(g, labels, measures))
    cut = _all_cuts(g, state) if "cut" in measures else None
    gain = None if objective == "map" else gain_sql(g, objective)  # the same for all sub-rounds
    trace = []

    def note(rnd: int, i: int, moved: int) -> None:
        trace.append((level, rnd, i, moved, state.select("c").distinct().count(), score_of(g, state, objective) if cfg.scores else math.nan))

    for rnd in range(cfg.max_rounds):
        if rnd and cfg.stats == "per_round":
            old, state = state, _kept(g, with_measures(g, state, measures))
            cut = _all_cuts(g, state) if "cut" in measures else None
            drop(old)
        moved = 0
        for i in range(cfg.sub_rounds):
            state, cut, n = _step(g, state, cut, rnd, i, cfg, objective, gain)
            moved += n
            if cfg.trace == "sub_rounds":
                note(rnd, i, n)
        note(rnd, cfg.sub_rounds, moved)
        if not moved:
            break
    return kept_by(state.select("id", "c"), state), trace
