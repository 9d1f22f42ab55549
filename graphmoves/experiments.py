"""Experiment workloads on the given tables: each returns rows shaped like model.RUNS, or a small report of them."""

from __future__ import annotations

import time
import uuid
from concurrent.futures import FIRST_COMPLETED, ThreadPoolExecutor, wait
from dataclasses import replace
from functools import reduce
from threading import BoundedSemaphore

from py4j.protocol import Py4JJavaError
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from graphmoves import quality as Q
from graphmoves.baselines import others as B
from graphmoves.baselines.sequential import MAX_EDGES, sequential_cluster
from graphmoves.model import RUNS, Config, WeightedGraph
from graphmoves.plans import levels as V
from graphmoves.plans.moving import local_moving
from graphmoves.session import snapshot
from graphmoves.sources import graphs as G
from graphmoves.sources.build import from_pairs, prepare

ALGOS = {
    "sync_modularity": ("modularity", lambda g, c: V.sync_modularity(g, c).labels),
    "sync_modularity_flat": ("modularity", lambda g, c: V.sync_modularity_flat(g, c).labels),
    "sync_map": ("map", lambda g, c: V.sync_map(g, c).labels),
    "sync_map_flat": ("map", lambda g, c: V.sync_map_flat(g, c).labels),
    "seq_modularity": ("modularity", lambda g, c: sequential_cluster(g, "modularity", c.seed)),
    "seq_map": ("map", lambda g, c: sequential_cluster(g, "map", c.seed)),
    "sync_constant_size": ("constant_size", lambda g, c: V.cluster(g, "constant_size", c).labels),
    "seq_map_directed": ("map", lambda g, c: B.seq_map_directed(g, c.seed)),
    "parallel_modularity": ("modularity", lambda g, c: B.parallel_cluster(g, "modularity", c.seed)),
    "parallel_map_directed": ("map", lambda g, c: B.parallel_cluster(g, "map", c.seed, flow=B.walk(g.edges, g.nodes))),
    "stale_map_standin": ("map", lambda g, c: B.stale_map_standin(g, c).labels),
    "chunk_merge_range": ("modularity", lambda g, c: B.chunk_merge(g, 4, "range", "modularity", c.seed)),
    "chunk_merge_lp": ("modularity", lambda g, c: B.chunk_merge(g, 4, "lp", "modularity", c.seed)),
    "unsplit_rounds": ("modularity", lambda g, c: V.sync_modularity(g, replace(c, sub_rounds=1)).labels),
    "label_propagation": ("none", lambda g, c: B.label_propagation(g)),
    "singleton": ("none", lambda g, c: g.nodes.select("id", F.col("id").alias("c"))),
}
#: Algorithms that hold the whole graph in one task.
ONE_WORKER = {"seq_modularity", "seq_map", "seq_map_directed"}


def executor_totals(spark: SparkSession) -> dict[str, int]:
    """Bytes that all executors have written and read in shuffles so far, and the largest heap any has had, if they report it."""
    rows = spark._jsc.sc().statusStore().executorList(False)
    out = {"shuffle_write_bytes": 0, "shuffle_read_bytes": 0, "peak_heap_bytes": 0}
    for i in range(rows.size()):
        x = rows.apply(i)
        out["shuffle_write_bytes"] += x.totalShuffleWrite()
        out["shuffle_read_bytes"] += x.totalShuffleRead()
        if x.peakMemoryMetrics().isDefined():
            out["peak_heap_bytes"] = max(out["peak_heap_bytes"], x.peakMemoryMetrics().get().getMetricValue("JVMHeapMemory"))
    return out


class Tally:
    """Bytes shuffled by the jobs under a tag; has to look from time to time, as Spark keeps only its last stages."""

    def __init__(self, spark: SparkSession):
        self.sc, self.tag, self.done, self.stages = spark._jsc.sc(), f"run-{uuid.uuid4().hex}", set(), {}

    def look(self) -> None:
        store = self.sc.statusStore()
        for j in set(self.sc.statusTracker().getJobIdsForTag(self.tag)) - self.done:
            try:
                job = store.job(j)
                ids = job.stageIds()
                for s in [ids.apply(i) for i in range(ids.size())]:
                    x = store.lastStageAttempt(s)
                    self.stages[s] = x.shuffleWriteBytes(), x.shuffleReadBytes()
            except Py4JJavaError:  # no longer kept
                continue
            if str(job.status()) != "RUNNING":
                self.done.add(j)

    def bytes(self) -> dict[str, int]:
        self.sc.listenerBus().waitUntilEmpty()
        self.look()
        return {f"shuffle_{k}_bytes": sum(x[i] for x in self.stages.values()) for i, k in enumerate(("write", "read"))}


class Study:
    """Runs algorithms over seeds, keeps labels, times them; reports are aggregates of its runs."""

    def __init__(self, spark: SparkSession, cfg: Config | None = None):
        self.spark, self.cfg, self.rows, self.labels = spark, cfg or Config(), [], {}

    def run(self, name: str, g: WeightedGraph, algos, seeds=range(3), truth: DataFrame | None = None, **params) -> Study:
        for algo in algos:
            for seed in seeds:
                before = executor_totals(self.spark)
                row, labels, after = self._once(name, g, algo, seed, truth, params)
                self._keep(row, labels, {k: after[k] - (before[k] if k.startswith("shuffle") else 0) for k in after})
        return self

    def run_together(self, graphs, algos, seeds=range(1)) -> Study:
        """The runs that `run` makes of (name, graph, truth), side by side; rows in the order of one after another.

        One-worker algorithms take two thirds of the cores at most, and as many at once as hold MAX_EDGES edges together.
        Bytes shuffled are of a run's own jobs; seconds are of runs that share the cluster.
        """
        cores = max(1, self.spark.sparkContext.defaultParallelism)
        most = max((g.edges.count() for _, g, _ in graphs), default=0)
        alone = BoundedSemaphore(max(1, min(2 * cores // 3, MAX_EDGES // max(1, most))))
        todo = [(name, g, algo, seed, truth) for name, g, truth in graphs for algo in algos for seed in seeds]
        tallies = [Tally(self.spark) for _ in todo]

        def one(i: int):
            name, g, algo, seed, truth = todo[i]
            tag = tallies[i].tag
            if algo not in ONE_WORKER:
                return self._once(name, g, algo, seed, truth, {}, tag)
            with alone:
                return self._once(name, g, algo, seed, truth, {}, tag)

        first = sorted(range(len(todo)), key=lambda i: ALGOS[todo[i][2]][0] != "map")  # the longest ones
        waiting = sum(x[2] in ONE_WORKER for x in todo)  # these may hold a thread while others run
        with ThreadPoolExecutor(max(1, min(len(todo), cores + waiting))) as pool:
            runs = {i: pool.submit(one, i) for i in first}
            left = set(runs.values())
            while left:
                left = wait(left, 5, FIRST_COMPLETED)[1]
                for t in tallies:
                    t.look()
        for i, t in enumerate(tallies):
            row, labels, after = runs[i].result()
            self._keep(row, labels, after | t.bytes())
        return self

    def _once(self, name: str, g: WeightedGraph, algo: str, seed: int, truth: DataFrame | None, params: dict, tag: str | None = None):
        """A row of RUNS without what was used, labels (None: out of memory), executor totals at the run's end. tag: of its jobs, without those of its scores."""
        objective, f = ALGOS[algo]
        if tag:
            self.spark.sparkContext.addJobTag(tag)
        try:
            began = time.perf_counter()
            labels = snapshot(f(g, replace(self.cfg, seed=seed, **params)))
            s, after = time.perf_counter() - began, executor_totals(self.spark)
        except MemoryError:
            return (name, algo, objective, seed, {"error": "out of memory"}, None, None, None, None, None), None, {}
        finally:
            if tag:
                self.spark.sparkContext.removeJobTag(tag)
        ari = Q.adjusted_rand(truth, labels) if truth is not None else None
        return (name, algo, objective, seed, {k: str(v) for k, v in params.items()}, s, *Q.scores(g, labels), ari), labels, after

    def _keep(self, row: tuple, labels: DataFrame | None, used: dict[str, int]) -> None:
        if labels is not None:
            self.labels[row[0], row[1], row[3], str(row[4])] = labels
            row = (*row[:4], row[4] | {k: str(v) for k, v in used.items()}, *row[5:])
        self.rows.append(row)

    def runs(self) -> DataFrame:
        return self.spark.createDataFrame(self.rows, RUNS)

    def to_best(self) -> DataFrame:
        """Mean likeness of each algorithm's runs to the best-scoring run of its graph and objective."""
        best, out = best_reference(self.runs()).collect(), []
        for b in best:
            ref = self.labels[b.graph, b.algo, b.seed, "{}"]
            out += [(g, a, b.objective, s, Q.adjusted_rand(ref, lab)) for (g, a, s, _), lab in self.labels.items() if g == b.graph and ALGOS[a][0] == b.objective]
        return self.spark.createDataFrame(out, "graph string, algo string, objective string, seed int, ari double").groupBy("graph", "objective", "algo").agg(F.avg("ari").alias("ari"))

    def stability(self) -> DataFrame:
        """Likeness of runs of one algorithm with different seeds."""
        out = [(g, a, s, t, Q.adjusted_rand(x, y)) for (g, a, s, p), x in self.labels.items() for (h, b, t, q), y in self.labels.items() if (g, a, p) == (h, b, q) and s < t]
        return self.spark.createDataFrame(out, "graph string, algo string, seed1 int, seed2 int, ari double")


def best_reference(runs: DataFrame) -> DataFrame:
    w = Window.partitionBy("graph", "objective").orderBy(F.when(F.col("objective") == "map", F.col("map_equation")).otherwise(-F.col("modularity")), "algo", "seed")
    return runs.where("objective <> 'none' and seconds is not null").withColumn("r", F.row_number().over(w)).where("r = 1").drop("r")


def mean_times(runs: DataFrame) -> DataFrame:
    return runs.groupBy("graph", "algo").agg(F.avg("seconds").alias("mean"), F.stddev_samp("seconds").alias("sd"), F.avg("modularity").alias("q"), F.avg("map_equation").alias("l"), F.avg("ari_truth").alias("ari"))


def ratio_table(runs: DataFrame, base: str) -> DataFrame:
    m = mean_times(runs).select("graph", "algo", "mean")
    return m.join(m.where(F.col("algo") == base).select("graph", F.col("mean").alias("base")), "graph").select("graph", "algo", (F.col("mean") / F.col("base")).alias("ratio"))


def weak_scaling(runs: DataFrame, hosts: DataFrame, base: int = 1) -> DataFrame:
    """Efficiency of each algorithm: its mean time on `base` hosts over that on more, at as many nodes a host. hosts: (graph, hosts)."""
    m = mean_times(runs).join(hosts, "graph").select("algo", "hosts", "mean")
    one = m.where(F.col("hosts") == base).select("algo", F.col("mean").alias("base"))
    return m.join(one, "algo").select("algo", "hosts", "mean", (F.col("base") / F.col("mean")).alias("efficiency"))


def used_by(runs: DataFrame) -> DataFrame:
    """Mean bytes shuffled and the largest heap of each algorithm on each graph, and runs that didn't fit."""
    v = lambda k: F.try_element_at("params", F.lit(k)).cast("double")
    return runs.groupBy("graph", "algo").agg(F.avg(v("shuffle_write_bytes")).alias("shuffle_write_bytes"), F.max(v("peak_heap_bytes")).alias("peak_heap_bytes"), F.sum(F.col("seconds").isNull().cast("int")).alias("out_of_memory"))


SYNC = ("sync_modularity", "sync_modularity_flat", "sync_map")
EVERY = (*SYNC, "seq_modularity", "parallel_modularity", "seq_map", "seq_map_directed", "parallel_map_directed", "stale_map_standin")


def planted_graph(spark, d, mu=0.4, seed=7):
    return from_pairs(G.planted(spark, d, mu, seed)), G.planted_truth(spark, d)


def w1_weak_scaling(spark, dirs, seeds=range(1), mu=0.4, algos=SYNC) -> Study:
    """One input per size; the caller chooses the cluster per size. Also truth likeness (w2)."""
    s = Study(spark)
    for d in dirs:
        g, t = planted_graph(spark, d, mu)
        s.run(d.rstrip("/").rsplit("/", 1)[-1], g, algos, seeds, t)
    return s


def w2_truth(study: Study) -> DataFrame:
    return study.runs().groupBy("graph", "algo").agg(F.avg("ari_truth").alias("ari"))


def w3_truth_contracted(spark, d, mu=0.4) -> dict:
    g, t = planted_graph(spark, d, mu)
    return Q.resolution_probe(g, t)


def w4_mu_sweep(spark, d, mus=tuple(i / 10 for i in range(1, 10)), algos=EVERY, seeds=range(1)) -> Study:
    """Scores and likeness to the truth over mixings; the graphs are built one after another, the runs go side by side."""
    return Study(spark).run_together([(f"planted_{mu}", *planted_graph(spark, d, mu)) for mu in mus], algos, seeds)


def w5_score_contestants(spark, d, mus=(0.2, 0.4, 0.6, 0.8)) -> DataFrame:
    out = []
    for mu in mus:
        g, t = planted_graph(spark, d, mu)
        one = g.nodes.select("id", F.col("id").alias("c"))
        out += [(mu, who, Q.modularity(g, x), Q.map_equation(g, x)) for who, x in (("truth", t), ("singleton", one), ("found", V.sync_map(g).labels))]
    return spark.createDataFrame(out, "mu double, who string, modularity double, map_equation double")


def w6_hub_growth(spark, d, graphs=("trade", "planted"), top=10) -> DataFrame:
    """Largest clusters of each graph after the first round, synchronous against sequential moves."""
    import random

    from graphmoves.baselines.sequential import _frame, on_one_worker, sweep

    def once(flow):
        c = list(range(len(flow.p)))
        sweep(flow, "modularity", random.Random(0), c, max_sweeps=1)
        return c

    out = []
    for graph in graphs:
        g = from_pairs(G.GRAPHS[graph](spark, d))
        sync, _ = local_moving(g, None, Config(max_rounds=1), "modularity")
        seq = snapshot(on_one_worker(_frame(g), g.nodes.count(), g.edges.count(), once, True))
        for who, x in (("synchronous", sync), ("sequential", seq)):
            out.append(x.groupBy("c").count().orderBy(F.desc("count")).limit(top).select(F.lit(graph).alias("graph"), F.lit(who).alias("who"), F.col("count").alias("size")))
    return reduce(DataFrame.union, out)


def w7_times(spark, d, graphs=("trade", "copurchase", "links", "neardup", "knn"), algos=EVERY, seeds=range(1)) -> Study:
    """Times, scores (w8) and likeness to the best run (w9) on the tables' graphs."""
    s = Study(spark)
    for name in graphs:
        s.run(name, from_pairs(G.GRAPHS[name](spark, d)), algos, seeds)
    return s


def w8_scores(study: Study) -> DataFrame:
    return study.runs().groupBy("graph").pivot("algo").agg(F.avg(F.when(F.col("objective") == "map", F.col("map_equation")).otherwise(F.col("modularity"))))


def w9_similarity(study: Study) -> DataFrame:
    return study.to_best()


def w10_ablation(spark, d, graph="planted", ks=(1, 2, 4, 8), rounds=(1, 2, 4, 8, 16)) -> DataFrame:
    g, out = from_pairs(G.GRAPHS[graph](spark, d)), []
    for k in ks:
        for r in rounds:
            labels, trace = local_moving(g, None, Config(sub_rounds=k, max_rounds=r), "modularity")
            out.append((k, r, len(trace), trace[-1][3], trace[-1][4], Q.modularity(g, labels)))
    return spark.createDataFrame(out, "k int, max_rounds int, rounds int, last_moved long, clusters long, modularity double")


def w11_contraction(spark, d, graphs=("planted", "links"), seeds=range(1)) -> Study:
    return w7_times(spark, d, graphs, ("sync_modularity", "sync_modularity_flat", "sync_map", "sync_map_flat"), seeds)


def w12_physical(spark, d, graph="planted", strategies=("edge_join", "broadcast_labels", "cluster_local"), partitions=(4, 16)) -> DataFrame:
    """Same labels whatever the strategy and number of partitions; seconds differ."""
    g, out, first = from_pairs(G.GRAPHS[graph](spark, d)), [], None
    was = spark.conf.get("spark.sql.shuffle.partitions")
    try:
        for s in strategies:
            for n in partitions:
                spark.conf.set("spark.sql.shuffle.partitions", n)
                began = time.perf_counter()
                labels, _ = local_moving(g, None, Config(max_rounds=1, strategy=s), "modularity")
                seconds = time.perf_counter() - began
                first = first if first is not None else labels
                out.append((s, n, seconds, labels.exceptAll(first).count() == 0))
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", was)
    return spark.createDataFrame(out, "strategy string, partitions int, seconds double, same boolean")


def w13_prepare(spark, d, graph="trade", seed=0) -> DataFrame:
    g, _ = prepare(from_pairs(G.GRAPHS[graph](spark, d)), seed)
    return Q.describe_graph(g)


def w14_lfr(spark, n=2000, mu=0.4, seed=0) -> DataFrame:
    """Achieved mixing, degrees and community sizes of a scaled-down generated graph."""
    pairs, truth = G.lfr(spark, n, mu, (5, 100, 2.0), (20, 200, 1.0), seed)
    at = pairs.join(truth.selectExpr("id as a", "c as ca"), "a").join(truth.selectExpr("id as b", "c as cb"), "b")
    sizes = truth.groupBy("c").count().agg(F.min("count").alias("smallest"), F.max("count").alias("largest"))
    return at.agg(F.count("*").alias("edges"), F.avg((F.col("ca") != F.col("cb")).cast("double")).alias("mu")).crossJoin(sizes)


def w15_directed(spark, d, graph="links") -> DataFrame:
    """Map equation on the undirected graph against the walk along the edges' own direction."""
    pairs = G.GRAPHS[graph](spark, d)
    g = from_pairs(pairs)
    und = sequential_cluster(g, "map", 0)
    arcs = snapshot(pairs.selectExpr("a as src", "b as dst", "w"))
    direct = B.seq_map_directed(g, 0, arcs)
    flow, visit = B.walk(arcs, g.nodes)
    out = [("undirected", Q.map_equation(g, und), Q.map_equation_directed(flow, visit, und)), ("directed", Q.map_equation(g, direct), Q.map_equation_directed(flow, visit, direct))]
    return spark.createDataFrame(out, "clustering string, map_equation double, directed double").crossJoin(spark.createDataFrame([(Q.adjusted_rand(und, direct),)], "ari double"))
