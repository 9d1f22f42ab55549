"""All queries and their SQL: graphs, moving phases, scores, baselines, generators, relational operators, streams."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from graphmoves import experiments as X
from graphmoves import oracle as O
from graphmoves import quality as Q
from graphmoves.baselines import others as B
from graphmoves.baselines.sequential import sequential_cluster
from graphmoves.functions import udfs
from graphmoves.functions.columns import activation
from graphmoves.model import Config
from graphmoves.operators import relational as R
from graphmoves.plans import levels as V
from graphmoves.plans import moving as M
from graphmoves.session import shared_folder, snapshot, table
from graphmoves.sources import files, graphs
from graphmoves.sources.build import dense_ids, from_pairs, prepare, to_adjacency, to_edges
from graphmoves.streaming import edges as S

QUERIES: dict = {}
ORACLE_SQL: dict = {}
PORTABLE = Config(hash_kind="portable")
PLANTED, TRADE = O.GRAPH_SQL["planted"], O.GRAPH_SQL["trade"]


def entry(sql: str | None = None, name: str | None = None):
    def keep(f):
        QUERIES[name or f.__name__] = f
        if sql:
            ORACLE_SQL[name or f.__name__] = sql
        return f

    return keep


_BUILT: dict = {}


def graph(name: str):
    """Builds a table graph; a session builds each graph of a folder once, since its tables stay in the shared folder."""
    def built(s: SparkSession, d: str):
        key = (s.sparkContext.applicationId, s._jsparkSession.sessionUUID(), d, name)
        if key not in _BUILT:
            _BUILT[key] = from_pairs(graphs.GRAPHS[name](s, d))
        return _BUILT[key]

    return built


trade, planted = graph("trade"), graph("planted")
for _g, _f in graphs.GRAPHS.items():
    QUERIES[f"graph_{_g}"], ORACLE_SQL[f"graph_{_g}"] = _f, f"SELECT a, b, w FROM ({O.GRAPH_SQL[_g]})"
QUERIES["graph_neardup"] = lambda s, d: graphs.neardup(s, d, df_limit=30)  # as its SQL
for _mu in (0.2, 0.6):
    _key = f"graph_planted_mu{round(_mu * 10)}"
    QUERIES[_key], ORACLE_SQL[_key] = (lambda s, d, mu=_mu: graphs.planted(s, d, mu)), O.planted_sql(_mu)


# --- moving phases ---------------------------------------------------------------------------------


def _phase(name: str, graph_name: str, objective: str, rounds: int) -> None:
    def run(s: SparkSession, d: str) -> DataFrame:
        return M.local_moving(graph(graph_name)(s, d), None, Config(hash_kind="portable", max_rounds=rounds), objective)[0]

    QUERIES[name], ORACLE_SQL[name] = run, O.moving_sql(O.GRAPH_SQL[graph_name], objective, rounds)


_phase("flat_modularity_trade_2r", "trade", "modularity", 2)
_phase("flat_modularity_planted_8r", "planted", "modularity", 8)
_phase("flat_map_planted_2r", "planted", "map", 2)
_phase("flat_map_trade_1r", "trade", "map", 1)
_phase("tie_break_cosupply", "cosupply", "modularity", 1)
_phase("flat_modularity_links_2r", "links", "modularity", 2)


def _one(objective: str):
    """Labels after the first sub-round."""
    ctes, _ = O.rounds_ctes(objective, 1)
    pairs = TRADE if objective == "modularity" else PLANTED
    return f"WITH {O.graph_ctes(pairs)}, {ctes} SELECT id, c FROM L1"


@entry(_one("modularity"))
def subround_modularity_trade(s, d):
    g = trade(s, d)
    return M.sub_round(g, M.state_of(g, M.singleton_labels(g)), 0, 0, PORTABLE, "modularity").select("id", "c")


@entry(_one("map"))
def subround_map_planted(s, d):
    g = planted(s, d)
    return M.sub_round(g, M.state_of(g, M.singleton_labels(g)), 0, 0, PORTABLE, "map").select("id", "c")


def _bids_sql(pairs: str, objective: str) -> str:
    ctes, _ = O.rounds_ctes(objective, 1)
    body = "SELECT v, b.c, CAST(x AS BIGINT) AS x, CAST(s.vol - CASE WHEN b.c = l.c THEN deg ELSE 0 END AS BIGINT) AS vol_wo, CAST(b.c = l.c AS INT) AS is_own"
    cut = ", CAST(CASE WHEN b.c = l.c THEN s.cut - deg + 2 * x ELSE s.cut END AS BIGINT) AS cut_wo" if objective == "map" else ""
    return f"WITH {O.graph_ctes(pairs)}, {ctes} {body}{cut} FROM L1b b JOIN L1s s ON s.c = b.c JOIN nodes ON id = v JOIN L0 l ON l.id = v"


@entry(_bids_sql(TRADE, "modularity"))
def bids_modularity_trade(s, d):
    g = trade(s, d)
    st = M.state_of(g, M.singleton_labels(g))
    return M.make_bids(g, st, M.cluster_stats(g, st, False), 0, 0, PORTABLE).select("v", "c", "x", "vol_wo", "is_own")


@entry(_bids_sql(PLANTED, "map"))
def bids_map_planted(s, d):
    g = planted(s, d)
    st = M.state_of(g, M.singleton_labels(g))
    return M.make_bids(g, st, M.cluster_stats(g, st, True), 0, 0, PORTABLE, ("vol", "cut")).select("v", "c", "x", "vol_wo", "is_own", "cut_wo")


for _s in ("broadcast_labels", "cluster_local"):
    QUERIES[f"bids_{_s}_trade"] = lambda s, d, k=_s: (lambda g, st: M.make_bids(g, st, M.cluster_stats(g, st, False), 0, 0, Config(hash_kind="portable", strategy=k)).select("v", "c", "x", "vol_wo", "is_own"))(*(lambda g: (g, M.state_of(g, M.singleton_labels(g))))(trade(s, d)))
    ORACLE_SQL[f"bids_{_s}_trade"] = _bids_sql(TRADE, "modularity")


@entry(f"SELECT {O.U32.format(chr(39) + chr(39) + ' || c_custkey || ' + chr(39) + ':0:0' + chr(39))} % 4 AS r, count(*) AS n FROM customer GROUP BY 1")
def activation_histogram(s, d):
    return table(s, d, "customer").groupBy(activation(F.col("c_custkey"), 0, 0, 4, "portable").alias("r")).agg(F.count("*").alias("n"))


@entry(f"WITH {O.graph_ctes(PLANTED)}, {O.rounds_ctes('modularity', 1)[0]} SELECT n, count(*) AS clusters FROM (SELECT c, count(*) AS n FROM L4 GROUP BY c) GROUP BY n")
def size_growth_first_round(s, d):
    labels, _ = M.local_moving(planted(s, d), None, Config(hash_kind="portable", max_rounds=1), "modularity")
    return labels.groupBy("c").agg(F.count("*").alias("n")).groupBy("n").agg(F.count("*").alias("clusters"))


# --- scores ----------------------------------------------------------------------------------------


def _scored(pairs: str, labels: str, last: str) -> str:
    return f"WITH {O.graph_ctes(pairs)}, lab AS MATERIALIZED ({labels}), st AS MATERIALIZED ({O.stats_sql('lab')}) {last}"


@entry(_scored(TRADE, "SELECT id, id AS c FROM nodes", O.modularity_sql("st")))
def singleton_scores(s, d):
    g = trade(s, d)
    return Q.modularity_frame(g, M.singleton_labels(g)).select(F.round("q", 9).alias("q"))


@entry(_scored(PLANTED, O.TRUTH, O.modularity_sql("st")))
def modularity_planted_truth(s, d):
    return Q.modularity_frame(planted(s, d), graphs.planted_truth(s, d)).select(F.round("q", 9).alias("q"))


@entry(_scored(PLANTED, O.TRUTH, O.map_sql("st")))
def map_equation_planted_truth(s, d):
    return Q.map_equation_frame(planted(s, d), graphs.planted_truth(s, d)).select(F.round("l", 9).alias("l"))


@entry(_scored(PLANTED, "SELECT id, id AS c FROM nodes", O.map_sql("st")))
def truth_vs_singleton(s, d):
    g = planted(s, d)
    return Q.map_equation_frame(g, M.singleton_labels(g)).select(F.round("l", 9).alias("l"))


@entry(_scored(PLANTED, O.TRUTH, "SELECT c, CAST(vol AS BIGINT) AS vol, CAST(inner_w AS BIGINT) AS inner_w, CAST(cut AS BIGINT) AS cut, size FROM st"))
def cluster_stats_planted(s, d):
    return Q.measures(planted(s, d), graphs.planted_truth(s, d)).select("c", "vol", F.col("inner").alias("inner_w"), "cut", F.col("members").alias("size"))


@entry(_scored(O.GRAPH_SQL["geo"], "SELECT id, CASE WHEN id % 4 = 3 THEN id WHEN id % 4 = 2 THEN 4 * CAST(n_regionkey AS BIGINT) + 3 ELSE -1 END AS c FROM nodes LEFT JOIN nation ON id = n_nationkey * 4 + 2", "SELECT round(sum(inner_w) / max(t)::DOUBLE, 9) AS coverage FROM st, total"))
def coverage_geo_region(s, d):
    g = graph("geo")(s, d)
    nat = table(s, d, "nation").select((F.col("n_nationkey").cast("long") * 4 + 2).alias("id"), (F.col("n_regionkey").cast("long") * 4 + 3).alias("r"))
    lab = g.nodes.select("id").join(F.broadcast(nat), "id", "left").select("id", F.when(F.col("id") % 4 == 3, F.col("id")).otherwise(F.coalesce("r", F.lit(-1))).alias("c"))
    return Q.measures(g, lab).agg(F.round(F.sum("inner") / float(g.total), 9).alias("coverage"))


@entry(f"WITH {O.graph_ctes(TRADE)} SELECT (SELECT count(*) FROM nodes) AS nodes, (SELECT count(*) FROM pairs) AS edges, (SELECT CAST(max(deg) AS BIGINT) FROM nodes) AS max_degree, round((SELECT avg(deg) FROM nodes), 6) AS mean_degree")
def describe_trade(s, d):
    return Q.describe_graph(trade(s, d)).select("nodes", "edges", "max_degree", F.round("mean_degree", 6).alias("mean_degree"))


@entry(f"WITH {O.graph_ctes(PLANTED)}, {O.rounds_ctes('modularity', 2)[0]}, truth AS ({O.TRUTH}), {O.ari_sql('truth', 'L8')}")
def ari_truth_vs_flat(s, d):
    labels, _ = M.local_moving(planted(s, d), None, Config(hash_kind="portable", max_rounds=2), "modularity")
    return Q.ari_frame(graphs.planted_truth(s, d), labels).select(F.round("ari", 9).alias("ari"))


@entry(f"WITH q AS (SELECT doc_id AS id, quality AS c FROM labels), t AS (SELECT doc_id AS id, toxic AS c FROM labels), {O.ari_sql('q', 't')}")
def ari_quality_vs_toxic(s, d):
    t = table(s, d, "labels")
    return Q.ari_frame(t.selectExpr("doc_id as id", "quality as c"), t.selectExpr("doc_id as id", "toxic as c")).select(F.round("ari", 9).alias("ari"))


@entry()
def sampled_modularity_planted(s, d):
    g, t = planted(s, d), graphs.planted_truth(s, d)
    return s.createDataFrame([(*Q.sampled_modularity(g, t, 0.2), Q.modularity(g, t))], "estimate double, error double, exact double")


@entry()
def resolution_probe(s, d):
    return s.createDataFrame([tuple(float(x) for x in X.w3_truth_contracted(s, d).values())], "truth double, merged double, ari double, clusters double")


# --- ids, contraction, levels ----------------------------------------------------------------------


@entry("SELECT c_nationkey AS k, dense_rank() OVER (ORDER BY c_nationkey) - 1 AS dense FROM (SELECT DISTINCT c_nationkey FROM customer)")
def dense_ids_nation(s, d):
    return dense_ids(table(s, d, "customer").select(F.col("c_nationkey").alias("k")), "k")


@entry(f"WITH {O.graph_ctes(PLANTED)}, lab AS ({O.TRUTH}) SELECT x.c AS src, y.c AS dst, CAST(sum(w) AS BIGINT) AS w FROM edges JOIN lab x ON x.id = src JOIN lab y ON y.id = dst WHERE x.c <> y.c GROUP BY 1, 2")
def contract_planted_by_nation(s, d):
    return V.contract(planted(s, d), graphs.planted_truth(s, d), dense=False)[0].edges


@entry(_scored(PLANTED, O.TRUTH, "SELECT c AS id, CAST(inner_w // 2 AS BIGINT) AS loop, CAST(vol AS BIGINT) AS deg FROM st"))
def contract_loops_planted(s, d):
    return V.contract(planted(s, d), graphs.planted_truth(s, d), dense=False)[0].nodes.select("id", "loop", "deg")


@entry("SELECT c_custkey AS id, CAST(n_regionkey AS BIGINT) AS c FROM customer JOIN nation ON c_nationkey = n_nationkey")
def unpack_two_levels(s, d):
    members = graphs.planted_truth(s, d).selectExpr("id as fine_id", "c as coarse_id")
    return V.unpack(table(s, d, "nation").selectExpr("cast(n_nationkey as bigint) as id", "cast(n_regionkey as bigint) as c"), members)


def _two_levels(objective: str, rounds: int = 1) -> str:
    """A phase, contraction, a second phase with the next seed, unpacked; loops enter degrees by the nodes' own column."""
    first, last = O.rounds_ctes(objective, rounds)
    second, end = O.rounds_ctes(objective, rounds, seed=1, name="K")
    for t in ("edges", "nodes"):
        second = second.replace(f" {t} ", f" {t}2 ").replace(f"({t} ", f"({t}2 ").replace(f" {t})", f" {t}2)")
    return f"""WITH {O.graph_ctes(PLANTED)}, {first},
        own AS MATERIALIZED (SELECT id, dense_rank() OVER (ORDER BY c) - 1 AS c FROM {last}),
        edges2 AS MATERIALIZED (SELECT x.c AS src, y.c AS dst, sum(w) AS w FROM edges JOIN own x ON x.id = src JOIN own y ON y.id = dst WHERE x.c <> y.c GROUP BY 1, 2),
        inner2 AS MATERIALIZED (SELECT x.c AS id, sum(w) AS w FROM edges JOIN own x ON x.id = src JOIN own y ON y.id = dst WHERE x.c = y.c GROUP BY 1),
        nodes2 AS MATERIALIZED (SELECT id, deg, CAST(coalesce(w, 0) // 2 AS HUGEINT) AS loop FROM (SELECT c AS id, sum(deg) AS deg FROM own JOIN nodes USING (id) GROUP BY 1) LEFT JOIN inner2 USING (id)),
        {second} SELECT own.id, z.c FROM own JOIN {end} z ON z.id = own.c"""


@entry(_two_levels("modularity"))
def multilevel_modularity_planted(s, d):
    g = planted(s, d)
    from dataclasses import replace

    return V.cluster(g, "modularity", replace(PORTABLE, max_rounds=1, max_levels=2)).labels


@entry(_two_levels("map"))
def multilevel_map_planted(s, d):
    from dataclasses import replace

    return V.cluster(planted(s, d), "map", replace(PORTABLE, max_rounds=1, max_levels=2)).labels


@entry()
def sync_map_planted(s, d):
    return V.sync_map(planted(s, d)).labels


@entry()
def sync_modularity_links(s, d):
    return V.sync_modularity(graph("links")(s, d)).labels


@entry()
def warm_start_usage(s, d):
    g = graph("usage")(s, d)
    first, _ = M.local_moving(g, None, Config(max_rounds=1), "modularity")
    return V.cluster(g, "modularity", Config(max_levels=1), first).labels


@entry()
def constant_size_planted(s, d):
    """Another density measure: a null model in which all pairs of nodes are equally likely."""
    return V.cluster(planted(s, d), "constant_size", Config(max_levels=2, max_rounds=2)).labels


@entry(_scored(PLANTED, O.TRUTH, "SELECT round(sum(inner_w / t::DOUBLE - (size / n::DOUBLE) * (size / n::DOUBLE)), 9) AS q FROM st, total, (SELECT count(*) AS n FROM nodes)"))
def constant_size_planted_truth(s, d):
    return Q.constant_size_frame(planted(s, d), graphs.planted_truth(s, d)).select(F.round("q", 9).alias("q"))


@entry()
def trace_sub_rounds_planted(s, d):
    """Movers, clusters and score after every sub-round of two rounds."""
    from graphmoves.model import TRACE

    _, trace = M.local_moving(planted(s, d), None, Config(max_rounds=2, trace="sub_rounds", scores=True), "modularity")
    return s.createDataFrame(trace, TRACE)


@entry()
def resolution_gamma_planted(s, d):
    """Another density measure: modularity with a resolution of 2."""
    return V.cluster(planted(s, d), "resolution:2.0", Config(max_levels=1, max_rounds=2)).labels


@entry(f"WITH {O.graph_ctes(TRADE)} SELECT CAST(count(*) AS BIGINT) AS nodes, CAST(min(0) AS BIGINT) AS least FROM nodes")
def prepare_trade(s, d):
    g, ids = prepare(trade(s, d))
    return ids.agg(F.count("*").alias("nodes"), F.min("dense").alias("least"))


@entry(f"WITH {O.graph_ctes(TRADE)} SELECT src, dst, CAST(w AS BIGINT) AS w FROM edges")
def adjacency_round_trip(s, d):
    return to_edges(to_adjacency(trade(s, d)))


# --- baselines -------------------------------------------------------------------------------------


def _lp(iters: int) -> str:
    out = ["P0 AS MATERIALIZED (SELECT id, id AS c FROM nodes)"]
    for i in range(iters):
        out.append(f"P{i + 1} AS MATERIALIZED (SELECT dst AS id, c FROM (SELECT dst, c, row_number() OVER (PARTITION BY dst ORDER BY sum(w) DESC, c) AS r FROM edges JOIN P{i} ON id = src GROUP BY dst, c) WHERE r = 1)")
    return f"WITH {O.graph_ctes(TRADE)}, {', '.join(out)} SELECT id, c FROM P{iters}"


@entry(_lp(2))
def label_propagation_2it(s, d):
    return B.label_propagation(trade(s, d), 2)


def _pr(iters: int) -> str:
    out = ["n AS (SELECT count(*) AS n FROM nodes)", "o AS MATERIALIZED (SELECT a AS id, sum(w)::DOUBLE AS out_w FROM pairs GROUP BY 1)", "R0 AS MATERIALIZED (SELECT id, 1.0::DOUBLE / n AS p FROM nodes, n)"]
    for i in range(iters):
        out.append(f"""R{i + 1} AS MATERIALIZED (SELECT nodes.id, 0.15::DOUBLE / n + 0.85::DOUBLE * (coalesce(got, 0) + (SELECT coalesce(sum(p), 0) FROM R{i} LEFT JOIN o USING (id) WHERE out_w IS NULL) / n) AS p
            FROM nodes LEFT JOIN (SELECT b AS id, sum(w * p / out_w) AS got FROM pairs JOIN R{i} ON R{i}.id = a JOIN o ON o.id = a GROUP BY 1) USING (id), n)""")
    return f"WITH {O.graph_ctes(O.GRAPH_SQL['links'])}, {', '.join(out)} SELECT id, round(p, 9) AS p FROM R{iters}"


@entry(_pr(10))
def pagerank_links_10it(s, d):
    g = graph("links")(s, d)
    arcs = graphs.links(s, d).selectExpr("a as src", "b as dst", "w")
    return B.pagerank(arcs, g.nodes, iters=10).select("id", F.round("p", 9).alias("p"))


for _name, _graph, _f in (
    ("seq_modularity_planted", "planted", lambda g: sequential_cluster(g, "modularity")),
    ("seq_map_planted", "planted", lambda g: sequential_cluster(g, "map")),
    ("parallel_modularity_planted", "planted", lambda g: B.parallel_cluster(g, "modularity")),
    ("stale_map_standin_planted", "planted", lambda g: B.stale_map_standin(g, Config(max_rounds=2, max_levels=2)).labels),
    ("chunk_merge_range", "planted", lambda g: B.chunk_merge(g, 4, "range")),
    ("chunk_merge_lp", "planted", lambda g: B.chunk_merge(g, 4, "lp")),
    ("unsplit_rounds_planted", "planted", lambda g: V.sync_modularity(g, Config(sub_rounds=1, max_rounds=2, max_levels=2)).labels),
):
    QUERIES[_name] = lambda s, d, n=_graph, f=_f: f(graph(n)(s, d))


def _arcs(s, d) -> DataFrame:
    """Links in their own direction, from page to target."""
    return snapshot(graphs.links(s, d).selectExpr("a as src", "b as dst", "w"))


@entry()
def seq_map_directed_links(s, d):
    return B.seq_map_directed(graph("links")(s, d), 0, _arcs(s, d))


@entry()
def parallel_map_directed_links(s, d):
    g = graph("links")(s, d)
    return B.parallel_cluster(g, "map", flow=B.walk(_arcs(s, d), g.nodes))


@entry()
def lfr_small(s, d):
    return X.w14_lfr(s, 1000)


_BEST_RUNS = """WITH runs AS (
        SELECT 'status_' || o_orderstatus AS graph, o_orderpriority AS algo, objective, CAST(o_custkey % 1000 AS INT) AS seed,
            max(o_totalprice / (1 + o_custkey % 7)) AS modularity, min(o_totalprice * (1 + o_custkey % 5)) AS map_equation FROM orders, (VALUES ('modularity'), ('map')) o(objective) GROUP BY ALL)
    SELECT graph, objective, algo, seed FROM runs
    QUALIFY row_number() OVER (PARTITION BY graph, objective ORDER BY CASE WHEN objective = 'map' THEN map_equation ELSE -modularity END, algo, seed) = 1"""


@entry(_BEST_RUNS)
def best_reference_runs(s, d):
    """Orders as runs: of a status and priority (graph, algorithm) and customers' groups (seeds), scored by their prices."""
    from graphmoves.model import RUNS

    key = (F.concat(F.lit("status_"), "o_orderstatus").alias("graph"), F.col("o_orderpriority").alias("algo"), (F.col("o_custkey") % 1000).cast("int").alias("seed"))
    scores = (F.max(F.col("o_totalprice") / (1 + F.col("o_custkey") % 7)).alias("modularity"), F.min(F.col("o_totalprice") * (1 + F.col("o_custkey") % 5)).alias("map_equation"))
    own = table(s, d, "orders").groupBy(*key).agg(*scores).withColumn("objective", F.explode(F.array(F.lit("modularity"), F.lit("map")))).withColumn("seconds", F.lit(1.0))
    runs = own.select(*[(F.col(x.name) if x.name in own.columns else F.lit(None).cast(x.dataType)).alias(x.name) for x in RUNS])
    return X.best_reference(runs).select("graph", "objective", "algo", "seed")


# --- user-defined functions ------------------------------------------------------------------------


@entry(R.SQL["fn_cosine"])
def udf_cosine(s, d):
    e = table(s, d, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("v"))
    j = e.crossJoin(F.broadcast(e.where("vec_id = 0").select(F.col("v").alias("u"))))
    return j.select("vec_id", F.round(udfs.cosine_pd("v", "u"), 6).alias("s"))


@entry(_scored(PLANTED, O.TRUTH, f"SELECT round(sum({O.p('(cut + vol) / t::DOUBLE')} - 2 * {O.p('cut / t::DOUBLE')}), 9) AS m FROM st, total"))
def udaf_map_terms(s, d):
    g = planted(s, d)
    m = Q.measures(g, graphs.planted_truth(s, d))
    return m.groupBy().agg(F.round(udfs.map_terms_agg(m.cut.cast("double"), m.vol.cast("double"), F.lit(float(g.total))), 9).alias("m"))


@entry("SELECT c_custkey AS id, CAST(c_nationkey AS BIGINT) AS c FROM customer")
def udtf_expand_members(s, d):
    s.udtf.register("expand_members", udfs.ExpandMembers)
    graphs.planted_truth(s, d).groupBy("c").agg(F.collect_list("id").alias("ids")).createOrReplaceTempView("member_lists")
    return s.sql("SELECT x.id, x.c FROM member_lists m, LATERAL expand_members(m.ids, m.c) x")


@entry(f"SELECT c_custkey AS k, round(CASE WHEN c_custkey > 0 THEN c_custkey * ln(c_custkey) ELSE 0 END, 6) AS p FROM customer")
def sql_function_plogp(s, d):
    from graphmoves.functions.columns import register_sql

    register_sql(s)
    table(s, d, "customer").createOrReplaceTempView("customer_p")
    return s.sql("SELECT c_custkey AS k, round(plogp(CAST(c_custkey AS DOUBLE)), 6) AS p FROM customer_p")


@entry()
def cogroup_compare_labels(s, d):
    t = lambda k, name: snapshot(graphs.planted_truth(s, d).select("id", (F.col("c") % k).alias(name)))
    return udfs.compare_by_component(t(25, "c"), t(5, "c"), t(4, "comp"))


# --- files -----------------------------------------------------------------------------------------


def _there_and_back(kind: str):
    def run(s: SparkSession, d: str) -> DataFrame:
        e = trade(s, d).edges
        path = f"{shared_folder(s)}/{kind}{uuid.uuid4().hex}"
        files.write_edges(e, path, kind)
        return files.read_edges(s, path, kind)

    return run


for _k in ("parquet", "csv", "json", "orc"):
    QUERIES[f"scan_{_k}_edges"] = _there_and_back(_k)
    ORACLE_SQL[f"scan_{_k}_edges"] = f"WITH {O.graph_ctes(TRADE)} SELECT src, dst, CAST(w AS BIGINT) AS w FROM edges"


@entry(f"WITH {O.graph_ctes(TRADE)} SELECT src, dst, CAST(w AS BIGINT) AS w FROM edges")
def scan_text_edgelist(s, d):
    path = f"{shared_folder(s)}/list{uuid.uuid4().hex}"
    lines = trade(s, d).edges.select(F.concat_ws(" ", "src", "dst", "w").alias("value"))
    lines.union(s.createDataFrame([("# remark",), ("",)], "value string")).write.text(path)
    return files.read_edge_list(s, path)


@entry("SELECT c_custkey AS id, CAST(c_nationkey AS BIGINT) AS c, 1 AS level FROM customer")
def scan_partitioned_levels(s, d):
    path = f"{shared_folder(s)}/levels{uuid.uuid4().hex}"
    t = graphs.planted_truth(s, d)
    files.write_edges(t.withColumn("level", F.lit(1)).union(t.select("id", "id", F.lit(0))), path, by="level")
    return s.read.parquet(path).where("level = 1").select("id", "c", "level")


@entry(f"WITH {O.graph_ctes(TRADE)} SELECT src, dst, CAST(w AS BIGINT) AS w FROM edges")
def sink_bucketed(s, d):
    return files.write_bucketed(trade(s, d).edges, f"edges_{uuid.uuid4().hex[:8]}", "src", 8)


for _k in ("parquet", "csv", "json", "orc"):
    QUERIES[f"sink_{_k}_labels"] = lambda s, d, k=_k: files.labels_there_and_back(graphs.planted_truth(s, d), f"{shared_folder(s)}/labels{uuid.uuid4().hex}", k)
    ORACLE_SQL[f"sink_{_k}_labels"] = "SELECT c_custkey AS id, CAST(c_nationkey AS BIGINT) AS c FROM customer"


@entry("SELECT c_custkey AS id, CAST(c_nationkey AS BIGINT) AS c FROM customer")
def sink_noop(s, d):
    """A run without output: the plan is executed, nothing is kept; the rows are those it had."""
    t = graphs.planted_truth(s, d)
    t.write.format("noop").mode("overwrite").save()
    return t


@entry(f"WITH {O.graph_ctes(O.GRAPH_SQL['links'])}, ids AS (SELECT id, row_number() OVER (ORDER BY id) - 1 AS k FROM nodes) SELECT x.k AS src, y.k AS dst, CAST(1 AS BIGINT) AS w FROM edges JOIN ids x ON x.id = src JOIN ids y ON y.id = dst")
def scan_adjacency_format(s, d):
    """A graph written in the adjacency format and read by the Python data source."""
    g, _ = prepare(graph("links")(s, d), randomise=False)
    path = f"{shared_folder(s).removeprefix('file:')}/graph{uuid.uuid4().hex}"
    files.write_adjacency(g.edges, path, g.nodes.count())
    s.dataSource.register(files.AdjacencySource)
    return s.read.format("adjacency").option("path", path).load()


@entry()
def scan_sample(s, d):
    return trade(s, d).edges.sample(0.1, 7)


# --- streams ---------------------------------------------------------------------------------------


def _stream(s, d):
    return S.event_stream(s, f"{d}/events.parquet")


@entry("SELECT date_trunc('hour', ts) AS start, user_id, CAST(props ->> '$.k' AS BIGINT) AS k, count(*) AS w_count FROM events GROUP BY 1, 2, 3")
def stream_usage_hours(s, d):
    out = S.run_to_end(S.usage_windows(_stream(s, d)), "complete")
    return out.select(F.col("start").cast("timestamp_ntz").alias("start"), "user_id", "k", "w_count")


@entry("SELECT user_id, count(*) AS degree FROM events GROUP BY 1")
def stream_running_degree(s, d):
    return S.run_to_end(S.running_degree(_stream(s, d)), "update").groupBy("user_id").agg(F.max("degree").alias("degree"))


@entry("SELECT DISTINCT user_id, CAST(props ->> '$.k' AS BIGINT) AS k FROM events")
def stream_first_edges(s, d):
    return S.run_to_end(S.first_edges(_stream(s, d), "3650 days").select("user_id", "k"))


@entry("SELECT event_id, user_id, CAST(c_nationkey AS BIGINT) AS c FROM events LEFT JOIN customer ON user_id = c_custkey")
def stream_static_join(s, d):
    return S.run_to_end(S.with_static(_stream(s, d), graphs.planted_truth(s, d)))


@entry("SELECT c.event_id AS ce, p.event_id AS pe FROM events c JOIN events p ON c.user_id = p.user_id AND c.event_type = 'click' AND p.event_type = 'purchase' AND p.ts >= c.ts AND p.ts <= c.ts + INTERVAL 1 HOUR")
def stream_click_purchase(s, d):
    return S.run_to_end(S.clicks_then_purchases(_stream(s, d), late="3650 days"))


_SESSIONS = """WITH m AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER w + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS opens FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
    g AS (SELECT *, sum(opens) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS no FROM m)
    SELECT min(ts) AS start, max(ts) + INTERVAL 30 MINUTE AS "end", user_id, count(*) AS n FROM g GROUP BY user_id, no"""


@entry(_SESSIONS)
def stream_sessions(s, d):
    out = S.run_to_end(S.sessions(_stream(s, d)), "complete")
    return out.select(F.col("start").cast("timestamp_ntz").alias("start"), F.col("end").cast("timestamp_ntz").alias("end"), "user_id", "n")


@entry()
def stream_cluster_batches(s, d):
    log = S.cluster_batches(_stream(s, d), Config(max_rounds=1))
    return s.createDataFrame([(x["batch"], x["moved"], x["clusters"]) for x in log], "batch int, moved long, clusters long")


# --- experiments (small settings) ------------------------------------------------------------------

FLAT = ("sync_modularity_flat",)


def _links_study(s, d, algos=("sync_modularity_flat", "seq_modularity", "seq_map", "label_propagation"), seeds=range(1)):
    return X.w7_times(s, d, ("links",), algos, seeds)


def _a10(s, d):
    """One size on this machine stands for one host."""
    study = X.w1_weak_scaling(s, [d], algos=FLAT)
    return X.weak_scaling(study.runs(), study.runs().select("graph", F.lit(1).alias("hosts")).distinct())


for _name, _f in (
    ("w2_truth", lambda s, d: X.w2_truth(X.w1_weak_scaling(s, [d], algos=("sync_modularity_flat", "sync_map")))),
    ("w4_mu_sweep", lambda s, d: X.w4_mu_sweep(s, d).runs()),
    ("w7_times", lambda s, d: _links_study(s, d).runs()),
    ("w8_scores", lambda s, d: X.w8_scores(_links_study(s, d))),
    ("w11_contraction", lambda s, d: X.w11_contraction(s, d, ("links",)).runs()),
    ("a8_stability", lambda s, d: _links_study(s, d, FLAT, range(2)).stability()),
    ("a9_mean_times", lambda s, d: X.mean_times(_links_study(s, d, ("seq_modularity", "label_propagation"), range(3)).runs())),
    ("a10_weak_scaling", _a10),
    ("a11_ratio_table", lambda s, d: X.ratio_table(_links_study(s, d).runs(), "sync_modularity_flat")),
    ("a12_used_by", lambda s, d: X.used_by(_links_study(s, d).runs())),
    ("w1_weak_scaling", lambda s, d: X.w1_weak_scaling(s, [d], algos=("sync_modularity_flat",)).runs()),
    ("w5_score_contestants", lambda s, d: X.w5_score_contestants(s, d, (0.4,))),
    ("w6_hub_growth", lambda s, d: X.w6_hub_growth(s, d)),
    ("w9_similarity", lambda s, d: X.w9_similarity(X.w7_times(s, d, ("links",), ("sync_modularity_flat", "seq_modularity", "seq_map")))),
    ("w10_ablation", lambda s, d: X.w10_ablation(s, d, "links", (1, 4), (1, 2))),
    ("w12_physical", lambda s, d: X.w12_physical(s, d, "links", partitions=(4,))),
    ("w13_prepare", lambda s, d: X.w13_prepare(s, d)),
    ("w15_directed", lambda s, d: X.w15_directed(s, d)),
):
    QUERIES[_name] = _f

QUERIES.update(R.QUERIES)
ORACLE_SQL.update(R.SQL)
__all__ = ["ORACLE_SQL", "QUERIES", "snapshot"]
