"""Graphs on the given tables, as undirected pairs (a, b, w). Keys of two kinds get even and odd ids."""

from __future__ import annotations

import math
from functools import reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from graphmoves.functions.columns import portable, power_law
from graphmoves.session import snapshot, table
from graphmoves.sources.build import dense_ids


def trade(spark: SparkSession, d: str) -> DataFrame:
    o = table(spark, d, "orders").select(F.col("o_orderkey").alias("k"), "o_custkey")
    li = table(spark, d, "lineitem").select(F.col("l_orderkey").alias("k"), "l_suppkey")
    return li.join(o, "k").groupBy((2 * F.col("o_custkey")).alias("a"), (2 * F.col("l_suppkey") + 1).alias("b")).agg(F.count("*").alias("w"))


def basket(spark: SparkSession, d: str) -> DataFrame:
    o = table(spark, d, "orders").select(F.col("o_orderkey").alias("k"), "o_custkey")
    li = table(spark, d, "lineitem").select(F.col("l_orderkey").alias("k"), "l_partkey")
    return li.join(o, "k").groupBy((2 * F.col("o_custkey")).alias("a"), (2 * F.col("l_partkey") + 1).alias("b")).agg(F.count("*").alias("w"))


def _same_order(spark: SparkSession, d: str, key: str) -> DataFrame:
    """An order has few lines, so a list of them is bounded; pairs come from it without a self-join."""
    lines = table(spark, d, "lineitem").groupBy("l_orderkey").agg(F.sort_array(F.collect_list(key)).alias("ks"))
    pairs = lines.select(F.explode("ks").alias("a"), "ks").select("a", F.explode("ks").alias("b")).where("a < b")
    return pairs.groupBy("a", "b").agg(F.count("*").alias("w"))


def copurchase(spark: SparkSession, d: str) -> DataFrame:
    return _same_order(spark, d, "l_partkey")


def cosupply(spark: SparkSession, d: str) -> DataFrame:
    return _same_order(spark, d, "l_suppkey")


def geo(spark: SparkSession, d: str) -> DataFrame:
    """Forest region - nation - customers and suppliers; ids times 4 plus the kind."""
    one = F.lit(1).cast("long").alias("w")
    link = lambda t, a, i, b, j: table(spark, d, t).select((F.col(a).cast("long") * 4 + i).alias("a"), (F.col(b).cast("long") * 4 + j).alias("b"), one)
    return link("customer", "c_custkey", 0, "c_nationkey", 2).union(link("supplier", "s_suppkey", 1, "s_nationkey", 2)).union(link("nation", "n_nationkey", 2, "n_regionkey", 3))


def planted(spark: SparkSession, d: str, mu: float = 0.4, seed: int = 7, degree: int = 20) -> DataFrame:
    """Customers with hashed partners inside their nation and anywhere; c_nationkey is the truth. Linear in the customers.

    Customers are numbered by nation and key, so a nation is a range of numbers and a partner in it a number drawn.
    """
    c = table(spark, d, "customer").select(F.struct(F.col("c_nationkey").cast("long").alias("k"), F.col("c_custkey").alias("x")).alias("kx"))
    at = snapshot(dense_ids(c, "kx").select("kx.x", "kx.k", F.col("dense").alias("pos")))
    spans = at.groupBy("k").agg(F.min("pos").alias("lo"), F.count("*").alias("s"))  # a row for each nation
    inner, outer = round(degree / 2 * (1 - mu)), round(degree / 2 * mu)
    many = lambda n: F.explode(F.sequence(F.lit(1), F.lit(max(1, n)))).alias("j")
    drawn = at.join(F.broadcast(spans), "k").select("x", "lo", "s", many(inner)).where(f"{inner} > 0")
    drawn = drawn.select("x", (F.col("lo") + portable(F.lit("in"), F.col("x"), F.col("j"), seed) % F.col("s")).alias("pos"))
    inside = drawn.join(at.select("pos", F.col("x").alias("y")), "pos").select("x", "y")
    n = c.agg(F.count("*").alias("n"))
    out = at.crossJoin(F.broadcast(n)).select("x", "n", many(outer)).where(f"{outer} > 0")
    across = out.select("x", (portable(F.lit("out"), F.col("x"), F.col("j"), seed) % F.col("n")).alias("y"))
    pairs = inside.union(across).where("x <> y").select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b"))
    return pairs.distinct().select("a", "b", F.lit(1).cast("long").alias("w"))


def planted_truth(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "customer").select(F.col("c_custkey").alias("id"), F.col("c_nationkey").cast("long").alias("c"))


def usage(spark: SparkSession, d: str) -> DataFrame:
    e = table(spark, d, "events").select("user_id", F.get_json_object("props", "$.k").cast("long").alias("k")).where("k is not null")
    return e.groupBy((2 * F.col("user_id")).alias("a"), (2 * F.col("k") + 1).alias("b")).agg(F.count("*").alias("w"))


#: Pairs of users in an hour that one task counts, about.
COACTIVE_PAIRS = 1 << 22


def coactive(spark: SparkSession, d: str) -> DataFrame:
    """Users active in the same hour in the same way; w counts hours and ways. Its edges are all pairs of an hour, by definition.

    Users are dealt into blocks. A task has two blocks and counts all their pairs, so users are copied to it, once for
    each other block, and no pair is ever shuffled.
    """
    e = snapshot(table(spark, d, "events").select("user_id", F.date_trunc("hour", "ts").alias("h"), "event_type").where("user_id is not null and h is not null and event_type is not null").distinct())
    pairs = e.groupBy("h", "event_type").count().agg(F.sum(F.col("count") * F.col("count") / 2)).first()[0] or 0
    n = max(1, math.ceil(math.sqrt(2 * pairs / COACTIVE_PAIRS)))
    lists = e.groupBy("h", "event_type", F.pmod(F.xxhash64("user_id"), F.lit(n)).alias("p")).agg(F.sort_array(F.collect_list("user_id")).alias("us"))
    both = lists.select("h", "event_type", "p", "us", F.explode(F.sequence(F.lit(0), F.lit(n - 1))).alias("q"))
    i, j = F.least("p", "q"), F.greatest("p", "q")
    both = both.select((j * (j + 1) / 2 + i).cast("int").alias("task"), "h", "event_type", (F.col("p") <= F.col("q")).alias("first"), (F.col("p") == F.col("q")).alias("alone"), "us")
    dealt = both.repartitionById(n * (n + 1) // 2, "task").groupBy("task", "h", "event_type")
    met = dealt.agg(F.max(F.when(F.col("first"), F.col("us"))).alias("xs"), F.max(F.when(~F.col("first") | F.col("alone"), F.col("us"))).alias("ys"), F.max("alone").alias("alone"))
    met = met.select("task", "alone", "ys", F.explode("xs").alias("x")).select("task", "alone", "x", F.explode("ys").alias("y")).where("not alone or x < y")
    return met.groupBy("task", F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).agg(F.count("*").alias("w")).select("a", "b", "w")


def links(spark: SparkSession, d: str) -> DataFrame:
    """Pages and the distinct link targets in them; a target's id is its rank among targets."""
    href = table(spark, d, "pages").select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1)).alias("t")).distinct()
    return href.select((2 * F.col("page_id")).alias("a"), (2 * portable(F.col("t")) + 1).alias("b"), F.lit(1).cast("long").alias("w")).distinct()


def neardup(spark: SparkSession, d: str, least: int = 5, df_limit: int | None = None) -> DataFrame:
    """Documents that share at least `least` five-word shingles; with `df_limit` only of those in at most that many documents.

    Documents of equal shingles form a class; classes are compared, and their links dealt to their members.
    """
    words = F.filter(F.split("text", r"\s+"), lambda w: w != "")
    w = table(spark, d, "documents").select("doc_id", words.alias("ws"))
    sh = w.where("size(ws) >= 5").select("doc_id", F.explode(F.array_distinct(F.transform(F.sequence(F.lit(1), F.size("ws") - 4), lambda i: F.xxhash64(F.array_join(F.slice("ws", i, 5), " "))))).alias("g"))
    if df_limit:
        sh = sh.join(sh.groupBy("g").agg(F.count("*").alias("n")).where(f"n <= {df_limit}").select("g"), "g")
    sets = sh.groupBy("doc_id").agg(F.sort_array(F.collect_list("g")).alias("gs"))
    classes = snapshot(sets.groupBy("gs").agg(F.min("doc_id").alias("k")))
    member = snapshot(sets.join(classes, "gs").select("doc_id", "k", F.size("gs").cast("long").alias("w")))
    own = classes.select("k", F.explode("gs").alias("g"))
    across = own.join(own.withColumnRenamed("k", "l"), "g").where("k < l").groupBy("k", "l").agg(F.count("*").alias("w")).where(f"w >= {least}")
    x, y = member.select("k", F.col("doc_id").alias("x")), member.select(F.col("k").alias("l"), F.col("doc_id").alias("y"))
    within = member.where(f"w >= {least}").select("k", "w", F.col("doc_id").alias("x")).join(x.withColumnRenamed("x", "y"), "k").where("x < y")
    links = across.join(x, "k").join(y, "l").select("x", "y", "w").union(within.select("x", "y", "w"))
    return links.select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b"), "w")


def knn(spark: SparkSession, d: str, k: int = 5, block: int = 512) -> DataFrame:
    """Union of k nearest by cosine; vectors in blocks of a fixed count, multiplied block by block. Exact, hence every block meets every other: a generator for tests, quadratic in the vectors."""
    import numpy as np
    import pandas as pd

    v = table(spark, d, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("embedding"))
    ids = v.select(F.pmod(F.xxhash64("vec_id"), F.lit(max(1, math.ceil(v.count() / block)))).alias("p"), "vec_id", "embedding")
    parts = [r.p for r in ids.select("p").distinct().collect()]
    other = lambda name: F.explode(F.array(*[F.lit(p).cast("long") for p in parts])).alias(name)
    left, right = ids.select("p", other("q"), "vec_id", "embedding"), ids.select(other("p"), F.col("p").alias("q"), F.col("vec_id").alias("vec_id"), F.col("embedding").alias("embedding"))

    def best(key, x: pd.DataFrame, y: pd.DataFrame) -> pd.DataFrame:
        if not len(x) or not len(y):
            return pd.DataFrame({"a": [], "b": [], "s": []})
        m, n = np.stack(x.embedding), np.stack(y.embedding)
        s = (m / np.linalg.norm(m, axis=1, keepdims=True)) @ (n / np.linalg.norm(n, axis=1, keepdims=True)).T
        s[x.vec_id.values[:, None] == y.vec_id.values] = -2
        top = np.argsort(-s, axis=1)[:, :k]
        return pd.DataFrame({"a": np.repeat(x.vec_id.values, top.shape[1]), "b": y.vec_id.values[top.reshape(-1)], "s": np.take_along_axis(s, top, 1).reshape(-1).round(9)})

    found = left.groupBy("p", "q").cogroup(right.groupBy("p", "q")).applyInPandas(best, "a long, b long, s double")
    near = found.withColumn("r", F.row_number().over(Window.partitionBy("a").orderBy(F.desc("s"), "b"))).where(f"r <= {k}")
    return near.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"), F.lit(1).cast("long").alias("w")).distinct()


def bench_hits(spark: SparkSession, d: str) -> DataFrame:
    """Documents and benchmark items by the number of five-word shingles they share."""
    def sh(name, i):
        ws = F.filter(F.split(F.lower("text"), r"\s+"), lambda w: w != "")
        t = table(spark, d, name).select(F.col(i), ws.alias("ws")).where("size(ws) >= 5")
        return t.select(i, F.explode(F.array_distinct(F.transform(F.sequence(F.lit(1), F.size("ws") - 4), lambda j: F.xxhash64(F.array_join(F.slice("ws", j, 5), " "))))).alias("g"))

    return sh("documents", "doc_id").join(sh("benchmark", "item_id"), "g").groupBy((2 * F.col("doc_id")).alias("a"), (2 * F.col("item_id") + 1).alias("b")).agg(F.count("*").alias("w"))


def talk(spark: SparkSession, d: str) -> DataFrame:
    """Conversations and the first words of their turns."""
    t = table(spark, d, "conversations").select("conv_id", F.lower(F.substring_index("text", " ", 2)).alias("t")).distinct()
    return t.select((2 * F.col("conv_id")).alias("a"), (2 * portable(F.col("t")) + 1).alias("b"), F.lit(1).cast("long").alias("w")).distinct()


GRAPHS = {f.__name__: f for f in (trade, copurchase, cosupply, basket, geo, planted, usage, coactive, links, neardup, knn, bench_hits, talk)}


def lfr(spark: SparkSession, n: int, mu: float = 0.4, degree=(50, 10000, 2.0), community=(50, 12000, 1.0), seed: int = 0) -> tuple[DataFrame, DataFrame]:
    """Power-law degrees and community sizes with mixing mu: pairs (a, b, w) and truth (id, c).

    Communities are drawn until their sizes cover n; stubs of a node are dealt inside its community and
    across, each paired by hashed order. Loops, and pairs of one community among those across, are dealt anew;
    what is left of them after three turns goes, as do doubled pairs.
    """
    u = lambda *x: (F.pmod(F.xxhash64(*x, F.lit(seed)), F.lit(1 << 52)) / float(1 << 52))
    mean = (community[1] - community[0]) / math.log(community[1] / community[0]) if community[2] == 1 else (community[0] + community[1]) / 2
    count = math.ceil(n / mean * 1.5) + 8
    sizes = spark.range(count).select(F.col("id").alias("c"), power_law(u("id", F.lit("size")), *community).cast("long").alias("s"))
    part = Window.partitionBy(F.lit(0)).orderBy("c")  # one row per community, n / mean size of them
    spans = sizes.select("c", (F.sum("s").over(part) - F.col("s")).alias("lo"), F.sum("s").over(part).alias("hi")).where(f"lo < {n}")
    spans = spans.select("c", F.explode(F.sequence(F.col("lo"), F.least("hi", F.lit(n)) - 1)).alias("id"))
    nodes = spans.select("id", "c", power_law(u("id", F.lit("deg")), *degree).cast("long").alias("k"))
    nodes = snapshot(nodes)
    stubs = nodes.select("id", "c", F.explode(F.sequence(F.lit(1), F.col("k"))).alias("j")).select("id", "c", "j", (u("id", "j", F.lit("mix")) < mu).alias("out"))

    def dealt(own: DataFrame, apart: bool) -> DataFrame:
        """Pairs of stubs by hashed order, of one community or (apart) of two; those that don't fit are dealt anew, three times in all."""
        done, rest = [], own.select("id", "c", "j")
        for t in range(3):
            h = F.xxhash64("id", "j", F.lit(seed), F.lit(t))
            # across communities, hashed buckets of near equal size stand for one global order
            group = F.pmod(F.xxhash64("id", "j", F.lit(seed), F.lit(t + 100)), F.lit(max(1, n // 2000))) if apart else F.col("c")
            r = rest.select("id", "c", "j", group.alias("group"), h.alias("h")).withColumn("r", F.row_number().over(Window.partitionBy("group").orderBy("h")) - 1)
            two = r.groupBy("group", F.floor(F.col("r") / 2).alias("pair")).agg(F.min(F.struct("id", "c", "j")).alias("x"), F.max(F.struct("id", "c", "j")).alias("y"))
            two = snapshot(two.withColumn("fits", F.expr("x.id <> y.id" + " and x.c <> y.c" * apart)))
            done.append(two.where("fits").select(F.col("x.id").alias("a"), F.col("y.id").alias("b")))
            rest = two.where("not fits").select(F.explode(F.array_distinct(F.array("x", "y"))).alias("s")).select("s.*")
        return reduce(DataFrame.union, done)

    pairs = dealt(stubs.where("not out"), False).union(dealt(stubs.where("out"), True)).distinct()
    return pairs.select("a", "b", F.lit(1).cast("long").alias("w")), nodes.select("id", "c")
