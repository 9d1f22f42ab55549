"""Near-duplicates by bottom-k sketches from one hash function.

A sketch is the k smallest hashes of a document's distinct word shingles. Documents of equal shingle
sets form one class first. Inverted lists of retained values then give candidates: of each class only
the values rarest in the corpus, and only so many that a linked pair must share one (`probe_size`). The
union-sketch estimate drops most candidates; exact Jaccard on full sets decides.
Lists are never expanded into all pairs: first each member meets its list's leader only; then members of
lists that lie in more than one component get new lists, by the rarest values of their full sets and their
sizes, and in these the members outside the list's largest component meet the others. A pair in one component needs no test, so no link is lost.
Edge cases: null or wordless texts have the empty set, class of their own, linked with nothing; rows
equal in id and text are one document, and rows that share an id are one node; rows without an id are a
document per text, and their component_id is null unless a row with an id joins them; an empty table gives no
rows; very long texts are held whole, one after another, as sets of hashes.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from graphmoves.llm.common import Rolling, blocks, doc_key, mix64, packed, read_table, real_id, snapshot, unpacked, utf8, words_of  # noqa: F401
from graphmoves.llm.components import components

SHINGLE = 5
K = 96
SIGMAS = 5
_HASH = Rolling(fold_case=True, seed=7)
_MULTIPLIERS = mix64(np.arange(1, 65, dtype=np.uint64)) | np.uint64(1)


def shingle_sets(data: np.ndarray, off: np.ndarray, size: int = SHINGLE):
    """Per document, its sorted distinct shingle hashes (signed 64 bits)."""
    for lo, hi in blocks(off):
        part, o = data[off[lo] : off[hi]], off[lo : hi + 1] - off[lo]
        start, end, first = words_of(part, o)
        word = mix64(_HASH.ranges(_HASH.prefix(part), start, end))
        m = max(0, len(word) - size + 1)
        full = np.zeros(m, np.uint64)
        for j in range(size):
            full += word[j : j + m] * _MULTIPLIERS[j]
        full = mix64(full).view(np.int64)
        for i in range(hi - lo):
            a, b = first[i], first[i + 1]
            if b - a >= size:
                yield np.unique(full[a : b - size + 1])
            elif b > a:
                yield mix64(np.array([(word[a:b] * _MULTIPLIERS[: b - a]).sum() + np.uint64(b - a)], np.uint64)).view(np.int64)
            else:
                yield np.empty(0, np.int64)


def _lists(values: list[np.ndarray]) -> pa.Array:
    off = np.concatenate([[0], np.cumsum([len(v) for v in values])]).astype(np.int32)
    return pa.ListArray.from_arrays(pa.array(off), pa.array(np.concatenate(values) if values else np.empty(0, np.int64)))


def sketches(docs: DataFrame, size: int = SHINGLE, k: int = K) -> DataFrame:
    """d, tk, n (distinct shingles), s1, s2 (128-bit key of the set; null if empty), sketch array<long>."""
    def run(batches):
        for b in batches:
            data, off = utf8(b.column(2))
            for lo in range(0, b.num_rows, 2048):
                hi = min(lo + 2048, b.num_rows)
                sets = list(shingle_sets(data[off[lo] : off[hi]], off[lo : hi + 1] - off[lo], size))
                keys = np.array([np.frombuffer(xxhash.xxh3_128_digest(s.tobytes()), np.int64) for s in sets]).reshape(-1, 2)
                none = np.array([len(s) == 0 for s in sets])
                yield pa.RecordBatch.from_arrays(
                    [b.column(0).slice(lo, hi - lo), b.column(1).slice(lo, hi - lo), pa.array([len(s) for s in sets], pa.int64()),
                     pa.array(keys[:, 0], mask=none), pa.array(keys[:, 1], mask=none), _lists([s[:k] for s in sets])],
                    names=["d", "tk", "n", "s1", "s2", "sketch"])

    return docs.select(*doc_key(), F.coalesce("text", F.lit("")).alias("text")).mapInArrow(run, "d long, tk long, n long, s1 long, s2 long, sketch array<long>")


def full_sets(docs: DataFrame, size: int = SHINGLE) -> DataFrame:
    """id, text -> id, shingles array<long>."""
    def run(batches):
        for b in batches:
            data, off = utf8(b.column(1))
            for lo in range(0, b.num_rows, 512):
                hi = min(lo + 512, b.num_rows)
                yield pa.RecordBatch.from_arrays([b.column(0).slice(lo, hi - lo), _lists(list(shingle_sets(data[off[lo] : off[hi]], off[lo : hi + 1] - off[lo], size)))], names=["id", "shingles"])

    return docs.select("id", "text").mapInArrow(run, "id long, shingles array<long>")


def probe_size(n: Column, percent: int, k: int) -> Column:
    """How many of the rarest retained values to look up so that linked pairs share one.

    Sketches that hold whole sets: exactly n - ceil(t n) + 1. Else a sketch of k values, drawn from a
    union of at most n / t, is expected to miss at most (1 - t) k of them in the other; SIGMAS standard
    deviations of that draw without replacement are looked up besides.
    """
    t = percent / 100
    union = F.greatest(n / t, F.lit(k + 1.0))
    sampled = F.ceil((1 - t) * k + SIGMAS * F.sqrt(k * t * (1 - t) * (union - k) / (union - 1))) + 1
    exact = n - F.ceil(n * percent / 100) + 1
    return F.when(n < math.floor(t * k), exact).otherwise(sampled).cast("int")


def near_duplicate_classes(docs: DataFrame, percent: int = 85, size: int = SHINGLE, k: int = K, exact: bool = False) -> DataFrame:
    """d, tk, n, c: every document with its set size and the least d of its component (its own d if the set is empty).

    exact: the rarest values of all full sets give candidates and no sketch rules any out, so no link can be lost, for
    several times the rows. Else only members of open lists are treated so, and a sample decides about the others.
    """
    own = snapshot(sketches(docs, size, k))  # documents that share an id are one node
    classes = own.where("s1 is not null").groupBy("s1", "s2").agg(F.min("d").alias("id"), F.min_by("tk", "d").alias("tk"), F.first("n").alias("n"), F.first("sketch").alias("sketch"))
    classes = snapshot(classes)
    probes = _probes(classes.select("id", F.col("tk").alias("tag"), "n", F.col("sketch").alias("vals")), probe_size(F.col("n"), percent, k))
    wanted = classes.select("id", "tk") if exact else classes.select("id", "tk").join(probes.select("id").distinct(), "id")
    known = snapshot(full_sets(_texts(docs, wanted), size))
    info = classes.select("id", "n", "sketch")

    # small tables of their own, so that the joins' hot partitions can be split
    leaders = snapshot(probes.groupBy("v").agg(F.min("id").alias("a")))
    stars = probes.join(leaders, "v").where("a < id").select("a", F.col("id").alias("b")).distinct()
    links = snapshot(_verified(stars, info, known, percent, k, exact))
    comp = components(links)

    # members of lists not yet in one component: now the rarest values of full sets decide, without a sample's slack
    open_ids = classes.select("id") if exact else _mixed(probes, comp).select("id").distinct()
    full = snapshot(known.join(open_ids, "id").select("id", F.xxhash64("shingles").alias("tag"), F.size("shingles").alias("n"), F.col("shingles").alias("vals")))
    lists = _mixed(_banded_probes(full, percent), comp)
    x = lists.where("c <> most").select("v", *[F.col(a).alias(a + "x") for a in ("id", "c", "band")])
    y = lists.select("v", "most", "same", *[F.col(a).alias(a + "y") for a in ("id", "c", "band")])
    meet = x.join(y, "v").where("cx <> cy and (cy = most or idx < idy) and (same or bandx <> bandy)")
    meet = meet.select(F.col("idx").alias("x"), F.col("idy").alias("y"))
    rest = meet.select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).distinct()
    more = _verified(rest, info, known, percent, k, exact)
    every = components(links.select("a", "b").union(more.select("a", "b")))

    to_class = classes.select("s1", "s2", "id").join(every.select("id", "c"), "id", "left").select("s1", "s2", F.coalesce("c", "id").alias("c"))
    out = own.select("d", "tk", "n", "s1", "s2").join(to_class, ["s1", "s2"], "left")
    return out.select("d", "tk", "n", F.coalesce("c", "d").alias("c"))


def _ranked(sets: DataFrame) -> DataFrame:
    """sets (id, tag, n, vals) -> id, n, lone (values that one set alone has), vs (the others, rarest first)."""
    postings = sets.select("id", "tag", F.explode("vals").alias("v"))
    common = snapshot(postings.groupBy("v").agg(F.count("*").alias("df")).where("df > 1"))
    held = postings.join(common, "v").groupBy("id", "tag").agg(F.sort_array(F.collect_list(F.struct("df", "v"))).alias("vs"))
    held = held.join(sets.select("id", "tag", "n", F.size("vals").alias("kept")), ["id", "tag"])
    return held.select("id", "n", (F.col("kept") - F.size("vs")).alias("lone"), F.transform("vs", lambda x: x["v"]).alias("vs"))


def _probes(sets: DataFrame, room: Column) -> DataFrame:
    """v, id: postings of each set's rarest values, as many as `room` of n tells."""
    left = room - F.col("lone")
    return snapshot(_ranked(sets).where(left > 0).select(F.explode(F.slice("vs", F.lit(1), left)).alias("v"), "id").distinct())


def _banded_probes(sets: DataFrame, percent: int) -> DataFrame:
    """v, id, band, same: exact postings, apart for each pair of size bands.

    Sets of sizes a and b are linked only if they share p (a + b) / (100 + p) values; so of each set
    all but that many, and one more, of its rarest values suffice, given the least size in the other's
    band. Near sizes leave half of what is needed when the other's size is open. v is keyed by the bands.
    """
    step = math.log(1.03)
    band = lambda n: F.floor(F.log(n.cast("double")) / step + 1e-9).cast("int")
    least = lambda b: F.greatest(F.lit(1), F.ceil(F.exp(b * step) - 1e-6))
    n = F.col("n")
    own = _ranked(sets).select("*", band(n).alias("band"), F.explode(F.sequence(band(F.greatest(F.lit(1), F.floor(n * percent / 100))), band(F.ceil(n * 100 / percent)))).alias("other"))
    need = F.ceil((n + least(F.col("other"))) * percent / (100 + percent) - 1e-9)
    left = (n - need + 1 - F.col("lone")).cast("int")
    own = own.where(left > 0).select("id", "band", "other", F.explode(F.slice("vs", F.lit(1), left)).alias("v"))
    key = F.xxhash64("v", F.least("band", "other"), F.greatest("band", "other"))
    return snapshot(own.select(key.alias("v"), "id", "band", (F.col("band") == F.col("other")).alias("same")).distinct())


def _mixed(probes: DataFrame, comp: DataFrame) -> DataFrame:
    """The probes with c and most: members of lists that lie in more than one component, with the list's largest component."""
    placed = snapshot(probes.join(comp.select("id", "c"), "id", "left").select(*probes.columns, F.coalesce("c", "id").alias("c")))
    parts = placed.groupBy("v", "c").agg(F.count("*").alias("m"))
    most = parts.groupBy("v").agg(F.max(F.struct("m", "c")).getField("c").alias("most"), F.count("*").alias("cs")).where("cs > 1").select("v", "most")
    return snapshot(placed.join(snapshot(most), "v"))


def _texts(docs: DataFrame, wanted: DataFrame) -> DataFrame:
    """id and text of the documents that represent the wanted classes."""
    have = docs.select(*doc_key(), "text")
    return have.join(wanted.select(F.col("id").alias("d"), "tk"), ["d", "tk"], "left_semi").dropDuplicates(["d", "tk"]).select(F.col("d").alias("id"), "text")


def _verified(pairs: DataFrame, info: DataFrame, known: DataFrame, percent: int, k: int, exact: bool = False) -> DataFrame:
    """Pairs whose exact Jaccard reaches the percentage; unless `exact`, the union sketch rules most others out before sets are joined."""
    side = lambda x, c, s: x.select(F.col("id").alias(s), *[F.col(y).alias(y + s) for y in c])
    own = pairs.join(side(info, ["n", "sketch"], "a"), "a").join(side(info, ["n", "sketch"], "b"), "b")
    union = F.slice(F.array_sort(F.array_union("sketcha", "sketchb")), 1, k)
    both = F.size(F.array_intersect(F.array_intersect(union, "sketcha"), "sketchb"))
    t = percent / 100
    low = F.when((F.col("na") <= k) & (F.col("nb") <= k) & (F.size(union) < k), F.lit(t - 1e-9)).otherwise(F.lit(t - 6 * math.sqrt(t * (1 - t) / k)))
    near = own.where(100 * F.least("na", "nb") >= percent * F.greatest("na", "nb")).where(F.lit(True) if exact else both >= low * F.size(union)).select("a", "b").distinct()
    full = near.join(side(known, ["shingles"], "a"), "a").join(side(known, ["shingles"], "b"), "b")
    shared = F.size(F.array_intersect("shinglesa", "shinglesb"))
    sized = full.select("a", "b", shared.alias("i"), (F.size("shinglesa") + F.size("shinglesb")).alias("both"))
    return sized.where(F.col("i") * 100 >= percent * (F.col("both") - F.col("i"))).select("a", "b")


def near_duplicates(docs: DataFrame, **options) -> DataFrame:
    """doc_id, n_shingles, component_id, kept."""
    own = near_duplicate_classes(docs, **options)
    return own.select(real_id().alias("doc_id"), F.col("n").alias("n_shingles"), real_id("c").alias("component_id"), F.expr("d = c").alias("kept"))


def one_of_each(docs: DataFrame, percent: int = 80, **options) -> DataFrame:
    """Documents without those that another of smaller id stands for; repeated rows leave one; all columns kept."""
    keep = near_duplicate_classes(docs, percent=percent, **options).where("d = c").groupBy("d", "tk").agg(F.first("n").alias("_n"))
    rows = packed(docs).select("doc", *[c.alias(x) for c, x in zip(doc_key("doc.doc_id", "doc.text"), ("d", "tk"), strict=True)])
    return unpacked(rows.join(keep.select("d", "tk"), ["d", "tk"], "left_semi").dropDuplicates(["d", "tk"]), docs.columns)
