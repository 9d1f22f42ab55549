"""Benchmark decontamination by templates.

Texts become templates: numbers (also written with marks), units after a number and capitalised words
inside a sentence turn into typed placeholders, all else is lower-cased without outer marks. Windows of `window`
template words are hash-joined with those of the benchmark. Matching windows of a document and an item
that lie equally far apart are one place, a copy of the item or of parts of it. In a place a slot value of
the item must always meet the same value in the document (whichever it is), else the shared template is a
coincidence. A document is contaminated if places that also agree with each other cover at least `share` of
an item's windows.
Where an item has fewer words than a window, its whole template is its only window, one of that many
words. Edge cases: null, empty and wordless texts match nothing; null item ids form one item;
repeated rows are judged alike; an empty table of documents gives no rows, an empty benchmark no leaks.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphmoves.llm.common import Rolling, blocks, doc_key, mix64, packed, real_id, unpacked, utf8, words_of

WINDOW = 8
SHARE = 0.3
UNITS = ("km", "m", "cm", "mm", "kg", "g", "mg", "l", "ml", "s", "sec", "seconds", "min", "minutes", "h", "hours", "days", "weeks", "months", "years", "percent", "dollars", "euros", "miles", "feet", "inches", "pounds", "degrees")
BITS = 22
#: Stands for the item without an id.
NO_ITEM = -(2**62)
_HASH = Rolling(fold_case=True, seed=9)
_NUMBER, _NAME, _UNIT = (np.uint64(x) for x in (0x1111111111111111, 0x2222222222222222, 0x3333333333333333))
_MULTIPLIERS = mix64(np.arange(1, 65, dtype=np.uint64))


def _unit_hashes() -> np.ndarray:
    return np.sort(np.array([_HASH.ranges(_HASH.prefix(b), np.array([0]), np.array([len(b)]))[0] for b in (np.frombuffer(u.encode(), np.uint8) for u in UNITS)]))


def templates(part: np.ndarray, o: np.ndarray):
    """Hash of each template word, its hash without placeholder, slot flags, starts, ends, and the first word of each document."""
    start, end, first = words_of(part, o)
    letter = np.zeros(256, np.int8)
    letter[48:58], letter[65:91], letter[97:123], letter[128:] = 1, 2, 3, 3
    k = letter[part]
    solid = np.concatenate([[0], np.cumsum(k > 0)])
    solid_at = np.flatnonzero(k > 0)
    keep = solid[end] > solid[start]
    first = np.concatenate([[0], np.cumsum(keep)])[first]
    start, end = start[keep], end[keep]
    if not len(start):
        return np.empty(0, np.uint64), np.empty(0, np.uint64), np.empty(0, bool), start, end, first
    stop = np.isin(part[end - 1], [33, 46, 58, 63])  # a sentence ends behind this word
    a, b = solid_at[solid[start]], solid_at[solid[end] - 1] + 1  # without outer marks
    h = mix64(_HASH.ranges(_HASH.prefix(part), a, b))
    digits = np.concatenate([[0], np.cumsum(k == 1)])
    lower = np.concatenate([[0], np.cumsum(k >= 2)])
    number = (digits[b] > digits[a]) & (lower[b] == lower[a])
    opens = np.ones(len(a), bool)
    opens[1:] = stop[:-1]
    opens[first[:-1][first[:-1] < len(a)]] = True
    new_line = np.concatenate([[0], np.cumsum(part == 10)])
    opens[1:] |= new_line[start[1:]] > new_line[end[:-1]]
    small = np.concatenate([[0], np.cumsum(k == 3)])
    name = (k[a] == 2) & ~opens & (small[b] > small[a])
    unit = np.isin(_HASH.ranges(_HASH.prefix(part), a, b), _unit_hashes())
    unit[1:] &= number[:-1]
    unit[first[:-1][first[:-1] < len(a)]] = False
    typed = np.where(number, _NUMBER, np.where(name, _NAME, np.where(unit, _UNIT, h)))
    return typed, np.where(number, _NUMBER, h), number | name | unit, a, b, first


def windows_of(df: DataFrame, id_columns: list[str], window: int, sizes: list[int], marked: np.ndarray | None = None) -> DataFrame:
    """Id columns, g (window hash), pos, n (windows of the text), size (words of the window), opening, slots array<string>.

    sizes: word counts below `window` of which windows are made too. Without `marked` texts are benchmark
    items, of which a window of such a size has to be the whole; else only hashes set in `marked` are made,
    and where the first word is taken as a name or unit for what stands before it, also the window in which
    it is neither, as it is at the head of an item (opening).
    """
    schema = ", ".join(f"{c} long" for c in id_columns) + ", g long, pos int, n int, size int, opening boolean, slots array<string>"

    def run(batches):
        for batch in batches:
            data, off = utf8(batch.column(len(id_columns)))
            for lo, hi in blocks(off):
                part, o = data[off[lo] : off[hi]], off[lo : hi + 1] - off[lo]
                h, plain, slot, a, b, first = templates(part, o)
                got = []
                for size in [window, *sizes]:
                    m = len(h) - size + 1
                    if m <= 0:
                        continue
                    rest = np.full(m, np.uint64(size))
                    for j in range(1, size):
                        rest += h[j : j + m] * _MULTIPLIERS[j]
                    fits = np.searchsorted(first, np.arange(m), side="right") == np.searchsorted(first, np.arange(m) + size - 1, side="right")
                    if marked is None:
                        fits &= (size == window) | (np.diff(first)[np.searchsorted(first, np.arange(m), side="right") - 1] == size)
                    for opening in (False,) if marked is None else (False, True):
                        head = (plain if opening else h)[:m]
                        g = mix64(rest + head * _MULTIPLIERS[0])
                        own = fits & (head != h[:m]) if opening else fits
                        if marked is not None:
                            own = own & marked[(g >> np.uint64(64 - BITS)).astype(np.int64)]
                        got += [(int(p), int(g[p]), size, opening) for p in np.flatnonzero(own)]
                if not got:
                    continue
                p = np.array([x[0] for x in got])
                doc = np.searchsorted(first, p, side="right") - 1
                words = np.diff(first)
                n = np.maximum(1, words - window + 1)[doc]
                slots = [[part[a[i] : b[i]].tobytes().decode("utf-8", "replace").lower() for i in range(q + opening, q + size) if slot[i]] for q, _, size, opening in got]
                ids = [batch.column(c).slice(lo, hi - lo).take(pa.array(doc)) for c in range(len(id_columns))]
                yield pa.RecordBatch.from_arrays([*ids, pa.array(np.array([x[1] for x in got], np.uint64).view(np.int64)), pa.array((p - first[doc]).astype(np.int32)),
                                                  pa.array(n.astype(np.int32)), pa.array([x[2] for x in got], pa.int32()), pa.array([x[3] for x in got], pa.bool_()), pa.array(slots, pa.list_(pa.string()))], names=[*id_columns, "g", "pos", "n", "size", "opening", "slots"])

    return df.mapInArrow(run, schema)


def contaminations(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, share: float = SHARE) -> DataFrame:
    """d, tk, item_id, windows, item_windows, consistent, leaked: each document and item that share a template window.

    What is broadcast has a fixed size: a bitmap of 2 ** 22 bits that thins out document windows before
    the exact hash join.
    """
    items = benchmark.select(F.coalesce(F.col("item_id").cast("long"), F.lit(NO_ITEM)).alias("item"), F.xxhash64("text").alias("it"), "text").dropDuplicates(["item", "it"])
    bench = windows_of(items, ["item", "it"], window, list(range(1, window)))
    bench = bench.persist()
    try:
        prefixes = bench.select(F.shiftrightunsigned("g", 64 - BITS).alias("b")).distinct().collect()  # at most 2 ** 22
        marked = np.zeros(1 << BITS, bool)
        marked[[r.b for r in prefixes]] = True
        short = [r[0] for r in bench.select("size").where(f"size < {window}").distinct().collect()]  # fewer than `window` numbers
    finally:
        bench.unpersist()
    found = windows_of(docs.select(*doc_key(), F.coalesce("text", F.lit("")).alias("text")), ["d", "tk"], window, short, marked)
    theirs = bench.select("item", "it", "g", F.col("pos").alias("ipos"), F.col("n").alias("item_windows"), F.col("slots").alias("islots"))
    hit = F.struct((F.col("pos") - F.col("ipos")).alias("place"), "ipos", F.arrays_zip(F.col("islots").alias("i"), F.col("slots").alias("v")).alias("pairs"))
    per = found.join(theirs, "g").where("ipos = 0 or not opening").groupBy("d", "tk", "item", "it", "item_windows").agg(F.collect_set(hit).alias("hits"))  # of one document and one item
    return per.select("d", "tk", F.when(F.col("item") != NO_ITEM, F.col("item")).alias("item_id"), "item_windows", "hits").mapInArrow(
        _judge(share), "d long, tk long, item_id long, windows long, item_windows int, consistent boolean, leaked boolean")


def _judge(share: float):
    def run(batches):
        for batch in batches:
            n, hits = batch.column(3).to_pylist(), batch.column(4)
            need = [max(1.0, share * x) for x in n]
            got = [agreeing_windows(hits[i].as_py(), need[i]) for i in range(len(n))]
            yield pa.RecordBatch.from_arrays([*batch.columns[:3], pa.array([w for w, _ in got], pa.int64()), batch.column(3), pa.array([c for _, c in got], pa.bool_()),
                                              pa.array([c and w >= x for (w, c), x in zip(got, need, strict=True)], pa.bool_())], names=["d", "tk", "item_id", "windows", "item_windows", "consistent", "leaked"])

    return run


def agreeing_windows(hits: list[dict], need: float) -> tuple[int, bool]:
    """How many of an item's windows places cover that agree in themselves and with each other, and if any place does.

    The search goes on until `need` is reached or no set of places can reach it; without a place that
    agrees, all windows are counted.
    """
    places: dict = {}
    for x in hits:
        windows, pairs = places.setdefault(x["place"], (set(), set()))
        windows.add(x["ipos"])
        pairs.update((p["i"], p["v"]) for p in x["pairs"])
    sound = [(w, dict(p)) for w, p in places.values() if len(dict(p)) == len(p)]
    if not sound:
        return len(set().union(*(w for w, _ in places.values()))), False

    def clashing(rest) -> set:
        seen: dict = {}
        return {i for _, v in rest for i in v if seen.setdefault(i, v[i]) != v[i]}

    merged: dict = {}  # places that differ in no value others contradict
    clash = clashing(sound)
    for w, v in sound:
        merged.setdefault(frozenset((i, x) for i, x in v.items() if i in clash), set()).update(w)
    order = [(w, dict(v)) for v, w in sorted(merged.items(), key=lambda m: (-len(m[1]), sorted(m[0])))]
    best = 0

    def search(covered: set, rest: list) -> None:
        nonlocal best
        clash = clashing(rest)
        covered = covered.union(*(w for w, v in rest if clash.isdisjoint(v)))
        rest = [(w, v) for w, v in rest if not w <= covered]
        if not rest:
            best = max(best, len(covered))
        for k, (w, v) in enumerate(rest):
            if best and (best >= need or len(covered.union(*(x for x, _ in rest[k:]))) < need):
                return
            search(covered | w, [(x, y) for x, y in rest[k + 1 :] if all(v.get(i, c) == c for i, c in y.items())])

    search(set(), order)
    return best, True


def decontaminated(docs: DataFrame, benchmark: DataFrame, **options) -> DataFrame:
    """Documents without those that hold a benchmark item, all columns kept."""
    bad = contaminations(docs, benchmark, **options).where("leaked").select("d", "tk").distinct()
    rows = packed(docs).select("doc", *[c.alias(n) for c, n in zip(doc_key("doc.doc_id", "doc.text"), ("d", "tk"), strict=True)])
    return unpacked(rows.join(bad, ["d", "tk"], "left_anti"), docs.columns)


def leaks(docs: DataFrame, benchmark: DataFrame, **options) -> DataFrame:
    """doc_id, item_id, windows, item_windows, consistent, leaked."""
    return contaminations(docs, benchmark, **options).select(real_id().alias("doc_id"), "item_id", "windows", "item_windows", "consistent", "leaked")
