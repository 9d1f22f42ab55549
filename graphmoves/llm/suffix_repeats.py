"""Repeated passages by a common-prefix interval tree over an enhanced suffix array.

Which byte strings of `min_bytes` occur more than once, anywhere? Each window of that length is
represented by its anchor, the position of the least of its k-gram hashes (k = min_bytes // 3), so equal
windows have equal anchors at equal distance. Windows of one anchor form a segment of text. Anchors
whose k-gram occurs once are dropped; segments of equal content are counted, not kept apart. What is
left, distinct segments that share an anchor k-gram, is sorted by the text from the anchor on into a
sparse suffix array; a stack scan over its common-prefix lengths builds the interval tree, and within
each interval the texts to the left of the anchors are compared in their own order: members with diverse
left extensions end there, and prefix plus left part of at least `min_bytes` is a repeat of all members
that share it, not just of neighbours.

A k-gram shared by more than `most` distinct segments is refined before sorting: its windows are dealt
by longer and longer common cores until each bucket is small or its core is the whole window, which is
then a repeat by itself. So no task sorts an unbounded group, and no occurrence is left out.

Edge cases: null text is empty; matches stay inside documents; rows equal in id and text are two
occurrences of all they hold; overlapping occurrences count; an empty table gives no rows; very long texts
yield as many segments as they have anchors, none longer than two windows.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from graphmoves.llm.common import Rolling, blocks, doc_key, drop_snapshot, mix64, packed, real_id, snapshot, utf8, words_of

MIN_BYTES = 400
#: Passages of more than 50 whole words are reported, not removed, where they take fewer bytes.
WORDS = 51
#: Distinct segments of one bucket that one task sorts together: at most 1 KB each, 1 MB. Larger buckets are refined.
MOST = 1024
_HASH = Rolling(seed=1)


def _sliding_min(x: np.ndarray, w: int) -> np.ndarray:
    """Minimum of each w consecutive values, by running minima over blocks from both sides."""
    n = len(x)
    pad = np.concatenate([x, np.full(-n % w, np.iinfo(np.uint64).max, np.uint64)]).reshape(-1, w)
    left = np.minimum.accumulate(pad, 1).reshape(-1)
    right = np.minimum.accumulate(pad[:, ::-1], 1)[:, ::-1].reshape(-1)
    return np.minimum(right[: n - w + 1], left[w - 1 : n])


def anchors_of(part: np.ndarray, o: np.ndarray, length: int, k: int):
    """Per segment: k-gram hash, document number, anchor p, first and last window start a, b (positions in `part`)."""
    w = length - k + 1
    if len(part) < length:
        return (np.empty(0, np.uint64), *(np.empty(0, np.int64),) * 4)
    gram = mix64(_HASH.grams(_HASH.prefix(part), k))
    least = _sliding_min((gram & np.uint64(0xFFFFFFFF00000000)) | np.arange(len(gram), dtype=np.uint64), w)
    at = (least & np.uint64(0xFFFFFFFF)).astype(np.int64)
    starts = np.arange(len(at))
    doc = np.searchsorted(o, starts, side="right") - 1
    inside = starts + length <= o[doc + 1]
    starts, at, doc = starts[inside], at[inside], doc[inside]
    if not len(starts):
        return (np.empty(0, np.uint64), *(np.empty(0, np.int64),) * 4)
    first = np.flatnonzero(np.concatenate([[True], (at[1:] != at[:-1]) | (doc[1:] != doc[:-1])]))
    last = np.concatenate([first[1:] - 1, [len(starts) - 1]])
    return gram[at[first]], doc[first], at[first], starts[first], starts[last]


def segments(docs: DataFrame, length: int) -> DataFrame:
    """h, sh (key of the segment's content), d, tk, p, a, b: each document's anchors; positions from the document's start."""
    k = length // 3

    def run(batches):
        for batch in batches:
            data, off = utf8(batch.column(2))
            for lo, hi in blocks(off):
                part, o = data[off[lo] : off[hi]], off[lo : hi + 1] - off[lo]
                h, doc, p, a, b = anchors_of(part, o, length, k)
                view = memoryview(np.ascontiguousarray(part))
                sh = [xxhash.xxh3_64_intdigest(view[x : y + length], z - x) for x, y, z in zip(a.tolist(), b.tolist(), p.tolist(), strict=True)]
                base, row = o[doc], pa.array(doc + lo)
                yield pa.RecordBatch.from_arrays(
                    [pa.array(h.view(np.int64)), pa.array(np.array(sh, np.uint64).view(np.int64)), batch.column(0).take(row), batch.column(1).take(row),
                     *(pa.array((x - base).astype(np.int32)) for x in (p, a, b))], names=["h", "sh", "d", "tk", "p", "a", "b"])

    return docs.select(*doc_key(), F.coalesce("text", F.lit("")).alias("text")).mapInArrow(run, "h long, sh long, d long, tk long, p int, a int, b int")


def _common(rows: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """Common prefix length of each row with the next."""
    differ = rows[1:] != rows[:-1]
    n = np.where(differ.any(1), differ.argmax(1), rows.shape[1])
    return np.minimum(n, np.minimum(sizes[1:], sizes[:-1]))


def _matrix(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    sizes = np.array([len(t) for t in texts])
    width = max(1, int(sizes.max()))
    return np.frombuffer(b"".join(t.ljust(width, b"\0") for t in texts), np.uint8).reshape(len(texts), width), sizes


def interval_tree(lcp: np.ndarray):
    """Yield (value, first, last) of every common-prefix interval, inner ones first, by one scan with a stack."""
    stack = [(0, 0)]
    for i, v in enumerate([*lcp.tolist(), 0], 1):
        left = i - 1
        while stack[-1][0] > v:
            value, left = stack.pop()
            yield value, left, i - 1
        if stack[-1][0] < v:
            stack.append((v, left))


def maximal_repeats(texts: list[bytes], anchors: list[int], length: int):
    """Repeats of at least `length` bytes around the anchors: yields (members, left, right).

    Every member's bytes [anchor - left, anchor + right) are the same, for no member can the string be
    longer on the right and still be shared by all of the interval; `members` are all occurrences.
    """
    rights, lefts = [t[p:] for t, p in zip(texts, anchors, strict=True)], [t[:p][::-1] for t, p in zip(texts, anchors, strict=True)]
    order = np.array(sorted(range(len(texts)), key=rights.__getitem__))
    m, sizes = _matrix([rights[i] for i in order])
    lcp = _common(m, sizes)
    left_m, left_sizes = _matrix(lefts)
    rank = np.empty(len(texts), np.int64)
    rank[sorted(range(len(texts)), key=lefts.__getitem__)] = np.arange(len(texts))
    reach = int(left_sizes.max())
    for value, first, last in interval_tree(lcp):
        need = length - value
        if need > reach:
            continue
        members = order[first : last + 1]
        members = members[np.argsort(rank[members])]
        own = left_m[members]
        shared = _common(own, left_sizes[members])
        if need <= 0 and len(members) > 1 and shared.min() == left_sizes[members].max():
            yield members, int(shared.min()), value  # no diversity on the left
            continue
        for low, f, l in interval_tree(shared):
            if low >= need:
                yield members[f : l + 1], low, value
        if need <= 0:
            yield members, 0, value


def _marks(texts: list[bytes], anchors: list[int], length: int) -> tuple[np.ndarray, np.ndarray]:
    """First and end of the repeated bytes of each text; -1, -1 where there are none."""
    left, right = np.full(len(texts), -1), np.zeros(len(texts), np.int64)
    for members, lo, hi in maximal_repeats(texts, anchors, length):
        left[members] = np.maximum(left[members], lo)
        right[members] = np.maximum(right[members], hi)
    p = np.array(anchors)
    return np.where(left >= 0, p - left, -1), np.where(left >= 0, p + right, -1)


def _tree_marks(pieces: DataFrame, length: int, at_once: int = 2048) -> DataFrame:
    """Sort and scan bucket after bucket; pieces (g, h, sh, cut, anchor, body) -> (h, sh, lo, hi) from the segment's start.

    Buckets of one task are taken together up to `at_once` suffixes: their k-grams keep them apart in the array.
    """
    def run(batches):
        held, last = [], None

        def done():
            texts = [r[4] for r in held]
            lo, hi = _marks(texts, [r[3] for r in held], length)
            own = np.flatnonzero(lo >= 0)
            cut = np.array([r[2] for r in held], np.int64)
            return pa.RecordBatch.from_arrays([pa.array([held[i][0] for i in own], pa.int64()), pa.array([held[i][1] for i in own], pa.int64()),
                                               pa.array((lo[own] + cut[own]).astype(np.int32)), pa.array((hi[own] + cut[own]).astype(np.int32))], names=["h", "sh", "lo", "hi"])

        for b in batches:
            for g, *row in zip(*(b.column(i).to_pylist() for i in range(6)), strict=True):
                if g != last and len(held) >= at_once:
                    yield done()
                    held = []
                last = g
                held.append(row)
        if held:
            yield done()

    return pieces.repartition("g").sortWithinPartitions("g").select("g", "h", "sh", "cut", "anchor", "body").mapInArrow(run, "h long, sh long, lo int, hi int")


def _refined(pieces: DataFrame, length: int, width: int, ways: int = 8) -> tuple[DataFrame, int]:
    """Deal each piece's windows by their distance from the anchor, `ways` ranges each; g becomes the hash of a range's common core."""
    step = -(-width // ways)

    def run(batches):
        for b in batches:
            rows = []
            for h, sh, cut, anchor, body in zip(*(b.column(i).to_pylist() for i in range(5)), strict=True):
                b_last = len(body) - length
                for low in range(0, width, step):
                    high = min(low + step, width) - 1  # windows that start `low`..`high` before the anchor
                    a, z = max(0, anchor - high), min(b_last, anchor - low)
                    if a > z:
                        continue
                    core = body[anchor - low : anchor - high + length]
                    rows.append((xxhash.xxh3_64_intdigest(core, low) - 2**63, h, sh, cut + a, anchor - low - a, body[a : z + length]))
            yield pa.RecordBatch.from_pydict(dict(zip(["g", "h", "sh", "cut", "anchor", "body"], (list(c) for c in zip(*rows)) if rows else [[]] * 6, strict=True)),
                                             schema=pa.schema([("g", pa.int64()), ("h", pa.int64()), ("sh", pa.int64()), ("cut", pa.int32()), ("anchor", pa.int32()), ("body", pa.binary())]))

    return pieces.select("h", "sh", "cut", "anchor", "body").mapInArrow(run, "g long, h long, sh long, cut int, anchor int, body binary"), step


def _bodies(docs: DataFrame, wanted: DataFrame, length: int) -> DataFrame:
    """Segments' contents out of the documents that represent them: g, h, sh, cut, anchor, body."""
    lists = wanted.groupBy("d", "tk").agg(F.collect_list(F.struct("h", "sh", "p", "a", "b")).alias("segs"))  # at most a document's own segments
    have = docs.select(*doc_key(), "text").join(lists, ["d", "tk"]).dropDuplicates(["d", "tk"]).select("text", "segs")

    def run(batches):
        for b in batches:
            data, off = utf8(b.column(0))
            segs = b.column(1)
            own, ends = segs.flatten(), np.asarray(segs.offsets) - segs.offsets[0].as_py()
            h, sh, p, a, z = (np.asarray(own.field(i)) for i in range(5))
            base = np.repeat(off[:-1], np.diff(ends))
            for lo in range(0, len(h), 4096):
                s = slice(lo, lo + 4096)
                bodies = [data[x:y].tobytes() for x, y in zip(base[s] + a[s], base[s] + z[s] + length, strict=True)]
                yield pa.RecordBatch.from_arrays([pa.array(h[s]), pa.array(h[s]), pa.array(sh[s]), pa.array(np.zeros(len(bodies), np.int32)), pa.array((p[s] - a[s]).astype(np.int32)), pa.array(bodies, pa.binary())],
                                                 names=["g", "h", "sh", "cut", "anchor", "body"])

    return have.mapInArrow(run, "g long, h long, sh long, cut int, anchor int, body binary")


def repeated_spans(docs: DataFrame, min_bytes: int = MIN_BYTES, most: int = MOST) -> DataFrame:
    """d, tk, spans array<struct<lo, hi>>: byte ranges of each document that `min_bytes` long repeats cover; may overlap."""
    found = segments(docs, min_bytes)
    # a table of its own: a join of two plain exchanges, whose hot partitions Spark can split
    twice = snapshot(found.groupBy("h").agg(F.count("*").alias("m")).where("m > 1").select("h"))
    found = snapshot(found.join(twice, "h"))
    kinds = snapshot(found.groupBy("h", "sh").agg(F.count("*").alias("m"), F.min(F.struct("d", "tk", "p", "a", "b")).alias("r")))
    whole = kinds.where("m > 1").select("h", "sh", F.lit(0).alias("lo"), (F.col("r.b") - F.col("r.a") + min_bytes).cast("int").alias("hi"))
    several = snapshot(kinds.groupBy("h").agg(F.count("*").alias("kinds"), F.min("m").alias("least")).where("kinds > 1 and least = 1").select("h"))
    pieces = snapshot(_bodies(docs, kinds.join(several, "h").select("h", "sh", "r.*"), min_bytes))

    marks, width, olds = [whole], min_bytes - min_bytes // 3 + 1, [twice, several, kinds]
    while True:
        sizes = snapshot(pieces.groupBy("g").agg(F.count("*").alias("kinds")).where("kinds > 1"))
        small = pieces.join(sizes.where(F.col("kinds") <= most).select("g"), "g")
        marks.append(snapshot(_tree_marks(small, min_bytes)))
        large = sizes.where(F.col("kinds") > most).select("g")
        hot = large.limit(1).count()
        olds += [pieces, sizes]
        if not hot:
            break
        rest = pieces.join(large, "g")
        if width == 1:  # the core is the window itself
            marks.append(snapshot(rest.select("h", "sh", F.col("cut").alias("lo"), (F.col("cut") + min_bytes).cast("int").alias("hi"))))
            break
        dealt, width = _refined(rest, min_bytes, width)
        pieces = snapshot(dealt)
    every = marks[0]
    for m in marks[1:]:
        every = every.union(m)
    every = snapshot(every.groupBy("h", "sh").agg(F.collect_set(F.struct("lo", "hi")).alias("marks")))  # ranges of one segment
    own = found.join(every, ["h", "sh"]).select("d", "tk", F.explode(F.transform("marks", lambda m: F.struct((F.col("a") + m["lo"]).alias("lo"), (F.col("a") + m["hi"]).alias("hi")))).alias("s"))
    spans = snapshot(own.groupBy("d", "tk").agg(F.collect_set("s").alias("spans")))  # ranges of one document
    for old in [found, every, *olds, *[m for m in marks if hasattr(m, "_snapshot_path")]]:
        drop_snapshot(old)
    return spans


def passage_spans(docs: DataFrame, words: int, under: int) -> DataFrame:
    """d, tk, spans array<struct<lo, hi>>: stretches of `words` whole words, shorter than `under` bytes, that occur more than once.

    Occurrences that overlap in one text, as in a run of one word, count once here.
    """
    def run(batches):
        for b in batches:
            data, off = utf8(b.column(2))
            for i, j in blocks(off):
                part, o = data[off[i] : off[j]], off[i : j + 1] - off[i]
                start, end, first = words_of(part, o)
                m = len(start) - words + 1
                if m <= 0:
                    continue
                lo, hi = start[:m], end[words - 1 :]
                doc = np.searchsorted(first, np.arange(m), side="right") - 1
                own = np.flatnonzero((hi - lo < under) & (np.arange(m) + words <= first[doc + 1]))
                h = [xxhash.xxh3_128_digest(part[x:y].tobytes()) for x, y in zip(lo[own], hi[own], strict=True)]
                doc, lo, hi = doc[own], lo[own], hi[own]
                yield pa.RecordBatch.from_arrays([*(b.column(c).slice(i, j - i).take(pa.array(doc)) for c in (0, 1)), pa.array(h, pa.binary()), pa.array((lo - o[doc]).astype(np.int32)), pa.array((hi - o[doc]).astype(np.int32))],
                                                 names=["d", "tk", "h", "lo", "hi"])

    found = snapshot(docs.select(*doc_key(), F.coalesce("text", F.lit("")).alias("text")).mapInArrow(run, "d long, tk long, h binary, lo int, hi int"))
    own = found.groupBy("h", "d", "tk").agg(F.count("*").alias("n"), F.size(F.collect_set("lo")).alias("places"), F.max("lo").alias("last"), F.min("hi").alias("over"))
    apart = F.max((F.col("n") > F.col("places")) | (F.col("last") >= F.col("over")))  # rows repeated, or twice in one text
    twice = snapshot(own.groupBy("h").agg(F.count("*").alias("texts"), apart.alias("apart")).where("texts > 1 or apart").select("h"))
    spans = snapshot(found.join(twice, "h").groupBy("d", "tk").agg(F.collect_set(F.struct("lo", "hi")).alias("spans")))  # ranges of one document
    for old in (found, twice):
        drop_snapshot(old)
    return spans


def word_segments(part: np.ndarray, o: np.ndarray, words: int, under: int):
    """Segments as by `anchors_of`, of windows of `words` whole words below `under` bytes: hash of the anchor's words // 3
    words, document number, first and end byte, distance of the anchor from the first."""
    start, end, first = words_of(part, o)
    m, k = len(start) - words + 1, words // 3
    own = np.empty(0, np.int64)
    if m > 0:
        doc = np.searchsorted(first, np.arange(m), side="right") - 1
        own = np.flatnonzero((end[words - 1 :] - start[:m] < under) & (np.arange(m) + words <= first[doc + 1]))
    if not len(own):
        return (np.empty(0, np.uint64), *(np.empty(0, np.int64),) * 4)
    gram = mix64(_HASH.ranges(_HASH.prefix(part), start[: len(start) - k + 1], end[k - 1 :]))
    least = _sliding_min((gram & np.uint64(0xFFFFFFFF00000000)) | np.arange(len(gram), dtype=np.uint64), words - k + 1)
    at = (least & np.uint64(0xFFFFFFFF)).astype(np.int64)[own]
    head = np.flatnonzero(np.concatenate([[True], (at[1:] != at[:-1]) | (own[1:] != own[:-1] + 1)]))
    tail = np.concatenate([head[1:] - 1, [len(own) - 1]])
    lo = start[own[head]]
    return gram[at[head]], doc[own[head]], lo, end[own[tail] + words - 1], start[at[head]] - lo


def word_passages(docs: DataFrame, words: int, under: int) -> DataFrame:
    """d, tk, passages array<struct<lo, hi>>: stretches of `words` whole words, shorter than `under` bytes, that also start elsewhere.

    Overlaps count, as for bytes. Equal segments are counted whole; only where distinct ones share an anchor is one of each
    kind taken apart into its windows.
    """
    def anchored(batches):
        for b in batches:
            data, off = utf8(b.column(2))
            for i, j in blocks(off):
                part, o = data[off[i] : off[j]], off[i : j + 1] - off[i]
                h, doc, lo, hi, p = word_segments(part, o, words, under)
                view = memoryview(np.ascontiguousarray(part))
                sh = [xxhash.xxh3_64_intdigest(view[x:y], z) for x, y, z in zip(lo.tolist(), hi.tolist(), p.tolist(), strict=True)]
                row = pa.array(doc + i)
                yield pa.RecordBatch.from_arrays([pa.array(h.view(np.int64)), pa.array(np.array(sh, np.uint64).view(np.int64)), b.column(0).take(row), b.column(1).take(row),
                                                  *(pa.array((x - o[doc]).astype(np.int32)) for x in (lo, hi))], names=["h", "sh", "d", "tk", "lo", "hi"])

    def windows(batches):
        for b in batches:
            data, off = utf8(b.column(0))
            for i in range(len(off) - 1):
                text = data[off[i] : off[i + 1]]
                start, end, _ = words_of(text, np.array([0, len(text)]))
                rows = []
                for seg in b.column(1)[i].as_py():
                    f, l = np.searchsorted(start, seg["lo"]), np.searchsorted(end, seg["hi"]) - words + 2
                    rows += [(xxhash.xxh3_128_digest(text[x:y].tobytes()), seg["h"], seg["sh"], x - seg["lo"], y - seg["lo"]) for x, y in zip(start[f:l].tolist(), end[f + words - 1 : l + words - 1].tolist(), strict=True)]
                kinds = [pa.binary(), pa.int64(), pa.int64(), pa.int32(), pa.int32()]
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds, strict=True)], names=["w", "h", "sh", "lo", "hi"])

    found = docs.select(*doc_key(), F.coalesce("text", F.lit("")).alias("text")).mapInArrow(anchored, "h long, sh long, d long, tk long, lo int, hi int")
    twice = snapshot(found.groupBy("h").agg(F.count("*").alias("m")).where("m > 1").select("h"))
    found = snapshot(found.join(twice, "h"))
    kinds = snapshot(found.groupBy("h", "sh").agg(F.count("*").alias("m"), F.min(F.struct("d", "tk", "lo", "hi")).alias("r")))
    several = kinds.groupBy("h").agg(F.count("*").alias("kinds"), F.min("m").alias("least")).where("kinds > 1 and least = 1").select("h")
    lists = kinds.join(several, "h").groupBy("r.d", "r.tk").agg(F.collect_list(F.struct("h", "sh", "r.lo", "r.hi")).alias("segs"))  # at most a document's own segments
    have = docs.select(*doc_key(), "text").join(lists, ["d", "tk"]).dropDuplicates(["d", "tk"]).select("text", "segs")
    pieces = snapshot(have.mapInArrow(windows, "w binary, h long, sh long, lo int, hi int"))
    shared = snapshot(pieces.groupBy("w").agg(F.count("*").alias("m")).where("m > 1").select("w"))
    whole = kinds.where("m > 1").select("h", "sh", F.lit(0).alias("lo"), (F.col("r.hi") - F.col("r.lo")).alias("hi"))
    marks = snapshot(whole.union(pieces.join(shared, "w").select("h", "sh", "lo", "hi")).groupBy("h", "sh").agg(F.collect_set(F.struct("lo", "hi")).alias("marks")))  # ranges of one segment
    own = found.select("h", "sh", "d", "tk", F.col("lo").alias("at")).join(marks, ["h", "sh"])
    moved = F.transform("marks", lambda m: F.struct((F.col("at") + m["lo"]).alias("lo"), (F.col("at") + m["hi"]).alias("hi")))
    spans = snapshot(own.groupBy("d", "tk").agg(F.flatten(F.collect_set(moved)).alias("passages")))  # ranges of one document
    for old in (twice, found, kinds, pieces, shared, marks):
        drop_snapshot(old)
    return spans


def merged(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    out: list[tuple[int, int]] = []
    for lo, hi in sorted(spans):
        if out and lo <= out[-1][1]:
            out[-1] = (out[-1][0], max(hi, out[-1][1]))
        else:
            out.append((lo, hi))
    return out


def _kept(text: bytes, cut: list[tuple[int, int]]) -> bytes:
    parts, at = [], 0
    for lo, hi in cut:
        parts.append(text[at:lo])
        at = hi
    return b"".join([*parts, text[at:]])


def _with_spans(docs: DataFrame, spans: DataFrame, *more: Column) -> DataFrame:
    """doc (all columns), text, lo array<int>, hi array<int>, and `more` of the spans' columns."""
    rows = packed(docs).select("doc", *[c.alias(x) for c, x in zip(doc_key("doc.doc_id", "doc.text"), ("d", "tk"), strict=True)])
    joined = rows.join(spans, ["d", "tk"], "left")
    return joined.select("doc", F.col("doc.text").alias("text"), F.transform("spans", lambda s: s["lo"]).alias("lo"), F.transform("spans", lambda s: s["hi"]).alias("hi"), *more)


def repeat_digest(docs: DataFrame, min_bytes: int = MIN_BYTES, most: int = MOST, words: int = WORDS) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256, text (what is left; a character cut in two shows as U+FFFD), n_repeated.

    n_repeated: bytes that repeats cover, with those passages of `words` words that are too short in bytes to be removed.
    """
    names, kinds = ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "text", "n_repeated"], [pa.int64()] * 3 + [pa.string()] * 2 + [pa.int64()]

    def run(batches):
        for b in batches:
            data, off = utf8(b.column(1))
            for first, end in blocks(off):
                rows = []
                for i, *ends in zip(range(first, end), *(b.column(c).slice(first, end - first).to_pylist() for c in range(2, 6)), strict=True):
                    lo, hi, begin, stop = (x or [] for x in ends)
                    text, cut = data[off[i] : off[i + 1]].tobytes(), merged(list(zip(lo, hi, strict=True)))
                    kept = _kept(text, cut)
                    both = merged([*cut, *zip(begin, stop, strict=True)])
                    rows.append((len(text), sum(y - x for x, y in cut), len(cut), hashlib.sha256(kept).hexdigest(), kept.decode("utf-8", "replace"), sum(y - x for x, y in both)))
                yield pa.RecordBatch.from_arrays([b.column(0).slice(first, end - first), *(pa.array(c, t) for c, t in zip(zip(*rows, strict=True), kinds, strict=True))], names=names)

    own = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    spans = repeated_spans(own, min_bytes, most).join(word_passages(own, words, min_bytes), ["d", "tk"], "full")
    rows = _with_spans(own, spans, F.transform("passages", lambda s: s["lo"]).alias("begin"), F.transform("passages", lambda s: s["hi"]).alias("stop"))
    rows = rows.select(F.col("doc.doc_id").alias("doc_id"), "text", "lo", "hi", "begin", "stop")
    return rows.mapInArrow(run, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, text string, n_repeated long")


def without_repeats(docs: DataFrame, min_bytes: int = MIN_BYTES, most: int = MOST, words: int | None = None) -> DataFrame:
    """All columns, with repeated bytes cut out of `text` (spans shrink to whole characters); n_chars follows, null text stays null.

    words: repeated stretches of that many words go too where they take less than `min_bytes`.
    """
    def run(batches):
        for b in batches:
            data, off = utf8(b.column(1))
            out = []
            for i, (lo, hi) in enumerate(zip(b.column(2).to_pylist(), b.column(3).to_pylist(), strict=True)):
                if lo is None or not b.column(1)[i].is_valid:
                    out.append(b.column(1)[i].as_py())
                    continue
                raw = data[off[i] : off[i + 1]]
                cut = []
                for x, y in merged(list(zip(lo, hi, strict=True))):
                    while x < y and raw[x] & 0xC0 == 0x80:
                        x += 1
                    while y > x and y < len(raw) and raw[y] & 0xC0 == 0x80:
                        y -= 1
                    cut.append((x, y))
                out.append(_kept(raw.tobytes(), cut).decode("utf-8", "replace"))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(out, pa.string())], names=["doc", "kept"])

    own = docs.select("doc_id", "text")
    spans = repeated_spans(own, min_bytes, most)
    if words:
        both = spans.union(passage_spans(own, words, min_bytes).select("d", "tk", F.col("spans").cast(spans.schema["spans"].dataType)))
        spans = both.groupBy("d", "tk").agg(F.flatten(F.collect_list("spans")).alias("spans"))
    rows = _with_spans(docs, spans)
    done = rows.mapInArrow(run, f"doc {rows.schema['doc'].dataType.simpleString()}, kept string")
    kept = {"text": F.col("kept"), "n_chars": F.length("kept").cast("long")}
    return done.select(*[kept.get(c, F.col("doc").getField(c)).alias(c) for c in docs.columns])
