"""Quality classifier: a factorisation machine over hashed words, structure statistics and text metadata.

Score of x: w0 + <w, x> + 1/2 * sum_f ((sum_i v_if x_i)^2 - sum_i v_if^2 x_i^2), linear in the number of
non-zero features. Training uses at most `sample` labelled documents of each class, by hash order, of at most 64 KB each;
the score covers every word of every text, however long. Edge cases: null and empty texts score from the statistics alone;
equal texts get equal scores; without labels every score is 0.5; an empty table gives no rows.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphmoves.llm.common import Rolling, blocks, mix64, utf8, words_of

HELD_OUT = "coalesce(crc32(cast(doc_id as string)) % 3 = 1, false)"
WORDS = 1 << 13
STATS = ("log_words", "word_bytes", "upper", "digit", "mark", "space", "non_ascii", "line_bytes", "same_lines", "distinct_words", "bar", "hash_marks", "few_words", "bias_free_log_bytes")
_LINE_HASH = Rolling(seed=6)


def features(data: np.ndarray, off: np.ndarray):
    """Per document: arrays of feature numbers and values. Words first (L2-normed counts), then statistics near [0, 1]."""
    kind = np.zeros(256, np.int8)
    kind[65:91], kind[97:123], kind[48:58], kind[128:] = 1, 2, 3, 4
    kind[[9, 10, 11, 12, 13, 32]] = 5
    for lo, hi in blocks(off):
        part, o = data[off[lo] : off[hi]], off[lo : hi + 1] - off[lo]
        prefix = _LINE_HASH.prefix(part)
        start, end, first = words_of(part, o)
        word = (mix64(_LINE_HASH.ranges(prefix, start, end)) % np.uint64(WORDS)).astype(np.int64)
        k = kind[part]
        sums = {i: np.concatenate([[0], np.cumsum(k == i)]) for i in range(6)}
        bars = np.concatenate([[0], np.cumsum(part == 124)])
        marks = np.concatenate([[0], np.cumsum(np.isin(part, [33, 35, 36, 37, 38, 42]))])
        breaks = np.flatnonzero(part == 10)
        at = np.searchsorted(breaks, o)
        for i in range(hi - lo):
            a, b = o[i], o[i + 1]
            n = max(1, b - a)
            ids, counts = np.unique(word[first[i] : first[i + 1]], return_counts=True)
            total = max(1, first[i + 1] - first[i])
            edges = np.concatenate([[a], breaks[at[i] : at[i + 1]] + 1, [b]])
            edges = edges[edges <= b]
            lines = len(np.unique(_LINE_HASH.ranges(prefix, edges[:-1], edges[1:]))) if len(edges) > 1 else 1
            share = lambda x: (x[b] - x[a]) / n  # noqa: B023, E731
            stats = np.array([
                np.log1p(total) / 10, min(2, (b - a) / total / 8), share(sums[1]), share(sums[3]), share(sums[0]), share(sums[5]), share(sums[4]),
                min(2, n / max(1, len(edges) - 1) / 200), 1 - lines / max(1, len(edges) - 1), len(ids) / total, share(bars) * 10, share(marks) * 4, float(total < 20), np.log1p(b - a) / 12])
            norm = np.sqrt(float((counts * counts).sum())) or 1.0
            yield np.concatenate([ids, np.arange(WORDS, WORDS + len(STATS))]).astype(np.int32), np.concatenate([counts / norm, stats]).astype(np.float32)


def fm_score(ids: np.ndarray, values: np.ndarray, m: dict) -> float:
    v = m["v"][ids] * values[:, None]
    s = v.sum(0)
    z = float(m["w0"] + m["w"][ids] @ values + 0.5 * (s @ s - (v * v).sum()))
    return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def train(rows: list[tuple[np.ndarray, np.ndarray]], y: np.ndarray, rank: int = 4, epochs: int = 8, rate: float = 0.1, seed: int = 2) -> dict:
    """Adagrad on the class-weighted logistic loss, in small batches."""
    rng = np.random.default_rng(seed)
    size = WORDS + len(STATS)
    m = {"w0": 0.0, "w": np.zeros(size), "v": rng.normal(0, 0.05, (size, rank))}
    gw, gv, g0 = np.full(size, 1e-6), np.full((size, rank), 1e-6), 1e-6
    n1 = max(1, int(y.sum()))
    weight = np.where(y == 1, len(y) / (2 * n1), len(y) / (2 * max(1, len(y) - n1)))
    for _ in range(epochs):
        order = rng.permutation(len(rows))
        for lo in range(0, len(order), 16):
            pick = order[lo : lo + 16]
            ids, x = np.concatenate([rows[i][0] for i in pick]), np.concatenate([rows[i][1] for i in pick])
            who = np.repeat(np.arange(len(pick)), [len(rows[i][0]) for i in pick])
            vx = m["v"][ids] * x[:, None]
            s = np.zeros((len(pick), rank))
            np.add.at(s, who, vx)
            z = m["w0"] + np.bincount(who, m["w"][ids] * x, len(pick)) + 0.5 * ((s * s).sum(1) - np.bincount(who, (vx * vx).sum(1), len(pick)))
            d = (1 / (1 + np.exp(-np.clip(z, -30, 30))) - y[pick]) * weight[pick] / len(pick)
            dw = d[who] * x
            dv = dw[:, None] * (s[who] - vx) + 1e-5 * m["v"][ids]
            u, back = np.unique(ids, return_inverse=True)
            sw, sv = np.bincount(back, dw, len(u)) + 1e-5 * m["w"][u], np.zeros((len(u), rank))
            np.add.at(sv, back, dv)
            gw[u] += sw * sw
            gv[u] += sv * sv
            g0 += d.sum() ** 2
            m["w"][u] -= rate * sw / np.sqrt(gw[u])
            m["v"][u] -= rate * 0.5 * sv / np.sqrt(gv[u])
            m["w0"] -= rate * d.sum() / np.sqrt(g0)
    return m


def training_sample(docs: DataFrame, labels: DataFrame, label: str, held_out: str, sample: int, longest: int = 1 << 16) -> DataFrame:
    """y and text of at most `sample` labelled documents of each class, none above `longest` bytes: what is broadcast and gathered is so bounded.

    An id with several labels counts by the least; of several texts of one id the least is taken.
    """
    own = labels.where(f"not {held_out} and doc_id is not null and {label} is not null").groupBy(F.col("doc_id").alias("_i")).agg(F.min(F.col(label).cast("int")).alias("y"))
    order = [F.xxhash64("_i"), "_i"]
    picked = own.where("y = 1").orderBy(*order).limit(sample).union(own.where("y = 0").orderBy(*order).limit(sample))
    rows = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).where(F.octet_length("text") <= longest).join(F.broadcast(picked), F.col("doc_id") == F.col("_i"))
    return rows.groupBy("doc_id").agg(F.first("y").alias("y"), F.min("text").alias("text")).select("y", "text")


def fit(docs: DataFrame, labels: DataFrame, sample: int = 2500) -> dict | None:
    def run(batches):
        for b in batches:
            data, off = utf8(b.column(1))
            got = list(features(data, off))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([i.tobytes() for i, _ in got], pa.binary()), pa.array([v.tobytes() for _, v in got], pa.binary())], names=["y", "ids", "x"])

    rows = training_sample(docs, labels, "quality", HELD_OUT, sample).mapInArrow(run, "y int, ids binary, x binary").collect()
    if not rows:
        return None
    rows.sort(key=lambda r: (r.y, bytes(r.ids), bytes(r.x)))
    return train([(np.frombuffer(r.ids, np.int32), np.frombuffer(r.x, np.float32)) for r in rows], np.array([r.y for r in rows], float))


def score_quality(docs: DataFrame, model: dict | None, threshold: float = 0.5) -> DataFrame:
    """doc_id, held_out, score, predicted."""
    def run(batches):
        for b in batches:
            data, off = utf8(b.column(1))
            scores = [fm_score(i, v, model) if model else 0.5 for i, v in features(data, off)]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(scores, pa.float64())], names=["doc_id", "score"])

    out = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, score double")
    return out.select("doc_id", F.expr(HELD_OUT).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))
