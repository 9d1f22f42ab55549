"""Language ID by a bidirectional gated recurrent network over bytes, trained here in numpy.

Every byte position gets a label distribution; a document's distribution is the mean over all its
positions. Texts are read in stretches of `stretch` bytes, each with fresh states at both ends, so that
thousands of stretches advance together and long texts cost no more memory.
Bounded training sample: `sample` documents by hash order, one window of `window` bytes each; rows equal in id
and text count once, by the least lang.
Edge cases: null text or no letters: "und", score 0. Equal texts get equal results. An empty table gives no rows; without
any lang to learn all are "und".
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphmoves.llm.common import packed, unpacked, utf8

HELD_OUT = "coalesce(crc32(cast(doc_id as string)) % 3 = 1, false)"


def _cell(x: np.ndarray, table: np.ndarray, wh: np.ndarray, keep: bool = False):
    """States (T, 2, H, B) of both directions over bytes x (T, B); gates r, z and candidate c in one logistic call.

    table (2, 256, 3H) and wh (2, 3H, H) are scaled for that: tanh(a) = 2 / (1 + exp(-2a)) - 1.
    """
    t, b = x.shape
    h3 = table.shape[2]
    h = h3 // 3
    state = np.zeros((2, h, b), np.float32)
    out = np.empty((t, 2, h, b), np.float32)
    gates = np.empty((t, 3, 2, h, b), np.float32) if keep else None
    into = np.empty((2, h3, b), np.float32)
    for i in range(t):
        into[0], into[1] = table[0][x[i]].T, table[1][x[t - 1 - i]].T
        rec = wh @ state
        with np.errstate(over="ignore"):
            rz = 1 / (1 + np.exp(-(into[:, : 2 * h] + rec[:, : 2 * h])))
            r, z = rz[:, :h], rz[:, h:]
            c = 2 / (1 + np.exp(-(into[:, 2 * h :] + r * rec[:, 2 * h :]))) - 1
        if keep:
            gates[i] = r, z, c
        state = c + z * (state - c)
        out[i, 0], out[t - 1 - i, 1] = state[0], state[1]
    return (out, gates) if keep else out


def _scaled(model: dict) -> tuple[np.ndarray, np.ndarray]:
    h = model["wh"].shape[2]
    scale = np.concatenate([np.ones(2 * h), np.full(h, 2)]).astype(np.float32)
    return model["table"] * scale, model["wh"] * scale[:, None]


def gradients(m: dict, x: np.ndarray, weight: np.ndarray, y: np.ndarray) -> dict:
    """Of the weighted mean cross-entropy over positions of bytes x (T, B) with labels y (B), by backpropagation through time."""
    t, batch = x.shape
    h = m["wh"].shape[2]
    hs, gates = _cell(x, *_scaled(m), keep=True)
    both = hs.reshape(t, 2 * h, batch)
    logit = np.einsum("kh,thb->tkb", m["out"], both, optimize=True) + m["bias"][:, None]
    p = np.exp(logit - logit.max(1, keepdims=True))
    p /= p.sum(1, keepdims=True)
    p[:, y, np.arange(batch)] -= 1
    p *= (weight / max(1e-6, weight.sum()))[:, None]
    g = {"out": np.einsum("tkb,thb->kh", p, both, optimize=True), "bias": p.sum((0, 2)), "table": np.zeros_like(m["table"]), "wh": np.zeros_like(m["wh"])}
    dh_out = np.einsum("kh,tkb->thb", m["out"], p, optimize=True).reshape(t, 2, h, batch)
    carry = np.zeros((2, h, batch), np.float32)
    for i in range(t - 1, -1, -1):
        r, z, c = gates[i]
        prev = np.stack([hs[i - 1, 0], hs[t - i, 1]]) if i else np.zeros_like(carry)
        dh = carry + np.stack([dh_out[i, 0], dh_out[t - 1 - i, 1]])
        dc = dh * (1 - z) * (1 - c * c)
        dz = dh * (prev - c) * z * (1 - z)
        dr = dc * (m["wh"][:, 2 * h :] @ prev) * r * (1 - r)
        into, back = np.concatenate([dr, dz, dc], 1), np.concatenate([dr, dz, dc * r], 1)
        g["wh"] += back @ prev.transpose(0, 2, 1)
        for d, xs in ((0, x[i]), (1, x[t - 1 - i])):
            np.add.at(g["table"][d], xs, into[d].T)
        carry = dh * z + m["wh"].transpose(0, 2, 1) @ back
    return g


def train(windows: list[bytes], labels: list[int], classes: int, hidden: int = 8, steps: int = 500, batch: int = 128, rate: float = 0.01, seed: int = 1) -> dict:
    """Adam on the mean cross-entropy of every position, by backpropagation through time."""
    rng = np.random.default_rng(seed)
    t = max(map(len, windows))
    x = np.zeros((len(windows), t), np.uint8)
    mask = np.zeros((len(windows), t), np.float32)
    for i, w in enumerate(windows):
        x[i, : len(w)], mask[i, : len(w)] = np.frombuffer(w, np.uint8), 1
    y = np.array(labels)
    weight = len(y) / (classes * np.maximum(1, np.bincount(y, minlength=classes)))
    h = hidden
    m = {"table": rng.normal(0, 0.3, (2, 256, 3 * h)), "wh": rng.normal(0, 0.3, (2, 3 * h, h)), "out": rng.normal(0, 0.3, (classes, 2 * h)), "bias": np.zeros(classes)}
    m = {k: v.astype(np.float32) for k, v in m.items()}
    mean, var = {k: np.zeros_like(v) for k, v in m.items()}, {k: np.zeros_like(v) for k, v in m.items()}
    for step in range(1, steps + 1):
        pick = rng.integers(0, len(y), batch)
        xb, wb = x[pick].T, (mask[pick] * weight[y[pick], None]).T
        g = gradients(m, xb, wb, y[pick])
        norm = np.sqrt(sum(float((v * v).sum()) for v in g.values()))
        now = rate * (1 - 0.9 * step / steps)
        for k in m:
            v = g[k] * min(1, 1 / max(norm, 1e-9))
            mean[k] = 0.9 * mean[k] + 0.1 * v
            var[k] = 0.999 * var[k] + 0.001 * v * v
            m[k] -= (now * (mean[k] / (1 - 0.9**step)) / (np.sqrt(var[k] / (1 - 0.999**step)) + 1e-8)).astype(np.float32)
    return m


def position_labels(data: np.ndarray, off: np.ndarray, model: dict, stretch: int = 128, at_once: int = 1024):
    """Yield (document of each stretch, bytes in it, probabilities (T, K, B)) until all positions have one."""
    n = np.diff(off)
    per = -(-n // stretch)
    doc = np.repeat(np.arange(len(n)), per)
    start = off[:-1][doc] + stretch * (np.arange(len(doc)) - np.repeat(np.cumsum(per) - per, per))
    size = np.minimum(off[1:][doc] - start, stretch)
    table, wh = _scaled(model)
    for lo in range(0, len(doc), at_once):
        s, k = start[lo : lo + at_once], size[lo : lo + at_once]
        t = int(k.max())
        x = data[np.minimum(s + np.arange(t)[:, None], len(data) - 1)]
        x = np.where(np.arange(t)[:, None] < k, x, 0)
        hs = _cell(x, table, wh).reshape(t, -1, len(s))
        logit = np.matmul(model["out"], hs) + model["bias"][:, None]
        np.exp(logit - logit.max(1, keepdims=True), out=logit)
        yield doc[lo : lo + at_once], k, logit / logit.sum(1, keepdims=True)


def pool(data: np.ndarray, off: np.ndarray, model: dict, classes: int) -> np.ndarray:
    """Mean label distribution of each document over all its bytes."""
    total = np.zeros((len(off) - 1, classes))
    for doc, k, p in position_labels(data, off, model):
        p *= (np.arange(len(p))[:, None] < k)[:, None]
        np.add.at(total, doc, p.sum(0).T)
    return total / np.maximum(1, np.diff(off))[:, None]


def fit(docs: DataFrame, sample: int = 4000, window: int = 96, hidden: int = 8, steps: int = 500) -> tuple[dict, list[str]]:
    """Train on a window from a hashed place in each of at most `sample` documents that aren't held out."""
    own = docs.select("doc_id", "text", "lang").where(f"not {HELD_OUT} and lang is not null and text rlike '\\\\p{{L}}'")
    # the sample's last hash first, so that texts of the sample only leave the executors
    own = own.select("lang", "text", F.xxhash64("doc_id", "text").alias("h"))
    last = own.select("h").orderBy("h").limit(sample).agg(F.max("h")).first()[0]
    place = F.pmod(F.xxhash64("text", F.lit(5)), F.greatest(F.lit(1), F.length("text") - window)) + 1
    rows = own.where(F.col("h") <= F.lit(last)).select("lang", "h", F.substring("text", place.cast("int"), F.lit(window)).alias("w"))
    rows = rows.groupBy("h").agg(F.min(F.struct("lang", "w")).alias("r")).select("h", "r.*").collect() if last is not None else []  # a row per hash: at most `sample`
    rows.sort(key=lambda r: (r.h, r.w))
    langs = sorted({r.lang for r in rows})
    if not langs:
        return {}, []
    windows = [r.w.encode()[:window] for r in rows]
    return train(windows, [langs.index(r.lang) for r in rows], len(langs), hidden, steps), langs


def predict_language(docs: DataFrame, model: dict, langs: list[str]) -> DataFrame:
    """All columns in struct `doc`, with lang_pred and score."""
    given = packed(docs).select("doc", F.when(F.col("doc.text").rlike(r"\p{L}"), F.col("doc.text")).alias("text"))
    if not langs:
        return given.select("doc", F.lit("und").alias("lang_pred"), F.lit(0.0).alias("score"))
    names = pa.array([*langs, "und"])

    def run(batches):
        for b in batches:
            for lo in range(0, b.num_rows, 512):
                part = b.slice(lo, 512)
                data, off = utf8(part.column(1))
                p = pool(data, off, model, len(langs))
                known = np.diff(off) > 0
                best = np.where(known, p.argmax(1), len(langs))
                yield pa.RecordBatch.from_arrays([part.column(0), names.take(pa.array(best)), pa.array(np.where(known, p.max(1), 0.0))], names=["doc", "lang_pred", "score"])

    kind = given.schema["doc"].dataType.simpleString()
    return given.mapInArrow(run, f"doc {kind}, lang_pred string, score double")


def identify(docs: DataFrame) -> DataFrame:
    """doc_id, held_out, lang_pred, score for every document."""
    model, langs = fit(docs)
    out = predict_language(docs.select("doc_id", "text"), model, langs)
    return out.select(F.col("doc.doc_id").alias("doc_id"), "lang_pred", "score").select("doc_id", F.expr(HELD_OUT).alias("held_out"), "lang_pred", "score")


def keep_known_language(docs: DataFrame, least: float = 0.4) -> DataFrame:
    """Drop documents without letters and those whose best language stays under `least`."""
    model, langs = fit(docs)
    out = predict_language(docs, model, langs).where((F.col("lang_pred") != "und") & (F.col("score") >= least))
    return unpacked(out, docs.columns)
