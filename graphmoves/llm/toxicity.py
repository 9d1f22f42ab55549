"""Toxicity: a support vector machine on a gap-weighted subsequence string kernel with Nystroem landmarks.

k(s, t) sums, over subsequences of three characters common to s and t, decay ** (spans in s and t), so
inserted characters lessen a match but don't break it. The one kernel used throughout is its normalised form
to the power POWER, (k(s, t) / sqrt(k(s, s) k(t, t))) ** POWER, a product of kernels. A word's features are its Nystroem map
K_mm ** -1/2 K(word, landmarks). Landmarks are whole words of labelled texts, taken one by one: the word whose
association with the label (one-sided z score over texts) times its distance from the span of those taken is largest.
A labelled text is a bag of words: of texts with label 1 the machine is trained on the words of positive margin (or the
largest there is), of others on the three of largest margin, all found anew in every pass. A text's score is a logistic function of its largest margin, of the sum of its positive ones and of their density.
Training takes at most `sample` labelled texts of each class. Runs of single characters ("x y z") are read
as one word; words longer than `longest` characters as overlapping stretches of that length.
Edge cases: null and empty texts score as texts without words; equal texts get equal scores; without labels of both classes,
or without any word that marks one, every score is 0.5; an empty table gives no rows; very long texts are scored word by
word, so memory goes with their distinct words.
"""

from __future__ import annotations

from collections import Counter

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphmoves.llm.common import blocks, utf8
from graphmoves.llm.quality import training_sample

HELD_OUT = "coalesce(crc32(cast(doc_id as string)) % 4 = 2, false)"
DECAY = 0.5
POWER = 2
#: The margin of a text without words, and the least one that counts.
NO_WORD = -1.0
_MARKS = regex.compile(r"[\W_]+")
_OUTER = regex.compile(r"^[\W_]+|[\W_]+$")
_RUNS = regex.compile(r"(?<!\S)\S(?:\s\S){2,}(?!\S)")


def words(text: str, longest: int = 24) -> set[str]:
    """Words without outer marks; one with inner marks counts without them too."""
    text = text.lower()
    out = set()
    for w in set(text.split()):
        if not w.isalnum():
            w = _OUTER.sub("", w)
            if not w.isalnum():
                out.add(_MARKS.sub("", w))
        out.add(w)
    out.update("".join(m[0].split()) for m in _RUNS.finditer(text))
    for w in [w for w in out if len(w) > longest]:
        out.remove(w)
        out.update(w[i : i + longest] for i in range(0, len(w) - longest // 2, longest // 2))
    return {w for w in out if len(w) > 2}


class Kernel:
    """Subsequence kernel of order 3 between many words and a fixed set of landmarks."""

    def __init__(self, landmarks: list[str], decay: float = DECAY):
        self.landmarks, self.m, self.width, self.decay = landmarks, len(landmarks), max(map(len, landmarks)), np.float32(decay)
        chars = sorted({c for x in landmarks for c in x})
        self.code = {c: i + 1 for i, c in enumerate(chars)}
        self.equal = np.zeros((len(chars) + 1, self.m, self.width), np.float32)
        for i, x in enumerate(landmarks):
            for j, c in enumerate(x):
                self.equal[self.code[c], i, j] = 1
        self.own = self_kernel(landmarks, decay)

    def raw(self, texts: list[str]) -> np.ndarray:
        out = np.zeros((len(texts), self.m), np.float32)
        reach = _reach(self.width, self.decay)
        first = (self.equal.reshape(-1, self.width) @ reach).reshape(self.equal.shape)
        by_size = sorted(range(len(texts)), key=lambda i: len(texts[i]))
        for lo in range(0, len(by_size), 512):
            pick = by_size[lo : lo + 512]
            x = np.zeros((len(texts[pick[-1]]), len(pick)), np.int64)
            for k, i in enumerate(pick):
                x[: len(texts[i]), k] = [self.code.get(c, 0) for c in texts[i]]
            out[pick] = _scan(((self.equal[row], first[row]) for row in x), (len(pick), self.m, self.width), reach, self.decay)
        return out

    def __call__(self, texts: list[str]) -> np.ndarray:
        """Normalised kernel to the power POWER between texts and landmarks."""
        norm = np.sqrt(self_kernel(texts, float(self.decay))[:, None] * self.own)
        return np.minimum(self.raw(texts) / norm, 1) ** POWER


def _reach(width: int, decay: float) -> np.ndarray:
    """A match at j reaches a later j' with decay for each step between."""
    gap = np.arange(width)[None] - np.arange(width)[:, None]
    return np.where(gap > 0, float(decay) ** (gap + 1.0), 0).astype(np.float32)


def _scan(rows, shape: tuple, reach: np.ndarray, decay) -> np.ndarray:
    """Kernel of order 3 by a scan over characters; rows yield which places of the other text match, and what the first match reaches."""
    one, two, total = np.zeros(shape, np.float32), np.zeros(shape, np.float32), np.zeros(shape[:-1], np.float32)
    for hit, first in rows:
        total += np.float32(decay) ** 2 * np.einsum("...j,...j->...", hit, two)
        two *= np.float32(decay)
        two += ((hit * one).reshape(-1, shape[-1]) @ reach).reshape(shape)
        one *= np.float32(decay)
        one += first
    return total


def self_kernel(texts: list[str], decay: float = DECAY) -> np.ndarray:
    """k(s, s) of each text, never 0."""
    out = np.zeros(len(texts), np.float32)
    by_size = sorted(range(len(texts)), key=lambda i: len(texts[i]))
    for lo in range(0, len(by_size), 4096):
        pick = by_size[lo : lo + 4096]
        size = len(texts[pick[-1]])
        x = np.zeros((len(pick), size), np.int64)
        for k, i in enumerate(pick):
            x[k, : len(texts[i])] = [ord(c) for c in texts[i]]
        reach = _reach(size, decay)
        hits = ((h := ((x == x[:, j : j + 1]) & (x > 0)).astype(np.float32), h @ reach) for j in range(size))
        out[pick] = _scan(hits, x.shape, reach, decay)
    return np.maximum(out, 1e-9)


def choose_landmarks(rows: list[tuple[int, set[str]]], count: int = 24, among: int = 600, least: float = 5.0) -> list[str]:
    """Words that mark label 1, each far from the span of those taken before in the kernel's feature space."""
    toxic, other = Counter(), Counter()
    for y, ws in rows:
        (toxic if y else other).update(w for w in ws if len(w) > 3)
    n1, n0 = max(1, sum(y for y, _ in rows)), max(1, sum(1 - y for y, _ in rows))

    def z(w: str) -> float:
        p = (toxic[w] + other[w]) / (n1 + n0)
        return (toxic[w] / n1 - other[w] / n0) / np.sqrt(p * (1 - p) * (1 / n1 + 1 / n0) + 1e-12)

    worth = sorted(((z(w), w) for w, n in toxic.items() if n >= 3), reverse=True)[:among]
    words_ = [w for v, w in worth if v >= least]
    if not words_:
        return []
    weight = np.array([v for v, _ in worth[: len(words_)]])
    rest, found, picked = np.ones(len(words_)), np.zeros((len(words_), 0)), []
    while len(picked) < min(count, len(words_)):  # pivoted Cholesky factor of the candidates' kernel matrix
        i = int(np.argmax(weight * rest))
        if rest[i] < 0.05:
            break
        picked.append(words_[i])
        column = Kernel([words_[i]])(words_)[:, 0]
        new = (column - found @ found[i]) / np.sqrt(rest[i])
        found = np.column_stack([found, new])
        rest = np.maximum(0, rest - new * new)
    return picked


def _logistic(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Weights and bias of a slightly regularised logistic regression, by Newton's method."""
    x = np.column_stack([x, np.ones(len(x))])
    w = np.zeros(x.shape[1])
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        d = p * (1 - p) + 1e-9
        w -= np.linalg.solve((x * d[:, None]).T @ x + 1e-2 * np.eye(len(w)), x.T @ (p - y) + 1e-2 * w)
    return w


def _machine(x: np.ndarray, y: np.ndarray, share: np.ndarray, start: np.ndarray, rounds: int) -> np.ndarray:
    """Weights and bias of a linear machine with squared hinge loss, classes weighing the same; full batches. share: a row's weight in its class."""
    x = np.column_stack([x, np.ones(len(x))])
    sign = 2.0 * y - 1
    weight = np.where(y == 1, 0.5 / max(1e-9, share[y == 1].sum()), 0.5 / max(1e-9, share[y == 0].sum())) * share
    w, m, v = start.copy(), np.zeros(x.shape[1]), np.zeros(x.shape[1])
    for t in range(1, rounds + 1):
        g = x.T @ (-2 * weight * np.maximum(0, 1 - sign * (x @ w)) * sign) + 2e-4 * np.append(w[:-1], 0)
        m, v = 0.9 * m + 0.1 * g, 0.99 * v + 0.01 * g * g
        w -= 0.1 * (1 - 0.9 * t / rounds) * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.99**t)) + 1e-9)
    return w


def pooled(margins: np.ndarray) -> tuple[float, float, float]:
    """What of a text's words counts: the largest margin, the logarithm of the sum of positive ones, and of that sum's density."""
    if not len(margins):
        return NO_WORD, 0.0, 0.0
    total = np.sort(margins[margins > 0]).sum()
    return float(max(margins.max(), NO_WORD)), float(np.log1p(total)), float(np.log1p(20 * total / (len(margins) + 5)))


def train(rows: list[tuple[int, set[str]]], passes: int = 6, rounds: int = 300) -> dict | None:
    """landmarks; weights and bias of a word's margin on its kernel values; link, the logistic function of what `pooled` gives."""
    marks = choose_landmarks(rows) if len({y for y, _ in rows}) == 2 else []
    if not marks:
        return None
    kernel = Kernel(marks)
    mm = kernel(marks)
    val, vec = np.linalg.eigh((mm + mm.T) / 2)
    root = vec @ np.diag(1 / np.sqrt(np.maximum(val, 1e-3))) @ vec.T
    vocabulary = sorted(set().union(*(ws for _, ws in rows)))
    at = {w: i for i, w in enumerate(vocabulary)}
    close = kernel(vocabulary)
    x = close @ root
    bags = [np.array(sorted(at[w] for w in ws)) for _, ws in rows]
    y = np.array([y for y, _ in rows])
    own = [i for i, b in enumerate(bags) if len(b)]
    margin = close.max(1) - 0.6  # at first, words close to a landmark speak for their text
    w = np.zeros(len(marks) + 1)
    for _ in range(passes):
        shown = []
        for i in own:
            m = margin[bags[i]]
            shown.append(bags[i][(m > 0) | (m == m.max())] if y[i] else bags[i][np.argsort(-m)[:3]])
        sizes = np.array([len(v) for v in shown])
        w = _machine(x[np.concatenate(shown)], np.repeat(y[own], sizes), np.repeat(1 / sizes, sizes), w, rounds)
        margin = x @ w[:-1] + w[-1]
    weights, bias = root @ w[:-1], float(w[-1])
    margin = np.round(close @ weights + bias, 4)
    return {"landmarks": marks, "weights": weights, "bias": bias, "link": _logistic(np.array([pooled(margin[b]) for b in bags]), y)}


class Scorer:
    """Scores of texts; keeps margins of words met before, up to `keep` words."""

    def __init__(self, model: dict, keep: int = 300_000):
        self.model, self.kernel, self.keep, self.known = model, Kernel(model["landmarks"]), keep, {}

    def learn(self, ws: set[str]) -> None:
        new = sorted(w for w in ws if w not in self.known)
        if len(self.known) + len(new) > self.keep:
            self.known, new = {}, sorted(ws)
        for lo in range(0, len(new), 8192):
            part = new[lo : lo + 8192]
            self.known.update(zip(part, np.round(self.kernel(part) @ self.model["weights"] + self.model["bias"], 4).tolist(), strict=True))

    def score(self, ws: set[str]) -> float:
        self.learn(ws)
        link = self.model["link"]
        return float(1 / (1 + np.exp(-np.clip(np.dot(pooled(np.array([self.known[w] for w in ws])), link[:-1]) + link[-1], -30, 30))))


def fit(docs: DataFrame, labels: DataFrame, sample: int = 2000) -> dict | None:
    rows = training_sample(docs, labels, "toxic", HELD_OUT, sample).collect()
    rows.sort(key=lambda r: (r.y, r.text or ""))
    return train([(r.y, words(r.text or "")) for r in rows])


def score_toxicity(docs: DataFrame, model: dict | None, threshold: float = 0.3) -> DataFrame:
    """doc_id, held_out, score, predicted."""
    def run(batches):
        scorer = Scorer(model) if model else None
        for b in batches:
            data, off = utf8(b.column(1))
            for lo, hi in blocks(off):
                sets = [words(data[off[i] : off[i + 1]].tobytes().decode("utf-8", "replace")) if model else set() for i in range(lo, hi)]
                if model:
                    scorer.learn(set().union(*sets))
                yield pa.RecordBatch.from_arrays([b.column(0).slice(lo, hi - lo), pa.array([scorer.score(s) if model else 0.5 for s in sets], pa.float64())], names=["doc_id", "score"])

    out = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, "doc_id long, score double")
    return out.select("doc_id", F.expr(HELD_OUT).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))
