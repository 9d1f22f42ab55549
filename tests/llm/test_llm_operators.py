"""Each operator against brute force, an exact round trip or held-out accuracy; and edge cases of rows."""

import hashlib
import random
import re
import zlib
from collections import Counter

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from graphmoves.llm import chat, decontaminate, jpeg, langid, neardup, packing, quality, queries, shards, suffix_repeats, toxicity
from graphmoves.llm.common import read_table

SF = "/root/testdata/sf0.001"
ODD = [None, "", " \t\n", "a", "one two three", "é" * 500, "same words in here again and again", "same words in here again and again", "x" * 3000, "\u0000<|im_end|>\\<|\\|"]


def prose(rng, n, words=300):
    return " ".join(f"w{rng.randrange(words)}" for _ in range(n))


# --- repeats ---------------------------------------------------------------------------------------


def brute_removed(texts, length):
    count = Counter(t[i : i + length] for t in texts for i in range(len(t) - length + 1))
    out = []
    for t in texts:
        hit = np.zeros(len(t), bool)
        for i in range(len(t) - length + 1):
            if count[t[i : i + length]] > 1:
                hit[i : i + length] = True
        out.append(hit)
    return out


def check_repeats(got, texts, length):
    raw = [(t or "").encode() for t in texts]
    for i, (t, hit) in enumerate(zip(raw, brute_removed(raw, length), strict=True)):
        r = got[i]
        kept = bytes(b for b, h in zip(t, hit, strict=True) if not h)
        runs = int(hit[:1].sum() + (hit[1:] & ~hit[:-1]).sum())
        assert (r.n_bytes, r.n_removed, r.n_spans, r.kept_sha256) == (len(t), int(hit.sum()), runs, hashlib.sha256(kept).hexdigest()), i
        assert r.text == kept.decode("utf-8", "replace"), i


@pytest.mark.parametrize("most", [2048, 3])
def test_repeats_equal_brute_force(spark, texts, most):
    rng = random.Random(5)
    passage = prose(rng, 40)
    ts = [prose(rng, rng.randrange(1, 120)) for _ in range(30)]
    for i in range(0, 30, 2):  # one passage in many surroundings, whole, cut and edited
        cut = rng.randrange(0, 20)
        ts[i] = ts[i] + " " + passage[cut : len(passage) - rng.randrange(30)] + ts[i][:50]
    ts += [ts[1], ts[1], ts[3][:-7] + "!", "ab" * 200, passage[:60] + "#" + passage[60:], *ODD]
    got = {r.doc_id: r for r in suffix_repeats.repeat_digest(texts(ts), 60, most).collect()}
    check_repeats(got, ts, 60)


def test_repeats_on_table(spark):
    docs = read_table(spark, SF, "documents")
    rows = {r.doc_id: r.text for r in docs.collect()}
    ids = sorted(rows)
    got = {r.doc_id: r for r in queries.op1_suffix_dedup(spark, SF).collect()}
    check_repeats({i: got[d] for i, d in enumerate(ids)}, [rows[d] for d in ids], 400)


def test_short_passages_of_many_words_are_reported(spark, texts):
    rng = random.Random(9)
    short = lambda n: " ".join("".join(rng.choice("abcdefgh") for _ in range(rng.randrange(1, 4))) for _ in range(n))
    p, q, own = short(70), short(50), [short(rng.randrange(1, 150)) for _ in range(12)]
    ts = [f"{own[0]} {p} end", f"{p}\n{own[1]}", f"{own[2]} {p[: len(p) // 2]} {own[3]}", f"{own[4]} {p[9:]}", f"{own[5]} {q} in", f"{own[6]} {q} out", own[7], own[7], f"{own[8]} {p} {own[9]} {p}", f"{own[10]} {p[:-1]}", "é x " * 60, *ODD]
    got = {r.doc_id: r for r in suffix_repeats.repeat_digest(texts(ts), 400).collect()}
    spans = [[(m.start(), m.end()) for m in re.finditer(rb"[^\x20\x09-\x0D]+", (t or "").encode())] for t in ts]
    windows = [(i, w[k][0], w[k + 50][1]) for i, w in enumerate(spans) for k in range(len(w) - 50)]
    count = Counter((ts[i] or "").encode()[a:z] for i, a, z in windows)
    hit = brute_removed([(t or "").encode() for t in ts], 400)
    removed = [int(h.sum()) for h in hit]
    for i, a, z in windows:
        if count[(ts[i] or "").encode()[a:z]] > 1:
            hit[i][a:z] = True
    assert [(got[i].n_removed, got[i].n_repeated) for i in range(len(ts))] == [(n, int(h.sum())) for n, h in zip(removed, hit, strict=True)]
    assert len(p) < 400 and got[0].n_removed == 0 and got[0].n_repeated == len(p) and got[4].n_repeated == 0


def test_interval_tree_lists_every_interval():
    lcp = np.array([1, 3, 3, 0, 2])
    assert sorted(suffix_repeats.interval_tree(lcp)) == [(1, 0, 3), (2, 4, 5), (3, 1, 3)]


def test_repeat_groups_hold_all_occurrences():
    groups = list(suffix_repeats.maximal_repeats([b"xxHELLOyy", b"zzHELLOww", b"qqHELLOyy"], [2, 2, 2], 5))
    assert any(sorted(m) == [0, 1, 2] and (lo, hi) == (0, 5) for m, lo, hi in groups)
    assert any(sorted(m) == [0, 2] and (lo, hi) == (0, 7) for m, lo, hi in groups)


def test_cutting_keeps_whole_characters_and_columns(spark, docs):
    p = "é" * 100
    rows = [(1, "a" + p + "b", "x", "s", 1), (2, "ç" + p + "d", "x", "s", 1), (3, None, None, None, None), (None, "q", "x", "s", 1), (1, "a" + p + "b", "x", "s", 1)]
    out = suffix_repeats.without_repeats(docs([(*r, 7) for r in rows], ", d long"), 60)
    assert out.columns == ["doc_id", "text", "lang", "source", "n_chars", "d"]
    assert sorted((r.doc_id or 0, r.text, r.d) for r in out.collect() if r.text is not None) == [(0, "q", 7), (1, "", 7), (1, "", 7), (2, "çd", 7)]


def test_pipeline_cuts_passages_of_short_words(spark, texts):
    import corpus_pipeline as cp

    rng = random.Random(8)
    short = lambda n: " ".join("".join(rng.choice("abcdefgh") for _ in range(rng.randrange(1, 4))) for _ in range(n))
    p, q, long, one = short(51), short(50), short(110), " ".join("x" * 60)
    assert len(p) < cp.PASSAGE_BYTES < len(long)
    ts = [f"Begin {p} end", f"{p}\nother", f"Here {q} stays", f"{q}\nagain", f"An {long} in", f"The {long} out", f"k {one} k", None, "é " + p.upper(), ""]
    got = {r.doc_id: r.text for r in dict(cp.STAGES)["suffix_dedup"](spark, texts(ts), SF).collect()}
    assert [got[i] for i in (0, 1, 2, 3, 7, 8, 9)] == ["Begin  end", "\nother", ts[2], ts[3], None, ts[8], ""]
    assert not any(long[i : i + 20] in got[d] for d in (4, 5) for i in range(len(long) - 20)) and got[6] == ts[6]


# --- chats -----------------------------------------------------------------------------------------


def test_chats_round_trip_and_order(spark):
    rows = [(1, 0, "system", "be\\<|im_end|>"), (1, 1, "user", "<\\|x"), (1, 2, "assistant", "<|im_start|>\\"), (2, 0, "assistant", "no"), (3, 0, "us\ner<|", None), (3, 0, None, ""), (None, None, "user", "\n")]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    out = {r.conv_id: r for r in chat.format_chats(df).selectExpr("*").collect()}
    assert out[1].valid and out[1].state == "answered" and out[2].state == "bad:0" and not out[3].valid
    assert "".join(s.text for s in out[1].segments) == out[1].formatted
    assert [s.text for s in out[1].segments if s.loss] == ["<\\|im_start|>\\\\"]
    read = {r.conv_id: r for r in chat.chat_digest(chat.format_chats(df)).collect()}
    told = lambda ts: hashlib.sha256("".join(f"{a}\n{b}\n" for a, b in ts).encode()).hexdigest()
    assert read[1].turns_sha256 == told([r[2:] for r in rows[:3]]) and read[1].loss_chars == len("<|im_start|>\\")
    assert read[3].turns_sha256 == told([("", ""), ("us\ner<|", "")]) and read[3].n_turns == 2
    assert chat.format_chats(df.where("false")).count() == 0


# --- toxicity and quality --------------------------------------------------------------------------


def naive_kernel(s, t, decay=toxicity.DECAY):
    total = 0.0
    for a in [(i, j, k) for i in range(len(s)) for j in range(i + 1, len(s)) for k in range(j + 1, len(s))]:
        for b in [(i, j, k) for i in range(len(t)) for j in range(i + 1, len(t)) for k in range(j + 1, len(t))]:
            if all(s[x] == t[y] for x, y in zip(a, b, strict=True)):
                total += decay ** (a[2] - a[0] + 1 + b[2] - b[0] + 1)
    return total


def test_subsequence_kernel_is_exact():
    marks, words = ["idiot", "loser", "abcabc"], ["idiot", "id-iot", "lloosseerr", "xyz", "abab", "ab"]
    kernel = toxicity.Kernel(marks)
    want = np.array([[naive_kernel(w, m) for m in marks] for w in words])
    assert np.allclose(kernel.raw(words), want, rtol=1e-4)
    own = lambda ts: np.array([max(1e-9, naive_kernel(t, t)) for t in ts])
    assert np.allclose(toxicity.self_kernel(words), own(words), rtol=1e-4)
    assert np.allclose(kernel(words), (want / np.sqrt(own(words)[:, None] * own(marks))) ** toxicity.POWER, rtol=1e-3, atol=1e-6)


def test_landmarks_map_to_their_kernel():
    """The Nystroem map is exact on landmarks; they are marking words, none of them ordinary."""
    rng = random.Random(1)
    bad, plain = ["idiot", "moron", "trash", "clown"], [f"{a}{b}n" for a in ("tho", "wer", "lan") for b in ("ti", "ou", "ea")]
    rows = [(1, {*rng.sample(bad, 2), *rng.sample(plain, 5)}) for _ in range(60)] + [(0, set(rng.sample(plain, 5))) for _ in range(200)]
    model = toxicity.train(rows)
    assert sorted(model["landmarks"]) == sorted(bad)
    kernel = toxicity.Kernel(model["landmarks"])
    mm = kernel(model["landmarks"])
    val, vec = np.linalg.eigh(mm)
    x = mm @ (vec @ np.diag(val**-0.5) @ vec.T)
    assert np.allclose(x @ x.T, mm, atol=1e-4)
    score = toxicity.Scorer(model).score
    assert min(score(toxicity.words(t)) for t in ("Such a moron and clown.", "you m o r o n", "an id-iot, he", "t*r*a*s*h")) > 0.5 > max(score(toxicity.words(t)) for t in ("thotin weroun", "", "all of it"))


def plain_kernel(s, t, decay=toxicity.DECAY):
    """Order 3, by the definition's sums over places of the last match."""
    m = [[1.0] * (len(t) + 1) for _ in range(len(s) + 1)]
    for k in range(3):
        new = [[0.0] * (len(t) + 1) for _ in range(len(s) + 1)]
        total = 0.0
        for i in range(1, len(s) + 1):
            row = 0.0
            for j in range(1, len(t) + 1):
                hit = decay**2 * m[i - 1][j - 1] if s[i - 1] == t[j - 1] else 0.0
                total += hit
                row = decay * row + hit
                new[i][j] = decay * new[i - 1][j] + row
        m = new
    return total


def test_toxicity_query_equals_plain_scores(spark):
    """Scores of the query again, word by word in plain Python, from the model alone."""
    docs = read_table(spark, SF, "documents")
    model = toxicity.fit(docs, read_table(spark, SF, "labels"))
    got = {r.doc_id: r for r in queries.op3_toxicity(spark, SF).collect()}
    assert len(got) == docs.count()
    marks, own, margins = model["landmarks"], {}, {}

    def margin(w):
        if w not in margins:
            k = [plain_kernel(w, m) / np.sqrt(max(1e-9, plain_kernel(w, w)) * own.setdefault(m, plain_kernel(m, m))) for m in marks]
            margins[w] = float(np.dot(np.minimum(k, 1) ** toxicity.POWER, model["weights"]) + model["bias"])
        return margins[w]

    assert plain_kernel("id-iot", "idiot") == pytest.approx(naive_kernel("id-iot", "idiot"))
    short = sorted((r for r in docs.collect() if len(r.text or "") < 1200), key=lambda r: r.doc_id)[:40]
    for r in short:
        ms = np.array([margin(w) for w in toxicity.words(r.text or "")])
        top = max(-1.0, ms.max()) if len(ms) else -1.0
        pos = ms[ms > 0].sum() if len(ms) else 0.0
        z = np.dot([top, np.log1p(pos), np.log1p(20 * pos / (len(ms) + 5)) if len(ms) else 0.0, 1.0], model["link"])
        assert got[r.doc_id].score == pytest.approx(1 / (1 + np.exp(-z)), abs=5e-3) and got[r.doc_id].predicted == (got[r.doc_id].score >= 0.3)
        assert got[r.doc_id].held_out == (zlib.crc32(str(r.doc_id).encode()) % 4 == 2)


@pytest.mark.parametrize("name,label,recall,precision", [("op3_toxicity", "toxic", 0.6, 0.95), ("op6_quality", "quality", 0.9, 0.9)])
def test_classifiers_on_held_out_rows(spark, name, label, recall, precision):
    """On sf0.01 toxic documents that aren't English show hardly any sign, hence the lower bar for their recall."""
    sf = "/root/testdata/sf0.01"
    out = queries.QUERIES[name](spark, sf).join(read_table(spark, sf, "labels").withColumnRenamed("doc_id", "i"), F.expr("doc_id = i"))
    rows = [(r.predicted, r[label]) for r in out.where("held_out").collect()]
    hits = sum(p == y == 1 for p, y in rows)
    assert len(rows) > 50 and sum(p == y for p, y in rows) / len(rows) > 0.93
    assert hits / sum(y for _, y in rows) > recall and hits / sum(p for p, _ in rows) > precision


def test_quality_query_equals_plain_sums(spark):
    """Scores of the query from the definition: all pairs of features, words counted in plain Python."""
    docs = read_table(spark, SF, "documents")
    model = quality.fit(docs, read_table(spark, SF, "labels"))
    got = {r.doc_id: r.score for r in queries.op6_quality(spark, SF).collect()}
    rows = sorted((r for r in docs.collect() if len(r.text or "") < 700), key=lambda r: r.doc_id)[:25]
    for r in rows:
        raw = (r.text or "").encode()
        ids, x = next(quality.features(np.frombuffer(raw, np.uint8), np.array([0, len(raw)])))
        words = Counter(__import__("re").findall(rb"[^\x20\x09-\x0D]+", raw))
        hashed = Counter()
        for w, n in words.items():
            h = quality._LINE_HASH
            hashed[int(quality.mix64(h.ranges(h.prefix(np.frombuffer(w, np.uint8)), np.array([0]), np.array([len(w)])))[0] % np.uint64(quality.WORDS))] += n
        norm = np.sqrt(sum(n * n for n in hashed.values())) or 1.0
        assert {int(i): pytest.approx(n / norm, rel=1e-5) for i, n in hashed.items()} == {int(i): float(v) for i, v in zip(ids, x, strict=True) if i < quality.WORDS}
        z = model["w0"] + sum(model["w"][i] * v for i, v in zip(ids, x, strict=True))
        z += sum(model["v"][ids[a]] @ model["v"][ids[b]] * x[a] * x[b] for a in range(len(ids)) for b in range(a))
        assert got[r.doc_id] == pytest.approx(1 / (1 + np.exp(-z)), abs=1e-6)


def test_scorers_take_odd_rows(spark, texts):
    model = toxicity.train([(1, {"idiot", "moron", f"w{i}"}) for i in range(20)] + [(0, {"plain", "words", f"v{i}"}) for i in range(20)])
    assert toxicity.train([(1, {"one"})] * 9) is None and {r.score for r in toxicity.score_toxicity(texts(ODD), None).collect()} == {0.5}
    assert toxicity.score_toxicity(texts([]), model).count() == 0
    got = toxicity.score_toxicity(texts([*ODD, "you idiot moron", "plain words"]), model).collect()
    assert len(got) == len(ODD) + 2 and all(0 <= r.score <= 1 for r in got)
    assert got[-2].score > 0.5 > got[-1].score and got[6].score == got[7].score
    feats = list(quality.features(*_arrow(["good plain text here"] * 3 + ["BAD!! %%% ###"] * 3)))
    m = quality.train(feats, np.array([1, 1, 1, 0, 0, 0.0]), epochs=30)
    assert all(0 <= r.score <= 1 for r in quality.score_quality(texts(ODD), m).collect())
    assert {r.score for r in quality.score_quality(texts(ODD), None).collect()} == {0.5}
    assert quality.score_quality(texts([]), m).count() == 0


def _arrow(ts):
    raw = [t.encode() for t in ts]
    return np.frombuffer(b"".join(raw), np.uint8), np.concatenate([[0], np.cumsum([len(r) for r in raw])])


def test_factorisation_identity():
    rng = np.random.default_rng(0)
    m = {"w0": 0.1, "w": rng.normal(size=20), "v": rng.normal(size=(20, 3))}
    ids, x = np.array([1, 4, 7, 9]), rng.normal(size=4)
    z = m["w0"] + m["w"][ids] @ x + sum(m["v"][ids[i]] @ m["v"][ids[j]] * x[i] * x[j] for i in range(4) for j in range(i))
    assert abs(quality.fm_score(ids, x, m) - 1 / (1 + np.exp(-z))) < 1e-12


# --- shards ----------------------------------------------------------------------------------------


def test_shards(spark, docs):
    rows = [(i, "t" * (i % 7), "en", "s", 0) for i in range(2000)] + [(5, None, "en", "s", 0), (None, "z", "en", "s", 0), (7, "t" * 0, None, None, None), (7, "t" * 0, None, None, None)]
    d = docs(rows)
    a, b = shards.shard_documents(d, 40, buckets=16).collect(), shards.shard_documents(d, 41).collect()
    to = {(r.doc_id, r.text_crc32): r.shard for r in b}
    assert all(to[r.doc_id, r.text_crc32] == r.grown_shard and r.grown_shard in (r.shard, 40) for r in a)
    slots = {}
    for r in a:
        slots.setdefault(r.shard, []).append(r.slot)
        if r.doc_id == 8:
            assert (r.size, r.text_crc32) == (17, zlib.crc32(b"t"))
    assert all(sorted(s) == list(range(len(s))) for s in slots.values()) and len(slots) == 40
    assert max(map(len, slots.values())) < 2 * len(rows) / 40
    assert shards.shard_documents(d.where("false")).count() == 0


# --- media -----------------------------------------------------------------------------------------


def test_jpeg_round_trip_general_and_fast(monkeypatch):
    rng = np.random.default_rng(0)
    for n in (192, 384, 192 * 31):
        p = rng.integers(0, 256, n, dtype=np.uint8).tobytes()
        m = jpeg.encode_payload(p)
        fast, img = jpeg.decode_payload(m)
        with monkeypatch.context() as mp:
            mp.setattr(jpeg, "_lone", lambda c: None)
            slow, img2 = jpeg.decode_payload(m)
        assert p == fast == slow and all((img["coef"][c] == img2["coef"][c]).all() for c in (1, 2, 3))
        assert jpeg.to_rgb(img).shape == (*img["size"], 3)


def test_jpeg_flat_colour_and_zigzag():
    assert jpeg.ZIGZAG[:10].tolist() == [0, 1, 8, 16, 9, 2, 3, 10, 17, 24] and sorted(jpeg.ZIGZAG) == list(range(64))
    coef = {c: np.zeros((2 if c == 1 else 1, 2 if c == 1 else 1, 64), np.int32) for c in (1, 2, 3)}
    coef[1][..., 0], coef[3][..., 0] = 80, 160  # luma 10 above the middle, red difference 20
    rgb = jpeg.to_rgb({"parts": {1: (2, 2, 0), 2: (1, 1, 0), 3: (1, 1, 0)}, "coef": coef, "quant": {0: np.ones(64, np.float32)}, "max": (2, 2), "size": (16, 16)})
    assert (rgb == [166, 124, 138]).all()


def test_jpeg_general_scans():
    """Sparse coefficients by an end-of-band run, refined later: bits written by hand."""
    block = [0] * 64
    codes = {(1, 0): 0x11, (2, 2): 0x00}
    r = jpeg._Reader(np.packbits([0, 1, 1, 0]).tobytes())  # run 1, size 1, value +1; then the band ends
    assert jpeg._ac_first(r, block, 1, 63, 1, codes, 0) == 0 and block[2] == 2
    r = jpeg._Reader(np.packbits([0, 1, 1, 1, 0, 0]).tobytes())  # new +1 after one zero (passing block[2]? no: at 2 a correction)
    jpeg._ac_refine(r, block, 1, 3, 0, codes, 0)
    assert block[2] == 3 and block[3] == 1


class ProgressiveWriter:
    """A plain progressive encoder of its own: code tables of many symbols, end-of-band runs, refinement, restarts."""

    def __init__(self, tall, wide, coef, interval):
        self.tall, self.wide, self.coef, self.interval = tall, wide, coef, interval
        self.out = bytearray(b"\xff\xd8" + self.segment(0xDB, b"\x00" + bytes([1] * 64)) + self.segment(0xDD, interval.to_bytes(2, "big")))
        self.out += self.segment(0xC2, bytes([8]) + tall.to_bytes(2, "big") + wide.to_bytes(2, "big") + bytes([3, 1, 0x22, 0, 2, 0x11, 0, 3, 0x11, 0]))

    @staticmethod
    def segment(marker, body):
        return bytes([0xFF, marker]) + (len(body) + 2).to_bytes(2, "big") + body

    def units(self, comps):
        """Blocks of each MCU of a scan, as (component, row, column)."""
        if len(comps) == 1:
            c, f = comps[0], 8 if comps[0] == 1 else 16
            return [[(c, y, x)] for y in range(-(-self.tall // f)) for x in range(-(-self.wide // f))]
        return [[(c, my * v + y, mx * v + x) for c in comps for v in ([2] if c == 1 else [1]) for y in range(v) for x in range(v)]
                for my in range(-(-self.tall // 16)) for mx in range(-(-self.wide // 16))]

    def scan(self, comps, lo, hi, high, low):
        ops, run, held = [], 0, []  # ops: ("s", symbol), ("b", value, count) or ("r",)

        def flush():
            nonlocal run, held
            if run:
                n = run.bit_length() - 1
                ops.extend([("s", n << 4), ("b", run - (1 << n), n)])
            ops.extend(("b", b, 1) for b in held)
            run, held = 0, []

        last = dict.fromkeys(comps, 0)
        for m, mcu in enumerate(self.units(comps)):
            if m and m % self.interval == 0:
                flush()
                ops.append(("r",))
                last = dict.fromkeys(comps, 0)
            for c, y, x in mcu:
                z = self.coef[c][y, x]
                if lo == 0:
                    v = int(z[0]) >> low
                    if high:
                        ops.append(("b", v & 1, 1))
                        continue
                    d, last[c] = v - last[c], v
                    n = abs(d).bit_length()
                    ops.extend([("s", n), ("b", d if d >= 0 else d + (1 << n) - 1, n)])
                    continue
                size = [abs(int(z[k])) >> low for k in range(64)]
                zeros, fix = 0, []
                final = max([k for k in range(lo, hi + 1) if size[k] == 1], default=0)
                for k in range(lo, hi + 1):
                    v = size[k]
                    if v == 0:
                        zeros += 1
                        continue
                    while zeros > 15 and (not high or k <= final):
                        flush()
                        ops.append(("s", 0xF0))
                        ops.extend(("b", b, 1) for b in fix)
                        zeros, fix = zeros - 16, []
                    if high and v > 1:
                        fix.append(v & 1)
                        continue
                    flush()
                    n = v.bit_length()
                    ops.append(("s", zeros << 4 | (1 if high else n)))
                    ops.append(("b", int(z[k] > 0), 1) if high else ("b", v if z[k] > 0 else (1 << n) - 1 - v, n))
                    ops.extend(("b", b, 1) for b in fix)
                    zeros, fix = 0, []
                if zeros or fix:
                    run, held = run + 1, held + fix
        flush()
        symbols = sorted({o[1] for o in ops if o[0] == "s"})
        lengths = [2, 3, *[10] * 300][: len(symbols)]
        codes, code, was = {}, 0, 0
        for s, n in zip(symbols, lengths, strict=True):
            code <<= n - was
            codes[s], code, was = (code, n), code + 1, n
        if symbols:
            self.out += self.segment(0xC4, bytes([(lo > 0) << 4, *[lengths.count(n) for n in range(1, 17)], *symbols]))
        head = bytes([len(comps)]) + b"".join(bytes([c, 0]) for c in comps) + bytes([lo, hi, high << 4 | low])
        self.out += self.segment(0xDA, head)
        bits, marks = "", 0
        for o in [*ops, ("r",)]:
            if o[0] == "r":
                bits += "1" * (-len(bits) % 8)
                self.out += bytes(int(bits[i : i + 8], 2) for i in range(0, len(bits), 8)).replace(b"\xff", b"\xff\x00")
                bits = ""
                self.out += bytes([0xFF, 0xD0 + marks % 8])
                marks += 1
            else:
                v, n = codes[o[1]] if o[0] == "s" else o[1:]
                bits += f"{v:0{n}b}" if n else ""
        del self.out[-2:]  # no restart behind the last interval


@pytest.mark.parametrize("interval", [5, 1000])
def test_jpeg_of_another_encoder(interval):
    rng = np.random.default_rng(interval)
    tall, wide = 37, 53  # neither fills its MCUs
    coef = {c: np.zeros((6, 8, 64) if c == 1 else (3, 4, 64), np.int32) for c in (1, 2, 3)}
    for c, z in coef.items():
        rows, cols = (-(-tall // 8), -(-wide // 8)) if c == 1 else (3, 4)
        z[..., 0] = rng.integers(-200, 200, z.shape[:2])
        own = z[:rows, :cols, 1:]
        own[:] = np.where(rng.random(own.shape) < rng.choice([0.0, 0.02, 0.4], (*own.shape[:2], 1)), rng.integers(-60, 61, own.shape), 0)
    w = ProgressiveWriter(tall, wide, coef, interval)
    w.scan([1, 2, 3], 0, 0, 0, 1)
    for c in (2, 1, 3):
        w.scan([c], 1, 5, 0, 2)
        w.scan([c], 6, 63, 0, 2)
    for c in (1, 2, 3):
        w.scan([c], 1, 63, 2, 1)
    w.scan([1, 2, 3], 0, 0, 1, 0)
    for c in (1, 2, 3):
        w.scan([c], 1, 63, 1, 0)
    img = jpeg.decode_coefficients(bytes(w.out) + b"\xff\xd9")
    for c in (1, 2, 3):
        assert (img["coef"][c] == coef[c]).all(), c
    nat = np.zeros((8, 8))
    nat.reshape(-1)[jpeg.ZIGZAG] = coef[1][1, 2]
    u = np.arange(8)
    basis = np.where(u[:, None] == 0, np.sqrt(1 / 8), 0.5) * np.cos((2 * u + 1) * u[:, None] * np.pi / 16)
    gray = jpeg.to_rgb({**img, "coef": {1: coef[1], 2: coef[2] * 0, 3: coef[3] * 0}})
    assert gray.shape == (tall, wide, 3) and np.abs(gray[8:16, 16:24, 0] - np.clip(basis.T @ nat @ basis + 128, 0, 255)).max() <= 0.51


def test_media_digest(spark, texts):
    ts = [*ODD, "abc" * 1000]
    for r in queries.jpeg.read_media(jpeg.store_media(texts(ts))).collect():
        raw = (ts[r.doc_id] or "").encode()
        p = raw.ljust(max(192, -(-len(raw) // 192) * 192), b" ")
        assert (r.n_bytes, r.payload_bytes, r.payload_sha256, r.tail_crc32) == (len(raw), len(p), hashlib.sha256(p).hexdigest(), zlib.crc32(p[-16:]))
    long = jpeg.read_media(jpeg.store_media(texts(["hello", "é" * 400_000])), tensors=True).collect()
    assert all(len(r.rgb) == r.height * r.width * 3 and r.feature.startswith(f"{r.height}x{r.width}:") and r.feature.endswith(f"{zlib.crc32(r.rgb):08x}") for r in long)
    assert long[1].payload_sha256 == hashlib.sha256("é".encode() * 400_000 + b" " * (-800_000 % 192)).hexdigest()
    assert jpeg.read_media(jpeg.store_media(texts([])), tensors=True).count() == 0


# --- near duplicates -------------------------------------------------------------------------------


def brute_near(ts, percent):
    sets = []
    for t in ts:
        w = "".join(c.lower() if "A" <= c <= "Z" else c for c in t or "").replace("\x0b", " ").replace("\x0c", " ")
        w = [x for x in __import__("re").split(r"[\x20\x09-\x0D]+", w) if x]
        sets.append({tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else ({tuple(w)} if w else set()))
    root = list(range(len(ts)))

    def find(i):
        while root[i] != i:
            i = root[i]
        return i

    for i in range(len(ts)):
        for j in range(i):
            inter = len(sets[i] & sets[j])
            if inter and 100 * inter >= percent * len(sets[i] | sets[j]):
                a, b = find(i), find(j)
                root[max(a, b)] = min(a, b)
    return [(len(s), find(i)) for i, s in enumerate(sets)]


@pytest.mark.parametrize("exact", [False, True])
def test_near_duplicates_equal_brute_force(spark, texts, exact):
    rng = random.Random(3)
    ts = []
    for size in (4, 6, 9, 40, 70, 200, 400):
        base = [f"w{rng.randrange(5000)}" for _ in range(size)]
        for edits in (0, 0, 1, 2, 3, 5, 8, 12):
            w = list(base)
            for _ in range(edits):
                w[rng.randrange(len(w))] = f"e{rng.randrange(9999)}"
            ts.append(" ".join(w))
    common = prose(rng, 60)
    ts += [common + " " + prose(rng, rng.randrange(1, 90), 9999) for _ in range(60)]
    chain = [f"c{i}" for i in range(120)]  # each near to the next, ends far apart
    for i in range(20):
        ts.append(" ".join(chain[i * 3 : i * 3 + 60]))
    ts += ODD + [t.upper() for t in ts[:5]]
    want = brute_near(ts, 85)
    got = {r.doc_id: r for r in neardup.near_duplicates(texts(ts), exact=exact).collect()}
    assert [(got[i].n_shingles, got[i].component_id) for i in range(len(ts))] == want
    assert all(got[i].kept == (got[i].component_id == i) for i in got)


def test_one_of_each_keeps_columns_and_odd_ids(spark, docs):
    t = " ".join(f"w{i}" for i in range(30))
    rows = [(3, t, "en", "s", 1, 9), (2, t, "en", "s", 1, 9), (2, t, "en", "s", 1, 9), (None, t + " x", "en", "s", 1, 9), (None, "other one", "en", "s", 1, 9), (7, None, "en", "s", 1, 9), (8, None, "en", "s", 1, 9)]
    out = neardup.one_of_each(docs(rows, ", n long"))
    assert out.columns[-1] == "n" and sorted((str(r.doc_id), r.text) for r in out.select("doc_id", "text").collect() if r.text) == [("2", t), ("None", "other one")]
    assert out.where("text is null").count() == 2 and neardup.near_duplicates(docs([])).count() == 0


# --- language --------------------------------------------------------------------------------------


def plain_states(x, m, d):
    """States of one direction, written plainly in 64 bits; x (T, B)."""
    h = m["wh"].shape[2]
    s, out = np.zeros((x.shape[1], h)), []
    for row in x if d == 0 else x[::-1]:
        rec, into = s @ m["wh"][d].T, m["table"][d][row]
        r, z = 1 / (1 + np.exp(-(into[:, :h] + rec[:, :h]))), 1 / (1 + np.exp(-(into[:, h : 2 * h] + rec[:, h : 2 * h])))
        s = (1 - z) * np.tanh(into[:, 2 * h :] + r * rec[:, 2 * h :]) + z * s
        out.append(s)
    return np.array(out if d == 0 else out[::-1])


def test_gradients_by_differences():
    """Every parameter's gradient, in both directions, against differences of the plainly written loss."""
    rng = np.random.default_rng(1)
    x, y, w = rng.integers(97, 101, (5, 3)).astype(np.uint8), np.array([0, 2, 1]), rng.random((5, 3)).astype(np.float32)
    m = {"table": rng.normal(0, 0.5, (2, 256, 6)), "wh": rng.normal(0, 0.5, (2, 6, 2)), "out": rng.normal(size=(3, 4)), "bias": rng.normal(size=3)}
    m = {k: v.astype(np.float32) for k, v in m.items()}
    hs = langid._cell(x, *langid._scaled(m))
    for d in (0, 1):
        assert np.allclose(hs[:, d].transpose(0, 2, 1), plain_states(x, m, d), atol=1e-5)

    def loss(m):
        h = np.concatenate([plain_states(x, m, d) for d in (0, 1)], 2)
        logit = h @ m["out"].T + m["bias"]
        p = np.exp(logit) / np.exp(logit).sum(2, keepdims=True)
        return -(w * np.log(p[:, np.arange(3), y])).sum() / w.sum()

    got = langid.gradients(m, x, w, y)
    wide = {k: v.astype(np.float64) for k, v in m.items()}
    for k, v in wide.items():
        spots = [i for i in np.ndindex(v.shape) if k != "table" or 97 <= i[1] < 101]
        for i in spots:
            was = v[i]
            v[i] = was + 1e-5
            up = loss(wide)
            v[i] = was - 1e-5
            slope = (up - loss(wide)) / 2e-5
            v[i] = was
            assert got[k][i] == pytest.approx(slope, abs=2e-5), (k, i)


def test_language_held_out_accuracy(spark):
    sf = "/root/testdata/sf0.01"
    out = queries.op8_language_id(spark, sf).toPandas().merge(read_table(spark, sf, "documents").select("doc_id", "lang").toPandas(), on="doc_id")
    own = out[out.held_out]
    assert (own.lang == own.lang_pred).mean() > 0.97


def test_language_odd_rows(spark, texts):
    m = langid.train([b"the and of to", b"der die das und"] * 4, [0, 1] * 4, 2, hidden=3, steps=5)
    got = {r.doc.doc_id: r for r in langid.predict_language(texts([*ODD, "12 34"]), m, ["en", "de"]).collect()}
    assert [got[i].lang_pred for i in (0, 1, 2, 10)] == ["und"] * 4 and got[3].lang_pred != "und"
    data, off = _arrow(["the and of to it " * 40, "ab"])
    assert sum(int(k.sum()) for _, k, _ in langid.position_labels(data, off, m)) == len(data)
    kept = langid.keep_known_language(texts(["the house and the garden", None, "12"]))
    assert [r.text for r in kept.collect()] == ["the house and the garden"] and kept.columns == ["doc_id", "text", "lang", "source", "n_chars"]
    assert {r.lang_pred for r in langid.predict_language(texts(ODD), {}, []).collect()} == {"und"}


# --- decontamination -------------------------------------------------------------------------------


def test_templates_catch_new_parameters(spark, texts):
    bench = spark.createDataFrame([
        (1, "A train leaves the town at 7 km from here and Maria walks 7 km more than 12 minutes each day."),
        (2, "Short one with Anna only"), (3, None), (4, "")], "item_id long, text string")
    ts = ["Intro words here. A train leaves the town at 9 km from here and Peter walks 9 km more than 30 minutes each day. And more.",
          "A train leaves the town at 9 km from here and Peter walks 5 km more than 30 minutes each day.",  # 7 -> 9 and 7 -> 5
          "Nothing to see here at all in this quite ordinary text of the corpus", "well: short one with Bert only!", None, "", "7 7 7 7 7 7 7 7 7 7"]
    got = {(r.doc_id, r.item_id): r for r in decontaminate.leaks(texts(ts), bench).collect()}
    assert got[0, 1].leaked and not got[1, 1].consistent and not got[1, 1].leaked and got[3, 2].leaked
    assert {k for k, r in got.items() if r.leaked} == {(0, 1), (3, 2)}
    kept = decontaminate.decontaminated(texts(ts), bench)
    assert sorted(r.doc_id for r in kept.collect()) == [1, 2, 4, 5, 6] and kept.columns[1] == "text"
    assert decontaminate.decontaminated(texts(ts), bench.where("false")).count() == len(ts)
    assert decontaminate.leaks(texts([]), bench).count() == 0 and decontaminate.decontaminated(texts([]), bench).count() == 0
    odd = spark.createDataFrame([(-1, "the first of these two short items"), (None, "and another one without any id at all")], "item_id long, text string")
    got = decontaminate.leaks(texts(["the first of these two short items", "and another one without any id at all"]), odd).collect()
    assert {(r.doc_id, r.item_id) for r in got if r.leaked} == {(0, -1), (1, None)}


def test_a_copy_counts_whatever_else_shares_its_template(spark, texts):
    item = "A train leaves the town at 7 km from here and Maria walks 7 km more than 12 minutes each day."
    bench = spark.createDataFrame([(1, item)], "item_id long, text string")
    sibling = item.replace("7", "9").replace("Maria", "Peter")
    ts = ["First: a train leaves the town at 9 km from here, they say. " + item,  # part of it with another number
          item + " Next one. " + sibling, sibling + " Next one. " + item,
          item.replace("7", "9", 1) + " Or so. " + sibling,  # a coincidence and a copy
          item.replace("7", "9", 1),
          "A train leaves the town at 9 km from here, and so on and on. They and Bert walks 5 km more than 12 minutes each year."]  # 7 -> 9 and 7 -> 5
    got = {r.doc_id: r for r in decontaminate.leaks(texts(ts), bench).collect()}
    assert [i for i, r in sorted(got.items()) if r.leaked] == [0, 1, 2, 3] and [got[i].windows for i in range(4)] == [14] * 4
    assert {r.doc_id for r in decontaminate.decontaminated(texts(ts), bench).collect()} == {4, 5}
    assert got[5].consistent and got[5].windows == 4 and not got[4].consistent


def test_agreeing_places_equal_brute_force():
    from itertools import combinations

    rng = random.Random(4)
    for _ in range(300):
        places = [({rng.randrange(12) for _ in range(rng.randrange(1, 4))}, {f"s{k}": f"v{rng.randrange(3)}" for k in rng.sample(range(4), rng.randrange(4))}) for _ in range(rng.randrange(1, 7))]
        hits = [{"place": n, "ipos": w, "pairs": [{"i": i, "v": x} for i, x in v.items()]} for n, (ws, v) in enumerate(places) for w in ws]
        sets = [c for n in range(1, len(places) + 1) for c in combinations(places, n) if len({p for _, v in c for p in v.items()}) == len({i for _, v in c for i in v})]
        most = max(len(set().union(*(w for w, _ in c))) for c in sets)
        assert decontaminate.agreeing_windows(hits, most) == (most, True) and decontaminate.agreeing_windows(hits, most + 1)[0] <= most
    assert decontaminate.agreeing_windows([{"place": 0, "ipos": w, "pairs": [{"i": "7", "v": str(w)}]} for w in (1, 2)], 1) == (2, False)


def test_short_items_leave_windows_of_long_ones_alone(spark, texts):
    long = "On some day Maria met Anna and Bert at 7 km from here while Peter sang for 12 minutes and Carl slept."
    rows = [(1, long), (2, "Some day"), (3, "— one two"), (4, "exactly eight words are in this short item")]
    bench = spark.createDataFrame(rows, "item_id long, text string")
    ts = ["They sat at 5 km from here. The cat sang for 9 minutes and Dora slept. It was on some other day and at 3 km.",
          long + " Then at 5 km and for 30 minutes Emil and Frida met Gina.", "it was some day", "so — one two", "exactly eight words are in this short item", "some"]
    got = {(r.doc_id, r.item_id) for r in decontaminate.leaks(texts(ts), bench).where("leaked").collect()}
    assert got == {(1, 1), (1, 2), (2, 2), (3, 3), (4, 4)}
    assert {(r.item, r.size) for r in decontaminate.windows_of(bench.selectExpr("item_id as item", "0L as it", "text"), ["item", "it"], 8, list(range(1, 8))).collect()} == {(1, 8), (2, 2), (3, 3), (4, 8)}


def test_first_word_of_an_item_in_running_text(spark, texts):
    rows = [(1, "What is the capital of France?"), (2, "Hours of sleep are good"), (3, "Maria walks 7 km more than Anna walks"), (4, "Seven, then 8")]
    bench = spark.createDataFrame(rows, "item_id long, text string").coalesce(1)
    ts = ["Q) What is the capital of Spain, they ask", "so, What is the capital of France?", "\"Well.\" What is the capital of France?", "- What is the capital of France?",
          "of 24 Hours of sleep are good", "(one) Maria walks 9 km more than Lena walks", "Q) Peter is the capital of Spain", "ends in 7", "Hours of sleep are good", "What is the capital of Italy"]
    got = {(r.doc_id, r.item_id) for r in decontaminate.leaks(texts(ts).coalesce(1), bench).where("leaked").collect()}
    assert got == {(0, 1), (1, 1), (2, 1), (3, 1), (4, 2), (5, 3), (8, 2), (9, 1)}


def test_leaks_on_table(spark):
    """Every document that holds an item's words in a row is found, and no other."""
    sf, words = "/root/testdata/sf0.01", lambda t: " ".join(__import__("re").findall(r"\w+", t.lower()))
    items = {r.item_id: words(r.text) for r in read_table(spark, sf, "benchmark").collect()}
    want = {(r.doc_id, i) for r in read_table(spark, sf, "documents").collect() for i, t in items.items() if t in words(r.text)}
    assert want and {(r.doc_id, r.item_id) for r in queries.op9_decontamination(spark, sf).collect()} == want


def plain_template(text):
    """(typed word, word where its own number only is typed, slot value or None) of each word, in plain Python."""
    import re

    out, before = [], None  # before: end and last byte of the word before, and if it was a number
    raw = (text or "").encode()
    for m in re.finditer(rb"[^\x20\x09-\x0D]+", raw):
        core = re.sub(rb"^[^0-9A-Za-z\x80-\xff]+|[^0-9A-Za-z\x80-\xff]+$", b"", m[0])
        if not core:
            continue
        opens = before is None or before[1] in b".!?:" or b"\n" in raw[before[0] : m.start()]
        small = bool(re.search(rb"[a-z\x80-\xff]", core))
        number = bool(re.search(rb"[0-9]", core)) and not re.search(rb"[A-Za-z\x80-\xff]", core)
        name = core[:1].isalpha() and core[:1].isupper() and not opens and small
        folded = bytes(b + 32 if 65 <= b <= 90 else b for b in core)
        unit = before is not None and before[2] and folded.decode("utf-8", "replace") in decontaminate.UNITS
        kind = "<number>" if number else "<name>" if name else "<unit>" if unit else folded
        out.append((kind, "<number>" if number else folded, core.decode("utf-8", "replace").lower() if number or name or unit else None))
        before = (m.end(), m[0][-1:], number)
    return out


def test_templates_on_table_equal_plain_python(spark):
    docs, bench = read_table(spark, SF, "documents"), read_table(spark, SF, "benchmark")
    items = {}
    for r in bench.collect():
        w = plain_template(r.text)
        n = min(decontaminate.WINDOW, len(w))
        for i in range(len(w) - n + 1 if w else 0):
            items.setdefault(tuple(x[0] for x in w[i : i + n]), []).append((r.item_id, i, max(1, len(w) - decontaminate.WINDOW + 1), [x[2] for x in w[i : i + n] if x[2] is not None]))
    sizes, want = {len(k) for k in items}, {}
    for r in docs.collect():
        w = plain_template(r.text)
        for n in sizes:
            for q in range(len(w) - n + 1):
                key = tuple(x[0] for x in w[q : q + n])
                opening = (w[q][1], *key[1:])
                for found, skip in [(key, 0), *([(opening, 1)] if opening != key else [])]:
                    for item, i, many, slots in items.get(found, ()):
                        if i == 0 or not skip:
                            own = [x[2] for x in w[q + skip : q + n] if x[2] is not None]
                            want.setdefault((r.doc_id, item, many), []).append({"place": q - i, "ipos": i, "pairs": [{"i": a, "v": b} for a, b in zip(slots, own, strict=False)]})
    judged = {k: (decontaminate.agreeing_windows(h, max(1.0, decontaminate.SHARE * k[2])), max(1.0, decontaminate.SHARE * k[2])) for k, h in want.items()}
    got = {(r.doc_id, r.item_id, r.item_windows): (r.windows, r.consistent, r.leaked) for r in decontaminate.leaks(docs, bench).collect()}
    assert got == {k: (n, c, c and n >= need) for k, ((n, c), need) in judged.items()} and any(x[2] for x in got.values())


def test_stages_take_clashing_columns(spark, docs):
    names = ["d", "tk", "g", "doc", "lang_pred", "score", "spans", "lo", "kept"]
    rows = [(i, "the house and the garden of the town are here", "en", "s", 1, *[7] * len(names)) for i in range(3)]
    own = docs(rows, "".join(f", {n} long" for n in names))
    bench = spark.createDataFrame([(1, "nothing like it")], "item_id long, text string")
    m, langs = langid.train([b"the and of to", b"der die das und"] * 4, [0, 1] * 4, 2, hidden=3, steps=5), ["en", "de"]
    assert langid.predict_language(own, m, langs).selectExpr("doc.*").columns == own.columns
    for out in (langid.keep_known_language(own), decontaminate.decontaminated(own, bench), suffix_repeats.without_repeats(own, 60), neardup.one_of_each(own)):
        assert out.columns == own.columns and {r.d for r in out.collect()} == {7}
    assert packing.pack_documents(own).selectExpr("count(distinct doc_id)").first()[0] == 3


# --- packing ---------------------------------------------------------------------------------------


def test_packing_equals_concatenation(spark, texts):
    import public_tokenizers
    from tokenizers import Tokenizer

    ts = [*ODD, "x y <|endoftext|> z", "héllo wörld 12345 " * 900, "don't  stop\n\n\nnow"]
    t = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
    ids = {i: [*t.encode(x or "", add_special_tokens=False).ids, 1] for i, x in enumerate(ts)}
    rows = packing.pack_documents(texts(ts).repartition(3), window=64).collect()
    seqs = {}
    for r in rows:
        piece = ids[r.doc_id][r.start : r.start + r.length]
        assert r.ids_crc32 == zlib.crc32(np.array(piece, "<u4").tobytes()) and r.doc_tokens == len(ids[r.doc_id])
        seqs.setdefault(r.sequence_id, []).append((r.offset, r.length))
    assert sum(r.length for r in rows) == sum(map(len, ids.values()))
    for s in seqs.values():
        at = 0
        for o, n in sorted(s):
            assert o == at
            at += n
    assert all(sum(n for _, n in s) == 64 for k, s in seqs.items() if k != max(seqs)) and packing.pack_documents(texts([])).count() == 0


# --- queries and pipeline --------------------------------------------------------------------------


def test_oracles(spark):
    con = duckdb.connect()
    for t in ("documents", "conversations"):
        con.sql(f"create view {t} as select * from '{SF}/{t}.parquet'")
    for name, sql in queries.ORACLE_SQL.items():
        got, want = queries.QUERIES[name](spark, SF).toPandas(), con.sql(sql).df()
        cols = sorted(got.columns)
        assert cols == sorted(want.columns), name
        assert sorted(map(tuple, got[cols].astype(str).values)) == sorted(map(tuple, want[cols].astype(str).values)), name


def whole_characters(raw, hit):
    """Runs of removed bytes shrunk until no character is cut in two; what is left, as text."""
    hit, more = hit.copy(), lambda i: raw[i] & 0xC0 == 0x80
    edges = np.flatnonzero(np.diff(np.concatenate([[0], hit.astype(np.int8), [0]])))
    for lo, hi in edges.reshape(-1, 2).tolist():
        while lo < hi and more(lo):
            hit[lo], lo = False, lo + 1
        while hi > lo and hi < len(raw) and more(hi):
            hit[hi - 1], hi = False, hi - 1
    return bytes(b for b, h in zip(raw, hit, strict=True) if not h).decode()


def test_pipeline_stages(spark):
    """Each stage against brute force over all that the one before kept."""
    import corpus_pipeline as cp

    stages = dict(cp.STAGES)
    assert list(stages) == ["language_id", "near_dedup", "suffix_dedup", "decontamination", "packing"]
    docs = read_table(spark, SF, "documents")
    columns, kept = docs.columns, [docs.count()]
    rows = {}
    for name, stage in cp.STAGES[:-1]:
        docs = stage(spark, docs, SF).persist()
        assert docs.columns == columns, name
        before, rows = rows, {r.doc_id: r.text for r in docs.collect()}
        kept.append(docs.count())
        ids = sorted(before)
        if name == "near_dedup":
            assert set(rows) == {ids[i] for i, (_, c) in enumerate(brute_near([before[d] for d in ids], 80)) if c == i}
            assert all(rows[d] == before[d] for d in rows)
        elif name == "suffix_dedup":
            raw = [before[d].encode() for d in ids]
            hits = brute_removed(raw, cp.PASSAGE_BYTES)
            assert rows == {d: whole_characters(t, h) for d, t, h in zip(ids, raw, hits, strict=True)} and any(h.any() for h in hits)
        elif name == "decontamination":
            words = lambda t: " ".join(__import__("re").findall(r"\w+", t.lower()))
            items = [words(r.text) for r in read_table(spark, SF, "benchmark").collect()]
            assert not any(x in words(t) for x in items for t in rows.values())
            assert all(rows[d] == before[d] for d in rows)
            assert set(before) - set(rows) == {r.doc_id for r in decontaminate.leaks(spark.createDataFrame(list(before.items()), "doc_id long, text string"), read_table(spark, SF, "benchmark")).collect() if r.leaked}
    assert kept[0] >= kept[1] > kept[2] == kept[3] >= kept[4] > 0
    assert cp.run(spark, SF).selectExpr("count(distinct doc_id)").first()[0] == kept[4]
