"""Toxicity: a bidirectional gated recurrent network with attention pooling over words, each read also by its characters.

A word's input is its own vector (for the frequent words of the training sample) and what a small bidirectional recurrent
network makes of its characters. A second one reads windows of 32 words, overlapping by half; attention pools its states,
and a logistic layer gives the window's score. A document's score is that of its highest window. Everything is numpy;
training runs on the driver on a bounded sample of labelled rows. In scoring, character states are made once for each
distinct word of a batch, and all windows of a batch, sorted by length, take each step together.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import id_and_text, text_slices

WINDOW, STRIDE, CHARS = 32, 16, 14
PART_STRIDES = 4096  # windows of a text that are read at a time
SAMPLE_TOXIC, SAMPLE_CLEAN = 900, 1300
_WORD = re.compile(r"\w+")
_PART = re.compile(r"[^\W_]+|_+")
_OOV = 0


def tokens(text: str) -> list[str]:
    """Words of at most CHARS characters. Longer runs are read at underscores and, what is still longer, in pieces that
    overlap by half, so that text without gaps is read whole."""
    words = _WORD.findall(text.lower())
    if max(map(len, words), default=0) <= CHARS:
        return words
    half, out = CHARS // 2, []
    for w in words:
        for p in [w] if len(w) <= CHARS else _PART.findall(w):
            out += [p[a : a + CHARS] for a in range(0, max(1, len(p) - half), half)]
    return out


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 0.5 * (np.tanh(0.5 * x) + 1)


def gru_forward(gates: np.ndarray, u: np.ndarray, mask: np.ndarray, back: bool):
    """States (steps, n, h) of a gated recurrent unit. gates: input part of reset, update, candidate; mask: (steps, n)."""
    steps, n, h3 = gates.shape
    h = h3 // 3
    state, out, kept = np.zeros((n, h), np.float32), np.zeros((steps, n, h), np.float32), []
    for t in range(steps - 1, -1, -1) if back else range(steps):
        rz = _sigmoid(gates[t, :, : 2 * h] + state @ u[:, : 2 * h])
        r, z = rz[:, :h], rz[:, h:]
        c = np.tanh(gates[t, :, 2 * h :] + (r * state) @ u[:, 2 * h :])
        m = mask[t][:, None]
        new = state + m * z * (c - state)
        kept.append((t, state, r, z, c, m))
        state = out[t] = new
    return out, kept


def gru_states(gates: np.ndarray, of: np.ndarray, u: np.ndarray, live: np.ndarray, back: bool) -> np.ndarray:
    """As gru_forward, for scoring: inputs are rows of `gates`, picked by `of` (steps, n); the first live[t] sequences have a
    step t, since they are sorted by falling length."""
    steps, n = of.shape
    h = u.shape[0]
    state, out = np.zeros((n, h), np.float32), np.zeros((steps, n, h), np.float32)
    for t in range(steps - 1, -1, -1) if back else range(steps):
        k = live[t]
        if not k:
            continue
        g, s = gates[of[t, :k]], state[:k]
        rz = _sigmoid(g[:, : 2 * h] + s @ u[:, : 2 * h])
        c = np.tanh(g[:, 2 * h :] + (rz[:, :h] * s) @ u[:, 2 * h :])
        s += rz[:, h:] * (c - s)
        out[t, :k] = s
    return out


def gru_backward(d_out: np.ndarray, kept, u: np.ndarray):
    """Gradients of gates and u."""
    steps, n, h = d_out.shape
    d_gates, d_u, d_state = np.zeros((steps, n, 3 * h), np.float32), np.zeros_like(u), np.zeros((n, h), np.float32)
    for t, state, r, z, c, m in reversed(kept):
        d_new = d_state + d_out[t]
        d_z = d_new * m * (c - state) * z * (1 - z)
        d_c = d_new * m * z * (1 - c * c)
        d_rs = d_c @ u[:, 2 * h :].T
        d_r = d_rs * state * r * (1 - r)
        d_rz = np.concatenate([d_r, d_z], axis=1)
        d_gates[t, :, : 2 * h], d_gates[t, :, 2 * h :] = d_rz, d_c
        d_u[:, : 2 * h] += state.T @ d_rz
        d_u[:, 2 * h :] += (r * state).T @ d_c
        d_state = d_new * (1 - m * z) + d_rs * r + d_rz @ u[:, : 2 * h].T
    return d_gates, d_u


@dataclass
class ToxicityModel:
    """Weights by name, known characters and words, and the scale and shift that turn a window's logit into a score."""

    weights: dict[str, np.ndarray]
    chars: dict[str, int]
    words: dict[str, int]
    scale: float = 1.0
    shift: float = 0.0
    memo: dict = field(default_factory=dict, repr=False)

    def __getstate__(self):
        return self.__dict__ | {"memo": {}}

    def spell(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Characters (CHARS, n) of each word, none of which is longer, and their numbers."""
        lens = np.fromiter(map(len, words), np.int64, len(words))
        get = self.chars.get
        flat = np.fromiter((get(c, _OOV) for w in words for c in w), np.int64, int(lens.sum()))
        out = np.zeros((len(words), CHARS), np.int64)
        out[np.arange(CHARS) < lens[:, None]] = flat
        return out.T, lens

    def word_gates(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Input parts of both word networks for distinct words; character states are computed in batches."""
        w = self.weights
        front, back = [], []
        for a in range(0, len(words), 8192):
            part = words[a : a + 8192]
            order = np.argsort([-min(len(x), CHARS) for x in part], kind="stable")
            spelled, lens = self.spell([part[i] for i in order])
            live = (np.arange(CHARS)[:, None] < lens).sum(1)
            f = gru_states(w["char"] @ w["cf_w"] + w["cf_b"], spelled, w["cf_u"], live, False)[lens - 1, np.arange(len(part))]
            b = gru_states(w["char"] @ w["cb_w"] + w["cb_b"], spelled, w["cb_u"], live, True)[0]
            x = np.empty((len(part), f.shape[1] * 2), np.float32)
            x[order] = np.concatenate([f, b], axis=1)
            x = np.concatenate([w["word"][[self.words.get(p, _OOV) for p in part]], x], axis=1)
            front.append(x @ w["wf_w"] + w["wf_b"])
            back.append(x @ w["wb_w"] + w["wb_b"])
        return np.concatenate(front).astype(np.float32), np.concatenate(back).astype(np.float32)

    def entries(self, words: list[str], memo_bytes: int) -> np.ndarray:
        """Row of each word in the gate tables, which grow by a batch's new words and start anew beyond memo_bytes."""
        memo, h3 = self.memo, self.weights["wf_w"].shape[1]
        if "at" not in memo or len(memo["at"]) * (8 * h3 + 200) > memo_bytes:  # both gate rows, the word and its place
            memo.update(at={}, front=np.zeros((1024, h3), np.float32), back=np.zeros((1024, h3), np.float32))
        at = memo["at"]
        new = [w for w in dict.fromkeys(words) if w not in at]
        if new:
            n = len(at)
            f, b = self.word_gates(new)
            while n + len(new) > len(memo["front"]):
                memo["front"], memo["back"] = (np.concatenate([memo[k], np.zeros_like(memo[k])]) for k in ("front", "back"))
            memo["front"][n : n + len(new)], memo["back"][n : n + len(new)] = f, b
            at.update(zip(new, range(n, n + len(new))))
        return np.fromiter(map(at.__getitem__, words), np.int64, len(words))

    def window_logits(self, of: np.ndarray, lens: np.ndarray) -> np.ndarray:
        """Logits of windows, sorted by falling length. of: (WINDOW, n) rows of the gate tables."""
        w = self.weights
        live = (np.arange(len(of))[:, None] < lens).sum(1)
        s = np.concatenate([gru_states(self.memo["front"], of, w["wf_u"], live, False), gru_states(self.memo["back"], of, w["wb_u"], live, True)], axis=2)
        a = np.tanh(s @ w["att_w"]) @ w["att_v"]
        a = np.where(np.arange(len(of))[:, None] < lens, a, np.float32(-1e9))
        a = np.exp(a - a.max(0))
        pooled = ((a / a.sum(0))[:, :, None] * s).sum(0)
        return pooled @ w["out_w"] + w["out_b"]

    def windows(self, split: list[list[str]], memo_bytes: int = 48 << 20) -> tuple[np.ndarray, np.ndarray]:
        """Logits of all overlapping windows of the word lists, and the number of each list."""
        n = np.fromiter(map(len, split), np.int64, len(split))
        flat = self.entries([w for s in split for w in s], memo_bytes)
        first = np.cumsum(n) - n
        count = np.maximum(1, -(-(n - WINDOW) // STRIDE) + 1)
        doc = np.repeat(np.arange(len(n)), count)
        start = (np.arange(len(doc)) - np.repeat(np.cumsum(count) - count, count)) * STRIDE
        lens = np.minimum(n[doc] - start, WINDOW)
        order = np.argsort(-lens, kind="stable")
        out = np.empty(len(doc), np.float32)
        for a in range(0, len(order), 2048):
            i = order[a : a + 2048]
            place = first[doc[i]] + start[i] + np.minimum(np.arange(WINDOW)[:, None], lens[i] - 1)
            out[i] = self.window_logits(flat[place], lens[i])
        return out, count

    def logits(self, texts: list[str], memo_bytes: int = 48 << 20) -> np.ndarray:
        """Highest window logit of each text; a text without words is read as one unknown word. The words of a long text
        are taken in parts that share the windows at their ends."""
        if not texts:
            return np.zeros(0, np.float32)
        part, parts, of = STRIDE * PART_STRIDES, [], []
        for i, t in enumerate(texts):
            words = tokens(t) or ["_"]
            for a in range(0, max(1, len(words) - WINDOW + STRIDE), part):
                parts.append(words[a : a + part + WINDOW - STRIDE])
                of.append(i)
        out = np.full(len(texts), -np.inf, np.float32)
        ends = np.cumsum([len(p) for p in parts])
        at = 0
        while at < len(parts):
            end = max(at + 1, int(np.searchsorted(ends, ends[at] - len(parts[at]) + 4 * part, side="right")))
            z, count = self.windows(parts[at:end], memo_bytes)
            np.maximum.at(out, of[at:end], np.maximum.reduceat(z, np.cumsum(count) - count))
            at = end
        return out

    def scores(self, texts: list[str], memo_bytes: int = 48 << 20) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.scale * self.logits(texts, memo_bytes).astype(np.float64) + self.shift, -30, 30)))


def new_model(texts: list[str], min_docs: int = 8, chars: int = 200, dim_char: int = 8, h_char: int = 8, dim_word: int = 8, h_word: int = 8, seed: int = 11) -> ToxicityModel:
    from collections import Counter

    seen, letters = Counter(), Counter()
    for t in texts:
        seen.update(set(tokens(t)))
    for w, c in seen.items():
        for x in w:
            letters[x] += c
    words = {w: i + 1 for i, w in enumerate(sorted(w for w, c in seen.items() if c >= min_docs))}
    known = {c: i + 1 for i, (c, _) in enumerate(sorted(letters.items(), key=lambda x: (-x[1], x[0]))[:chars])}
    rng = np.random.default_rng(seed)

    def draw(*shape, scale=None):
        return rng.normal(0, scale or 1 / np.sqrt(shape[0]), shape).astype(np.float32)

    w = {"char": draw(len(known) + 1, dim_char, scale=0.5), "word": draw(len(words) + 1, dim_word, scale=0.05)}
    for net, size, h in (("cf", dim_char, h_char), ("cb", dim_char, h_char), ("wf", dim_word + 2 * h_char, h_word), ("wb", dim_word + 2 * h_char, h_word)):
        w |= {f"{net}_w": draw(size, 3 * h), f"{net}_u": draw(h, 3 * h), f"{net}_b": np.zeros(3 * h, np.float32)}
    w |= {"att_w": draw(2 * h_word, h_word), "att_v": draw(h_word, scale=0.5), "out_w": draw(2 * h_word, scale=0.5), "out_b": np.zeros(1, np.float32)}
    return ToxicityModel(w, known, words)


def gradients(m: ToxicityModel, windows: list[list[str]], weight: np.ndarray, target: np.ndarray) -> tuple[float, dict[str, np.ndarray]]:
    """Weighted logistic loss of windows and its gradient by each weight."""
    w, g = m.weights, {}
    lens = np.fromiter(map(len, windows), np.int64, len(windows))
    vocab: dict[str, int] = {}
    flat = np.array([vocab.setdefault(x, len(vocab)) for s in windows for x in s])
    of = np.zeros((WINDOW, len(windows)), np.int64)
    inside = np.arange(WINDOW)[:, None] < lens
    of.T[inside.T] = flat
    spelled, clens = m.spell(list(vocab))
    cmask = (np.arange(CHARS)[:, None] < clens).astype(np.float32)
    cin = w["char"][spelled]
    cf, cf_kept = gru_forward(cin @ w["cf_w"] + w["cf_b"], w["cf_u"], cmask, False)
    cb, cb_kept = gru_forward(cin @ w["cb_w"] + w["cb_b"], w["cb_u"], cmask, True)
    ids = np.array([m.words.get(x, _OOV) for x in vocab])
    h = cf.shape[2]
    x = np.concatenate([w["word"][ids], cf[-1], cb[0]], axis=1)
    mask = inside.astype(np.float32)
    wf, wf_kept = gru_forward((x @ w["wf_w"] + w["wf_b"])[of], w["wf_u"], mask, False)
    wb, wb_kept = gru_forward((x @ w["wb_w"] + w["wb_b"])[of], w["wb_u"], mask, True)
    s = np.concatenate([wf, wb], axis=2)
    hidden = np.tanh(s @ w["att_w"])
    a = np.where(inside, hidden @ w["att_v"], np.float32(-1e9))
    a = np.exp(a - a.max(0))
    a /= a.sum(0)
    pooled = (a[:, :, None] * s).sum(0)
    z = pooled @ w["out_w"] + w["out_b"]
    p = _sigmoid(z)
    loss = float((weight * (np.logaddexp(0, z) - target * z)).sum())
    d_z = (weight * (p - target)).astype(np.float32)
    g["out_w"], g["out_b"] = pooled.T @ d_z, d_z.sum(keepdims=True)
    d_pool = d_z[:, None] * w["out_w"]
    d_s = a[:, :, None] * d_pool
    d_a = (d_pool * s).sum(2)
    d_e = a * (d_a - (a * d_a).sum(0))
    g["att_v"] = np.einsum("tn,tnh->h", d_e, hidden)
    d_hid = d_e[:, :, None] * w["att_v"] * (1 - hidden**2)
    g["att_w"] = np.einsum("tni,tnh->ih", s, d_hid)
    d_s += d_hid @ w["att_w"].T
    d_x = np.zeros_like(x)
    hw = wf.shape[2]
    for net, part, kept in (("wf", d_s[:, :, :hw], wf_kept), ("wb", d_s[:, :, hw:], wb_kept)):
        d_gate, g[f"{net}_u"] = gru_backward(np.ascontiguousarray(part), kept, w[f"{net}_u"])
        by_word = np.zeros((len(vocab), d_gate.shape[2]), np.float32)
        np.add.at(by_word, of[inside], d_gate[inside])
        g[f"{net}_w"], g[f"{net}_b"] = x.T @ by_word, by_word.sum(0)
        d_x += by_word @ w[f"{net}_w"].T
    d = w["word"].shape[1]
    g["word"], g["char"] = np.zeros_like(w["word"]), np.zeros_like(w["char"])
    np.add.at(g["word"], ids, d_x[:, :d])
    for net, part, kept, where in (("cf", d_x[:, d : d + h], cf_kept, -1), ("cb", d_x[:, d + h :], cb_kept, 0)):
        d_out = np.zeros((CHARS, len(vocab), h), np.float32)
        d_out[where] = part
        d_gate, g[f"{net}_u"] = gru_backward(d_out, kept, w[f"{net}_u"])
        g[f"{net}_w"], g[f"{net}_b"] = np.einsum("tni,tnh->ih", cin, d_gate), d_gate.sum((0, 1))
        np.add.at(g["char"], spelled, d_gate @ w[f"{net}_w"].T)
    return loss, g


def train(texts: list[str], toxic: np.ndarray, share: float | None = None, steps: int = 320, batch: int = 256, rate: float = 0.02, per_doc: int = 20, seed: int = 5) -> ToxicityModel:
    """Fits windows with their document's label, then scale and shift of the highest window on the documents.

    Toxic documents also hold harmless windows. From the third pass on, their windows far below the document's highest
    weigh nothing, and of clean documents the highest windows are always among those read, as they decide its score.
    share: of toxic documents where the model is to be used, if the sample has another. steps, batch, rate: how many, windows
    in each, and their size; the sample is passed over as often as that takes. per_doc: windows of a document that are read in one pass, drawn anew in each, so that long
    documents do not fill the sample; scoring always reads all windows."""
    m, rng = new_model(texts), np.random.default_rng(seed)
    split = [tokens(t) or ["_"] for t in texts]
    count = np.fromiter((max(1, -(-(len(s) - WINDOW) // STRIDE) + 1) for s in split), np.int64, len(split))
    doc = np.repeat(np.arange(len(split)), count)
    start = (np.arange(len(doc)) - np.repeat(np.cumsum(count) - count, count)) * STRIDE
    label, z = toxic[doc].astype(np.float32), None
    mean, square, step, epoch = {}, {}, 0, 0
    while step < steps and len(doc):
        # windows of long documents are drawn by chance, so that a few documents cannot fill the sample
        draw = rng.random(len(doc))
        if z is not None:
            top = np.maximum.reduceat(z, np.cumsum(count) - count)[doc]
            draw = np.where(label == 1, np.where(z > top - 1.5, draw, 2 + draw), np.where(z > top - 0.5, draw / 4, draw))
        order = np.lexsort((draw, doc))
        read = order[np.arange(len(doc)) - np.repeat(np.cumsum(count) - count, count) < per_doc]
        read = rng.permutation(read[draw[read] < 2])
        pos = max(1.0, float(label[read].sum()))
        weight = np.where(label == 1, max(1.0, (len(read) - pos) / pos * 0.5), 1.0)
        for a in range(0, len(read), batch):
            if step == steps:
                break
            i = read[a : a + batch]
            _, g = gradients(m, [split[doc[k]][start[k] : start[k] + WINDOW] for k in i], weight[i] / weight[i].sum(), label[i])
            step += 1
            lr = rate * min(1, step / 20) * max(0.05, 1 - 0.95 * step / steps)
            norm = np.sqrt(sum(float((x * x).sum()) for x in g.values()))
            for k, x in g.items():
                x = x * min(1, 1 / max(norm, 1e-9))
                mean[k] = 0.9 * mean.get(k, 0) + 0.1 * x
                square[k] = 0.999 * square.get(k, 0) + 0.001 * x * x
                m.weights[k] = (m.weights[k] - lr * (mean[k] / (1 - 0.9**step)) / (np.sqrt(square[k] / (1 - 0.999**step)) + 1e-8)).astype(np.float32)
        epoch += 1
        if epoch % 2 == 0 or step == steps:
            m.memo = {}
            z = np.concatenate([m.windows(split[a : a + 500])[0] for a in range(0, len(split), 500)]) if split else np.zeros(0)
    z = np.maximum.reduceat(z, np.cumsum(count) - count).astype(np.float64) if split else np.zeros(0)
    m.scale, m.shift = _calibrate(z, toxic)
    if share and 0 < toxic.sum() < len(toxic):
        m.shift += float(np.log(share / (1 - share)) - np.log(toxic.mean() / (1 - toxic.mean())))
    m.memo = {}
    return m


def _calibrate(z: np.ndarray, y: np.ndarray) -> tuple[float, float]:
    """Scale and shift of a logit for which labels are likeliest, a little smoothed."""
    if not len(z) or y.min() == y.max():
        return 1.0, -1.0 if not len(z) or y.max() == 0 else 1.0
    a, b = 1.0, 0.0
    t = np.where(y == 1, (y.sum() + 1) / (y.sum() + 2), 1 / ((y == 0).sum() + 2))
    for _ in range(100):
        p = 1 / (1 + np.exp(-np.clip(a * z + b, -30, 30)))
        r, v = p - t, p * (1 - p) + 1e-9
        grad = np.array([(r * z).sum() + 1e-3 * a, r.sum()])
        hess = np.array([[(v * z * z).sum() + 1e-3, (v * z).sum()], [(v * z).sum(), v.sum() + 1e-6]])
        step = np.linalg.solve(hess, grad)
        step *= min(1, 2 / np.abs(step).max())
        a, b = a - step[0], b - step[1]
    return float(a), float(b)


def fit(docs: DataFrame, labels: DataFrame, toxic: int = SAMPLE_TOXIC, clean: int = SAMPLE_CLEAN) -> ToxicityModel:
    """Learns from at most `toxic` and `clean` labelled rows whose crc32(doc_id) mod 5 is not 0, by the hash of their id.

    The bounds are on the number of rows for training only; their texts are read whole. Rows without a label, an
    id or a text teach nothing; without any usable label the model scores every document below one half."""
    y = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("toxic").cast("int").alias("y")).where("y IN (0, 1) AND doc_id IS NOT NULL")
    y = y.where(F.crc32(F.col("doc_id").cast("string")) % 5 != 0).groupBy("doc_id").agg(F.max("y").alias("y"))
    n, ones = y.agg(F.count(F.lit(1)), F.sum("y")).first()
    chosen = y.where("y = 1").orderBy(F.xxhash64("doc_id"), "doc_id").limit(toxic).unionByName(y.where("y = 0").orderBy(F.xxhash64("doc_id"), "doc_id").limit(clean))
    rows = id_and_text(docs).join(F.broadcast(chosen), "doc_id").where("text <> ''")  # bounded by the two parameters
    rows = rows.groupBy("doc_id").agg(F.min("text").alias("text"), F.max("y").alias("y")).orderBy("doc_id").collect()
    return train([r["text"] for r in rows], np.array([r["y"] for r in rows], np.int64), share=ones / n if n else None)


def score(docs: DataFrame, model: ToxicityModel, keep: bool = False, memo_mb: int = 48) -> DataFrame:
    """doc_id, score (0 to 1) of every whole text; keep: all columns, with __cw_score.

    Null and empty texts are read as one unknown word and get its score; a text of any length is read in parts of about
    2 MB; repeated rows get one each; a null doc_id stays null; an empty table gives no row. A map without shuffle, to
    which only the text travels; the model is broadcast, its size does not grow, and a worker keeps at most memo_mb of words."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    @F.arrow_udf("double")
    def scored(arrays: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for texts in arrays:
            out = [shared.value.scores(part.to_pylist(), memo_mb << 20) for part in text_slices(texts, 2_000_000)]
            yield pa.array(np.concatenate(out) if out else np.zeros(0))

    # not deterministic: the optimiser then never writes the expression out twice
    value = scored.asNondeterministic()(F.coalesce(docs["text"], F.lit("")))
    return docs.select("*", value.alias("__cw_score")) if keep else docs.select(F.col("doc_id").cast("long").alias("doc_id"), value.alias("score"))
