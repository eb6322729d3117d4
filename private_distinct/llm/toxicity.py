"""Toxicity scores from a bidirectional gated recurrent network with attention pooling, in numpy.

A word is read twice: as a vocabulary entry, and byte by byte by a bidirectional recurrent encoder.  Both go
into a bidirectional recurrent layer over the words of a window; attention pools its states into one logit per
window.  A text's logit is the soft maximum over all its overlapping windows, in training as in scoring, so a
text is labelled as a whole but a few words can decide.  What the byte encoder and the input layer make of a
word depends on the word alone and is kept in a bounded memo per worker.

Training takes at most ``per_class`` labelled texts (label 0, label 1) of any length, those with the least hash of
their id.  Of a text with more than ``train_windows`` windows (some 3,000 words) as many are drawn, and of a word
of more than ``TRAIN_BYTES`` bytes the first ones train; these are bounds of the fit alone.  Scoring reads whole
texts and whole words.

Edge cases: null and blank texts have one empty window; very long words are read whole; repeated rows get the
same score; without labelled rows the score is the constant prior; an empty table gives no rows.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

BYTE_DIM, BYTE_STATE, WORD_DIM, STATE, ATTENTION = 12, 12, 16, 8, 8
WINDOW, STRIDE, SHARPNESS = 64, 48, 2.0
VOCABULARY, MEMO_WORDS, TRAIN_BYTES = 20_000, 250_000, 256
_STRIP = "\t\n\r .,;:!?\"'()[]{}<>*_-"


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 0.5 * np.tanh(0.5 * x) + 0.5


def _closed(table: np.ndarray) -> np.ndarray:
    """Input rows plus one for padding, whose update gate keeps the state."""
    pad = np.zeros((1, table.shape[1]), table.dtype)
    pad[0, : table.shape[1] // 3] = 40
    return np.concatenate([table, pad])


def recur(table: np.ndarray, steps: np.ndarray, u: np.ndarray, keep: list | None = None) -> np.ndarray:
    """States after each step; ``steps``: (time, batch) rows of the input table, gates in z, r, n order."""
    h = np.zeros((steps.shape[1], len(u)), np.float32)
    out = np.empty((*steps.shape, len(u)), np.float32)
    s = len(u)
    for t, rows in enumerate(steps):
        x, g = table[rows], h @ u
        zr = _sigmoid(x[:, : 2 * s] + g[:, : 2 * s])
        z, r = zr[:, :s], zr[:, s:]
        n = np.tanh(x[:, 2 * s :] + r * g[:, 2 * s :])
        if keep is not None:
            keep.append((rows, h, z, r, n, g[:, 2 * s :]))
        h = n + z * (h - n)
        out[t] = h
    return out


def recur_back(keep: list, d_out: np.ndarray, u: np.ndarray, d_table: np.ndarray) -> np.ndarray:
    """Adds to d_table and returns the gradient of u; ``d_out``: of the states after each step."""
    du, dh, steps = np.zeros_like(u), np.zeros_like(d_out[0]), []
    for (rows, h, z, r, n, gn), d in zip(reversed(keep), d_out[::-1], strict=True):
        dh = dh + d
        dn = (1 - z) * dh * (1 - n * n)
        dz, dr = (h - n) * dh * z * (1 - z), dn * gn * r * (1 - r)
        dg = np.concatenate([dz, dr, dn * r], 1)
        steps.append(np.concatenate([dz, dr, dn], 1))
        du += h.T @ dg
        dh = z * dh + dg @ u.T
    rows, grads = np.concatenate([k[0] for k in reversed(keep)]), np.concatenate(steps)
    order = np.argsort(rows, kind="stable")
    first = np.flatnonzero(np.diff(rows[order], prepend=-1))
    d_table[rows[order][first]] += np.add.reduceat(grads[order], first)
    return du


class Network:
    """Parameters and passes; small, so it is broadcast."""

    def __init__(self, vocabulary: dict[str, int], seed: int = 7):
        rng = np.random.default_rng(seed)
        make = lambda *shape: (rng.standard_normal(shape) / np.sqrt(shape[0])).astype(np.float32)
        inputs = 2 * BYTE_STATE + WORD_DIM
        self.vocabulary, self.fitted = vocabulary, False
        self.p = {
            "byte": make(256, BYTE_DIM) * 4, "bw0": make(BYTE_DIM, 3 * BYTE_STATE), "bw1": make(BYTE_DIM, 3 * BYTE_STATE), "bu0": make(BYTE_STATE, 3 * BYTE_STATE), "bu1": make(BYTE_STATE, 3 * BYTE_STATE),
            "bb0": np.zeros(3 * BYTE_STATE, np.float32), "bb1": np.zeros(3 * BYTE_STATE, np.float32), "word": make(len(vocabulary) + 1, WORD_DIM), "w0": make(inputs, 3 * STATE), "w1": make(inputs, 3 * STATE),
            "u0": make(STATE, 3 * STATE), "u1": make(STATE, 3 * STATE), "b0": np.zeros(3 * STATE, np.float32), "b1": np.zeros(3 * STATE, np.float32), "aw": make(2 * STATE, ATTENTION), "ab": np.zeros(ATTENTION, np.float32),
            "av": make(ATTENTION), "ow": make(2 * STATE), "ob": np.full(1, -1, np.float32),
        }
        self._fresh()

    def __getstate__(self):
        return {k: v for k, v in self.__dict__.items() if k not in ("memo", "tables", "filled")}

    def __setstate__(self, state):
        self.__dict__ |= state
        self._fresh()

    # words ---------------------------------------------------------------------------------------

    def byte_steps(self, words: list[bytes]) -> np.ndarray:
        size = np.fromiter(map(len, words), np.int64, len(words))
        steps = np.full((len(words), max(1, size.max(initial=0))), 256, np.int64)
        steps[np.arange(steps.shape[1]) < size[:, None]] = np.frombuffer(b"".join(words), np.uint8)
        return steps.T

    def word_ids(self, words: list[str]) -> np.ndarray:
        known = self.vocabulary.get
        return np.fromiter((known(w.strip(_STRIP), 0) for w in words), np.int64, len(words))

    def encode_words(self, words: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Input rows of the two word layers."""
        p, n = self.p, len(words)
        raw = [w.encode(errors="replace") for w in words]
        features = np.empty((n, 2 * BYTE_STATE), np.float32)
        for mine in by_length(raw):
            for some in np.array_split(mine, len(mine) // 4096 + 1):
                steps = self.byte_steps([raw[i] for i in some])
                for d in (0, 1):
                    table = _closed(p["byte"] @ p[f"bw{d}"] + p[f"bb{d}"])
                    features[some, d * BYTE_STATE : (d + 1) * BYTE_STATE] = _last(table, steps[:: 1 - 2 * d], p[f"bu{d}"])
        x = np.concatenate([features, p["word"][self.word_ids(words)]], 1)
        return x @ p["w0"] + p["b0"], x @ p["w1"] + p["b1"]

    # windows -------------------------------------------------------------------------------------

    def window_logits(self, tables: list[np.ndarray], steps: np.ndarray, pad: int) -> np.ndarray:
        p = self.p
        o = np.concatenate([recur(tables[0], steps, p["u0"]), recur(tables[1], steps[::-1], p["u1"])[::-1]], 2)
        e = np.tanh(o @ p["aw"] + p["ab"]) @ p["av"]
        e = np.where(steps == pad, -np.inf, e) if (steps[-1] == pad).any() else e
        a = np.exp(e - np.maximum(e.max(0), -1e30))
        a /= np.maximum(a.sum(0), 1e-30)
        return np.einsum("tb,tbk,k->b", a, o, p["ow"], optimize=True) + p["ob"][0]

    def _fresh(self) -> None:
        self.memo = _Memo()
        self.tables = [np.zeros((1024, 3 * STATE), np.float32) for _ in range(2)]
        self.tables[0][0] = self.tables[1][0] = _closed(np.zeros((0, 3 * STATE), np.float32))[0]
        self.filled = 1  # row 0 is padding

    def score(self, texts: list[str | None]) -> np.ndarray:
        """Probability of the label for each whole text."""
        if not self.fitted:
            return np.full(len(texts), 1 / (1 + np.exp(-self.p["ob"][0])))
        if self.filled > MEMO_WORDS:
            self._fresh()
        get = self.memo.__getitem__
        rows = []
        for t in texts:
            words = (t or "").lower().split()
            rows.append(np.fromiter(map(get, words), np.int32, len(words)))
        if self.memo.fresh:
            n = self.filled + len(self.memo.fresh)
            made = self.encode_words(self.memo.fresh)
            for d in (0, 1):
                if n > len(self.tables[d]):
                    self.tables[d] = np.concatenate([self.tables[d][: self.filled], np.empty((n, 3 * STATE), np.float32)])
                self.tables[d][self.filled : n] = made[d]
            self.filled = n
            self.memo.fresh.clear()
        index, doc = windows(rows)
        logits = np.empty(len(doc), np.float32)
        size = (index > 0).sum(1)
        order = np.argsort(size, kind="stable")
        for i in range(0, len(order), 1024):
            some = order[i : i + 1024]
            longest = max(1, int(size[some[-1]]))
            logits[some] = self.window_logits(self.tables, np.ascontiguousarray(index[some, :longest].T), 0)
        return 1 / (1 + np.exp(-soft_maximum(logits.astype(np.float64), doc, len(texts))[0]))


class _Memo(dict):
    def __init__(self):
        super().__init__()
        self.fresh: list[str] = []

    def __missing__(self, word: str) -> int:
        self.fresh.append(word)
        self[word] = n = len(self) + 1
        return n


def by_length(raw: list[bytes]) -> list[np.ndarray]:
    """Places of the words of about one length."""
    width = np.ceil(np.log2(np.maximum(np.fromiter(map(len, raw), np.int64, len(raw)), 8)) * 2).astype(int)
    return [np.flatnonzero(width == k) for k in np.unique(width)]


def _last(table: np.ndarray, steps: np.ndarray, u: np.ndarray) -> np.ndarray:
    return recur(table, steps, u)[-1]


def windows(rows: list[np.ndarray], length: int = WINDOW, stride: int = STRIDE) -> tuple[np.ndarray, np.ndarray]:
    """All overlapping windows of all texts, padded with 0, and the text of each."""
    sizes = np.fromiter(map(len, rows), np.int64, len(rows))
    n = np.maximum(0, -(-(sizes - length) // stride)) + 1
    doc = np.repeat(np.arange(len(rows)), n)
    first = (np.arange(len(doc)) - np.repeat(np.cumsum(n) - n, n)) * stride
    flat = np.concatenate([*rows, np.zeros(length, np.int32)])
    place = first[:, None] + np.arange(length)
    inside = place < sizes[doc][:, None]
    place += (np.cumsum(sizes) - sizes)[doc][:, None]
    return np.where(inside, flat[np.minimum(place, len(flat) - 1)], 0), doc


def soft_maximum(logits: np.ndarray, doc: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Per text the logits' mean, weighted towards the largest; and the weights."""
    top = np.full(n, -np.inf)
    np.maximum.at(top, doc, logits)
    w = np.exp(SHARPNESS * (logits - top[doc]))
    w /= np.bincount(doc, w, n)[doc]
    return np.bincount(doc, w * logits, n), w


def cut_words(words: list[str], most: int | None = None) -> list[list[str]]:
    """The overlapping windows of a text, or ``most`` of them, drawn by the text itself."""
    n = max(0, -(-(len(words) - WINDOW) // STRIDE)) + 1
    some = range(n)
    if most is not None and n > most:
        some = np.sort(np.random.default_rng(zlib.crc32(" ".join(words).encode(errors="replace"))).choice(n, most, replace=False)).tolist()
    return [words[i * STRIDE : i * STRIDE + WINDOW] for i in some]


def train(texts: list, labels: list[int], seed: int = 7, batch: int = 32, steps: int = 220, rate: float = 0.01) -> Network:
    """Fit by Adam on texts, each a string or a list of windows; ``steps`` batches, at least one pass."""
    df: dict[str, int] = {}
    lower = [cut_words(t.lower().split()) if isinstance(t, str) else [w.split() for w in t] for t in texts]
    for found in lower:
        for w in {w.strip(_STRIP) for words in found for w in words}:
            df[w] = df.get(w, 0) + 1
    common = sorted((w for w, n in df.items() if n > 3 and w), key=lambda w: (-df[w], w))[:VOCABULARY]
    net = Network({w: i + 1 for i, w in enumerate(common)}, seed)
    y = np.array(labels, np.float64)
    if not len(texts) or y.min() == y.max():
        share = (y.sum() + 0.5) / (len(y) + 10)
        net.p["ob"][0] = np.log(share / (1 - share))
        return net
    p, rng = net.p, np.random.default_rng(seed)
    m = {k: np.zeros_like(v) for k, v in p.items()}
    v2 = {k: np.zeros_like(v) for k, v in p.items()}
    order: list[int] = []
    total = max(steps, -(-len(texts) // batch))
    for step in range(1, total + 1):
        while len(order) < batch:
            order += rng.permutation(len(texts)).tolist()
        some, order = order[:batch], order[batch:]
        grad = _gradient(net, [lower[i] for i in some], y[some], rng)
        lr = rate * min(1, step / 20) * (1 - 0.9 * step / total)
        norm = np.sqrt(sum(float((g * g).sum()) for g in grad.values()))
        for k, g in grad.items():
            g = g * min(1, 2 / max(norm, 1e-9))
            m[k] += 0.1 * (g - m[k])
            v2[k] += 0.01 * (g * g - v2[k])
            p[k] -= (lr * (m[k] / (1 - 0.9**step)) / (np.sqrt(v2[k] / (1 - 0.99**step)) + 1e-7)).astype(np.float32)
    net.fitted = True
    return net


def _gradient(net: Network, lower: list[list[list[str]]], y: np.ndarray, rng, blank: float = 0.5) -> dict[str, np.ndarray]:
    """Of the mean loss of some texts, each given by its windows."""
    p, words = net.p, {}
    doc = np.repeat(np.arange(len(lower)), [len(ws) for ws in lower])
    index = np.zeros((len(doc), max(1, max(len(w) for ws in lower for w in ws))), np.int64)
    for i, w in enumerate(w for ws in lower for w in ws):
        index[i, : len(w)] = [words.setdefault(x, len(words)) + 1 for x in w]
    words = list(words) or [""]
    pad = len(words)
    steps = np.ascontiguousarray(np.where(index > 0, index - 1, pad).T)
    ids = np.where(rng.random(len(words)) < blank, 0, net.word_ids(words))  # some words are known by their bytes only
    raw = [w.encode(errors="replace")[:TRAIN_BYTES] for w in words]
    alike, kept, tables = by_length(raw), [[], []], []
    x = np.empty((len(words), 2 * BYTE_STATE + WORD_DIM), np.float32)
    x[:, 2 * BYTE_STATE :] = p["word"][ids]
    for d in (0, 1):
        table = _closed(p["byte"] @ p[f"bw{d}"] + p[f"bb{d}"])
        for mine in alike:
            kept[d].append([])
            x[mine, d * BYTE_STATE : (d + 1) * BYTE_STATE] = recur(table, net.byte_steps([raw[i] for i in mine])[:: 1 - 2 * d], p[f"bu{d}"], kept[d][-1])[-1]
    keep2, outs = [[], []], []
    for d in (0, 1):
        tables.append(_closed(x @ p[f"w{d}"] + p[f"b{d}"]))
        outs.append(recur(tables[d], steps[:: 1 - 2 * d], p[f"u{d}"], keep2[d])[:: 1 - 2 * d])
    o = np.concatenate(outs, 2)
    hid = np.tanh(o @ p["aw"] + p["ab"])
    e = np.where(steps == pad, -1e30, hid @ p["av"])
    a = np.exp(e - e.max(0))
    a = (a / a.sum(0)).astype(np.float32)
    c = np.einsum("tb,tbk->bk", a, o)
    z = (c @ p["ow"] + p["ob"][0]).astype(np.float64)
    pooled, w = soft_maximum(z, doc, len(lower))
    dp = (1 / (1 + np.exp(-pooled)) - y) / len(y)
    dz = (dp[doc] * w * (1 + SHARPNESS * (z - pooled[doc]))).astype(np.float32)
    g = {"ob": dz.sum(keepdims=True), "ow": c.T @ dz}
    dc = dz[:, None] * p["ow"]
    da = np.einsum("tbk,bk->tb", o, dc)
    de = a * (da - (a * da).sum(0))
    do = a[:, :, None] * dc
    g["av"] = np.einsum("tb,tbk->k", de, hid)
    dhid = de[:, :, None] * p["av"] * (1 - hid * hid)
    g["ab"], g["aw"] = dhid.sum((0, 1)), np.tensordot(o, dhid, ((0, 1), (0, 1)))
    do = do + dhid @ p["aw"].T
    dx = np.zeros_like(x)
    for d in (0, 1):
        dt = np.zeros_like(tables[d])
        g[f"u{d}"] = recur_back(keep2[d], do[:, :, d * STATE : (d + 1) * STATE][:: 1 - 2 * d], p[f"u{d}"], dt)
        g[f"w{d}"], g[f"b{d}"] = x.T @ dt[:-1], dt[:-1].sum(0)
        dx += dt[:-1] @ p[f"w{d}"].T
    g["word"], g["byte"] = np.zeros_like(p["word"]), np.zeros_like(p["byte"])
    np.add.at(g["word"], ids, dx[:, 2 * BYTE_STATE :])
    for d in (0, 1):
        dt, g[f"bu{d}"] = np.zeros((257, 3 * BYTE_STATE), np.float32), 0
        for mine, keep in zip(alike, kept[d], strict=True):
            last = np.zeros((len(keep), len(mine), BYTE_STATE), np.float32)
            last[-1] = dx[mine, d * BYTE_STATE : (d + 1) * BYTE_STATE]
            g[f"bu{d}"] = g[f"bu{d}"] + recur_back(keep, last, p[f"bu{d}"], dt)
        g[f"bw{d}"], g[f"bb{d}"] = p["byte"].T @ dt[:-1], dt[:-1].sum(0)
        g["byte"] += dt[:-1] @ p[f"bw{d}"].T
    return {k: v.astype(np.float32) for k, v in g.items()}


def fit(docs: DataFrame, labels: DataFrame, usable: Column, label: str = "toxic", per_class: tuple[int, int] = (3000, 1500), train_windows: int = 64) -> Network:
    """Network fitted on a bounded sample of the labelled rows for which ``usable`` (of doc_id) holds."""
    ids = labels.where(usable & F.col("doc_id").isNotNull()).groupBy("doc_id").agg(F.max(label).alias("y")).where("y in (0, 1)")
    picked = [ids.where(F.col("y") == y).orderBy(F.xxhash64("doc_id"), "doc_id").limit(2 * per_class[y]) for y in (0, 1)]
    sample = F.broadcast(picked[0].union(picked[1]))  # at most 2 * sum(per_class) rows

    def cut(batches):
        for b in batches:
            found = [[" ".join(w) for w in cut_words((t.as_py() or "").lower().split(), train_windows)] for t in b.column(2)]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(found, pa.list_(pa.string()))], names=["doc_id", "y", "windows"])

    kind = docs.schema["doc_id"].dataType.simpleString()
    rows = docs.select("doc_id", F.col("text").alias("_text")).join(sample, "doc_id").select("doc_id", F.col("y").cast("int").alias("y"), "_text")
    rows = rows.mapInArrow(cut, f"doc_id {kind}, y int, windows array<string>")
    rows = [r for y in (0, 1) for r in rows.where(F.col("y") == y).orderBy(F.xxhash64("doc_id"), "doc_id", "windows").limit(per_class[y]).collect()]
    return train([r.windows for r in rows], [int(r.y) for r in rows])


def score(self, texts: list[str | None]) -> np.ndarray:
        """Probability of the label for each whole text."""
        if not self.fitted:
            return np.full(len(texts), 1 / (1 + np.exp(-self.p["ob"][0])))
        if self.filled > MEMO_WORDS:
            self._fresh()
        get = self.memo.__getitem__
        rows = []
        for t in texts:
            words = (t or "").lower().split()
            rows.append(np.fromiter(map(get, words), np.int32, len(words)))
        if self.memo.fresh:
            n = self.filled + len(self.memo.fresh)
            made = self.encode_words(self.memo.fresh)
            for d in (0, 1):
                if n > len(self.tables[d]):
                    self.tables[d] = np.concatenate([self.tables[d][: self.filled], np.empty((n, 3 * STATE), np.float32)])
                self.tables[d][self.filled : n] = made[d]
            self.filled = n
            self.memo.fresh.clear()
        index, doc = windows(rows)
        logits = np.empty(len(doc), np.float32)
        size = (index > 0).sum(1)
        order = np.argsort(size, kind="stable")
        for i in range(0, len(order), 1024):
            some = order[i : i + 1024]
            longest = max(1, int(size[some[-1]]))
            logits[some] = self.window_logits(self.tables, np.ascontiguousarray(index[some, :longest].T), 0)
        return 1 / (1 + np.exp(-soft_maximum(logits.astype(np.float64), doc, len(texts))[0]))


class _Memo(dict):
    def __init__(self):
        super().__init__()
        self.fresh: list[str] = []

    def __missing__(self, word: str) -> int:
        self.fresh.append(word)
        self[word] = n = len(self) + 1
        return n


def by_length(raw: list[bytes]) -> list[np.ndarray]:
    """Places of the words of about one length."""
    width = np.ceil(np.log2(np.maximum(np.fromiter(map(len, raw), np.int64, len(raw)), 8)) * 2).astype(int)
    return [np.flatnonzero(width == k) for k in np.unique(width)]


def _last(table: np.ndarray, steps: np.ndarray, u: np.ndarray) -> np.ndarray:
    return recur(table, steps, u)[-1]


def windows(rows: list[np.ndarray], length: int = WINDOW, stride: int = STRIDE) -> tuple[np.ndarray, np.ndarray]:
    """All overlapping windows of all texts, padded with 0, and the text of each."""
    sizes = np.fromiter(map(len, rows), np.int64, len(rows))
    n = np.maximum(0, -(-(sizes - length) // stride)) + 1
    doc = np.repeat(np.arange(len(rows)), n)
    first = (np.arange(len(doc)) - np.repeat(np.cumsum(n) - n, n)) * stride
    flat = np.concatenate([*rows, np.zeros(length, np.int32)])
    place = first[:, None] + np.arange(length)
    inside = place < sizes[doc][:, None]
    place += (np.cumsum(sizes) - sizes)[doc][:, None]
    return np.where(inside, flat[np.minimum(place, len(flat) - 1)], 0), doc


def soft_maximum(logits: np.ndarray, doc: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Per text the logits' mean, weighted towards the largest; and the weights."""
    top = np.full(n, -np.inf)
    np.maximum.at(top, doc, logits)
    w = np.exp(SHARPNESS * (logits - top[doc]))
    w /= np.bincount(doc, w, n)[doc]
    return np.bincount(doc, w * logits, n), w


def cut_words(words: list[str], most: int | None = None) -> list[list[str]]:
    """The overlapping windows of a text, or ``most`` of them, drawn by the text itself."""
    n = max(0, -(-(len(words) - WINDOW) // STRIDE)) + 1
    some = range(n)
    if most is not None and n > most:
        some = np.sort(np.random.default_rng(zlib.crc32(" ".join(words).encode(errors="replace"))).choice(n, most, replace=False)).tolist()
    return [words[i * STRIDE : i * STRIDE + WINDOW] for i in some]


def train(texts: list, labels: list[int], seed: int = 7, batch: int = 32, steps: int = 220, rate: float = 0.01) -> Network:
    """Fit by Adam on texts, each a string or a list of windows; ``steps`` batches, at least one pass."""
    df: dict[str, int] = {}
    lower = [cut_words(t.lower().split()) if isinstance(t, str) else [w.split() for w in t] for t in texts]
    for found in lower:
        for w in {w.strip(_STRIP) for words in found for w in words}:
            df[w] = df.get(w, 0) + 1
    common = sorted((w for w, n in df.items() if n > 3 and w), key=lambda w: (-df[w], w))[:VOCABULARY]
    net = Network({w: i + 1 for i, w in enumerate(common)}, seed)
    y = np.array(labels, np.float64)
    if not len(texts) or y.min() == y.max():
        share = (y.sum() + 0.5) / (len(y) + 10)
        net.p["ob"][0] = np.log(share / (1 - share))
        return net
    p, rng = net.p, np.random.default_rng(seed)
    m = {k: np.zeros_like(v) for k, v in p.items()}
    v2 = {k: np.zeros_like(v) for k, v in p.items()}
    order: list[int] = []
    total = max(steps, -(-len(texts) // batch))
    for step in range(1, total + 1):
        while len(order) < batch:
            order += rng.permutation(len(texts)).tolist()
        some, order = order[:batch], order[batch:]
        grad = _gradient(net, [lower[i] for i in some], y[some], rng)
        lr = rate * min(1, step / 20) * (1 - 0.9 * step / total)
        norm = np.sqrt(sum(float((g * g).sum()) for g in grad.values()))
        for k, g in grad.items():
            g = g * min(1, 2 / max(norm, 1e-9))
            m[k] += 0.1 * (g - m[k])
            v2[k] += 0.01 * (g * g - v2[k])
            p[k] -= (lr * (m[k] / (1 - 0.9**step)) / (np.sqrt(v2[k] / (1 - 0.99**step)) + 1e-7)).astype(np.float32)
    net.fitted = True
    return net


def _gradient(net: Network, lower: list[list[list[str]]], y: np.ndarray, rng, blank: float = 0.5) -> dict[str, np.ndarray]:
    """Of the mean loss of some texts, each given by its windows."""
    p, words = net.p, {}
    doc = np.repeat(np.arange(len(lower)), [len(ws) for ws in lower])
    index = np.zeros((len(doc), max(1, max(len(w) for ws in lower for w in ws))), np.int64)
    for i, w in enumerate(w for ws in lower for w in ws):
        index[i, : len(w)] = [words.setdefault(x, len(words)) + 1 for x in w]
    words = list(words) or [""]
    pad = len(words)
    steps = np.ascontiguousarray(np.where(index > 0, index - 1, pad).T)
    ids = np.where(rng.random(len(words)) < blank, 0, net.word_ids(words))  # some words are known by their bytes only
    raw = [w.encode(errors="replace")[:TRAIN_BYTES] for w in words]
    alike, kept, tables = by_length(raw), [[], []], []
    x = np.empty((len(words), 2 * BYTE_STATE + WORD_DIM), np.float32)
    x[:, 2 * BYTE_STATE :] = p["word"][ids]
    for d in (0, 1):
        table = _closed(p["byte"] @ p[f"bw{d}"] + p[f"bb{d}"])
        for mine in alike:
            kept[d].append([])
            x[mine, d * BYTE_STATE : (d + 1) * BYTE_STATE] = recur(table, net.byte_steps([raw[i] for i in mine])[:: 1 - 2 * d], p[f"bu{d}"], kept[d][-1])[-1]
    keep2, outs = [[], []], []
    for d in (0, 1):
        tables.append(_closed(x @ p[f"w{d}"] + p[f"b{d}"]))
        outs.append(recur(tables[d], steps[:: 1 - 2 * d], p[f"u{d}"], keep2[d])[:: 1 - 2 * d])
    o = np.concatenate(outs, 2)
    hid = np.tanh(o @ p["aw"] + p["ab"])
    e = np.where(steps == pad, -1e30, hid @ p["av"])
    a = np.exp(e - e.max(0))
    a = (a / a.sum(0)).astype(np.float32)
    c = np.einsum("tb,tbk->bk", a, o)
    z = (c @ p["ow"] + p["ob"][0]).astype(np.float64)
    pooled, w = soft_maximum(z, doc, len(lower))
    dp = (1 / (1 + np.exp(-pooled)) - y) / len(y)
    dz = (dp[doc] * w * (1 + SHARPNESS * (z - pooled[doc]))).astype(np.float32)
    g = {"ob": dz.sum(keepdims=True), "ow": c.T @ dz}
    dc = dz[:, None] * p["ow"]
    da = np.einsum("tbk,bk->tb", o, dc)
    de = a * (da - (a * da).sum(0))
    do = a[:, :, None] * dc
    g["av"] = np.einsum("tb,tbk->k", de, hid)
    dhid = de[:, :, None] * p["av"] * (1 - hid * hid)
    g["ab"], g["aw"] = dhid.sum((0, 1)), np.tensordot(o, dhid, ((0, 1), (0, 1)))
    do = do + dhid @ p["aw"].T
    dx = np.zeros_like(x)
    for d in (0, 1):
        dt = np.zeros_like(tables[d])
        g[f"u{d}"] = recur_back(keep2[d], do[:, :, d * STATE : (d + 1) * STATE][:: 1 - 2 * d], p[f"u{d}"], dt)
        g[f"w{d}"], g[f"b{d}"] = x.T @ dt[:-1], dt[:-1].sum(0)
        dx += dt[:-1] @ p[f"w{d}"].T
    g["word"], g["byte"] = np.zeros_like(p["word"]), np.zeros_like(p["byte"])
    np.add.at(g["word"], ids, dx[:, 2 * BYTE_STATE :])
    for d in (0, 1):
        dt, g[f"bu{d}"] = np.zeros((257, 3 * BYTE_STATE), np.float32), 0
        for mine, keep in zip(alike, kept[d], strict=True):
            last = np.zeros((len(keep), len(mine), BYTE_STATE), np.float32)
            last[-1] = dx[mine, d * BYTE_STATE : (d + 1) * BYTE_STATE]
            g[f"bu{d}"] = g[f"bu{d}"] + recur_back(keep, last, p[f"bu{d}"], dt)
        g[f"bw{d}"], g[f"bb{d}"] = p["byte"].T @ dt[:-1], dt[:-1].sum(0)
        g["byte"] += dt[:-1] @ p[f"bw{d}"].T
    return {k: v.astype(np.float32) for k, v in g.items()}


def fit(docs: DataFrame, labels: DataFrame, usable: Column, label: str = "toxic", per_class: tuple[int, int] = (3000, 1500), train_chars: int = 2500) -> Network:
    """Network fitted on a bounded sample of the labelled rows for which ``usable`` (of doc_id) holds."""
    ids = labels.where(usable & F.col("doc_id").isNotNull()).groupBy("doc_id").agg(F.max(label).alias("y")).where("y in (0, 1)")
    picked = [ids.where(F.col("y") == y).orderBy(F.xxhash64("doc_id"), "doc_id").limit(2 * per_class[y]) for y in (0, 1)]
    sample = F.broadcast(picked[0].union(picked[1]))  # at most 2 * sum(per_class) rows
    text = F.coalesce(F.col("text"), F.lit(""))
    rows = docs.select("doc_id", text.alias("text")).where(F.length("text") <= train_chars).join(sample, "doc_id")
    rows = [r for y in (0, 1) for r in rows.where(F.col("y") == y).orderBy(F.xxhash64("doc_id"), "doc_id").limit(per_class[y]).collect()]
    return train([r.text for r in rows], [int(r.y) for r in rows])


def score(docs: DataFrame, network: Network, keep: list[str], text: str = "text") -> DataFrame:
    """``keep`` columns and the score of each row's whole text."""
    shared = docs.sparkSession.sparkContext.broadcast(network)
    schema = docs.select(*keep, F.lit(0.0).alias("score")).schema

    def run(batches):
        net = shared.value
        for b in batches:
            texts, done, i = b.column(at).to_pylist(), [], 0
            while i < len(texts):
                j, size = i, 0
                while j < len(texts) and size < 1 << 20:
                    size += len(texts[j] or "")
                    j += 1
                done.append(net.score(texts[i:j]))
                i = j
            yield pa.RecordBatch.from_arrays([*b.columns[: len(keep)], pa.array(np.concatenate(done or [np.empty(0)]).astype(np.float64))], names=[*keep, "score"])

    at = keep.index(text) if text in keep else len(keep)
    return docs.select(*keep, *[F.col(text).alias("_text")][: at == len(keep)]).mapInArrow(run, schema)
