"""Toxicity: a bidirectional gated recurrent network with attention pooling, trained here in numpy.

A word's input is its own vector (words seen often enough in training) beside the mean of vectors of its
hashed character n-grams, so inflected and unseen forms share what their letters tell. A text is read
in overlapping windows of ``WINDOW`` words that start every ``STRIDE`` words, all of them, to its end. Both
directions' states are pooled by attention, and a text scores as its worst window.

Training takes a bounded sample (``SAMPLE`` rows of each label at most, of texts up to ``SAMPLE_CHARS``
characters). Labels hold for texts, not for windows, so training begins with all windows of a toxic
text and goes on with its worst window (multiple-instance learning); windows of other texts are drawn
among all and among their worst.

Defined results: null and wordless texts score 0; every text does if nothing can be learned; rows are
judged one by one; rows of ``labels`` with null fields are not learned from, and repeated ones count
repeatedly; an empty table gives an empty result; further columns are ignored.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import stored

WINDOW, STRIDE = 32, 24
HIDDEN, WORD_DIM, CHAR_DIM = 8, 8, 8
CHAR_BUCKETS = 1 << 15
LEAST_COUNT, MOST_WORDS = 8, 20_000
SAMPLE, SAMPLE_CHARS = 1500, 30_000
EPOCHS, BATCH, RATE = 8, 256, 0.01
#: Small samples are gone through more often, to about so many steps; the first quarter takes all windows.
STEPS = 150
#: Pull of input vectors towards zero, a step and unit of rate.
DECAY = 0.3
KNOWN = 150_000
#: Everything in ASCII but letters separates words; other bytes belong to letters.
_TABLE = bytes(c if c >= 128 or chr(c).isalpha() else 32 for c in range(256))


def words_of(text: str | None) -> list[bytes]:
    return text.lower().encode("utf-8", "surrogatepass").translate(_TABLE).split() if text else []


def window_starts(n: int) -> range:
    """Starts of all windows of n words; the last window reaches the end."""
    return range(0, max(1, n - WINDOW + STRIDE), STRIDE)


def char_features(words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Buckets of the n-grams (3 to 5 bytes, with a mark at either end) of all words, and their word numbers."""
    flat = np.frombuffer(b"<" + b"><".join(words) + b">", np.uint8).astype(np.uint32)
    lens = np.fromiter(map(len, words), np.int64, len(words)) + 2
    word = np.repeat(np.arange(len(words)), lens)
    end = np.cumsum(lens)[word]
    at = np.arange(len(flat))
    got, own = [], []
    for n in (3, 4, 5):
        h = np.full(max(0, len(flat) - n + 1), n * 0x9E3779B1 & 0xFFFFFFFF, np.uint32)
        for k in range(n):
            h = (h ^ flat[k : k + len(h)]) * np.uint32(0x01000193)
            h ^= h >> np.uint32(13)
        ok = at[: len(h)] + n <= end[: len(h)]
        got.append((h[ok] * np.uint32(0x85EBCA6B)) >> np.uint32(32 - 15))
        own.append(word[: len(h)][ok])
    b, w = np.concatenate(got), np.concatenate(own)
    order = np.argsort(w, kind="stable")
    return b[order].astype(np.int64), w[order]


def char_means(b: np.ndarray, w: np.ndarray, table: np.ndarray, n: int) -> tuple[np.ndarray, np.ndarray]:
    count = np.bincount(w, minlength=n).astype(np.float32)
    starts = np.searchsorted(w, np.arange(n))
    out = np.zeros((n, table.shape[1]), np.float32)
    some = count > 0
    if some.any():
        out[some] = np.add.reduceat(table[b], starts[some], axis=0) / count[some, None]
    return out, count


class Network:
    """Parameters, the forward pass and its gradients. Row 0 of inputs stands for padding."""

    def __init__(self, vocabulary: list[bytes], seed: int = 8):
        r = np.random.default_rng(seed)
        f = lambda *s, scale: (r.standard_normal(s) * scale).astype(np.float32)
        d, h = WORD_DIM + CHAR_DIM, HIDDEN
        self.number = {w: i + 1 for i, w in enumerate(vocabulary)}
        self.p = {"words": f(len(vocabulary) + 1, WORD_DIM, scale=0.1), "chars": f(CHAR_BUCKETS, CHAR_DIM, scale=0.2)}
        for k in "fb":
            self.p |= {f"w{k}": f(d, 3 * h, scale=d**-0.5), f"u{k}": f(h, 3 * h, scale=h**-0.5), f"c{k}": np.zeros(3 * h, np.float32)}
        self.p |= {"att": f(2 * h, scale=0.3), "out": f(2 * h, scale=0.3), "bias": np.full(1, -1, np.float32)}
        self.p["words"][0] = 0

    def inputs(self, words: list[bytes]) -> tuple[np.ndarray, tuple]:
        """Input vectors of distinct words; row 0 is padding."""
        ids = np.fromiter((self.number.get(w, 0) for w in words), np.int64, len(words))
        b, w = char_features(words) if words else (np.empty(0, np.int64), np.empty(0, np.int64))
        mean, count = char_means(b, w, self.p["chars"], len(words))
        x = np.zeros((len(words) + 1, WORD_DIM + CHAR_DIM), np.float32)
        x[1:, :WORD_DIM] = self.p["words"][ids]
        x[1:, WORD_DIM:] = mean
        return x, (ids, b, w, count)

    def run(self, gates: dict[str, np.ndarray], ids: np.ndarray, keep: bool = False):
        """Logits of windows (rows of input numbers). gates: inputs already multiplied, by direction."""
        n, steps, h = *ids.shape, HIDDEN
        states, saved = np.empty((n, steps, 2 * h), np.float32), {}
        for k, cols, order in (("f", slice(0, h), range(steps)), ("b", slice(h, 2 * h), range(steps - 1, -1, -1))):
            s, u, past = np.zeros((n, h), np.float32), self.p[f"u{k}"], []
            for t in order:
                x, y = gates[k][ids[:, t]], s @ u
                zr = x[:, : 2 * h] + y[:, : 2 * h]
                zr *= 0.5
                np.tanh(zr, out=zr)
                zr *= 0.5
                zr += 0.5
                z, r = zr[:, :h], zr[:, h:]
                c = np.tanh(x[:, 2 * h :] + r * y[:, 2 * h :])
                if keep:
                    past.append((t, s, z, r, c, y[:, 2 * h :]))
                s = c + z * (s - c)
                states[:, t, cols] = s
            saved[k] = past
        score = states @ self.p["att"]
        score[ids == 0] = -1e9
        e = np.exp(score - score.max(axis=1, keepdims=True))
        a = e / e.sum(axis=1, keepdims=True)
        pooled = np.einsum("nt,nth->nh", a, states)
        logit = pooled @ self.p["out"] + self.p["bias"][0]
        return (logit, states, a, pooled, saved) if keep else logit

    def gates(self, x: np.ndarray) -> dict[str, np.ndarray]:
        return {k: x @ self.p[f"w{k}"] + self.p[f"c{k}"] for k in "fb"}

    def gradients(self, words: list[bytes], ids: np.ndarray, y: np.ndarray) -> dict[str, np.ndarray]:
        x, (own, b, w, count) = self.inputs(words)
        gates, h, p = self.gates(x), HIDDEN, self.p
        logit, states, a, pooled, saved = self.run(gates, ids, keep=True)
        dl = ((1 / (1 + np.exp(-logit)) - y) / len(y)).astype(np.float32)
        g = {"out": pooled.T @ dl, "bias": dl.sum(keepdims=True)}
        dp = dl[:, None] * p["out"]
        da = np.einsum("nth,nh->nt", states, dp)
        ds = a * (da - (a * da).sum(axis=1, keepdims=True))
        g["att"] = np.einsum("nt,nth->h", ds, states)
        dstates = a[:, :, None] * dp[:, None, :] + ds[:, :, None] * p["att"]
        dx = np.zeros_like(x)
        for k, cols in (("f", slice(0, h)), ("b", slice(h, 2 * h))):
            u, dg = p[f"u{k}"], np.zeros((len(x), 3 * h), np.float32)
            du, back = np.zeros_like(u), np.zeros((len(y), h), np.float32)
            for t, s, z, r, c, yc in reversed(saved[k]):
                d = back + dstates[:, t, cols]
                dz, dc = d * (s - c) * z * (1 - z), d * (1 - z) * (1 - c * c)
                dr = dc * yc * r * (1 - r)
                dy = np.concatenate((dz, dr, dc * r), axis=1)
                back = d * z + dy @ u.T
                du += s.T @ dy
                np.add.at(dg, ids[:, t], np.concatenate((dz, dr, dc), axis=1))
            g[f"u{k}"], g[f"c{k}"], g[f"w{k}"] = du, dg.sum(axis=0), x.T @ dg
            dx += dg @ p[f"w{k}"].T
        dx = dx[1:]
        g["words"], g["chars"] = np.zeros_like(p["words"]), np.zeros_like(p["chars"])
        np.add.at(g["words"], own, dx[:, :WORD_DIM])
        g["words"][0] = 0
        if len(b):
            np.add.at(g["chars"], b, (dx[:, WORD_DIM:] / np.maximum(count, 1)[:, None])[w])
        return g


def window_table(ids: np.ndarray) -> np.ndarray:
    """All windows of a text's word numbers, a row each; 0 pads the last one."""
    begins = np.array(window_starts(len(ids)))
    padded = np.zeros(int(begins[-1]) + WINDOW, ids.dtype)
    padded[: len(ids)] = ids
    return np.lib.stride_tricks.sliding_window_view(padded, WINDOW)[begins]


def train(rows: list[tuple[str, int]], seed: int = 8) -> Network | None:
    """rows: (text, label)."""
    # Words become numbers text by text, and windows rows of numbers, so that little more than these is held.
    place: dict[bytes, int] = {}
    tables, labels, seen = [], [], Counter()
    for t, y in rows:
        d = words_of(t)
        if not d:
            continue
        ids = np.fromiter((place.setdefault(w, len(place) + 1) for w in d), np.int32, len(d))
        seen.update(np.unique(ids).tolist())
        tables.append(window_table(ids))
        labels.append(y)
    if len(set(labels)) < 2:
        return None
    names = list(place)
    net = Network([names[i - 1] for i, n in seen.most_common(MOST_WORDS) if n >= LEAST_COUNT], seed)
    r = np.random.default_rng(seed)
    doc_y, sizes = np.array(labels), [len(t) for t in tables]
    table = np.concatenate(tables)
    del tables, place
    y_of = np.repeat(doc_y, sizes).astype(np.float32)
    starts = np.concatenate(([0], np.cumsum(sizes)[:-1]))
    m = {k: np.zeros_like(v) for k, v in net.p.items()}
    v2 = {k: np.zeros_like(v) for k, v in net.p.items()}
    step = 0
    per_epoch = max(1, 3 * min(int((doc_y == 1).sum()), 2000) // BATCH)
    epochs = max(EPOCHS, min(60, STEPS // per_epoch))
    for epoch in range(epochs):
        pos, neg = np.flatnonzero(y_of == 1), np.flatnonzero(y_of == 0)
        if epoch >= epochs // 4:
            if (epoch - epochs // 4) % max(1, epochs // 12) == 0:
                logit = scores(net, names, table)
            worst = np.array([s + int(logit[s:e].argmax()) for s, e in zip(starts, [*starts[1:], len(table)], strict=True)])
            pos = worst[doc_y == 1]
            hard = worst[doc_y == 0]
            most = max(512, 2 * len(pos))
            neg = np.concatenate((r.permutation(hard)[:most], r.permutation(neg)[:most]))
        else:
            size = min(len(pos), len(neg), 6000 * EPOCHS // epochs)
            pos, neg = r.permutation(pos)[:size], r.permutation(neg)[: 2 * size]
        pick = r.permutation(np.concatenate((pos, neg)))
        for at in range(0, len(pick), BATCH):
            part = pick[at : at + BATCH]
            ids = table[part].astype(np.int64)
            ids[(r.random(ids.shape) < 0.05) & (np.arange(WINDOW) > 0)] = 0
            own, local = np.unique(ids, return_inverse=True)
            local = local.reshape(ids.shape)
            if own[0] != 0:
                own, local = np.concatenate(([0], own)), local + 1
            g = net.gradients([names[i - 1] for i in own[1:]], local, y_of[part])
            step += 1
            rate = RATE * (1 if epoch < 3 * epochs // 4 else 0.3)
            for k, d in g.items():
                if k in ("words", "chars"):
                    net.p[k] *= 1 - rate * DECAY
                m[k] += 0.1 * (d - m[k])
                v2[k] += 0.001 * (d * d - v2[k])
                net.p[k] -= (rate * (m[k] / (1 - 0.9**step)) / (np.sqrt(v2[k] / (1 - 0.999**step)) + 1e-6)).astype(np.float32)
    return net


def scores(net: Network, names: list[bytes], table: np.ndarray) -> np.ndarray:
    gates = net.gates(net.inputs(names)[0])
    return np.concatenate([net.run(gates, table[i : i + 2048]) for i in range(0, len(table), 2048)])


class Scorer:
    """Scores texts with a table of known words' gate inputs that starts anew at a bounded size."""

    def __init__(self, net: Network):
        self.net = net
        self.reset()

    def reset(self) -> None:
        self.row: dict[bytes, int] = {}
        start = self.net.gates(self.net.inputs([])[0])
        self.gates = {k: np.empty((4096, 3 * HIDDEN), np.float32) for k in "fb"}
        for k in "fb":
            self.gates[k][0] = start[k][0]

    def learn(self, new: list[bytes]) -> None:
        at = len(self.row) + 1
        more = self.net.gates(self.net.inputs(new)[0])
        for k in "fb":
            if at + len(new) > len(self.gates[k]):
                grown = np.empty((max(2 * len(self.gates[k]), at + len(new)), 3 * HIDDEN), np.float32)
                grown[:at] = self.gates[k][:at]
                self.gates[k] = grown
            self.gates[k][at : at + len(new)] = more[k][1:]
        self.row.update(zip(new, range(at, at + len(new)), strict=True))

    def score(self, texts: list[str | None]) -> list[float]:
        docs = [words_of(t) for t in texts]
        if len(self.row) > KNOWN:
            self.reset()
        self.learn(list({w for d in docs for w in d} - self.row.keys()))
        tables, counts = [], []
        for d in docs:
            if not d:
                counts.append(0)
                continue
            tables.append(window_table(np.fromiter(map(self.row.__getitem__, d), np.int64, len(d))))
            counts.append(len(tables[-1]))
        out = [0.0] * len(texts)
        if tables:
            table = np.concatenate(tables)
            logit = np.concatenate([self.net.run(self.gates, table[i : i + 2048]) for i in range(0, len(table), 2048)])
            at = 0
            for k, n in enumerate(counts):
                if n:
                    out[k] = float(1 / (1 + np.exp(-np.float64(logit[at : at + n].max()))))
                    at += n
        return out


def sample(docs: DataFrame, labels: DataFrame, id_col: str, text: str, label: str, folds: int, held: int, most: int) -> list[tuple[str, int]]:
    fold = F.crc32(F.col(id_col).cast("string")) % folds
    known = labels.where(F.col(id_col).isNotNull() & F.col(label).isin(0, 1) & (fold != held)).select(id_col, F.col(label).alias("__y"))
    sizes = {r["__y"]: r["count"] for r in known.groupBy("__y").count().collect()}
    draw = F.crc32(F.concat(F.lit("sample|"), F.col(id_col).cast("string"))) / F.lit(2.0**32)
    rate = F.lit(0.0)
    for y, n in sizes.items():
        rate = F.when(F.col("__y") == y, min(1.0, most * (1 + (y == 0)) / n)).otherwise(rate)
    # At most about 3 * ``most`` rows of 12 bytes: the limit is a guard above the expected size.
    picked = stored(known.where(draw < rate).limit(4 * most), "labelled").select(F.col(id_col).alias("__id"), "__y")
    small = docs.select(id_col, text).where(F.col(text).isNotNull() & (F.length(text) <= SAMPLE_CHARS))
    got = small.join(F.broadcast(picked), F.col(id_col) == F.col("__id")).select(text, F.col("__y").cast("int").alias("y")).collect()
    return sorted((r[0], r[1]) for r in got)


def rate_texts(
    docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text: str = "text", label: str = "toxic", folds: int = 5, held: int = 0, most: int = SAMPLE
) -> DataFrame:
    """id, held_out, score, predicted of every row; learns labels of the other folds only."""
    net = train(sample(docs, labels, id_col, text, label, folds, held, most))
    shared = docs.sparkSession.sparkContext.broadcast(net)
    kind = docs.schema[id_col].dataType.simpleString()
    fold = F.crc32(F.col(id_col).cast("string")) % folds

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scorer = Scorer(shared.value) if shared.value is not None else None
        for batch in batches:
            texts, out, held_back, size = batch.column(2), [], [], 0
            for t in [*texts, None]:
                if t is not None:
                    held_back.append(t.as_py())
                    size += len(held_back[-1] or "")
                if size > 1_500_000 or t is None:  # about so many characters at a time
                    out += scorer.score(held_back) if scorer else [0.0] * len(held_back)
                    held_back, size = [], 0
            score = pa.array(out, pa.float64())
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), score, pa.array([int(x >= 0.5) for x in out], pa.int32())], names=[id_col, "held_out", "score", "predicted"])

    base = docs.select(F.col(id_col), F.coalesce(fold == held, F.lit(False)).alias("held_out"), F.col(text).alias("__text"))
    return base.mapInArrow(run, f"`{id_col}` {kind}, held_out boolean, score double, predicted int")
