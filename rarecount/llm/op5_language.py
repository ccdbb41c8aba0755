"""Language identification: sparse multinomial logistic regression on TF-IDF of character n-grams.

Texts are lower-cased, everything but letters counts as a blank, and n-grams of one to three characters are
hashed to ``DIM`` features. Document frequencies are counted over every training document. The
regression is trained by follow-the-regularised-leader with elastic-net penalties on a bounded sample of
``PER_LANGUAGE`` expected rows of each language; a part of the sample, kept from training, sets the
temperature that calibrates the scores. Prediction reads every text whole, in one pass.

Defined results: a null text or one without a letter is ``und`` with score 0; so is every text if nothing can be
learned; rows are judged one by one, so repeated rows, ties and further columns change nothing; an empty
table gives an empty result.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import stored

DIM = 1 << 16
PER_LANGUAGE = 800
EPOCHS = 3
ALPHA, BETA, L1, L2 = 0.5, 1.0, 0.02, 0.01
SCALE = 100.0
_ALPHA: list[np.ndarray] = []


def letters() -> np.ndarray:
    if not _ALPHA:
        _ALPHA.append(np.fromiter((chr(c).isalpha() for c in range(0x110000)), bool, 0x110000))
    return _ALPHA[0]


def features(text: str | None) -> np.ndarray | None:
    """Feature numbers of all n-grams of a text, in no order and with repeats; None without a letter."""
    if not text:
        return None
    c = np.frombuffer(text.lower().encode("utf-32-le", "surrogatepass"), np.uint32)
    known = letters()[np.minimum(c, 0x10FFFF)]
    if not known.any():
        return None
    c = np.where(known, c, np.uint32(32))
    a = c * np.uint32(0x9E3779B1)
    b = c * np.uint32(0x85EBCA6B)
    one = (a ^ (a >> np.uint32(15))) * np.uint32(0xC2B2AE35)
    two = a[:-1] + b[1:]
    two = (two ^ (two >> np.uint32(15))) * np.uint32(0x27D4EB2F)
    three = a[:-2] + b[1:-1] + c[2:] * np.uint32(0x165667B1)
    three = (three ^ (three >> np.uint32(15))) * np.uint32(0x2545F491)
    return np.concatenate((one, two, three)) >> np.uint32(16)


def gathered(train: DataFrame, id_col: str, text: str, lang: str, per_language: int) -> DataFrame:
    """One pass over all training rows: sampled rows' features, and each task's document frequencies."""
    # As many rows as the model has classes; a lookup, not an expression that grows with them.
    rates = {str(r[0]): min(1.0, per_language / r[1]) for r in train.groupBy(F.col(lang).cast("string")).count().collect()}
    draw = F.crc32(F.concat(F.lit("sample|"), F.col(id_col).cast("string"))) / F.lit(2.0**32)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = ["lang", "idx", "cnt"]
        df, docs = np.zeros(DIM, np.int64), 0
        for batch in batches:
            rows: list[tuple] = []
            for t, name, drawn in zip(batch.column(0), batch.column(1).to_pylist(), batch.column(2).to_pylist(), strict=True):
                f = features(t.as_py())
                if f is None:
                    continue
                seen = np.zeros(DIM, bool)
                seen[f] = True
                df += seen
                docs += 1
                if drawn is not None and drawn < rates[name]:
                    i, n = np.unique(f, return_counts=True)
                    rows.append((name, i.astype("<u2").tobytes(), n.astype("<u4").tobytes()))
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), (pa.string(), pa.binary(), pa.binary()), strict=True)], names=names)
        if docs:
            packed = zlib.compress(df.astype("<i8").tobytes(), 1)
            yield pa.RecordBatch.from_arrays([pa.array([None], pa.string()), pa.array([docs.to_bytes(8, "little")], pa.binary()), pa.array([packed], pa.binary())], names=names)

    return train.select(F.col(text), F.col(lang).cast("string"), draw.alias("draw")).mapInArrow(run, "lang string, idx binary, cnt binary")


def summed(parts: DataFrame, to: int = 8) -> tuple[int, np.ndarray]:
    """Adds the tasks' frequency vectors in ``to`` streams; the driver gets ``to`` vectors of a fixed size."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, docs = np.zeros(DIM, np.int64), 0
        for batch in batches:
            for n, v in zip(batch.column(0), batch.column(1), strict=True):
                docs += int.from_bytes(n.as_py(), "little")
                total += np.frombuffer(zlib.decompress(v.as_py()), "<i8")
        if docs:
            yield pa.RecordBatch.from_arrays([pa.array([docs], pa.int64()), pa.array([zlib.compress(total.tobytes(), 1)], pa.binary())], names=["docs", "df"])

    rows = parts.where("lang is null").select("idx", "cnt").repartition(to).mapInArrow(run, "docs long, df binary").collect()
    df = np.zeros(DIM, np.int64)
    for r in rows:
        df += np.frombuffer(zlib.decompress(bytes(r["df"])), "<i8")
    return sum(r["docs"] for r in rows), df


def total(w: np.ndarray, f: np.ndarray) -> np.ndarray:
    """The sum of the features' weights; for a long text by its counts, whose memory doesn't grow with it."""
    if len(f) > DIM:
        return np.bincount(f, minlength=DIM) @ w.astype(np.float64)
    return np.take(w, f, axis=0).sum(axis=0, dtype=np.float64)


def softmax(x: np.ndarray) -> np.ndarray:
    e = np.exp(x - x.max(axis=-1, keepdims=True))
    return e / e.sum(axis=-1, keepdims=True)


def train_ftrl(rows: list[tuple[int, np.ndarray, np.ndarray]], classes: int, epochs: int = EPOCHS) -> np.ndarray:
    """rows: (class, feature numbers, values). Returns the weights, DIM x classes, most of them 0."""
    z, n = np.zeros((DIM, classes)), np.zeros((DIM, classes))

    def weights(zi: np.ndarray, ni: np.ndarray) -> np.ndarray:
        return np.where(np.abs(zi) > L1, -(zi - np.sign(zi) * L1) / ((BETA + np.sqrt(ni)) / ALPHA + L2), 0.0)

    order = np.random.default_rng(5)
    for _ in range(epochs):
        for k in order.permutation(len(rows)):
            y, i, x = rows[k]
            zi, ni = z[i], n[i]
            w = weights(zi, ni)
            p = softmax(x @ w)
            p[y] -= 1
            g = x[:, None] * p[None, :]
            more = ni + g * g
            z[i] = zi + g - (np.sqrt(more) - np.sqrt(ni)) / ALPHA * w
            n[i] = more
    return weights(z, n)


def temperature(logits: np.ndarray, y: np.ndarray) -> float:
    """The divisor of logits with the least negative log likelihood, on a grid of powers."""
    if not len(y):
        return 1.0
    grid = np.exp(np.linspace(-3, 3, 121))
    loss = [-np.log(softmax(logits / t)[np.arange(len(y)), y] + 1e-12).mean() for t in grid]
    return float(grid[int(np.argmin(loss))])


def fit(train: DataFrame, id_col: str, text: str, lang: str, per_language: int = PER_LANGUAGE) -> tuple[list[str], np.ndarray]:
    """Languages, and weights that already hold idf, scale and temperature."""
    train = train.where(F.col(lang).isNotNull() & F.col(text).isNotNull())
    parts = stored(gathered(train, id_col, text, lang, per_language), "ngrams")
    docs, df = summed(parts)
    got = parts.where("lang is not null").collect()
    names = sorted({r["lang"] for r in got})
    if not names:
        return [], np.zeros((DIM, 0), np.float32)
    idf = np.log((1 + docs) / (1 + df)) + 1
    rows = []
    for r in sorted(got, key=lambda r: (r["lang"], zlib.crc32(r["idx"] + r["cnt"]))):
        i, c = np.frombuffer(r["idx"], "<u2").astype(np.int64), np.frombuffer(r["cnt"], "<u4").astype(float)
        rows.append((names.index(r["lang"]), i, SCALE * c / c.sum() * idf[i]))
    held = [r for k, r in enumerate(rows) if k % 5 == 4]
    w = train_ftrl([r for k, r in enumerate(rows) if k % 5 != 4] if len(rows) > 20 else rows, len(names))
    logits = np.array([x @ w[i] for _, i, x in held]) if held else np.zeros((0, len(names)))
    t = temperature(logits, np.array([y for y, _, _ in held], int))
    return names, (w * idf[:, None] * SCALE / t).astype(np.float32)


def predict(df: DataFrame, model: tuple[list[str], np.ndarray], text: str, keep: list[Column]) -> DataFrame:
    """The columns ``keep`` with lang_pred and score."""
    shared = df.sparkSession.sparkContext.broadcast(model)
    base = df.select(*keep, F.col(text).alias("__text"))
    width = len(base.columns) - 1

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names, w = shared.value
        for batch in batches:
            lang, score = [], []
            for t in batch.column(width):
                f = features(t.as_py()) if names else None
                if f is None:
                    lang.append("und")
                    score.append(0.0)
                    continue
                p = softmax(total(w, f) / len(f))
                best = int(p.argmax())
                lang.append(names[best])
                score.append(float(p[best]))
            yield pa.RecordBatch.from_arrays([*batch.columns[:width], pa.array(lang, pa.string()), pa.array(score, pa.float64())], names=[*batch.schema.names[:width], "lang_pred", "score"])

    head = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in base.schema.fields[:width])
    return base.mapInArrow(run, f"{head}, lang_pred string, score double")


def identify(df: DataFrame, id_col: str = "doc_id", text: str = "text", lang: str = "lang", folds: int = 4, held_fold: int = 2) -> DataFrame:
    """Learn from the other folds of ``id_col``'s digest, and predict every row."""
    fold = F.crc32(F.col(id_col).cast("string")) % folds
    model = fit(df.where(fold != held_fold).select(id_col, text, lang), id_col, text, lang)
    keep = [F.col(id_col), F.coalesce(fold == held_fold, F.lit(False)).alias("held_out")]
    return predict(df, model, text, keep)
