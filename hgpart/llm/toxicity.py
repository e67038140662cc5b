"""Toxicity: a linear classifier on character n-grams scaled by naive Bayes log-count ratios."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import column_stretches, mix64, small_batches, tidy

#: Labelled rows of a class that are fitted on, the first by hash of their id.
MAX_PER_CLASS = 3_000
#: N-grams are counted in so many buckets; each feature is one bucket.
BUCKETS = 1 << 20
LENGTHS = (3, 4, 5)
#: Buckets that stay features, those with the largest weighted log-count ratios.
FEATURES = 30_000


def _codes(text: str) -> np.ndarray:
    return np.frombuffer(text.lower().encode("utf-32-le", "surrogatepass"), np.uint32).astype(np.uint64)


def bucket_arrays(texts: list[str]):
    """(bucket, text index) of every n-gram of every length, texts joined by a gap that no n-gram crosses."""
    codes = [_codes(f" {t} ") for t in texts]
    sizes = np.array([len(c) for c in codes], np.int64)
    if not len(sizes):
        return
    flat = np.concatenate(codes)
    owner = np.repeat(np.arange(len(codes), dtype=np.int32), sizes)
    run = np.zeros(len(flat), np.uint64)
    for n in range(1, max(LENGTHS) + 1):
        end = len(flat) - n + 1
        if end <= 0:
            return
        run = run[:end] * np.uint64(0x100000001B3) + flat[n - 1:] + np.uint64(1)
        if n in LENGTHS:
            whole = owner[:end] == owner[n - 1:]
            buckets = (mix64(run) & np.uint64(BUCKETS - 1)).astype(np.int32)
            yield buckets[whole], owner[:end][whole]


def _batches_of(texts: list[str], chars: int = 1 << 20):
    held, size, at = [], 0, 0
    for i, t in enumerate(texts):
        held.append(t)
        size += len(t)
        if size >= chars:
            yield at, held
            held, size, at = [], 0, i + 1
    if held:
        yield at, held


@dataclass
class Model:
    """``weight`` by bucket (0: no feature) and a bias; the score is the logistic of their sum over a text's distinct buckets."""

    buckets: np.ndarray
    weights: np.ndarray
    bias: float

    def score(self, texts: list[str]) -> np.ndarray:
        table = np.full(BUCKETS, -1, np.int32)
        table[self.buckets] = np.arange(len(self.buckets), dtype=np.int32)
        out = np.full(len(texts), self.bias)
        for at, part in _batches_of(texts):
            for buckets, owner in bucket_arrays(part):
                feature = table[buckets]
                on = feature >= 0
                pair = np.unique(owner[on].astype(np.int64) * len(self.buckets) + feature[on])
                out[at:at + len(part)] += np.bincount(pair // max(1, len(self.buckets)), weights=self.weights[pair % max(1, len(self.buckets))], minlength=len(part))
        return 1.0 / (1.0 + np.exp(-np.clip(out, -35, 35)))


def _pairs(texts: list[str]):
    """(text, bucket), each once, for a stretch of texts at a time."""
    for at, part in _batches_of(texts):
        for buckets, owner in bucket_arrays(part):
            pair = np.unique(owner.astype(np.int64) * BUCKETS + buckets)
            yield (pair // BUCKETS + at).astype(np.int32), (pair % BUCKETS).astype(np.int32)


def fit_arrays(texts: list[str], labels: np.ndarray, strength: float = 1e-4, rounds: int = 150, smooth: float = 1.0, features: int = FEATURES, least: int = 3) -> Model:
    """Logistic regression on presence times log-count ratio, by accelerated gradient steps.

    An n-gram of one length counts once a text. A first pass counts all buckets and picks the features, a second keeps
    theirs alone, in stretches that bound what a step holds: at most ``features`` buckets, each in at least ``least`` texts. Without texts of both classes the
    model is a constant: the smoothed share of positives.
    """
    y = np.asarray(labels, float)
    positive = y.sum()
    if not len(y) or positive in (0, len(y)):
        p = (positive + 1) / (len(y) + 2)
        return Model(np.zeros(0, np.int64), np.zeros(0), float(np.log(p / (1 - p))))
    with_p, total = np.zeros(BUCKETS), np.zeros(BUCKETS)
    for rows, cols in _pairs(texts):
        with_p += np.bincount(cols, weights=y[rows], minlength=BUCKETS)
        total += np.bincount(cols, minlength=BUCKETS)
    # shares of texts, not of n-grams: long texts of one class don't shift the ratio
    ratio = np.log((with_p + smooth) / (positive + 2 * smooth)) - np.log((total - with_p + smooth) / (len(y) - positive + 2 * smooth))
    rank = np.where(total >= least, np.abs(ratio) * np.sqrt(total), 0.0)
    chosen = np.sort(np.argsort(-rank, kind="stable")[:features])
    chosen = chosen[rank[chosen] > 0]
    index = np.full(BUCKETS, -1, np.int32)
    index[chosen] = np.arange(len(chosen), dtype=np.int32)
    held = []
    for rows, cols in _pairs(texts):
        col = index[cols]
        held.append((rows[col >= 0], col[col >= 0]))
    r = ratio[chosen]
    n, m = len(y), len(chosen)
    # classes count alike
    share = np.where(y == 1, 0.5 / positive, 0.5 / (n - positive))

    def times(w):
        z = np.zeros(n)
        x = r * w
        for row, col in held:
            z += np.bincount(row, weights=x[col], minlength=n)
        return z

    def back(g):
        out = np.zeros(m)
        for row, col in held:
            out += np.bincount(col, weights=g[row], minlength=m)
        return r * out

    # the largest curvature, by power iteration
    v, top = np.ones(m), 1.0
    for _ in range(12):
        v /= max(1e-300, np.linalg.norm(v))
        v = back(share * times(v))
        top = np.linalg.norm(v)
    step = 1.0 / (0.3 * (top + 1.0) + strength)
    w, b, old_w, old_b = np.zeros(m), 0.0, np.zeros(m), 0.0
    for k in range(rounds):
        momentum = k / (k + 3)
        look_w, look_b = w + momentum * (w - old_w), b + momentum * (b - old_b)
        z = times(look_w) + look_b
        g = share * (1.0 / (1.0 + np.exp(-np.clip(z, -35, 35))) - y)
        old_w, old_b = w, b
        w = look_w - step * (back(g) + strength * look_w)
        b = look_b - step * float(g.sum())
    return Model(chosen.astype(np.int64), w * r, b)


def fit_toxicity(labelled: DataFrame, text_col: str = "text", label_col: str = "toxic") -> Model:
    """Fit in one task on ``labelled`` (bounded by the caller); only the model reaches the driver.

    Null labels are left out; null texts are empty.
    """

    def run(batches):
        parts = [b for b in batches if len(b)]
        pdf = pd.concat(parts) if parts else pd.DataFrame({"text": [], "y": []})
        pdf = pdf.sort_values(["y", "text"], kind="stable")
        model = fit_arrays(pdf["text"].tolist(), pdf["y"].to_numpy(float))
        yield pd.DataFrame({"buckets": [model.buckets.tobytes()], "weights": [model.weights.tobytes()], "bias": [model.bias]})

    rows = labelled.filter(F.col(label_col).isNotNull()).select(F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"), F.col(label_col).cast("int").alias("y"))
    got = rows.repartition(1).mapInPandas(tidy(run), "buckets binary, weights binary, bias double").collect()
    if not got:
        return fit_arrays([], np.zeros(0))
    return Model(np.frombuffer(got[0]["buckets"], np.int64), np.frombuffer(got[0]["weights"], np.float64), got[0]["bias"])


def held_out(id_col: str) -> Column:
    """crc32 of the id as text leaves 1 modulo 3; null ids are held out of training too."""
    return F.coalesce(F.crc32(F.col(id_col).cast("string").cast("binary")) % 3 == 1, F.lit(True))


def training_rows(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic", per_class: int = MAX_PER_CLASS) -> DataFrame:
    """(text, label) of at most ``per_class`` labelled rows a class, not held out, the first by a hash of the id.

    Labels are picked first, so what is joined to the documents is small by
    that bound and broadcast. An id labelled both ways is left out.
    """
    own = labels.filter(F.col(id_col).isNotNull() & F.col(label_col).isNotNull() & ~held_out(id_col)).groupBy(id_col).agg(F.min(label_col).alias("_lo"), F.max(label_col).alias("_hi")).filter("_lo = _hi").select(F.col(id_col).alias("_id"), F.col("_lo").alias("_y"))
    picked = None
    for y in (0, 1):
        part = own.filter(F.col("_y") == y).orderBy(F.xxhash64("_id"), "_id").limit(per_class)
        picked = part if picked is None else picked.union(part)
    return docs.select(F.col(id_col).alias("_id"), F.col(text_col).alias("text")).join(F.broadcast(picked), "_id").select("text", F.col("_y").alias("toxic"))


def score_toxicity(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text", threshold: float = 0.7, carry: tuple[str, ...] = ()) -> DataFrame:
    """One row per document: id, held_out, score, predicted, and the ``carry`` columns. No shuffle.

    Null and empty texts get the score of an empty text. Repeated rows and null ids are returned. Columns to carry that are named like a result column give way to it.
    """
    small_batches(docs.sparkSession)
    carry = tuple(c for c in carry if c not in ("held_out", "score", "predicted"))
    columns = list(dict.fromkeys([id_col, *carry]))
    kind = {f.name: f.dataType.simpleString() for f in docs.schema}

    def run(batches):
        for batch in batches:
            scores = np.concatenate([np.zeros(0), *(model.score([t or "" for t in part]) for _, part in column_stretches(batch.column("body"), 4 << 20))])
            names = [n for n in batch.schema.names if n != "body"]
            yield pa.RecordBatch.from_arrays([*(batch.column(n) for n in names), pa.array(scores, pa.float64())], [*names, "score"])

    rows = docs.select(*[F.col(c).alias(f"c{i}") for i, c in enumerate(columns)], F.col(text_col).cast("string").alias("body"))
    out = rows.mapInArrow(tidy(run), "".join(f"c{i} {kind[c]}, " for i, c in enumerate(columns)) + "score double")
    out = out.select(*[F.col(f"c{i}").alias(c) for i, c in enumerate(columns)], "score")
    return out.select(id_col, held_out(id_col).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"), *[c for c in carry if c != id_col])
