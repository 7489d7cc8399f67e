"""Toxicity by multiple-instance learning: a document is a bag of sentences, its probability is the noisy-or of theirs.

A sentence's log-odds is a bias plus the sum of its distinct words' weights; a word's weight is the sum over hashed features
(the word and its prefixes). Only document labels train it; the sentence scores then locate what offends. The model is fitted
on a bounded sample of labelled rows (``most_rows`` and ``most_bytes`` of whole texts of each label, by hash order); every text is scored whole.

Edge cases: null and empty texts score as a bag of no sentence (the noisy-or of nothing, 0); with no labelled row, or
one label only, the model has no weight and scores are 0; rows with null labels are not learnt from; equal
labels of a document are one row of the fit, though each counts in the labels' shares; documents that share an id are learnt from together, or not at all where they pass
``most_bytes``; extra columns are kept by ``reject`` and ignored elsewhere."""

from __future__ import annotations

import re
from array import array

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common as C

BITS = 18
_EDGE = re.compile(r"^[\W_]+|[\W_]+$")
_STOP = re.compile(rb"[.!?]+(?=[\x20\t\n\r\x0b\x0c])|\n+")


def features(word: str) -> list[int]:
    w = word.lower()
    names = [w, *(f"{w[:k]}*" for k in (3, 4, 5, 6) if len(w) > k)]
    return [xxhash.xxh3_64_intdigest(x, 3) >> (64 - BITS) for x in names]


def sentences(text: bytes | None) -> list[tuple[int, int]]:
    """Byte spans of the sentences: up to a full stop and white space, or a line's end."""
    out, at = [], 0
    for m in _STOP.finditer(text or b""):
        out.append((at, m.end()))
        at = m.end()
    if text and at < len(text):
        out.append((at, len(text)))
    return out


def plain(word: bytes) -> str:
    return _EDGE.sub("", word.decode("utf-8", "replace"))


class Model:
    """Weights of hashed features, and a bias."""

    def __init__(self, weight: np.ndarray | None = None, bias: float = 0.0):
        self.weight, self.bias = weight, bias

    def word(self, raw: bytes) -> float:
        w = plain(raw)
        return float(self.weight[features(w)].sum()) if w else 0.0

    def scorer(self):
        memo = C.Memo(self.word)

        def score(text: bytes | None) -> np.ndarray:
            """Probability of each sentence."""
            if self.weight is None or not text:
                return np.zeros(len(sentences(text)))
            odds = [self.bias + sum(map(memo.__getitem__, set(text[lo:hi].split()))) for lo, hi in sentences(text)]
            return 1 / (1 + np.exp(-np.clip(np.array(odds), -30, 30)))

        return score


def noisy_or(p: np.ndarray) -> float:
    return float(-np.expm1(np.log1p(-np.minimum(p, 1 - 1e-12)).sum())) if len(p) else 0.0


def _useful(doc, word, owner, feat, y, least_z: float) -> np.ndarray:
    """1.0 at the features of positive association with label 1."""
    per = np.bincount(owner, minlength=word.max() + 1)
    head = np.cumsum(per) - per
    in1, in0 = np.zeros(1 << BITS), np.zeros(1 << BITS)
    cut = np.searchsorted(doc, np.arange(0, len(y) + 256, 256))
    for lo, hi in zip(cut[:-1], cut[1:]):  # some documents at a time, so that memory stays small
        w = word[lo:hi]
        n = per[w]
        f = feat[np.repeat(head[w] - (np.cumsum(n) - n), n) + np.arange(n.sum())]
        both = np.unique(np.repeat(doc[lo:hi].astype(np.int64), n) << 32 | f)
        d, f = both >> 32, both & 0xFFFFFFFF
        in1 += np.bincount(f[y[d] > 0], minlength=1 << BITS)
        in0 += np.bincount(f[y[d] == 0], minlength=1 << BITS)
    n1, n0 = y.sum(), len(y) - y.sum()
    p = (in1 + in0 + 1) / (n1 + n0 + 2)
    z = (in1 / n1 - in0 / n0) / np.sqrt(p * (1 - p) * (1 / n1 + 1 / n0))
    return ((z > least_z) & (in1 >= 4)).astype(float)


def gradient(z: np.ndarray, doc: np.ndarray, y: np.ndarray, cost: np.ndarray) -> tuple[np.ndarray, float]:
    """Derivative of the mean weighted log-likelihood of the documents' labels by the log-odds z of their sentences, and that likelihood."""
    p = 1 / (1 + np.exp(-z))
    keep = np.bincount(doc, np.log1p(-np.minimum(p, 1 - 1e-9)), len(y))  # log of the chance that no sentence offends
    hit = np.maximum(-np.expm1(keep), 1e-9)
    # -p for a clean document, p * (1 - P) / P for a toxic one
    g = np.where(y[doc] > 0, p * ((1 - hit) / hit)[doc], -p) * cost[doc] / len(y)
    return g, float((cost * np.where(y > 0, np.log(hit), keep)).sum() / len(y))


def fit(rows: list[tuple[bytes | None, int]], counts: tuple[int, int] | None = None, rounds: int = 120, rate: float = 0.1, ridge: float = 1e-5, least_z: float = 5.0) -> Model:
    """Full-batch Adam on the noisy-or likelihood of document labels.

    Only features whose presence in documents of label 1 exceeds that in documents of label 0 by ``least_z`` standard errors get
    a weight. ``counts`` are all labelled rows of each label, to which the sample is weighted back."""
    if len({y for _, y in rows}) < 2:
        return Model()
    vocab: dict[str, int] = {}
    words, sent_len, doc_len, label = [], [], [], []
    for text, y in rows:
        spans = sentences(text)
        if not spans:
            continue
        for lo, hi in spans:
            own = {vocab.setdefault(w, len(vocab)) for w in map(plain, set(text[lo:hi].split())) if w}
            words.append(np.fromiter(own, np.int32, len(own)))
            sent_len.append(len(own))
        doc_len.append(len(spans))
        label.append(y)
    if not words:
        return Model()
    word = np.concatenate(words)
    words.clear()
    sent = np.repeat(np.arange(len(sent_len), dtype=np.int32), sent_len)
    doc = np.repeat(np.arange(len(doc_len), dtype=np.int32), doc_len)
    y, n_words = np.array(label, float), len(vocab)
    flat, sizes = array("i"), array("b")
    for w in vocab:
        f = features(w)
        flat.extend(f)
        sizes.append(len(f))
    owner, feat = np.repeat(np.arange(len(vocab), dtype=np.int32), np.frombuffer(sizes, np.int8)), np.frombuffer(flat, np.int32)
    have = np.array([len(y) - y.sum(), y.sum()])
    real = np.array(counts if counts else have, float)
    cost = np.where(y > 0, real[1] / have[1], real[0] / have[0]) * len(y) / real.sum()
    useful = _useful(doc[sent], word, owner, feat, y, least_z)
    vocab.clear()
    w, b = np.zeros(1 << BITS), -5.0
    m, v, mb, vb = np.zeros_like(w), np.zeros_like(w), 0.0, 0.0
    for t in range(1, rounds + 1):
        ww = np.bincount(owner, w[feat], n_words)
        z = np.clip(b + np.bincount(sent, ww[word], len(sent_len)), -30, 30)
        gz, _ = gradient(z, doc, y, cost)
        gw = np.bincount(word, gz[sent], n_words)
        g = (np.bincount(feat, gw[owner], 1 << BITS) - ridge * w) * useful
        gb = gz.sum()
        m, v = 0.9 * m + 0.1 * g, 0.99 * v + 0.01 * g * g
        mb, vb = 0.9 * mb + 0.1 * gb, 0.99 * vb + 0.01 * gb * gb
        c1, c2 = 1 - 0.9**t, 1 - 0.99**t
        w += rate * (m / c1) / (np.sqrt(v / c2) + 1e-7)
        b += rate * (mb / c1) / (np.sqrt(vb / c2) + 1e-7)
    return Model(w, b)


def train(docs: DataFrame, labels: DataFrame, most_rows: int = 2000, exclude=None, most_bytes: int = 64 << 20) -> Model:
    """Fit on at most ``most_rows`` documents and ``most_bytes`` of text of each label, the first by hash whose texts still fit whole; ``exclude`` names
    rows not to learn from."""
    lab = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("toxic").cast("int").alias("toxic")).where("toxic in (0, 1) and doc_id is not null")
    if exclude is not None:
        lab = lab.where(~exclude)
    seen = {r.toxic: r["count"] for r in lab.groupBy("toxic").count().collect()}
    picked = []
    for y in (0, 1):
        picked += [(r.doc_id, y) for r in lab.where(F.col("toxic") == y).orderBy(F.xxhash64("doc_id"), "doc_id").limit(most_rows).collect()]
    if not picked:
        return Model()
    picked = list(dict.fromkeys(picked))
    spark, text = docs.sparkSession, F.col("text").cast("string")

    def of(ids: list[tuple[int, int]], *columns) -> DataFrame:
        """The rows of the chosen ids, at most 2 * most_rows by construction, so that side can be broadcast at any corpus size."""
        return docs.select(F.col("doc_id").cast("long").alias("doc_id"), *columns).join(F.broadcast(spark.createDataFrame(ids, "doc_id long, toxic int")), "doc_id")

    size = {(r.doc_id, r.toxic): r.size for r in of(picked, (F.coalesce(F.octet_length(text), F.lit(0)) + 16).cast("long").alias("n")).groupBy("doc_id", "toxic").agg(F.sum("n").alias("size")).collect()}
    room, fitting = {0: most_bytes, 1: most_bytes}, []
    for key in picked:
        if key in size and size[key] <= room[key[1]]:
            room[key[1]] -= size[key]
            fitting.append(key)
    if not fitting:
        return Model()
    rows = of(fitting, text.cast("binary").alias("text")).collect()
    return fit([(bytes(r.text) if r.text is not None else None, r.toxic) for r in sorted(rows, key=lambda r: (r.doc_id, r.toxic))], (seen.get(0, 0), seen.get(1, 0)))


def score(docs: DataFrame, model: Model, threshold: float = 0.3, *keep: str) -> DataFrame:
    """``keep`` columns, score, predicted, and the worst sentence's byte span and score (null without sentences)."""
    shared = docs.sparkSession.sparkContext.broadcast((model.weight, model.bias))  # of a fixed size
    rest, text = F.struct(*keep).alias("_rest"), F.col("text").cast("string").alias("text")
    src = docs.withColumn("text", text).select(rest) if "text" in keep else docs.select(rest, text)

    def run(batches):
        scorer = Model(*shared.value).scorer()
        for batch in batches:
            s, where, worst = [], [], []
            for t in C.texts(batch):
                p = scorer(t)
                s.append(noisy_or(p))
                k = int(p.argmax()) if len(p) else None
                where.append(None if k is None else list(sentences(t)[k]))
                worst.append(None if k is None else float(p[k]))
            yield pa.record_batch([batch.column(0), pa.array(s, pa.float64()), pa.array([int(x >= threshold) for x in s], pa.int32()), pa.array(where, pa.list_(pa.int64())), pa.array(worst, pa.float64())], names=["_rest", "score", "predicted", "worst_span", "worst_score"])

    out = src.mapInArrow(C.task(run), f"_rest {src.schema['_rest'].dataType.simpleString()}, score double, predicted int, worst_span array<bigint>, worst_score double")
    return out.select("_rest.*", "score", "predicted", "worst_span", "worst_score")


def reject(docs: DataFrame, model: Model, threshold: float = 0.3) -> DataFrame:
    """The rows of ``docs``, all columns, whose score is below the threshold."""
    return score(docs, model, threshold, *docs.columns).where("predicted = 0").select(*docs.columns)


def op3_toxicity(spark, sf_dir: str) -> DataFrame:
    docs = C.table(spark, sf_dir, "documents")
    model = train(docs, C.table(spark, sf_dir, "labels"), exclude=C.held_out(4, 2))
    return score(docs, model, 0.3, "doc_id").select("doc_id", C.held_out(4, 2).alias("held_out"), "score", "predicted")
