"""Language identification by segmentation-marginalised unigrams over the fixed public pieces.

Each language has a probability for every piece. A word's likelihood is the sum over all its segmentations into pieces of the whole
vocabulary (forward algorithm); characters without a piece count as an unknown piece. Words are the letters, in their own case, and the
marks upon them of each white-space word, behind the vocabulary's word mark; other characters are left out. Training takes one expectation step from
uniform pieces: forward-backward expected counts over all words of all training rows, in every task over its distinct words, summed by
(lang, piece) in Spark, so what reaches the driver is bounded by languages times pieces. Substrings are looked up by rolling
code-point hashes for all words of a block at once; words of more than ``SHORT`` code points go one by one with rescaled sums, which
gives the same value at any length.

Edge cases: null texts and texts without a letter get ``und`` and score 0; null langs are not learnt from; without any
training row every text gets ``und``; ties go to the language first in order; repeated rows count as often
as they occur; extra columns are ignored."""

from __future__ import annotations

import unicodedata
from collections import Counter
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common as C
from . import pieces as P

#: Code points of the longest word that is worked on together with others: its likelihood fits a double at any vocabulary.
SHORT = 20
_SALT = C.U64(0x2545F4914F6CDD1D)


def _extend(h: np.ndarray, code: np.ndarray) -> np.ndarray:
    """Hashes of substrings, one code point longer."""
    h = (h + code + C.U64(1)) * _SALT
    return h ^ (h >> C.U64(29))


@lru_cache(2)
def _known(path: str) -> tuple[dict[str, int], int, int]:
    """Ids of the normal pieces, code points of the longest one, and the vocabulary's size."""
    names, _, types = P.vocabulary(path)
    known = {p: i for i, (p, t) in enumerate(zip(names, types)) if t == 1 and p}
    return known, max(map(len, known), default=1), len(names)


@lru_cache(2)
def _lookup(path: str):
    """Per length: sorted hashes of the pieces, their ids, and a bit map of the hashes' top bits; the longest length; the vocabulary's size."""
    known, widest, size = _known(path)
    by: dict[int, list[str]] = {}
    for p in known:
        by.setdefault(len(p), []).append(p)
    out = {}
    for n, names in by.items():
        h = np.zeros(len(names), C.U64)
        codes = np.frombuffer("".join(names).encode("utf-32-le"), np.uint32).reshape(-1, n).astype(C.U64)
        for k in range(n):
            h = _extend(h, codes[:, k])
        order = np.argsort(h)
        h = h[order]
        bits = np.zeros(1 << 20, bool)
        bits[h >> C.U64(44)] = True
        out[n] = h, np.array([known[p] for p in names], np.int64)[order], bits
    return out, widest, size


def _tables(codes: np.ndarray, path: str) -> list:
    """[(n, ids)]: for each piece length, the piece id at every (start, word), or -1; single characters fall back to the unknown
    piece, whose id is the vocabulary's size. ``codes`` is (code point, word)."""
    found, widest, size = _lookup(path)
    out, wide = [], codes.astype(C.U64)
    h = np.zeros(codes.shape, C.U64)
    for n in range(1, min(widest, len(codes)) + 1):
        h = _extend(h[: len(codes) - n + 1], wide[n - 1 :])
        ids = np.full(h.shape, size if n == 1 else -1, np.int64)
        if n in found:
            keys, who, bits = found[n]
            flat = h.ravel()
            maybe = np.flatnonzero(bits[flat >> C.U64(44)])
            own = flat[maybe]
            at = np.minimum(np.searchsorted(keys, own), len(keys) - 1)
            ok = keys[at] == own
            ids.ravel()[maybe[ok]] = who[at[ok]]
        out.append((n, ids))
    return out


def _marked(words: list[str]) -> dict[int, tuple[np.ndarray, np.ndarray]]:
    """Words by length: their positions, and code points with the word mark in front as (code point, word)."""
    by: dict[int, list[int]] = {}
    for i, w in enumerate(words):
        if len(w) <= SHORT:
            by.setdefault(len(w) + 1, []).append(i)
    out = {}
    for n, at in by.items():
        flat = np.frombuffer("".join(["▁" + words[i] for i in at]).encode("utf-32-le"), np.uint32)
        out[n] = np.array(at), np.ascontiguousarray(flat.reshape(-1, n).T)
    return out


def _matches(word: str, path: str):
    """(start, [(code points, id)]) of the marked word's pieces, in order of start; single characters always have an entry."""
    known, widest, size = _known(path)
    for i in range(len(word)):
        found = [(1, known.get(word[i], size))]
        for k in range(2, min(widest, len(word) - i) + 1):
            if (x := known.get(word[i : i + k])) is not None:
                found.append((k, x))
        yield i, found


def long_likelihood(word: str, prob: np.ndarray, path: str) -> np.ndarray:
    """The same for one word of any length; prob is (pieces + 1, languages). Only the sums that a piece can reach are held, and they are rescaled."""
    marked, width = "▁" + word, _known(path)[1]
    ahead = np.zeros((width + 1, prob.shape[1]))  # sums of the ends 0.. from the present start
    ahead[0] = 1
    scale = np.zeros(prob.shape[1])
    for i, found in _matches(marked, path):
        for k, x in found:
            ahead[k] += ahead[0] * prob[x]
        ahead[:-1] = ahead[1:]
        ahead[-1] = 0
        if i % 8 == 7:
            top = np.maximum(ahead.max(axis=0), 1e-300)
            ahead /= top
            scale += np.log(top)
    return np.log(np.maximum(ahead[0], 1e-300)) + scale


def likelihoods(words: list[str], logp: np.ndarray, path: str) -> np.ndarray:
    """Log of the sum over segmentations, per word and language; logp is (languages, pieces + 1)."""
    prob = np.ascontiguousarray(np.exp(logp).T)
    out = np.zeros((len(words), len(logp)))
    for n, (at, codes) in _marked(words).items():
        for lo in range(0, len(at), 8192):
            part = codes[:, lo : lo + 8192]
            tables = _tables(part, path)
            alpha = np.zeros((n + 1, part.shape[1], len(logp)))
            alpha[0] = 1
            for end in range(1, n + 1):
                for k, ids in tables:
                    if k > end:
                        break
                    i = ids[end - k]
                    if k == 1:
                        alpha[end] += alpha[end - 1] * prob[i]
                    elif (hit := np.flatnonzero(i >= 0)).size:
                        alpha[end, hit] += alpha[end - k, hit] * prob[i[hit]]
            out[at[lo : lo + 8192]] = np.log(np.maximum(alpha[n], 1e-300))
    for i, w in enumerate(words):
        if len(w) > SHORT:
            out[i] = long_likelihood(w, prob, path)
    return out


def _long_expected(word: str, times: float, path: str, total: np.ndarray) -> None:
    """Add the expected counts of one word of any length: sums per code point are kept with a common exponent each."""
    marked, (_, width, size) = "▁" + word, _known(path)
    n, p = len(marked), 1.0 / size
    found = [f for _, f in _matches(marked, path)]
    a, b = np.zeros(n + 1 + width), np.zeros(n + 1 + width)  # a[i] * exp(sa[i]) is the sum of the ways to i
    sa, sb = np.zeros(n + 1), np.zeros(n + 1)
    a[0], now = 1.0, 0.0
    for i in range(n):
        if i and i % 16 == 0:  # rescale the sums that pieces from here on use and fill
            top = a[i : i + width].max()
            a[i : i + width + 1] /= top
            now += np.log(top)
        sa[i] = now
        for k, _ in found[i]:
            a[i + k] += a[i] * p
    sa[n] = now
    b[n], now = 1.0, 0.0
    for i in range(n - 1, -1, -1):
        # sums behind i lie at the exponents they were made with
        b[i] = sum(p * b[i + k] * np.exp(sb[i + k] - now) for k, _ in found[i])
        sb[i] = now
        if i % 16 == 0:
            now += np.log(b[i])
            b[i], sb[i] = 1.0, now
    whole = np.log(a[n]) + sa[n]
    for i in range(n):
        for k, x in found[i]:
            total[x] += times * p * a[i] * b[i + k] * np.exp(sa[i] + sb[i + k] - whole)


def expected(words: list[str], times: np.ndarray, path: str) -> np.ndarray:
    """Expected piece counts of the words under uniform pieces (forward-backward over all segmentations)."""
    size = _known(path)[2]
    p = 1.0 / size
    total = np.zeros(size + 1)
    for n, (at, codes) in _marked(words).items():
        for lo in range(0, len(at), 8192):
            part, t = codes[:, lo : lo + 8192], times[at[lo : lo + 8192]]
            tables = [(k, start, hit, ids[start][hit]) for k, ids in _tables(part, path) for start in range(n - k + 1) if (hit := np.flatnonzero(ids[start] >= 0)).size]
            a, b = np.zeros((n + 1, part.shape[1])), np.zeros((n + 1, part.shape[1]))
            a[0] = b[n] = 1
            for k, start, hit, _ in sorted(tables, key=lambda x: x[1]):
                a[start + k, hit] += a[start, hit] * p
            for k, start, hit, _ in sorted(tables, key=lambda x: -x[1]):
                b[start, hit] += b[start + k, hit] * p
            scale = t * p / np.maximum(a[n], 1e-300)
            total += np.bincount(np.concatenate([i for *_, i in tables]), np.concatenate([a[start, hit] * b[start + k, hit] * scale[hit] for k, start, hit, _ in tables]), size + 1)
    for i, w in enumerate(words):
        if len(w) > SHORT:
            _long_expected(w, float(times[i]), path, total)
    return total


def letters(raw: bytes) -> str:
    """Letters of a white-space word, with the marks upon them; nothing without a letter."""
    w = raw.decode("utf-8", "replace")
    if w.isalpha():
        return w
    if w.isascii():
        return "".join([c for c in w if c.isalpha()])
    w = "".join([c for c in w if c.isalpha() or unicodedata.category(c)[0] == "M"])
    return w if any(map(str.isalpha, w)) else ""


def _count(path: str):
    def run(batches):
        seen: dict[str, Counter] = {}
        size = 0

        def out():
            for lang, c in seen.items():
                words: Counter = Counter()
                for raw, k in c.items():
                    if w := letters(raw):
                        words[w] += k
                own = list(words)
                total = expected(own, np.array([words[w] for w in own], float), path) if own else np.zeros(1)
                hit = np.flatnonzero(total > 0)
                yield pa.record_batch([pa.array([lang] * len(hit), pa.string()), pa.array(hit, pa.int32()), pa.array(total[hit])], names=["lang", "piece", "n"])

        for batch in batches:
            for lang, t in zip(batch.column(0).to_pylist(), C.texts(batch)):
                words = (t or b"").split()
                seen.setdefault(lang, Counter()).update(words)
                size += len(t or b"")
                if size > 16 << 20:
                    yield from out()
                    seen, size = {}, 0
        yield from out()

    return run


class Model:
    """Languages, their log probabilities of pieces, and the piece file."""

    def __init__(self, langs: list[str], logp: np.ndarray | None, path: str):
        self.langs, self.logp, self.path = langs, logp, path


def train(docs: DataFrame, path: str | None = None, smoothing: float = 0.5) -> Model:
    """Learn from text and non-null lang of every row of ``docs``."""
    path = path or P.default_model()
    src = docs.where("lang is not null and text is not null").select(F.col("lang").cast("string").alias("lang"), F.col("text").cast("string").alias("text"))
    counts = src.mapInArrow(_count(path), "lang string, piece int, n double").groupBy("lang", "piece").agg(F.sum("n").alias("n")).toArrow()
    size = _known(path)[2]
    lang = counts.column("lang").to_pylist()
    langs = sorted(set(lang))
    if not langs:
        return Model([], None, path)
    n = np.full((len(langs), size + 1), smoothing)
    at = {x: i for i, x in enumerate(langs)}
    np.add.at(n, (np.array([at[x] for x in lang]), counts.column("piece").to_numpy()), counts.column("n").to_numpy())
    return Model(langs, np.log(n / n.sum(axis=1, keepdims=True)), path)


def predict(docs: DataFrame, model: Model, *keep: str) -> DataFrame:
    """``keep`` columns, lang_pred and score (the posterior of the prediction under equal priors)."""
    shared = docs.sparkSession.sparkContext.broadcast((model.langs, model.logp, model.path))
    src = docs.select(F.struct(*keep).alias("_rest"), F.col("text").cast("string").alias("text"))

    def run(batches):
        langs, logp, path = shared.value
        memo: dict[bytes, int] = {}
        rows = np.zeros((1 << 16, max(1, len(langs))), np.float32)

        def learn(texts_):
            """Likelihoods of the words not yet known, all at once."""
            nonlocal rows
            new = list({w for ws in texts_ for w in ws if w not in memo})
            parts = [letters(w) for w in new]
            flat = list(dict.fromkeys(p for p in parts if p))
            got = likelihoods(flat, logp, path)
            at = {p: i for i, p in enumerate(flat)}
            while len(memo) + len(new) > len(rows):
                rows = np.concatenate((rows, np.zeros_like(rows)))
            first = len(memo)
            memo.update(zip(new, range(first, first + len(new))))
            one = np.array([at[p] if p else -1 for p in parts], np.int64)
            rows[first : first + len(new)] = np.where(one[:, None] >= 0, got[one] if len(got) else 0, 0)

        for batch in batches:
            pred, score = [], []
            docs_ = C.texts(batch)
            for lo in range(0, len(docs_), 256):
                words = [(t or b"").split() for t in docs_[lo : lo + 256]]
                if len(memo) > 400_000:
                    memo.clear()
                if langs:
                    learn(words)
                for ws in words:
                    total = rows[np.fromiter(map(memo.__getitem__, ws), np.int64, len(ws))].sum(axis=0, dtype=float) if langs and ws else None
                    if total is None or not total.any():
                        pred.append("und")
                        score.append(0.0)
                        continue
                    e = np.exp(total - total.max())
                    pred.append(langs[int(total.argmax())])
                    score.append(float(1 / e.sum()))
            yield pa.record_batch([batch.column(0), pa.array(pred, pa.string()), pa.array(score, pa.float64())], names=["_rest", "lang_pred", "score"])

    out = src.mapInArrow(run, f"_rest {src.schema['_rest'].dataType.simpleString()}, lang_pred string, score double")
    return out.select("_rest.*", "lang_pred", "score")


def op10_language_id(spark, sf_dir: str) -> DataFrame:
    docs = C.table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    model = train(docs.where(~C.held_out(3, 1)))
    return predict(docs, model, "doc_id").select("doc_id", C.held_out(3, 1).alias("held_out"), "lang_pred", "score")
