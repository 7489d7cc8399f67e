"""Count-only Viterbi tokenisation: pieces per text of a unigram tokenizer over the fixed public vocabulary.

An Aho-Corasick automaton enumerates all vocabulary matches in a word; dynamic programming over its characters carries the best
score and the piece count alone. Ties are the tokenizer's: ends are reached in order of start, and a later equal score does not
replace an earlier one. A character without a piece is the unknown piece, ten below the lowest score, which
counts its UTF-8 bytes (byte fallback). White space is the mark U+2581 with one in front of the text; pieces hold the mark only at their
start or as a run of marks, so words are independent and each distinct one is solved once per worker.

Scores add up in double precision within a word. The best path is the one that the library's lattice lists first; its fast
one-best encoder has been seen to keep a worse path for words such as "the" + "a...", which is not imitated.

Edge cases: null and empty texts have no token; runs of spaces are words of marks; rows, ties and extra columns as they are."""

from __future__ import annotations

import re
from functools import lru_cache

import ahocorasick
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common as C
from . import pieces as P

MARK = "▁"
_WORD = re.compile(f"{MARK}+[^{MARK}]*|[^{MARK}]+")


@lru_cache(2)
def automaton(path: str):
    """Matches of the normal pieces (length, score), and the unknown piece's score."""
    names, scores, types = P.vocabulary(path)
    a = ahocorasick.Automaton()
    low = 0.0
    for p, s, t in zip(names, scores, types):
        if t == 1:
            a.add_word(p, (len(p), s))
            low = min(low, s)
    a.make_automaton()
    return a, low - 10.0


def count(word: str, path: str) -> int:
    """Pieces of the best segmentation of a marked word."""
    a, unknown = automaton(path)
    n = len(word)
    by: list[list] = [[] for _ in range(n)]
    for end, (size, s) in a.iter(word):
        by[end + 1 - size].append((size, s))
    best: list = [None] * (n + 1)
    best[0] = (0.0, 0)
    for i in range(n):
        score, pieces = best[i]
        single = False
        for size, s in sorted(by[i]):
            single |= size == 1
            j = best[i + size]
            if j is None or score + s > j[0]:
                best[i + size] = (score + s, pieces + 1)
        if not single:
            j = best[i + 1]
            if j is None or score + unknown > j[0]:
                best[i + 1] = (score + unknown, pieces + len(word[i].encode()))
    return best[n][1]


def marked(text: str) -> str:
    return MARK + text.replace(" ", MARK) if text else ""


def count_text(text: str, path: str, memo=None) -> int:
    words = _WORD.findall(marked(text))
    return sum(map(memo.__getitem__, words)) if memo is not None else sum(count(w, path) for w in words)


@lru_cache(2)
def worker_memo(path: str):
    return C.Memo(lambda w: count(w, path), 600_000)


def counted(docs: DataFrame, path: str | None = None) -> DataFrame:
    """(doc_id, n_tokens) of every row."""
    path = path or P.default_model()

    def run(batches):
        memo = worker_memo(path)
        for batch in batches:
            yield pa.record_batch([batch.column(0), pa.array([count_text(t.decode(), path, memo) if t else 0 for t in C.texts(batch)], pa.int64())], names=["doc_id", "n_tokens"])

    src = docs.select("doc_id", F.col("text").cast("string").alias("text"))
    return src.mapInArrow(run, f"doc_id {src.schema['doc_id'].dataType.simpleString()}, n_tokens long")


def op7_token_counts(spark, sf_dir: str) -> DataFrame:
    return counted(C.table(spark, sf_dir, "documents"))
