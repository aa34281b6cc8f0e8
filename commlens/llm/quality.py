"""Quality rules: base counts of every text, and a hashed n-gram likelihood ratio of trusted to raw text.

Words and pairs of neighbouring words are hashed to ``BUCKETS`` cells. The raw multinomial counts the
cells of all documents, the trusted one those of the trusted documents; both are smoothed by one. A
document's score is the mean log ratio of its n-grams, so long and short texts compare. The verdict
compares it with one number, the same for every document: the given quantile of the trusted
documents' own scores, less a margin.

All labelled documents of quality 1 form the target and set the threshold; counts, scores and verdicts cover every document. A task
sends a row per non-empty cell, whatever it has read; BUCKETS numbers reach the driver and go back to the tasks, and the driver sees the
scores below the quantile.

Cases: null text and text without words have zero counts, score zero and fail the base rules; repeated
rows each get a row; with no trusted documents the ratio is zero everywhere and all documents that pass the
base rules are kept; an empty table gives an empty table; other columns are ignored.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from commlens.llm.common import SPACE, Scratch, column_bytes, limit_batches, map_batches

BUCKETS = 1 << 14
#: The share of trusted documents that the threshold may cut, and what is taken off it.
QUANTILE, MARGIN = 0.002, 0.05
MIN_WORDS = 50
_SYMBOLS = b"#*$%&|<>"
_MIX = np.uint64(0x9E3779B97F4A7C15)


class WordIndex:
    """Numbers the distinct words of one text."""

    def __init__(self, words: list[bytes]) -> None:
        seen: dict[bytes, int] = {}
        add = seen.setdefault
        self.ids = np.array([add(w, len(seen)) for w in words], dtype=np.int64)
        self.distinct = list(seen)


def repeated_words(ids: np.ndarray, distinct: int) -> int:
    """Words in windows of three that occur twice or more."""
    n = len(ids) - 2
    if n < 2:
        return 0
    pair = ids[:-1] * distinct + ids[1:]
    if distinct >= 1 << 21:
        pair = np.unique(pair, return_inverse=True)[1]
    key = pair[:-1] * distinct + ids[2:]
    order = np.argsort(key, kind="stable")
    same = key[order[1:]] == key[order[:-1]]
    twice = np.zeros(n, dtype=bool)
    twice[order[1:][same]] = True
    twice[order[:-1][same]] = True
    covered = np.zeros(len(ids), dtype=bool)
    for k in range(3):
        covered[k : k + n] |= twice
    return int(covered.sum())


def base_counts(raw: bytes, words: list[bytes], index: WordIndex) -> tuple[int, int, int, int, int]:
    """n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words of a text."""
    bare = raw.translate(None, SPACE)
    chars = len(bare) if bare.isascii() else len(bare.decode())
    lines = [x for x in raw.split(b"\n") if x.strip(SPACE)]
    return len(words), chars, len(raw) - len(raw.translate(None, _SYMBOLS)), len(lines) - len(set(lines)), repeated_words(index.ids, len(index.distinct))


def base_fails(n_words: int, n_repeat: int) -> bool:
    return n_words < MIN_WORDS or 100 * n_repeat > 50 * n_words


def cells(index: WordIndex, buckets: int = BUCKETS) -> np.ndarray:
    """The cell of each word and of each pair of neighbours."""
    h = np.array([zlib.crc32(w) for w in index.distinct], dtype=np.uint64)[index.ids] if len(index.ids) else np.zeros(0, np.uint64)
    two = (h[:-1] * np.uint64(31) + h[1:] + np.uint64(1)) * _MIX
    return (np.concatenate([h * _MIX, two]) >> np.uint64(64 - buckets.bit_length() + 1)).astype(np.int64)


def trusted_ids(labels: DataFrame) -> DataFrame:
    """The doc_ids whose labels all say quality 1."""
    rows = labels.where(F.col("doc_id").isNotNull()).groupBy("doc_id").agg(F.min("quality").alias("low"), F.max("quality").alias("high"))
    return rows.where("low = 1 and high = 1").select("doc_id")


def log_ratios(docs: DataFrame, trusted: DataFrame, buckets: int = BUCKETS) -> np.ndarray:
    """log(trusted / raw) of each cell, from counts over all documents."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts = np.zeros((2, buckets), dtype=np.int64)
        for batch in batches:
            for raw, good in zip(column_bytes(batch, "text"), batch.column("good").to_pylist(), strict=True):
                got = np.bincount(cells(WordIndex(raw.split()), buckets), minlength=buckets)
                counts[0] += got
                if good:
                    counts[1] += got
        at = np.flatnonzero(counts[0])
        yield pa.RecordBatch.from_arrays([pa.array(at.astype(np.int32)), pa.array(counts[0][at]), pa.array(counts[1][at])], ["cell", "n_raw", "n_trusted"])

    limit_batches(docs.sparkSession)
    marked = docs.select("doc_id", "text").join(trusted.withColumn("good", F.lit(True)).hint("shuffle_hash"), "doc_id", "left").select("text", "good")
    sums = marked.mapInArrow(run, "cell int, n_raw bigint, n_trusted bigint").groupBy("cell").agg(F.sum("n_raw"), F.sum("n_trusted"))
    raw, good = np.ones(buckets), np.ones(buckets)
    for cell, a, b in sums.collect():
        raw[cell] += a
        good[cell] += b
    if good.sum() == buckets:
        return np.zeros(buckets)
    return np.log(good / good.sum()) - np.log(raw / raw.sum())


def score_documents(docs: DataFrame, ratios: np.ndarray) -> DataFrame:
    """The base counts, the verdict of the base rules and ``score`` of every document."""
    buckets = len(ratios)

    def make():
        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            rows = []
            for raw in column_bytes(batch, "text"):
                words = raw.split()
                index = WordIndex(words)
                counts = base_counts(raw, words, index)
                score = float(ratios[cells(index, buckets)].mean()) if words else 0.0
                failed = base_fails(counts[0], counts[4])
                rows.append((*counts, failed, score))
            kinds = [pa.int64()] * 5 + [pa.bool_()] + [pa.float64()]
            return pa.RecordBatch.from_arrays([batch.column("doc_id"), *(pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True))], names)

        return step

    names = ["doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "score"]
    schema = f"doc_id {docs.schema['doc_id'].dataType.simpleString()}, n_words bigint, word_chars bigint, n_symbols bigint, n_dup_lines bigint, n_repeat_words bigint, base_failed boolean, score double"
    return map_batches(docs.select("doc_id", "text"), make, schema)


def fitted_threshold(scored: DataFrame, trusted: DataFrame, quantile: float = QUANTILE, margin: float = MARGIN) -> float | None:
    """The quantile of the scores of all trusted documents that pass the base rules, less the margin."""
    scores = scored.where(~F.col("base_failed")).join(trusted, "doc_id", "left_semi").select("score")
    at = quantile * (scores.count() - 1)
    if at < 0:
        return None
    low = [r[0] for r in scores.orderBy("score").limit(int(at) + 2).collect()][int(at) :]
    return low[0] + (low[-1] - low[0]) * (at - int(at)) - margin


def judge_documents(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """Every document with its base counts and verdict, trusted text being what the labels call good."""
    scratch = Scratch(docs.sparkSession)
    trusted = scratch.table(trusted_ids(labels))
    scored = scratch.table(score_documents(docs, log_ratios(docs, trusted)))
    threshold = fitted_threshold(scored, trusted)
    kept = ~F.col("base_failed") if threshold is None else ~F.col("base_failed") & (F.col("score") >= threshold)
    return scored.select(*scored.columns[:-1], kept.alias("kept"), "score")
