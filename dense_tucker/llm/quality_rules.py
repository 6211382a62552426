"""Quality rules: text statistics and a hashed n-gram log-likelihood ratio of trusted against raw text.

Two multinomials over hashed word 1-grams and 2-grams are counted over all documents: one of the trusted
documents, one of the raw corpus. A document's score is the mean log ratio of its n-grams. Every document
below a fixed threshold, or failing the base rules, is not kept.
Words are runs of bytes other than white space. Null and empty texts have no words, score 0 and fail.
Repeated rows count as often as they occur; tables may be empty; other columns are ignored. A text is one pass, whose
memory is about a dozen times the text.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import lexing
from .common import broadcast_if_small, map_texts, passes, texts_of

BUCKETS = 1 << 16
#: Prior count of each bucket's ratio.
SMOOTHING = 1.0
#: Mean log ratio under which a document is rejected.
THRESHOLD = -0.1
_SYMBOL = np.zeros(256, bool)
_SYMBOL[list(b"#*$%&|<>")] = True


def base_counts(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> dict[str, np.ndarray]:
    """Counts of the base rules for each text."""
    word = lexing.SPACED[data]
    h, a, b, row = lexing.words(data, starts, ends)
    n_words = lexing.tally(a, starts, ends)
    out = {
        "n_words": n_words,
        "word_chars": lexing.sums_by(word & ((data & 0xC0) != 0x80), starts, ends),
        "n_symbols": lexing.sums_by(_SYMBOL[data], starts, ends),
    }
    # lines: between line feeds, within texts
    feeds = np.flatnonzero(data == 0x0A)
    some = starts < ends
    first = np.sort(np.concatenate([starts[some], feeds + 1]))
    last = np.sort(np.concatenate([ends[some], feeds]))
    last = np.maximum(last, first)
    full = lexing.tally(a, first, last) > 0
    first, last = first[full], last[full]
    line_row = lexing.owners(first, starts, ends)
    line = lexing.numbered(data, lexing.span_hashes(data, first, last), first, last)
    kept = np.unique(line_row * (1 + int(line.max(initial=0))) + line, return_index=True)[1]
    lines = np.bincount(line_row, minlength=len(starts))
    out["n_dup_lines"] = lines - np.bincount(line_row[kept], minlength=len(starts))
    # three-word windows found twice or more
    repeat = np.zeros(len(h), bool)
    if len(h) > 2:
        at = np.flatnonzero(row[2:] == row[:-2])
        number = lexing.numbered(data, h, a, b).astype(np.uint64)
        # the places of three numbers in one: exact, as equal neighbours are compared
        window = lexing.mix(lexing.mix(lexing.mix(number[:-2] ^ (row[:-2].astype(np.uint64) << np.uint64(32))) + number[1:-1]) ^ number[2:])[at]
        sort = np.argsort(window, kind="stable")
        order, window = at[sort], window[sort]
        equal = np.zeros(len(order), bool)
        if len(order) > 1:
            twin = window[1:] == window[:-1]
            meet = np.flatnonzero(twin)
            exact = row[order[meet]] == row[order[meet + 1]]
            for k in range(3):
                exact &= number[order[meet] + k] == number[order[meet + 1] + k]
            if not exact.all():  # hashes alone met: sort by the numbers themselves
                order = at[np.lexsort((number[at + 2], number[at + 1], number[at], row[at]))]
                twin = np.logical_and.reduce([row[order[1:]] == row[order[:-1]], *(number[order[1:] + k] == number[order[:-1] + k] for k in range(3))])
            equal[1:] |= twin
            equal[:-1] |= twin
        hit = order[equal]
        for k in range(3):
            repeat[hit + k] = True
    out["n_repeat_words"] = np.bincount(row[repeat], minlength=len(starts))
    return {k: v.astype(np.int64) for k, v in out.items()} | {"_h": h, "_row": row}


def buckets_of(h: np.ndarray, row: np.ndarray, buckets: int) -> tuple[np.ndarray, np.ndarray]:
    """Bucket and row of every 1-gram and 2-gram."""
    if not len(h):
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    pair = lexing.mix(h[:-1] + lexing.mix(h[1:]))[row[1:] == row[:-1]]
    both = np.concatenate([h, pair])
    return (both % np.uint64(buckets)).astype(np.int64), np.concatenate([row, row[:-1][row[1:] == row[:-1]]])


def count_ngrams(docs: DataFrame, trusted: DataFrame, buckets: int = BUCKETS, text: str = "text") -> tuple[np.ndarray, np.ndarray]:
    """Counts of the trusted documents (ids in `trusted`) and of all documents, each over `buckets` buckets."""
    ids = broadcast_if_small(trusted.select(F.col("doc_id").alias("__id")).where("__id is not null").distinct().withColumn("__good", F.lit(True)))
    marked = docs.select(F.col("doc_id").alias("__id"), F.col(text).alias("__text")).join(ids, "__id", "left").select("__text", F.coalesce("__good", F.lit(False)).alias("__good"))

    def run(batches):
        raw, good = np.zeros(buckets, np.int64), np.zeros(buckets, np.int64)
        for batch in batches:
            data, starts, ends = texts_of(batch.column(0))
            mark = batch.column(1).to_numpy(zero_copy_only=False).astype(bool)
            for a, b in passes(starts, ends):
                low, high = int(starts[a]), int(ends[b - 1])
                h, _, _, row = lexing.words(data[low:high], starts[a:b] - low, ends[a:b] - low)
                at, owner = buckets_of(h, row, buckets)
                raw += np.bincount(at, minlength=buckets)
                good += np.bincount(at[mark[a:b][owner]], minlength=buckets)
        some = np.flatnonzero(raw)
        if len(some):
            yield pa.RecordBatch.from_arrays([pa.array(some), pa.array(good[some]), pa.array(raw[some])], names=["bucket", "good", "raw"])

    counts = marked.mapInArrow(run, "bucket long, good long, raw long").groupBy("bucket").agg(F.sum("good").alias("good"), F.sum("raw").alias("raw"))
    good, raw = np.zeros(buckets, np.int64), np.zeros(buckets, np.int64)
    for r in counts.collect():  # at most one row for each bucket
        good[r["bucket"]], raw[r["bucket"]] = r["good"], r["raw"]
    return good, raw


def log_ratios(good: np.ndarray, raw: np.ndarray, smoothing: float = SMOOTHING) -> np.ndarray:
    """Log ratio of the two smoothed multinomials, shrunk towards zero where both are rarely seen."""
    p = raw / max(1, raw.sum())
    prior = smoothing * 64 * np.maximum(p, 1 / (64 * len(raw)))
    total = max(1.0, float(good.sum()))
    expected = p * total
    return np.log((good + prior) / (expected + prior))


def rate(docs: DataFrame, ratios: np.ndarray, threshold: float = THRESHOLD, text: str = "text") -> DataFrame:
    """doc_id, base counts, base_failed, score and kept for every document."""
    buckets = len(ratios)

    def work(data, starts, ends):
        out = base_counts(data, starts, ends)
        h, row = out.pop("_h"), out.pop("_row")
        at, owner = buckets_of(h, row, buckets)
        n = np.bincount(owner, minlength=len(starts))
        score = np.bincount(owner, ratios[at], minlength=len(starts)) / np.maximum(1, n)
        failed = (out["n_words"] < 50) | (100 * out["n_repeat_words"] > 50 * out["n_words"])
        return out | {"base_failed": failed, "score": score, "kept": ~failed & (score >= threshold)}

    return map_texts(docs, "n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, score double, kept boolean", work, text=text)


def apply(docs: DataFrame, trusted: DataFrame, buckets: int = BUCKETS, threshold: float = THRESHOLD) -> DataFrame:
    return rate(docs, log_ratios(*count_ngrams(docs, trusted, buckets)), threshold)
