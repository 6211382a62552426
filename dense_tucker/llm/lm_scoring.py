"""Cross-entropy difference of two matched n-gram models.

A target model (trusted documents) and a background model (all documents) of the same form share one
vocabulary: every word that occurs at least twice in the corpus; the other words are one unknown word. A word's
probability after another is that of a Dirichlet-smoothed bigram, backed by the model's smoothed unigram, and adds up to 1 over the vocabulary:

    P(w) = (c(w) + ADD) / (N + ADD * (words and the unknown one))
    P(w | h) = (c(h, w) + WEIGHT * P(w)) / (followed(h) + WEIGHT)

The first word of a text has P(w). The background's counts are scaled to the target's number of words (expected counts of
a random part of that size), so smoothing weighs alike in both. A document's own counts are taken out of the
models that hold it. Its score is its mean loss per word under the target model less that under the background model: the
lower, the more like the target. It is target-like up to the score that LIKE of the trusted documents reach, each of which was
scored without its own counts (0 where there is none).

Word and bigram counts are exact (words and bigrams are told apart by 64-bit hashes) and nothing bounds how
many there are. No task or driver holds a whole table of counts: chunks of texts send their distinct words to
buckets of the hash range, a bucket sums over all chunks and answers each, and then the same goes for bigrams.
The number of buckets grows with the corpus, so a bucket's size does not.

Words are lower-cased runs of other than white space. Null and empty texts have no words and zero losses.
Repeated rows are documents of their own and count as often as they occur; tables may be empty; without a trusted document the
target model is uniform; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import lexing
from .common import broadcast_if_small, discard, materialise, passes, texts_of

#: Prior count of every word.
ADD = 0.5
#: Weight of the unigram in a bigram's probability, in words.
WEIGHT = 2.0
#: Share of the trusted documents whose scores count as target-like.
LIKE = 0.8
#: Counts of a word in both models: all, and at the end of a text.
WORD_COUNTS = ("target", "background", "target_last", "background_last")
#: Words and rows after which a chunk of texts is closed.
CHUNK_WORDS = 1 << 19
CHUNK_ROWS = 100_000
#: Keys that a bucket of the hash range gets from all chunks together, about.
BUCKET_KEYS = 1 << 20
_ANSWER = "chunk long, bucket long, counts binary, n_vocab long, unknown array<long>, every array<long>"


def _pack(x: np.ndarray) -> bytes:
    """Numbers by planes of equal significance, compressed, behind their count."""
    planes = np.ascontiguousarray(x).view(np.uint8).reshape(len(x), x.itemsize).T.tobytes()
    return len(x).to_bytes(8, "little") + pa.compress(planes, "zstd", asbytes=True)


def _unpack(raw: bytes, kind: type) -> np.ndarray:
    size = np.dtype(kind).itemsize
    planes = pa.decompress(raw[8:], size * int.from_bytes(raw[:8], "little"), "zstd", asbytes=True)
    return np.ascontiguousarray(np.frombuffer(planes, np.uint8).reshape(size, -1).T).reshape(-1).view(kind)


def _rows(batches: Iterator[pa.RecordBatch]) -> Iterator[dict]:
    """Rows one by one, so that one chunk at a time is unpacked."""
    for batch in batches:
        for i in range(batch.num_rows):
            yield batch.slice(i, 1).to_pylist()[0]


def chunks(docs: DataFrame, trusted: DataFrame, text: str = "text", words: int = CHUNK_WORDS) -> DataFrame:
    """chunk, doc_ids, lengths (words of each document), marks (trusted), keys (distinct words, the commonest first), tokens (places in keys) and their numbers."""
    ids = broadcast_if_small(trusted.select(F.col("doc_id").alias("__id")).where("__id is not null").distinct().withColumn("__good", F.lit(True)))
    marked = docs.select(F.col("doc_id").alias("__id"), F.col(text).alias("__text")).join(ids, "__id", "left").select("__id", "__text", F.coalesce("__good", F.lit(False)).alias("__good"))
    kind = docs.schema["doc_id"].dataType.simpleString()

    def run(batches):
        part, number = TaskContext.get().partitionId(), 0
        held: list[tuple] = []

        def close() -> pa.RecordBatch:
            ids = pa.concat_arrays([x[0] for x in held])
            marks, lengths, hashes = (np.concatenate([x[k] for x in held]) for k in (1, 2, 3))
            held.clear()
            keys, tokens, n = np.unique(hashes, return_inverse=True, return_counts=True)
            order = np.argsort(-n, kind="stable")
            rank = np.empty(len(keys), np.int32)
            rank[order] = np.arange(len(keys))
            keys, tokens = keys[order], rank[tokens]
            return pa.RecordBatch.from_arrays(
                [
                    pa.array([part << 32 | number], pa.int64()),
                    pa.ListArray.from_arrays(pa.array([0, len(ids)], pa.int32()), ids),
                    *(pa.array([_pack(x)], pa.binary()) for x in (lengths.astype(np.int32), marks, keys, tokens)),
                    *(pa.array([len(x)], pa.int64()) for x in (keys, tokens)),
                ],
                names=["chunk", "doc_ids", "lengths", "marks", "keys", "tokens", "n_keys", "n_tokens"],
            )

        for batch in batches:
            data, starts, ends = texts_of(batch.column(1))
            marks = batch.column(2).to_numpy(zero_copy_only=False).astype(bool)
            for a, b in passes(starts, ends):
                low = int(starts[a])
                h, _, _, row = lexing.words(data[low : int(ends[b - 1])], starts[a:b] - low, ends[a:b] - low, lower=True)
                held.append((batch.column(0).slice(a, b - a), marks[a:b], np.bincount(row, minlength=b - a), h))
                if sum(len(x[3]) for x in held) >= words or sum(len(x[0]) for x in held) >= CHUNK_ROWS:
                    yield close()
                    number += 1
        if held:
            yield close()

    return marked.mapInArrow(run, f"chunk long, doc_ids array<{kind}>, lengths binary, marks binary, keys binary, tokens binary, n_keys long, n_tokens long")


def _requests(chunk: int, keys: np.ndarray, counts: list[np.ndarray], buckets: int) -> pa.RecordBatch:
    """A chunk's sorted keys and their counts, one row for each bucket of the hash range."""
    bucket = ((keys >> np.uint64(32)) * np.uint64(buckets)) >> np.uint64(32)
    named, heads = np.unique(bucket, return_index=True)
    cuts = list(zip(heads.tolist(), [*heads[1:].tolist(), len(keys)], strict=True)) if len(keys) else []
    steps = [_pack(np.diff(keys[a:b], prepend=np.uint64(0))) for a, b in cuts]
    packed = [_pack(np.concatenate([x[a:b] for x in counts]).astype(np.int32)) for a, b in cuts]
    return pa.RecordBatch.from_arrays([pa.array(named.astype(np.int64)), pa.array([chunk] * len(cuts), pa.int64()), pa.array(steps, pa.binary()), pa.array(packed, pa.binary())], names=["bucket", "chunk", "keys", "counts"])


def _answers(requests: DataFrame, kinds: int) -> DataFrame:
    """The counts (of so many kinds) over all chunks of each chunk's keys, and on one row of each bucket its part of the totals."""

    def add(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = [r for batch in batches for r in batch.select(["chunk", "keys", "counts"]).to_pylist()]
        parts = [np.cumsum(_unpack(r["keys"], np.uint64), dtype=np.uint64) for r in rows]
        keys, where = np.unique(np.concatenate(parts), return_inverse=True)
        ends = np.cumsum([len(x) for x in parts])[:-1]
        counts = [_unpack(r["counts"], np.int32).reshape(kinds, -1) for r in rows]
        sums = np.stack([np.bincount(where, np.concatenate([x[k] for x in counts]), minlength=len(keys)).astype(np.int64) for k in range(kinds)])
        single = sums[1] < 2
        own = [sums[:, w] for w in np.split(where, ends)]
        unknown, every = ([x.sum(1).tolist(), *[[0] * kinds] * (len(rows) - 1)] for x in (sums[:, single], sums))
        yield pa.RecordBatch.from_arrays(
            [
                pa.array([r["chunk"] for r in rows], pa.int64()),
                pa.array([key[0].as_py()] * len(rows), pa.int64()),
                pa.array([_pack(x.ravel()) for x in own], pa.binary()),
                pa.array([int((~single).sum())] + [0] * (len(rows) - 1), pa.int64()),
                *(pa.array(x, pa.list_(pa.int64())) for x in (unknown, every)),
            ],
            names=["chunk", "bucket", "counts", "n_vocab", "unknown", "every"],
        )

    return requests.groupBy("bucket").applyInArrow(add, _ANSWER)


_REQUEST = "bucket long, chunk long, keys binary, counts binary"


def _ends(lengths: np.ndarray) -> np.ndarray:
    """Places of the last words of texts."""
    return (np.cumsum(lengths) - 1)[lengths > 0]


def _word_requests(parts: DataFrame, buckets: int) -> DataFrame:
    def run(batches):
        for r in _rows(batches):
            keys, tokens = _unpack(r["keys"], np.uint64), _unpack(r["tokens"], np.int32)
            lengths = _unpack(r["lengths"], np.int32).astype(np.int64)
            good = np.repeat(_unpack(r["marks"], np.bool_), lengths)
            last = np.zeros(len(tokens), bool)
            last[_ends(lengths)] = True
            order = np.argsort(keys)
            yield _requests(r["chunk"], keys[order], [np.bincount(x, minlength=len(keys))[order] for x in (tokens[good], tokens, tokens[good & last], tokens[last])], buckets)

    return parts.select("chunk", "lengths", "marks", "keys", "tokens").mapInArrow(run, _REQUEST)


def _pairs(r: dict) -> tuple[np.ndarray, ...]:
    """Of a chunk's row: places of words after another one of their text, sorted distinct bigrams, and the bigram of each such place."""
    keys = np.where(_unpack(r["word_counts"], np.int64).reshape(len(WORD_COUNTS), -1)[1] > 1, _unpack(r["keys"], np.uint64), np.uint64(0))
    tokens, lengths = _unpack(r["tokens"], np.int32), _unpack(r["lengths"], np.int32).astype(np.int64)
    inside = np.ones(len(tokens), bool)
    inside[(np.cumsum(lengths) - lengths)[lengths > 0]] = False
    at = np.flatnonzero(inside)
    pairs, where = np.unique(lexing.mix(lexing.mix(keys)[tokens[at - 1]] + keys[tokens[at]]), return_inverse=True)
    return at, pairs, where


def _pair_requests(parts: DataFrame, buckets: int) -> DataFrame:
    def run(batches):
        for r in _rows(batches):
            at, pairs, where = _pairs(r)
            good = np.repeat(_unpack(r["marks"], np.bool_), _unpack(r["lengths"], np.int32))[at]
            yield _requests(r["chunk"], pairs, [np.bincount(x, minlength=len(pairs)) for x in (where[good], where)], buckets)

    return parts.select("chunk", "lengths", "marks", "keys", "tokens", "word_counts").mapInArrow(run, _REQUEST)


def _gathered(parts: DataFrame, answers: DataFrame):
    """Rows of chunks and of their answers by chunk; the chunk's own row has no bucket."""
    return parts.unionByName(answers.select("chunk", "bucket", "counts"), allowMissingColumns=True).groupBy("chunk")


def _read(batches: Iterator[pa.RecordBatch], fields: list[str], kinds: int) -> tuple[pa.Array, dict, np.ndarray]:
    """doc_ids and fields of the chunk's own row; the answered counts (kinds x keys) in the order of its sorted keys."""
    ids, own, found = None, {}, []
    for batch in batches:
        for i, bucket in enumerate(batch.column("bucket").to_pylist()):
            if bucket is None:
                ids = batch.column("doc_ids")[i].values
                own = {k: batch.column(k)[i].as_py() for k in fields}
            else:
                found.append((bucket, _unpack(batch.column("counts")[i].as_py(), np.int64).reshape(kinds, -1)))
    found.sort(key=lambda x: x[0])
    return ids, own, np.concatenate([x for _, x in found] or [np.zeros((kinds, 0), np.int64)], axis=1)


def count_words(parts: DataFrame, bucket_keys: int = BUCKET_KEYS) -> tuple[DataFrame, dict[str, int]]:
    """Chunks with both models' counts of their distinct words, and the totals of the corpus."""
    fields, kinds = ["lengths", "marks", "keys", "tokens"], len(WORD_COUNTS)
    buckets = 1 + (parts.agg(F.sum("n_keys")).first()[0] or 0) // bucket_keys
    answers = materialise(_answers(_word_requests(parts, buckets), kinds), "word-answers")
    sums = [F.sum("n_vocab").alias("n_vocab")] + [F.sum(F.col(c)[k]).alias(f"{c}_{name}") for c in ("unknown", "every") for k, name in enumerate(WORD_COUNTS)]
    totals = {k: v or 0 for k, v in answers.agg(*sums).first().asDict().items()}

    def join(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, own, found = _read(batches, fields, kinds)
        place = np.argsort(np.argsort(_unpack(own["keys"], np.uint64)))
        yield pa.RecordBatch.from_arrays(
            [pa.array([key[0].as_py()], pa.int64()), pa.ListArray.from_arrays(pa.array([0, len(ids)], pa.int32()), ids)]
            + [pa.array([own[k]], pa.binary()) for k in fields]
            + [pa.array([_pack(found[:, place].ravel())], pa.binary())],
            names=["chunk", "doc_ids", *fields, "word_counts"],
        )

    kind = parts.schema["doc_ids"].dataType.simpleString()
    schema = f"chunk long, doc_ids {kind}, lengths binary, marks binary, keys binary, tokens binary, word_counts binary"
    made = materialise(_gathered(parts.select("chunk", "doc_ids", *fields), answers).applyInArrow(join, schema), "word-counts")
    discard(answers)
    return made, totals


def unigram(count: np.ndarray, total: np.ndarray | float, n_vocab: int) -> np.ndarray:
    """P(w) of words with these counts in a model of `total` words; the unknown word is one more than n_vocab."""
    return (count + ADD) / (total + ADD * (n_vocab + 1))


def bigram(pair: np.ndarray, followed: np.ndarray, backed: np.ndarray, weight: float = WEIGHT) -> np.ndarray:
    """P(w | h) from c(h, w), followed(h) and P(w)."""
    return (pair + weight * backed) / (followed + weight)


def _within(row: np.ndarray, items: np.ndarray, n_items: int) -> np.ndarray:
    """How often each place's item occurs in its own document."""
    _, where, times = np.unique(row * max(1, n_items) + items, return_inverse=True, return_counts=True)
    return times[where]


def losses(tokens: np.ndarray, lengths: np.ndarray, marks: np.ndarray, counts: np.ndarray, pairs: np.ndarray, at: np.ndarray, where: np.ndarray, totals: dict[str, int]) -> tuple[list[np.ndarray], np.ndarray]:
    """Mean loss per word of each text under both models, its own counts left out, and its number of unknown words.

    counts (4 x distinct words) and pairs (2 x distinct bigrams) are of the whole corpus; at and where as from _pairs().
    """
    lengths = lengths.astype(np.int64)
    row = np.repeat(np.arange(len(lengths)), lengths)
    unknown = counts[1] < 2
    word = np.where(unknown, len(unknown), np.arange(len(unknown)))[tokens]  # one number for all unknown words
    own = _within(row, word, len(unknown) + 1)
    own_pair = _within(row[at], where, pairs.shape[1])
    before = word[at - 1]
    last = np.full(len(lengths), -1)
    last[lengths > 0] = word[_ends(lengths)]
    own_followed = own[at - 1] - (before == last[row[at]])
    n = np.maximum(1, lengths)
    out = []
    scale = totals["every_target"] / totals["every_background"] if totals["every_target"] else 1.0
    for k, (model, size) in enumerate((("target", 1.0), ("background", scale))):
        holds = np.ones(len(lengths), bool) if k else marks
        mine = holds[row]
        every = np.append(counts[k], 0)
        every[:-1][unknown] = totals[f"unknown_{model}"]
        every[-1] = totals[f"unknown_{model}"]
        followed = every.copy()
        followed[:-1] -= np.where(unknown, totals[f"unknown_{model}_last"], counts[k + 2])
        followed[-1] -= totals[f"unknown_{model}_last"]
        total = totals[f"every_{model}"] - np.where(holds, lengths, 0)
        p = unigram(size * (every[word] - own * mine), size * total[row], totals["n_vocab"])
        p[at] = bigram(size * (pairs[k][where] - own_pair * mine[at]), size * (followed[before] - own_followed * mine[at]), p[at])
        out.append(np.bincount(row, -np.log(p), minlength=len(lengths)) / n)
    return out, np.bincount(row[unknown[tokens]], minlength=len(lengths))


def score(counted: DataFrame, totals: dict[str, int], bucket_keys: int = BUCKET_KEYS) -> DataFrame:
    """doc_id, n_words, n_unknown, ce_target, ce_background, score and trusted of every document."""
    fields = ["lengths", "marks", "keys", "tokens", "word_counts"]
    answers = _answers(_pair_requests(counted, 1 + totals["every_background"] // (2 * bucket_keys)), 2)  # about two words to a distinct bigram of a chunk

    def work(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, own, pairs = _read(batches, fields, 2)
        at, _, where = _pairs(own)
        tokens, lengths = _unpack(own["tokens"], np.int32), _unpack(own["lengths"], np.int32)
        marks = _unpack(own["marks"], np.bool_)
        (t, b), n_unknown = losses(tokens, lengths, marks, _unpack(own["word_counts"], np.int64).reshape(len(WORD_COUNTS), -1), pairs, at, where, totals)
        arrays = [ids, pa.array(lengths.astype(np.int64)), pa.array(n_unknown.astype(np.int64)), *map(pa.array, (t, b, t - b, marks))]
        yield pa.RecordBatch.from_arrays(arrays, names=["doc_id", "n_words", "n_unknown", "ce_target", "ce_background", "score", "trusted"])

    kind = counted.schema["doc_ids"].dataType.elementType.simpleString()
    return _gathered(counted, answers).applyInArrow(work, f"doc_id {kind}, n_words long, n_unknown long, ce_target double, ce_background double, score double, trusted boolean")


def apply(docs: DataFrame, trusted: DataFrame, chunk_words: int = CHUNK_WORDS, bucket_keys: int = BUCKET_KEYS, like: float = LIKE) -> DataFrame:
    """doc_id, n_words, n_unknown, ce_target, ce_background, score, trusted, threshold and target_like of every document."""
    parts = materialise(chunks(docs, trusted, words=chunk_words), "word-chunks")
    counted, totals = count_words(parts, bucket_keys)
    discard(parts)
    scored = materialise(score(counted, totals, bucket_keys=bucket_keys), "scores")
    discard(counted)
    threshold = scored.where("trusted and n_words > 0").agg(F.percentile_approx("score", like)).first()[0] or 0.0
    return scored.withColumn("threshold", F.lit(float(threshold))).withColumn("target_like", (F.col("n_words") > 0) & (F.col("score") <= threshold))
