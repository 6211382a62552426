"""Language identification by error-correcting output codes.

Every language has a codeword; each of its bits is predicted by a binary classifier over hashed byte
3-grams of lower-cased letters (log ratio of the two sides' n-gram multinomials, averaged over the text and
scaled on the training rows). Decoding adds up the logistic losses of the bits and takes the codeword of the
least loss; a small lead over the second marks the text as ambiguous.

Few languages get the exhaustive code, more a random one with well separated rows. At most TRAIN_DOCS
documents of the training split, each of up to TRAIN_TEXT_BYTES, are used for fitting, those with the least hashed ids. Null texts and texts
without a letter are `und` with score 0. Repeated rows get equal answers; an empty table gives an empty
result; without a training row everything is `und`. Of languages with equal losses the first by name is taken. Other columns are ignored.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import lexing
from .common import held_out, map_texts, passes, texts_of, training_texts

TRAIN_DOCS = 6_000
BUCKETS = 1 << 16
#: Bytes whose n-grams are looked up at a time.
SLICE = 1 << 18
#: Lead of the best probability over the second under which a text is ambiguous.
LEAD = 0.2
_LETTERS = np.where(lexing.ALNUM & ~((np.arange(256) >= 0x30) & (np.arange(256) < 0x3A)), lexing.LOWER, 0x20).astype(np.uint8)
_LETTERS[0x41:0x5B] = np.arange(0x61, 0x7B)


def codewords(n: int, seed: int = 7) -> np.ndarray:
    """n rows of +1 and -1: the exhaustive code up to 7 languages, else the best separated of random ones."""
    if n < 2:
        return np.ones((n, 1))
    if n <= 7:
        bits = 2 ** (n - 1) - 1
        table = np.ones((n, bits))
        for r in range(1, n):
            run = 2 ** (n - 1 - r)
            table[r] = np.where((np.arange(bits) // run) % 2 == 0, -1, 1)
        return table
    rng, best, apart = np.random.default_rng(seed), None, -1
    for _ in range(200):
        table = rng.choice([-1.0, 1.0], (n, int(np.ceil(10 * np.log2(n)))))
        if (np.abs(table.sum(0)) == n).any():
            continue
        near = (table.shape[1] - (table @ table.T)[~np.eye(n, dtype=bool)].max()) / 2
        if near > apart:
            best, apart = table, near
    return best


def gram_slots(data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Bucket of the 3-gram that starts at each byte, and whether it holds a letter."""
    x = _LETTERS[data].astype(np.uint32)
    padded = np.concatenate([x, np.full(2, 0x20, np.uint32)])
    code = (padded[:-2] << 16) | (padded[1:-1] << 8) | padded[2:]
    return ((code * np.uint32(2654435761)) >> np.uint32(16)).astype(np.int64), (padded[:-2] != 0x20) | (padded[1:-1] != 0x20)


@dataclass
class Coder:
    languages: list[str]
    code: np.ndarray  # languages x bits
    weights: np.ndarray  # buckets x bits
    scale: np.ndarray  # of each bit's mean

    def margins(self, data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
        """Scaled prediction of each bit for each text."""
        out = np.zeros((len(starts), self.weights.shape[1]))
        n = np.zeros(len(starts), np.int64)
        for low in range(0, len(data), SLICE):  # bounds memory when a text is long
            high = min(low + SLICE, len(data))
            slots, counted = (x[: high - low] for x in gram_slots(data[low : high + 2]))
            rows = np.arange(np.searchsorted(ends, low, "right"), np.searchsorted(starts, high, "left"))
            rows = rows[ends[rows] > starts[rows]]
            if len(rows):
                cuts = np.maximum(starts[rows] - low, 0)
                out[rows] += np.add.reduceat(self.weights[slots] * counted[:, None], cuts, axis=0)
                n[rows] += np.add.reduceat(counted, cuts, dtype=np.int64)
        return out / np.maximum(1, n)[:, None] * self.scale

    def decode(self, margins: np.ndarray) -> np.ndarray:
        """Probability of each language: softmax of the negative summed logistic losses."""
        loss = np.logaddexp(0, -margins[:, None, :] * self.code[None]).sum(2)
        loss -= loss.min(1, keepdims=True)
        p = np.exp(-loss)
        return p / p.sum(1, keepdims=True)


def fit(data: np.ndarray, starts: np.ndarray, ends: np.ndarray, langs: list[str]) -> Coder:
    names = sorted(set(langs))
    code = codewords(len(names))
    counts = np.zeros((len(names), BUCKETS))
    number = {k: i for i, k in enumerate(names)}
    y = np.asarray([number[k] for k in langs], np.int64)
    for a, b in passes(starts, ends):
        low, high = int(starts[a]), int(ends[b - 1])
        slots, counted = gram_slots(data[low:high])
        own = y[a:b][lexing.owners(np.arange(high - low), starts[a:b] - low, ends[a:b] - low)] if high > low else np.zeros(0, np.int64)
        for k in range(len(names)):
            counts[k] += np.bincount(slots[counted & (own == k)], minlength=BUCKETS)
    share = counts / np.maximum(1, counts.sum(1, keepdims=True))
    weights = np.zeros((BUCKETS, code.shape[1]), np.float32)
    for b in range(code.shape[1]):
        plus, minus = share[code[:, b] > 0], share[code[:, b] < 0]
        p, q = (x.mean(0) if len(x) else np.zeros(BUCKETS) for x in (plus, minus))
        weights[:, b] = np.log((p + 1e-6) / (q + 1e-6))
    coder = Coder(names, code, weights, np.ones(code.shape[1]))
    means = [coder.margins(data[int(starts[a]) : int(ends[b - 1])], starts[a:b] - starts[a], ends[a:b] - starts[a]) for a, b in passes(starts, ends)]
    if means:
        coder.scale = 4.0 / np.maximum(1e-6, np.median(np.abs(np.concatenate(means)), axis=0))
    return coder


def train(docs: DataFrame, most: int = TRAIN_DOCS) -> Coder | None:
    marked = docs.where(F.col("lang").isNotNull() & F.col("text").isNotNull() & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id")))
    rows = training_texts(docs, marked.select("doc_id", F.col("lang").alias("label")), most)
    if not rows.num_rows:
        return None
    return fit(*texts_of(rows.column("text").combine_chunks()), rows.column("label").to_pylist())


def predict(docs: DataFrame, coder: Coder | None, text: str = "text") -> DataFrame:
    """doc_id, lang_pred, score and ambiguous of every document."""

    def work(data, starts, ends):
        letter = (_LETTERS[data] != 0x20) & (data < 0x80)
        lettered = lexing.sums_by(letter, starts, ends) > 0
        for i in np.flatnonzero(~lettered & (lexing.sums_by(data >= 0x80, starts, ends) > 0)).tolist():
            lettered[i] = any(map(str.isalpha, data[starts[i] : ends[i]].tobytes().decode("utf-8", "replace")))
        if coder is None:
            n = len(starts)
            return {"lang_pred": pa.array(["und"] * n), "score": np.zeros(n), "ambiguous": np.ones(n, bool)}
        p = coder.decode(coder.margins(data, starts, ends))
        best = p.argmax(1)
        ranked = np.sort(p, 1)
        lead = ranked[:, -1] - (ranked[:, -2] if p.shape[1] > 1 else 0)
        names = [coder.languages[k] if ok else "und" for k, ok in zip(best.tolist(), lettered.tolist(), strict=True)]
        return {"lang_pred": pa.array(names, pa.string()), "score": np.where(lettered, ranked[:, -1], 0.0), "ambiguous": ~lettered | (lead < LEAD)}

    return map_texts(docs, "lang_pred string, score double, ambiguous boolean", work, text=text)


def apply(docs: DataFrame) -> DataFrame:
    coder = train(docs)
    return predict(docs, coder).withColumn("held_out", F.coalesce(held_out(F.col("doc_id")), F.lit(False)))
