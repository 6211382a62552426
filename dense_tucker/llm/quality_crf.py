"""Quality classifier: a linear-chain conditional random field over the lines of a text.

Each line is described by binned measures of its own and of its two neighbours. The field has the states bad
and good; it is fitted by gradient ascent on its likelihood, every line of a labelled document bearing that
document's label. The score is the mean of the forward-backward marginals of `good`, weighted by line length.

Labelled rows for fitting are at most TRAIN_DOCS documents of the training split, each of up to TRAIN_TEXT_BYTES, those
with the least hashed ids; an id with both labels has none. Scoring reads every whole text, a long one in pieces of whole lines,
and the marginals of a text of many lines come from a parallel scan of its transitions. Null, empty and blank texts have no line and score 0. Repeated rows get
equal scores; an empty table gives an empty result; without training rows of both labels every score is 0.5.
Other columns are ignored.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import lexing
from .common import PASS_BYTES, held_out, map_texts, passes, texts_of, training_texts

TRAIN_DOCS = 6_000
THRESHOLD = 0.7
BINS = 10
_UPPER = np.zeros(256, bool)
_UPPER[0x41:0x5B] = True
_LETTER = _UPPER | (np.arange(256) >= 0x80)
_LETTER[0x61:0x7B] = True
_DIGIT = np.zeros(256, bool)
_DIGIT[0x30:0x3A] = True
_SYMBOL = np.zeros(256, bool)
_SYMBOL[list(b"#*$%&<>{}[]=_~^\\/@+")] = True
_BAR = np.arange(256) == 0x7C
_BANG = np.arange(256) == 0x21
_STOP = np.zeros(256, bool)
_STOP[list(b".,;:?")] = True
#: Upper borders of the bins of a share.
_SHARES = np.asarray([0.0, 0.005, 0.02, 0.05, 0.1, 0.2, 0.35, 0.6])
GROUPS = 13
#: Column of the repeats of a line.
REPEATS = 8
#: Lines from which a text's marginals come from the scan.
MANY_LINES = 1_000


def line_features(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Bins (lines x GROUPS) of all lines with a word, the text of each and its length in bytes."""
    bins, row, length, key = [np.concatenate(x) for x in zip(*(_measured(data, a, b, r) for a, b, r in _pieces(data, starts, ends)), strict=True)]
    # equal lines of the same text
    _, group, times = np.unique(lexing.mix(key ^ lexing.mix(row.astype(np.uint64))), return_inverse=True, return_counts=True)
    bins[:, REPEATS] = np.minimum(4, times[group] - 1) if len(group) else group
    return bins, row, length


def _pieces(data: np.ndarray, starts: np.ndarray, ends: np.ndarray):
    """Starts, ends and rows of parts of the texts: all at once, but a text of several passes by whole lines of about one pass."""
    at = 0
    for i in np.flatnonzero(ends - starts > 2 * PASS_BYTES).tolist():
        yield starts[at:i], ends[at:i], np.arange(at, i)
        feeds = np.flatnonzero(data[starts[i] : ends[i]] == 0x0A) + 1 + starts[i]
        low = int(starts[i])
        while low < ends[i]:
            k = int(np.searchsorted(feeds, low + PASS_BYTES))
            high = int(feeds[k]) if k < len(feeds) else int(ends[i])
            yield np.array([low]), np.array([high]), np.array([i])
            low = high
        at = i + 1
    yield starts[at:], ends[at:], np.arange(at, len(starts))


def _measured(data: np.ndarray, starts: np.ndarray, ends: np.ndarray, rows: np.ndarray) -> tuple[np.ndarray, ...]:
    """Bins without the repeats of lines, row, length and hash of each line of these (adjacent) parts."""
    base = int(starts[0]) if len(starts) else 0
    data, starts, ends = data[base : int(ends[-1]) if len(ends) else 0], starts - base, ends - base
    word = lexing.SPACED[data]
    feeds = np.flatnonzero(data == 0x0A)
    some = starts < ends
    first = np.sort(np.concatenate([starts[some], feeds + 1]))
    last = np.maximum(np.sort(np.concatenate([ends[some], feeds])), first)

    def of(flags):
        return lexing.sums_by(flags, first, last)

    filled = of(word)
    keep = filled > 0
    first, last, filled = first[keep], last[keep], filled[keep]
    row = lexing.owners(first, starts, ends)
    length = last - first
    h, a, b, _ = lexing.words(data, starts, ends)
    line = np.searchsorted(first, a, "right") - 1
    n_words = np.bincount(line, minlength=len(first)).astype(np.int64) if len(first) else np.zeros(0, np.int64)
    # words equal to the word before, and words seen in the line already
    same = np.zeros(len(h), bool)
    if len(h) > 1:
        same[1:] = (h[1:] == h[:-1]) & (line[1:] == line[:-1])
    tagged = lexing.mix(h ^ lexing.mix(line.astype(np.uint64)))
    _, at = np.unique(tagged, return_index=True)
    distinct = np.bincount(line[at], minlength=len(first))
    doubled = np.bincount(line[same], minlength=len(first))
    def share(x, of_what):
        return np.searchsorted(_SHARES, x / np.maximum(1, of_what), "left")

    letters = of(_LETTER[data])
    many = np.maximum(1, n_words)
    columns = [
        np.minimum(9, np.log2(length).astype(np.int64)) if len(length) else length,
        share(of(_UPPER[data]), letters),
        share(of(_SYMBOL[data]), length),
        share(of(_DIGIT[data]), length),
        share(of(_BAR[data]), n_words),
        share(of(_BANG[data]), n_words),
        share(doubled, many),
        share(n_words - distinct, many),
        np.zeros(len(first), np.int64),
        np.minimum(9, (filled / many).astype(np.int64)),
        share(of(_STOP[data]), n_words),
        np.minimum(9, np.log2(many).astype(np.int64)),
        _UPPER[data[first]].astype(np.int64) + 2 * _STOP[data[last - 1]] if len(first) else first,
    ]
    bins = np.stack(columns, 1).astype(np.int8) if len(first) else np.zeros((0, GROUPS), np.int8)
    return bins, rows[row] if len(row) else row, length, lexing.span_hashes(data, first, last)


def _slots(bins: np.ndarray, row: np.ndarray) -> np.ndarray:
    """Indices into the flat weights: own, previous and next line's bins (slot 0 of a neighbour group: none)."""
    width = GROUPS * (BINS + 1)
    own = (np.arange(GROUPS) * (BINS + 1) + bins + 1).astype(np.int32)
    edge = (np.arange(GROUPS) * (BINS + 1)).astype(np.int32)
    before = np.broadcast_to(edge, own.shape).copy()
    after = before.copy()
    if len(own) > 1:
        same = row[1:] == row[:-1]
        before[1:][same] = own[:-1][same]
        after[:-1][same] = own[1:][same]
    return np.concatenate([own, before + width, after + 2 * width], 1)


@dataclass
class Field:
    weights: np.ndarray  # of binned features, for the state good
    moves: np.ndarray  # 2 x 2 transition scores
    bias: float

    @classmethod
    def blank(cls) -> Field:
        return cls(np.zeros(3 * GROUPS * (BINS + 1)), np.zeros((2, 2)), 0.0)

    def emissions(self, slots: np.ndarray) -> np.ndarray:
        return self.weights[slots].sum(1) + self.bias

    def judged(self, bins: np.ndarray, row: np.ndarray) -> np.ndarray:
        """Emissions of all lines, whose slots are made for some lines at a time."""
        step = 1 << 15
        out = np.empty(len(bins))
        for a in range(0, len(bins), step):
            low, high = max(0, a - 1), min(len(bins), a + step + 1)
            out[a : a + step] = self.emissions(_slots(bins[low:high], row[low:high]))[a - low : a - low + step]
        return out

    def good(self, emissions: np.ndarray, n: np.ndarray) -> np.ndarray:
        """P(good) of each line; n: each text's number of lines."""
        first = np.cumsum(n) - n
        long = np.flatnonzero(n > MANY_LINES)
        short = np.ones(len(emissions), bool)
        out = np.empty(len(emissions))
        for i in long.tolist():
            at = slice(int(first[i]), int(first[i] + n[i]))
            short[at] = False
            out[at] = self.scanned(emissions[at])
        some = n.copy()
        some[long] = 0
        out[short] = self.marginals(emissions[short], np.cumsum(some) - some, some)[0]
        return out

    def scanned(self, emissions: np.ndarray) -> np.ndarray:
        """P(good) of each line of one text, by prefix and suffix products of 2 x 2 matrices in doubling steps."""
        weight = np.stack([np.ones_like(emissions), np.exp(np.clip(emissions, -30, 30))], 1)
        step = np.exp(self.moves)[None] * weight[:, None, :]
        ahead = step.copy()
        ahead[0] = np.diag(weight[0])
        back = np.concatenate([step[1:], np.eye(2)[None]])
        k = 1
        while k < len(step):
            ahead[k:] = ahead[:-k] @ ahead[k:]
            back[:-k] = back[:-k] @ back[k:]
            for x in (ahead, back):
                x /= x.sum((1, 2), keepdims=True)
            k *= 2
        both = ahead.sum(1) * back.sum(2)
        return both[:, 1] / both.sum(1)

    def marginals(self, good: np.ndarray, first: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """P(good) of each line, summed pair marginals (2 x 2) and log partition of each text.

        first, n: each text's first line and number of lines. Texts run side by side, the longest first."""
        order = np.argsort(-n, kind="stable")
        first, n = first[order], n[order]
        longest = int(n[0]) if len(n) else 0
        alive = np.searchsorted(-n, -np.arange(longest), "left") if longest else np.zeros(0, np.int64)  # texts with more than t lines
        move = np.exp(self.moves)
        forward = np.zeros((len(good), 2))
        scale = np.ones(len(good))
        odds = np.clip(good, -30, 30)
        weight = np.stack([np.ones_like(odds), np.exp(odds)], 1)
        for t in range(longest):
            at = first[: alive[t]] + t
            now = weight[at] * (forward[at - 1] @ move) if t else weight[at].copy()
            scale[at] = now.sum(1)
            forward[at] = now / scale[at][:, None]
        backward = np.ones((len(good), 2))
        for t in range(longest - 2, -1, -1):
            at = first[: alive[t + 1]] + t
            backward[at] = (weight[at + 1] * backward[at + 1]) @ move.T / scale[at + 1][:, None]
        both = forward * backward
        p = both[:, 1] / both.sum(1)
        inner = np.ones(len(good), bool)
        inner[first[n > 0]] = False
        at = np.flatnonzero(inner)
        joint = forward[at - 1][:, :, None] * move * (weight[at] * backward[at])[:, None, :] / scale[at][:, None, None]
        log_z = np.log(scale)
        return p, joint.sum(0), log_z


def fit(bins: np.ndarray, row: np.ndarray, labels: np.ndarray, rounds: int = 150, rate: float = 0.08, ridge: float = 1e-3) -> Field:
    """Maximum likelihood by Adam over all given lines; labels has one entry for each line's text."""
    field = Field.blank()
    y = labels[row].astype(float)
    if len(y) == 0 or y.min() == y.max():
        return field
    slots = _slots(bins, row)
    n = np.bincount(row, minlength=len(labels))
    first = np.cumsum(n) - n
    inner = np.zeros(len(row), bool)
    inner[1:] = row[1:] == row[:-1]
    stay = np.zeros((2, 2))
    for k in (0, 1):
        stay[k, k] = (inner & (y == k)).sum()
    texts = max(1, int((n > 0).sum()))
    flat = np.concatenate([field.weights, field.moves.ravel(), [0.0]])
    m, v = np.zeros_like(flat), np.zeros_like(flat)
    size = len(field.weights)
    for step in range(1, rounds + 1):
        field = Field(flat[:size], flat[size : size + 4].reshape(2, 2), float(flat[-1]))
        p, joint, _ = field.marginals(field.emissions(slots), first, n)
        miss = y - p
        slope = np.bincount(slots.ravel(), np.repeat(miss, slots.shape[1]), minlength=size)
        full = np.concatenate([slope, (stay - joint).ravel(), [miss.sum()]]) / texts - ridge * flat
        m, v = 0.9 * m + 0.1 * full, 0.99 * v + 0.01 * full**2
        flat = flat + rate * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.99**step)) + 1e-8)
    return Field(flat[:size], flat[size : size + 4].reshape(2, 2), float(flat[-1]))


def train(docs: DataFrame, labels: DataFrame, most: int = TRAIN_DOCS) -> Field:
    """Fit on at most `most` labelled documents of the training split (least hashed ids first)."""
    marked = labels.where(F.col("quality").isin(0, 1) & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id"))).select("doc_id", F.col("quality").cast("int").alias("label"))
    rows = training_texts(docs, marked, most)
    data, starts, ends = texts_of(rows.column("text"))
    y = rows.column("label").to_numpy()
    bins, row = [], []
    for a, b in passes(starts, ends):
        low = int(starts[a])
        f, r, _ = line_features(data[low : int(ends[b - 1])], starts[a:b] - low, ends[a:b] - low)
        bins.append(f)
        row.append(r + a)
    if not bins:
        return Field.blank()
    return fit(np.concatenate(bins), np.concatenate(row), y)


def _judge(field: Field, threshold: float, data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> dict[str, np.ndarray]:
    """score, predicted, n_lines and n_bad_lines of each text."""
    bins, row, length = line_features(data, starts, ends)
    n = np.bincount(row, minlength=len(starts))
    p = field.good(field.judged(bins, row), n)
    total = np.bincount(row, length, minlength=len(starts))
    mean = np.clip(np.bincount(row, p * length, minlength=len(starts)) / np.maximum(1, total), 0, 1)
    return {"score": mean, "predicted": (mean >= threshold).astype(np.int32), "n_lines": n.astype(np.int64), "n_bad_lines": np.bincount(row[p < 0.5], minlength=len(starts)).astype(np.int64)}


def score(docs: DataFrame, field: Field, threshold: float = THRESHOLD, text: str = "text", keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """doc_id, score, predicted, n_lines and n_bad_lines of every document."""
    return map_texts(docs, "score double, predicted int, n_lines long, n_bad_lines long", partial(_judge, field, threshold), keep=keep, text=text)


def apply(docs: DataFrame, labels: DataFrame) -> DataFrame:
    field = train(docs, labels)
    return score(docs, field).withColumn("held_out", F.coalesce(held_out(F.col("doc_id")), F.lit(False)))


def keep(docs: DataFrame, labelled: DataFrame, labels: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """Documents that the classifier accepts, with all their columns; `labelled` holds the texts of `labels`."""
    field, place = train(labelled, labels), docs.columns.index("text")

    def run(batches):
        for batch in batches:
            data, starts, ends = texts_of(batch.column(place))
            for a, b in passes(starts, ends):
                low, high = int(starts[a]), int(ends[b - 1])
                good = _judge(field, threshold, data[low:high], starts[a:b] - low, ends[a:b] - low)["predicted"] == 1
                yield batch.slice(a, b - a).filter(pa.array(good))

    return docs.mapInArrow(run, docs.schema)


__all__ = ["Field", "apply", "fit", "keep", "line_features", "score", "train"]
