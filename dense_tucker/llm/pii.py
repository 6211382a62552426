"""Personal data: base patterns, and a character BiLSTM with CRF transitions that adds spans to them.

The network is trained in numpy by gradient ascent on the CRF likelihood, from labelled spans: those that the base patterns
find in at most TRAIN_DOCS documents, and values in writings that the base patterns do not know (`jo (at) mail (dot) org`,
`192[.]0[.]2[.]7`, numbers without a plus sign, with dots or in words), set into text of these documents beside harmless
numbers and words. At use it reads every character of every text in windows of WINDOW characters that overlap by twice
MARGIN; each character's tag is taken from the window in which it stands most central, and spans are cut over the
whole text, at the borders of words. A span is added if it meets no base span and, written plainly, passes the
base rule's check of its kind (parts up to 255, Luhn, number of digits, form of an address).

Null and empty texts have no spans. Spans are code points, end exclusive. Repeated rows are answered one by
one; an empty table gives an empty result; without a training text only base patterns answer. Other columns
are ignored (redact keeps them). Base patterns take time in proportion to the text, whatever it holds.
"""

from __future__ import annotations

import hashlib
import re
from dataclasses import dataclass, field
from itertools import accumulate

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import lexing
from .common import TRAIN_TEXT_BYTES, slices, texts_of

KINDS = ("email", "ip", "card", "phone")
TRAIN_DOCS = 2_000
#: Characters of a window, and of its borders that its neighbours decide.
WINDOW = 768
MARGIN = 32
#: Lengths of windows are rounded up to a multiple of this, so that a window's answer does not hang on its neighbours in a batch.
ROUND = 128
#: Bytes of texts that are tagged together: enough for full batches of windows.
SLICE_BYTES = 8 << 20
#: Characters of a training window, and training windows made for each document.
SAMPLE = 88
PER_DOC = 3
#: Words by which a found span may grow or shrink at either border.
REACH = 6
HIDDEN = 12
EMBED = 8
#: Fixed patterns of the base rules.
_LOCAL = re.compile(r"[A-Za-z0-9._%+-]+")
_DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_EMAIL = re.compile(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+")
_PARTS = re.compile(r"[0-9]++(?:\.[0-9]++)*+")
_CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])++")
_PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
_TRIGGER = np.zeros(256, bool)
_TRIGGER[0x30:0x3A] = True
_TRIGGER[0x40] = True
_CLASS = np.full(128, 96, np.uint8)
_CLASS[0x20:0x7F] = np.arange(1, 96)
_CLASS[0x0A] = 97
#: Written digits.
_WORDS = ("zero", "one", "two", "three", "four", "five", "six", "seven", "eight", "nine")
Span = tuple[str, int, int]


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = ord(c) - 48
        if i % 2:
            d = d * 2 - 9 if d > 4 else d * 2
        total += d
    return total % 10 == 0


def _emails(text: str) -> list[Span]:
    """Each @ takes the address characters before it that no earlier match holds, and labels after it."""
    out: list[Span] = []
    at, free = text.find("@"), 0
    while at >= 0:
        before = _LOCAL.match(text[free:at][::-1])
        after = _DOMAIN.match(text, at + 1) if before else None
        free = at + 1
        if after:
            out.append(("email", at - before.end(), after.end()))
            free = after.end()
        at = text.find("@", free)
    return out


def _ips(text: str) -> list[Span]:
    """Fours of the parts of every maximal run of dotted numbers."""
    out: list[Span] = []
    for m in _PARTS.finditer(text):
        parts = m[0].split(".")
        start = m.start()
        for k in range(0, len(parts) // 4 * 4, 4):
            four = parts[k : k + 4]
            end = start + sum(map(len, four)) + 3
            if all(_small(x) for x in four):
                out.append(("ip", start, end))
            start = end + 1
    return out


def _small(digits: str) -> bool:
    digits = digits.lstrip("0")
    return len(digits) < 4 and int(digits or "0") <= 255


def base_spans(text: str) -> list[Span]:
    """Spans of the base rules, by start, then kind as listed; one pass over the text for each kind."""
    out = _emails(text) if "@" in text else []
    if "." in text:
        out += _ips(text)
    for m in _CARD.finditer(text):
        if 12 <= m.end() - m.start() <= 37:
            digits = m[0].replace(" ", "").replace("-", "")
            if 12 <= len(digits) <= 19 and luhn(digits):
                out.append(("card", m.start(), m.end()))
    if "+" in text:
        out += [("phone", m.start(), m.end()) for m in _PHONE.finditer(text) if 9 <= sum(map(str.isdigit, m[0])) <= 15]
    return sorted(out, key=lambda s: (s[1], KINDS.index(s[0])))


def written(spans: list[Span]) -> str:
    return ",".join(f"{k}:{a}:{b}" for k, a, b in spans)


def _codes(text: str) -> np.ndarray:
    """Class of each character: 1-95 printable ASCII, 96 other, 97 line feed; 0 is padding."""
    if text.isascii():
        return _CLASS[np.frombuffer(text.encode(), np.uint8)]
    points = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), "<u4")
    return np.where(points < 128, _CLASS[np.minimum(points, 127)], np.uint8(96))


# Values and their writings, for training


def _one(rng: np.random.Generator, options):
    return options[int(rng.integers(0, len(options)))]


def _plain(rng: np.random.Generator, kind: str, words: list[str]) -> str:
    """A value that its base pattern finds."""
    number = lambda n: "".join(map(str, rng.integers(0, 10, n)))
    if kind == "email":
        name = [_one(rng, words).lower() for _ in range(3)]
        local = _one(rng, [name[0], f"{name[0]}.{name[1]}", f"{name[0]}{rng.integers(1, 99)}", f"{name[0][:1]}{name[1]}"])
        return f"{local}@{name[2]}.{_one(rng, ['com', 'org', 'net', 'de', 'fr', 'example.com', 'co.uk', 'io'])}"
    if kind == "ip":
        return ".".join(map(str, rng.integers(0, 256, 4)))
    if kind == "card":
        body = str(rng.integers(3, 7)) + number(_one(rng, [13, 14, 14, 14]))
        digits = next(body + str(d) for d in range(10) if luhn(body + str(d)))
        return _one(rng, ["", " ", "-"]).join(digits[i : i + 4] for i in range(0, len(digits), 4))
    a, b = str(rng.integers(1, 100)), number(3)
    return _one(rng, [f"+{a} {b} {number(7)}", f"+{a} ({b}) {number(3)}-{number(4)}", f"+{a}{b}{number(7)}", f"+{a}-{b}-{number(3)}-{number(4)}"])


def _disguised(rng: np.random.Generator, kind: str, value: str) -> str:
    """The value in a writing that its base pattern does not find."""
    digits = re.sub("[^0-9]", "", value)
    if kind == "email":
        local, host = value.split("@")
        at = _one(rng, [" at ", " (at) ", "[at]", " AT ", "(at)", " [at] ", " @ "])
        dot = {" at ": " dot ", " AT ": " DOT ", " (at) ": " (dot) ", "[at]": "[dot]", "(at)": "(dot)", " [at] ": " [dot] ", " @ ": " . "}[at]
        return local + at + host.replace(".", dot if rng.random() < 0.7 or at in (" @ ", " at ", " AT ") else ".")
    if kind == "ip":
        return value.replace(".", _one(rng, ["[.]", " . ", "(.)", " dot ", "[dot]"]))
    if kind == "card":
        step = _one(rng, [".", "_", "/", "  ", "words"])
        if step == "words":
            return " ".join(_WORDS[int(d)] for d in digits)
        return step.join(digits[i : i + 4] for i in range(0, len(digits), 4))
    form = int(rng.integers(0, 6))
    if form == 0:
        return "plus " + " ".join(_WORDS[int(d)] for d in digits)
    last = digits[-10:]
    return (f"({last[:3]}) {last[3:6]}-{last[6:]}", f"({last[:3]}) {last[3:6]}-{last[6:]}", f"00{digits[:2]} {digits[2:5]} {digits[5:]}", f"{last[:3]}.{last[3:6]}.{last[6:]}", f"{last[:3]}-{last[3:6]}-{last[6:]}", f"{last[:3]}/{last[3:6]}-{last[6:]}")[form]


def _harmless(rng: np.random.Generator, words: list[str]) -> str:
    """Numbers and words that are no personal data."""
    n = lambda a, b: int(rng.integers(a, b))
    a, b, c = (_one(rng, words) for _ in range(3))
    forms = (
        lambda: f"{n(1900, 2100)}-{n(1, 13):02d}-{n(1, 29):02d}", lambda: f"{n(1, 29)}/{n(1, 13)}/{n(1900, 2100)}", lambda: f"{n(0, 24)}:{n(0, 60):02d}", lambda: f"{n(1, 999)},{n(0, 1000):03d}.{n(0, 100):02d}",
        lambda: f"v{n(0, 20)}.{n(0, 20)}.{n(0, 20)}", lambda: f"{n(1, 100)}.{n(0, 100)}%", lambda: f"{a} at {b}", lambda: f"{a} (at {b})", lambda: f"a dot {a}", lambda: f"{' '.join(_WORDS[k] for k in rng.integers(0, 10, n(1, 4)))} {a}",
        lambda: f"{a}@{b}", lambda: f"@{a}", lambda: f"{a}.{b}.{c}", lambda: f"{n(1, 10**6)}", lambda: f"no. {n(1, 10**4)}", lambda: f"{n(10, 99)} {n(10, 99)} {n(10, 99)}", lambda: f"{n(1900, 2000)}-{n(2000, 2100)}", lambda: f"[{n(1, 99)}]",
        lambda: f"({n(1, 99)})", lambda: f"{n(1, 20)}.{n(1, 20)}", lambda: f"+{n(1, 99)}", lambda: f"{a}/{b}/{n(1, 99)}", lambda: f"#{n(1, 10**5)}", lambda: f"{n(1, 50)}, {n(1, 50)}, {n(1, 50)}, {n(1, 50)}", lambda: f"{a} [{b}] {c}", lambda: f"{a} {b}. {c}", lambda: f"{a} at www.{b}.com",
    )
    return _one(rng, forms)()


def disguised_samples(texts: list[str], n: int, seed: int) -> list[tuple[str, list[Span], list[Span]]]:
    """n windows of these texts with values set in: (window, all spans, those in a writing that base patterns do not find)."""
    rng = np.random.default_rng(seed)
    words = sorted({w for t in texts[:500] for w in re.findall(r"[A-Za-z]{2,10}", t[:2_000])}) or ["name", "mail", "host"]
    full = [t for t in texts if t] or [" "]
    out = []
    for _ in range(n):
        text = full[int(rng.integers(0, len(full)))]
        start = int(rng.integers(0, max(1, len(text) - 40)))
        piece = text[start : start + int(rng.integers(10, 60))]
        cut = piece.rfind(" ", 0, int(rng.integers(1, len(piece) + 1))) + 1
        head, tail = piece[:cut], piece[cut:]
        what, hidden = rng.random(), False
        if what < 0.12:
            put, kind = "", None
        elif what < 0.35:
            put, kind = _harmless(rng, words), None
        else:
            kind = _one(rng, KINDS)
            put = _plain(rng, kind, words)
            if what > 0.5:
                put, hidden = _disguised(rng, kind, put), True
        before, after = _one(rng, ["", "", "", "(", ": ", "\n", "call ", "tel. ", "mail: ", "see "]), _one(rng, [" ", " ", " ", ". ", ", ", ") ", "\n"])
        made = head + before + put + after + tail
        at = len(head) + len(before)
        spans = base_spans(made) if kind is None or not hidden else [s for s in base_spans(made) if s[2] <= at or s[1] >= at + len(put)]
        mine = [(kind, at, at + len(put))] if hidden else []
        out.append((made, sorted(spans + mine, key=lambda s: s[1]), mine))
    return out


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 0.5 * np.tanh(0.5 * x) + 0.5


@dataclass
class Tagger:
    """Parameters by name; tags: 0 outside, then begin and inside of each kind. Gates in order: forget, input, output, candidate.

    `w` and `out` have one layer for each direction; the backward one reads a window from its (padded) end.
    """

    p: dict[str, np.ndarray] = field(default_factory=dict)

    @classmethod
    def new(cls, hidden: int = HIDDEN, embed: int = EMBED, seed: int = 11) -> Tagger:
        rng = np.random.default_rng(seed)
        tags = 1 + 2 * len(KINDS)
        p = {"embed": rng.normal(0, 0.3, (98, embed)), "out": rng.normal(0, 0.2, (2, hidden, tags)), "out_b": np.zeros(tags), "move": np.zeros((tags, tags))}
        p["w"] = rng.normal(0, 1 / np.sqrt(embed + hidden), (2, embed + hidden, 4 * hidden))
        p["b"] = np.zeros((2, 4 * hidden))
        p["b"][:, :hidden] = 1
        return cls({k: v.astype(np.float32) for k, v in p.items()})

    def emissions(self, codes: np.ndarray):
        """codes: batch x time. Scores time x batch x tags, and what gradients() needs."""
        x = self.p["embed"][codes.T]
        x = np.stack([x, x[::-1]], 1)  # time x direction x batch x embed
        w, e = self.p["w"], x.shape[3]
        n = w.shape[2] // 4
        drive = x @ w[:, :e] + self.p["b"][:, None]
        shape = (*x.shape[:3], n)
        h, c, gates, tanh_c = np.zeros((shape[0] + 1, *shape[1:]), x.dtype), np.zeros((shape[0] + 1, *shape[1:]), x.dtype), np.empty((*shape[:3], 4 * n), x.dtype), np.empty(shape, x.dtype)
        for t in range(shape[0]):
            z = drive[t] + h[t] @ w[:, e:]
            gates[t, ..., : 3 * n] = _sigmoid(z[..., : 3 * n])
            gates[t, ..., 3 * n :] = np.tanh(z[..., 3 * n :])
            f, i, o, g = (gates[t, ..., k * n : (k + 1) * n] for k in range(4))
            c[t + 1] = f * c[t] + i * g
            np.tanh(c[t + 1], out=tanh_c[t])
            h[t + 1] = o * tanh_c[t]
        scores = h[1:, 0] @ self.p["out"][0] + h[1:, 1][::-1] @ self.p["out"][1] + self.p["out_b"]
        return scores, (x, h, c, gates, tanh_c)

    def marginals(self, scores: np.ndarray, mask: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Tag probabilities (time x batch x tags) and expected transitions, by scaled forward-backward."""
        move = np.exp(self.p["move"].astype(np.float64))
        e = np.exp(scores.astype(np.float64) - scores.max(2, keepdims=True))
        e = np.where(mask[:, :, None], e, 1.0)
        T = len(e)
        fwd, scale = np.empty_like(e), np.empty(e.shape[:2] + (1,))
        now = e[0]
        for t in range(T):
            if t:
                now = np.where(mask[t][:, None], e[t] * (fwd[t - 1] @ move), fwd[t - 1])
            scale[t] = now.sum(1, keepdims=True)
            fwd[t] = now / scale[t]
        bwd = np.ones_like(e)
        pair = np.zeros_like(move)
        for t in range(T - 2, -1, -1):
            ahead = e[t + 1] * bwd[t + 1] / scale[t + 1]
            live = mask[t + 1][:, None]
            pair += move * ((fwd[t] * live).T @ (ahead * live))
            bwd[t] = np.where(live, ahead @ move.T, bwd[t + 1])
        post = fwd * bwd
        return post / post.sum(2, keepdims=True), pair

    def gradients(self, codes: np.ndarray, tags: np.ndarray) -> dict[str, np.ndarray]:
        """Ascent direction of the mean log likelihood of tags (batch x time; -1 is padding)."""
        mask = (tags >= 0).T
        scores, (x, h, c, gates, tanh_c) = self.emissions(codes)
        post, pair = self.marginals(scores, mask)
        n_tags = scores.shape[2]
        d = ((np.eye(n_tags)[np.maximum(tags.T, 0)] - post) * mask[:, :, None]).astype(x.dtype) / len(codes)
        inner = mask[1:] & mask[:-1]
        seen = np.zeros((n_tags, n_tags))
        np.add.at(seen, (np.maximum(tags.T[:-1], 0)[inner], np.maximum(tags.T[1:], 0)[inner]), 1)
        both, n_hidden = np.stack([d, d[::-1]], 1), h.shape[3]
        grads = {"move": ((seen - pair) / len(codes)).astype(x.dtype), "out": h[1:].transpose(1, 3, 0, 2).reshape(2, n_hidden, -1) @ both.transpose(1, 0, 2, 3).reshape(2, -1, n_tags), "out_b": d.sum((0, 1))}
        d_h = both @ self.p["out"].transpose(0, 2, 1)
        w, e = self.p["w"], x.shape[3]
        n = w.shape[2] // 4
        back = w.transpose(0, 2, 1)
        dz = np.empty_like(gates)
        dh, dc = np.zeros_like(h[0]), np.zeros_like(h[0])
        for t in range(len(x) - 1, -1, -1):
            f, i, o, g = (gates[t, ..., k * n : (k + 1) * n] for k in range(4))
            dh = dh + d_h[t]
            dc = dc + dh * o * (1 - tanh_c[t] ** 2)
            dz[t, ..., :n] = dc * c[t] * f * (1 - f)
            dz[t, ..., n : 2 * n] = dc * g * i * (1 - i)
            dz[t, ..., 2 * n : 3 * n] = dh * tanh_c[t] * o * (1 - o)
            dz[t, ..., 3 * n :] = dc * i * (1 - g * g)
            dh = dz[t] @ back[..., e:]
            dc = dc * f
        flat = dz.transpose(1, 0, 2, 3).reshape(2, -1, 4 * n)
        inputs = np.concatenate([x, h[:-1]], 3).transpose(1, 0, 2, 3).reshape(2, flat.shape[1], -1)
        grads["w"], grads["b"] = inputs.transpose(0, 2, 1) @ flat, flat.sum(1)
        dx = dz @ back[..., :e]
        dx = dx[:, 0] + dx[::-1, 1]
        grads["embed"] = np.stack([np.bincount(codes.T.ravel(), dx[..., k].ravel(), minlength=98) for k in range(e)], 1).astype(x.dtype)
        return grads

    def scores(self, codes: np.ndarray) -> np.ndarray:
        """codes: batch x time. Scores time x tags x batch, in a layout that keeps all steps in long contiguous rows."""
        # a gate is 1 / (1 + exp(-z)) and tanh(z) is 2 / (1 + exp(-2z)) - 1, so products become divisions by 1 + exp; the cell is kept times -2.
        # An exponential that overflows leaves the limits 0 and -1.
        n, e = self.p["w"].shape[2] // 4, self.p["embed"].shape[1]
        w = np.concatenate([self.p["w"].transpose(0, 2, 1), self.p["b"][:, :, None]], 2)
        w[:, : 3 * n] *= -1
        w[:, 3 * n :] *= -2
        bias = np.stack([self.p["out_b"], np.zeros_like(self.p["out_b"])])
        # one product gives the gates of a step and the scores of the step before, whose hidden state is the one that it reads
        out = np.concatenate([np.zeros((2, bias.shape[1], e), w.dtype), self.p["out"].transpose(0, 2, 1), bias[:, :, None]], 2)
        w, embed = np.concatenate([w, out], 1), np.ascontiguousarray(self.p["embed"].T)
        B, T = codes.shape
        at = np.ascontiguousarray(codes.T).astype(np.intp)
        state = np.zeros((2, e + n + 1, B), np.float32)
        state[:, -1] = 1
        h, c, every, part = state[:, e:-1], np.zeros((2, n, B), np.float32), np.empty((2, w.shape[1], B), np.float32), np.empty((2, n, B), np.float32)
        z, now = every[:, : 4 * n], every[:, 4 * n :]
        f, i, o, g = (z[:, k * n : (k + 1) * n] for k in range(4))
        made = np.empty((T, out.shape[1], B), np.float32)
        with np.errstate(over="ignore"):
            for t in range(T + 1):
                if t < T:
                    np.take(embed, at[t], axis=1, out=state[0, :e], mode="clip")
                    np.take(embed, at[T - 1 - t], axis=1, out=state[1, :e], mode="clip")
                np.matmul(w, state, out=every)
                if t and t - 1 < T - t:
                    made[t - 1], made[T - t] = now
                elif t and t - 1 == T - t:
                    np.add(now[0], now[1], out=made[t - 1])
                elif t:
                    made[t - 1] += now[0]
                    made[T - t] += now[1]
                if t == T:
                    break
                np.exp(z, out=z)
                z += 1
                c /= f
                np.divide(-4, g, out=part)
                part += 2
                part /= i
                c += part
                np.exp(c, out=part)
                part += 1
                np.divide(2, part, out=part)
                part -= 1
                np.divide(part, o, out=h)
        return made

    def undecided(self, scores: np.ndarray, mask: np.ndarray | None = None) -> np.ndarray:
        """Of scores time x tags x batch: the rows whose best path is not all `outside`, by a Viterbi pass without links; mask (time x batch): no padding.

        First with three tags (outside, any begin, any inside) and the best transition between any two of each, which no path outdoes;
        then with all tags for the rows that this leaves.
        """
        move = self.p["move"] - self.p["move"][0, 0]
        kinds = [[0], list(range(1, len(move), 2)), list(range(2, len(move), 2))]
        rough = np.asarray([[move[np.ix_(a, b)].max() for b in kinds] for a in kinds], np.float32)
        away = None if mask is None or mask.all() else np.where(mask, np.float32(0), np.float32(1e4))
        some = np.flatnonzero(_gains(scores, rough, away, True) > 1e-4)
        return some[_gains(scores[:, :, some], move, None if away is None else away[:, some]) > 1e-4] if len(some) else some

    def decode(self, scores: np.ndarray, mask: np.ndarray) -> np.ndarray:
        """Of scores time x batch x tags: best tag sequence (batch x time, by Viterbi)."""
        move = self.p["move"]
        T, B, K = scores.shape
        best = np.empty((T, K, B), np.result_type(scores, move))
        best[0] = scores[0].T
        ways = np.empty((K, K, B), best.dtype)
        for t in range(1, T):
            np.add(best[t - 1][:, None], move[:, :, None], out=ways)
            np.max(ways, 0, out=best[t])
            best[t] += scores[t].T
            if not mask[t].all():
                best[t] = np.where(mask[t], best[t], best[t - 1])
        tags = np.zeros((T, B), np.int64)
        now = best[-1].argmax(0)
        for t in range(T - 1, -1, -1):
            tags[t] = np.where(mask[t], now, 0)
            if t:
                now = np.where(mask[t], (best[t - 1] + move[:, now]).argmax(0), now)
        return tags.T


def _gains(scores: np.ndarray, move: np.ndarray, away: np.ndarray | None = None, rough: bool = False) -> np.ndarray:
    """How much the best path of each row gains over the one that keeps the first tag; move: transitions over that tag's to itself.

    away (time x batch) is taken from the other tags; rough: of three tags, the second and third stand for the odd and the even ones.
    """
    move = move[:, :, None].astype(np.float32)
    steps, _, rows = scores.shape
    if rough:
        over = np.empty((steps, 2, rows), np.float32)
        np.max(scores[:, 1::2], 1, out=over[:, 0])
        np.max(scores[:, 2::2], 1, out=over[:, 1])
        over -= scores[:, :1]
    else:
        over = scores[:, 1:] - scores[:, :1]
    if away is not None:
        over -= away[:, None]
    best, ways = np.zeros((len(move), rows), np.float32), np.empty((*move.shape[:2], rows), np.float32)
    others = best[1:]
    others += over[0]
    for step in over[1:]:
        np.add(best[:, None], move, out=ways)
        np.maximum.reduce(ways, 0, out=best)
        others += step
    return best.max(0)


def _tags(n: int, spans: list[Span]) -> np.ndarray:
    tags = np.zeros(n, np.int64)
    for kind, a, b in spans:
        if not tags[a:b].any():
            k = KINDS.index(kind)
            tags[a:b] = 2 + 2 * k
            tags[a] = 1 + 2 * k
    return tags


def examples(texts: list[str], seed: int = 5) -> tuple[list[np.ndarray], list[np.ndarray]]:
    """Training windows and their tags: one around each base span, and windows with values set in."""
    rng = np.random.default_rng(seed)
    xs: list[np.ndarray] = []
    ys: list[np.ndarray] = []
    for text in texts:
        spans = base_spans(text)
        if spans:
            tags, codes = _tags(len(text), spans), _codes(text)
            for _, a, b in spans:
                f = max(0, min(a - int(rng.integers(0, 40)), b + 20 - SAMPLE))
                xs.append(codes[f : f + SAMPLE])
                ys.append(tags[f : f + SAMPLE])
    for text, spans, _ in disguised_samples(texts, PER_DOC * len(texts), seed):
        xs.append(_codes(text)[:SAMPLE])
        ys.append(_tags(len(text), spans)[:SAMPLE])
    return xs, ys


def fit(texts: list[str], steps: int = 900, batch: int = 32, rate: float = 0.02, seed: int = 5) -> Tagger | None:
    """Train on the labelled windows of these texts; None without a text."""
    if not any(texts):
        return None
    xs, ys = examples(texts, seed)
    rng = np.random.default_rng(seed)
    net = Tagger.new()
    m = {k: np.zeros_like(v) for k, v in net.p.items()}
    v2 = {k: np.zeros_like(v) for k, v in net.p.items()}
    for step in range(1, steps + 1):
        pick = rng.choice(len(xs), batch)
        codes, tags = np.zeros((batch, SAMPLE), np.int64), np.full((batch, SAMPLE), -1, np.int64)
        for r, i in enumerate(pick.tolist()):
            codes[r, : len(xs[i])], tags[r, : len(xs[i])] = xs[i], ys[i]
        now = rate * (1 - 0.95 * step / steps)
        for k, g in net.gradients(codes, tags).items():
            m[k] = 0.9 * m[k] + 0.1 * g
            v2[k] = 0.99 * v2[k] + 0.01 * g * g
            net.p[k] = (net.p[k] + now * (m[k] / (1 - 0.9**step)) / (np.sqrt(v2[k] / (1 - 0.99**step)) + 1e-6)).astype(np.float32)
    return net


def train(docs: DataFrame, most: int = TRAIN_DOCS, longest: int = TRAIN_TEXT_BYTES) -> Tagger | None:
    """Fit on at most `most` documents of up to `longest` bytes, those with the least hashed ids."""
    ids = docs.where(F.col("text").isNotNull() & F.col("doc_id").isNotNull()).select("doc_id").orderBy(F.xxhash64("doc_id"), "doc_id").limit(most).distinct()
    short = docs.select("doc_id", F.col("text").cast("string").alias("text")).where(F.col("text").isNotNull() & (F.octet_length("text") <= longest))
    rows = short.join(F.broadcast(ids), "doc_id").groupBy("doc_id").agg(F.min("text").alias("text")).orderBy("doc_id").select("text").toArrow()
    return fit(rows.column("text").to_pylist())


def windows_of(n: int, size: int = WINDOW, margin: int = MARGIN) -> list[tuple[int, int, int, int]]:
    """First and end character of each window of a text of n characters, and the part of it that the window decides."""
    step = size - 2 * margin
    firsts = range(0, max(1, n - 2 * margin), step) if n else ()
    last = len(firsts) - 1
    return [(f, min(n, f + size), f + margin if k else 0, n if k == last else f + margin + step) for k, f in enumerate(firsts)]


def model_spans(texts: list[str], net: Tagger, batch: int = 512) -> list[list[Span]]:
    """Spans that the network finds in each text, reconciled over its windows."""
    coded = [_codes(t) for t in texts]
    alike: dict[int, list[tuple[int, int, int, int, int]]] = {}
    for i, c in enumerate(coded):
        for f, e, a, b in windows_of(len(c)):
            alike.setdefault(-(-(e - f) // ROUND) * ROUND, []).append((i, f, e, a, b))
    tags: dict[int, np.ndarray] = {}
    for size, places in alike.items():
        held: list[tuple[np.ndarray, np.ndarray, list]] = []  # what is left to decode: few windows of each batch
        for s in range(0, len(places), batch):
            part = places[s : s + batch]
            codes = np.zeros((len(part), size), np.uint8)
            for r, (i, f, e, _, _) in enumerate(part):
                codes[r, : e - f] = coded[i][f:e]
            scores = net.scores(codes)
            mask = codes.T > 0
            open_ = net.undecided(scores, mask)
            if len(open_):
                held.append((scores[:, :, open_].transpose(0, 2, 1), mask[:, open_], [part[k] for k in open_.tolist()]))
        if not held:
            continue
        best = net.decode(np.concatenate([x[0] for x in held], 1), np.concatenate([x[1] for x in held], 1))
        for r, (i, f, _, a, b) in enumerate(x for _, _, windows in held for x in windows):
            if i not in tags:
                tags[i] = np.zeros(len(coded[i]), np.int8)
            tags[i][a:b] = best[r, a - f : b - f]
    found: list[list[Span]] = [[] for _ in texts]
    for i, t in tags.items():
        at = np.flatnonzero(t)
        if not len(at):
            continue
        kind = (t[at] - 1) // 2
        new = np.ones(len(at), bool)
        new[1:] = (np.diff(at) > 1) | (kind[1:] != kind[:-1]) | (t[at[1:]] % 2 == 1)
        heads = np.flatnonzero(new)
        for h, e in zip(heads.tolist(), np.append(heads[1:], len(at)).tolist(), strict=True):
            found[i].append((KINDS[int(kind[h])], int(at[h]), int(at[e - 1]) + 1))
    return found


_AT = re.compile(r"\s*[\[(]\s*at\s*[\])]\s*|\s+at\s+|\s+@\s+", re.I)
_DOT = re.compile(r"\s*[\[(]\s*(?:dot|\.)\s*[\])]\s*|\s+dot\s+|\s+\.\s+", re.I)
_WORD = re.compile("|".join(_WORDS), re.I | re.A)
_NUMBER = re.compile(r"(?:\+|plus)?[0-9\s().,_/-]+", re.I)


def plainly(kind: str, written_: str) -> str | None:
    """The value in the base pattern's writing if it passes that pattern's check, else None."""
    if kind == "email":
        plain = _DOT.sub(".", _AT.sub("@", written_))
        return plain if _EMAIL.fullmatch(plain) else None
    if kind == "ip":
        plain = _DOT.sub(".", written_)
        parts = plain.split(".")
        return plain if len(parts) == 4 and all(x.isascii() and x.isdigit() and _small(x) for x in parts) else None
    spelled = _WORD.sub(lambda m: str(_WORDS.index(m[0].lower())), written_)
    if not _NUMBER.fullmatch(spelled):
        return None
    digits = re.sub("[^0-9]", "", spelled)
    if kind == "card":
        return digits if 12 <= len(digits) <= 19 and luhn(digits) else None
    return f"+{digits}" if 9 <= len(digits) <= 15 else None


_TOKEN = re.compile(r"[^\s]+")
_DIGITS = re.compile(f"[0-9]|(?=(?:{'|'.join(_WORDS)}))", re.I | re.A)
_CALL = re.compile(r"00|[+(]|plus |[0-9]{3}[./-][0-9]{3}[.-][0-9]{4}\Z", re.I)


def _barriers(kind: str, words: list[str]) -> list[int] | None:
    """For each word, how many before it end a value of this kind; None: no stretch of these words can pass the kind's check.

    In numbers these are words with letters that spell no digit, in addresses words that a space parts from the next one for good.
    """
    whole = " ".join(words)
    if kind == "email":
        if "@" not in whole and not _AT.search(f" {whole} "):
            return None
        link = [w.lower() in ("at", "dot", "@", ".") for w in words]
        stops = [not (p or q or w[-1] in "[(])" or v[0] in "[(])") for w, v, p, q in zip(words, words[1:], link, link[1:], strict=False)]
    else:
        if len(_DIGITS.findall(whole)) < (4 if kind == "ip" else 9):
            return None
        stops = [kind != "ip" and any(c.isalnum() and not "0" <= c <= "9" for c in re.sub("plus", "", _WORD.sub("0", w), flags=re.I)) for w in words]
    return [0, *accumulate(stops)]


def _snapped(text: str, kind: str, a: int, b: int) -> Span | None:
    """The longest stretch of whole words, up to REACH more or less at either border, that passes the kind's check.

    Punctuation at the borders is no part of it. A number that fails as a card or address but looks like one for calls may be a phone.
    """
    low = max(0, a - 200)
    words = [(m.start(), m.end()) for m in _TOKEN.finditer(text, low, min(len(text), b + 200))]
    if low and words and words[0][0] == low:
        words = words[1:]
    inside = [i for i, (x, y) in enumerate(words) if x < b and a < y]
    if not inside:
        return None
    first, last = inside[0], inside[-1]
    low, high = max(0, first - REACH), min(len(words) - 1, last + REACH)
    words = words[low : high + 1]
    first, last, more = first - low, last - low, int(kind != "email")
    ends = _barriers(kind, [text[x:y] for x, y in words])
    if ends is None:
        return None
    best: Span | None = None
    for i in range(min(first + REACH, last) + 1):
        if ends[max(i, last - REACH) + more] > ends[i]:
            continue
        x = words[i][0]
        while x < words[i][1] and not (text[x].isalnum() or text[x] in "+(" and text[x + 1 : x + 2].isdigit()):
            x += 1
        if x == words[i][1]:
            continue
        for j in range(len(words) - 1, max(i, last - REACH) - 1, -1):
            y = words[j][1]
            while y > words[j][0] and not text[y - 1].isalnum():
                y -= 1
            if y == words[j][0] or y <= x:
                continue
            if text[x] == "(" and text.count("(", x, y) > text.count(")", x, y):
                x += 1
            if best is not None and y - x <= best[2] - best[1]:
                break
            if ends[j + more] > ends[i]:
                continue
            value = text[x:y]
            fits = kind if plainly(kind, value) else "phone" if kind in ("card", "ip") and _CALL.match(value) and plainly("phone", value) else None
            if fits:
                best = (fits, x, y)
                break
    return best


def added_spans(text: str, base: list[Span], found: list[Span]) -> list[Span]:
    """Found spans, moved to the borders of words, that meet no base span nor each other and pass their kind's check."""
    out: list[Span] = []
    for kind, a, b in found:
        made = _snapped(text, kind, a, b)
        if made is not None and not any(made[1] < y and x < made[2] for _, x, y in base + out):
            out.append(made)
    return out


def all_spans(texts: list[str], net: Tagger | None, triggered: list[bool] | None = None) -> list[tuple[list[Span], list[Span]]]:
    """Base spans and all spans of each text; texts marked as not triggered hold no base span."""
    base = [base_spans(t) if triggered is None or triggered[i] else [] for i, t in enumerate(texts)]
    extra = model_spans(texts, net) if net is not None else [[] for _ in texts]
    return [(own, sorted(own + added_spans(t, own, more), key=lambda s: (s[1], KINDS.index(s[0]), s[2]))) for t, own, more in zip(texts, base, extra, strict=True)]


def _triggered(column: pa.Array) -> list[bool]:
    """Whether each text holds a digit or @."""
    data, starts, ends = texts_of(column)
    return (lexing.sums_by(_TRIGGER[data], starts, ends) > 0).tolist()


def find(docs: DataFrame, net: Tagger | None, text: str = "text") -> DataFrame:
    """doc_id, counts of base spans by kind, base_sha256, spans, n_spans and n_added of every document."""
    kind = docs.schema["doc_id"].dataType.simpleString()

    def run(batches):
        for batch in (part for whole in batches for part in slices(whole, 1, SLICE_BYTES)):
            column = batch.column(1)
            rows = all_spans([t or "" for t in column.to_pylist()], net, _triggered(column))
            counts = [pa.array([sum(k == name for k, _, _ in own) for own, _ in rows], pa.int64()) for name in KINDS]
            sums = pa.array([hashlib.sha256(written(own).encode()).hexdigest() for own, _ in rows], pa.string())
            every, added = (pa.array(x, pa.int64()) for x in ([len(e) for _, e in rows], [len(e) - len(own) for own, e in rows]))
            yield pa.RecordBatch.from_arrays([batch.column(0), *counts, sums, pa.array([written(e) for _, e in rows], pa.string()), every, added], names=["doc_id", *(f"n_{k}" for k in KINDS), "base_sha256", "spans", "n_spans", "n_added"])

    return docs.select("doc_id", F.col(text).cast("string").alias("text")).mapInArrow(run, f"doc_id {kind}, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string, n_spans long, n_added long")


def apply(docs: DataFrame) -> DataFrame:
    return find(docs, train(docs))


def masked(text: str, spans: list[Span]) -> str:
    """Text with every span replaced by its kind in brackets; overlapping spans make one, of the first kind."""
    out, at, reach = [], 0, 0
    for kind, a, b in spans:
        if a >= reach:
            out += [text[at:a], f"[{kind.upper()}]"]
        reach = max(reach, b)
        at = reach
    return "".join(out) + text[at:]


def redact(docs: DataFrame, labelled: DataFrame) -> DataFrame:
    """The same rows and columns, personal data in `text` masked and `n_chars` (if there) counted anew."""
    net = train(labelled)
    place, names = docs.columns.index("text"), docs.columns
    count = names.index("n_chars") if "n_chars" in names else None

    def run(batches):
        for batch in (part for whole in batches for part in slices(whole, place, SLICE_BYTES)):
            column = batch.column(place)
            texts = column.to_pylist()
            arrays = list(batch.columns)
            changed = [(r, every) for r, (_, every) in enumerate(all_spans([t or "" for t in texts], net, _triggered(column))) if every]
            if changed:
                chars = arrays[count].to_pylist() if count is not None else []
                for r, every in changed:
                    texts[r] = masked(texts[r], every)
                    if count is not None:
                        chars[r] = len(texts[r])
                arrays[place] = pa.array(texts, column.type)
                if count is not None:
                    arrays[count] = pa.array(chars, arrays[count].type)
            yield pa.RecordBatch.from_arrays(arrays, names=names)

    return docs.mapInArrow(run, docs.schema)
