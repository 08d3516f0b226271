"""Secret scans: fixed patterns, and a linear-chain conditional random field that adds spans.

The patterns give the base spans. The field tags every token of a text (a run of letters and digits, or
one other character) as begin, inside or outside of a secret, in one chain a text between two outside
tags. Decoding is exact: a token whose outside score is ahead by more than any pair scores around it can
give back is outside on the best path, and Viterbi runs over what lies between such tokens. Features are
shapes of the token and its neighbours, announcing words before and after it, and features of the whole
file. Weights come from maximum likelihood (forward and backward sums over padded batches) on windows of
tokens that the patterns label; the announcing words are hidden in half of the training windows, so the
field learns the shape of a secret as well as its announcement. Each labelled secret also stands in a
variant of its surroundings (`CUES`, `PREFIXES`) that no pattern finds; all other windows, with their dates,
numbers, addresses and names, are examples of what is no secret.

`TRAINING_ROWS` and `TRAINING_CHUNKS` bound the training sample: the distinct texts with the smallest
hashes among all documents, and the distinct windows with the smallest hashes in those; texts and windows
with secrets, and windows with digits, have better chances (`CHANCES`). Everything else covers every
character of every text.

Defined results: a null text is an empty one and has no spans; repeated rows are scanned each; spans
of the field that touch a base span are dropped, base spans never; with no window to learn from, the
field adds nothing. Columns other than the named ones are not read; `mask` replaces the text column
and keeps all others.
"""

from __future__ import annotations

import functools
import hashlib
import math
import random
import re
import string
import zlib
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from galoislake.llm.common import release, table, tidied

# The words that announce a secret, the kinds of spans and their least lengths.
KEYWORDS = ("password", "passwd", "secret", "token", "api_?key")
KINDS = ("assign", "access", "hex", "crf")
# How a secret may stand in a text where no pattern finds it; the field learns from such variants.
CUES = ("", "", "bearer ", "pwd=", "passphrase: ", "auth_key=", "credential ", "access key ", "private key: ", "login with ", "signature=", "the key is ", "use ", "pass ")
PREFIXES = ("", "", "", "ghp_", "sk-", "xoxb-", "AIza")
ALPHABETS = ("0123456789abcdef", string.ascii_lowercase + string.digits, string.ascii_letters + string.digits, string.ascii_letters)
VARIANTS = 8  # of each secret
TRAINING_ROWS, TRAINING_CHUNKS = 5_000, 20_000
WIDTH = 1 << 12
WINDOW = 16  # tokens of a training window
CHANCES = (1, 8, 64)  # of a window to be learned from: plain, with a digit, with a secret; the last one also of a text that may hold one
TOKENS = 1 << 15  # about as many are held at once; arrays of that size stay in the caches

_ANY_CASE = "|".join("".join(f"[{c.upper()}{c}]" if c.isalpha() else c for c in k) for k in KEYWORDS)
ASSIGN = re.compile(rf"""({_ANY_CASE})["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""")
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{32,}")  # a run of that length is a maximal run of the class
_HINTS = ("passw", "secret", "token", "api")
_PIECES = re.compile(r"\s*(?:[^\W_]+|[^\w\s]|_)")  # each token with the white space before it
_ANNOUNCING = re.compile("|".join(KEYWORDS)).search


def base_spans(text: str) -> list[tuple[int, int, str]]:
    """(start, end, kind) of the fixed patterns, by start, then kind as listed."""
    out = []
    low = text.lower()
    if any(h in low for h in _HINTS):
        out += [(m.start(), m.end(), "assign") for m in ASSIGN.finditer(text) if m.end(2) - m.start(2) >= 8]
    if "AKIA" in text:
        out += [(m.start(), m.end(), "access") for m in ACCESS.finditer(text) if m.end() - m.start() >= 16]
    out += [(m.start(), m.end(), "hex") for m in HEX.finditer(text)]
    return sorted(out, key=lambda s: (s[0], KINDS.index(s[2])))


def _shape(token: str) -> str:
    if not token[0].isalnum():
        return token if token.isascii() else "other"
    low = token.lower()
    digits = not token.isalpha() and any(c.isdigit() for c in token)
    upper = "B" if token[1:] != low[1:] else "A" if token[0] != low[0] else ""
    hexadecimal = "" if token.strip("0123456789abcdef") else "h"
    return f"{'d' if digits else ''}{'a' if token != token.upper() else ''}{upper}{'' if token.isascii() else 'u'}{min(9, len(token) // 4)}{hexadecimal}"


def _crc(x: str) -> int:
    return zlib.crc32(x.encode("utf-8", "surrogatepass"))


_LENGTH, _BLANKS, _SHAPE, _MIXED, _VARIETY, _OWN, _TOLD, _PART, _DIGIT = range(9)


_MIXTURES = re.compile(r"[0-9][A-Za-z]|[A-Za-z][0-9]").findall
_VARIETIES = [int(2 * math.log2(n + 1)) for n in range(256)]


_PARTS = {"api": 1, "_": 2, "key": 3}  # of an announcing word that is several tokens


@functools.cache
def _place(kind: str, value: object) -> int:
    return 1 + (_crc(f"{kind}={value}") >> 2)


_UNMIXED = _place("m", 0) % WIDTH
_HIDDEN = _crc("w=") % WIDTH


class _Tokens(dict):
    """Number of each distinct token, and what is known of it alone in `rows`. Number 0 is a text's border."""

    def __init__(self):
        super().__init__()
        self._made, self._count, self._fresh, self.chars = np.zeros((1 << 12, 9), dtype=np.int32), 0, [0] * 9, 0
        self._held, self._scores, self._scored = None, np.zeros((1 << 12, 3), dtype=np.float32), 0
        self[""] = 0

    def __missing__(self, token: str) -> int:
        k = self[token] = len(self)
        t = token.lstrip()
        low, letters, size = t.lower(), t.isalpha(), len(t)
        self.chars += len(token)
        if letters:
            mixed, digit = _UNMIXED, 0
            if low == t and t.isascii() and size > 8 and t.strip("abcdef"):  # most words: lower case, not hexadecimal
                self._fresh += (len(token), len(token) - size, _place("s", f"a{min(9, size // 4)}"), mixed, _place("v", _VARIETIES[min(len(set(t)), 255)]) % WIDTH, _HIDDEN, int(_ANNOUNCING(t) is not None), 0, 0)
                return k
        else:
            mixed, digit = _place("m", min(6, len(_MIXTURES(t))) if size > 1 else 0) % WIDTH, int(any(c.isdigit() for c in t))
        own = _crc("w=" + low) % WIDTH if letters and size < 9 else _HIDDEN
        told = int(size > 4 and _ANNOUNCING(low) is not None)
        self._fresh += (len(token), len(token) - size, _place("s", _shape(t)), mixed, _place("v", _VARIETIES[min(len(set(t)), 255)]) % WIDTH, own, told, _PARTS.get(low, 0), digit)
        return k

    @property
    def rows(self) -> np.ndarray:
        new, self._fresh = self._fresh, []
        before, self._count = self._count, self._count + len(new) // 9
        self._made = _roomy(self._made, self._count)
        self._made[before : self._count] = np.array(new, dtype=np.int32).reshape(-1, 9)
        return self._made[: self._count]

    def scores(self, field: Field) -> np.ndarray:
        """What each distinct token scores by itself; computed once a token and field."""
        rows = self.rows
        if self._held is not field:
            self._held, self._scored = field, 0
        if self._scored < len(rows):
            some = rows[self._scored :]
            self._scores = _roomy(self._scores, len(rows))
            self._scores[self._scored : len(rows)] = sum(field.light[f] for f in _own_features(some, some[:, _OWN]))
            self._scored = len(rows)
        return self._scores[: len(rows)]


def _roomy(x: np.ndarray, size: int) -> np.ndarray:
    """x, or a copy with room for more rows than `size`."""
    return x if size <= len(x) else np.concatenate([x, np.zeros((2 * size - len(x), x.shape[1]), dtype=x.dtype)])


_KNOWN = _Tokens()


def _forget_tokens() -> None:
    _KNOWN.clear()
    _KNOWN.__init__()


def _hashed(kind: int, a: np.ndarray, b: np.ndarray | int) -> np.ndarray:
    """Places of pairs of numbers among the weights."""
    x = a.astype(np.uint32) * np.uint32(0x9E3779B1) + np.asarray(b).astype(np.uint32) * np.uint32(0x85EBCA77) + np.uint32(kind * 0xC2B2AE3D & 0xFFFFFFFF)
    x = (x ^ (x >> np.uint32(15))) * np.uint32(0x2C1B3C6D)
    return (x >> np.uint32(20)).astype(np.int32)


def _own_features(k: np.ndarray, own: np.ndarray) -> list[np.ndarray]:
    """Hashed features of tokens by themselves. k: columns as in _Tokens."""
    return [_hashed(1, k[:, _SHAPE], 0), k[:, _MIXED], k[:, _VARIETY], own, _hashed(10, k[:, _MIXED], k[:, _SHAPE] * 64 + k[:, _VARIETY] % 64)]


_NEAR = np.array([0, 1, 2, 3, 3, 4, 4, 4, 4, 0])  # classes of distances to announcing words; 0 beyond


@dataclass
class _Chain:
    """Texts as one row of tokens with a border before and after each. Columns of `known` as in _Tokens."""

    known: np.ndarray
    numbers: np.ndarray  # of the tokens
    border: np.ndarray  # places of the borders
    files: np.ndarray  # a number for each text's features as a whole

    def starts(self) -> np.ndarray:
        """Of each token (without its white space) in its text."""
        ends = np.cumsum(self.known[:, _LENGTH], dtype=np.int64)
        base = np.repeat(ends[self.border], np.diff(np.append(self.border, len(ends))))
        return ends - self.known[:, _LENGTH] + self.known[:, _BLANKS] - base

    def features(self, hide: np.ndarray | bool = False) -> list[np.ndarray]:
        """Hashed features of every token, one array for each. hide: leave announcing words out."""
        own = np.where(hide, _HIDDEN, self.known[:, _OWN])
        return _own_features(self.known, own) + self.surroundings(own, hide)

    def surroundings(self, own: np.ndarray, hide: np.ndarray | bool = False) -> list[np.ndarray]:
        """The features that tokens have by their place."""
        k, n = self.known, len(self.known)
        at, shape, edge = np.arange(n), np.ascontiguousarray(k[:, _SHAPE]).view(np.uint32), np.zeros(n, dtype=bool)
        edge[self.border] = True
        gap = (k[:, _BLANKS] > 0) | edge
        one, two = np.roll(k[:, _PART], 1), np.roll(k[:, _PART], 2)
        told = (k[:, _TOLD] > 0) | (k[:, _PART] == 3) & ((one == 1) | (one == 2) & (two == 1))
        left = np.maximum.accumulate(np.where(told | edge, at, 0))
        left = np.concatenate([[0], left[:-1]])
        right = np.minimum.accumulate(np.where(told | edge, at, n - 1)[::-1])[::-1]
        right = np.concatenate([right[1:], [n - 1]])
        before = np.where(told[left], _NEAR[np.minimum(at - left, 9)], 0)
        after = np.where(told[right], _NEAR[np.minimum(right - at, 9)], 0)
        place = np.minimum(at - np.maximum.accumulate(np.where(gap, at, 0)), 4)
        file = np.repeat(self.files, np.diff(np.append(self.border, n)))
        before, after = np.where(hide, 0, before), np.where(hide, 0, after)
        second = np.where(np.roll(edge, 1), 0, np.roll(own, 2))  # of the same text
        return [
            _hashed(2, np.roll(shape, 1), shape * 2 + gap), _hashed(3, shape, np.roll(shape, -1) * 2 + np.roll(gap, -1)),
            _hashed(4, shape, before), _hashed(5, shape, after), _hashed(6, shape, file), _hashed(7, shape, place),
            _hashed(8, np.roll(own, 1), shape), _hashed(9, second, shape),
        ]


def _chains(texts: list[str]) -> Iterator[tuple[int, _Chain]]:
    """(place of its first text, chain) of groups of texts of bounded size."""
    first, numbers, border, files, size = 0, [], [], [], 0
    for i, text in enumerate(texts):
        if not numbers and (len(_KNOWN) > 300_000 or _KNOWN.chars > 1 << 23):
            _forget_tokens()  # numbers are used within a group only
        tokens = _PIECES.findall(text.rstrip())
        border.append(size)
        files.append(_crc(file_kind(text)))
        numbers.append(np.fromiter(map(_KNOWN.__getitem__, tokens), np.int64, len(tokens)))
        size += 1 + len(tokens)
        if size >= TOKENS or i + 1 == len(texts):
            flat = np.zeros(size + 1, dtype=np.int64)
            for b, x in zip(border, numbers, strict=True):
                flat[b + 1 : b + 1 + len(x)] = x
            yield first, _Chain(_KNOWN.rows[flat], flat, np.array([*border, size]), np.array([*files, 0]))
            first, numbers, border, files, size = i + 1, [], [], [], 0


def file_kind(text: str) -> str:
    low = text.lower()
    return f"{int(any(h in low for h in _HINTS))}{int('{' in text or ';' in text)}{min(4, len(text).bit_length() // 4)}"


def _lse(x: np.ndarray, axis: int) -> np.ndarray:
    top = x.max(axis=axis, keepdims=True)
    return (top + np.log(np.exp(x - top).sum(axis=axis, keepdims=True))).squeeze(axis)


_NEVER = -1e4  # an inside tag neither begins a chain nor follows an outside tag


@dataclass(frozen=True, eq=False)
class Field:
    """Weights of the chain: of features by tag (0 outside, 1 begin, 2 inside) and of tag pairs."""

    weights: np.ndarray
    pairs: np.ndarray

    @functools.cached_property
    def light(self) -> np.ndarray:
        return self.weights.astype(np.float32)

    def decode(self, rows: list[list[int]]) -> list[int]:
        unary = self.weights[np.array(rows)].sum(axis=1)
        best, back = unary[0] + np.array([0, 0, _NEVER]), []
        for u in unary[1:]:
            step = best[:, None] + self.pairs
            back.append(step.argmax(axis=0))
            best = step.max(axis=0) + u
        tags = [int(best.argmax())]
        for b in reversed(back):
            tags.append(int(b[tags[-1]]))
        return tags[::-1]

    def tags(self, chain: _Chain) -> np.ndarray:
        """The best tags of all tokens of a chain; borders are outside."""
        u = _KNOWN.scores(self)[chain.numbers]
        for f in chain.surroundings(chain.known[:, _OWN]):
            u += self.light[f]
        u, p = u.astype(np.float64), self.pairs
        u[chain.border] = [0, 2 * _NEVER, 2 * _NEVER]
        # What the pair scores may lose when a token turns to outside, and an inside one after it to begin.
        before = max(0, (p[:, 1:] - p[:, :1]).max())
        after = max(0, (p[1:, :2] - p[:1, :2]).max(), p[1:, 2].max() - p[0, 1] + max(0, (p[2] - p[1]).max()))
        turned = np.append(np.maximum(u[1:, 2] - u[1:, 1], 0), 0)
        sure = u[:, 0] - u[:, 1:].max(axis=1) > before + after + turned
        sure[chain.border] = True
        out = np.zeros(len(u), dtype=np.int64)
        edges = np.flatnonzero(np.diff(sure.astype(np.int8)))
        if not len(edges):
            return out
        # All stretches between sure tokens at once, the longest ones first, a token of each in a step.
        low, size = edges[::2] + 1, edges[1::2] - edges[::2]
        order = np.argsort(-size, kind="stable")
        low, size = low[order], size[order]
        live = np.searchsorted(-size, -np.arange(size[0]), side="left")  # stretches that are longer than each step
        best, back = np.tile([0.0, 2 * _NEVER, 2 * _NEVER], (len(low), 1)), np.zeros((len(u), 3), dtype=np.int8)
        for t, m in enumerate(live.tolist()):
            step = best[:m, :, None] + p
            back[low[:m] + t] = step.argmax(axis=1)
            best[:m] = step.max(axis=1) + u[low[:m] + t]
        tag = (best + p[:, 0]).argmax(axis=1)
        for t in range(len(live) - 1, -1, -1):
            at = low[: live[t]] + t
            out[at] = tag[: live[t]]
            tag[: live[t]] = back[at, tag[: live[t]]]
        return out


def train(samples: list[tuple[np.ndarray, np.ndarray]], weights: list[float] | None = None, epochs: int = 8, rate: float = 0.3, decay: float = 1e-4) -> Field | None:
    """Maximum likelihood by AdaGrad over padded batches."""
    if not samples:
        return None
    base = np.zeros((3, 3))
    base[0, 2] = _NEVER
    w, pairs = np.zeros((WIDTH, 3)), np.zeros((3, 3))
    gw, gp = np.full_like(w, 1e-6), np.full_like(pairs, 1e-6)
    weights = weights or [1.0] * len(samples)
    samples = sorted(((*s, m) for s, m in zip(samples, weights, strict=True)), key=lambda s: len(s[1]))
    batches = [samples[i : i + 256] for i in range(0, len(samples), 256)]
    order = np.random.default_rng(7)
    for _ in range(epochs):
        for k in order.permutation(len(batches)):
            batch = batches[k]
            n, t, f = len(batch), max(len(y) for _, y, _ in batch), len(batch[0][0][0])
            x = np.zeros((n, t, f), dtype=np.int64)
            y = np.zeros((n, t), dtype=np.int64)
            live = np.zeros((n, t), dtype=bool)
            for i, (rows, tags, _) in enumerate(batch):
                x[i, : len(rows)], y[i, : len(tags)], live[i, : len(tags)] = rows, tags, True
            mass = np.array([m for _, _, m in batch])
            unary, trans = w[x].sum(axis=2), pairs + base
            alpha, beta = np.zeros((t, n, 3)), np.zeros((t, n, 3))
            alpha[0] = unary[:, 0] + np.array([0, 0, _NEVER])
            for j in range(1, t):
                nxt = _lse(alpha[j - 1][:, :, None] + trans, 1) + unary[:, j]
                alpha[j] = np.where(live[:, j, None], nxt, alpha[j - 1])
            for j in range(t - 2, -1, -1):
                prv = _lse(trans + (unary[:, j + 1] + beta[j + 1])[:, None, :], 2)
                beta[j] = np.where(live[:, j + 1, None], prv, 0)
            z = _lse(alpha[-1], 1)
            p = np.exp(alpha + beta - z[None, :, None]).transpose(1, 0, 2) * live[:, :, None]
            g = -p
            g[np.arange(n)[:, None], np.arange(t)[None], y] += live
            g *= mass[:, None, None]
            dw = np.zeros_like(w)
            np.add.at(dw, x[live], g[live][:, None, :])
            dp = np.zeros_like(pairs)
            for j in range(1, t):
                on = live[:, j]
                both = alpha[j - 1][:, :, None] + trans + (unary[:, j] + beta[j])[:, None, :] - z[:, None, None]
                dp -= (np.exp(both[on]) * mass[on, None, None]).sum(axis=0)
                np.add.at(dp, (y[on, j - 1], y[on, j]), mass[on])
            dw, dp = dw / mass.sum() - decay * w, dp / mass.sum() - decay * pairs
            gw += dw**2
            gp += dp**2
            w += rate * dw / np.sqrt(gw)
            pairs += rate * dp / np.sqrt(gp)
    return Field(w, pairs + base)


def secret_parts(text: str) -> list[tuple[int, int]]:
    """What of the base spans is the secret itself; these label the training chunks."""
    out = []
    if any(h in text.lower() for h in _HINTS):
        out += [m.span(2) for m in ASSIGN.finditer(text) if m.end(2) - m.start(2) >= 8]
    return out + [(a, b) for a, b, kind in base_spans(text) if kind != "assign"]


def variants(text: str, each: int = VARIANTS) -> list[tuple[str, list[tuple[int, int]]]]:
    """(text, secret parts): for every secret of the text, others of its kind in its place, announced
    otherwise or not at all. Drawn from the secret's own hash, so that repeated texts give equal variants."""
    out = []
    spans = base_spans(text)
    for s, e in secret_parts(text):
        low, high = min((a for a, b, _ in spans if a <= s < b), default=s), max((b for a, b, _ in spans if a <= s < b), default=e)
        draw = random.Random(_crc(text[s:e]))
        for _ in range(each):
            letters = draw.choice(ALPHABETS)
            body = draw.choice(PREFIXES) + "".join(draw.choice(letters) for _ in range(draw.randint(16, 40)))
            before, after = text[max(0, low - 60) : low] + draw.choice(CUES), draw.choice(("", "", "", ".", ";", "@")) + text[high : high + 60]
            out.append((before + body + after, [(len(before), len(before) + len(body))]))
    return out


def _windows(texts: list[str]) -> Iterator[tuple[int, bytes, bytes]]:
    """(rank, features, tags) of the training windows of the texts and of their secrets' variants."""
    parts = [secret_parts(t) for t in texts]
    more = [v for t, p in zip(texts, parts, strict=True) if p for v in variants(t)]
    texts, parts = texts + [t for t, _ in more], parts + [p for _, p in more]
    for first, chain in _chains(texts):
        n = len(chain.known)
        start = chain.starts()
        tags, rank, hide = np.zeros(n, dtype=np.int64), {}, np.zeros(n, dtype=bool)
        for i, b in enumerate(chain.border[:-1]):
            text, last = texts[first + i], chain.border[i + 1]
            for s, e in parts[first + i]:
                low, high = b + 1 + np.searchsorted(start[b + 1 : last], [s, e])
                tags[low:high] = 2
                tags[low : min(low + 1, high)] = 1
            for low in range(b + 1, last, WINDOW):
                high = min(low + WINDOW, last)
                own = _crc(text[max(0, start[low] - 40) : start[high - 1] + chain.known[high - 1, _LENGTH]])
                chance = CHANCES[2 if tags[low:high].any() else int(chain.known[low:high, _DIGIT].any())]
                rank[low, high] = own * (CHANCES[-1] // chance)
                hide[low:high] = own & 1
        x = np.stack(chain.features(hide), axis=1).astype("<u2")
        for (low, high), r in rank.items():
            y = tags[low:high].astype("u1")
            y[0] = min(y[0], 1)  # a secret that began before the window
            yield r, x[low:high].tobytes(), y.tobytes()


def _rank(text: str) -> int:
    """Of a text, as one to learn from."""
    low = text.lower()
    likely = any(h in low for h in _HINTS) or "AKIA" in text or HEX.search(text)
    return _crc(text) * (1 if likely else CHANCES[-1] // CHANCES[0])


def fit(docs: DataFrame, most: int = TRAINING_CHUNKS, rows: int = TRAINING_ROWS, *, text: str = "text") -> Field | None:
    """Train on at most `most` distinct windows, those with the smallest ranks in the `rows` distinct texts
    with the smallest ranks.

    A window that stands n times weighs 1 + log2(n): more than one does, but never the whole sample."""

    def samples(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[tuple[int, bytes, bytes], int] = {}
        top = math.inf  # no window of a higher rank is among the distinct ones of this partition
        for b in batches:
            for w in _windows([t for t in b.column(0).to_pylist() if t and _rank(t) <= least]):
                if w[0] <= top:
                    held[w] = held.get(w, 0) + 1
            if len(held) > 2 * most:
                held = {w: held[w] for w in sorted(held)[:most]}
                top = max((w[0] for w in held), default=-1)
        _forget_tokens()
        kept = sorted(held)[:most]
        yield pa.RecordBatch.from_arrays([pa.array([w[0] for w in kept], pa.int64()), pa.array([w[1] for w in kept], pa.binary()), pa.array([w[2] for w in kept], pa.binary()), pa.array([held[w] for w in kept], pa.int64())], names=["rank", "x", "y", "n"])

    def ranked(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            yield pa.RecordBatch.from_arrays([pa.array([_rank(t) for t in b.column(0).to_pylist() if t], pa.int64())], names=["rank"])

    texts = docs.select(F.col(text))
    least = texts.mapInArrow(tidied(ranked), "rank long").distinct().orderBy("rank").limit(rows).agg(F.max("rank")).first()[0]
    if least is None:
        return None
    found = texts.mapInArrow(tidied(samples), "rank long, x binary, y binary, n long")
    some = found.groupBy("rank", "x", "y").agg(F.sum("n").alias("n")).orderBy("rank", "x", "y").limit(most).select("x", "y", "n").toArrow().to_pydict()
    return train([(np.frombuffer(x, "<u2").reshape(len(y), -1), np.frombuffer(y, "u1")) for x, y in zip(some["x"], some["y"], strict=True)], [1 + math.log2(n) for n in some["n"]])


def scans(texts: list[str | None], field: Field | None) -> list[list[tuple[int, int, str]]]:
    """All spans of each text: those of the patterns and those the field adds."""
    every = [base_spans(t or "") for t in texts]
    if field:
        for first, chain in _chains([t or "" for t in texts]):
            tags = field.tags(chain)
            begins = np.flatnonzero(tags == 1)
            if not len(begins):
                continue
            start = chain.starts()
            others = np.flatnonzero(tags != 2)
            last = others[np.searchsorted(others, begins, side="right")] - 1  # a border comes after each text
            ends = start[last] + chain.known[last, _LENGTH] - chain.known[last, _BLANKS]
            added: dict[int, list[tuple[int, int]]] = {}
            for i, s, e in zip((np.searchsorted(chain.border, begins) - 1).tolist(), start[begins].tolist(), ends.tolist(), strict=True):
                added.setdefault(first + i, []).append((s, e))
            for i, found in added.items():
                base = [(s, e) for s, e, _ in every[i]]
                every[i] += [(s, e, "crf") for s, e in found if not any(s < q and p < e for p, q in base)]
                every[i].sort(key=lambda s: (s[0], KINDS.index(s[2])))
    return every


def scan(text: str | None, field: Field | None) -> list[tuple[int, int, str]]:
    """All spans of a text."""
    return scans([text], field)[0]


def _joined(spans: list[tuple[int, int, str]]) -> str:
    return ",".join(f"{k}:{s}:{e}" for s, e, k in spans)


def find(docs: DataFrame, field: Field | None, *, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """Per document: counts of base spans by kind, a digest of them, and all spans."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            every = scans(b.column(1).to_pylist(), field)
            base = [[s for s in spans if s[2] != "crf"] for spans in every]
            count = lambda kind: pa.array([sum(s[2] == kind for s in spans) for spans in base], pa.int64())  # noqa: E731, B023
            yield pa.RecordBatch.from_arrays(
                [b.column(0), count("assign"), count("access"), count("hex"), pa.array([hashlib.sha256(_joined(s).encode()).hexdigest() for s in base], pa.string()), pa.array([_joined(s) for s in every], pa.string())],
                names=[doc_id, "n_assign", "n_access", "n_hex", "base_sha256", "spans"],
            )

    kind = docs.schema[doc_id].dataType.simpleString()
    return docs.select(doc_id, text).mapInArrow(run, f"`{doc_id}` {kind}, n_assign long, n_access long, n_hex long, base_sha256 string, spans string")


def masker(field: Field | None, mark: str = "[secret]") -> Callable[[Iterator[pa.Array]], Iterator[pa.Array]]:
    """Texts with every span replaced by the mark; a worker keeps no tokens after them."""

    def run(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for b in batches:
            texts = b.to_pylist()
            yield pa.array([t if t is None else _masked(t, spans, mark) for t, spans in zip(texts, scans(texts, field), strict=True)], pa.string())
            release()
        _forget_tokens()  # workers live on, and the stages after this one need the memory

    return tidied(run)


def mask(docs: DataFrame, field: Field | None, mark: str = "[secret]", *, text: str = "text") -> DataFrame:
    """docs with every span of its texts replaced by the mark; null texts stay null."""
    return docs.withColumn(text, F.arrow_udf(masker(field, mark), "string")(F.col(text)))


def _masked(text: str, spans: list[tuple[int, int, str]], mark: str) -> str:
    out, at = [], 0
    for s, e, _ in spans:
        if s >= at:
            out += [text[at:s], mark]
        at = max(at, e)
    return "".join(out) + text[at:] if spans else text


def op5_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return find(docs, fit(docs))
