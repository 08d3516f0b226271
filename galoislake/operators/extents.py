"""Closures of many attribute sets over rows in memory, from the rows that their parents already have.

Sets grow by one attribute at a time. The extents of a batch of sets lie behind one another in one array of
row numbers; one pass deals them out over the attributes asked for, which gives the extents, closures and
supports of all grown sets of the batch at once. Batches are bounded, and deeper ones come first, so memory
holds a few batches for each level and never the extents of a whole level.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np

from galoislake.functions import bits

_KEYS = 1 << 16  # sets times attributes of a batch: keys of 16 bits are sorted by their digits
_CELLS = 1 << 23  # rows times attributes of a batch


def spread(words: np.ndarray, m: int) -> np.ndarray:
    """Packed sets as a matrix of m flags."""
    n, width = words.shape
    flags = np.unpackbits(np.ascontiguousarray(words, dtype=">i8").view(np.uint8).reshape(n, 8 * width), axis=1)
    return flags.reshape(n, width, bits.WORD + 1)[:, :, 1:].reshape(n, width * bits.WORD)[:, :m].astype(bool)


def masks(m: int) -> tuple[np.ndarray, np.ndarray]:
    """For each rank, the words of that attribute alone, and of all ranks before it."""
    own = np.array([bits.pack([r], bits.width(m)) for r in range(m)], dtype=np.int64).reshape(m, bits.width(m))
    before = np.array([bits.pack(range(r), bits.width(m)) for r in range(m)], dtype=np.int64).reshape(m, bits.width(m))
    return own, before


@dataclass
class Batch:
    """sets: packed; extents: row numbers, those of one set behind those of the one before; lengths: how
    many each set has; more: one array for each further column."""

    sets: np.ndarray
    extents: np.ndarray
    lengths: np.ndarray
    more: dict[str, np.ndarray]

    def cut(self, low: int, high: int) -> Batch:
        at = np.concatenate([[0], np.cumsum(self.lengths)])
        return Batch(self.sets[low:high], self.extents[at[low] : at[high]], self.lengths[low:high], {k: v[low:high] for k, v in self.more.items()})

    def bounded(self, m: int) -> tuple[Batch, Batch | None]:
        """The first sets that are handled at once, and the rest."""
        sized = int(np.searchsorted(np.cumsum(self.lengths), _CELLS // max(1, m), "right"))
        high = max(1, min(_KEYS // max(1, m), sized))
        return (self, None) if high >= len(self.sets) else (self.cut(0, high), self.cut(high, len(self.sets)))


class Rows:
    """Distinct packed rows with weights."""

    def __init__(self, words: np.ndarray, weights: np.ndarray, m: int):
        self.words, self.weights, self.m, self.n = np.ascontiguousarray(words), np.asarray(weights, dtype=np.int64), m, len(words)
        self.full = np.array(bits.full_words(m), dtype=np.int64)
        self.has = spread(self.words, m)
        self.own, self.before = masks(m)

    def closed(self, extent: np.ndarray) -> np.ndarray:
        """What all rows of an extent share; all attributes for none."""
        return np.bitwise_and.reduce(self.words[extent], axis=0) if len(extent) else self.full.copy()

    def top(self) -> np.ndarray:
        return np.arange(self.n, dtype=np.int32)

    def grown(self, b: Batch, asked: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Every set of the batch with each attribute asked of it that some of its rows have: the set's
        number, the attribute, closure and support, and the extents with their lengths."""
        owner = np.repeat(np.arange(len(b.sets)), b.lengths)
        pair, p = np.nonzero(self.has[b.extents] & asked[owner])
        key = owner[pair] * self.m + p
        order = np.argsort(key.astype(np.uint16) if len(b.sets) * self.m <= _KEYS else key, kind="stable")
        key, extents = key[order], b.extents[pair[order]]
        starts = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]])) if len(key) else np.zeros(0, np.int64)
        if not len(starts):
            none = np.zeros(0, np.int64)
            return none, none, np.zeros((0, len(self.full)), np.int64), none, extents, none
        closure = np.stack([np.bitwise_and.reduceat(self.words[extents, k], starts) for k in range(len(self.full))], axis=1)
        support = np.add.reduceat(self.weights[extents], starts)
        at = key[starts]
        return at // self.m, at % self.m, closure, support, extents, np.diff(np.append(starts, len(key)))

    def close(self, seeds: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(closure, support) of each seed: seeds that begin alike share the extents of what they share."""
        width, m = seeds.shape[1], self.m
        order = np.lexsort([-seeds[:, k] for k in reversed(range(width))])  # by ranks: a set that goes on comes before the one that ends
        u = seeds[order]
        fresh = np.ones(len(u), dtype=bool)
        fresh[1:] = (u[1:] != u[:-1]).any(axis=1)
        u, place = u[fresh], np.cumsum(fresh) - 1
        out, support = np.tile(self.full, (len(u), 1)), np.zeros(len(u), dtype=np.int64)
        wants = spread(u, m)
        sizes = wants.sum(axis=1)
        if len(u) and not sizes[-1]:
            out[-1], support[-1] = self.closed(self.top()), self.weights.sum()
        ranks = np.full((len(u), int(sizes.max(initial=0)) + 1), m, dtype=np.int32)  # the ranks of each seed, ended by m
        at, p = np.nonzero(wants)
        ranks[at, np.arange(len(at)) - np.repeat(np.cumsum(sizes) - sizes, sizes)] = p
        stack = []
        some = int((sizes > 0).sum())
        if some and self.n:
            stack.append((0, Batch(np.zeros((1, width), np.int64), self.top(), np.array([self.n]), {"low": np.array([0]), "high": np.array([some])})))
        while stack:
            depth, b = stack.pop()
            b, rest = b.bounded(m)
            if rest is not None:
                stack.append((depth, rest))
            low, held = b.more["low"], b.more["high"] - b.more["low"]
            owner = np.repeat(np.arange(len(low)), held)
            seed = np.arange(held.sum()) + np.repeat(low - (np.cumsum(held) - held), held)
            keys = owner * m + ranks[seed, depth]
            asked = np.zeros((len(low), m), dtype=bool)
            asked.reshape(-1)[keys] = True
            node, p, closure, count, extents, lengths = self.grown(b, asked)
            if not len(node):
                continue
            # Seeds of one grown set are neighbours; the one that ends there is the last of them.
            mine = node * m + p
            first, last = seed[np.searchsorted(keys, mine, "left")], seed[np.searchsorted(keys, mine, "right") - 1]
            ends = ranks[last, depth + 1] == m
            out[last[ends]], support[last[ends]] = closure[ends], count[ends]
            deeper = ranks[first, depth + 1] < m
            if deeper.any():
                stack.append((depth + 1, Batch(closure[deeper], extents[np.repeat(deeper, lengths)], lengths[deeper], {"low": first[deeper], "high": (last + 1 - ends)[deeper]})))
        back = np.empty(len(order), dtype=np.int64)
        back[order] = place
        return out[back], support[back]

    def children(self, b: Batch) -> Batch:
        """The intents one attribute below those of the batch (more: last, the attribute added last), each
        generated once: an attribute beyond the last one is added and closed, and the closure is kept if
        it adds nothing before that attribute. more: parent, last, support."""
        m, last = self.m, b.more["last"]
        has = spread(b.sets, m)
        node, p, closure, count, extents, lengths = self.grown(b, ~has & (np.arange(m) > last[:, None]))
        kept = ((closure & ~b.sets[node] & self.before[p]) == 0).all(axis=1)
        out = Batch(closure[kept], extents[np.repeat(kept, lengths)], lengths[kept], {"parent": node[kept], "last": p[kept], "support": count[kept]})
        # An attribute that no row of the extent has closes to all attributes, which may add none before it.
        first = np.where(has.all(axis=1), m, has.argmin(axis=1)) if m else np.zeros(len(has), np.int64)
        met = np.zeros((len(has), m + 1), dtype=bool)
        met[node, p] = True
        bare = np.flatnonzero((first < m) & (first > last) & ~met[np.arange(len(has)), first])
        if len(bare):
            none = np.zeros(len(bare), np.int64)
            out = Batch(np.concatenate([out.sets, np.tile(self.full, (len(bare), 1))]), out.extents, np.concatenate([out.lengths, none]), {"parent": np.concatenate([out.more["parent"], bare]), "last": np.concatenate([out.more["last"], first[bare]]), "support": np.concatenate([out.more["support"], none])})
        return out

    def first(self) -> Batch:
        """The closure of the empty set."""
        return Batch(self.closed(self.top())[None, :], self.top(), np.array([self.n]), {"last": np.array([-1]), "support": np.array([self.weights.sum()]), "level": np.array([0])})

    def walk(self) -> Iterator[Batch]:
        """All intents in batches, with level, last and support."""
        stack = [self.first()]
        yield stack[0]
        while stack:
            b, rest = stack.pop().bounded(self.m)
            if rest is not None:
                stack.append(rest)
            below = self.children(b)
            if len(below.sets):
                below.more["level"] = b.more["level"][below.more["parent"]] + 1
                stack.append(below)
                yield below

    def lectic(self) -> Iterator[tuple[np.ndarray, int]]:
        """(intent, support) in lectic order: of what lies below an intent, that of the largest added
        attribute comes first, as it keeps the longest part of the intent unchanged."""
        stack = [self.first()]
        while stack:
            b = stack.pop()
            yield b.sets[0], int(b.more["support"][0])
            below = self.children(b)
            for k in np.argsort(below.more["last"], kind="stable"):
                stack.append(below.cut(int(k), int(k) + 1))
