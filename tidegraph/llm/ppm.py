"""Prediction by partial matching over bytes, with frozen statistics.

A model is a trie of byte contexts up to some order, made from counts of byte strings one longer
than the longest context. A symbol is coded in the longest known context; a context that lacks it
costs an escape (method D: each distinct symbol gives half a count to escapes), after which the symbols it holds
are excluded in the next shorter context. As seen symbols of a context are seen in its suffixes
too, every exclusion depends on one trie node only, so all of it can be worked out once, when the
counts are frozen. A document is framed by 0xFF, which UTF-8 never has: contexts before its start
and one closing symbol, which makes the code lengths those of a distribution over whole texts.
"""

from __future__ import annotations

import numpy as np

from tidegraph.llm.textblocks import Block

FRAME = 0xFF
_U = np.uint64


def _mask(n_bytes: int) -> np.uint64:
    return _U((1 << (8 * n_bytes)) - 1)


def framed_keys(block: Block, order: int, fold: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Keys of order + 1 bytes ending at each byte and at each closing frame, and offsets by document.

    The first order keys of a document's range but the first document's are of no document: a range
    is first[i] to first[i] + length + 1.
    """
    n, lengths = block.n, block.lengths
    lead = order + 1
    framed = np.full(len(block.data) + lead * n + order, FRAME, np.uint8)
    shift = np.repeat(np.arange(n, dtype=np.int64) * lead + order, lengths)
    shift += np.arange(len(block.data))
    framed[shift] = block.data if fold is None else fold[block.data]
    kind = np.uint32 if order < 4 else np.uint64
    key = framed[: len(framed) - order].astype(kind)
    for k in range(1, order + 1):
        key <<= kind(8)
        key |= framed[k : len(framed) - order + k]
    return key, block.offsets[:-1] + np.arange(n, dtype=np.int64) * lead


def own_keys(block: Block, order: int, fold: np.ndarray | None = None) -> np.ndarray:
    """All keys of the block's documents, those of no document left out."""
    keys, first = framed_keys(block, order, fold)
    use = np.ones(len(keys), bool)
    ends = first + block.lengths + 1
    for k in range(order):
        at = ends + k
        use[at[at < len(use)]] = False
    return keys[use]


def by_document(values: np.ndarray, first: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """Sum of values over each document's range."""
    cut = np.empty(2 * len(first), np.int64)
    cut[::2], cut[1::2] = first, first + lengths + 1
    padded = np.append(values, values.dtype.type(0))
    return np.add.reduceat(padded, cut, dtype=np.float64)[::2]


class KeyTable:
    """Distinct unsigned keys to their positions, in open addressing with at least `room` places a key."""

    def __init__(self, keys: np.ndarray, room: int = 4):
        self.n = len(keys)
        self.bits = max(10, int(self.n * room - 1).bit_length())
        self.kind = keys.dtype.type
        self.size = 8 * keys.dtype.itemsize
        self.scale = self.kind(0x9E3779B1 if self.size == 32 else 0x9E3779B97F4A7C15)
        self.keys = np.zeros(1 << self.bits, keys.dtype)
        self.slots = np.full(1 << self.bits, -1, np.int32)
        todo = np.arange(self.n)
        at = self._home(keys)
        while len(todo):
            free = self.slots[at] < 0
            self.slots[at[free]] = todo[free]  # of several, the last write stays
            self.keys[at[free]] = keys[todo[free]]
            lost = self.slots[at] != todo
            todo, at = todo[lost], (at[lost] + 1) & ((1 << self.bits) - 1)

    def _home(self, keys: np.ndarray) -> np.ndarray:
        return ((keys * self.scale) >> self.kind(self.size - self.bits)).astype(np.int64)

    def find(self, keys: np.ndarray) -> np.ndarray:
        """Positions, -1 for unknown keys."""
        at = self._home(keys)
        out = self.slots[at]
        left = np.flatnonzero((self.keys[at] != keys) & (out >= 0))
        at = at[left]
        while len(left):
            at = (at + 1) & ((1 << self.bits) - 1)
            got = self.slots[at]
            out[left] = np.where(self.keys[at] == keys[left], got, -1)
            on = (self.keys[at] != keys[left]) & (got >= 0)
            left, at = left[on], at[on]
        return out


def add_up(keys: np.ndarray, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct keys, ascending, and the sums of their counts."""
    order = np.argsort(keys, kind="stable")
    keys = keys[order]
    new = np.ones(len(keys), bool)
    new[1:] = keys[1:] != keys[:-1]
    at = np.flatnonzero(new)
    return keys[at], np.add.reduceat(counts[order], at) if len(at) else counts[:0]


def _find(table: np.ndarray, keys: np.ndarray) -> np.ndarray:
    if not len(table):
        return np.full(len(keys), -1)
    at = np.minimum(np.searchsorted(table, keys), len(table) - 1)
    return np.where(table[at] == keys, at, -1)


class FrozenTrie:
    """Code lengths in bits from counts of (context, symbol) keys of order + 1 bytes.

    below: (m, keys, counts) if keys are only those of some contexts of m bytes; all keys of m bytes with their
    counts, from which contexts shorter than m are made, so that keys of those contexts cost what they do in the whole.
    """

    def __init__(self, keys: np.ndarray, counts: np.ndarray, order: int, below: tuple[int, np.ndarray, np.ndarray] | None = None):
        self.order = order
        keys, counts = keys.astype(np.uint64), counts.astype(np.float64)
        self.symbol_key, self.symbol_count, self.node_key = [], [], []
        self.enter, self.escape, self.barred, self.barred_escape = [], [], [], []
        total, kinds = [], []
        for k in range(order, -1, -1):
            if below and k == below[0] - 1:
                keys, counts = below[1].astype(np.uint64), below[2].astype(np.float64)
            sk, sc = add_up(keys & _mask(k + 1), counts)
            keys, counts = sk, sc  # a shorter context's counts are sums of a longer one's
            nk, at = np.unique(sk >> _U(8), return_index=True)
            self.symbol_key.insert(0, sk)
            self.symbol_count.insert(0, sc)
            self.node_key.insert(0, nk)
            total.insert(0, np.add.reduceat(sc, at) if len(at) else sc)
            kinds.insert(0, np.diff(np.append(at, len(sk))).astype(np.float64))
        with np.errstate(divide="ignore", invalid="ignore"):
            for k in range(order + 1):
                n, q = total[k], kinds[k]
                self.enter.append(np.log2(2 * n))
                self.escape.append(np.log2(2 * n / q))
                if k:
                    above = _find(self.node_key[k - 1], self.node_key[k] & _mask(k - 1))
                    shorter = self.symbol_count[k - 1][_find(self.symbol_key[k - 1], self.symbol_key[k] & _mask(k))]
                    at = np.searchsorted(self.symbol_key[k] >> _U(8), self.node_key[k])
                    left = total[k - 1][above] - (np.add.reduceat(shorter, at) if len(at) else shorter)
                    kept = kinds[k - 1][above] - q
                    self.barred.append(np.log2(2 * left))
                    self.barred_escape.append(np.where(kept > 0, np.log2(2 * left / kept), 0.0))
                else:
                    self.barred.append(np.zeros(0))
                    self.barred_escape.append(np.zeros(0))
        self.last = np.log2(256.0 - (kinds[0][0] if len(kinds[0]) else 0.0)) if not len(kinds[0]) or kinds[0][0] < 256 else 0.0

    def bits(self, keys: np.ndarray) -> np.ndarray:
        """Code length of the last byte of each key after the others."""
        keys = keys.astype(np.uint64)
        out = np.zeros(len(keys))
        todo = np.arange(len(keys))
        before = np.full(len(keys), -1)  # the node one longer from which the symbol escaped, if any
        for k in range(self.order, -1, -1):
            here = keys[todo] & _mask(k + 1)
            node = _find(self.node_key[k], here >> _U(8))
            symbol = _find(self.symbol_key[k], here)
            fresh = (before < 0) & (node >= 0)
            came = before >= 0
            hit = symbol >= 0
            cost = np.zeros(len(todo))
            cost[fresh & hit] = self.enter[k][node[fresh & hit]]
            cost[fresh & ~hit] = self.escape[k][node[fresh & ~hit]]
            if k < self.order and came.any():
                cost[came & hit] = self.barred[k + 1][before[came & hit]]
                cost[came & ~hit] = self.barred_escape[k + 1][before[came & ~hit]]
            cost[hit] -= np.log2(2 * self.symbol_count[k][symbol[hit]] - 1)
            out[todo] += cost
            todo, before = todo[~hit], node[~hit]
        out[todo] += self.last
        return out


class AdaptiveTrie:
    """The same coder learning as it goes; plain Python, for single documents and for tests.

    update=False codes with what it has learnt so far.
    """

    def __init__(self, order: int):
        self.order = order
        self.nodes: dict[bytes, dict[int, int]] = {}

    def code(self, text: bytes, update: bool = True) -> float:
        framed = bytes([FRAME]) * self.order + text + bytes([FRAME])
        return sum(self._symbol(framed[i - self.order : i], framed[i], update) for i in range(self.order, len(framed)))

    def _symbol(self, context: bytes, symbol: int, update: bool) -> float:
        barred: set[int] = set()
        bits, done = 0.0, False
        for k in range(self.order, -1, -1):
            seen = self.nodes.get(context[self.order - k :])
            if done or not seen:
                continue
            open_ = {s: c for s, c in seen.items() if s not in barred}
            whole = 2 * sum(open_.values())
            if symbol in open_:
                bits += np.log2(whole / (2 * open_[symbol] - 1))
                done = True
            elif open_:
                bits += np.log2(whole / len(open_))
            barred |= set(seen)
        if not done:
            bits += np.log2(256 - len(barred))
        if update:
            for k in range(self.order + 1):
                node = self.nodes.setdefault(context[self.order - k :], {})
                node[symbol] = node.get(symbol, 0) + 1
        return bits
