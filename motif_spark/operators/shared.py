"""Graphs with the same neighbour lists share their connected sets.

These are grown once, and the shape of each (its canonical form without labels) and the shape's automorphisms are found
once. A graph then only reads its labels off: the least word over a set's readings names its class, the readings
that reach it are the class's mappings, and the nodes that these put at a place are the place's image.
"""

from __future__ import annotations

from collections import OrderedDict
from functools import lru_cache

import numpy as np

from . import vector as V
from .canonical import canonical_of, parse_code
from .match import automorphisms_of

#: Sets of one structure, readings of one size, and automorphisms of one shape, above which nothing is shared.
SETS, READINGS, TURNS = 300_000, 600_000, 48
#: Bytes of plans, structures that were met and codes that a worker remembers.
BYTES, MET, TEXTS = 100_000_000, 20_000, 300_000


@lru_cache(maxsize=20_000)
def _shape(k: int, bits: int) -> tuple[int, int, tuple[int, ...]]:
    """Canonical bits of a set without its labels, automorphisms, and the node at each place."""
    code, turns, order, _ = canonical_of((0,) * k, bits)
    return parse_code(code)[1], turns, order


class Plan:
    """The connected sets of one size in a structure (in the order of their sorted nodes) and all their readings."""

    def __init__(self, near: np.ndarray, members: np.ndarray):
        s = np.sort(members, 1)
        s = s[np.lexsort(s.T[::-1])]
        self.sets, self.size, self.nodes = s, s.shape[1], len(near)
        kinds, which = np.unique(V.triangle(near[s[:, :, None], s[:, None, :]]), return_inverse=True)
        found = [_shape(self.size, b) for b in kinds.tolist()]
        turns = np.array([t for _, t, _ in found])
        if turns.max() > TURNS or turns[which].sum() > READINGS:
            raise V.SearchSpaceTooLarge("too many readings to be shared")
        self.forms, at = np.unique([f for f, _, _ in found], return_inverse=True)
        self.shape = at[which]
        self.count = turns[which]
        self.start = np.cumsum(self.count) - self.count
        self.of = np.repeat(np.arange(len(s)), self.count)
        spots = np.empty((len(self.of), self.size), np.uint8)
        for kind, (form, n, order) in enumerate(found):
            own = np.flatnonzero(which == kind)
            places = np.array(order)[np.array(automorphisms_of(self.size, form))]
            spots[self.start[own][:, None] + np.arange(n)] = s[own][:, places]
        self.spots = np.ascontiguousarray(spots.T)
        self.pairs = [a * np.uint16(self.nodes) + b for a, b in zip(self.spots[:-1:2].astype(np.uint16), self.spots[1::2])]
        self.masks = (np.int64(1) << s.astype(np.int64)).sum(1)
        self.by_mask = np.argsort(self.masks)
        self.bytes = 2 * spots.nbytes + s.nbytes + 5 * self.of.nbytes


class Level:
    """Classes of one size in a graph, as mni.Level has them: freq, support, of (the class of each set), texts, and first,
    the least set of each class."""

    def __init__(self, plan: Plan, labels: np.ndarray):
        self.plan, self.size, k = plan, plan.size, plan.size
        self.width = max(1, int(labels.max()).bit_length())
        two = (labels[:, None] << self.width | labels).ravel()
        word = np.zeros(len(plan.of), np.int64)
        for pair in plan.pairs:
            word <<= 2 * self.width
            word |= two[pair]
        if k % 2:
            word = word << self.width | labels[plan.spots[-1]]
        self.word, self.least = word, np.minimum.reduceat(word, plan.start)
        index = len(plan.sets).bit_length()
        packed = np.sort((plan.shape << self.width * k | self.least) << index | np.arange(len(plan.sets)))
        key, at = packed >> index, packed & (1 << index) - 1
        new = np.diff(key, prepend=-1) != 0
        begin = np.flatnonzero(new)
        self.first, self.keys = at[begin], key[begin]
        self.freq = np.diff(begin, append=len(key))
        self.of = np.empty(len(at), np.int64)
        self.of[at] = np.cumsum(new) - 1

    @property
    def sample(self) -> np.ndarray:
        return self.plan.sets[self.first]

    def automorphisms(self, rows: np.ndarray | slice = slice(None)) -> np.ndarray:
        """Automorphisms of classes: how many readings of a set reach its word."""
        at = self.first[rows]
        count, least = self.plan.count[at], self.least[at]
        start = np.cumsum(count) - count
        spots = np.arange(count.sum()) + np.repeat(self.plan.start[at] - start, count)
        return np.add.reduceat(self.word[spots] == np.repeat(least, count), start, dtype=np.int64)

    @property
    def support(self) -> np.ndarray:
        """Least image of a class's places: the distinct nodes that its mappings put there."""
        plan = self.plan
        hit = np.flatnonzero(self.word == np.repeat(self.least, plan.count))
        own = self.of[plan.of[hit]]
        order = np.argsort(own.astype(np.uint16) if len(self.first) < 1 << 16 else own, kind="stable")
        hit, own = hit[order], own[order]
        begin = np.flatnonzero(np.diff(own, prepend=-1))
        bit = np.uint64(1) << np.arange(plan.nodes, dtype=np.uint64)
        images = [np.bitwise_count(np.bitwise_or.reduceat(bit[spots[hit]], begin)) for spots in plan.spots]
        return np.minimum.reduce(images).astype(np.int64)

    def raw(self, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Labels and bits of classes, not in the order of their codes."""
        forms, words = self.words()
        return spelled(self.size, self.width, words[rows]), forms[rows]

    def words(self) -> tuple[np.ndarray, np.ndarray]:
        """Form and least word of every class, which texts_of() needs to name it."""
        return self.plan.forms[self.keys >> self.width * self.size], self.keys & (1 << self.width * self.size) - 1

    def texts(self, rows: np.ndarray) -> list[str]:
        forms, words = self.words()
        return texts_of(self.size, self.width, forms[rows], words[rows])

    def rows(self, graph: int, kept: np.ndarray) -> list[tuple]:
        """Rows as mni.CENSUS has them."""
        return [(graph, self.size, c, f, m) for c, f, m in zip(self.texts(kept), self.freq[kept].tolist(), self.support[kept].tolist())]

    def find(self, code: str) -> int | None:
        """The class of a code, if the graph has it."""
        labels, bits = parse_code(code)
        form, turns, order = _shape(self.size, bits)
        shape = int(np.searchsorted(self.plan.forms, form))
        if max(labels) >> self.width or shape == len(self.plan.forms) or self.plan.forms[shape] != form:
            return None
        words = []
        for turn in automorphisms_of(self.size, form):
            word = 0
            for p in turn:
                word = word << self.width | labels[order[p]]
            words.append(word)
        key = shape << self.width * self.size | min(words)
        at = int(np.searchsorted(self.keys, key))
        return at if at < len(self.keys) and self.keys[at] == key else None

    def class_of(self, members: np.ndarray) -> np.ndarray:
        """Classes of connected sets that are given by their nodes, a row each."""
        plan = self.plan
        masks = (np.int64(1) << members.astype(np.int64)).sum(1)
        return self.of[plan.by_mask[np.searchsorted(plan.masks, masks, sorter=plan.by_mask)]]


def spelled(size: int, width: int, words: np.ndarray) -> np.ndarray:
    """The labels of words."""
    return np.stack([words >> width * j & (1 << width) - 1 for j in range(size - 1, -1, -1)], 1)


def texts_of(size: int, width: int, forms: np.ndarray, words: np.ndarray) -> list[str]:
    """Codes of classes, each made once while there is room to remember it."""
    names = list(zip([size * 64 + width] * len(words), forms.tolist(), words.tolist()))
    out = [_texts.get(x) for x in names]
    missing = [i for i, x in enumerate(out) if x is None]
    if missing:
        kinds = V.Classes(spelled(size, width, words[missing]), forms[missing])
        for i, text in zip(missing, kinds.texts(np.arange(len(missing)))):
            out[i] = text
            if len(_texts) < TEXTS:
                _texts[names[i]] = text
    return out


def least_codes(parts: list[tuple[np.ndarray, np.ndarray]]) -> tuple[list[str], np.ndarray]:
    """The least code of each part, a part being labels and bits of classes of one size, and its row in the part."""
    labels, bits = (np.concatenate([p[i] for p in parts]) for i in (0, 1))
    first, which = V.alike(labels, bits)
    texts = np.array(V.Classes(labels[first], bits[first]).texts(np.arange(len(first))), object)
    order = np.argsort(texts)
    rank = np.empty(len(order), np.int64)
    rank[order] = np.arange(len(order))
    rows = np.array([len(p[1]) for p in parts])
    start = np.cumsum(rows) - rows
    least = np.minimum.reduceat(rank[which], start)
    at = np.flatnonzero(rank[which] == np.repeat(least, rows))
    return texts[order[least]].tolist(), at[np.searchsorted(at, start)] - start


_texts: dict[tuple[int, int, int], str] = {}
_met: OrderedDict = OrderedDict()
_plans: OrderedDict = OrderedDict()


def plans(nbrs: list[list[int]], sizes: tuple[int, ...]) -> dict[int, Plan] | None:
    """Plans of a structure that was met before; none where it is new, has over 62 nodes, or too many sets."""
    if len(nbrs) > 62 or not len(nbrs) or max(sizes) > 11:
        return None
    key = (tuple(map(tuple, nbrs)), sizes)
    if key in _plans:
        _plans.move_to_end(key)
        return _plans[key]
    met = hash(key)
    if met not in _met:
        _met[met] = None
        if len(_met) > MET:
            _met.popitem(last=False)
        return None
    _plans[key] = _made(nbrs, sizes)
    while len(_plans) > 1 and (len(_plans) > MET or sum(p.bytes for x in _plans.values() for p in (x or {}).values()) > BYTES):
        _plans.popitem(last=False)
    return _plans[key]


def _made(nbrs: list[list[int]], sizes: tuple[int, ...]) -> dict[int, Plan] | None:
    near, held = V.adjacency(nbrs), {k: [] for k in sizes}
    try:
        for members in V.connected_sets(near, max(sizes), np.arange(len(near)), SETS):
            if members.shape[1] in held:
                held[members.shape[1]].append(members)
        return {k: Plan(near, np.concatenate(parts)) for k, parts in held.items() if parts}
    except V.SearchSpaceTooLarge:
        return None


def levels(labels: list[int], nbrs: list[list[int]], sizes: set[int]) -> dict[int, Level] | None:
    """Level of each size that a graph has sets of; none where its sets are not shared or its words do not fit."""
    held = plans(nbrs, tuple(sorted(sizes)))
    if held is None:
        return None
    own = np.array(labels, np.int64)
    width = max(1, int(own.max()).bit_length())
    if own.min() < 0 or any(width * k + len(p.forms).bit_length() + len(p.sets).bit_length() > 62 for k, p in held.items()):
        return None
    return {k: Level(p, own) for k, p in held.items()}
