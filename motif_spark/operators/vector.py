"""Connected sets, their keys and canonical codes for whole arrays of sets at once.

A set is a row of node numbers. Codes equal those of `canonical`: rows whose colours become single by refinement,
or are shared only by nodes that can change places at will, are coded here; the few rows with other symmetries go
through `canonical_of`.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np

from .canonical import canonical_of, code_text

#: Sets that are grown together, and cells of their frontier that are held at once.
ROWS, CELLS = 20_000, 4_000_000


class SearchSpaceTooLarge(RuntimeError):
    """More connected sets in a unit than the guard allows."""


def adjacency(nbrs: list[list[int]]) -> np.ndarray:
    near = np.zeros((len(nbrs), len(nbrs)), bool)
    for u, row in enumerate(nbrs):
        near[u, row] = True
    return near


def connected_sets(near: np.ndarray, k_max: int, roots: np.ndarray, guard: int) -> Iterator[np.ndarray]:
    """Arrays (sets, size) of the connected sets whose smallest node is a root, each set once, sizes 1 to k_max.

    A set's children take one node of its frontier each; a child keeps the frontier after that node and gains
    the node's neighbours that are above the root and were not seen. Blocks are grown depth first, so what is
    held is bounded by the size times the block.
    """
    n, made = len(near), 0
    if not len(roots):
        return
    most = max(1, min(ROWS, CELLS // max(n, 1)))
    number = np.arange(n)
    todo = []
    for a in range(0, len(roots), most):
        r = roots[a : a + most]
        front = near[r] & (number > r[:, None])
        todo.append((r[:, None], front, near[r] | (number == r[:, None])))
    while todo:
        members, front, seen = todo.pop()
        made += len(members)
        if made > guard:
            raise SearchSpaceTooLarge(f"over {guard} connected sets; raise the guard or sample instead")
        yield members
        if members.shape[1] == k_max:
            continue
        row, node = np.nonzero(front)
        for a in range(0, len(row), most):
            i, w = row[a : a + most], node[a : a + most]
            grown = np.concatenate([members[i], w[:, None]], 1)
            if grown.shape[1] == k_max:
                todo.append((grown, front[:0], seen[:0]))
                continue
            above = number > members[i, :1]
            later = front[i] & (number > w[:, None]) | near[w] & above & ~seen[i]
            todo.append((grown, later, seen[i] | near[w]))


def keys(members: np.ndarray, labels: np.ndarray, near: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Sorted members, their labels, and adjacency bits (upper triangle, row by row) of every set; sizes up to 11."""
    s = np.sort(members, 1)
    return s, labels[s], triangle(near[s[:, :, None], s[:, None, :]])


def triangle(adj: np.ndarray) -> np.ndarray:
    k = adj.shape[1]
    if k > 11:
        raise ValueError("adjacency bits of more than 11 nodes do not fit a long")
    bits = np.zeros(len(adj), np.int64)
    for i in range(k):
        for j in range(i + 1, k):
            bits = bits << 1 | adj[:, i, j]
    return bits


def square(bits: np.ndarray, k: int) -> np.ndarray:
    adj, at = np.zeros((len(bits), k, k), bool), k * (k - 1) // 2
    for i in range(k):
        for j in range(i + 1, k):
            at -= 1
            adj[:, i, j] = adj[:, j, i] = bits >> at & 1
    return adj


def alike(labels: np.ndarray, bits: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """First row of each distinct (labels, bits), and for each row the number of its own."""
    packs, width = [bits], max(1, int(labels.max()).bit_length() if labels.size else 1)
    per = 62 // width
    for a in range(0, labels.shape[1], per):
        part = np.zeros(len(bits), np.int64)
        for j in range(a, min(a + per, labels.shape[1])):
            part = part << width | labels[:, j]
        packs.append(part)
    order = np.lexsort(packs[::-1])
    new = np.zeros(len(order), bool)
    new[:1] = True
    for p in packs:
        new[1:] |= p[order[1:]] != p[order[:-1]]
    which = np.empty(len(order), np.int64)
    which[order] = np.cumsum(new) - 1
    return order[new], which


def _ranks(x: np.ndarray) -> np.ndarray:
    order = np.argsort(x, 1, kind="stable")
    held = np.take_along_axis(x, order, 1)
    step = np.zeros(x.shape, np.int64)
    step[:, 1:] = np.cumsum(held[:, 1:] != held[:, :-1], 1)
    out = np.empty_like(step)
    np.put_along_axis(out, order, step, 1)
    return out


def refined(labels: np.ndarray, adj: np.ndarray) -> np.ndarray:
    """Colours of every row's nodes: ranks of labels, then of (colour, sorted neighbour colours) until nothing splits."""
    k = labels.shape[1]
    colour = _ranks(labels)
    live = np.flatnonzero(colour.max(1) < k - 1) if k > 1 else np.zeros(0, np.int64)
    while len(live):
        c, a = colour[live], adj[live]
        around = np.sort(np.where(a, c[:, None, :] + 1, 15), 2)
        key = c + 1
        for j in range(k - 1):
            key = key << 4 | np.where(around[:, :, j] == 15, 0, around[:, :, j])
        now = _ranks(key)
        split = now.max(1) > c.max(1)
        colour[live] = now
        live = live[split & (now.max(1) < k - 1)]
    return colour


def twins(adj: np.ndarray, colour: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Rows whose nodes of one colour all have the same neighbours but for each other, and their automorphisms:
    such nodes take any order, so each colour counts the orders of its nodes."""
    k = colour.shape[1]
    mask = (adj * (1 << np.arange(k))).sum(2)
    alike, seen, count = np.ones(len(adj), bool), np.ones((len(adj), k), np.int64), np.ones(len(adj), np.int64)
    for j in range(1, k):
        for i in range(j):
            same = colour[:, i] == colour[:, j]
            alike &= ~same | ((mask[:, i] ^ mask[:, j]) & ~(1 << i | 1 << j) == 0)
            seen[:, j] += same
        count *= seen[:, j]
    return alike, count


class Classes:
    """Codes of distinct (labels, bits): code text, automorphisms, and for each place its node's place in the code
    and the first place of its orbit there."""

    def __init__(self, labels: np.ndarray, bits: np.ndarray, text: bool = True):
        k = labels.shape[1]
        adj = square(bits, k)
        colour = refined(labels, adj)
        alone, self.automorphisms = twins(adj, colour)
        # Nodes of a colour stand together, so the first of them has as many places before it as there are lower colours.
        self.place = (colour[:, None, :] < colour[:, :, None]).sum(2)
        order = np.argsort(colour, 1, kind="stable")
        form = triangle(np.take_along_axis(np.take_along_axis(adj, order[:, :, None], 1), order[:, None, :], 2))
        own = np.take_along_axis(labels, order, 1)
        for r in np.flatnonzero(~alone).tolist():
            code, count, seq, orbit = canonical_of(tuple(labels[r].tolist()), int(bits[r]))
            got, value = code.split(":")
            own[r], form[r], self.automorphisms[r] = [int(x) for x in got.split(".")], int(value), count
            at = {x: i for i, x in enumerate(seq)}
            self.place[r] = [min(at[y] for y in range(k) if orbit[y] == orbit[x]) for x in range(k)]
        self.labels, self.form = own, form

    def texts(self, rows: np.ndarray) -> list[str]:
        return [code_text(tuple(x), b) for x, b in zip(self.labels[rows].tolist(), self.form[rows].tolist())]


def counted(members: np.ndarray, labels: np.ndarray, near: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Distinct (labels, bits) of the sets with how many there are and the least set of each."""
    s, own, bits = keys(members, labels, near)
    order = np.lexsort(s.T[::-1])  # so that the first of each kind is the least
    s, own, bits = s[order], own[order], bits[order]
    first, which = alike(own, bits)
    return own[first], bits[first], np.bincount(which, minlength=len(first)), s[first]
