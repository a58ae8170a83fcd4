"""Candidate domains over a target's arrays: the rules of ``domains``, for tasks that hold the arrays anyway.

Experiments run thousands of small searches on one target. Each is prepared and run inside a task, so that it costs no Spark
job of its own; the table form in ``domains`` is for targets of any size.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Sequence
from functools import reduce

import numpy as np

from ..model import Csr, PatternGraph
from .domains import WORD, LabelMatch, words


#: Words of masks that are handled at a time.
BLOCK = 1 << 20
#: Bytes of masks up to which they are plain rows.
PLAIN = 32 << 20


def _bits(masks: np.ndarray, i: int) -> np.ndarray:
    return masks[:, i // WORD] >> i % WORD & 1 != 0


class Initial:
    """Initial masks, equal label and no smaller in- or out-degree, as a class per vertex and the classes' masks."""

    def __init__(self, csr: Csr, pattern: PatternGraph, label_match: LabelMatch | None = None):
        names = [None if x is None else {x} if label_match is None else set(label_match.get(x, ())) for x in pattern.labels]
        wanted = sorted({csr.label_code[y] for x in names if x for y in x if y in csr.label_code})
        ins, outs = (sorted({f(i) for i in range(pattern.size)}) for f in (pattern.in_degree, pattern.out_degree))
        code = np.full(len(csr.label_code), len(wanted))
        code[wanted] = np.arange(len(wanted))
        shape = len(wanted) + 1, len(ins) + 1, len(outs) + 1
        table = np.zeros((*shape, words(pattern)), np.int64)
        for i, some in enumerate(names):
            labels = slice(None) if some is None else [code[csr.label_code[x]] for x in some if x in csr.label_code]
            table[labels, ins.index(pattern.in_degree(i)) + 1 :, outs.index(pattern.out_degree(i)) + 1 :, i // WORD] |= 1 << i % WORD
        self.table = table.reshape(-1, words(pattern))
        self.of = np.empty(csr.n, np.int32)
        for at in range(0, csr.n, BLOCK):
            v = slice(at, at + BLOCK)
            into, out = (np.searchsorted(have, np.diff(ptr[at : at + BLOCK + 1]), "right") for have, ptr in ((ins, csr.in_ptr), (outs, csr.out_ptr)))
            self.of[v] = (code[csr.vlabel[v]] * shape[1] + into) * shape[2] + out

    def __getitem__(self, v) -> np.ndarray:
        return self.table[self.of[v]]


class Coded:
    """Masks as a class per vertex and the classes' masks, added a block of vertices at a time: few of them differ, and 4 bytes a vertex are less than its words."""

    def __init__(self, n: int, width: int):
        self.of, self.table, self.codes = np.zeros(n, np.int32), np.zeros((0, width), np.int64), {}

    def _code(self, row: np.ndarray) -> int:
        code = self.codes.setdefault(row.tobytes(), len(self.codes))
        if code >= len(self.table):
            self.table = np.concatenate([self.table, np.zeros((max(64, len(self.table)), row.shape[0]), np.int64)])
        if code == len(self.codes) - 1:
            self.table[code] = row
        return code

    def put(self, a: int, b: int, rows: np.ndarray) -> None:
        mixed = np.zeros(len(rows), np.uint64)
        for w in range(rows.shape[1]):
            mixed = (mixed ^ rows[:, w].astype(np.uint64)) * np.uint64(0x9E3779B97F4A7C15)
            mixed ^= mixed >> np.uint64(29)
        _, first, back = np.unique(mixed, return_index=True, return_inverse=True)
        if not np.array_equal(rows[first][back], rows):
            _, first, back = np.unique(rows, axis=0, return_index=True, return_inverse=True)
        self.of[a:b] = np.array([self._code(x) for x in rows[first]], np.int32)[back.ravel()]

    @property
    def shape(self) -> tuple[int, int]:
        return len(self.of), self.table.shape[1]

    def __len__(self) -> int:
        return len(self.of)

    def __getitem__(self, at) -> np.ndarray:
        v, rest = (at[0], at[1:]) if isinstance(at, tuple) else (at, ())
        return np.array(self.table[(self.of[v], *rest)])

    def __setitem__(self, at, rows: np.ndarray) -> None:
        if isinstance(at, slice):
            self.put(*at.indices(len(self))[:2], rows)
        else:
            self.of[at] = self._code(rows)

    def copy(self) -> Coded:
        new = Coded(0, self.table.shape[1])
        new.of, new.table, new.codes = self.of.copy(), self.table.copy(), dict(self.codes)
        return new


def initial(csr: Csr, pattern: PatternGraph, label_match: LabelMatch | None = None) -> np.ndarray:
    """Masks, a row per vertex."""
    return Initial(csr, pattern, label_match)[:]


def _gathered(ptr: np.ndarray, to: np.ndarray, a: int, b: int, masks: np.ndarray | Initial | Coded) -> np.ndarray:
    """Masks of the neighbours of the vertices from ``a`` to ``b``, together per vertex. A vertex of its own may have any number."""
    low, high = int(ptr[a]), int(ptr[b])
    if b == a + 1:
        parts = [np.bitwise_or.reduce(masks[to[at : min(at + BLOCK, high)]], axis=0) for at in range(low, high, BLOCK)]
        return np.bitwise_or.reduce([masks[:0].sum(axis=0), *parts], axis=0)[None]
    out = np.zeros((b - a, masks[:0].shape[1]), np.int64)
    some = np.diff(ptr[a : b + 1]) > 0
    if high > low:
        out[some] = np.bitwise_or.reduceat(masks[to[low:high]], ptr[a:b][some] - low, axis=0)
    return out


def _around(csr: Csr, label: str | None) -> tuple[tuple[np.ndarray, np.ndarray], ...]:
    """(where a vertex's neighbours begin, neighbours), out and in, by edges of a label."""
    if label is None:
        return (csr.out_ptr, csr.out_to), (csr.in_ptr, csr.in_to)
    keys, n = csr.keys_of(label), max(csr.n, 1)
    src, dst = keys // n, keys % n
    back = np.argsort(dst, kind="stable")
    ptr = lambda x: np.concatenate([[0], np.cumsum(np.bincount(x, minlength=csr.n))])
    return (ptr(src), dst), (ptr(dst), src[back])


def consistent(csr: Csr, pattern: PatternGraph, masks: np.ndarray | Initial | Coded) -> tuple[np.ndarray | Coded, tuple[int, ...]]:
    """One simultaneous round of neighbourhood consistency, a block of vertices at a time: masks, and the domains' sizes."""
    width = words(pattern)
    loops: set[tuple[int, str | None]] = {(s, x) for s, d, x in pattern.edges if s == d}
    needs: dict[str | None, np.ndarray] = defaultdict(lambda: np.zeros((2, pattern.size, width), np.int64))
    for s, d, x in pattern.edges:
        if s != d:
            needs[x][0, s, d // WORD] |= 1 << d % WORD
            needs[x][1, d, s // WORD] |= 1 << s % WORD
    around = {x: _around(csr, x) for x in needs}
    new, count = np.empty((csr.n, width), np.int64) if 8 * csr.n * width <= PLAIN else Coded(csr.n, width), np.zeros(pattern.size, np.int64)
    for a, b in csr.blocks(BLOCK // width):
        own = masks[np.arange(a, b)]
        some = np.bitwise_or.reduce(own, axis=0)
        for label, need in needs.items():
            for (ptr, to), wanted in zip(around[label], need, strict=True):
                near = _gathered(ptr, to, a, b, masks)
                for i in np.flatnonzero(wanted.any(axis=1)):
                    if some[i // WORD] >> i % WORD & 1:
                        lost = reduce(np.logical_or, [near[:, w] & x != x for w, x in enumerate(wanted[i]) if x])
                        own[lost, i // WORD] &= ~(1 << int(i) % WORD)
        for i, label in loops:
            v = np.arange(a, b)
            own[~csr.has_edge(v, v, label), i // WORD] &= ~(1 << i % WORD)
        new[a:b] = own
        some = np.bitwise_or.reduce(own, axis=0)
        for i in range(pattern.size):
            if some[i // WORD] >> i % WORD & 1:
                count[i] += np.count_nonzero(_bits(own, i))
    return new, tuple(count.tolist())


def sizes(pattern: PatternGraph, masks: np.ndarray) -> tuple[int, ...]:
    return tuple(int(_bits(masks, i).sum()) for i in range(pattern.size))


def forward_check(pattern: PatternGraph, masks: np.ndarray, now: Sequence[int]) -> tuple[int, ...]:
    """Rounds in which each new singleton's vertex leaves all other domains, in place; stops when there is none, or one is empty. Returns the sizes, which were ``now``."""
    now, done = list(now), set()
    while True:
        new = {i: next(at + int(x[0]) for at in range(0, len(masks), BLOCK) if len(x := np.flatnonzero(_bits(masks[at : at + BLOCK], i)))) for i in range(pattern.size) if now[i] == 1 and i not in done}
        if 0 in now or not new:
            return tuple(now)
        done |= set(new)
        owners = defaultdict(list)
        for i, v in new.items():
            owners[v].append(i)
        for v, own in owners.items():
            stays = np.zeros(masks.shape[1], np.int64)
            if len(own) == 1:
                stays[own[0] // WORD] = 1 << own[0] % WORD
            for i in range(pattern.size):
                now[i] -= int(masks[v, i // WORD] & ~stays[i // WORD]) >> i % WORD & 1
            masks[v] &= stays


def prepare(csr: Csr, pattern: PatternGraph, method: str, rounds: int | str = 1) -> tuple[np.ndarray, tuple[int, ...]]:
    """(masks, sizes) as ``method`` wants them; an empty domain ends the rounds."""
    first = Initial(csr, pattern)
    counts = np.bincount(first.of, minlength=len(first.table))
    now, done, masks = tuple(int(counts[_bits(first.table, i)].sum()) for i in range(pattern.size)), 0, first
    while 0 not in now and (rounds == "fixpoint" or done < int(rounds)):
        before, done = now, done + 1
        masks, now = consistent(csr, pattern, masks)
        if rounds == "fixpoint" and now == before:
            break
    masks = masks[:] if masks is first else masks
    if method in ("dom_f", "dom_sf") and 0 not in now:
        now = forward_check(pattern, masks, now)
    return masks, now
