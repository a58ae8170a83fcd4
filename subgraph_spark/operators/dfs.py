"""Depth-first search over arrays: what one task runs on its seeds.

The kernel keeps a stack of blocks of partial mappings. It takes a part of the newest block, makes and tests all of that part's
candidates with array operations, and puts the survivors on top: depth-first with a bounded block instead of one mapping.
A pair is counted when it is tested, so counts don't depend on blocks, seeds, tasks or budgets.
"""

from __future__ import annotations

import copy
import time
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np

from ..model import Csr
from ..plans.search_plan import Check, SearchPlan, Step
from .domains import WORD, LabelMatch
from .steal_sim import TaskTree

#: Pairs that are made at a time.
BLOCK = 1 << 16
#: Roots that are tested at a time.
ROOTS = 1 << 20


@dataclass
class Counters:
    pairs: int = 0
    matches: int = 0
    by_depth: np.ndarray = field(default_factory=lambda: np.zeros(0, np.int64))
    timed_out: bool = False


class Grown:
    """Mappings one longer than those of ``part``: the row that each grew from, and its candidate. A vertex with very many neighbours so takes no copy of its mapping for each."""

    def __init__(self, part: np.ndarray, row: np.ndarray, cand: np.ndarray):
        self.part, self.row, self.cand = (part, row, cand) if len(row) >= len(part) else (part[row], np.arange(len(row)), cand)

    @property
    def shape(self) -> tuple[int, int]:
        return len(self.cand), self.part.shape[1] + 1

    def __len__(self) -> int:
        return len(self.cand)

    def __getitem__(self, rows: slice) -> Grown:
        new = copy.copy(self)
        new.row, new.cand = self.row[rows], self.cand[rows]
        return new

    def images(self, pos: int) -> np.ndarray:
        return self.cand if pos == self.part.shape[1] else self.part[self.row, pos]

    def whole(self) -> np.ndarray:
        return np.concatenate([self.part[self.row], self.cand[:, None]], axis=1)


def _whole(block: np.ndarray | Grown) -> np.ndarray:
    return block.whole() if isinstance(block, Grown) else block


class Kernel:
    """``lookahead`` (domain methods): a candidate must leave each later neighbour in the pattern an unused vertex of its domain."""

    def __init__(self, csr: Csr, plan: SearchPlan, label_match: LabelMatch | None = None, induced: bool = False, lookahead: bool = False):
        self.csr, self.plan, self.induced = csr, plan, induced
        place = {s.pv: s.pos for s in plan.steps}
        self.ahead: list[list[tuple[int, bool, np.ndarray]]] = [[] for _ in plan.steps]
        for s, d, _ in plan.pattern.edges if lookahead and plan.uses_domains else ():
            if s != d:
                v, u, out = (s, d, True) if place[s] < place[d] else (d, s, False)
                self.ahead[place[v]].append((u, out, self._open(u, out)))
        self.wanted = [self._codes(s.vlabel, label_match) for s in plan.steps]
        self.have = {(s, d) for s, d, _ in plan.pattern.edges}

    def _codes(self, label: str | None, label_match: LabelMatch | None) -> np.ndarray | None:
        if label is None:
            return None
        names = label_match.get(label, ()) if label_match is not None else (label,)
        return np.array(sorted(self.csr.label_code[x] for x in names if x in self.csr.label_code), np.int64)

    def _open(self, u: int, out: bool) -> np.ndarray:
        """Per vertex, its neighbours in the domain of pattern vertex ``u``."""
        ptr, to = (self.csr.out_ptr, self.csr.out_to) if out else (self.csr.in_ptr, self.csr.in_to)
        return np.diff(np.concatenate([[0], np.cumsum(self._in_domain(to, u))])[ptr])

    def _leaves_open(self, block: np.ndarray, row: np.ndarray, cand: np.ndarray, step: Step) -> np.ndarray:
        """Candidates that leave each later neighbour something: its candidates beside them, less those that are used."""
        fine = np.ones(len(cand), bool)
        for u, out, open_ in self.ahead[step.pos]:
            left = open_[cand]
            for i in range(step.pos):
                image = block[row, i]
                left = left - (self._in_domain(image, u) & self._edge(cand, image, Check(0, out, None)))
            fine &= left > 0
        return fine

    def roots(self, step: Step) -> np.ndarray:
        """Candidates of a position without an anchor: all vertices, or the domain's."""
        if not self.plan.uses_domains:
            return np.arange(self.csr.n)
        word, bit = step.pv // WORD, step.pv % WORD
        return np.concatenate([np.zeros(0, np.int64), *(at + np.flatnonzero(self.csr.masks[at : at + ROOTS, word] >> bit & 1) for at in range(0, self.csr.n, ROOTS))])

    def _in_domain(self, cand: np.ndarray, pv: int) -> np.ndarray:
        return self.csr.masks[cand, pv // WORD] >> pv % WORD & 1 != 0

    def _edge(self, image: np.ndarray, cand: np.ndarray, check: Check) -> np.ndarray:
        s, d = (image, cand) if check.out else (cand, image)
        return self.csr.has_edge(s, d, check.elabel)

    def fan_out(self, block: np.ndarray | Grown, step: Step) -> np.ndarray:
        """How many candidates each mapping of the block has."""
        if step.anchor is None:
            return np.full(len(block), len(self.roots(step)))
        ptr = self.csr.out_ptr if step.anchor.out else self.csr.in_ptr
        at = block.images(step.anchor.pos) if isinstance(block, Grown) else block[:, step.anchor.pos]
        return ptr[at + 1] - ptr[at]

    def pairs(self, block: np.ndarray, step: Step) -> tuple[np.ndarray, np.ndarray]:
        """(row of the block, candidate), in order."""
        count = self.fan_out(block, step)
        row = np.repeat(np.arange(len(block)), count)
        inner = np.arange(len(row)) - np.repeat(np.cumsum(count) - count, count)
        if step.anchor is None:
            return row, self.roots(step)[inner]
        ptr, to = (self.csr.out_ptr, self.csr.out_to) if step.anchor.out else (self.csr.in_ptr, self.csr.in_to)
        return row, to[np.repeat(ptr[block[:, step.anchor.pos]], count) + inner].astype(np.int64, copy=False)

    def passing(self, block: np.ndarray, row: np.ndarray, cand: np.ndarray, step: Step) -> np.ndarray:
        """Indices of the pairs that meet all rules; each rule sees what the ones before it left."""
        at = np.arange(len(cand))
        if self.plan.uses_domains:
            at = at[self._in_domain(cand, step.pv)]
        for i in range(step.pos):
            at = at[block[row[at], i] != cand[at]]
        if not self.plan.uses_domains:
            if self.wanted[step.pos] is not None:
                at = at[np.isin(self.csr.vlabel[cand[at]], self.wanted[step.pos])]
            at = at[(self.csr.degree(cand[at], False) >= step.indeg) & (self.csr.degree(cand[at], True) >= step.outdeg)]
        labelled = [step.anchor] if step.anchor is not None and step.anchor.elabel is not None else []
        for check in [*labelled, *step.checks]:
            at = at[self._edge(block[row[at], check.pos], cand[at], check)]
        for label in step.loops:
            at = at[self._edge(cand[at], cand[at], Check(step.pos, True, label))]
        if self.induced:
            for i in range(step.pos):
                u = self.plan.steps[i].pv
                for check, edge in ((Check(i, True, None), (u, step.pv)), (Check(i, False, None), (step.pv, u))):
                    if edge not in self.have:
                        at = at[~self._edge(block[row[at], i], cand[at], check)]
            if not step.loops:
                at = at[~self.csr.has_edge(cand[at], cand[at])]
        return at[self._leaves_open(block, row[at], cand[at], step)] if self.ahead[step.pos] else at

    def seeds(self, chosen: np.ndarray | None = None, counters: Counters | None = None) -> np.ndarray:
        """Root mappings that pass, of all root candidates or the ``chosen`` ones."""
        step = self.plan.steps[0]
        cand = self.roots(step) if chosen is None else chosen
        if counters is not None:
            counters.pairs += len(cand)
            if len(counters.by_depth):
                counters.by_depth[0] += len(cand)
        some = [cand[at : at + ROOTS] for at in range(0, len(cand), ROOTS)]
        return np.concatenate([cand[:0], *(x[self.passing(np.zeros((len(x), 0), np.int64), np.arange(len(x)), x, step)] for x in some)])[:, None]

    def run(self, seeds: np.ndarray, counters: Counters, budget: int | None = None, deadline: float | None = None, first_only: bool = False, block: int = BLOCK) -> Iterator[tuple[str, np.ndarray]]:
        """Yields ("match", full mappings) and, where the budget ends the search, ("todo", partial mappings), shallowest first."""
        k = len(self.plan.steps)
        if not len(counters.by_depth):
            counters.by_depth = np.zeros(k, np.int64)
        if seeds.shape[1] == k:
            counters.matches += len(seeds)
            yield "match", seeds
            return
        stack, spent = [seeds], 0
        while stack:
            top = stack.pop()
            if not len(top):
                continue
            if budget is not None and spent >= budget or deadline is not None and time.monotonic() > deadline:
                if deadline is not None and time.monotonic() > deadline:
                    counters.timed_out = True
                yield from (("todo", _whole(x)) for x in [*stack, top] if len(x))
                return
            step = self.plan.steps[top.shape[1]]
            upto = max(1, int(np.searchsorted(np.cumsum(self.fan_out(top[:ROOTS], step)), block if budget is None else min(block, budget - spent), "right")))
            part, rest = _whole(top[:upto]), top[upto:]
            row, cand = self.pairs(part, step)
            spent += len(cand)
            counters.pairs += len(cand)
            counters.by_depth[step.pos] += len(cand)
            at = self.passing(part, row, cand, step)
            if len(rest):
                stack.append(rest)
            new = Grown(part, row[at], cand[at])
            if step.pos + 1 == k:
                counters.matches += len(new)
                if len(new):
                    yield "match", new.whole()
                    if first_only:
                        return
            elif len(new):
                stack.append(new)


def search_tree(kernel: Kernel, max_nodes: int = 10**6) -> dict[str, np.ndarray]:
    """Every pair considered, as a tree: node, parent (-1 for roots), depth, vt, consistent. Children of one parent are adjacent and in candidate order."""
    step, out, n = kernel.plan.steps[0], [], 0
    block, owner = np.zeros((1, 0), np.int64), np.array([-1])
    for step in kernel.plan.steps:
        if n + int(kernel.fan_out(block, step).sum()) > max_nodes:
            raise ValueError(f"the tree has more than {max_nodes} nodes")
        row, cand = kernel.pairs(block, step)
        at = kernel.passing(block, row, cand, step)
        good = np.zeros(len(cand), bool)
        good[at] = True
        out.append((n + np.arange(len(cand)), owner[row], np.full(len(cand), step.pos), kernel.csr.vids[cand], good))
        block, owner = np.concatenate([block[row[at]], cand[at][:, None]], axis=1), n + at
        n += len(cand)
    names = ("node_id", "parent_id", "depth", "vt", "consistent")
    return {k: np.concatenate(x) for k, x in zip(names, zip(*out, strict=True), strict=True)}


def task_tree(kernel: Kernel, max_nodes: int | None = None, block: int = 1 << 18) -> TaskTree:
    """The tasks of ``search_tree``, a level after the other, whose pairs are made ``block`` at a time and not kept."""
    steps = kernel.plan.steps
    cand = kernel.roots(steps[0])
    nodes = roots = len(cand)
    some = [(at, cand[at : at + ROOTS]) for at in range(0, roots, ROOTS)]
    root_at = np.concatenate([cand[:0], *(at + kernel.passing(np.zeros((len(x), 0), np.int64), np.arange(len(x)), x, steps[0]) for at, x in some)])
    level, last, made, out = cand[root_at][:, None], 0, 0, []
    for step in steps[1:]:
        if max_nodes is not None and nodes > max_nodes:
            break
        generated = kernel.fan_out(level, step)
        nodes += int(generated.sum())
        last = step.pos if generated.any() else last
        kids, new, a = np.zeros(len(level), np.int64), [np.zeros((0, step.pos + 1), np.int64)], 0
        ends = np.cumsum(generated)
        while step.pos + 1 < len(steps) and a < len(level) and (max_nodes is None or nodes <= max_nodes):
            b = max(a + 1, int(np.searchsorted(ends, ends[a] - generated[a] + block, "right")))
            part = level[a:b]
            row, cand = kernel.pairs(part, step)
            at = kernel.passing(part, row, cand, step)
            kids[a:b] = np.bincount(row[at], minlength=b - a)
            new.append(np.concatenate([part[row[at]], cand[at][:, None]], axis=1))
            a = b
        made += len(level)
        out.append((np.full(len(level), step.pos - 1, np.int32), generated, made + np.cumsum(kids) - kids, kids))
        level = np.concatenate(new)
    if max_nodes is not None and nodes > max_nodes:
        raise ValueError(f"the tree has more than {max_nodes} nodes")
    return TaskTree(roots, last, root_at, *(np.concatenate([np.zeros(0, np.int64), *x]) for x in (zip(*out, strict=True) if out else [()] * 4)))
