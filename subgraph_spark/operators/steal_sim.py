"""Deterministic simulation of work stealing with private deques, over a recorded search tree.

One tick checks one pair. It reproduces what a cluster's tasks can't do (hand over single tasks in nanoseconds), and
so shows load, steals and group sizes without a clock. A tree is one group of ``applyInPandas``, bounded by its maker.
"""

from __future__ import annotations

import random
from collections import deque
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession


@dataclass
class Outcome:
    makespan: int
    states: list[int]
    steals_ok: int
    steals_failed: int
    cells_copied: int
    token_hops: int

    @property
    def spread(self) -> float:
        return float(np.std(self.states))


@dataclass
class TaskTree:
    """What a simulation needs of a search tree: the consistent nodes that generate pairs, consistent roots first and the children of a node side by side. Of other nodes only the numbers are held."""

    roots: int  # consistent or not
    last: int  # depth of the deepest pairs
    root_at: np.ndarray  # places of the consistent roots among all
    depth: np.ndarray
    generated: np.ndarray  # pairs
    first: np.ndarray  # first consistent child
    kids: np.ndarray  # consistent children


def children_of(parent: np.ndarray, consistent: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Per node: the number of pairs it generates, and where its consistent children lie in one array."""
    n = len(parent)
    generated = np.bincount(parent[parent >= 0], minlength=n)
    good = np.flatnonzero(consistent & (parent >= 0))
    order = good[np.argsort(parent[good], kind="stable")]
    return generated, np.concatenate([[0], np.cumsum(np.bincount(parent[order], minlength=n))]), order


def tasks_of(parent: np.ndarray, depth: np.ndarray, consistent: np.ndarray) -> TaskTree:
    """The tasks of a recorded tree."""
    generated, first, order = children_of(parent, consistent)
    roots = np.flatnonzero(parent < 0)
    root_at = np.flatnonzero(consistent[roots])
    node = np.concatenate([roots[root_at], order])
    return TaskTree(len(roots), int(depth.max()) if len(depth) else 0, root_at, depth[node], generated[node], len(root_at) + first[node], first[node + 1] - first[node])


def simulate(parent: np.ndarray, depth: np.ndarray, consistent: np.ndarray, *how, **ways) -> Outcome:
    """A recorded tree under ``simulate_tasks``."""
    return simulate_tasks(tasks_of(parent, depth, consistent), *how, **ways)


def simulate_tasks(tree: TaskTree, workers: int, group: int = 4, seed: int = 0, stealing: bool = True, copy_cost: float = 1.0, copy: str = "on_steal", min_states: int = 1, initiator: str = "receiver", deal: str = "block") -> Outcome:
    """``copy="per_task"`` copies the mapping at every task; ``min_states`` explores that many pairs before giving work away;
    ``initiator="sender"`` lets loaded workers push to a random one instead. ``deal``: contiguous blocks or round robin."""
    generated, first, kids, depth, last = tree.generated, tree.first, tree.kids, tree.depth, tree.last
    if deal == "block":
        size, more = divmod(tree.roots, workers)
        ends = np.cumsum([size + (w < more) for w in range(workers)])
        states = np.diff(ends, prepend=0).tolist()
        owner = np.searchsorted(ends, tree.root_at, "right")
    else:
        states = [len(range(w, tree.roots, workers)) for w in range(workers)]
        owner = tree.root_at % workers
    rng = random.Random(seed)
    queues: list[deque] = [deque() for _ in range(workers)]
    busy = list(states)  # ticks still to spend
    for w in range(workers):
        good = np.flatnonzero(owner == w).tolist() if last > 0 else []
        queues[w].extend(tuple(good[i : i + group]) for i in range(0, len(good), group))
    since = [0] * workers
    asks: list[int | None] = [None] * workers  # who has asked this worker
    waits: list[int | None] = [None] * workers  # whom this worker has asked
    open_ = [bool(q) for q in queues]
    ok = failed = copied = hops = now = ended = 0
    holder, white, clean = 0, True, 0
    while True:
        if busy[holder] > 1:  # ticks at which workers only spend time are taken at once
            least = min(busy)
            if not least and not stealing and not any(q for q, b in zip(queues, busy, strict=True) if not b):
                least = min(b for b in busy if b)
            if least > 1:
                busy = [b and b - least + 1 for b in busy]
                now += least - 1
                ended, white, clean = now, False, 0
        for w in range(workers):
            if busy[w] > 0:
                busy[w] -= 1
                ended = now + 1
                continue
            if not queues[w]:
                open_[w] = False
                if asks[w] is not None:  # nothing to give
                    waits[asks[w]], asks[w] = None, None
                    failed += 1
                if stealing and initiator == "receiver" and workers > 1 and waits[w] is None:
                    victim = rng.randrange(workers - 1)
                    victim += victim >= w
                    if open_[victim] and asks[victim] is None:
                        asks[victim], waits[w] = w, victim
                    else:
                        failed += 1
                continue
            task_group, ended = queues[w].popleft(), now + 1
            open_[w] = bool(queues[w])
            if initiator == "sender" and stealing and workers > 1 and queues[w] and since[w] >= min_states:
                other = rng.randrange(workers - 1)
                other += other >= w
                if not queues[other] and not busy[other]:
                    asks[w] = other
            thief = asks[w]
            if thief is not None:
                asks[w], waits[thief] = None, None
                if queues[w] and since[w] >= min(min_states, since[w] + 1):
                    given = queues[w].pop()
                    level = int(depth[given[0]]) + 1
                    queues[thief].append(given)
                    busy[thief] += int(1 + copy_cost * level)
                    copied += level
                    ok += 1
                    open_[w], open_[thief] = bool(queues[w]), False
                    since[w] = 0
                else:
                    failed += 1
            for task in task_group:
                ticks = int(generated[task])
                states[w] += ticks
                since[w] += ticks
                busy[w] += max(1, ticks)
                if copy == "per_task":
                    level = int(depth[task]) + 1
                    busy[w] += int(copy_cost * level)
                    copied += level
                if depth[task] + 1 < last:
                    own = range(int(first[task]), int(first[task] + kids[task]))
                    for i in reversed(range(0, len(own), group)):
                        queues[w].appendleft(tuple(own[i : i + group]))
            open_[w] = bool(queues[w])
            busy[w] -= 1
        now += 1
        # The token moves on from an idle holder; a busy one blackens it.
        if busy[holder] > 0 or queues[holder] or waits[holder] is not None and queues[waits[holder]]:
            white, clean = False, 0
        else:
            clean = clean + 1 if white else 1
            white, hops, holder = True, hops + 1, (holder + 1) % workers
        if clean > workers and not any(busy) and not any(queues):
            break
    return Outcome(ended, states, ok, failed, copied, hops)


GRID = "instance string, workers int, group_size int, seed int, stealing boolean, pairs long, makespan long, spread double, steals_ok long, steals_failed long, cells_copied long, token_hops long"


def simulate_grid(tree: DataFrame, settings: DataFrame, max_nodes: int = 10**6) -> DataFrame:
    """``tree`` (instance, node_id, parent_id, depth, consistent) under each row of ``settings`` (workers, group_size, seed, stealing).

    Trees are bounded: ``max_nodes`` in all. They are broadcast once as arrays, and the settings are dealt.
    """
    n = tree.count()
    if n > max_nodes:
        raise ValueError(f"the trees have {n} nodes, {max_nodes} are allowed")
    rows = tree.select("instance", "node_id", "parent_id", "depth", "consistent").toPandas().sort_values(["instance", "node_id"])
    trees = {k: (x.parent_id.to_numpy(), x.depth.to_numpy(), x.consistent.to_numpy()) for k, x in rows.groupby("instance")}
    shared = tree.sparkSession.sparkContext.broadcast(trees)
    names = [x.strip().split(" ")[0] for x in GRID.split(",")]

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for x in batch.itertuples(index=False):
                for k, arrays in shared.value.items():
                    got = simulate(*arrays, int(x.workers), int(x.group_size), int(x.seed), bool(x.stealing))
                    yield pd.DataFrame([(k, *x, sum(got.states), got.makespan, got.spread, got.steals_ok, got.steals_failed, got.cells_copied, got.token_hops)], columns=names)

    dealt = settings.select("workers", "group_size", "seed", "stealing")
    return dealt.repartition(2 * tree.sparkSession.sparkContext.defaultParallelism, "workers", "group_size", "seed", "stealing").mapInPandas(run, GRID)


WAYS = "way string, pairs long, makespan long, spread double, steals_ok long, steals_failed long, cells_copied long, token_hops long"


def simulate_ways(spark: SparkSession, tree: dict[str, np.ndarray], ways: dict[str, dict], workers: int, group: int = 4, seed: int = 0) -> DataFrame:
    """One tree, whose size its maker bounds, under named settings of ``simulate``; a task each."""
    shared = spark.sparkContext.broadcast((tree["parent_id"], tree["depth"], tree["consistent"]))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for way in batch["way"]:
                got = simulate(*shared.value, workers, group, seed, **ways[way])
                yield pd.DataFrame([(way, sum(got.states), got.makespan, got.spread, got.steals_ok, got.steals_failed, got.cells_copied, got.token_hops)], columns=[x.strip().split(" ")[0] for x in WAYS.split(",")])

    return spark.createDataFrame([(k,) for k in ways], "way string").repartition(len(ways), "way").mapInPandas(run, WAYS)
