"""The search of one work unit to its end without learning, many assignments side by side.

It visits the assignments that the kernel visits in its modes ``plain`` and ``no_lookup`` and gives the same rows in the same
order and the same counts. The candidates of a position depend on the images of its mapped neighbours only: lists have
numbers, an assignment carries those of its open positions, and a list is met with the neighbours of a vertex once, for all
assignments that agree on them. A learning search depends on what it saw before and stays with the kernel.
"""

from __future__ import annotations

import time
from collections.abc import Iterator

import numpy as np

from .kernel import BATCH, Meets, Result, SlotTable

#: Assignments side by side, more or less; roots that share their lists; and numbers in lists from which on a part has lists of its own.
WIDE, ROOTS, HELD = 200_000, 256, 4_000_000


def _grown(x: np.ndarray, n: int) -> np.ndarray:
    return x if n <= len(x) else np.concatenate([x, np.zeros(max(n, 2 * len(x)) - len(x), x.dtype)])


class Lists:
    def __init__(self, adjacency, meet: Meets):
        self.adjacency, self.meet, self.lists, self.met, self.links, self.held = adjacency, meet, [], {}, {}, 0
        self.size, self.start = np.zeros(64, np.int64), np.zeros(64, np.int64)
        self.flat, self.used = np.zeros(1024, np.int64), 0  # members of the lists that were laid out
        self.next, self.linked_to = np.zeros(1024, np.int64), 0

    def add(self, values: list[int]) -> int:
        k = len(self.lists)
        self.lists.append(values)
        self.size, self.start = _grown(self.size, k + 1), _grown(self.start, k + 1)
        self.size[k], self.start[k] = len(values), -1
        self.held += len(values)
        return k

    def lay_out(self, numbers: np.ndarray) -> None:
        for k in np.unique(numbers[self.start[numbers] < 0]).tolist():
            values = self.lists[k]
            self.flat = _grown(self.flat, self.used + len(values))
            self.flat[self.used : self.used + len(values)] = values
            self.start[k], self.used = self.used, self.used + len(values)

    def linked(self, a: int, b: int) -> int:
        """Where in next the numbers begin of list b met with the neighbours of each member of list a."""
        at = self.links.get((a, b))
        if at is None:
            out = []
            for v in self.lists[a]:
                k = self.met.get((b, v))
                if k is None:
                    k = self.met[b, v] = self.add(self.meet(b, self.lists[b], self.adjacency.get(v, frozenset())))
                out.append(k)
            at = self.links[a, b] = self.linked_to
            self.linked_to += len(out)
            self.next = _grown(self.next, self.linked_to)
            self.next[at : self.linked_to] = out
            self.held += len(out)
        return at


def search_wide(nbr_mask: list[int], domains: list[list[int]], adjacency, *, every: bool, injective: bool = True, labels: list | None = None, embeddings: bool = True) -> Iterator[list[tuple[int, ...]]]:
    """Yields batches of embeddings, if they are asked for, and returns a Result without rows. every: a position without a candidate
    fails an assignment wherever it is, not only where it is next. labels: of the positions; images of different ones differ."""
    n, began = len(nbr_mask), time.perf_counter_ns()
    count = dict.fromkeys(("search_calls", "f_wipeout", "f_reuse", "f_known", "f_child", "f_check", "n_found"), 0)
    later = [[i for i in range(k + 1, n) if nbr_mask[k] >> i & 1] for k in range(n)]
    alike = [[j for j in range(k) if injective and (labels is None or labels[j] == labels[k])] for k in range(n)]

    def run(pool: Lists, asg: np.ndarray, ids: np.ndarray):
        """The rows of one level, and which of them lead to an embedding. asg: images of the mapped positions, a column each; ids: lists of all."""
        level = asg.shape[1]
        count["search_calls"] += len(asg)
        if level == n:
            count["n_found"] += len(asg)
            for s in range(0, len(asg) if embeddings else 0, BATCH):
                yield list(map(tuple, asg[s : s + BATCH].tolist()))
            return np.ones(len(asg), bool)
        good, sizes = np.zeros(len(asg), bool), pool.size[ids[:, level:] if every else ids[:, level : level + 1]]
        live = np.flatnonzero((sizes > 0).all(1))
        count["f_wipeout"] += len(asg) - len(live)
        ends = np.cumsum(pool.size[ids[live, level]])
        lo = 0
        while lo < len(live):
            hi = max(lo + 1, int(np.searchsorted(ends, (ends[lo - 1] if lo else 0) + WIDE, "right")))
            part, lo = live[lo:hi], hi
            held, mine = pool, ids[part]
            if pool.held > HELD and level:  # what is met from here on is dropped with this part
                held, own = Lists(adjacency, Meets()), np.unique(mine[:, level:])
                numbers = np.array([held.add(pool.lists[k]) for k in own.tolist()])
                mine[:, level:] = numbers[np.searchsorted(own, mine[:, level:])]
            options = mine[:, level]
            held.lay_out(options)
            many = held.size[options]
            parent = np.repeat(np.arange(len(part)), many)
            place = np.arange(len(parent)) - np.repeat(np.cumsum(many) - many, many)
            values = held.flat[held.start[options][parent] + place]
            free = np.ones(len(parent), bool)
            for j in alike[level]:
                free &= asg[part, j][parent] != values
            if not free.all():
                count["f_reuse"] += len(free) - int(np.count_nonzero(free))
                parent, place, values = parent[free], place[free], values[free]
            if level == n - 1 and not embeddings:  # each is an embedding and a call
                count["search_calls"] += len(values)
                count["n_found"] += len(values)
                good[part[parent]] = True
                continue
            below = mine[parent]
            for i in later[level]:
                pairs, which = np.unique(options << 32 | mine[:, i], return_inverse=True)
                at = np.array([held.linked(k >> 32, k & 0xFFFFFFFF) for k in pairs.tolist()], np.int64)
                below[:, i] = held.next[at[which][parent] + place]
            found = yield from run(held, np.column_stack([asg[part][parent], values]), below)
            count["f_child"] += len(found) - int(np.count_nonzero(found))
            good[part[parent[found]]] = True
        return good

    roots, meet = domains[0] if n else [], Meets(domains)
    for s in range(0, max(1, len(roots)), ROOTS):
        pool = Lists(adjacency, meet)
        ids = np.array([[pool.add(d) for d in ([roots[s : s + ROOTS], *domains[1:]] if n else [])]], np.int64).reshape(1, n)
        pool.held = 0
        yield from run(pool, np.zeros((1, 0), np.int64), ids)
        count["search_calls"] -= s > 0  # the root call counts once
        if every and not all(domains):
            break
    count |= {"capped": False, "dnf": False, "slot_writes": 0, "slot_overwrites": 0, "slot_hits": 0, "slots_used": 0, "elapsed_ns": time.perf_counter_ns() - began}
    return Result([], count, SlotTable(), [])
