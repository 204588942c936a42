"""A graph inside one process: domains, filters and orders of many small patterns.

Neighbour lists are arrays in chunks, as a rule mapped from the files of broadcasts that all processes of a machine share,
so that a process holds only the lists its searches meet.
"""

from __future__ import annotations

import time
from bisect import bisect_right
from collections import Counter, OrderedDict
from collections.abc import Iterator
from itertools import compress

import numpy as np

from branchwise.plans import ordering
from branchwise.plans.pattern import PatternGraph

from .candidates import _saturates

#: Neighbours of the lists a process keeps as sets, bytes of the counts it keeps, and vertices whose lists are read at once.
KEPT, KEPT_BYTES, AT_ONCE = 1_000_000, 64_000_000, 50_000
#: Bytes of the lists by label pair a process keeps.
PAIR_BYTES = 128_000_000
#: Filters that ask for neighbours of one label.
BY_PAIR = {"labels", "arcs", "tree", "bipartite"}


class OutOfTime(Exception):
    pass


class Neighbours:
    """vertex -> set of neighbours, read when first asked for; when too many are held all are dropped."""

    def __init__(self, graph: LocalGraph):
        self.graph, self.held, self.size = graph, {}, 0

    def get(self, v: int, default=frozenset()):
        found = self.held.get(v)
        if found is None:
            if self.size > KEPT:
                self.held, self.size = {}, 0
            found = self.held[v] = frozenset(self.graph.near(v))
            self.size += len(found)
        return found

    __getitem__ = get


class LocalGraph:
    """vids: sorted; codes: of their labels, into names. The neighbours of the vertices from place first[k] on are in chunks[k]: places,
    list after list, with as many each as degree says. pair_counts: edges by labels of source and target."""

    def __init__(self, vids, codes, names, degree, first, chunks, pair_counts=(), loops=()):
        self.vids, self.codes, self.names, self.degree, self.chunks = vids, codes, names, degree, chunks
        self.first = [*first, len(vids)]
        self.start = np.cumsum(degree, dtype=np.int64) - degree
        for a, b in zip(self.first, self.first[1:]):
            if a < b:
                self.start[a:b] -= self.start[a]
        self.dense = bool(len(vids)) and int(vids[-1] - vids[0]) == len(vids) - 1
        order = np.argsort(codes, kind="stable")
        ends = np.cumsum(np.bincount(codes, minlength=len(names)))
        self.by_label: dict[str, np.ndarray] = {x: order[e - n : e] for x, e, n in zip(names, ends.tolist(), np.diff(ends, prepend=0).tolist())}
        self.rank = np.empty(len(vids), np.int32)  # of a place among those of its label
        for x in self.by_label.values():
            self.rank[x] = np.arange(len(x), dtype=np.int32)
        self.loops = np.isin(vids, np.asarray(loops, np.int64))
        self.pair_counts = Counter({k: n for k, n in dict(pair_counts).items() if n})
        self.adjacency = Neighbours(self)
        self._lists: dict[str, list[int]] = {}
        self._counts: OrderedDict[tuple[str, str], np.ndarray] = OrderedDict()
        self._pairs: OrderedDict[tuple[str, str], tuple[np.ndarray, np.ndarray]] = OrderedDict()

    def place(self, v: int) -> int:
        return v - int(self.vids[0]) if self.dense else int(np.searchsorted(self.vids, v))

    def near(self, v: int) -> list[int]:
        """The neighbours of a vertex, rising."""
        i = self.place(v)
        n = int(self.degree[i])
        if not n:
            return []
        s = int(self.start[i])
        return self.vids[self.chunks[bisect_right(self.first, i) - 1][s : s + n]].tolist()

    def label(self, v: int) -> str:
        return self.names[self.codes[self.place(v)]]

    def starts(self) -> list[int]:
        """The vertices with a neighbour, rising."""
        return self.vids[self.degree > 0].tolist()

    def _read(self, members: np.ndarray) -> Iterator[tuple[slice, np.ndarray, np.ndarray, np.ndarray]]:
        """Of members (places, rising) a part, where the lists of each begin and end, and the lists."""
        at = np.searchsorted(members, self.first).tolist()
        for k, (lo, hi) in enumerate(zip(at, at[1:])):
            for s in range(lo, hi, AT_ONCE):
                part = members[s : min(hi, s + AT_ONCE)]
                n = self.degree[part].astype(np.int64)
                ends = np.cumsum(n)
                if not ends[-1]:
                    continue
                yield slice(s, s + len(part)), ends - n, ends, self.chunks[k][np.arange(ends[-1]) + np.repeat(self.start[part] - ends + n, n)]

    def among(self, members: np.ndarray, flags: np.ndarray) -> np.ndarray:
        """How many neighbours of each are flagged."""
        out = np.zeros(len(members), np.int32)
        for part, heads, ends, near in self._read(members):
            total = np.concatenate([[0], np.cumsum(flags[near])])
            out[part] = total[ends] - total[heads]
        return out

    def index(self, p: PatternGraph, filters: tuple[str, ...]) -> None:
        """For the label pairs of a pattern: of each vertex of the first label the neighbours of the second. Kept for all queries of the
        process; a pattern whose pairs would take more than PAIR_BYTES is filtered over the whole lists."""
        ends = {(p.labels[x - 1], p.labels[y - 1]) for a, b in p.edges for x, y in ((a, b), (b, a))}
        needed = sorted(k for k in ends if k[0] in self.by_label and k[1] in self.by_label)
        if not BY_PAIR & set(filters) or not self.pair_counts or 4 * sum(self.pair_counts[k] + len(self.by_label[k[0]]) + 1 for k in needed) > PAIR_BYTES:
            return
        for label in {x for x, _ in needed}:
            others = [y for x, y in needed if x == label and (x, y) not in self._pairs]
            codes, members = [self.names.index(y) for y in others], self.by_label[label]
            counts, near = [np.zeros(len(members), np.int32) for _ in others], [[np.zeros(0, np.int32)] for _ in others]
            for part, heads, _, found in self._read(members) if others else ():
                theirs = self.codes[found]
                for c, n, kept in zip(codes, counts, near):
                    same = theirs == c
                    total = np.concatenate([[0], np.cumsum(same)])
                    n[part] = np.diff(total[np.append(heads, len(found))])
                    kept.append(self.rank[found[same]])
            for y, n, kept in zip(others, counts, near):
                self._pairs[label, y] = np.concatenate([[0], np.cumsum(n)]).astype(np.int32), np.concatenate(kept)
        for k in needed:
            self._pairs.move_to_end(k)
        while sum(x.nbytes for held in self._pairs.values() for x in held) > PAIR_BYTES and next(iter(self._pairs)) not in needed:
            self._pairs.popitem(last=False)

    def reached(self, label: str, other: str, asked: np.ndarray) -> np.ndarray:
        """Of the vertices of a label, how many neighbours each has among those of the other label that are asked for; both by rank, of a
        pair that is kept."""
        held = self._pairs[label, other]
        total = np.zeros(len(held[1]) + 1, np.int32)
        np.cumsum(asked[held[1]], out=total[1:])
        return np.diff(total[held[0]])

    def touching(self, label: str, other: str, asked: np.ndarray) -> np.ndarray:
        """Which vertices of a label have such a neighbour."""
        return self.reached(label, other, asked) > 0

    def ranked(self, label: str, members: np.ndarray) -> np.ndarray:
        out = np.zeros(len(self.by_label[label]), bool)
        out[self.rank[members]] = True
        return out

    def label_counts(self, label: str, other: str) -> np.ndarray:
        """For the vertices of a label, how many neighbours have the other one."""
        key = label, other
        if key in self._pairs:
            return np.diff(self._pairs[key][0])
        if key not in self._counts:
            self._counts[key] = self.among(self.by_label[label], self.codes == self.names.index(other))
            while len(self._counts) > 1 and sum(x.nbytes for x in self._counts.values()) > KEPT_BYTES:
                self._counts.popitem(last=False)
        return self._counts[key]

    def flags(self, members: np.ndarray) -> np.ndarray:
        out = np.zeros(len(self.vids), bool)
        out[members] = True
        return out

    def _listed(self, label: str, members: np.ndarray) -> list[int]:
        whole = self.by_label.get(label, members)
        if 8 * len(members) < len(whole):
            return self.vids[members].tolist()
        if label not in self._lists:
            self._lists[label] = self.vids[whole].tolist()
        # Numbers that are there already: making them anew took longer than the filters.
        return self._lists[label] if members is whole else list(compress(self._lists[label], self.ranked(label, members).tobytes()))

    def domains(self, p: PatternGraph, filters: tuple[str, ...] = (), allowed: dict[int, set] | None = None, until_ns: int | None = None) -> dict[int, list[int]]:
        """allowed: by vertex of the pattern, the only images it may have. Past until_ns on the clock of the process it gives up by OutOfTime."""
        nothing = np.zeros(0, np.int64)

        def watch():
            if until_ns is not None and time.perf_counter_ns() > until_ns:
                raise OutOfTime

        dom = {u: self.by_label.get(x, nothing) for u, x in enumerate(p.labels, 1)}
        for u in p.loops:
            dom[u] = dom[u][self.loops[dom[u]]]
        for u, only in (allowed or {}).items():
            dom[u] = dom[u][np.isin(self.vids[dom[u]], np.array(sorted(only), np.int64))]
        near = {u: sorted(p.neighbors(u)) for u in dom}
        for name in filters:
            if name == "degree":
                dom = {u: d[self.degree[d] >= len(near[u])] for u, d in dom.items()}
            elif name == "labels":
                for u, label in enumerate(p.labels, 1):
                    for x, k in Counter(p.labels[w - 1] for w in near[u]).items():
                        watch()
                        if x not in self.by_label or not len(dom[u]):
                            dom[u] = nothing
                        else:
                            dom[u] = dom[u][self.label_counts(label, x)[self.rank[dom[u]]] >= k]
            elif name in ("arcs", "tree"):
                links = [(a, b) for x, y in p.edges for a, b in ((x, y), (y, x))] * 2 if name == "arcs" else [(a, c) for a, c in reversed(p.bfs_tree())] + [(c, a) for a, c in p.bfs_tree()]
                by_pair = all((p.labels[a - 1], p.labels[b - 1]) in self._pairs for a, b in links)
                kept = {u: self.ranked(p.labels[u - 1], dom[u]) for u in {a for a, _ in links}} if by_pair else {}
                held: dict = {}  # of a link, the images of its other end when it was last followed
                for a, b in links:
                    watch()
                    if not by_pair:
                        dom[a] = dom[a][self.among(dom[a], self.flags(dom[b])) > 0]
                    elif held.get((a, b)) is not kept[b]:  # else all that is left of a touches them
                        held[a, b] = kept[b]
                        left = kept[a] & self.touching(p.labels[a - 1], p.labels[b - 1], kept[b])
                        if (left != kept[a]).any():
                            kept[a] = left
                dom.update({u: self.by_label[p.labels[u - 1]][k] for u, k in kept.items()})
            elif name == "bipartite":
                size = None
                while size != (size := sum(map(len, dom.values()))):  # until a round drops nothing
                    before = dict(dom)
                    sets = {}
                    for u in dom:
                        met: dict[int, np.ndarray] = {}  # by neighbour, how many images it has next to each of dom[u]
                        for w in near[u]:  # without a partner for each there is no matching, with one neighbour it is all of it
                            watch()
                            x, y = p.labels[u - 1], p.labels[w - 1]
                            met[w] = self.reached(x, y, self.ranked(y, before[w]))[self.rank[dom[u]]] if (x, y) in self._pairs else self.among(dom[u], self.flags(before[w]))
                            some = met[w] > 0
                            dom[u], met = dom[u][some], {k: n[some] for k, n in met.items()}
                        keep = np.ones(len(dom[u]), bool)
                        for y, k in Counter(p.labels[w - 1] for w in near[u]).items():  # images of different labels differ
                            watch()
                            alike = [w for w in near[u] if p.labels[w - 1] == y]
                            if k == 1:
                                continue
                            # Where the scarcest has one, the next two and so on, they are given out in that order.
                            sure = (np.sort([met[w] for w in alike], 0) > np.arange(k)[:, None]).all(0)
                            for w in alike:
                                if w not in sets and not sure.all():
                                    sets[w] = set(self.vids[before[w]].tolist())
                            for j, i in enumerate(np.flatnonzero(keep & ~sure).tolist()):
                                if not j & 63:
                                    watch()
                                v = int(self.vids[dom[u][i]])
                                keep[i] = _saturates(alike, {w: sorted(self.adjacency.get(v) & sets[w]) for w in alike})
                        dom[u] = dom[u][keep]
            else:
                raise ValueError(f"no filter {name}")
        watch()
        return {u: self._listed(p.labels[u - 1], d) for u, d in dom.items()}

    def order(self, p: PatternGraph, name: str, dom: dict[int, list[int]]) -> tuple[int, ...]:
        counts = {u: len(d) for u, d in dom.items()}
        if name == "given":
            return ordering.given(p)
        if name == "smallest":
            return ordering.smallest_domain_first(p, counts)
        if name == "join_size":
            sel = {(a, b): n / max(1, len(self.by_label.get(a, ())) * len(self.by_label.get(b, ()))) for (a, b), n in self.pair_counts.items()}
            return ordering.join_size_greedy(p, counts, sel)
        if name == "tree_path":
            return ordering.tree_path_first(p, counts, self.pair_counts)
        if name == "dense":
            return ordering.dense_then_tree_then_leaf(p)
        if name == "rare_edge":
            return ordering.rare_edge_spanning(p, self.pair_counts)
        raise ValueError(f"no order {name}")
