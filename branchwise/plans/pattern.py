"""Pattern graphs: labels, edges, numbering, structure and text form."""

from __future__ import annotations

import re
from dataclasses import dataclass
from itertools import permutations


class PatternError(ValueError):
    pass


@dataclass(frozen=True)
class PatternGraph:
    """Vertices are numbered 1..n; edges are pairs of numbers, undirected. An edge from a vertex to itself is kept in
    ``loops``: it asks for a data vertex with such an edge."""

    labels: tuple[str, ...]
    edges: tuple[tuple[int, int], ...]
    loops: tuple[int, ...] = ()

    def __post_init__(self):
        n = len(self.labels)
        seen = set()
        for a, b in (*self.edges, *((u, u) for u in self.loops)):
            if not (1 <= a <= n and 1 <= b <= n):
                raise PatternError(f"edge {(a, b)} does not join two of {n} vertices")
            seen.add((min(a, b), max(a, b)))
        object.__setattr__(self, "labels", tuple(map(str, self.labels)))
        object.__setattr__(self, "edges", tuple(sorted((a, b) for a, b in seen if a != b)))
        object.__setattr__(self, "loops", tuple(sorted(a for a, b in seen if a == b)))

    @property
    def n(self) -> int:
        return len(self.labels)

    @classmethod
    def from_text(cls, text: str) -> PatternGraph:
        """Chains such as ``(a:X)-(b:Y)-(c:Z), (a)-(c)``; a vertex is numbered where it first appears."""
        number, labels, edges = {}, {}, []
        for chain in text.split(","):
            before = None
            for name, label in re.findall(r"\(\s*(\w+)\s*(?::\s*([^)]*?)\s*)?\)", chain):
                number.setdefault(name, len(number) + 1)
                if label:
                    labels[name] = label
                if before:
                    edges.append((number[before], number[name]))
                before = name
        if missing := [x for x in number if x not in labels]:
            raise PatternError(f"no label for {missing}")
        return cls(tuple(labels[x] for x in number), tuple(edges))

    @classmethod
    def from_row(cls, row) -> PatternGraph:
        return cls(tuple(v["label"] for v in sorted(row["vertices"], key=lambda v: v["u"])), tuple((e["a"], e["b"]) for e in row["edges"]))

    def to_row(self, query_id: int, order: tuple[int, ...] | None = None) -> tuple:
        return query_id, self.n, [(i + 1, x) for i, x in enumerate(self.labels)], [*self.edges, *((u, u) for u in self.loops)], list(order or range(1, self.n + 1))

    def neighbors(self, u: int) -> set[int]:
        return {b for a, b in self.edges if a == u} | {a for a, b in self.edges if b == u}

    def nbr_mask(self, order: tuple[int, ...] | None = None) -> list[int]:
        """Per position of the order: bits of the positions of its neighbours."""
        order = order or tuple(range(1, self.n + 1))
        pos = {u: i for i, u in enumerate(order)}
        return [sum(1 << pos[w] for w in self.neighbors(u)) for u in order]

    def is_connected(self) -> bool:
        if not self.n:
            return True
        seen, todo = {1}, [1]
        while todo:
            for w in self.neighbors(todo.pop()) - seen:
                seen.add(w)
                todo.append(w)
        return len(seen) == self.n

    def core2(self) -> set[int]:
        """Vertices left after peeling those of degree 1 or 0 again and again."""
        left = set(range(1, self.n + 1))
        while gone := {u for u in left if len(self.neighbors(u) & left) < 2}:
            left -= gone
        return left

    def bfs_tree(self, root: int = 1) -> list[tuple[int, int]]:
        """(parent, child) pairs in breadth-first order; further components hang nowhere."""
        tree, seen, todo = [], {root}, [root]
        while todo:
            u = todo.pop(0)
            for w in sorted(self.neighbors(u) - seen):
                seen.add(w)
                tree.append((u, w))
                todo.append(w)
        return tree

    def automorphisms(self) -> list[tuple[int, ...]]:
        """Renumberings that keep labels and edges; meant for small patterns."""
        edges, loops = set(self.edges), set(self.loops)
        by_label = [tuple(i for i, x in enumerate(self.labels) if x == y and (i + 1 in loops) == (k + 1 in loops)) for k, y in enumerate(self.labels)]
        return [p for p in permutations(range(self.n)) if all(p[i] in by_label[i] for i in range(self.n)) and all((min(p[a - 1], p[b - 1]) + 1, max(p[a - 1], p[b - 1]) + 1) in edges for a, b in edges)]


QUERY_SET = "query_id int, n_vertices int, vertices array<struct<u: int, label: string>>, edges array<struct<a: int, b: int>>, match_order array<int>"
