"""Depth-first search of one work unit with an explicit stack, in three modes.

plain       looks only at the next position's candidates and learns nothing
no_lookup   also fails as soon as any unmapped vertex has no candidate
learned     keeps a reason for each exhausted fruitless assignment and skips what it explains

A reason is recorded only for exhausted subtrees: a stop by time or calls leaves no trace,
while a stop by the cap always has a report in each open subtree.
"""

from __future__ import annotations

import time
from bisect import bisect_left
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

from branchwise.functions.reasons import fold_reason, prefix_length, reason_reuse, reason_wipeout

MODES = ("plain", "no_lookup", "learned")


@dataclass
class SlotTable:
    """Nogoods by (position, vertex): one each, or with store="set" all of them."""

    match: str = "prefix"
    policy: str = "last"
    store: str = "slots"
    slots: dict = field(default_factory=dict)
    bits: dict = field(default_factory=dict)
    writes: int = 0
    overwrites: int = 0
    hits: int = 0

    def put(self, pos: int, vid: int, reason: int, ids: list[int], asg: list[int]) -> None:
        size = prefix_length(reason, pos)
        bits = self.bits.get((reason, pos))
        if bits is None:
            bits = self.bits[reason, pos] = [i for i in range(pos) if reason >> i & 1]
        values = tuple([asg[i] for i in bits])
        entry = (ids[size], size, reason, values)
        held = self.slots.get((pos, vid))
        self.writes += 1
        if self.store == "set":
            self.slots.setdefault((pos, vid), []).append(entry)
            return
        if held is not None:
            if self.policy == "smallest" and held[0][2].bit_count() < reason.bit_count():
                return
            self.overwrites += 1
        self.slots[pos, vid] = [entry]

    def get(self, pos: int, vid: int, ids: list[int], asg: list[int]) -> int | None:
        """The reason of an entry that explains the assignment extended by vid, if there is one."""
        for number, size, reason, values in self.slots.get((pos, vid), ()):
            if self.match == "prefix":
                hit = ids[size] == number
            else:
                hit = all(asg[i] == v for i, v in zip((i for i in range(pos) if reason >> i & 1), values))
            if hit:
                self.hits += 1
                return reason
        return None

    def clear(self) -> None:
        self.slots.clear()

    def __len__(self) -> int:
        return sum(map(len, self.slots.values()))

    def export(self) -> list[tuple]:
        """(pos, vid, reason, prefix_len, prefix_id, vals) of every entry."""
        return [(p, v, r, n, i, list(x)) for (p, v), entries in self.slots.items() for i, n, r, x in entries]


@dataclass
class Result:
    rows: list[tuple[int, ...]]
    stats: dict
    slots: SlotTable
    trace: list[tuple]


#: Rows that a search holds before it hands them on, and numbers in the candidate lists it keeps to be met with once.
BATCH, MET = 4096, 1_000_000
#: A condition on several mapped positions: their bits, and a test of the assignment (by position).
Check = tuple[int, Callable[[list[int]], bool]]


def search_unit(nbr_mask: list[int], domains: list[list[int]], adjacency: dict, **options) -> Result:
    """search_rows with all its rows in one list: for small results."""
    rows: list[tuple[int, ...]] = []
    search = search_rows(nbr_mask, domains, adjacency, **options)
    while True:
        try:
            rows += next(search)
        except StopIteration as done:
            done.value.rows = rows
            return done.value


def _meet(candidates: list[int], near) -> list[int]:
    """The candidates (sorted) among the neighbours (a set), from the smaller side."""
    if len(near) * 8 < len(candidates):
        return sorted(c for c in near if _has(candidates, c))
    return [c for c in candidates if c in near]


class Meets:
    """_meet for lists with numbers, of which the first ones are domains: one that is asked for often is kept as a set."""

    def __init__(self, domains: list[list[int]] = ()):
        self.asked, self.sets = [0] * len(domains), [None] * len(domains)

    def __call__(self, number: int, candidates: list[int], near) -> list[int]:
        if number < len(self.asked) and len(near) * 8 < len(candidates):
            whole = self.sets[number]
            if whole is None:
                self.asked[number] += 1
                if self.asked[number] * 512 > len(candidates):
                    whole = self.sets[number] = frozenset(candidates)
            if whole is not None:
                return sorted(near & whole)
        return _meet(candidates, near)


def search_rows(nbr_mask: list[int], domains: list[list[int]], adjacency: dict, *, mode: str = "learned", match: str = "prefix", store: str = "slots", policy: str = "last",
                lookahead: str | None = None, wipeout_choice: str = "first", backjump: bool = False, infeasible_stop: bool = False, injective: bool = True, cap: int | None = None,
                deadline_ns: int | None = None, checks: tuple[Check, ...] = (), trace: bool = False, drop_current: bool = False) -> Iterator[list[tuple[int, ...]]]:
    """Yields batches of embeddings and returns a Result without rows. domains: sorted candidates by position; adjacency:
    vertex -> set of neighbours. A check is made when its last position is mapped; its failure is a reason of its own,
    all the positions it reads. drop_current reproduces a known wrong reading of the reuse reason and is for tests only."""
    n, table, log = len(nbr_mask), SlotTable(match, policy, store), []
    every = (lookahead or ("next" if mode == "plain" else "all")) == "all"
    learn = mode == "learned"
    rows: list[tuple[int, ...]] = []
    calls = f_wipeout = f_reuse = f_known = f_child = f_check = 0
    slots, by_prefix = table.slots, match == "prefix" and store != "set"
    later = [[i for i in range(k + 1, n) if nbr_mask[k] >> i & 1] for k in range(n)]
    # Lists have numbers: a list is met with the neighbours of a vertex once, for all assignments that agree on them.
    numbers, met, fresh, held, meet = [list(range(n))], {}, n, 0, Meets(domains)
    due = [[(bits, test) for bits, test in checks if bits.bit_length() == i + 1] for i in range(n)]
    n_found = 0
    asg, holder, ids = [0] * n, {}, [0] * (n + 1)
    cand, union, found, at = [list(domains)], [0] * (n + 1), [False] * (n + 1), [0] * (n + 1)
    began, capped, dnf, stop, last = time.perf_counter_ns(), False, False, False, 0
    empty: frozenset = frozenset()
    level, entering = 0, True
    while level >= 0 and not stop:
        done = None  # (found, reason) once the current level is settled
        if entering:
            entering = False
            ids[level] = calls
            calls += 1
            union[level], found[level], at[level] = 0, False, 0
            if deadline_ns is not None and not calls & 255 and time.perf_counter_ns() - began > deadline_ns:
                dnf = True
                break
            if level == n:
                rows.append(tuple(asg))
                n_found += 1
                done = (True, 0)
                if len(rows) >= BATCH:
                    yield rows
                    rows = []
                if cap is not None and n_found >= cap:
                    capped = stop = True
            else:
                narrowed = later[level - 1] if level else range(n)
                if level:
                    new, number = cand[level - 1], numbers[level - 1]
                    if narrowed:
                        new, number, v, near = list(new), list(number), asg[level - 1], None
                        for i in narrowed:
                            one = met.get((number[i], v))
                            if one is None:
                                if near is None:
                                    near = adjacency.get(v, empty)
                                fresh += 1
                                one = meet(number[i], new[i], near), fresh
                                held += len(one[0]) + 1
                                if held > MET:
                                    met.clear()
                                    held = 0
                                met[number[i], v] = one
                            new[i], number[i] = one
                    del cand[level:], numbers[level:]
                    cand.append(new)
                    numbers.append(number)
                if every:  # what was not narrowed had a candidate before
                    void = [i for i in narrowed if not cand[level][i]]
                    if void:
                        mapped = (1 << level) - 1
                        i = void[0] if wipeout_choice == "first" else min(void, key=lambda i: (nbr_mask[i] & mapped).bit_count())
                        f_wipeout += 1
                        done = (False, reason_wipeout(nbr_mask[i], mapped))
        if done is None:
            options, i = cand[level][level], at[level]
            jump = backjump and union[level] and not found[level] and i and not last >> level & 1
            while i < len(options) and not jump:
                v = options[i]
                i += 1
                if injective and v in holder:
                    f_reuse += 1
                    last = 1 << holder[v] if drop_current else reason_reuse(holder[v], level)
                    union[level] |= last
                    continue
                if not learn or (entry := slots.get((level, v))) is None:
                    known = None
                elif by_prefix:
                    known = entry[0][2] if ids[entry[0][1]] == entry[0][0] else None
                    table.hits += known is not None
                else:
                    known = table.get(level, v, ids, asg)
                if known is not None:
                    f_known += 1
                    last = known
                    union[level] |= known
                    if backjump and not found[level] and not known >> level & 1:
                        break
                    continue
                asg[level] = v
                if due[level] and (failed := next((bits for bits, test in due[level] if not test(asg)), 0)):
                    f_check += 1
                    last = failed
                    union[level] |= failed
                    continue
                if level == n - 1 and not trace:  # an embedding, which is a call, without a level of its own
                    calls += 1
                    if deadline_ns is not None and not calls & 255 and time.perf_counter_ns() - began > deadline_ns:
                        dnf = True
                        break
                    rows.append(tuple(asg))
                    n_found += 1
                    found[level] = True
                    if len(rows) >= BATCH:
                        yield rows
                        rows = []
                    if cap is not None and n_found >= cap:
                        capped = stop = True
                        break
                    continue
                if injective:
                    holder[v] = level
                at[level] = i
                level, entering = level + 1, True
                break
            if entering:
                continue
            if dnf:
                break
            mapped = (1 << level) - 1
            if found[level]:
                done = (True, 0)
            elif jump or backjump and union[level] and not last >> level & 1:
                done = (False, last & mapped)
            elif not cand[level][level]:
                f_wipeout += 1
                done = (False, reason_wipeout(nbr_mask[level], mapped))
            else:
                done = (False, fold_reason(union[level], level, nbr_mask[level], mapped))
        good, reason = done
        if trace:
            log.append((ids[level], level, tuple(asg[:level]), good, reason))
        if not good and infeasible_stop and reason == 0:
            stop = True
        if level:
            if not good and learn:
                table.put(level - 1, asg[level - 1], reason, ids, asg)
            if injective:
                del holder[asg[level - 1]]
        level -= 1
        if level >= 0:
            if good:
                found[level] = True
            else:
                f_child += 1
                last = reason
                union[level] |= reason
    if rows:
        yield rows
    count = {"search_calls": calls, "f_wipeout": f_wipeout, "f_reuse": f_reuse, "f_known": f_known, "f_child": f_child, "f_check": f_check, "n_found": n_found, "capped": capped, "dnf": dnf, "slot_writes": table.writes, "slot_overwrites": table.overwrites, "slot_hits": table.hits, "slots_used": len(table), "elapsed_ns": time.perf_counter_ns() - began}
    return Result([], count, table, log)


def is_fruitless(nbr_mask: list[int], domains: list[list[int]], adjacency: dict, partial: dict[int, int]) -> bool:
    """Whether no complete embedding extends the given positions (an exhaustive search, for tests)."""
    held = [[partial[i]] if i in partial and _has(d, partial[i]) else [] if i in partial else d for i, d in enumerate(domains)]
    return not search_unit(nbr_mask, held, adjacency, mode="plain", cap=1).rows


def _has(values: list[int], v: int) -> bool:
    i = bisect_left(values, v)
    return i < len(values) and values[i] == v
