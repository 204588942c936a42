"""ANSI SQL of patterns over views ``v(vid, label)`` and ``le(src, dst, sl, dl)``, the edges in both directions with their labels."""

from __future__ import annotations

from .pattern import PatternGraph

#: Views that every graph's SQL ends with; views e(src, dst) and v(vid, label) come before them.
LABELLED = "le AS MATERIALIZED (SELECT src, dst, x.label AS sl, y.label AS dl FROM e JOIN v x ON x.vid = src JOIN v y ON y.vid = dst)"


def quoted(x: str) -> str:
    return "'" + str(x).replace("'", "''") + "'"


def connected_order(p: PatternGraph) -> tuple[int, ...]:
    """The least vertex next that an edge ties to those before, as long as there is one."""
    out: list[int] = []
    while len(out) < p.n:
        left = [u for u in range(1, p.n + 1) if u not in out]
        out.append(next((u for u in left if p.neighbors(u) & set(out)), left[0]))
    return tuple(out)


def to_sql(p: PatternGraph, order_limit: int | None = None, injective: bool = True, select: str | None = None, order: tuple[int, ...] | None = None) -> str:
    """One materialised step per vertex, each an equi-join of the step before with edges of two given labels, so that
    the text runs well whatever a planner makes of it. select may name m1..mn."""
    steps, done = [], []
    for k, u in enumerate(order or connected_order(p)):
        back = [w for w in done if w in p.neighbors(u)]
        edges = lambda w: f"(SELECT src, dst FROM le WHERE sl = {quoted(p.labels[w - 1])} AND dl = {quoted(p.labels[u - 1])})"  # noqa: B023, E731
        own = f"(SELECT vid FROM v WHERE label = {quoted(p.labels[u - 1])}{' AND vid IN (SELECT vid FROM loops)' if u in p.loops else ''})"
        before = "".join(f"s.m{w}, " for w in done)
        if not done:
            sql = f"SELECT vid AS m{u} FROM {own} o"
        elif not back:
            sql = f"SELECT {before}o.vid AS m{u} FROM s{k} s CROSS JOIN {own} o"
        else:
            sql = f"SELECT {before}x{back[0]}.dst AS m{u} FROM s{k} s JOIN {edges(back[0])} x{back[0]} ON x{back[0]}.src = s.m{back[0]}"
            sql += "".join(f" JOIN {edges(w)} x{w} ON x{w}.src = s.m{w} AND x{w}.dst = x{back[0]}.dst" for w in back[1:])
            if u in p.loops:
                sql += f" JOIN {own} o ON o.vid = x{back[0]}.dst"
        new = f"x{back[0]}.dst" if back else "o.vid"
        apart = [w for w in done if injective and p.labels[w - 1] == p.labels[u - 1] and w not in back]
        if apart:
            sql += " WHERE " + " AND ".join(f"s.m{w} <> {new}" for w in apart)
        steps.append(f"s{k + 1} AS MATERIALIZED ({sql})")
        done.append(u)
    names = ", ".join(f"m{i}" for i in range(1, p.n + 1))
    if not steps:
        return f"SELECT {select or '1 AS nothing'}"
    out = f"SELECT {select or names} FROM (WITH {', '.join(steps)} SELECT {names} FROM s{p.n}) AS found"
    return out if order_limit is None else out + f" ORDER BY {names} LIMIT {order_limit}"


def brute_force_sql(p: PatternGraph, injective: bool = True) -> str:
    """The definition itself: the product of all label domains, with every condition as a filter. For small graphs and tests."""
    where = [f"v{i}.label = {quoted(x)}" for i, x in enumerate(p.labels, 1)]
    where += [f"EXISTS (SELECT 1 FROM e WHERE e.src = v{a}.vid AND e.dst = v{b}.vid)" for a, b in p.edges]
    where += [f"v{u}.vid IN (SELECT vid FROM loops)" for u in p.loops]
    if injective:
        where += [f"v{i}.vid <> v{j}.vid" for i in range(1, p.n + 1) for j in range(i + 1, p.n + 1)]
    return f"SELECT {', '.join(f'v{i}.vid AS m{i}' for i in range(1, p.n + 1))} FROM {', '.join(f'v v{i}' for i in range(1, p.n + 1))} WHERE {' AND '.join(where)}"
