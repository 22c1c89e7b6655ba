"""SQL for DuckDB that states what a pattern query must return: plain self-joins over a view, written apart from the plans."""

from __future__ import annotations


from flowmatch.plans.pattern import Pattern
from flowmatch.sources.views import SQL


def _labels(alias: str, labels: tuple[str, ...]) -> str:
    tests = [f"starts_with({alias}.label, '{x[:-1]}')" if x.endswith("*") else f"{alias}.label = '{x}'" for x in labels]
    return "(" + " or ".join(tests) + ")"


def columns(pattern: Pattern) -> str:
    """The vertex and edge columns of embeddings, over tables named by query edge."""
    at = _places(pattern)
    return ", ".join([f"{at[v.name]} as v_{v.name}" for v in pattern.vertices] + [f"{e.name}.edge_id as e_{e.name}" for e in pattern.edges])


def _joined(pattern: Pattern) -> list:
    """The edges in an order in which each touches those before it, cycles closed at once."""
    order, left, bound = [], list(pattern.edges), set()
    while left:
        e = next((x for x in left if x.ends() <= bound), None) or next((x for x in left if x.ends() & bound), left[0])
        left.remove(e)
        order.append(e)
        bound |= e.ends()
    return order


def _places(pattern: Pattern) -> dict[str, str]:
    at: dict[str, str] = {}
    for e in _joined(pattern):
        at.setdefault(e.src, f"{e.name}.src")
        at.setdefault(e.dst, f"{e.name}.dst")
    return at


def stepwise(pattern: Pattern, view: str, injective: bool = True) -> str:
    """All embeddings, one materialized join after another in pattern order: for patterns too large for a join reorderer."""
    ctes, have, done, last = [], [], [], None
    for k, e in enumerate(_joined(pattern)):
        fresh = [v for v in dict.fromkeys((e.src, e.dst)) if v not in have]
        end = lambda v: "c.src" if v == e.src else "c.dst"  # noqa: E731, B023
        tests = [_labels("c", e.labels)] if e.labels else []
        tests += [f"{end(v)} = p.v_{v}" for v in dict.fromkeys((e.src, e.dst)) if v in have]
        if injective:
            tests += [f"{end(v)} <> p.v_{w}" for v in fresh for w in have] + (["c.src <> c.dst"] if len(fresh) == 2 else [])
            tests += [f"c.edge_id <> p.e_{d}" for d in done if pattern.edge(d).ends() == e.ends()]
        new = ", ".join([*[f"{end(v)} as v_{v}" for v in fresh], f"c.edge_id as e_{e.name}"])
        source = f"p.*, {new} from step{k - 1} p join g c" if last is not None else f"{new} from g c"
        ctes.append(f"step{k} as materialized (select {source} {'on' if last is not None else 'where'} {' and '.join(tests) or 'true'})")
        last, have, done = k, [*have, *fresh], [*done, e.name]
    names = ", ".join([f"v_{v.name}" for v in pattern.vertices] + [f"e_{e.name}" for e in pattern.edges])
    return f"with g as materialized ({SQL[view]}), {', '.join(ctes)} select {names} from step{last}"


def embeddings(pattern: Pattern, view: str, injective: bool = True, pairs=(), within: int | None = None, symmetry=(), select: str | None = None, extra: str = "", source: str | None = None, prefix: str | None = None) -> str:
    """All embeddings, by joins in a connected order over the filtered candidates of each query edge, so no optimizer is needed.

    ``select`` replaces the vertex and edge columns, ``source`` the view by a name of a WITH clause, which ``prefix`` may hold.
    """
    at, ctes, joins, bound, done = _places(pattern), [], [], [], []
    for e in _joined(pattern):
        tests = [_labels("t", e.labels)] if e.labels else []
        if e.where:
            tests.append(f"t.{e.where}")
        if e.src == e.dst:
            tests.append("t.src = t.dst")
        ctes.append(f"c_{e.name} as materialized (select * from {source or 'g'} t where {' and '.join(tests) or 'true'})")
        on, fresh = [], []
        for end, v in dict.fromkeys((("src", e.src), ("dst", e.dst))):
            if v in bound:
                on.append(f"{e.name}.{end} = {at[v]}")
            elif v not in fresh:
                fresh.append(v)
        for v in fresh:
            on += [f"{at[v]} <> {at[w]}" for w in bound] if injective else []
            bound.append(v)
        done.append(e.name)
        if injective:
            on += [f"{e.name}.edge_id <> {d}.edge_id" for d in done[:-1] if pattern.edge(d).ends() == e.ends()]
        on += [f"{a}.ts < {b}.ts" for a, b in pairs if e.name in (a, b) and a in done and b in done]
        on += [f"{at[a]} < {at[b]}" for a, b in symmetry if a in bound and b in bound and {a, b} & set(fresh)]
        if within is not None:
            on += [f"abs({e.name}.ts - {d}.ts) <= {within}" for d in done[:-1]]
        joins.append((f"c_{e.name} {e.name}", on))
    first, where = joins[0][0], joins[0][1]
    tables = first + "".join(f" join {t} on {' and '.join(on) or 'true'}" for t, on in joins[1:])
    head = f"{prefix}, " if prefix else "with " if source else f"with g as materialized ({SQL[view]}), "
    return f"{head}{', '.join(ctes)} select {select or columns(pattern)} from {tables} where {' and '.join(where) or 'true'}{extra}"
