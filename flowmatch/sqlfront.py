"""A text front end: ``MATCH pattern [WHERE tests] [WITHIN n unit] [SEMANTICS name] [RETURN columns] [LIMIT n]``.

Tests are joined by AND.  ``x.ts < y.ts`` orders two edges in time; any other test names one edge (``x.weight > 40``,
``x.label = 'click'``) and reaches the scan as its predicate.  The semantics are iso (default) and homo, symmetric_iso for one embedding
of each orbit.  The answer is a DataFrame, and with ``view`` a temporary view that further SQL can read.
"""

from __future__ import annotations

import re
from dataclasses import dataclass, replace

from pyspark.sql import DataFrame

from flowmatch.operators.enumeration import Semantics, enumerate_all
from flowmatch.plans.pattern import Pattern, parse_pattern, symmetry_breaking
from flowmatch.plans.planner import compile_plan
from flowmatch.sources.snapshots import DAY, HOUR, MINUTE

UNITS = {"minute": MINUTE, "hour": HOUR, "day": DAY, "second": 1_000_000}
_PART = re.compile(r"\b(MATCH|WHERE|WITHIN|SEMANTICS|RETURN|LIMIT)\b", re.I)
_ORDER = re.compile(r"^\s*(\w+)\.ts\s*<\s*(\w+)\.ts\s*$", re.I)


@dataclass(frozen=True)
class Match:
    pattern: Pattern
    semantics: Semantics
    columns: tuple[str, ...] = ()
    limit: int | None = None


def parse(text: str) -> Match:
    pieces = _PART.split(text.strip().rstrip(";"))
    if pieces[0].strip() or len(pieces) < 3:
        raise ValueError("a statement starts with MATCH")
    parts: dict[str, str] = {}
    for word, body in zip(pieces[1::2], pieces[2::2]):
        if word.upper() in parts:
            raise ValueError(f"{word} is there twice")
        parts[word.upper()] = body.strip()
    pattern = parse_pattern(parts["MATCH"])
    names, pairs, tests = {e.name for e in pattern.edges}, [], {}
    for test in re.split(r"\s+AND\s+", parts.get("WHERE", ""), flags=re.I) if parts.get("WHERE") else []:
        if order := _ORDER.match(test):
            if not {order[1], order[2]} <= names:
                raise ValueError(f"no such edge in: {test}")
            pairs.append((order[1], order[2]))
            continue
        used = {x for x in re.findall(r"\b(\w+)\.\w+", re.sub(r"'[^']*'", "", test))}
        if len(used) != 1 or not used <= names:
            raise ValueError(f"a test names one edge of the pattern: {test}")
        edge = used.pop()
        tests.setdefault(edge, []).append(re.sub(rf"\b{edge}\.", "", test))
    pattern = replace(pattern, edges=tuple(replace(e, where=" AND ".join(f"({t})" for t in tests[e.name])) if e.name in tests else e for e in pattern.edges))
    within = None
    if "WITHIN" in parts:
        span = re.fullmatch(r"(\d+)\s*(second|minute|hour|day)s?", parts["WITHIN"], re.I)
        if not span:
            raise ValueError(f"not a span of time: {parts['WITHIN']}")
        within = int(span[1]) * UNITS[span[2].lower()]
    kind = parts.get("SEMANTICS", "iso").lower()
    if kind not in ("iso", "homo", "symmetric_iso"):
        raise ValueError("semantics are iso, homo and symmetric_iso")
    semantics = Semantics(kind != "homo", tuple(pairs), True, within, tuple(symmetry_breaking(pattern)) if kind == "symmetric_iso" else ())
    columns = tuple(c.strip() for c in parts["RETURN"].split(",")) if "RETURN" in parts else ()
    return Match(pattern, semantics, columns, int(parts["LIMIT"]) if "LIMIT" in parts else None)


def bind(found: Match, edges: DataFrame) -> None:
    """Rejects tests on columns that the edges lack."""
    for e in found.pattern.edges:
        if e.where:
            edges.where(e.where)  # analysed, not run


def match(edges: DataFrame, text: str, view: str | None = None) -> DataFrame:
    found = parse(text)
    bind(found, edges)
    rows = enumerate_all(edges, found.pattern, found.semantics, compile_plan(found.pattern, profile=found.semantics.profile), limit=found.limit)
    if found.columns:
        known = {v.name: f"v_{v.name}" for v in found.pattern.vertices} | {e.name: f"e_{e.name}" for e in found.pattern.edges}
        if missing := [c for c in found.columns if c not in known]:
            raise ValueError(f"not in the pattern: {', '.join(missing)}")
        rows = rows.select(*[known[c] for c in found.columns])
    if view:
        rows.createOrReplaceTempView(view)
    return rows
