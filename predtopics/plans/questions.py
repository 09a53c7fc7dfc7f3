"""Query graphs as questions in English."""

from __future__ import annotations

import re

from .patterns import QueryGraph


def spoken(name: str) -> str:
    return re.sub(r"[_\W]+", " ", re.sub(r"([a-z])([A-Z])", r"\1 \2", name.lstrip("?"))).strip().lower()


def listed(items: list[str]) -> str:
    if len(items) < 2:
        return "".join(items)
    return ", ".join(items[:-1]) + " and " + items[-1]


def to_question(q: QueryGraph) -> str:
    """What are the A, B and C of a D? D is the variable in most patterns; filters are told behind."""
    if not q.patterns:
        return "what is there?"
    often: dict[str, int] = {}
    for x in q.patterns:
        for v in x.variables():
            often[v] = often.get(v, 0) + 1
    subject = max(sorted(often), key=lambda v: often[v])
    things = list(dict.fromkeys(spoken(x.p) for x in q.patterns))
    name = spoken(dict(q.types).get(subject, subject))
    article = "an" if name[:1] in "aeiou" else "a"
    verb = "are" if len(things) > 1 else "is"
    told = {"=": "is", "!=": "is not", "<": "is below", "<=": "is at most", ">": "is above", ">=": "is at least"}
    where = listed([f"{spoken(f.left)} {told[f.op]} {spoken(f.right) if f.right.startswith('?') else f.right}" for f in q.filters])
    return f"what {verb} the {listed(things)} of {article} {name}{' where ' + where if where else ''}?"
