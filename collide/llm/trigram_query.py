"""Boolean trigram queries that every match of a regular expression satisfies.

The expression's syntax tree is walked once. A part either stands for a few known strings or for unknown text; known
strings of neighbouring parts are joined, and where they end their trigrams are required. A query is a trigram, True (any
text may match), ("and", parts) or ("or", parts). Text and strings are compared in lower case.
"""

from __future__ import annotations

from typing import Any

from re import _constants as kinds
from re import _parser as syntax

#: More alternatives than this are treated as unknown text, which only weakens the query.
ALTERNATIVES = 64

Query = Any


def all_of(parts: list[Query]) -> Query:
    flat: list[Query] = []
    for p in parts:
        if p is True:
            continue
        flat += list(p[1]) if isinstance(p, tuple) and p[0] == "and" else [p]
    flat = list(dict.fromkeys(flat))
    return True if not flat else flat[0] if len(flat) == 1 else ("and", tuple(flat))


def any_of(parts: list[Query]) -> Query:
    if any(p is True for p in parts):
        return True
    flat = list(dict.fromkeys(parts))
    return flat[0] if len(flat) == 1 else ("or", tuple(flat))


def strings_query(strings: set[str]) -> Query:
    """Any of the strings occurs."""
    return any_of([all_of([s[i : i + 3] for i in range(len(s) - 2)]) for s in sorted(strings)])


def _items(tree) -> list[tuple[set[str] | None, Query]]:
    """(known strings or None, query) of each part of a sequence."""
    out: list[tuple[set[str] | None, Query]] = []
    for kind, value in tree:
        if kind is kinds.LITERAL:
            out.append(({chr(value).lower()}, True))
        elif kind is kinds.SUBPATTERN:
            out += _items(value[3])
        elif kind is kinds.BRANCH:
            branches = [_whole(x) for x in value[1]]
            strings = [b[0] for b in branches]
            known = set().union(*strings) if all(s is not None for s in strings) else None
            if known is not None and len(known) > ALTERNATIVES:
                known = None
            out.append((known, any_of([_required(*b) for b in branches])))
        elif kind is kinds.IN:
            chars: set[str] | None = set()
            for k, v in value:
                if k is kinds.LITERAL and chars is not None:
                    chars.add(chr(v).lower())
                elif k is kinds.RANGE and chars is not None and v[1] - v[0] < 8:
                    chars |= {chr(c).lower() for c in range(v[0], v[1] + 1)}
                else:
                    chars = None
            out.append((chars if chars is not None and len(chars) <= 8 else None, True))
        elif kind in (kinds.MAX_REPEAT, kinds.MIN_REPEAT):
            low, high, inner = value
            known, query = _whole(inner)
            if high == 1 and low == 0:
                out.append((known | {""} if known is not None else None, True))
            elif low >= 1:
                out.append((None, _required(known, query)))
                if known is not None and low == high == 1:
                    out[-1] = (known, query)
            else:
                out.append((None, True))
        elif kind is kinds.AT:
            continue
        else:
            out.append((None, True))
    return out


def _required(known: set[str] | None, query: Query) -> Query:
    return all_of([query, strings_query(known)]) if known is not None else query


def _whole(tree) -> tuple[set[str] | None, Query]:
    """Known strings of the whole sequence, or None and what is required of it."""
    run: set[str] = {""}
    exact = True
    needs: list[Query] = []
    for known, query in _items(tree):
        needs.append(query)
        if known is not None and len(run) * len(known) <= ALTERNATIVES:
            run = {a + b for a in run for b in known}
        else:
            needs.append(strings_query(run))
            exact = False
            run = set(known) if known is not None else {""}
    if exact:
        return run, all_of(needs)
    return None, all_of([*needs, strings_query(run)])


def derive(pattern: str) -> Query:
    """The query of a pattern in the syntax that Python and Java share."""
    return _required(*_whole(syntax.parse(pattern)))


def trigrams(query: Query) -> set[str]:
    if query is True:
        return set()
    if isinstance(query, str):
        return {query}
    return set().union(*(trigrams(p) for p in query[1]))


def holds(query: Query, text: str) -> bool:
    """Does a text satisfy the query? For tests."""
    if query is True:
        return True
    if isinstance(query, str):
        return query in text.lower()
    return (all if query[0] == "and" else any)(holds(p, text) for p in query[1])


