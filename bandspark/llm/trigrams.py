"""Boolean trigram queries of regular expressions.

``query_of(pattern)`` is a condition on the lower-case trigrams that every text with a match must hold: ``True`` (none is
mandatory), a trigram, or ("and" | "or", [conditions]). It is found bottom-up over the parsed pattern: a part that
can only be one of a few strings stays a set of strings; where a set ends, the trigrams of its strings are demanded.
"""

from __future__ import annotations

import re
import re._constants as C
import re._parser as parser

#: Most strings of a set, and most characters of a class that is spelled out.
MOST_STRINGS, MOST_CHARS = 64, 16

Query = bool | str | tuple


def _both(parts: list[Query]) -> Query:
    flat: list[Query] = []
    for p in parts:
        if p is not True:
            flat += p[1] if isinstance(p, tuple) and p[0] == "and" else [p]
    flat = list(dict.fromkeys(flat))
    return True if not flat else flat[0] if len(flat) == 1 else ("and", tuple(flat))


def _either(parts: list[Query]) -> Query:
    if not parts or any(p is True for p in parts):
        return True
    flat: list[Query] = []
    for p in parts:
        flat += p[1] if isinstance(p, tuple) and p[0] == "or" else [p]
    flat = list(dict.fromkeys(flat))
    return flat[0] if len(flat) == 1 else ("or", tuple(flat))


def _demand(strings: frozenset[str]) -> Query:
    return _either([_both([s[i : i + 3] for i in range(len(s) - 2)]) for s in sorted(strings)])


def _class(items) -> frozenset[str] | None:
    out: set[str] = set()
    for op, arg in items:
        if op is C.LITERAL:
            out.add(chr(arg).lower())
        elif op is C.RANGE and arg[1] - arg[0] < MOST_CHARS:
            out |= {chr(c).lower() for c in range(arg[0], arg[1] + 1)}
        else:
            return None
    return frozenset(out) if len(out) <= MOST_CHARS else None


def _walk(tree) -> tuple[frozenset[str] | None, Query]:
    """(the only strings it can be, or None; the condition of what was already given up)."""
    strings: frozenset[str] | None = frozenset({""})
    demands: list[Query] = []

    def flush() -> None:
        nonlocal strings
        demands.append(_demand(strings))
        strings = frozenset({""})

    def append(more: frozenset[str]) -> None:
        nonlocal strings
        if len(strings) * len(more) > MOST_STRINGS:
            flush()
        strings = frozenset(a + b for a in strings for b in more) if len(more) <= MOST_STRINGS else frozenset({""})

    exact = True
    for op, arg in tree:
        own: frozenset[str] | None = None
        demand: Query = True
        if op is C.LITERAL:
            own = frozenset({chr(arg).lower()})
        elif op is C.IN:
            own = _class(arg)
        elif op is C.SUBPATTERN:
            own, demand = _walk(arg[3])
        elif op is C.ATOMIC_GROUP:
            own, demand = _walk(arg)
        elif op is C.BRANCH:
            ways = [_walk(w) for w in arg[1]]
            if all(w[0] is not None for w in ways) and sum(len(w[0]) for w in ways) <= MOST_STRINGS:
                own = frozenset().union(*[w[0] for w in ways])
            else:
                demand = _either([w[1] if w[0] is None else _both([w[1], _demand(w[0])]) for w in ways])
        elif op in (C.MAX_REPEAT, C.MIN_REPEAT, C.POSSESSIVE_REPEAT):
            least, most, body = arg
            inner, inner_demand = _walk(body)
            if inner is not None and most == 1:
                own = inner | {""} if least == 0 else inner
            elif inner is not None and least == most and most <= 8:
                own = frozenset({""})
                for _ in range(least):
                    own = frozenset(a + b for a in own for b in inner) if len(own) * len(inner) <= MOST_STRINGS else None
                    if own is None:
                        break
            elif least >= 1:
                demand = inner_demand if inner is None else _both([inner_demand, _demand(inner)])
        elif op in (C.AT, C.ASSERT, C.ASSERT_NOT):
            own = frozenset({""})
        if own is not None:
            append(own)
        else:
            exact = False
            flush()
            demands.append(demand)
    if exact and not any(d is not True for d in demands) and len(demands) == 0:
        return strings, True
    flush()
    return None, _both(demands)


def query_of(pattern: str) -> Query:
    strings, demand = _walk(parser.parse(pattern, re.IGNORECASE if "(?i" in pattern else 0))
    return demand if strings is None else _both([demand, _demand(strings)])


def trigrams_of(query: Query) -> set[str]:
    if query is True:
        return set()
    if isinstance(query, str):
        return {query}
    return set().union(*map(trigrams_of, query[1]))


def holds(query: Query, text: str) -> bool:
    """Whether a text meets the condition; the plain form of what the index answers."""
    if query is True:
        return True
    if isinstance(query, str):
        return query in text.lower()
    return (all if query[0] == "and" else any)(holds(q, text) for q in query[1])
