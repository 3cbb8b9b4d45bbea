"""Boolean trigram queries derived from regular expressions.

A query is ``True`` (anything may match), ``("tri", t)``, ``("all", parts)`` or
``("any", parts)``. A text that matches the expression always satisfies the
query, so texts that fail it need no regex run. Letters are folded to lower
case, which only widens the query.
"""

from __future__ import annotations


from re import _constants as op
from re import _parser as parser

#: Most literal strings followed at once; beyond it, what is known is flushed.
MAX_STRINGS = 64
#: Most characters that a class may have to be enumerated.
MAX_CLASS = 16


def derive(pattern: str):
    """The trigram query of a regex."""
    exact, query = _sequence(parser.parse(pattern))
    return both(query, literal_query(exact)) if exact is not None else query


def trigrams_of(query) -> set[str]:
    if query is True:
        return set()
    if query[0] == "tri":
        return {query[1]}
    return set().union(*map(trigrams_of, query[1]))


def satisfied(query, present: set[str]) -> bool:
    """Evaluates a query on a set of trigrams."""
    if query is True:
        return True
    if query[0] == "tri":
        return query[1] in present
    return (all if query[0] == "all" else any)(satisfied(q, present) for q in query[1])


def both(*queries):
    parts = []
    for query in queries:
        if query is not True:
            parts += query[1] if query[0] == "all" else [query]
    unique = [q for i, q in enumerate(parts) if q not in parts[:i]]
    return True if not unique else unique[0] if len(unique) == 1 else ("all", unique)


def either(*queries):
    if any(q is True for q in queries) or not queries:
        return True
    unique = [q for i, q in enumerate(queries) if q not in queries[:i]]
    # a conjunction that demands more than another one adds nothing to the choice
    plain = [q for q in unique if q[0] == "tri" or q[0] == "all" and all(p[0] == "tri" for p in q[1])]
    unique = [q for q in unique if not (q in plain and any(trigrams_of(p) < trigrams_of(q) for p in plain))]
    return unique[0] if len(unique) == 1 else ("any", unique)


def thinned(query, ends: int = 1):
    """A wider query: of each conjunction of trigrams, the first and last ``ends``."""
    if query is True or query[0] == "tri":
        return query
    parts = [thinned(q, ends) for q in query[1]]
    if query[0] == "any":
        return either(*parts)
    plain, rest = [q for q in parts if q[0] == "tri"], [q for q in parts if q[0] != "tri"]
    return both(*(plain if len(plain) <= 2 * ends else plain[:ends] + plain[-ends:]), *rest)


def literal_query(strings):
    """Some string of the set occurs: all trigrams of one of them do."""
    if not strings or min(map(len, strings)) < 3:
        return True
    return either(*(both(*(("tri", s[i : i + 3]) for i in range(len(s) - 2))) for s in sorted(strings)))


def _sequence(nodes):
    """(exact strings or None, query) of a concatenation."""
    strings, query, whole = {""}, True, True
    for node in nodes:
        exact, part = _node(node)
        if exact is None:
            query, strings, whole = both(query, literal_query(strings), part), {""}, False
            continue
        longer = {a + b for a in strings for b in exact}
        if len(longer) > MAX_STRINGS:
            query, whole = both(query, literal_query(strings)), False
            longer = {a[-2:] + b for a in strings for b in exact}
            if len(longer) > MAX_STRINGS:
                query, longer = both(query, literal_query(exact)), {b[-2:] for b in exact}
            if len(longer) > MAX_STRINGS:
                longer = {""}
        strings = longer
    return (strings, True) if whole else (None, both(query, literal_query(strings)))


def _node(node):
    kind, value = node
    if kind is op.LITERAL:
        return {chr(value).lower()}, True
    if kind is op.IN:
        return _class(value), True
    if kind is op.AT:
        return {""}, True
    if kind is op.SUBPATTERN:
        return _sequence(value[-1])
    if kind is op.BRANCH:
        parts = [_sequence(branch) for branch in value[1]]
        if all(exact is not None for exact, _ in parts):
            strings = set().union(*(exact for exact, _ in parts))
            if len(strings) <= MAX_STRINGS:
                return strings, True
        return None, either(*(both(q, literal_query(e)) if e is not None else q for e, q in parts))
    if kind in (op.MAX_REPEAT, op.MIN_REPEAT, op.POSSESSIVE_REPEAT):
        return _repeat(*value)
    return None, True  # any character, negations, look-arounds, back references


def _repeat(least, most, nodes):
    exact, query = _sequence(nodes)
    if least == 0:
        return (exact | {""}, True) if exact is not None and most == 1 else (None, True)
    if exact is None:
        return None, query
    strings = {""}
    for _ in range(min(least, 3) if least != most else least):
        strings = {a + b for a in strings for b in exact}
        if len(strings) > MAX_STRINGS:
            return None, literal_query(exact)
    return (strings, True) if least == most else (None, literal_query(strings))


def _class(items):
    chars: set[str] = set()
    for kind, value in items:
        if kind is op.LITERAL:
            chars.add(chr(value).lower())
        elif kind is op.RANGE and value[1] - value[0] < 4 * MAX_CLASS:
            chars |= {chr(c).lower() for c in range(value[0], value[1] + 1)}
        else:
            return None
    return chars if len(chars) <= MAX_CLASS else None


