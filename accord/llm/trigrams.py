"""Boolean trigram queries from regular expressions: what trigrams a text must hold for the expression to match anywhere in it.

A query is True (nothing is mandatory), a trigram, ("and", parts) or ("or", parts). Everything is in lower case, so that it holds for
expressions with and without case. Follows the parse tree of the standard library's regular-expression parser.
"""

from __future__ import annotations

from functools import reduce
from re import _constants as C
from re import _parser

#: Strings kept at once while literals are joined; beyond it the query is cut, which makes it weaker, never wrong.
MOST_STRINGS = 64


def both(a, b):
    if a is True or a == b:
        return b
    if b is True:
        return a
    parts = [y for x in (a, b) for y in (x[1] if x[0] == "and" and not isinstance(x, str) else (x,))]
    return ("and", tuple(dict.fromkeys(parts)))


def either(parts):
    parts = list(dict.fromkeys(parts))
    return True if True in parts or not parts else parts[0] if len(parts) == 1 else ("or", tuple(parts))


def _of_strings(strings) -> object:
    """One of the strings: all trigrams of one of them. A string that holds all trigrams of another adds nothing."""
    sets = {frozenset(s[i : i + 3] for i in range(len(s) - 2)) for s in strings}
    least = sorted((sorted(x) for x in sets if not any(y < x for y in sets)))
    return either([reduce(both, x, True) for x in least])


def _chars(items) -> set | None:
    """The characters of a class, if they are few."""
    out: set = set()
    for kind, value in items:
        if kind is C.LITERAL:
            out.add(chr(value).lower())
        elif kind is C.RANGE and value[1] - value[0] < 16:
            out |= {chr(c).lower() for c in range(value[0], value[1] + 1)}
        else:
            return None
    return out if len(out) <= 16 else None


def _walk(tree) -> tuple[set | None, object]:
    """(all strings that it matches, if few; else None, what they must hold)."""
    run, query = {""}, True
    exact = True

    def cut():
        nonlocal run, query, exact
        query, run, exact = both(query, _of_strings(run)), {""}, False

    for kind, value in tree:
        strings, must = None, True
        if kind is C.LITERAL:
            strings = {chr(value).lower()}
        elif kind is C.IN:
            strings = _chars(value)
        elif kind is C.AT or kind in (C.ASSERT, C.ASSERT_NOT):
            strings = {""}
        elif kind is C.SUBPATTERN:
            strings, must = _walk(value[3])
        elif kind is C.BRANCH:
            parts = [_walk(x) for x in value[1]]
            if all(s is not None for s, _ in parts):
                strings = set().union(*(s for s, _ in parts))
            else:
                must = either([m if s is None else _of_strings(s) for s, m in parts])
        elif kind in (C.MAX_REPEAT, C.MIN_REPEAT, C.POSSESSIVE_REPEAT):
            low, high, inner = value
            s, m = _walk(inner)
            if s is not None and low == 0 and high == 1:
                strings = s | {""}
            elif s is not None and low == high and low <= 4:
                strings = {""}
                for _ in range(low):
                    strings = {a + b for a in strings for b in s}
            elif low:
                must = m if s is None else _of_strings(s)
        if strings is not None and len(strings) * len(run) <= MOST_STRINGS:
            run = {a + b for a in run for b in strings}
        else:
            cut()
            if strings is not None and len(strings) <= MOST_STRINGS:
                run = set(strings)
            else:
                query = both(query, must if strings is None else _of_strings(strings))
    return (run, _of_strings(run)) if exact else (None, both(query, _of_strings(run)))


def trigram_query(pattern: str) -> object:
    return _walk(_parser.parse(pattern))[1]


def trigrams_of(query) -> set[str]:
    return set() if query is True else {query} if isinstance(query, str) else set().union(*map(trigrams_of, query[1]))
