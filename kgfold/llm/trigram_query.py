"""Boolean trigram queries from regular expressions.

A rule's pattern is parsed, and from the strings every match must contain the clauses of a query are derived: a
disjunction of conjunctions of trigrams, in lower case.  A pattern that forces no trigram has no query (None): it must
scan every text.  Clauses only ever lose information, so a text without a satisfied clause can't hold a match.
"""

from __future__ import annotations

import re._constants as C
import re._parser as parser
from itertools import product

MOST_STRINGS = 64
Clause = frozenset[str]
Query = frozenset[Clause] | None


def _strings(node: tuple) -> set[str] | None:
    """All strings a node matches, if they are few."""
    op, arg = node
    if op is C.LITERAL:
        return {chr(arg)}
    if op is C.IN and all(k is C.LITERAL for k, _ in arg):
        return {chr(v) for _, v in arg}
    if op is C.SUBPATTERN:
        return _sequence_strings(arg[3])
    if op is C.BRANCH:
        sets = [_sequence_strings(s) for s in arg[1]]
        return None if any(s is None for s in sets) else set().union(*sets)
    if op in (C.MAX_REPEAT, C.MIN_REPEAT, C.POSSESSIVE_REPEAT) and arg[1] is not C.MAXREPEAT and arg[1] <= 6:
        inner = _sequence_strings(arg[2])
        if inner is None:
            return None
        out: set[str] = set()
        for n in range(arg[0], arg[1] + 1):
            if len(inner) ** n > MOST_STRINGS:
                return None
            out |= {"".join(p) for p in product(inner, repeat=n)}
        return out if len(out) <= MOST_STRINGS else None
    if op in (C.AT, C.ASSERT_NOT):
        return {""}
    return None


def _sequence_strings(seq) -> set[str] | None:
    out = {""}
    for node in seq:
        own = _strings(node)
        if own is None or len(out) * len(own) > MOST_STRINGS:
            return None
        out = {a + b for a in out for b in own}
    return out


def _from_strings(strings: set[str]) -> Query:
    if any(len(s) < 3 for s in strings):
        return None
    return _least({frozenset(s.lower()[i : i + 3] for i in range(len(s) - 2)) for s in strings})


def _least(clauses) -> Query:
    return frozenset(c for c in clauses if not any(d < c for d in clauses))


def _both(a: Query, b: Query) -> Query:
    if a is None or b is None:
        return b if a is None else a
    joined = {x | y for x in a for y in b}
    return _least(joined) if len(joined) <= MOST_STRINGS else min(a, b, key=len)


def _sequence(seq) -> Query:
    found: Query = None
    run = {""}
    for node in seq:
        own = _strings(node)
        if own is not None and len(run) * len(own) <= MOST_STRINGS:
            run = {a + b for a in run for b in own}
            continue
        found, run = _both(found, _from_strings(run)), own if own is not None else {""}
        op, arg = node
        if own is not None:
            continue
        if op is C.SUBPATTERN:
            found = _both(found, _sequence(arg[3]))
        elif op is C.BRANCH:
            options = [_sequence(s) for s in arg[1]]
            found = _both(found, None if any(o is None for o in options) else _least(set().union(*options)))
        elif op in (C.MAX_REPEAT, C.MIN_REPEAT, C.POSSESSIVE_REPEAT) and arg[0] >= 1:
            found = _both(found, _sequence(arg[2]))
    return _both(found, _from_strings(run))


def trigram_query(pattern: str) -> Query:
    """Clauses of which one must hold (all its trigrams present) in the lower-cased text; None if nothing is forced."""
    return _sequence(parser.parse(pattern))
