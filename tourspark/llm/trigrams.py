"""Boolean trigram queries from regular expressions.

``query_of(pattern)`` gives a query that every text with a match must satisfy: ``ANY`` (no
demand), or an and/or tree over trigrams. It is a tree of nested tuples:
``("and", parts)``, ``("or", parts)`` or a trigram. Case is folded, as the index is.

The analysis follows the parsed pattern. Each node carries the exact set of strings it can
match while that set is small, or else what is known of its prefixes and suffixes, and the
demands collected so far.
"""

from __future__ import annotations

import re._constants as C
import re._parser as parser
from dataclasses import dataclass

ANY = ("and", ())
#: Limits on string sets; beyond them knowledge is given up, never a match.
MOST_STRINGS, MOST_CLASS = 32, 8


@dataclass(frozen=True)
class Known:
    exact: frozenset[str] | None
    head: frozenset[str]
    tail: frozenset[str]
    need: tuple | str


def both(a, b):
    parts = list(dict.fromkeys(p for q in (a, b) for p in (q[1] if isinstance(q, tuple) and q[0] == "and" else (q,))))
    return parts[0] if len(parts) == 1 else ("and", tuple(parts))


def either(queries):
    parts = list(dict.fromkeys(queries))
    if ANY in parts:
        return ANY
    return parts[0] if len(parts) == 1 else ("or", tuple(parts))


def _demand(strings) -> tuple | str:
    """One of ``strings`` occurs: any of their trigram conjunctions."""
    found = []
    for s in strings:
        q = ANY
        for i in range(len(s) - 2):
            q = both(q, s[i : i + 3])
        found.append(q)
    return either(found) if found else ANY


def _cut(strings, tail: bool) -> frozenset[str]:
    return frozenset(s[-2:] if tail else s[:2] for s in strings)


def _loose(k: Known) -> Known:
    """Give up the exact set, after it has been turned into demands and ends."""
    if k.exact is None:
        return k
    return Known(None, _cut(k.exact, False), _cut(k.exact, True), both(k.need, _demand(k.exact)))


def _one(chars) -> Known:
    s = frozenset(c.lower() for c in chars)
    return Known(s, s, s, ANY)


def _unknown() -> Known:
    return Known(None, frozenset({""}), frozenset({""}), ANY)


def _then(a: Known, b: Known) -> Known:
    if a.exact is not None and b.exact is not None and len(a.exact) * len(b.exact) <= MOST_STRINGS:
        s = frozenset(x + y for x in a.exact for y in b.exact)
        return Known(s, s, s, both(a.need, b.need))
    a, b = _loose(a) if a.exact is not None and len(a.exact) > 1 and b.exact is None else a, b
    left, right = (a.exact if a.exact is not None else a.tail), (b.exact if b.exact is not None else b.head)
    need = both(a.need, b.need)
    if len(left) * len(right) <= MOST_STRINGS * MOST_STRINGS:
        need = both(need, _demand({x + y for x in left for y in right}))
    head = {x + y for x in a.exact for y in right} if a.exact is not None else a.head
    tail = {x + y for x in left for y in b.exact} if b.exact is not None else b.tail
    return Known(None, _cut(head, False), _cut(tail, True), need)


def _fork(parts: list[Known]) -> Known:
    if all(p.exact is not None for p in parts):
        s = frozenset(x for p in parts for x in p.exact)
        if len(s) <= MOST_STRINGS:
            return Known(s, s, s, either([p.need for p in parts]))
    parts = [_loose(p) for p in parts]
    return Known(None, frozenset(x for p in parts for x in p.head), frozenset(x for p in parts for x in p.tail), either([p.need for p in parts]))


def _chars(items) -> list[str] | None:
    out: list[str] = []
    for op, arg in items:
        if op is C.LITERAL:
            out.append(chr(arg))
        elif op is C.RANGE and arg[1] - arg[0] < MOST_CLASS:
            out += [chr(c) for c in range(arg[0], arg[1] + 1)]
        else:
            return None
    out = sorted({c.lower() for c in out})
    return out if len(out) <= MOST_CLASS else None


def _walk(nodes) -> Known:
    so_far = _one([""])
    for op, arg in nodes:
        if op is C.LITERAL:
            k = _one([chr(arg)])
        elif op is C.IN:
            k = _one(c) if (c := _chars(arg)) else _unknown()
        elif op is C.BRANCH:
            k = _fork([_walk(p) for p in arg[1]])
        elif op is C.SUBPATTERN:
            k = _walk(arg[3])
        elif op in (C.MAX_REPEAT, C.MIN_REPEAT, C.POSSESSIVE_REPEAT):
            least, most, inner = arg
            k = _walk(inner)
            if (least, most) == (0, 1):
                k = _fork([_one([""]), k])
            elif least == 0:
                k = _unknown()
            elif (least, most) != (1, 1):
                first = k
                for _ in range(min(least, 3) - 1):
                    k = _then(k, first)
                if most != least or least > 3:
                    k = _loose(k)
        elif op is C.AT or op in (C.ASSERT, C.ASSERT_NOT):
            k = _one([""])
        else:
            k = _unknown()
        so_far = _then(so_far, k)
    return so_far


def query_of(pattern: str):
    return _simple(_loose(_walk(parser.parse(pattern))).need)


def _simple(q):
    if isinstance(q, str) or q == ANY:
        return q
    parts = list(dict.fromkeys(_simple(p) for p in q[1]))
    if q[0] == "and":
        parts = [p for p in parts if p != ANY]
        return ANY if not parts else parts[0] if len(parts) == 1 else ("and", tuple(parts))
    if ANY in parts:
        return ANY
    flat = [frozenset((p,) if isinstance(p, str) else p[1]) for p in parts]
    # a branch that asks for all that another asks for, and more, adds nothing
    parts = [p for p, own in zip(parts, flat, strict=True) if not any(other < own for other in flat)]
    return parts[0] if len(parts) == 1 else ("or", tuple(parts))


def trigrams_of(q) -> list[str]:
    """The trigrams of a query, once each, sorted."""
    return [q] if isinstance(q, str) else sorted({t for p in q[1] for t in trigrams_of(p)})


def holds(q, has) -> bool:
    """Whether a set of trigrams satisfies a query."""
    return q in has if isinstance(q, str) else (all if q[0] == "and" else any)(holds(p, has) for p in q[1])
