"""A small text form of graph patterns.

SELECT [DISTINCT] vars or * WHERE { patterns separated by dots; FILTER(?v op term);
OPTIONAL { patterns }; { patterns } UNION { patterns } } ORDER BY vars LIMIT n OFFSET n
"""

from __future__ import annotations

import re

from probejoin.plans.patterns import GraphPattern, TriplePattern

_TERM = re.compile(r'"(?:[^"\\]|\\.)*"|\?\w+|[^\s{}()."]+(?:\.[^\s{}()."]+)*')
_TOKEN = re.compile(r'"(?:[^"\\]|\\.)*"|!=|<=|>=|[{}()=<>]|\.(?=\s|$|\})|\?\w+|\*|[^\s{}()"=<>!]+?(?=\.?(?:\s|$|[{}()=<>!]))')


def split_terms(text: str) -> list[str]:
    terms = _TERM.findall(text.strip())
    if len(terms) != 3:
        raise ValueError(f"a pattern has three terms: {text!r}")
    return terms


class _Reader:
    def __init__(self, text: str):
        self.tokens, self.at = _TOKEN.findall(text), 0

    def peek(self) -> str:
        return self.tokens[self.at] if self.at < len(self.tokens) else ""

    def next(self, expected: str | None = None) -> str:
        got = self.peek()
        if not got or expected is not None and got.upper() != expected:
            raise ValueError(f"expected {expected or 'more'}, found {got or 'the end'!r}")
        self.at += 1
        return got

    def accept(self, word: str) -> bool:
        if self.peek().upper() == word:
            self.at += 1
            return True
        return False

    def triples(self) -> tuple[TriplePattern, ...]:
        """Patterns up to the closing brace."""
        out = []
        while self.peek() != "}":
            out.append(TriplePattern(self.next(), self.next(), self.next()))
            self.accept(".")
        self.next("}")
        return tuple(out)


def parse(text: str) -> GraphPattern:
    r = _Reader(text)
    r.next("SELECT")
    distinct = r.accept("DISTINCT")
    select: list[str] = []
    while r.peek().upper() != "WHERE":
        select.append(r.next())
    r.next("WHERE")
    r.next("{")
    patterns, filters, optional, union = [], [], [], []
    while r.peek() != "}":
        if r.accept("FILTER"):
            r.next("(")
            filters.append((r.next(), r.next(), r.next()))
            r.next(")")
        elif r.accept("OPTIONAL"):
            r.next("{")
            optional.append(r.triples())
        elif r.accept("{"):
            union.append(r.triples())
            while r.accept("UNION"):
                r.next("{")
                union.append(r.triples())
        else:
            patterns.append(TriplePattern(r.next(), r.next(), r.next()))
        r.accept(".")
    r.next("}")
    order: list[tuple[str, bool]] = []
    limit, offset = None, 0
    while r.peek():
        if r.accept("ORDER"):
            r.next("BY")
            while r.peek().startswith("?") or r.peek().upper() in ("ASC", "DESC"):
                down = r.accept("DESC")
                order.append(((r.next() if not r.accept("ASC") else r.next())[1:], not down))
        elif r.accept("LIMIT"):
            limit = int(r.next())
        elif r.accept("OFFSET"):
            offset = int(r.next())
        else:
            raise ValueError(f"unexpected {r.peek()!r}")
    names = () if select == ["*"] else tuple(v.lstrip("?") for v in select)
    return GraphPattern(tuple(patterns), names, distinct, tuple(filters), tuple(optional), tuple(union), tuple(order), limit, offset)
