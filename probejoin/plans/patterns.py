"""Triple patterns and graph patterns: the plan side of the engine, never data."""

from __future__ import annotations

from dataclasses import dataclass, field


def is_var(term: str) -> bool:
    return term.startswith("?")


@dataclass(frozen=True)
class TriplePattern:
    s: str
    p: str
    o: str

    @property
    def vars(self) -> tuple[str, ...]:
        """Names of the variables in order of first use, without the mark."""
        return tuple(dict.fromkeys(t[1:] for t in (self.s, self.p, self.o) if is_var(t)))

    def at(self, position: str) -> str:
        return getattr(self, position)

    def position_of(self, var: str) -> str:
        """Positions (s, p, o) at which a variable stands."""
        return "".join(k for k in "spo" if self.at(k) == f"?{var}")

    def shape(self, bound: frozenset[str] = frozenset()) -> str:
        """Which positions are given: `s`, `p`, `o` where they are, `?` where not."""
        return "".join(k if not is_var(self.at(k)) or self.at(k)[1:] in bound else "?" for k in "spo")

    def __str__(self) -> str:
        return f"{self.s} {self.p} {self.o}"


@dataclass(frozen=True)
class GraphPattern:
    patterns: tuple[TriplePattern, ...]
    select: tuple[str, ...] = ()
    distinct: bool = False
    filters: tuple[tuple[str, str, str], ...] = ()
    optional: tuple[tuple[TriplePattern, ...], ...] = ()
    union: tuple[tuple[TriplePattern, ...], ...] = ()
    order_by: tuple[tuple[str, bool], ...] = ()
    limit: int | None = None
    offset: int = 0

    @property
    def vars(self) -> tuple[str, ...]:
        every = [*self.patterns, *(p for g in (*self.union, *self.optional) for p in g)]
        return tuple(dict.fromkeys(v for p in every for v in p.vars))


def pattern(text: str) -> TriplePattern:
    """`?x placedBy customer/7` as a pattern; a literal keeps its quotes and may hold spaces."""
    from probejoin.plans.syntax import split_terms

    return TriplePattern(*split_terms(text))


def bgp(*texts: str, select: tuple[str, ...] = ()) -> GraphPattern:
    return GraphPattern(tuple(pattern(t) for t in texts), select)


@dataclass
class Step:
    """One operation of a plan: scan, probe, multi (several probes on one variable) or row (one lookup for all)."""

    kind: str
    patterns: list[TriplePattern]
    var: str | None = None
    index: str | None = None
    notes: list[str] = field(default_factory=list)

    def __str__(self) -> str:
        return f"{self.kind}({'; '.join(map(str, self.patterns))})" + (f" on ?{self.var}" if self.var else "") + (f" in {self.index}" if self.index else "")
