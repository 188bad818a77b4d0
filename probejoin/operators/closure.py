"""Closure of triples under class, property, transitivity and inverse axioms."""

from __future__ import annotations

from collections.abc import Sequence, Set

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from probejoin.functions.terms import TYPE
from probejoin.sources.storage import written


def transitive(edges: DataFrame, rounds: int = 64) -> DataFrame:
    """All pairs (a, b) joined by a path of edges (a, b), the edges included: semi-naive, a round for each length."""
    known = written(edges.distinct(), "closure")
    base, frontier = known, known
    for _ in range(rounds):
        longer = frontier.select("a", F.col("b").alias("m")).join(base.select(F.col("a").alias("m"), "b"), "m").select("a", "b")
        frontier = written(longer.distinct().join(known, ["a", "b"], "left_anti"), "closure")
        if frontier.isEmpty():
            return known
        known = written(known.unionByName(frontier), "closure")
    raise RuntimeError(f"no fixpoint within {rounds} rounds")


Axiom = tuple[str, str, str]


def derived(axioms: Sequence[Axiom]) -> set[str]:
    """Predicates of which the axioms may make triples."""
    return {o for _, a, o in axioms if a == "subPropertyOf"} | {x for s, a, o in axioms if a == "inverseOf" for x in (s, o)} | ({TYPE} if any(a == "subClassOf" for _, a, _ in axioms) else set())


def below(axioms: Sequence[Axiom], name: str) -> set[str]:
    """Classes whose members are members of a class, itself not included unless the axioms say so."""
    out, new = set(), {name}
    while new:
        new = {s for s, a, o in axioms if a == "subClassOf" and o in new} - out
        out |= new
    return out


def behind(axioms: Sequence[Axiom], name: str, asserted: Set[str], classes: Set[str] | None = None) -> tuple[set[str], list[Axiom]]:
    """Asserted predicates from which the axioms make further triples of a predicate, and the axioms they need.

    Back from the predicate over subproperties and inverses, with the side of subject and object
    kept: what leads back to the predicate with its sides as they are adds nothing. For classes
    only, members of these are enough; none of them, and there is nothing to add.
    """
    if name == TYPE:
        return ({TYPE}, [x for x in axioms if x[1] == "subClassOf"]) if classes is None or classes else (set(), [])
    seen, new = {(name, False)}, {(name, False)}
    while new:
        new = {(s, side) for s, a, o in axioms for p, side in new if a == "subPropertyOf" and o == p} | {(y, not side) for s, a, o in axioms if a == "inverseOf" for x, y in ((s, o), (o, s)) for p, side in new if x == p}
        new -= seen
        seen |= new
    chained = any(s == p and a == "isTransitive" for s, a, _ in axioms for p, _ in seen)
    roots = {p for p, side in seen if p in asserted and (chained or (p, side) != (name, False))}
    kept = {p for p, _ in seen}
    return roots, [x for x in axioms if x[1] in ("subPropertyOf", "inverseOf", "isTransitive") and x[0] in kept and (x[1] == "isTransitive" or x[2] in kept)] if roots else []


def touched(schema: DataFrame) -> set[str]:
    """Predicates whose triples some axiom reads; as many as there are axioms at most."""
    rows = schema.where("p in ('subPropertyOf', 'inverseOf', 'isTransitive')").collect()
    return {TYPE} | {r["s"] for r in rows} | {r["o"] for r in rows if r["p"] == "inverseOf"}


def inferred(triples: DataFrame, schema: DataFrame, rounds: int = 64) -> DataFrame:
    """What the axioms add to triples, each once; some of it may be asserted, too. Only what axioms touch is kept on the way.

    The axioms are closed first, so classes and properties are inherited in one pass; then
    inverses, then only the transitive properties iterate over data.
    """
    edge = lambda p: schema.where(F.col("p") == p).select(F.col("s").alias("a"), F.col("o").alias("b"))
    classes, properties = transitive(edge("subClassOf"), rounds), transitive(edge("subPropertyOf"), rounds)
    heirs = [r["a"] for r in classes.select("a").distinct().collect()]  # axioms, not data
    read = (F.col("p") != TYPE) & F.col("p").isin(*sorted(touched(schema))) | (F.col("p") == TYPE) & F.col("o").isin(*sorted(heirs))
    out = triples.select("s", "p", "o").where(read)
    kinds = out.where(F.col("p") == TYPE).join(classes, F.col("o") == F.col("a")).select("s", "p", F.col("b").alias("o"))
    inverse = edge("inverseOf")
    both = inverse.unionByName(inverse.select(F.col("b").alias("a"), F.col("a").alias("b")))

    def inherited(df: DataFrame) -> DataFrame:
        return df.join(properties, F.col("p") == F.col("a")).select("s", F.col("b").alias("p"), "o")

    def turned(df: DataFrame) -> DataFrame:
        return df.join(both, F.col("p") == F.col("a")).select(F.col("o").alias("s"), F.col("b").alias("p"), F.col("s").alias("o"))

    facts = out.where(F.col("p") != TYPE)
    up = inherited(facts)
    back = turned(facts.unionByName(up))
    more = up.unionByName(back).unionByName(inherited(back))
    chained = [r["s"] for r in schema.where("p = 'isTransitive'").select("s").collect()]  # axioms, not data
    every = kinds.unionByName(more)
    for name in chained:
        pairs = facts.unionByName(more).where(F.col("p") == name).select(F.col("s").alias("a"), F.col("o").alias("b"))
        every = every.unionByName(transitive(pairs, rounds).select(F.col("a").alias("s"), F.lit(name).alias("p"), F.col("b").alias("o")))
    return every.distinct()


def materialize(triples: DataFrame, schema: DataFrame, rounds: int = 64) -> DataFrame:
    """triples and all that the axioms add, each once."""
    return triples.select("s", "p", "o").unionByName(inferred(triples, schema, rounds)).distinct()
