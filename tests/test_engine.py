"""Joins over small graphs against a nested-loop evaluator, and plans of bucketed joins."""

import itertools
import random
from collections import Counter

import pytest

from probejoin.operators import closure, costs, merge_baseline, probe, rowindex, sextuple, shuffle_baseline
from probejoin.plans import planner
from probejoin.plans.access import OI, SI
from probejoin.plans.patterns import GraphPattern, bgp, is_var, pattern

PAPERS = [
    ("doc/A", "title", '"T1"'), ("doc/A", "year", '"2011"'), ("doc/A", "author", "person/P"), ("doc/A", "author", "person/Q"),
    ("doc/B", "title", '"T2"'), ("doc/B", "year", '"2011"'), ("doc/B", "author", "person/Q"), ("doc/B", "author", "person/P"), ("doc/B", "cite", "doc/A"),
]
CLASSES = [("person/P", "rdf:type", "class/Human"), ("person/Q", "rdf:type", "class/Human"), ("person/P", "knows", "person/Q"), ("note/1", "about", "class/Human"), ("x|y", "rdf:type", "c|d")]
STAR = bgp("?a title ?t", "?a author ?w", "?a year ?y")


def made(spark, triples, name, **kw):
    spark.conf.set("spark.sql.requireAllClusterKeysForCoPartition", "false")
    return rowindex.build(spark.createDataFrame(triples, "s string, p string, o string"), name, 4, **kw)


@pytest.fixture(scope="module")
def papers(spark):
    return made(spark, [*PAPERS, PAPERS[0]], "papers")


@pytest.fixture(scope="module")
def classes(spark):
    return made(spark, CLASSES, "classes")


def bag(df, names=None):
    return Counter(tuple(r[c] for c in (names or sorted(df.columns))) for r in df.collect())


def naive(triples, patterns):
    """Nested loops over the set of triples."""
    out = [{}]
    for p in patterns:
        new = []
        for m, t in itertools.product(out, set(triples)):
            n = dict(m)
            for term, value in zip((p.s, p.p, p.o), t, strict=True):
                if is_var(term) and n.setdefault(term, value) != value or not is_var(term) and term != value:
                    break
            else:
                new.append(n)
        out = new
    names = sorted({v for p in patterns for v in p.vars})
    return Counter(tuple(m["?" + v] for v in names) for m in out)


def test_rows_of_both_indexes(papers):
    flat = lambda which: {r["row_key"]: dict(r["cells"]) for r in rowindex.row_view(papers, which).collect()}
    assert flat("SI") == {"doc/A": {"title": ['"T1"'], "year": ['"2011"'], "author": ["person/P", "person/Q"]}, "doc/B": {"title": ['"T2"'], "year": ['"2011"'], "author": ["person/P", "person/Q"], "cite": ["doc/A"]}}
    assert flat("OI")['"2011"'] == {"year": ["doc/A", "doc/B"]} and flat("OI")["doc/A"] == {"cite": ["doc/B"]}


def test_star_in_every_way(papers):
    want = naive(PAPERS, STAR.patterns)
    assert sum(want.values()) == 4
    first, rest = probe.read(papers, STAR.patterns[0]), STAR.patterns[1:]
    ways = [
        probe.cascade(papers, STAR.patterns), probe.cascade(papers, STAR.patterns, "region"), probe.cascade(papers, STAR.patterns, "broadcast"), probe.cascade(papers, STAR.patterns, "keyed"),
        probe.cascade(papers, STAR.patterns, materialize="parquet"), probe.multiway(papers, first, rest), probe.row_multiway(papers, first, rest, "a", SI), probe.star_scan(papers, STAR.patterns, "a"),
        probe.grouped_product(first, papers, rest, "a"), shuffle_baseline.cascade(papers.triples, STAR.patterns), shuffle_baseline.cascade(papers.triples, STAR.patterns, skew="salt"),
        shuffle_baseline.star(papers.triples, STAR.patterns, "a"), merge_baseline.cascade(papers.triples, STAR.patterns), planner.hybrid(papers, STAR)[0],
    ]
    for df in ways:
        assert bag(df) == want


def test_costs_of_the_star(papers):
    got = {r["variant"]: r["value"] for r in costs.lookups(papers, "f1", STAR.patterns, True).collect()}
    assert got == {"cascade": 6, "multiway": 4, "row": 2}
    moved = {r["variant"]: r["value"] for r in costs.rows_moved(papers, "f1", STAR.patterns).collect()}
    assert moved["shuffle cascade"] == 12 and moved["shuffle star"] == 8 and moved["probe returned"] == 8


def test_classes_and_compound_keys(spark, classes):
    assert bag(probe.read(classes, pattern("?s rdf:type class/Human"), OI)) == Counter([("person/P",), ("person/Q",)])
    assert sum(bag(probe.read(classes, pattern("?s ?p class/Human"))).values()) == 3
    assert bag(probe.read(classes, pattern("?s rdf:type ?o"), OI)) == naive(CLASSES, [pattern("?s rdf:type ?o")])
    assert bag(probe.read(classes, pattern("?s rdf:type c|d"))) == Counter([("x|y",)])
    plain = made(spark, CLASSES, "plain", compound=frozenset())
    for text in ("?s rdf:type class/Human", "?s ?p class/Human", "?s rdf:type ?o", "?x ?y ?z"):
        assert bag(probe.read(plain, pattern(text), OI)) == bag(probe.read(classes, pattern(text), OI))
    rows = {(r["keys"], r["metric"]): r["value"] for r in rowindex.balance(classes).collect()}
    assert rows["compound", "max_row"] < rows["plain", "max_row"]


EDGES = {
    "repeated variable": ([("a", "p", "a"), ("a", "p", "b")], ["?x p ?x"], 1),
    "shared second variable": ([("a", "p", '"1"'), ("a", "p", '"2"'), ("a", "q", '"2"'), ("a", "q", '"3"'), ("a", "r", '"0"')], ["?x r ?z", "?x p ?v", "?x q ?v"], 1),
    "missing cell": ([("a", "p", '"1"'), ("a", "r", '"0"')], ["?x r ?z", "?x p ?v", "?x q ?w"], 0),
    "disjoint": ([("a", "p", "1"), ("b", "p", "2"), ("c", "q", "3"), ("d", "q", "4"), ("e", "q", "5")], ["?a p ?b", "?c q ?d"], 6),
    "existence": ([("a", "p", "b"), ("b", "q", "c")], ["?x p ?y", "b q c"], 1),
    "predicate variable": ([("a", "p", "b"), ("c", "p", "d"), ("c", "q", "e")], ["a ?r b", "?s ?r ?t"], 2),
    "nothing": (PAPERS, ["?x nosuch ?y"], 0),
}


@pytest.mark.parametrize("name", EDGES)
def test_edges(spark, name):
    triples, texts, n = EDGES[name]
    idx = made(spark, triples, "edge " + name)
    gp = bgp(*texts)
    assert sum(naive(triples, gp.patterns).values()) == n
    for strategy in ("cascade", "multiway", "row"):
        for mode in ("identity", "connected"):
            assert bag(planner.execute(idx, gp, strategy, mode)) == naive(triples, gp.patterns)


def test_projection_keeps_duplicates(papers):
    assert bag(planner.execute(papers, GraphPattern(bgp("?a author ?w").patterns, ("a",)))) == Counter({("doc/A",): 2, ("doc/B",): 2})


def test_random_patterns(spark):
    rnd = random.Random(7)
    triples = list({(rnd.choice("abcd"), rnd.choice("pqr"), rnd.choice("abcd")) for _ in range(30)})
    idx = made(spark, triples, "random")
    term = lambda names, values: "?" + rnd.choice(names) if rnd.random() < 0.7 else rnd.choice(values)
    for _ in range(12):
        gp = bgp(*[f"{term('xyz', 'abcd')} {term('uv', 'pqr') if rnd.random() < 0.2 else rnd.choice('pqr')} {term('xyz', 'abcd')}" for _ in range(rnd.randint(1, 3))])
        if not gp.vars:
            continue
        want = naive(triples, gp.patterns)
        for strategy in ("cascade", "row"):
            assert bag(planner.execute(idx, gp, strategy)) == want, [str(p) for p in gp.patterns]


def test_shapes_in_six_orders(spark, papers):
    store = sextuple.build(papers.triples)
    for text in ("doc/A title \"T1\"", "?s author person/P", "doc/A ?p person/P", "doc/A author ?o", "?s ?p person/P", "?s author ?o", "doc/A ?p ?o", "?s ?p ?o"):
        p = pattern(text)
        want = naive(PAPERS, [p])
        for df in (probe.read(papers, p), probe.read(papers, p, OI), sextuple.read(store, p)):
            assert sum(bag(df).values()) == sum(want.values())
            if p.vars:
                assert bag(df) == want


def test_closure(spark):
    triples = [("c/1", "inNation", "n/1"), ("n/1", "inRegion", "r/1"), ("c/1", "rdf:type", "Small")]
    axioms = [("Small", "subClassOf", "Mid"), ("Mid", "subClassOf", "Top"), ("inNation", "subPropertyOf", "within"), ("inRegion", "subPropertyOf", "within"), ("within", "isTransitive", "true"), ("hosts", "inverseOf", "inNation")]
    frame = lambda rows: spark.createDataFrame(rows, "s string, p string, o string")
    got = {tuple(r) for r in closure.materialize(frame(triples), frame(axioms)).collect()}
    assert got == {*triples, ("c/1", "rdf:type", "Mid"), ("c/1", "rdf:type", "Top"), ("c/1", "within", "n/1"), ("n/1", "within", "r/1"), ("c/1", "within", "r/1"), ("n/1", "hosts", "c/1")}


def test_upsert_and_splits(spark, papers):
    frame = lambda rows: spark.createDataFrame(rows, "s string, p string, o string")
    new = rowindex.upsert(papers, frame([PAPERS[0], ("doc/C", "title", '"T3"')]), frame([PAPERS[1]]), "papers 2")
    assert new.triples.count() == len(PAPERS)
    splits = rowindex.split_points(papers, "SI", 3).collect()
    assert sum(r["n"] for r in splits) == len(PAPERS)


def test_index_is_not_exchanged(spark, papers):
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        assert costs.exchanges(probe.star_scan(papers, STAR.patterns, "a")) == 0
        outer = spark.createDataFrame([("doc/A",), ("doc/B",)], "a string")
        one = probe.step(outer, papers, STAR.patterns[1], "region")
        assert costs.exchanges(one) <= 1
        assert costs.exchanges(probe.multiway(papers, outer, STAR.patterns[1:], "region")) <= 1
        assert costs.exchanges(shuffle_baseline.cascade(papers.triples, STAR.patterns)) >= 3
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
