"""Plans alone: no session is needed."""

import pytest

from probejoin.operators.costs import phases
from probejoin.plans import ordering, planner
from probejoin.plans.access import OI, SI, choose
from probejoin.plans.patterns import bgp, pattern
from probejoin.plans.syntax import parse
from probejoin.workloads import SHAPES, WORKLOADS


def test_ranks_of_all_shapes():
    ranked = sorted(SHAPES, key=lambda s: ordering.rank(SHAPES[s].patterns[0]))
    assert ranked == ["spo", "sxo", "spx", "xpo", "sxx", "xxo", "xpx", "xxx"]


def test_access_of_all_shapes():
    got = {s: (choose(g.patterns[0]).index, choose(g.patterns[0]).mode) for s, g in SHAPES.items()}
    assert got == {"spo": (SI, "GET"), "xpo": (OI, "GET"), "sxo": (SI, "GET"), "spx": (SI, "GET"), "xxo": (OI, "GET+RANGE"), "xpx": (SI, "SCAN"), "sxx": (SI, "GET"), "xxx": (SI, "SCAN")}
    assert choose(pattern("?s rdf:type Customer")).mode == "RANGE"


def test_connected_order_has_no_product():
    for w in ("l7", "l8", "x2"):
        bound = set()
        for p in ordering.connected(WORKLOADS[w].patterns):
            assert not bound or bound & set(p.vars)
            bound |= set(p.vars)
    assert str(ordering.static(WORKLOADS["l8"].patterns)[1]) == "?y rdf:type Nation"


def test_static_plan_forms_no_product_that_a_later_pattern_joins():
    """`static` puts all orders beside the parts of one supplier; the orders wait for the parts' orders."""
    for strategy in ("cascade", "multiway", "row"):
        bound = set()
        for p in [p for s in planner.plan(WORKLOADS["l7"], strategy, "static") for p in s.patterns]:
            assert not bound or bound & set(p.vars)
            bound |= set(p.vars)
    apart = bgp("?a p ?b", "?c q ?d", "?d r ?e").patterns
    assert ordering.deferred(apart) == list(apart)
    assert [str(p) for p in ordering.deferred(bgp("?x a ?y", "?z b ?w", "c d e", "?y f ?z").patterns)] == ["?x a ?y", "c d e", "?y f ?z", "?z b ?w"]


@pytest.mark.parametrize(("w", "cascade", "multiway"), [("l1", 1, 1), ("l4", 4, 1), ("l7", 3, 2), ("l8", 4, 3), ("s1", 2, 1), ("s2", 8, 1), ("x2", 3, 3), ("l6", 1, 1)])
def test_phases(w, cascade, multiway):
    assert phases(planner.plan(WORKLOADS[w], "cascade")) == cascade
    assert phases(planner.plan(WORKLOADS[w], "multiway")) == multiway


def test_row_steps_and_eligibility():
    assert [s.kind for s in planner.plan(WORKLOADS["l4"], "row")] == ["scan", "row"]
    shared = bgp("?x r ?z", "?x p ?v", "?x q ?v").patterns
    assert not planner.multiway_eligible(["x", "z"], shared[1:])
    assert planner.row_eligible("x", ["x", "z"], shared[1:]) is None
    classes = bgp("?c is ?k", "?a rdf:type ?c", "?b p ?c").patterns
    assert planner.row_eligible("c", ["c", "k"], classes[1:]) is None
    assert planner.row_eligible("c", ["c"], bgp("?a p ?c", "?b q ?c").patterns) == OI


def test_choices_follow_statistics():
    stats = {"p": {"n_triples": 1_000_000, "n_subjects": 1_000_000, "n_objects": 10}, "q": {"n_triples": 20, "n_subjects": 20, "n_objects": 20}}
    assert planner.choose_single(pattern("?x p ?y"), stats) == "distributed"
    assert planner.choose_single(pattern("?x q ?y"), stats) == "local"
    assert planner.choose_join(5, pattern("?x p ?y"), stats) == "keyed"
    assert planner.choose_join(1_000_000, pattern("?x p ?y"), stats) == "region"


def test_text_form():
    gp = parse('SELECT DISTINCT ?x WHERE { ?x name "a b. c" . ?x size ?v FILTER(?v >= 3) OPTIONAL { ?x brand ?b } } ORDER BY DESC ?v LIMIT 3 OFFSET 1')
    assert gp.distinct and gp.select == ("x",) and gp.limit == 3 and gp.offset == 1 and gp.order_by == (("v", False),)
    assert gp.patterns[0].o == '"a b. c"' and gp.filters == (("?v", ">=", "3"),) and str(gp.optional[0][0]) == "?x brand ?b"
    with pytest.raises(ValueError):
        parse("SELECT ?x { ?x a b }")
    folded = planner.fold_filters(WORKLOADS["s3a"])
    assert folded.patterns[1].p == "orderdate" and not folded.filters


def test_cheapest_order_checks_before_it_multiplies():
    """Orders were joined with all suppliers of their parts before, 30 times as many rows as there are line items."""
    from probejoin.queries import JOINS

    n = 600_000
    counts = lambda *c: dict(zip(("n_triples", "n_subjects", "n_objects"), c, strict=True))
    stats = {"contains": counts(n, n // 4, 20_000), "supplies": counts(n, 1_000, 20_000), "ofOrder": counts(n, n, n // 4), "suppliedBy": counts(n, n, 1_000), "ofPart": counts(n, n, 20_000), "inNation": counts(16_000, 16_000, 25)}
    ps = JOINS["probe_multikey"].patterns
    got = planner.order(ps, "cheapest", stats)
    assert sorted(map(str, got)) == sorted(map(str, ps)) and got[0] == ps[5]
    most = lambda order: max(planner.joined_extent(order[: k + 1], stats) for k in range(len(order)))
    assert most(got) <= n < 10 * n < most(ps)
    assert planner.order(ps * 3, "cheapest", stats)[0] == ps[5]  # too many to compare
