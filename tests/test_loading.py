"""Loading of the indexes: in parts, without shuffle files that stay, and only what is asked for; queries that read a table."""

import os

import duckdb
import pytest

from probejoin.operators import rowindex
from probejoin.queries import ORACLES, QUERIES

SF = "/root/testdata/sf0.001"
TRIPLES = [("a", "knows", "b"), ("a", "knows", "c"), ("b", "knows", "a"), ("a", "age", '"7"'), ("a", "rdf:type", "T"), ("b", "rdf:type", "T"), ("a", "knows", "b")]


def test_parts_make_the_same_index(spark):
    frame = spark.createDataFrame(TRIPLES, "s string, p string, o string")
    whole = rowindex.build(frame, "parts-whole", 3)
    parts = rowindex.build([(g, frame.where(frame.p.isin(*g))) for g in (("knows",), ("age", "rdf:type"))], "parts-two", 3)
    for which in ("SI", "OI"):
        got, want = (sorted(map(tuple, idx.table(which).select("row_key", "value", "p").collect())) for idx in (parts, whole))
        assert got == want and len(got) == len(set(TRIPLES))
    assert sorted(map(tuple, parts.triples.select("s", "p", "o").collect())) == sorted(set(TRIPLES))


def test_object_index_and_plain_file_are_written_when_asked_for(spark):
    idx = rowindex.build(spark.createDataFrame(TRIPLES, "s string, p string, o string"), "on-demand", 3)
    assert spark.catalog.tableExists(idx.si) and not spark.catalog.tableExists(idx.oi) and "triples" not in idx.held
    idx.table("OI")
    assert spark.catalog.tableExists(idx.oi)


def test_shuffle_files_go_with_the_write(spark):
    manager = spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().mapOutputTracker().shuffleStatuses()
    before = manager.size()
    idx = rowindex.build(spark.createDataFrame(TRIPLES, "s string, p string, o string"), "tidy", 3)
    idx.table("OI")
    assert manager.size() <= before


def test_groups_of_predicates(monkeypatch):
    monkeypatch.setattr(rowindex, "GROUP_ROWS", 10)
    sizes = {"a": 4, "b": 5, "c": 30, "d": 1, "e": 0}
    got = rowindex.grouped(sizes)
    assert [p for g in got for p in g] == list(sizes) and got == [("a", "b"), ("c",), ("d", "e")]


@pytest.mark.parametrize("name", ["access_paths", "tp_xxx", "six_tp_xxx"])
def test_queries_over_tables(spark, name):
    con = duckdb.connect()
    for t in "region nation customer supplier part orders lineitem".split():
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    df = QUERIES[name](spark, SF)
    assert any("orders.parquet" in f or "index" in f or "copy" in f for f in df.inputFiles())
    cur = con.execute(ORACLES[name])
    assert sorted(map(tuple, df.select(*[c[0] for c in cur.description]).collect())) == sorted(cur.fetchall())


def on_demand(spark, name):
    asked = []

    def source(units):
        for p, o in units:
            asked.append((p, o))
            rows = spark.createDataFrame([t for t in TRIPLES if t[1] == p and o in (None, t[2])] + [("c", p, o or "U")] * 2, "s string, p string, o string")
            yield 40, rows

    return rowindex.on_demand(spark, source, [("knows",), ("age", "rdf:type")], name, 8), asked


def test_units_are_loaded_when_asked_for(spark, monkeypatch):
    monkeypatch.setattr(rowindex, "GROUP_ROWS", 10)  # in slices
    idx, asked = on_demand(spark, "units")
    read = lambda which, wanted=None: sorted((r["p"], r["value"]) for r in idx.table(which, wanted).collect())
    assert read("SI", [("rdf:type", "T")]) == [("rdf:type", "T")] * 3 and asked == [("rdf:type", "T")]
    assert read("SI", [("rdf:type", "T")]) == [("rdf:type", "T")] * 3 and len(asked) == 1  # not again
    assert read("SI", [("age", None), ("rdf:type", "T")]) == [("age", '"7"'), ("age", "U"), *[("rdf:type", "T")] * 3]
    every = sorted({(s, p, o) for s, p, o in TRIPLES} | {("c", p, "U") for p in ("knows", "age", "rdf:type")} | {("c", "rdf:type", "T")})
    assert sorted(map(tuple, idx.triples.collect())) == every  # the class that was there before is not there twice
    assert sorted((r["value"], r["p"], r["o"]) for r in idx.table("OI").collect()) == [t for t in every if t != ("c", "rdf:type", "T")]


def test_query_loads_only_its_predicates(spark, tmp_path):
    """A query of customers wrote all 31 predicates, most of them of line items, before."""
    import shutil

    shutil.copytree(SF, tmp_path / "sf")
    QUERIES["w_l4_shuffle"](spark, str(tmp_path / "sf")).count()
    from probejoin.queries import catalog

    idx = catalog(spark, str(tmp_path / "sf"))
    held = {r["p"] for r in spark.table(idx.si).select("p").distinct().collect()}
    assert held == {"rdf:type", "inNation", "name", "acctbal", "segment"} and not spark.catalog.tableExists(idx.oi)
    QUERIES["hybrid_plan"](spark, str(tmp_path / "sf")).count()
    assert spark.table(idx.si).where("value = 'LineItem'").isEmpty()


def test_what_axioms_add_comes_from():
    from probejoin.operators import closure
    from probejoin.sources.triplify import AXIOMS

    given = {"inNation", "inRegion", "placedBy", "name", "rdf:type"}
    behind = lambda p, c=None: closure.behind(AXIOMS, p, given, c)[0]
    assert behind("within") == {"inNation", "inRegion"} and behind("placed") == {"placedBy"} and behind("hosts") == {"inNation"}
    assert behind("placedBy") == behind("name") == behind("inNation") == behind("rdf:type", set()) == set()
    assert closure.below(AXIOMS, "Party") >= {"Customer", "Supplier", "BuildingCustomer"} and not closure.below(AXIOMS, "LineItem")
    both_ways = [("q", "subPropertyOf", "p"), ("q", "inverseOf", "p")]
    assert closure.behind(both_ways, "p", {"p"})[0] == {"p"}  # its own triples turned


@pytest.mark.parametrize("name", ["tp_xxx", "six_tp_xxx"])
def test_free_pattern_gives_its_mappings(spark, name):
    """The pattern of three variables gave counts by predicate instead of its triples before."""
    df = QUERIES[name](spark, SF)
    assert sorted(df.columns) == ["o", "p", "s"]
    assert not df.where("s = 'order/5' and p = 'placedBy' and o like 'customer/%'").isEmpty() and df.count() > 31


@pytest.mark.parametrize("again", [False, True])
def test_a_table_is_dealt_once_for_all_its_predicates(spark, monkeypatch, again):
    """Each predicate read, dealt and ordered its whole table before."""
    monkeypatch.setattr(rowindex, "GROUP_ROWS", 2)  # in slices
    rows = [("a", "1", "x"), ("b", None, "x"), ("c", "2", None), ("d", None, None)] + [("a", "1", "y"), ("a", "1", "x")] * again
    asked = []

    def source(units):
        asked.extend(units)
        yield 1, spark.createDataFrame([("c", p, "z") for p, _ in units], "s string, p string, o string")

    def tables(predicates):
        if {"size", "kind"} <= set(predicates):
            yield len(rows), spark.createDataFrame(rows, "row_key string, size string, kind string")

    idx = rowindex.on_demand(spark, source, [("size", "kind"), ("name",)], f"table-{again}", 8, tables=tables)
    want = sorted({(s, p, o) for s, size, kind in rows for p, o in (("size", size), ("kind", kind)) if o} | {("c", "name", "z")})
    for _ in range(2):  # and not again
        assert sorted(map(tuple, idx.asserted().select("s", "p", "o").collect())) == want and asked == [("name", None)]
    few = rowindex.on_demand(spark, source, idx.groups, f"few-{again}", 8, tables=tables)
    few.asserted([("size", None), ("kind", None)])
    assert asked[1:] == [("size", None), ("kind", None)]  # one by one
    assert not spark.catalog.tableExists(f"{idx.si}_rows")
    shared = spark.conf.get("spark.checkpoint.dir").removeprefix("file://")
    assert not any(f"{idx.si}_rows" in f for f in os.listdir(shared))  # what lay beside the index is gone


def test_predicates_of_one_table(spark):
    from probejoin.sources import triplify

    got = triplify.alone(["ofOrder", "tax", "brand", "size", "name", "acctbal", "rdf:type", "segment"])
    assert got == {"part": ["brand", "size"], "lineitem": ["ofOrder", "tax"]}  # others have names, balances and classes, too; a segment is alone
    wide = triplify.beside(spark, SF, "lineitem", got["lineitem"])
    one = triplify.triples(spark, SF, ("lineitem",), {"tax"}).select("s", "o")
    assert sorted(map(tuple, wide.select("row_key", "tax").collect())) == sorted(map(tuple, one.collect()))


def test_estimates_write_nothing(spark, tmp_path):
    import shutil

    from probejoin.queries import catalog

    shutil.copytree(SF, tmp_path / "sf")
    idx = catalog(spark, str(tmp_path / "sf"))
    wanted = [("ofOrder", None), ("ofPart", None), ("inNation", None), ("rdf:type", "Supplier")]
    got = idx.estimates(wanted)
    assert not spark.catalog.tableExists(idx.si) and not spark.catalog.tableExists(idx.oi)
    exact = catalog(spark, SF).stats(wanted)
    for u in map(rowindex.named, wanted):
        for k in ("n_triples", "n_subjects", "n_objects"):
            assert abs(got[u][k] - exact[u][k]) <= 0.15 * exact[u][k]
    assert idx.estimates(wanted) == got
