"""Registry of the graph-pattern queries with their SQL."""

from __future__ import annotations

from collections.abc import Callable, Iterator, Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from probejoin import oracles as sql
from probejoin.operators import closure, costs, merge_baseline, probe, rowindex, sextuple, shuffle_baseline
from probejoin.plans import ordering, planner
from probejoin.plans.access import OI, SI
from probejoin.plans.patterns import GraphPattern, TriplePattern, bgp, pattern
from probejoin.plans.syntax import parse
from probejoin.sources import ntriples, sinks, triplify
from probejoin.sources.storage import table, written
from probejoin.workloads import SHAPES, TEXTS, VARIANTS, WORKLOADS

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}
_CATALOGS: dict[tuple[str, str, str], object] = {}


def held(spark: SparkSession, sf_dir: str, what: str, make: Callable[[], object]) -> object:
    """One index or store for each session and folder."""
    key = (spark.sparkContext.applicationId, sf_dir, what)
    if key not in _CATALOGS:
        _CATALOGS[key] = make()
    return _CATALOGS[key]


def loaded(spark: SparkSession, sf_dir: str) -> rowindex.IndexCatalog:
    """The index of the core tables and what the axioms add; it loads what queries ask for."""
    counts = triplify.counts(spark, sf_dir)
    sizes = triplify.sizes(counts)
    groups = rowindex.grouped(sizes | {p: 0 for p in closure.derived(triplify.AXIOMS) if p not in sizes})

    def read(predicates: set[str], classes: set[str] | None) -> tuple[int, DataFrame]:
        """Asserted triples and how many they are at most; members of some classes only, or all."""
        if classes is None:
            return sum(sizes[p] for p in predicates), triplify.triples(spark, sf_dir, predicates=predicates)
        tables = triplify.with_classes(triplify.CORE, classes)
        return sum(counts[t] for t in tables), triplify.triples(spark, sf_dir, tables, predicates).where(F.col("o").isin(*sorted(classes)))

    def source(wanted: Sequence[rowindex.Unit]) -> Iterator[tuple[int, DataFrame]]:
        """What is asserted and what is inferred of a unit go in one part, as an index drops what occurs again within a part only."""
        for p, o in wanted:
            own = None if o is None else {o}
            n, rows = read({p}, own) if p in sizes else (0, None)
            roots, axioms = closure.behind(triplify.AXIOMS, p, set(sizes), None if o is None else closure.below(triplify.AXIOMS, o))
            if roots:
                m, more = read(roots, None if o is None else closure.below(triplify.AXIOMS, o))
                more = closure.inferred(more, spark.createDataFrame(axioms, "s string, p string, o string")).where(F.col("p") == p)
                more = more if o is None else more.where(F.col("o") == o)
                n, rows = n + m, more if rows is None else rows.unionByName(more)
            if rows is not None:
                yield n, rows

    def tables(wanted: Sequence[str]) -> Iterator[tuple[int, DataFrame]]:
        """The largest first; predicates to which axioms add something stay with the source."""
        plain = [p for p in wanted if p in sizes and not closure.behind(triplify.AXIOMS, p, set(sizes))[0]]
        for name, predicates in sorted(triplify.alone(plain).items(), key=lambda x: -counts[x[0]]):
            yield counts[name], triplify.beside(spark, sf_dir, name, predicates)

    buckets = max(int(spark.conf.get("spark.sql.shuffle.partitions")), min(rowindex.MOST_BUCKETS, sum(sizes.values()) // rowindex.GROUP_ROWS))
    return rowindex.on_demand(spark, source, groups, f"{spark.sparkContext.applicationId}:{sf_dir}", buckets, tables=tables)


def catalog(spark: SparkSession, sf_dir: str) -> rowindex.IndexCatalog:
    """Both indexes over the core tables and their closure."""
    spark.conf.set("spark.sql.requireAllClusterKeysForCoPartition", "false")  # a join on the row key and more keeps the buckets
    return held(spark, sf_dir, "index", lambda: loaded(spark, sf_dir))


def store(spark: SparkSession, sf_dir: str) -> sextuple.SextupleStore:
    return held(spark, sf_dir, "six", lambda: sextuple.build(catalog(spark, sf_dir).asserted()))


def query(name: str, oracle: str | None = None):
    def keep(f: Query) -> Query:
        QUERIES[name] = f
        if oracle:
            ORACLES[name] = oracle
        return f

    return keep


def add(name: str, f: Query, oracle: str | None = None) -> None:
    query(name, oracle)(f)


# --- storage -----------------------------------------------------------------------------

_CELLS = f"SELECT p, count(*) AS n, count(DISTINCT {{key}}) AS n_keys, min({{value}}) AS low, max({{value}}) AS high FROM ({sql.everything()}) GROUP BY p"


def cells(which: str, key: str) -> Query:
    return lambda spark, d: catalog(spark, d).table(which).groupBy("p").agg(F.count("*").alias("n"), F.count_distinct(key).alias("n_keys"), F.min("value").alias("low"), F.max("value").alias("high"))


add("si_cells", cells(SI, "row_key"), _CELLS.format(key="s", value="o"))
add("oi_cells", cells(OI, "o"), _CELLS.format(key="o", value="s"))


def flat_rows(which: str) -> Query:
    def run(spark: SparkSession, d: str) -> DataFrame:
        rows = rowindex.row_view(catalog(spark, d), which)
        return rows.select("row_key", F.size("cells").alias("n_columns"), F.aggregate(F.map_values("cells"), F.lit(0), lambda a, v: a + F.size(v)).alias("n_cells"), F.array_join(F.sort_array(F.map_keys("cells")), ",").alias("columns"))

    return run


_ROWS = "SELECT {key} AS row_key, CAST(count(DISTINCT p) AS INTEGER) AS n_columns, CAST(count(*) AS INTEGER) AS n_cells, string_agg(DISTINCT p, ',' ORDER BY p) AS columns FROM ({all}) GROUP BY 1"
add("si_rows", flat_rows(SI), _ROWS.format(key="s", all=sql.everything()))
add("oi_rows", flat_rows(OI), _ROWS.format(key="CASE WHEN p = 'rdf:type' THEN o || '|' || s ELSE o END", all=sql.everything()))
add("class_range_scan", lambda spark, d: probe.read(catalog(spark, d), pattern("?s rdf:type Customer"), OI), sql.answer(bgp("?s rdf:type Customer")))
_KEYED = "SELECT CASE WHEN p = 'rdf:type' THEN o || '|' || s ELSE o END AS a, o AS b FROM ({})".format(sql.everything())
add(
    "region_balance",
    lambda spark, d: rowindex.balance(catalog(spark, d)),
    " UNION ALL ".join(
        f"SELECT '{label}' AS keys, unnest(['max_row', 'n_rows', 'n_cells']) AS metric, unnest([max(n), count(*), CAST(sum(n) AS BIGINT)]) AS value FROM (SELECT count(*) AS n FROM ({_KEYED}) GROUP BY {c})"
        for label, c in (("compound", "a"), ("plain", "b"))
    ),
)
add("load_counts", lambda spark, d: catalog(spark, d).triples.groupBy("p").agg(F.count("*").alias("n")), f"SELECT p, count(*) AS n FROM ({sql.everything()}) GROUP BY p")
add("triples_by_predicate", lambda spark, d: triplify.triples(spark, d).groupBy("p").agg(F.count("*").alias("n"), F.count_distinct("s").alias("subjects"), F.count_distinct("o").alias("objects")), f"SELECT p, count(*) AS n, count(DISTINCT s) AS subjects, count(DISTINCT o) AS objects FROM ({sql.everything(False)}) GROUP BY p")
_STATS = (
    "WITH t AS ({all}) SELECT b.p AS p, n_triples, n_subjects, n_objects, max_objects_per_subject, max_subjects_per_object FROM "
    "(SELECT p, count(*) AS n_triples, count(DISTINCT s) AS n_subjects, count(DISTINCT o) AS n_objects FROM t GROUP BY p) b "
    "JOIN (SELECT p, max(n) AS max_objects_per_subject FROM (SELECT p, s, count(*) AS n FROM t GROUP BY p, s) GROUP BY p) x ON x.p = b.p "
    "JOIN (SELECT p, max(n) AS max_subjects_per_object FROM (SELECT p, o, count(*) AS n FROM t GROUP BY p, o) GROUP BY p) y ON y.p = b.p"
)
add("stats_exact", lambda spark, d: rowindex.collect_stats(catalog(spark, d).triples), _STATS.format(all=sql.everything()))
add("stats_approx", lambda spark, d: rowindex.collect_stats(catalog(spark, d).triples, exact=False))
add("predicate_fatness", lambda spark, d: sextuple.predicate_balance(catalog(spark, d).triples), f"SELECT p, count(*) AS n FROM ({sql.everything()}) GROUP BY p")
_N = f"(SELECT count(*) AS n FROM ({sql.everything()}))"
_LAYOUTS = f"SELECT 'six orders' AS layout, 6 AS copies, 18 AS stored_copies, n * 6 AS n_rows FROM {_N} UNION ALL SELECT 'two indexes', 2, 6, n * 2 FROM {_N}"
add("six_storage", lambda spark, d: sextuple.storage(store(spark, d)), _LAYOUTS)


def storage_ratio(spark: SparkSession, d: str) -> DataFrame:
    """Share of the six orders' rows that both indexes hold."""
    idx = catalog(spark, d)
    two = idx.table(SI).agg(F.count("*").alias("a")).crossJoin(idx.table(OI).agg(F.count("*").alias("b")))
    six = store(spark, d)
    total = None
    for name in sextuple.ORDERS:
        n = six.copy(name).agg(F.count("*").alias("n"))
        total = n if total is None else total.unionByName(n)
    return two.crossJoin(total.agg(F.sum("n").alias("c"))).select((F.col("a") + F.col("b")).alias("two"), F.col("c").alias("six"), F.round((F.col("a") + F.col("b")) / F.col("c"), 6).alias("ratio"))


add("storage_ratio", storage_ratio, f"SELECT 2 * n AS two, 6 * n AS six, round(2.0 * n / (6.0 * n), 6) AS ratio FROM {_N}")
for _name, _p in (("closure_type", "rdf:type"), ("closure_within", "within")):
    add(_name, (lambda p: lambda spark, d: catalog(spark, d).plain([(p, None)]).where(F.col("p") == p).select("s", "o"))(_p), sql.of(_p))
add("closure_inverse", lambda spark, d: catalog(spark, d).plain([("hosts", None), ("placed", None)]).where("p in ('hosts', 'placed')"), " UNION ALL ".join(f"SELECT s, '{p}' AS p, o FROM ({sql.of(p)})" for p in ("hosts", "placed")))

# --- patterns by shape -------------------------------------------------------------------


def by_predicate(df: DataFrame) -> DataFrame:
    """Triples counted by predicate. Subjects and objects are counted apart: an index that lies by one of them moves nothing for it."""
    subjects = df.groupBy("p", "s").agg(F.count("*").alias("k")).groupBy("p").agg(F.sum("k").alias("n"), F.count("*").alias("subjects"))
    objects = df.select("p", "o").distinct().groupBy("p").agg(F.count("*").alias("objects"))
    return subjects.join(objects, "p")


for _shape, _gp in SHAPES.items():
    _p = _gp.patterns[0]
    _oracle = sql.match([_p])
    add(f"tp_{_shape}", (lambda p: lambda spark, d: probe.read(catalog(spark, d), p))(_p), _oracle)
    if _shape != "xxx":
        add(f"tp_{_shape}_object_index", (lambda p: lambda spark, d: probe.read(catalog(spark, d), p, OI))(_p), _oracle)
    add(f"six_tp_{_shape}", (lambda p: lambda spark, d: sextuple.read(store(spark, d), p))(_p), _oracle)
add("tp_xxx_object_index", lambda spark, d: by_predicate(probe.read(catalog(spark, d), SHAPES["xxx"].patterns[0], OI)), f"SELECT p, count(*) AS n, count(DISTINCT s) AS subjects, count(DISTINCT o) AS objects FROM ({sql.everything()}) GROUP BY p")


@query("pushdown_report")
def pushdown_report(spark: SparkSession, d: str) -> DataFrame:
    """Filters that reach the scan for each shape: (shape, partition_filters, pushed_filters)."""
    import re

    rows = []
    for shape, gp in SHAPES.items():
        text = probe.read(catalog(spark, d), gp.patterns[0])._jdf.queryExecution().executedPlan().toString()
        found = lambda k: "; ".join(re.findall(rf"{k}: \[([^\]]*)\]", text))  # noqa: B023, E731
        rows.append((shape, found("PartitionFilters"), found("PushedFilters")))
    return spark.createDataFrame(rows, "shape string, partition_filters string, pushed_filters string")


_CHOICES = "(VALUES ('spo','SI','GET',true,true), ('xpo','OI','GET',true,false), ('sxo','SI','GET',false,true), ('spx','SI','GET',true,false), ('xxo','OI','GET+RANGE',false,false), ('xpx','SI','SCAN',true,false), ('sxx','SI','GET',false,false), ('xxx','SI','SCAN',false,false)) t(shape, path, mode, column_filter, value_filter)"
_MASKED = "SELECT DISTINCT shape, " + ", ".join(f"CASE WHEN shape[{i}] = '{k}' THEN {k} ELSE '?{k}' END AS {k}" for i, k in enumerate("spo", 1))
_ORDERS = " UNION ALL ".join(f"SELECT s, '{p}' AS p, o FROM ({x})" for p in ("placedBy", "rdf:type") for x in sql.ASSERTED[p] if x.endswith(" orders"))


@query(
    "access_paths",
    f"SELECT shape, path, CASE WHEN shape = 'xpo' AND p = 'rdf:type' THEN 'RANGE' ELSE mode END AS mode, column_filter, value_filter, count(*) AS n FROM ({_MASKED} FROM ({_ORDERS}), (SELECT shape FROM {_CHOICES})) JOIN (SELECT * FROM {_CHOICES}) USING (shape) GROUP BY ALL",
)
def access_paths(spark: SparkSession, d: str) -> DataFrame:
    """Index, mode and filters chosen for the patterns of each shape that the orders' triples answer, and how many such patterns there are."""
    from probejoin.plans.access import choose

    given = lambda k: F.when(F.col("shape").contains(k), F.col(k)).otherwise(F.lit(f"?{k}")).alias(k)
    rows = triplify.triples(spark, d, ("orders",), {"placedBy", "rdf:type"}).select("*", F.explode(F.array(*[F.lit(x) for x in SHAPES])).alias("shape"))
    counted = rows.select("shape", *[given(k) for k in "spo"]).distinct().groupBy("shape", "p").agg(F.count("*").alias("n"), F.min("s").alias("s"), F.min("o").alias("o"))

    @F.udf("path string, mode string, column_filter boolean, value_filter boolean")
    def chosen(s: str, p: str, o: str) -> tuple:
        a = choose(TriplePattern(s, p, o))  # depends on which terms are given, and on the predicate
        return a.index, a.mode, a.column_filter, a.value_filter

    return counted.select("shape", chosen("s", "p", "o").alias("a"), "n").groupBy("shape", "a").agg(F.sum("n").alias("n")).select("shape", "a.*", "n")


# --- joins -------------------------------------------------------------------------------


def joined(name: str, gp: GraphPattern, run: Callable[[rowindex.IndexCatalog, GraphPattern], DataFrame]) -> None:
    add(name, lambda spark, d: run(catalog(spark, d), gp).select(*(gp.select or gp.vars)), sql.answer(gp))


def flat(idx: rowindex.IndexCatalog, gp: GraphPattern) -> DataFrame:
    """The plain file for a pattern."""
    return idx.plain(rowindex.units(gp.patterns, idx.compound))


def by_cascade(idx: rowindex.IndexCatalog, gp: GraphPattern) -> DataFrame:
    return probe.cascade(idx, gp.patterns)


def by_cheapest(idx: rowindex.IndexCatalog, gp: GraphPattern) -> DataFrame:
    """A cascade in the order that statistics give: patterns that only check come before those they keep from multiplying."""
    return probe.cascade(idx, planner.order(gp.patterns, "cheapest", idx.estimates(rowindex.units(gp.patterns, idx.compound))))


JOINS: dict[str, GraphPattern] = {
    "probe_base": bgp("?x name ?t", "?x brand ?b"),
    "probe_cross": bgp("?a inRegion ?b", "?c rdf:type Region"),
    "probe_exists": bgp("?x name ?t", "?x rdf:type Supplier"),
    "probe_predvar": bgp("nation/3 ?r region/3", "customer/7 ?r ?y"),
    "probe_multikey": bgp("?o contains ?y", "?s supplies ?y", "?l ofOrder ?o", "?l suppliedBy ?s", "?l ofPart ?y", "?s inNation nation/3"),
    "probe_ss": bgp("?x placedBy ?c", "?x status ?v"),
    "probe_so": bgp("?x placedBy customer/7", "?l ofOrder ?x"),
    "probe_os": bgp("?x placedBy ?c", "?c segment ?g"),
    "probe_oo": bgp("?a inNation ?n", "?b inNation ?n", "?a rdf:type Supplier", "?b rdf:type Supplier"),
    "probe_chain3": bgp("?o placedBy ?c", "?c inNation ?n", "?n inRegion ?r"),
    "probe_chain4": WORKLOADS["x2"],
    "probe_unordered": WORKLOADS["l7"],
    "multiway_shared2": bgp("?x rdf:type Customer", "?x inNation ?n", "?x within ?n"),
}
for _name, _gp in JOINS.items():
    joined(_name, _gp, by_cheapest if _name == "probe_multikey" else by_cascade)
for _mode in ("region", "broadcast", "keyed"):
    joined(f"probe_mode_{_mode}", WORKLOADS["x4"], (lambda m: lambda idx, gp: probe.cascade(idx, gp.patterns, m))(_mode))
    joined(f"probe_chain_{_mode}", WORKLOADS["x2"], (lambda m: lambda idx, gp: probe.cascade(idx, ordering.connected(gp.patterns, True), m))(_mode))
joined("probe_materialized", WORKLOADS["x2"], lambda idx, gp: probe.cascade(idx, gp.patterns, materialize="parquet"))
for _mode in ("static", "connected", "bound_aware", "stats"):
    joined("probe_reordered" if _mode == "connected" else f"probe_reordered_{_mode}", WORKLOADS["l7"], (lambda m: lambda idx, gp: planner.execute(idx, gp, "cascade", m))(_mode))
joined("probe_multiway", WORKLOADS["l4"], lambda idx, gp: probe.multiway(idx, probe.read(idx, gp.patterns[0]), gp.patterns[1:]))
joined("probe_mixed", WORKLOADS["l8"], lambda idx, gp: planner.execute(idx, gp, "multiway"))
joined("probe_mixed_row", WORKLOADS["l8"], lambda idx, gp: planner.execute(idx, gp, "row", "stats"))
joined("probe_rowmulti_s", WORKLOADS["x1"], lambda idx, gp: probe.row_multiway(idx, probe.read(idx, gp.patterns[0]), gp.patterns[1:], "x", SI))
joined("probe_rowmulti_const", WORKLOADS["l4"], lambda idx, gp: probe.row_multiway(idx, probe.read(idx, gp.patterns[0]), gp.patterns[1:], "x", SI))
joined("probe_rowmulti_o", bgp("?y brand ?b", "?x contains ?y", "?s supplies ?y", "?y size \"7\""), lambda idx, gp: probe.row_multiway(idx, probe.cascade(idx, [gp.patterns[0], gp.patterns[3]]), gp.patterns[1:3], "y", OI))
joined("probe_rowmulti_missing", bgp("?x name ?t", "?x brand ?b", "?x segment ?g"), lambda idx, gp: probe.row_multiway(idx, probe.read(idx, gp.patterns[0]), gp.patterns[1:], "x", SI))
joined("star_scan", WORKLOADS["x1"], lambda idx, gp: probe.star_scan(idx, gp.patterns, "x"))
joined("grouped_merge", WORKLOADS["x1"], lambda idx, gp: probe.grouped_product(probe.read(idx, gp.patterns[0], SI), idx, gp.patterns[1:], "x"))
joined("base_shuffle2", WORKLOADS["l1"], lambda idx, gp: shuffle_baseline.cascade(flat(idx, gp), gp.patterns))
joined("base_shuffle_chain", WORKLOADS["x2"], lambda idx, gp: shuffle_baseline.cascade(flat(idx, gp), gp.patterns))
joined("base_shuffle_star", WORKLOADS["l4"], lambda idx, gp: shuffle_baseline.star(flat(idx, gp), gp.patterns, "x"))
joined("base_skew_salted", JOINS["probe_os"], lambda idx, gp: shuffle_baseline.cascade(flat(idx, gp), gp.patterns, skew="salt"))
joined("base_replicated", JOINS["probe_os"], lambda idx, gp: shuffle_baseline.cascade(flat(idx, gp), gp.patterns, small="broadcast"))
joined("base_merge", JOINS["probe_os"], lambda idx, gp: merge_baseline.join2(flat(idx, gp), *gp.patterns))
joined("base_merge_chain", JOINS["probe_chain3"], lambda idx, gp: merge_baseline.cascade(flat(idx, gp), gp.patterns))
joined("base_scan", WORKLOADS["l6"], lambda idx, gp: shuffle_baseline.scan(flat(idx, gp), gp.patterns[0]))
joined("one_pattern", WORKLOADS["l6"], lambda idx, gp: probe.single(idx, gp.patterns[0]))
joined("one_pattern_local", WORKLOADS["l6"], lambda idx, gp: probe.single(idx, gp.patterns[0], local=True))
joined("hybrid_plan", WORKLOADS["l8"], lambda idx, gp: planner.hybrid(idx, gp)[0])
joined("get_one", bgp("order/5 ?p ?o"), lambda idx, gp: probe.read(idx, gp.patterns[0]))
add("get_many", lambda spark, d: catalog(spark, d).table(SI).where(F.col("row_key").isin("order/5", "order/6", "customer/7")).select(F.col("row_key").alias("s"), "p", F.col("value").alias("o")), f"SELECT s, p, o FROM ({sql.everything()}) WHERE s IN ('order/5', 'order/6', 'customer/7')")

# --- workloads in every way --------------------------------------------------------------


def way(variant: str, gp: GraphPattern) -> Callable[[rowindex.IndexCatalog], DataFrame]:
    folded = planner.fold_filters(gp)
    if variant in ("cascade", "multiway", "row"):
        return lambda idx: planner.execute(idx, gp, variant)
    if variant == "shuffle":
        return lambda idx: shuffle_baseline.cascade(flat(idx, folded), planner.order(folded.patterns))
    if variant == "shuffle_star":
        return lambda idx: shuffle_baseline.star(flat(idx, folded), folded.patterns, "x")
    if variant == "base_scan":
        return lambda idx: shuffle_baseline.scan(flat(idx, folded), folded.patterns[0])
    return lambda idx: probe.single(idx, folded.patterns[0], local=variant == "local")


for _w, _variants in VARIANTS.items():
    for _v in _variants:
        joined(f"w_{_w}_{_v}", WORKLOADS[_w], (lambda run: lambda idx, gp: run(idx))(way(_v, WORKLOADS[_w])))
for _name, (_w, _text) in TEXTS.items():
    joined(f"sparql_text_{_name}", WORKLOADS[_w], (lambda text: lambda idx, gp: planner.execute(idx, parse(text), "row"))(_text))

# --- orders and costs --------------------------------------------------------------------


@query("order_rank", "SELECT * FROM (VALUES ('spo', 1), ('sxo', 2), ('spx', 3), ('xpo', 4), ('sxx', 5), ('xxo', 6), ('xpx', 7), ('xxx', 8)) t(shape, rank)")
def order_rank(spark: SparkSession, d: str) -> DataFrame:
    ranked = sorted(SHAPES, key=lambda s: ordering.rank(SHAPES[s].patterns[0]))
    return spark.createDataFrame([(s, k) for k, s in enumerate(ranked, 1)], "shape string, rank int")


@query("order_connected", "SELECT * FROM (VALUES ('static', 1, '?x rdf:type Customer'), ('static', 2, '?y rdf:type Nation'), ('static', 3, '?y within region/1'), ('static', 4, '?x inNation ?y'), ('static', 5, '?x name ?z'), ('connected', 1, '?x rdf:type Customer'), ('connected', 2, '?x inNation ?y'), ('connected', 3, '?y rdf:type Nation'), ('connected', 4, '?y within region/1'), ('connected', 5, '?x name ?z')) t(mode, place, pattern)")
def order_connected(spark: SparkSession, d: str) -> DataFrame:
    rows = [(m, k, str(p)) for m in ("static", "connected") for k, p in enumerate(planner.order(WORKLOADS["l8"].patterns, m), 1)]
    return spark.createDataFrame(rows, "mode string, place int, pattern string")


COSTED = {k: WORKLOADS[k].patterns for k in ("l4", "s1", "x1", "x2")}
STARS = ("l4", "s1", "x1")


def _prefix(w: str, k: int) -> str:
    return sql.match(COSTED[w][: k + 1])


_PHASES = {"l1": (1, 1), "l4": (4, 1), "l7": (3, 2), "l8": (4, 3), "s1": (2, 1), "s2": (8, 1), "x1": (3, 1), "x2": (3, 3), "l6": (1, 1)}


@query("phase_counts", "SELECT * FROM (VALUES " + ", ".join(f"('{w}', '{v}', {n})" for w, pair in _PHASES.items() for v, n in zip(("cascade", "multiway"), pair, strict=True)) + ") t(workload, variant, phases)")
def phase_counts(spark: SparkSession, d: str) -> DataFrame:
    return costs.phase_rows(spark, {w: WORKLOADS[w] for w in _PHASES})


add("intermediate_sizes", lambda spark, d: costs._union([costs.intermediate(catalog(spark, d), w, ps) for w, ps in COSTED.items()]), " UNION ALL ".join(sql.counted(_prefix(w, k), workload=w, step=k) for w, ps in COSTED.items() for k in range(len(ps))))


def _lookup_sql(w: str) -> str:
    n = len(COSTED[w])
    parts = [f"SELECT '{w}' AS workload, 'cascade' AS variant, CAST(sum(value) AS BIGINT) AS value FROM ({' UNION ALL '.join(sql.counted(_prefix(w, k), step=k) for k in range(n - 1))})"]
    if w in STARS:
        met = [f"SELECT count(*) AS value FROM (SELECT DISTINCT x FROM ({_prefix(w, k)}))" for k in range(n - 1)]
        parts.append(f"SELECT '{w}', 'multiway', CAST(sum(value) AS BIGINT) FROM ({' UNION ALL '.join(met)})")
        parts.append(f"SELECT '{w}', 'row', count(*) FROM ({_prefix(w, 0)})")
    return " UNION ALL ".join(parts)


add("lookup_counts", lambda spark, d: costs._union([costs.lookups(catalog(spark, d), w, ps, w in STARS) for w, ps in COSTED.items()]), " UNION ALL ".join(_lookup_sql(w) for w in COSTED))
add("multiway_lookups", lambda spark, d: costs.lookups(catalog(spark, d), "l4", COSTED["l4"], True).where("variant = 'multiway'"), f"SELECT * FROM ({_lookup_sql('l4')}) WHERE variant = 'multiway'")


def _moved_sql(w: str) -> str:
    ps = COSTED[w]
    n = len(ps)
    size = [f"(SELECT count(*) FROM ({_prefix(w, k)}))" for k in range(n)]
    ext = [f"(SELECT count(*) FROM ({sql.match([p])}))" for p in ps]
    rows = {"shuffle cascade": "+".join(size[:-1] + ext[1:]), "shuffle star": "+".join(ext), "probe returned": "+".join(size[1:]), "probe sent": "+".join(size[:-1])}
    return " UNION ALL ".join(f"SELECT '{w}' AS workload, '{k}' AS variant, CAST({v} AS BIGINT) AS value" for k, v in rows.items())


add("rows_moved", lambda spark, d: costs._union([costs.rows_moved(catalog(spark, d), w, ps) for w, ps in COSTED.items()]), " UNION ALL ".join(_moved_sql(w) for w in COSTED))
_SELECTIVE = ("l1", "l4", "l8", "s1", "s2", "s3a")
add(
    "workload_selectivity",
    lambda spark, d: costs.selectivity(catalog(spark, d), {w: planner.execute(catalog(spark, d), WORKLOADS[w], "row") for w in _SELECTIVE}),
    " UNION ALL ".join(f"SELECT '{w}' AS workload, (SELECT count(*) FROM ({sql.answer(WORKLOADS[w])})) AS answers, n AS triples FROM {_N}" for w in _SELECTIVE),
)

# --- sources, sinks, versions, maintenance ------------------------------------------------

add("scan_orders", lambda spark, d: table(spark, d, "orders").where("o_orderstatus = 'F'").select("o_orderkey", "o_custkey"), "SELECT o_orderkey, o_custkey FROM orders WHERE o_orderstatus = 'F'")
for _fmt in ("parquet", "csv", "json", "orc"):
    add("sink_roundtrip" if _fmt == "parquet" else f"sink_{_fmt}", (lambda fmt: lambda spark, d: sinks.roundtrip(planner.execute(catalog(spark, d), WORKLOADS["l8"]), fmt))(_fmt), sql.answer(WORKLOADS["l8"]))
add("nt_roundtrip", lambda spark, d: ntriples.roundtrip(triplify.triples(spark, d, ("region", "nation", "supplier", "part"))), " UNION ALL ".join(f"SELECT s, '{p}' AS p, o FROM ({' UNION ALL '.join(kept)})" for p in sql.ASSERTED if (kept := [x for x in sql.ASSERTED[p] if x.endswith((" region", " nation", " supplier", " part"))])))
add("cell_versions", lambda spark, d: rowindex.versions(table(spark, d, "events"), ["user_id"], ["ts", "event_id"], 3).select("user_id", "event_id", "version"), "SELECT user_id, event_id, CAST(version AS INTEGER) AS version FROM (SELECT user_id, event_id, row_number() OVER (PARTITION BY user_id ORDER BY ts DESC, event_id DESC) AS version FROM events) WHERE version <= 3")


@query("index_upsert", "SELECT s, 'name' AS p, o FROM (SELECT 'region/' || r_regionkey AS s, '\"' || r_name || '\"' AS o FROM region) UNION ALL SELECT 'region/99', 'name', '\"NOWHERE\"' UNION ALL SELECT 'nation/' || n_nationkey, 'name', '\"' || n_name || '\"' FROM nation WHERE n_nationkey <> 3")
def index_upsert(spark: SparkSession, d: str) -> DataFrame:
    base = triplify.triples(spark, d, ("region", "nation"), {"name"})
    new = spark.createDataFrame([("region/99", "name", '"NOWHERE"'), ("region/1", "name", '"AMERICA"')], "s string, p string, o string")
    gone = spark.createDataFrame([("nation/3", "name", '"NATION_3"')], "s string, p string, o string")
    tag = f"{spark.sparkContext.applicationId}:{d}:small"
    idx = rowindex.upsert(rowindex.build(base, tag, 2), new, gone, tag + ":2")
    return idx.table(SI).select(F.col("row_key").alias("s"), "p", F.col("value").alias("o"))


@query("region_splits", f"SELECT count(*) AS n_keys_cells, count(DISTINCT s) AS n_keys FROM ({sql.everything()})")
def region_splits(spark: SparkSession, d: str) -> DataFrame:
    """Every cell is in one range and ranges do not share keys: their sums against the index's."""
    idx = catalog(spark, d)
    splits = rowindex.split_points(idx, SI, 10_000)
    keys = idx.table(SI).select("row_key").distinct().agg(F.count("*").alias("n_keys"))
    return splits.agg(F.sum("n").alias("n_keys_cells")).crossJoin(keys)
