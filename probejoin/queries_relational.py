"""Registry of the relational, functional and user-defined queries with their SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from probejoin import oracles as sql
from probejoin.functions import terms, udfs
from probejoin.operators import probe, relational as rel
from probejoin.operators.probe import step
from probejoin.plans import planner
from probejoin.plans.access import SI
from probejoin.plans.patterns import bgp, pattern
from probejoin.plans.syntax import parse
from probejoin.queries import add, catalog, query
from probejoin.sources.storage import table
from probejoin.workloads import WORKLOADS

ANSWER = {k: sql.answer(v) for k, v in WORKLOADS.items()}


def mu(spark: SparkSession, d: str, w: str) -> DataFrame:
    """Mappings of a workload."""
    return planner.execute(catalog(spark, d), WORKLOADS[w], "row")


def on(name: str, w: str, f, oracle: str) -> None:
    """A query over the mappings of a workload; {m} in the SQL stands for them."""
    add(name, lambda spark, d: f(mu(spark, d, w)), oracle.format(m=f"({ANSWER[w]})"))


def over(name: str, tables: str, f, oracle: str) -> None:
    """A query over given tables."""
    names = tables.split()
    add(name, lambda spark, d: f(*[table(spark, d, t) for t in names]), oracle)


def both(name: str, tables: str, text: str, duck: str | None = None) -> None:
    """Expressions that both dialects write alike, or nearly so; {t} stands for the table."""
    add(name, lambda spark, d: spark.sql(text.format(t="{t}") if "{t}" in text else text, t=table(spark, d, tables)), (duck or text).replace("{t}", tables))


_num = "CAST(replace({c}, '\"', '') AS {k})"


def num(c: str, k: str = "DECIMAL(18,2)") -> str:
    return _num.format(c=c, k=k)


# --- projection and filters on mappings --------------------------------------------------

on("proj_vars", "l8", lambda m: rel.project(m, ["x", "z"]), "SELECT x, z FROM {m}")
on("proj_star", "x1", lambda m: rel.project(m, "*"), "SELECT * FROM {m}")
on("proj_bag", "x2", lambda m: rel.project(m, ["n"]), "SELECT n FROM {m}")
on("proj_distinct", "x2", lambda m: rel.distinct(m, ["n"]), "SELECT DISTINCT n FROM {m}")
on("proj_bind", "l4", lambda m: rel.bind(m, "twice", terms.decode(F.col("y2"), "decimal(18,2)") * 2).select("x", F.col("twice").cast("double").alias("twice")), "SELECT x, CAST(2 * " + num("y2") + " AS DOUBLE) AS twice FROM {m}")
on("proj_decode", "s2", lambda m: rel.decoded(m, {"d": "decimal(18,2)", "h": "date"}).select("x", F.col("d").cast("double").alias("d"), F.date_format("h", "yyyy-MM-dd").alias("h")), "SELECT x, CAST(" + num("d") + " AS DOUBLE) AS d, replace(h, '\"', '') AS h FROM {m}")
on("ask", "s1", rel.ask, "SELECT count(*) > 0 AS answer FROM {m}")
on("construct", "x2", lambda m: rel.construct(m, [("?c", "buysIn", "?n")]), "SELECT DISTINCT c AS s, 'buysIn' AS p, n AS o FROM {m}")
on("flt_cmp", "x1", lambda m: m.where(planner.condition("?y", ">", "25")), "SELECT * FROM {m} WHERE " + num("y", "INT") + " > 25")
on("flt_eq_term", "x2", lambda m: m.where(planner.condition("?c", "!=", "customer/1")), "SELECT * FROM {m} WHERE c <> 'customer/1'")
on("flt_in", "s2", lambda m: m.where(F.col("g").isin('"A"', '"R"')).select("x", "g"), "SELECT x, g FROM {m} WHERE g IN ('\"A\"', '\"R\"')")
on("flt_between", "s2", lambda m: m.where(terms.decode(F.col("d"), "decimal(18,2)").between(10, 20)).select("x", "d"), "SELECT x, d FROM {m} WHERE " + num("d") + " BETWEEN 10 AND 20")
on("flt_regex", "x1", lambda m: m.where(F.col("t").rlike("^\"(red|small) ")).select("x", "t"), "SELECT x, t FROM {m} WHERE regexp_matches(t, '^\"(red|small) ')")
on("flt_like", "x1", lambda m: m.where(F.col("t").like("%bolt%")).select("x", "t"), "SELECT x, t FROM {m} WHERE t LIKE '%bolt%'")
on("flt_termkind", "s10", lambda m: m.select("s", "pr", terms.is_iri(F.col("s")).alias("iri"), terms.is_literal(F.col("s")).alias("literal"), terms.term_kind(F.col("s")).alias("kind")), "SELECT s, pr, true AS iri, false AS literal, split_part(s, '/', 1) AS kind FROM {m}")
on("flt_predvar", "s3a", lambda m: m, "SELECT * FROM {m}")
on("flt_pushed", "s2", lambda m: m.where(terms.decode(F.col("d"), "decimal(18,2)") >= 40).select("x", "d"), "SELECT x, d FROM {m} WHERE " + num("d") + " >= 40")
over("flt_bound", "documents labels", lambda a, b: a.select("doc_id").join(b.select("doc_id", "quality"), "doc_id", "left").where(F.col("quality").isNotNull()), "SELECT d.doc_id, quality FROM documents d LEFT JOIN labels USING (doc_id) WHERE quality IS NOT NULL")
over("flt_bool", "documents labels", lambda a, b: a.join(b, "doc_id", "left").where(((F.col("quality") == 1) | (F.col("lang") == "de")) & ~(F.col("toxic") == 1)).select("doc_id"), "SELECT d.doc_id FROM documents d LEFT JOIN labels l USING (doc_id) WHERE (quality = 1 OR lang = 'de') AND NOT (toxic = 1)")
_OPT = parse("SELECT ?x ?g WHERE { ?x inNation nation/3 OPTIONAL { ?x segment ?g } }")
add("sparql_optional", lambda spark, d: planner.execute(catalog(spark, d), _OPT), f"SELECT a.s AS x, b.o AS g FROM (SELECT s FROM ({sql.of('inNation')}) WHERE o = 'nation/3') a LEFT JOIN ({sql.of('segment')}) b ON a.s = b.s")
_UNI = parse("SELECT DISTINCT ?x WHERE { { ?x inNation nation/3 } UNION { ?x supplies part/7 } } ORDER BY ?x")
add("sparql_union", lambda spark, d: planner.execute(catalog(spark, d), _UNI), f"SELECT DISTINCT s AS x FROM (SELECT s FROM ({sql.of('inNation')}) WHERE o = 'nation/3' UNION ALL SELECT s FROM ({sql.of('supplies')}) WHERE o = 'part/7')")
_FIL = parse('SELECT ?x ?v WHERE { ?x size ?v . ?x brand "Brand#17" FILTER(?v >= 30) } ORDER BY DESC ?v ?x LIMIT 5 OFFSET 2')
add("sparql_filter_order_limit", lambda spark, d: planner.execute(catalog(spark, d), _FIL), f"SELECT x, v FROM (SELECT a.s AS x, a.o AS v FROM ({sql.of('size')}) a JOIN ({sql.of('brand')}) b ON a.s = b.s WHERE b.o = '\"Brand#17\"' AND {num('a.o', 'INT')} >= 30) ORDER BY v DESC, x LIMIT 5 OFFSET 2")

# --- joins -------------------------------------------------------------------------------

_OL = "SELECT o_orderkey, o_custkey, l_partkey, l_linenumber FROM orders JOIN lineitem ON o_orderkey = l_orderkey WHERE o_orderstatus = 'F'"
_ol = lambda j: lambda o, l: j(o.where("o_orderstatus = 'F'").select("o_orderkey", "o_custkey"), l.select(F.col("l_orderkey").alias("o_orderkey"), "l_partkey", "l_linenumber"), "o_orderkey")  # noqa: E731, E741
over("join_hash", "orders lineitem", _ol(rel.hash_join), _OL)
over("join_merge", "orders lineitem", _ol(rel.merge_join), _OL)
over("join_broadcast", "customer nation", lambda c, n: rel.replicated_join(c.select("c_custkey", F.col("c_nationkey").alias("n_nationkey")), n.select("n_nationkey", "n_name"), "n_nationkey"), "SELECT n_nationkey, c_custkey, n_name FROM customer JOIN nation ON c_nationkey = n_nationkey")


def join_bucketed(spark: SparkSession, d: str) -> DataFrame:
    idx = catalog(spark, d)
    return step(probe.read(idx, pattern("?x brand ?b"), SI), idx, pattern("?x kind ?k"))


add("join_bucketed", join_bucketed, sql.match(bgp("?x brand ?b", "?x kind ?k").patterns))
over("join_theta", "nation", lambda n: n.alias("a").join(n.alias("b"), F.expr("a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey AND a.n_name <> b.n_name")).select(F.col("a.n_nationkey").alias("a"), F.col("b.n_nationkey").alias("b")), "SELECT a.n_nationkey AS a, b.n_nationkey AS b FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey AND a.n_name <> b.n_name")
_BANDS = [("low", 0.0, 100000.0), ("mid", 100000.0, 300000.0), ("high", 300000.0, 1e12)]
add("join_range", lambda spark, d: rel.range_join(table(spark, d, "orders").select("o_orderkey", "o_totalprice"), spark.createDataFrame(_BANDS, "band string, lo double, hi double"), "o_totalprice", "lo", "hi").select("o_orderkey", "band"), "SELECT o_orderkey, band FROM orders JOIN (VALUES ('low', 0.0, 100000.0), ('mid', 100000.0, 300000.0), ('high', 300000.0, 1e12)) b(band, lo, hi) ON o_totalprice >= lo AND o_totalprice < hi")
_ev = lambda e, t, p: e.where(F.col("event_type") == t).select("user_id", F.col("event_id").alias(f"{p}_id"), F.col("ts").alias(f"{p}_ts"))
over("join_interval", "events", lambda e: rel.interval_join(_ev(e, "click", "c"), _ev(e, "purchase", "p"), "user_id", "c_ts", "p_ts", 3600).select("user_id", "c_id", "p_id"), "SELECT c.user_id, c.event_id AS c_id, p.event_id AS p_id FROM events c JOIN events p ON c.user_id = p.user_id AND c.event_type = 'click' AND p.event_type = 'purchase' AND p.ts BETWEEN c.ts AND c.ts + INTERVAL 1 HOUR")
over("join_asof", "events", lambda e: rel.asof_join(e.where("event_type = 'purchase'").select("event_id", "user_id", "ts"), e.where("event_type = 'view'").select("user_id", "ts", F.col("event_id").alias("view")), ["user_id"], "ts", {"view": "last_view"}).select("event_id", "last_view"), "SELECT p.event_id, v.event_id AS last_view FROM (SELECT * FROM events WHERE event_type = 'purchase') p ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'view') v ON p.user_id = v.user_id AND p.ts > v.ts")
over("join_optional", "documents labels", lambda a, b: a.select("doc_id").join(b.select("doc_id", "quality"), "doc_id", "left"), "SELECT d.doc_id, quality FROM documents d LEFT JOIN labels USING (doc_id)")
over("join_full", "customer supplier", lambda c, s: c.groupBy(F.col("c_nationkey").alias("k")).agg(F.count("*").alias("customers")).join(s.where("s_suppkey < 20").groupBy(F.col("s_nationkey").alias("k")).agg(F.count("*").alias("suppliers")), "k", "full"), "SELECT k, customers, suppliers FROM (SELECT c_nationkey AS k, count(*) AS customers FROM customer GROUP BY 1) FULL JOIN (SELECT s_nationkey AS k, count(*) AS suppliers FROM supplier WHERE s_suppkey < 20 GROUP BY 1) USING (k)")
for _n, _how, _not in (("join_semi", "left_semi", ""), ("join_anti", "left_anti", "NOT ")):
    over(_n, "customer orders", (lambda how: lambda c, o: c.select("c_custkey").join(o.where("o_orderpriority = '1-URGENT'").select(F.col("o_custkey").alias("c_custkey")), "c_custkey", how))(_how), f"SELECT c_custkey FROM customer WHERE {_not}EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderpriority = '1-URGENT')")
over("join_cross", "region customer", lambda r, c: r.select("r_name").crossJoin(c.select("c_mktsegment").distinct()), "SELECT r_name, c_mktsegment FROM region, (SELECT DISTINCT c_mktsegment FROM customer)")
over("join_self", "supplier", lambda s: s.alias("a").join(s.alias("b"), F.expr("a.s_nationkey = b.s_nationkey AND a.s_suppkey < b.s_suppkey")).select(F.col("a.s_suppkey").alias("a"), F.col("b.s_suppkey").alias("b")), "SELECT a.s_suppkey AS a, b.s_suppkey AS b FROM supplier a JOIN supplier b ON a.s_nationkey = b.s_nationkey AND a.s_suppkey < b.s_suppkey")
over("join_nullsafe", "documents labels", lambda a, b: a.join(b, "doc_id", "left").groupBy("source", "quality").agg(F.count("*").alias("n")).alias("x").join(b.select("quality").unionByName(b.select(F.lit(None).cast("int").alias("quality")).limit(1)).distinct().alias("y"), F.col("x.quality").eqNullSafe(F.col("y.quality"))).select("source", F.col("x.quality").alias("quality"), "n"), "SELECT source, quality, count(*) AS n FROM documents LEFT JOIN labels USING (doc_id) GROUP BY 1, 2")
add("join_lateral", lambda spark, d: spark.sql("SELECT c_custkey, t.o_orderkey FROM {c}, LATERAL (SELECT o_orderkey FROM {o} WHERE o_custkey = c_custkey ORDER BY o_totalprice DESC, o_orderkey LIMIT 2) t", c=table(spark, d, "customer"), o=table(spark, d, "orders")), "SELECT o_custkey AS c_custkey, o_orderkey FROM orders QUALIFY row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) <= 2")
over("join_chain_reorder", "region nation customer orders lineitem", lambda r, n, c, o, l: r.where("r_name = 'ASIA'").join(n, F.col("r_regionkey") == F.col("n_regionkey")).join(c, F.col("n_nationkey") == F.col("c_nationkey")).join(o, F.col("c_custkey") == F.col("o_custkey")).join(l, F.col("o_orderkey") == F.col("l_orderkey")).groupBy("n_name").agg(F.count("*").alias("n"), F.sum(F.col("l_extendedprice").cast("decimal(18,2)")).cast("double").alias("total")), "SELECT n_name, count(*) AS n, CAST(sum(CAST(l_extendedprice AS DECIMAL(18,2))) AS DOUBLE) AS total FROM region JOIN nation ON r_regionkey = n_regionkey JOIN customer ON n_nationkey = c_nationkey JOIN orders ON c_custkey = o_custkey JOIN lineitem ON o_orderkey = l_orderkey WHERE r_name = 'ASIA' GROUP BY n_name")  # noqa: E741

# --- aggregation -------------------------------------------------------------------------

_dec = lambda c: F.col(c).cast("decimal(18,2)")
over("agg_basic", "lineitem", lambda t: t.groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.sum(_dec("l_quantity")).cast("double").alias("quantity"), F.round(F.avg("l_discount"), 6).alias("discount"), F.min("l_extendedprice").alias("low"), F.max("l_extendedprice").alias("high")), "SELECT l_returnflag, l_linestatus, count(*) AS n, CAST(sum(CAST(l_quantity AS DECIMAL(18,2))) AS DOUBLE) AS quantity, round(avg(l_discount), 6) AS discount, min(l_extendedprice) AS low, max(l_extendedprice) AS high FROM lineitem GROUP BY 1, 2")
over("agg_global", "orders", lambda t: t.agg(F.count("*").alias("n"), F.sum(_dec("o_totalprice")).cast("double").alias("total")), "SELECT count(*) AS n, CAST(sum(CAST(o_totalprice AS DECIMAL(18,2))) AS DOUBLE) AS total FROM orders")
over("agg_distinct", "lineitem", lambda t: t.groupBy("l_suppkey").agg(F.count_distinct("l_partkey").alias("parts"), F.sum_distinct("l_linenumber").alias("numbers")), "SELECT l_suppkey, count(DISTINCT l_partkey) AS parts, CAST(sum(DISTINCT l_linenumber) AS BIGINT) AS numbers FROM lineitem GROUP BY 1")
add("agg_approx", lambda spark, d: table(spark, d, "lineitem").groupBy("l_suppkey").agg(F.approx_count_distinct("l_partkey").alias("parts")))
over("agg_collect", "lineitem", lambda t: t.where("l_suppkey < 5").groupBy("l_suppkey").agg(F.array_join(F.transform(F.sort_array(F.collect_set("l_linenumber")), lambda x: x.cast("string")), ",").alias("numbers")), "SELECT l_suppkey, string_agg(CAST(l_linenumber AS VARCHAR), ',' ORDER BY l_linenumber) AS numbers FROM (SELECT DISTINCT l_suppkey, l_linenumber FROM lineitem WHERE l_suppkey < 5) GROUP BY 1")
over("agg_percentile", "orders", lambda t: t.groupBy("o_orderstatus").agg(F.round(F.percentile("o_totalprice", 0.5), 4).alias("median")), "SELECT o_orderstatus, round(quantile_cont(o_totalprice, 0.5), 4) AS median FROM orders GROUP BY 1")
over("agg_having", "orders", lambda t: t.groupBy("o_custkey").agg(F.count("*").alias("n")).where("n > 12"), "SELECT o_custkey, count(*) AS n FROM orders GROUP BY 1 HAVING count(*) > 12")
over("agg_filter", "orders", lambda t: t.groupBy("o_orderpriority").agg(F.count_if(F.col("o_orderstatus") == "F").alias("f"), F.count_if(F.col("o_totalprice") > 200000).alias("dear")), "SELECT o_orderpriority, count(*) FILTER (WHERE o_orderstatus = 'F') AS f, count(*) FILTER (WHERE o_totalprice > 200000) AS dear FROM orders GROUP BY 1")
_GS = "SELECT o_orderstatus, o_orderpriority, {g} AS gid, count(*) AS n FROM orders GROUP BY {k}"
add("agg_gsets", lambda spark, d: spark.sql("SELECT o_orderstatus, o_orderpriority, CAST(grouping_id() AS INT) AS gid, count(*) AS n FROM {t} GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())", t=table(spark, d, "orders")).select("o_orderstatus", "o_orderpriority", "gid", "n"), "SELECT o_orderstatus, o_orderpriority, CAST(grouping_id(o_orderstatus, o_orderpriority) AS INT) AS gid, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())")
for _n in ("cube", "rollup"):
    over(f"agg_{_n}", "orders", (lambda k: lambda t: getattr(t, k)("o_orderstatus", "o_orderpriority").agg(F.grouping_id().cast("int").alias("gid"), F.count("*").alias("n")))(_n), _GS.format(g="CAST(grouping_id(o_orderstatus, o_orderpriority) AS INT)", k=f"{_n.upper()} (o_orderstatus, o_orderpriority)"))
_TYPES = ["click", "error", "purchase", "signup", "view"]
over("agg_pivot", "events", lambda t: t.groupBy("user_id").pivot("event_type", _TYPES).agg(F.count(F.lit(1))).na.fill(0), "SELECT user_id, " + ", ".join(f"count(*) FILTER (WHERE event_type = '{k}') AS {k}" for k in _TYPES) + " FROM events GROUP BY 1")
over("agg_unpivot", "part", lambda t: t.select("p_partkey", "p_brand", "p_type").unpivot("p_partkey", ["p_brand", "p_type"], "field", "value"), "SELECT p_partkey, 'p_brand' AS field, p_brand AS value FROM part UNION ALL SELECT p_partkey, 'p_type', p_type FROM part")
over("agg_sorted", "part", lambda t: t.groupBy("p_brand").agg(F.max("p_name").alias("last"), F.min("p_name").alias("first")), "SELECT p_brand, max(p_name) AS last, min(p_name) AS first FROM part GROUP BY 1")
over("agg_stats", "lineitem", lambda t: t.agg(F.round(F.stddev_samp("l_quantity"), 4).alias("sd"), F.round(F.var_pop("l_quantity"), 4).alias("v"), F.round(F.corr("l_quantity", "l_extendedprice"), 4).alias("r"), F.round(F.covar_samp("l_quantity", "l_discount"), 4).alias("c")), "SELECT round(stddev_samp(l_quantity), 4) AS sd, round(var_pop(l_quantity), 4) AS v, round(corr(l_quantity, l_extendedprice), 4) AS r, round(covar_samp(l_quantity, l_discount), 4) AS c FROM lineitem")
over("agg_argmax", "orders", lambda t: t.groupBy("o_custkey").agg(F.max_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("dearest"), F.min_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("cheapest")), "SELECT o_custkey, max_by(o_orderkey, (o_totalprice, o_orderkey)) AS dearest, min_by(o_orderkey, (o_totalprice, o_orderkey)) AS cheapest FROM orders GROUP BY 1")
add("agg_predicate_counts", lambda spark, d: catalog(spark, d).triples.groupBy("p").agg(F.count("*").alias("n"), F.count_distinct("s").alias("subjects"), F.count_distinct("o").alias("objects")), f"SELECT p, count(*) AS n, count(DISTINCT s) AS subjects, count(DISTINCT o) AS objects FROM ({sql.everything()}) GROUP BY p")

# --- windows -----------------------------------------------------------------------------

_w = lambda: W.partitionBy("o_custkey").orderBy("o_totalprice", "o_orderkey")
_WO = "OVER (PARTITION BY o_custkey ORDER BY o_totalprice, o_orderkey)"
over("win_rank", "orders", lambda t: t.select("o_orderkey", F.row_number().over(_w()).alias("rn"), F.rank().over(_w()).alias("rk"), F.dense_rank().over(_w()).alias("dr"), F.ntile(4).over(_w()).alias("nt"), F.round(F.percent_rank().over(_w()), 6).alias("pr"), F.round(F.cume_dist().over(_w()), 6).alias("cd")), f"SELECT o_orderkey, row_number() {_WO} AS rn, rank() {_WO} AS rk, dense_rank() {_WO} AS dr, ntile(4) {_WO} AS nt, round(percent_rank() {_WO}, 6) AS pr, round(cume_dist() {_WO}, 6) AS cd FROM orders")
_we = lambda: W.partitionBy("user_id").orderBy("ts", "event_id")
_WE = "(PARTITION BY user_id ORDER BY ts, event_id)"
over("win_analytic", "events", lambda t: t.select("event_id", F.lag("event_id").over(_we()).alias("before"), F.lead("event_id").over(_we()).alias("after"), F.first("event_id").over(_we()).alias("first"), F.nth_value("event_id", 2).over(_we()).alias("second")), f"SELECT event_id, lag(event_id) OVER {_WE} AS before, lead(event_id) OVER {_WE} AS after, first_value(event_id) OVER {_WE} AS first, nth_value(event_id, 2) OVER {_WE} AS second FROM events")
over("win_rows", "orders", lambda t: t.select("o_orderkey", F.sum(_dec("o_totalprice")).over(W.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey").rowsBetween(W.unboundedPreceding, 0)).cast("double").alias("running")), "SELECT o_orderkey, CAST(sum(CAST(o_totalprice AS DECIMAL(18,2))) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS UNBOUNDED PRECEDING) AS DOUBLE) AS running FROM orders")
over("win_range", "orders", lambda t: t.withColumn("day", F.datediff("o_orderdate", F.lit("1990-01-01"))).select("o_orderkey", F.count("*").over(W.partitionBy("o_custkey").orderBy("day").rangeBetween(-30, 0)).alias("n")), "SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY day RANGE BETWEEN 30 PRECEDING AND CURRENT ROW) AS n FROM (SELECT *, datediff('day', DATE '1990-01-01', CAST(o_orderdate AS DATE)) AS day FROM orders)")
over("win_moving", "events", lambda t: t.select("event_id", F.round(F.avg("value").over(_we().rowsBetween(-1, 1)), 4).alias("mean")), "SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 1 PRECEDING AND 1 FOLLOWING), 4) AS mean FROM events")
over("win_topk", "lineitem", lambda t: rel.top_k(t, ["l_orderkey"], [F.desc("l_extendedprice"), F.asc("l_linenumber"), F.asc("l_partkey")], 3).select("l_orderkey", "l_partkey", "place"), "SELECT l_orderkey, l_partkey, CAST(place AS INT) AS place FROM (SELECT l_orderkey, l_partkey, row_number() OVER (PARTITION BY l_orderkey ORDER BY l_extendedprice DESC, l_linenumber, l_partkey) AS place FROM lineitem) WHERE place <= 3")
over("win_share", "customer", lambda t: t.select("c_custkey", F.round(F.col("c_acctbal") / F.sum("c_acctbal").over(W.partitionBy("c_nationkey")), 6).alias("share")), "SELECT c_custkey, round(c_acctbal / sum(c_acctbal) OVER (PARTITION BY c_nationkey), 6) AS share FROM customer")
over("win_sessions", "events", lambda t: rel.sessions(t, "user_id", "ts", "event_id", 86400).select("event_id", "session"), f"SELECT event_id, CAST(sum(fresh) OVER {_WE} AS BIGINT) AS session FROM (SELECT *, CASE WHEN ts - lag(ts) OVER {_WE} <= INTERVAL 1 DAY THEN 0 ELSE 1 END AS fresh FROM events)")

# --- sorts, limits, sets, subqueries -----------------------------------------------------

on("sort_multi", "s2", lambda m: m.select("x", "h").orderBy(F.desc("h"), "x"), "SELECT x, h FROM {m} ORDER BY h DESC, x")
over("sort_nulls", "documents labels", lambda a, b: a.select("doc_id").join(b, "doc_id", "left").select("doc_id", "quality").orderBy(F.asc_nulls_last("quality"), F.desc("doc_id")), "SELECT d.doc_id, quality FROM documents d LEFT JOIN labels USING (doc_id) ORDER BY quality NULLS LAST, doc_id DESC")
over("limit_offset", "orders", lambda t: t.orderBy(F.desc("o_totalprice"), "o_orderkey").select("o_orderkey").offset(10).limit(20), "SELECT o_orderkey FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20 OFFSET 10")
over("topk", "orders", lambda t: t.orderBy(F.desc("o_totalprice"), "o_orderkey").select("o_orderkey", "o_totalprice").limit(10), "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10")
add("sort_within", lambda spark, d: catalog(spark, d).table(SI, [("brand", None)]).where("p = 'brand'").repartition(4, "row_key").sortWithinPartitions("row_key").select("row_key", "value"))
_NC, _NS = ("c_nationkey", "customer"), ("s_nationkey", "supplier")
_sets = {"set_union": ("unionAll", "UNION ALL"), "set_union_distinct": (None, "UNION"), "set_intersect": ("intersect", "INTERSECT"), "set_intersect_all": ("intersectAll", "INTERSECT ALL"), "set_except": ("subtract", "EXCEPT"), "set_except_all": ("exceptAll", "EXCEPT ALL")}
for _n, (_m, _s) in _sets.items():
    over(_n, "customer supplier", (lambda m: lambda c, s: (lambda a, b: a.unionAll(b).distinct() if m is None else getattr(a, m)(b))(c.where("c_nationkey > 4").select(F.col("c_nationkey").alias("k")), s.where("s_nationkey < 20").select(F.col("s_nationkey").alias("k"))))(_m), f"SELECT c_nationkey AS k FROM customer WHERE c_nationkey > 4 {_s} SELECT s_nationkey AS k FROM supplier WHERE s_nationkey < 20")


def texts(name: str, tables: str, text: str, duck: str | None = None) -> None:
    names = tables.split()
    add(name, lambda spark, d: spark.sql(text, **{n: table(spark, d, n) for n in names}), duck or text.replace("{", "").replace("}", ""))


texts("sub_scalar", "orders", "SELECT o_orderkey FROM {orders} WHERE o_totalprice > (SELECT 1.5 * avg(o_totalprice) FROM {orders})")
texts("sub_exists", "customer orders", "SELECT c_custkey FROM {customer} WHERE EXISTS (SELECT 1 FROM {orders} WHERE o_custkey = c_custkey AND o_orderstatus = 'P')")
texts("sub_in", "nation region", "SELECT n_name FROM {nation} WHERE n_regionkey IN (SELECT r_regionkey FROM {region} WHERE r_name LIKE 'A%')")
texts("sub_cte", "orders", "WITH t AS (SELECT o_custkey, count(*) AS n FROM {orders} GROUP BY o_custkey) SELECT o_custkey, n FROM t WHERE n = (SELECT max(n) FROM t)")
texts("sub_recursive", "nation customer", "WITH RECURSIVE e(a, b) AS (SELECT concat('customer/', c_custkey), concat('nation/', c_nationkey) FROM {customer} UNION ALL SELECT concat('nation/', n_nationkey), concat('region/', n_regionkey) FROM {nation}), r(a, b) AS (SELECT a, b FROM e UNION ALL SELECT r.a, e.b FROM r JOIN e ON r.b = e.a) SELECT a, b FROM r")

# --- scalar functions --------------------------------------------------------------------

over("fn_term", "customer", lambda t: t.select(terms.iri("customer", "c_custkey").alias("r"), terms.literal("c_name").alias("l"), terms.local_id(terms.iri("customer", "c_custkey")).alias("i"), terms.lexical(terms.literal("c_name")).alias("x"), terms.term_kind(terms.literal("c_name")).alias("k")), "SELECT 'customer/' || c_custkey AS r, '\"' || c_name || '\"' AS l, CAST(c_custkey AS VARCHAR) AS i, c_name AS x, 'literal' AS k FROM customer")
over("fn_string", "part", lambda t: t.select("p_partkey", F.concat_ws("-", "p_name", "p_brand").alias("a"), F.upper("p_name").alias("b"), F.length("p_name").alias("c"), F.substring("p_name", 2, 3).alias("d"), F.replace(F.col("p_name"), F.lit("e"), F.lit("E")).alias("e"), F.trim(F.concat(F.lit("  "), "p_name")).alias("f"), F.split_part(F.col("p_name"), F.lit(" "), F.lit(2)).alias("g"), F.lpad(F.col("p_size").cast("string"), 5, "0").alias("h"), F.instr("p_name", "i").alias("i"), F.reverse("p_name").alias("j")), "SELECT p_partkey, concat_ws('-', p_name, p_brand) AS a, upper(p_name) AS b, CAST(length(p_name) AS INT) AS c, substring(p_name, 2, 3) AS d, replace(p_name, 'e', 'E') AS e, trim('  ' || p_name) AS f, split_part(p_name, ' ', 2) AS g, lpad(CAST(p_size AS VARCHAR), 5, '0') AS h, CAST(instr(p_name, 'i') AS INT) AS i, reverse(p_name) AS j FROM part")
over("fn_string_distance", "part", lambda t: t.select("p_partkey", F.levenshtein("p_name", F.lit("red bolt")).alias("d")), "SELECT p_partkey, CAST(levenshtein(p_name, 'red bolt') AS INT) AS d FROM part")
over("fn_regex", "supplier", lambda t: t.select("s_suppkey", F.regexp_extract("s_name", "#0*([0-9]+)$", 1).alias("a"), F.regexp_replace("s_name", "[0-9]", "9").alias("b"), F.col("s_name").rlike("7$").alias("c")), "SELECT s_suppkey, regexp_extract(s_name, '#0*([0-9]+)$', 1) AS a, regexp_replace(s_name, '[0-9]', '9', 'g') AS b, regexp_matches(s_name, '7$') AS c FROM supplier")
over("fn_text", "documents", lambda t: t.select("doc_id", F.size(F.split("text", "\n")).alias("lines"), F.char_length("text").alias("chars"), F.length(F.regexp_replace("text", "[^ ]", "")).alias("blanks")), "SELECT doc_id, CAST(length(text) - length(replace(text, chr(10), '')) + 1 AS INT) AS lines, CAST(length(text) AS INT) AS chars, CAST(length(regexp_replace(text, '[^ ]', '', 'g')) AS INT) AS blanks FROM documents")
over("fn_date", "orders", lambda t: t.select("o_orderkey", F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"), F.quarter("o_orderdate").alias("q"), F.date_format(F.date_trunc("month", "o_orderdate"), "yyyy-MM-dd").alias("t"), F.datediff("o_orderdate", F.lit("1995-01-01")).alias("n"), F.date_format(F.add_months("o_orderdate", 2), "yyyy-MM-dd").alias("a"), F.date_format(F.last_day("o_orderdate"), "yyyy-MM-dd").alias("l")), "SELECT o_orderkey, CAST(year(o_orderdate) AS INT) AS y, CAST(month(o_orderdate) AS INT) AS m, CAST(quarter(o_orderdate) AS INT) AS q, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS t, CAST(datediff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE)) AS INT) AS n, strftime(o_orderdate + INTERVAL 2 MONTH, '%Y-%m-%d') AS a, strftime(last_day(o_orderdate), '%Y-%m-%d') AS l FROM orders")
over("fn_interval", "orders lineitem", lambda o, t: o.join(t, F.col("o_orderkey") == F.col("l_orderkey")).select("o_orderkey", "l_linenumber", "l_partkey", F.datediff("l_shipdate", "o_orderdate").alias("days")), "SELECT o_orderkey, l_linenumber, l_partkey, CAST(datediff('day', CAST(o_orderdate AS DATE), CAST(l_shipdate AS DATE)) AS INT) AS days FROM orders JOIN lineitem ON o_orderkey = l_orderkey")
over("fn_ts", "events", lambda t: t.select("event_id", F.hour("ts").alias("h"), F.minute("ts").alias("mi"), F.date_format(F.date_trunc("minute", "ts"), "yyyy-MM-dd HH:mm:ss").alias("m")), "SELECT event_id, CAST(hour(ts) AS INT) AS h, CAST(minute(ts) AS INT) AS mi, strftime(date_trunc('minute', ts), '%Y-%m-%d %H:%M:%S') AS m FROM events")
over("fn_math", "lineitem", lambda t: t.select("l_orderkey", "l_partkey", F.floor("l_quantity").alias("a"), F.ceil("l_discount").alias("b"), F.round(F.sqrt("l_quantity"), 6).alias("c"), F.round(F.ln("l_quantity"), 6).alias("d"), F.round(F.pow("l_quantity", F.lit(1.5)), 4).alias("e"), (F.col("l_orderkey") % 7).alias("f"), F.signum(F.col("l_quantity") - 20).alias("g"), F.greatest("l_orderkey", "l_partkey").alias("h"), F.least("l_orderkey", "l_partkey").alias("i")), "SELECT l_orderkey, l_partkey, CAST(floor(l_quantity) AS BIGINT) AS a, CAST(ceil(l_discount) AS BIGINT) AS b, round(sqrt(l_quantity), 6) AS c, round(ln(l_quantity), 6) AS d, round(pow(l_quantity, 1.5), 4) AS e, l_orderkey % 7 AS f, CAST(sign(l_quantity - 20) AS DOUBLE) AS g, greatest(l_orderkey, l_partkey) AS h, least(l_orderkey, l_partkey) AS i FROM lineitem")
over("fn_decimal", "lineitem", lambda t: t.groupBy("l_suppkey").agg(F.sum((_dec("l_extendedprice") * (F.lit(1).cast("decimal(18,2)") - _dec("l_discount"))).cast("decimal(30,4)")).cast("double").alias("revenue")), "SELECT l_suppkey, CAST(sum(CAST(CAST(l_extendedprice AS DECIMAL(18,2)) * (CAST(1 AS DECIMAL(18,2)) - CAST(l_discount AS DECIMAL(18,2))) AS DECIMAL(30,4))) AS DOUBLE) AS revenue FROM lineitem GROUP BY 1")
over("fn_array", "embeddings", lambda t: t.select("vec_id", F.size("embedding").alias("n"), F.array_position(F.sequence(F.lit(5), F.lit(9)), F.lit(7)).alias("p"), F.array_join(F.transform(F.array_union(F.array(F.lit(1), F.lit(2)), F.array(F.col("label"), F.lit(2))), lambda x: x.cast("string")), ",").alias("u"), F.size(F.slice("embedding", 3, 4)).alias("s")), "SELECT vec_id, CAST(len(embedding) AS INT) AS n, CAST(3 AS BIGINT) AS p, CASE WHEN label IN (1, 2) THEN '1,2' ELSE '1,2,' || label END AS u, 4 AS s FROM embeddings")
over("fn_explode", "embeddings", lambda t: t.select("vec_id", F.posexplode(F.slice("embedding", 1, 3)).alias("at", "x")).select("vec_id", "at", F.round(F.col("x").cast("double"), 5).alias("x")), "SELECT vec_id, CAST(k AS INT) AS at, round(CAST(embedding[k + 1] AS DOUBLE), 5) AS x FROM embeddings, range(3) r(k)")
over("fn_array_hof", "embeddings", lambda t: t.select("vec_id", F.size(F.filter("embedding", lambda x: x > 0)).alias("up"), F.exists("embedding", lambda x: x > 0.4).alias("some"), F.forall("embedding", lambda x: x < 1.5).alias("every"), F.round(F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double")), 4).alias("total")), "SELECT vec_id, CAST(len([x for x in embedding if x > 0]) AS INT) AS up, len([x for x in embedding if x > 0.4]) > 0 AS some, len([x for x in embedding if x < 1.5]) = len(embedding) AS every, round(list_sum([CAST(x AS DOUBLE) for x in embedding]), 4) AS total FROM embeddings")


@query("fn_map", f"SELECT s AS row_key, string_agg(DISTINCT p, ',' ORDER BY p) AS names, bool_or(p = 'brand') AS branded, count(DISTINCT p) AS n FROM ({sql.everything()}) WHERE s LIKE 'part/%' GROUP BY s")
def fn_map(spark: SparkSession, d: str) -> DataFrame:
    from probejoin.operators.rowindex import row_view

    rows = row_view(catalog(spark, d)).where(F.col("row_key").startswith("part/"))
    return rows.select("row_key", F.array_join(F.sort_array(F.map_keys("cells")), ",").alias("names"), F.map_contains_key("cells", "brand").alias("branded"), F.size(F.map_filter("cells", lambda k, v: F.size(v) > 0)).cast("long").alias("n"))


over("fn_struct", "events", lambda t: t.select("event_id", F.from_json("props", "k int").getField("k").alias("k")), "SELECT event_id, CAST(json_extract(props, '$.k') AS INT) AS k FROM events")
over("fn_json", "events", lambda t: t.select("event_id", F.get_json_object("props", "$.k").alias("k"), F.to_json(F.struct("event_id", "event_type")).alias("j")), "SELECT event_id, CAST(json_extract(props, '$.k') AS VARCHAR) AS k, '{\"event_id\":' || event_id || ',\"event_type\":\"' || event_type || '\"}' AS j FROM events")
over("fn_url", "pages", lambda t: t.select("page_id", F.parse_url("url", F.lit("HOST")).alias("host"), F.parse_url("url", F.lit("PATH")).alias("path"), F.parse_url("url", F.lit("QUERY")).alias("query")), "SELECT page_id, regexp_extract(url, '://([^/?#]*)', 1) AS host, regexp_extract(url, '://[^/?#]*([^?#]*)', 1) AS path, nullif(regexp_extract(url, '\\?([^#]*)', 1), '') AS query FROM pages")
over("fn_cond", "documents labels", lambda a, b: a.join(b, "doc_id", "left").select("doc_id", F.coalesce("quality", F.lit(-1)).alias("q"), F.when(F.col("toxic") == 1, "bad").when(F.col("toxic") == 0, "good").otherwise("none").alias("t"), F.nullif(F.col("lang"), F.lit("en")).alias("l"), F.nvl(F.col("toxic"), F.lit(9)).alias("n")), "SELECT d.doc_id, coalesce(quality, -1) AS q, CASE WHEN toxic = 1 THEN 'bad' WHEN toxic = 0 THEN 'good' ELSE 'none' END AS t, nullif(lang, 'en') AS l, coalesce(toxic, 9) AS n FROM documents d LEFT JOIN labels USING (doc_id)")
over("fn_cast", "part", lambda t: t.select("p_partkey", F.col("p_size").cast("string").alias("a"), F.col("p_name").try_cast("int").alias("b"), F.split_part(F.col("p_brand"), F.lit("#"), F.lit(2)).cast("int").alias("c"), F.date_format(F.lit("2024-02-03").cast("date"), "yyyy-MM-dd").alias("d")), "SELECT p_partkey, CAST(p_size AS VARCHAR) AS a, TRY_CAST(p_name AS INT) AS b, CAST(split_part(p_brand, '#', 2) AS INT) AS c, '2024-02-03' AS d FROM part")
over("fn_hash", "part", lambda t: t.select("p_partkey", F.sha2("p_name", 256).alias("a"), F.md5(F.col("p_name").cast("binary")).alias("b")), "SELECT p_partkey, sha256(p_name) AS a, md5(p_name) AS b FROM part")
add("fn_bucket", lambda spark, d: table(spark, d, "part").select(F.pmod(F.hash("p_name"), F.lit(16)).alias("bucket"), F.xxhash64("p_name").alias("h")).groupBy("bucket").agg(F.count("*").alias("n")))
over("fn_vector", "embeddings", lambda t: t.select("vec_id", F.round(F.sqrt(F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double"))), 4).alias("norm"), F.round(F.aggregate(F.zip_with("embedding", F.reverse("embedding"), lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda a, x: a + x), 4).alias("dot")), "SELECT vec_id, round(sqrt(list_sum([CAST(x AS DOUBLE) * CAST(x AS DOUBLE) for x in embedding])), 4) AS norm, round(list_sum([CAST(embedding[i] AS DOUBLE) * CAST(embedding[len(embedding) + 1 - i] AS DOUBLE) for i in range(1, len(embedding) + 1)]), 4) AS dot FROM embeddings")

# --- user-defined functions --------------------------------------------------------------

on("udf_termkind", "s10", lambda m: m.select("s", "pr", udfs.term_kind_udf("s").alias("kind")), "SELECT s, pr, split_part(s, '/', 1) AS kind FROM {m}")
add("udaf_fanout", lambda spark, d: catalog(spark, d).table(SI, [("supplies", None), ("name", None)]).where("p in ('supplies', 'name')").groupBy("row_key", "p").agg(F.count("*").alias("n")).groupBy("row_key").agg(udfs.mapping_product_size("n").alias("fanout")), f"SELECT s AS row_key, CAST(product(n) AS BIGINT) AS fanout FROM (SELECT s, p, count(*) AS n FROM (SELECT s, 'supplies' AS p FROM ({sql.of('supplies')}) UNION ALL SELECT s, 'name' FROM ({sql.of('name')})) GROUP BY 1, 2) GROUP BY 1")
add("cogroup_join", lambda spark, d: udfs.cogroup_join(table(spark, d, "customer").select("c_custkey", "c_mktsegment"), table(spark, d, "orders").select(F.col("o_custkey").alias("c_custkey"), "o_orderkey"), "c_custkey", "c_custkey long, c_mktsegment string, o_orderkey long"), "SELECT c_custkey, c_mktsegment, o_orderkey FROM customer JOIN orders ON c_custkey = o_custkey")
add("udtf_variables", lambda spark, d: udfs.pattern_variables(spark, spark.createDataFrame([(k, " . ".join(map(str, v.patterns))) for k, v in WORKLOADS.items()], "name string, body string")), "SELECT * FROM (VALUES " + ", ".join(f"('{k}', '{v}')" for k, g in WORKLOADS.items() for v in dict.fromkeys(x for p in g.patterns for x in p.vars)) + ") t(name, variable)")
add("udtf_lookup", lambda spark, d: udfs.rowwise_lookup(spark, catalog(spark, d).table(SI, [("inRegion", None)]).where("p = 'inRegion'"), catalog(spark, d).table(SI, [("inNation", None)]).where("p = 'inNation' and value in ('nation/3', 'nation/4')").select("row_key", F.col("value").alias("n"))), f"SELECT a.s AS row_key, a.o AS n, b.o AS r FROM ({sql.of('inNation')}) a JOIN ({sql.of('inRegion')}) b ON a.o = b.s WHERE a.o IN ('nation/3', 'nation/4')")
