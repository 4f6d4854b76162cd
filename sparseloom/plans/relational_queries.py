"""Driver queries of the surrounding relational operators: scans, expressions, joins, aggregates, windows, sets, UDFs."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import vectors
from ..operators import relational
from ..sources import generator, graphs, tables
from . import sampling_queries as sq

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    """Register a query over the given tables (one argument) or over (tables, spark)."""

    def add(f):
        wide = f.__code__.co_argcount == 2
        QUERIES[name] = lambda spark, d: f(tables.load(spark, d), spark) if wide else f(tables.load(spark, d))
        if sql is not None:
            ORACLES[name] = sql
        return f

    return add


def _n(alias: str = "n"):
    return F.count(F.lit(1)).alias(alias)


def same_sql(name: str, sql: str, *views: str) -> None:
    """A query whose text both engines understand."""
    QUERIES[name] = lambda spark, d: tables.load(spark, d).register_views(*views).sql(sql)
    ORACLES[name] = sql


def L(c):
    return F.col(c).cast("long") if isinstance(c, str) else c.cast("long")


# ------------------------------------------------------------------ scans, sources, sinks

query("scan_pushdown", "SELECT l_orderkey, l_quantity FROM lineitem WHERE l_shipdate >= TIMESTAMP '1995-01-01' AND l_quantity > 45")(
    lambda t: t.lineitem.where((F.col("l_shipdate") >= F.lit("1995-01-01").cast("timestamp")) & (F.col("l_quantity") > 45)).select("l_orderkey", "l_quantity")
)
same_sql("sql_view", "SELECT c_mktsegment, count(*) AS n, round(sum(c_acctbal), 2) AS balance FROM customer GROUP BY c_mktsegment", "customer")
QUERIES["sql_params"] = lambda spark, d: tables.load(spark, d).register_views("orders").sql("SELECT o_orderkey, o_totalprice FROM orders WHERE o_orderstatus = :status AND o_totalprice > :least", args={"status": "O", "least": 100000.0})
ORACLES["sql_params"] = "SELECT o_orderkey, o_totalprice FROM orders WHERE o_orderstatus = 'O' AND o_totalprice > 100000.0"


@query("edges_roundtrip", f"SELECT src, dst, CAST(1 AS BIGINT) AS val, CAST(5 AS BIGINT) AS formats FROM ({sq.SUPPLIES})")
def edges_roundtrip(t, spark):
    edges, out = graphs.supplies_graph(t), None
    for fmt in ("parquet", "orc", "csv", "json", "text"):
        back = tables.read_edges(spark, tables.write_edges(edges, tables.shared_folder(spark, f"edges-{fmt}"), fmt), fmt)
        out = back if out is None else out.unionByName(back)
    return out.groupBy("src", "dst", "val").agg(_n("formats"))


@query("bucketed_join", f"SELECT e.src, count(*) AS n FROM ({sq.SUPPLIES}) e JOIN supplier ON e.src = s_suppkey GROUP BY 1")
def bucketed_join(t, spark):
    import uuid

    stored = tables.save_adjacency(graphs.supplies_graph(t), f"adjacency_{uuid.uuid4().hex}", 4)
    met = t.supplier.select(F.col("s_suppkey").alias("src")).hint("merge").join(stored, "src")
    return met.select("src", F.size("nbrs").cast("long").alias("n"))


@query("minibatch_files", sq.ORACLES["node_sample_1hop"].replace("SELECT * FROM h0", "SELECT batch, layer, count(*) AS n FROM h0 GROUP BY 1, 2"))
def minibatch_files(t, spark):
    path = tables.save_minibatches(sq.QUERIES["node_sample_1hop"](spark, t.sf_dir), tables.shared_folder(spark, "minibatches"), 4)
    return spark.read.parquet(path).groupBy("batch", L("layer").alias("layer")).agg(_n())


_X = "((i % 2147483647 * 48271 + 1 + 84 * 69621) % 2147483647)"
_U = f"(({_X} * {_X} % 2147483647 * 69621 + i) % 2147483647 / 2147483647.0::DOUBLE)"


@query("generated_graph", f"SELECT CAST(floor(2000::DOUBLE * u * u * u) AS BIGINT) AS src, count(*) AS deg FROM (SELECT {_U} AS u FROM (SELECT o_orderkey AS i FROM orders)) GROUP BY 1")
def generated_graph(t, spark):
    """The generator makes the edge of each order's key; orders of one key, and of none, each count."""
    orders = t.orders.select(F.col("o_orderkey").alias("i")).groupBy("i").agg(_n())
    made = generator.generated_edges_at(orders, vertices=2000, skew=3).withColumnRenamed("i", "of")
    return orders.join(made, F.col("i").eqNullSafe(F.col("of"))).groupBy("src").agg(F.sum("n").alias("deg"))


# ------------------------------------------------------------------ projection, filter, functions

query("project_basic", "SELECT l_orderkey AS k, CAST(l_linenumber AS BIGINT) AS line, round(l_extendedprice * (1 - l_discount), 4) AS net FROM lineitem")(
    lambda t: t.lineitem.select(F.col("l_orderkey").alias("k"), L("l_linenumber").alias("line"), F.round(F.col("l_extendedprice") * (1 - F.col("l_discount")), 4).alias("net"))
)
query("filter_basic", "SELECT p_partkey FROM part WHERE p_size BETWEEN 10 AND 20 AND p_brand IN ('Brand#11', 'Brand#12', 'Brand#23') AND p_name IS NOT NULL AND p_type LIKE '%S%' AND regexp_matches(p_name, '[aeiou]')")(
    lambda t: t.part.where(F.col("p_size").between(10, 20) & F.col("p_brand").isin("Brand#11", "Brand#12", "Brand#23") & F.col("p_name").isNotNull() & F.col("p_type").like("%S%") & F.col("p_name").rlike("[aeiou]")).select("p_partkey")
)
query("expr_conditional", "SELECT d.doc_id, CASE WHEN quality = 1 THEN 'good' WHEN quality = 0 THEN 'poor' ELSE 'unknown' END AS mark, CAST(coalesce(toxic, -1) AS BIGINT) AS toxic, nullif(lang, 'en') AS other FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id")(
    lambda t: t.documents.join(t.labels, "doc_id", "left").select("doc_id", F.when(F.col("quality") == 1, "good").when(F.col("quality") == 0, "poor").otherwise("unknown").alias("mark"), F.coalesce("toxic", F.lit(-1)).cast("long").alias("toxic"), F.nullif(F.col("lang"), F.lit("en")).alias("other"))
)
query(
    "fn_string",
    "SELECT page_id, lower(substr(url, 1, 8)) AS head, CAST(length(html) AS BIGINT) AS n, split_part(url, '/', 3) AS host, md5(url) AS h, trim('  x ') || '-' || upper(split_part(url, '/', 4)) AS tag, regexp_replace(url, '[0-9]+', '#', 'g') AS shape FROM pages",
)(
    lambda t: t.pages.select(
        "page_id", F.lower(F.substring("url", 1, 8)).alias("head"), L(F.length("html")).alias("n"), F.split_part("url", F.lit("/"), F.lit(3)).alias("host"), F.md5("url").alias("h"),
        F.concat(F.trim(F.lit("  x ")), F.lit("-"), F.upper(F.split_part("url", F.lit("/"), F.lit(4)))).alias("tag"), F.regexp_replace("url", "[0-9]+", "#").alias("shape"),
    )
)
query(
    "fn_date",
    "SELECT o_orderkey, date_trunc('month', o_orderdate) AS month, CAST(year(o_orderdate) AS BIGINT) AS y, CAST(quarter(o_orderdate) AS BIGINT) AS q, CAST(date_diff('day', CAST(o_orderdate AS DATE), DATE '1998-12-31') AS BIGINT) AS days, o_orderdate + INTERVAL 90 DAY AS due FROM orders",
)(
    lambda t: t.orders.select(
        "o_orderkey", F.date_trunc("month", "o_orderdate").alias("month"), L(F.year("o_orderdate")).alias("y"), L(F.quarter("o_orderdate")).alias("q"),
        L(F.datediff(F.lit("1998-12-31").cast("date"), F.to_date("o_orderdate"))).alias("days"), (F.col("o_orderdate") + F.expr("INTERVAL 90 DAYS")).alias("due"),
    )
)
query("fn_math", "SELECT l_orderkey, l_linenumber, round(log2(l_quantity), 6) AS a, round(sqrt(l_extendedprice), 6) AS b, round(pow(l_quantity, 2), 4) AS c, l_partkey % 7 AS d, CAST(floor(l_extendedprice / 100) AS BIGINT) AS e, greatest(l_partkey, l_suppkey) AS f, l_partkey & 15 AS g FROM lineitem")(
    lambda t: t.lineitem.select(
        "l_orderkey", "l_linenumber", F.round(F.log2("l_quantity"), 6).alias("a"), F.round(F.sqrt("l_extendedprice"), 6).alias("b"), F.round(F.pow("l_quantity", F.lit(2)), 4).alias("c"), F.pmod("l_partkey", F.lit(7)).alias("d"),
        L(F.floor(F.col("l_extendedprice") / 100)).alias("e"), F.greatest("l_partkey", "l_suppkey").alias("f"), F.col("l_partkey").bitwiseAND(15).alias("g"),
    )
)
query(
    "fn_array",
    f"WITH a AS (SELECT src, list_sort(list(dst)) AS nbrs FROM ({sq.SUPPLIES}) GROUP BY src) SELECT src, CAST(list_sum(list_transform(nbrs, lambda x: x * 2)) AS BIGINT) AS twice, CAST(len(list_filter(nbrs, lambda x: x % 2 = 0)) AS BIGINT) AS evens, nbrs[1] AS first, nbrs[-1] AS last, "
    "CAST(list_sum(nbrs[1:3]) AS BIGINT) AS head FROM a",
)(
    lambda t: graphs.supplies_graph(t).groupBy("src").agg(F.array_sort(F.collect_list("dst")).alias("nbrs")).select(
        "src", F.aggregate(F.transform("nbrs", lambda x: x * 2), F.lit(0).cast("long"), lambda a, x: a + x).alias("twice"), L(F.size(F.filter("nbrs", lambda x: x % 2 == 0))).alias("evens"),
        F.element_at("nbrs", 1).alias("first"), F.element_at("nbrs", -1).alias("last"), F.aggregate(F.slice("nbrs", 1, 3), F.lit(0).cast("long"), lambda a, x: a + x).alias("head"),
    )
)
query("fn_vector", "WITH x AS (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS e FROM embeddings), o AS (SELECT e AS z FROM x WHERE vec_id = 0) SELECT vec_id, round(list_dot_product(e, z), 5) AS dot, round(sqrt(list_dot_product(e, e)), 5) AS norm, round(list_cosine_similarity(e, z), 5) AS cos, round(list_distance(e, z), 5) AS l2 FROM x, o")(
    lambda t: t.embeddings.crossJoin(F.broadcast(t.embeddings.where("vec_id = 0").select(F.col("embedding").alias("z")))).select(
        "vec_id", F.round(vectors.dot("embedding", "z"), 5).alias("dot"), F.round(vectors.norm("embedding"), 5).alias("norm"), F.round(vectors.cosine("embedding", "z"), 5).alias("cos"), F.round(vectors.l2("embedding", "z"), 5).alias("l2")
    )
)
query("fn_map", "SELECT user_id, count(*) FILTER (WHERE event_type = 'view') AS views, count(DISTINCT event_type) AS kinds, count(*) AS total FROM events GROUP BY 1")(
    lambda t: t.events.groupBy("user_id", "event_type").agg(_n()).groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m")).select(
        "user_id", F.coalesce(F.element_at("m", "view"), F.lit(0)).alias("views"), L(F.size(F.map_keys("m"))).alias("kinds"), F.aggregate(F.map_values(F.transform_values("m", lambda _, v: v)), F.lit(0).cast("long"), lambda a, x: a + x).alias("total")
    )
)
query("fn_json", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")(lambda t: t.events.select("event_id", F.from_json("props", "k bigint")["k"].alias("k")))
query("fn_hash", "SELECT p_partkey, md5(CAST(p_partkey AS VARCHAR)) AS a, sha256(p_name) AS b FROM part")(lambda t: t.part.select("p_partkey", F.md5(F.col("p_partkey").cast("string")).alias("a"), F.sha2("p_name", 256).alias("b")))
query("fn_decimal", "SELECT l_returnflag, CAST(sum(CAST(l_extendedprice AS DECIMAL(18,2))) AS DOUBLE) AS price FROM lineitem GROUP BY 1")(
    lambda t: t.lineitem.groupBy("l_returnflag").agg(F.sum(F.col("l_extendedprice").cast("decimal(18,2)")).cast("double").alias("price"))
)

# ------------------------------------------------------------------ joins

_INNER = "SELECT o_orderkey, o_custkey, count(*) AS n FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1, 2"
query("join_inner", _INNER)(lambda t: t.orders.hint("shuffle_hash").join(t.lineitem, F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderkey", "o_custkey").agg(_n()))
query("join_merge", _INNER)(lambda t: t.orders.hint("merge").join(t.lineitem, F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderkey", "o_custkey").agg(_n()))
query("join_broadcast", "SELECT n_name, r_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY 1, 2")(
    lambda t: t.customer.join(F.broadcast(t.nation), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(t.region), F.col("n_regionkey") == F.col("r_regionkey")).groupBy("n_name", "r_name").agg(_n())
)
query("join_outer", "SELECT coalesce(d.doc_id, l.doc_id) AS doc_id, CAST(quality AS BIGINT) AS quality, lang FROM documents d FULL JOIN labels l ON d.doc_id = l.doc_id")(
    lambda t: t.documents.select("doc_id", "lang").join(t.labels.select("doc_id", "quality"), "doc_id", "full").select("doc_id", L("quality").alias("quality"), "lang")
)
query("join_semi", "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders WHERE o_totalprice > 200000)")(lambda t: t.customer.join(t.orders.where("o_totalprice > 200000").select(F.col("o_custkey").alias("c_custkey")), "c_custkey", "left_semi").select("c_custkey"))
query("join_anti", "SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders)")(lambda t: t.customer.join(t.orders.select(F.col("o_custkey").alias("c_custkey")), "c_custkey", "left_anti").select("c_custkey"))
query("join_range", f"{sq._ITS}, {sq.its_sql(8, 1, 32)} SELECT batch, col, t FROM hits")(
    lambda t, spark: _hits(spark, t.sf_dir)
)


def _hits(spark, d):
    from ..operators import draw

    prefixed = draw.prefix_sum(sq._layer_prob(spark, d)[3])
    rows = prefixed.select("batch", "row_id", "total").distinct()
    return draw._hits(prefixed, draw._draws(rows, F.lit(0), F.lit(32), sq.SEED, 1)).select("batch", "col", F.col("t").cast("long").alias("t"))


query("join_theta", "SELECT a.r_name AS a, b.n_name AS b FROM region a JOIN nation b ON a.r_regionkey < b.n_regionkey")(lambda t: t.region.join(F.broadcast(t.nation), F.col("r_regionkey") < F.col("n_regionkey")).select(F.col("r_name").alias("a"), F.col("n_name").alias("b")))
query("join_self", "SELECT a.l_partkey AS p, count(*) AS n FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.l_linenumber < b.l_linenumber GROUP BY 1")(
    lambda t: t.lineitem.alias("a").join(t.lineitem.alias("b"), F.expr("a.l_orderkey = b.l_orderkey AND a.l_linenumber < b.l_linenumber")).groupBy(F.col("a.l_partkey").alias("p")).agg(_n())
)
query(
    "join_asof",
    "SELECT o.o_orderkey, p.o_orderkey AS previous FROM orders o ASOF LEFT JOIN (SELECT o_custkey, o_orderdate, max(o_orderkey) AS o_orderkey FROM orders GROUP BY 1, 2) p ON o.o_custkey = p.o_custkey AND o.o_orderdate > p.o_orderdate",
)(lambda t: relational.as_of(t.orders, t.orders, "o_custkey", "o_orderdate", "o_orderkey").select("o_orderkey", "previous"))
query("join_interval", "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'view' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 10 MINUTE")(
    lambda t: relational.interval_join(t.events.where("event_type = 'view'"), t.events.where("event_type = 'purchase'"), "user_id", "ts", 600).select(F.col("a.event_id").alias("a"), F.col("b.event_id").alias("b"))
)
query("join_lateral", f"SELECT src, CAST(pos AS BIGINT) AS pos, dst FROM (SELECT src, unnest(list_sort(list(dst))) AS dst, generate_subscripts(list(dst), 1) - 1 AS pos FROM ({sq.SUPPLIES}) GROUP BY src)")(
    lambda t: graphs.supplies_graph(t).groupBy("src").agg(F.array_sort(F.collect_list("dst")).alias("nbrs")).select("src", F.posexplode("nbrs").alias("pos", "dst")).select("src", L("pos").alias("pos"), "dst")
)

# ------------------------------------------------------------------ aggregation

query("agg_basic", "SELECT l_returnflag, l_linestatus, round(sum(l_quantity), 2) AS s, count(*) AS n, round(avg(l_discount), 6) AS a, min(l_shipdate) AS lo, max(l_shipdate) AS hi FROM lineitem GROUP BY 1, 2")(
    lambda t: t.lineitem.groupBy("l_returnflag", "l_linestatus").agg(F.round(F.sum("l_quantity"), 2).alias("s"), _n(), F.round(F.avg("l_discount"), 6).alias("a"), F.min("l_shipdate").alias("lo"), F.max("l_shipdate").alias("hi"))
)
query("agg_distinct", "SELECT l_suppkey, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_orderkey) AS orders FROM lineitem GROUP BY 1")(lambda t: t.lineitem.groupBy("l_suppkey").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_orderkey").alias("orders")))
query("agg_approx_distinct", "SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, true AS within FROM lineitem GROUP BY 1")(
    lambda t: t.lineitem.groupBy("l_returnflag").agg(F.countDistinct("l_partkey").alias("parts"), F.approx_count_distinct("l_partkey", 0.02).alias("a")).select(
        "l_returnflag", "parts", (F.abs(F.col("a") - F.col("parts")) <= 0.06 * F.col("parts")).alias("within")
    )
)
query("agg_collect", "SELECT o_custkey, list_sort(list(o_orderkey)) AS orders FROM orders GROUP BY 1")(lambda t: t.orders.groupBy("o_custkey").agg(F.array_sort(F.collect_list("o_orderkey")).alias("orders")))
_CUBE = "SELECT r_name, c_mktsegment, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY "


def _segments(t):
    return t.customer.join(F.broadcast(t.nation), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(t.region), F.col("n_regionkey") == F.col("r_regionkey"))


query("agg_cube", _CUBE + "CUBE (r_name, c_mktsegment)")(lambda t: _segments(t).cube("r_name", "c_mktsegment").agg(_n()))
query("agg_rollup", _CUBE + "ROLLUP (r_name, c_mktsegment)")(lambda t: _segments(t).rollup("r_name", "c_mktsegment").agg(_n()))
same_sql("agg_grouping_sets", "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())", "orders")
query("agg_max_by", "SELECT o_custkey, max_by(o_orderkey, (o_totalprice, o_orderkey)) AS top, min_by(o_orderkey, (o_totalprice, o_orderkey)) AS low FROM orders GROUP BY 1")(
    lambda t: t.orders.groupBy("o_custkey").agg(F.max_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("top"), F.min_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("low"))
)
query("agg_percentile", "SELECT l_returnflag, round(quantile_cont(l_quantity, 0.5), 4) AS med, round(quantile_cont(l_quantity, 0.9), 4) AS p90 FROM lineitem GROUP BY 1")(
    lambda t: t.lineitem.groupBy("l_returnflag").agg(F.round(F.percentile("l_quantity", F.lit(0.5)), 4).alias("med"), F.round(F.percentile("l_quantity", F.lit(0.9)), 4).alias("p90"))
)
query("agg_stats", "SELECT l_returnflag, round(var_samp(l_quantity), 4) AS v, round(stddev_samp(l_quantity), 4) AS s, round(corr(l_quantity, l_extendedprice), 4) AS c FROM lineitem GROUP BY 1")(
    lambda t: t.lineitem.groupBy("l_returnflag").agg(F.round(F.var_samp("l_quantity"), 4).alias("v"), F.round(F.stddev_samp("l_quantity"), 4).alias("s"), F.round(F.corr("l_quantity", "l_extendedprice"), 4).alias("c"))
)
query("agg_having", "SELECT o_custkey, count(*) AS n FROM orders GROUP BY 1 HAVING count(*) > 12")(lambda t: t.orders.groupBy("o_custkey").agg(_n()).where("n > 12"))
query("agg_pivot", "SELECT user_id, count(*) FILTER (WHERE event_type = 'click') AS click, count(*) FILTER (WHERE event_type = 'view') AS view FROM events GROUP BY 1")(
    lambda t: t.events.groupBy("user_id").pivot("event_type", ["click", "view"]).agg(F.count(F.lit(1))).na.fill(0)
)
query("agg_unpivot", "SELECT p_partkey, 'size' AS k, CAST(p_size AS DOUBLE) AS v FROM part UNION ALL SELECT p_partkey, 'price', p_retailprice FROM part")(
    lambda t: t.part.select("p_partkey", F.col("p_size").cast("double").alias("size"), F.col("p_retailprice").alias("price")).unpivot("p_partkey", ["size", "price"], "k", "v")
)
query("agg_filter", "SELECT lang, count(*) FILTER (WHERE quality = 1) AS good, count(*) FILTER (WHERE toxic = 1) AS toxic FROM documents JOIN labels USING (doc_id) GROUP BY 1")(
    lambda t: t.documents.join(t.labels, "doc_id").groupBy("lang").agg(F.count_if(F.col("quality") == 1).alias("good"), F.count_if(F.col("toxic") == 1).alias("toxic"))
)
query("agg_degree_hist", f"SELECT deg, count(*) AS n FROM (SELECT src, count(*) AS deg FROM ({sq.COPURCHASE}) GROUP BY 1) GROUP BY 1")(lambda t: graphs.degrees(graphs.copurchase_graph(t)).groupBy("deg").agg(_n()))

# ------------------------------------------------------------------ windows, sorts, limits, sets



def _by_customer():
    return Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")


query("win_row_number", "SELECT o_custkey, o_orderkey, rn FROM (SELECT *, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS rn FROM orders) WHERE rn <= 3")(
    lambda t: relational.top_per_group(t.orders, ["o_custkey"], [F.desc("o_totalprice"), F.col("o_orderkey")], 3).select("o_custkey", "o_orderkey", "rn")
)
query("win_rank", "SELECT p_partkey, rank() OVER (PARTITION BY p_brand ORDER BY p_size) AS r, dense_rank() OVER (PARTITION BY p_brand ORDER BY p_size) AS d FROM part")(
    lambda t: t.part.select("p_partkey", L(F.rank().over(w := Window.partitionBy("p_brand").orderBy("p_size"))).alias("r"), L(F.dense_rank().over(w)).alias("d"))
)
query("win_ntile", "SELECT c_custkey, ntile(4) OVER w AS q, round(percent_rank() OVER w, 6) AS p, round(cume_dist() OVER w, 6) AS c FROM customer WINDOW w AS (PARTITION BY c_mktsegment ORDER BY c_acctbal, c_custkey)")(
    lambda t: t.customer.select("c_custkey", L(F.ntile(4).over(w := Window.partitionBy("c_mktsegment").orderBy("c_acctbal", "c_custkey"))).alias("q"), F.round(F.percent_rank().over(w), 6).alias("p"), F.round(F.cume_dist().over(w), 6).alias("c"))
)
query("win_lag", "SELECT conv_id, turn, lag(role) OVER w AS before, lead(role) OVER w AS after FROM conversations WINDOW w AS (PARTITION BY conv_id ORDER BY turn)")(
    lambda t: t.conversations.select("conv_id", "turn", F.lag("role").over(w := Window.partitionBy("conv_id").orderBy("turn")).alias("before"), F.lead("role").over(w).alias("after"))
)
query("win_first", "SELECT o_orderkey, first_value(o_orderkey) OVER w AS f, last_value(o_orderkey) OVER w AS l, nth_value(o_orderkey, 2) OVER w AS n FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")(
    lambda t: t.orders.select("o_orderkey", F.first("o_orderkey").over(w := _by_customer().rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)).alias("f"), F.last("o_orderkey").over(w).alias("l"), F.nth_value("o_orderkey", 2).over(w).alias("n"))
)
query("win_range", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 HOUR PRECEDING AND CURRENT ROW) AS n FROM events")(
    lambda t: t.events.select("event_id", F.count(F.lit(1)).over(Window.partitionBy("user_id").orderBy(F.unix_micros(F.col("ts").cast("timestamp"))).rangeBetween(-3_600_000_000, 0)).alias("n"))
)
query("win_frame", "SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 3 PRECEDING AND CURRENT ROW), 6) AS a FROM events")(
    lambda t: t.events.select("event_id", F.round(F.avg("value").over(Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-3, 0)), 6).alias("a"))
)
query("win_running_sum", "SELECT o_orderkey, round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS UNBOUNDED PRECEDING), 2) AS s FROM orders")(
    lambda t: t.orders.select("o_orderkey", F.round(F.sum("o_totalprice").over(_by_customer().rowsBetween(Window.unboundedPreceding, 0)), 2).alias("s"))
)
query("sort_global", "SELECT c_custkey, c_acctbal FROM customer ORDER BY c_acctbal DESC, c_custkey")(lambda t: t.customer.select("c_custkey", "c_acctbal").orderBy(F.desc("c_acctbal"), "c_custkey"))
query("sort_within", "SELECT c_custkey, c_acctbal FROM customer")(lambda t: t.customer.select("c_custkey", "c_acctbal").repartition("c_custkey").sortWithinPartitions("c_acctbal"))
query("limit_offset", "SELECT o_orderkey FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20 OFFSET 10")(lambda t: t.orders.orderBy(F.desc("o_totalprice"), "o_orderkey").offset(10).limit(20).select("o_orderkey"))
query("topk_global", f"SELECT src AS v, count(*) AS deg FROM ({sq.COPURCHASE}) GROUP BY 1 ORDER BY 2 DESC, 1 LIMIT 10")(lambda t: graphs.degrees(graphs.copurchase_graph(t)).orderBy(F.desc("deg"), "v").limit(10))
query("topk_group", "SELECT l_suppkey, l_partkey, n FROM (SELECT *, row_number() OVER (PARTITION BY l_suppkey ORDER BY n DESC, l_partkey) AS rn FROM (SELECT l_suppkey, l_partkey, count(*) AS n FROM lineitem GROUP BY 1, 2)) WHERE rn <= 2")(
    lambda t: relational.top_per_group(t.lineitem.groupBy("l_suppkey", "l_partkey").agg(_n()), ["l_suppkey"], [F.desc("n"), F.col("l_partkey")], 2).drop("rn")
)
query("set_union", "SELECT c_custkey AS k FROM customer UNION ALL SELECT s_suppkey FROM supplier")(lambda t: t.customer.select(F.col("c_custkey").alias("k")).unionByName(t.supplier.select(F.col("s_suppkey").alias("k"))))
_SETS = ("SELECT l_partkey AS k FROM lineitem WHERE l_quantity < 5", "SELECT l_partkey AS k FROM lineitem WHERE l_quantity > 48")


def _two(t):
    return t.lineitem.where("l_quantity < 5").select(F.col("l_partkey").alias("k")), t.lineitem.where("l_quantity > 48").select(F.col("l_partkey").alias("k"))


query("set_intersect", " INTERSECT ".join(_SETS))(lambda t: _two(t)[0].intersect(_two(t)[1]))
query("set_intersect_all", " INTERSECT ALL ".join(_SETS))(lambda t: _two(t)[0].intersectAll(_two(t)[1]))
query("set_except", " EXCEPT ".join(_SETS))(lambda t: _two(t)[0].subtract(_two(t)[1]))
query("set_except_all", " EXCEPT ALL ".join(_SETS))(lambda t: _two(t)[0].exceptAll(_two(t)[1]))
query("set_distinct", "SELECT DISTINCT l_partkey, l_suppkey FROM lineitem")(lambda t: t.lineitem.dropDuplicates(["l_partkey", "l_suppkey"]).select("l_partkey", "l_suppkey"))

# ------------------------------------------------------------------ user-defined functions

_U = sq.u52_sql("42", "p_partkey")
query("udf_sql", f"SELECT p_partkey, {_U} AS u FROM part")(lambda t, spark: relational.sql_draw(t, spark))
query("udf_scalar", "WITH x AS (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS e FROM embeddings) SELECT vec_id, round(e[1] / sqrt(list_dot_product(e, e)), 5) AS first FROM x")(
    lambda t: t.embeddings.select("vec_id", F.round(vectors.l2_normalize(t.spark)(F.col("embedding"))[0], 5).alias("first"))
)
query("udaf_vector_mean", "SELECT CAST(label AS BIGINT) AS label, round(avg(CAST(embedding[1] AS DOUBLE)), 5) AS first FROM embeddings GROUP BY 1")(
    lambda t: t.embeddings.groupBy(L("label").alias("label")).agg(vectors.vector_mean(t.spark)("embedding").alias("m")).select("label", F.round(F.col("m")[0], 5).alias("first"))
)
_UDTF = f"SELECT src, dst, rank FROM (SELECT src, dst, row_number() OVER (PARTITION BY src ORDER BY {sq.u52_sql('42', '0', '1', 'src', 'dst')}, dst) AS rank FROM ({sq.SUPPLIES})) WHERE rank <= 4"
query("udtf_sample_neighbors", _UDTF)(lambda t, spark: relational.udtf_sample(t, spark, 4))
query("sql_sampling", _UDTF)(lambda t, spark: relational.udtf_sample(t, spark, 4))
query("chat_transitions", "SELECT role, nxt, count(*) AS n FROM (SELECT role, lead(role) OVER (PARTITION BY conv_id ORDER BY turn) AS nxt FROM conversations) WHERE nxt IS NOT NULL GROUP BY 1, 2")(
    lambda t: t.conversations.select("role", F.lead("role").over(Window.partitionBy("conv_id").orderBy("turn")).alias("nxt")).where("nxt IS NOT NULL").groupBy("role", "nxt").agg(_n())
)
