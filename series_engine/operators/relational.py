"""Relational operators that users of the search methods need, each on a given table.

``OPERATORS`` maps a name to (query, SQL): the query is DataFrame code over (spark,
sf_dir); the SQL says the same for the same tables.  Sums of money and quantities are
rounded to four places, other doubles to six.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

OPERATORS: dict[str, tuple[Callable[[SparkSession, str], DataFrame], str]] = {}


class Tables:
    """Tables of one folder by attribute."""

    def __init__(self, spark: SparkSession, sf_dir: str):
        self.spark, self._dir = spark, sf_dir

    def __getattr__(self, name: str) -> DataFrame:
        return self.spark.read.parquet(f"{self._dir}/{name}.parquet")


def operator(sql: str):
    def keep(f: Callable[[Tables], DataFrame]):
        def query(spark: SparkSession, sf_dir: str) -> DataFrame:
            return f(Tables(spark, sf_dir))

        query.__name__, query.__doc__ = f.__name__, f.__doc__
        OPERATORS[f.__name__] = (query, sql)
        return f

    return keep


def money(c: Column) -> Column:
    return F.round(c, 4)


def micros(column: str = "ts") -> Column:
    """Microseconds since 1970 of a timestamp, whatever the session's time zone."""
    return F.expr(f"timestampdiff(MICROSECOND, timestamp_ntz'1970-01-01', cast({column} AS timestamp_ntz))")


def count() -> Column:
    return F.count(F.lit(1))


# ---- scans, filters, projections ------------------------------------------------------


@operator("SELECT vec_id, label FROM embeddings WHERE label IN (1, 3, 5)")
def op_scan_prune(t):
    return t.embeddings.where(F.col("label").isin(1, 3, 5)).select("vec_id", "label")


@operator("SELECT event_id, user_id, value FROM events WHERE ts >= TIMESTAMP '2024-01-02 00:00:00' AND ts < TIMESTAMP '2024-01-12 00:00:00' AND value > 50")
def op_filter_time(t):
    return t.events.where("ts >= timestamp'2024-01-02 00:00:00' and ts < timestamp'2024-01-12 00:00:00' and value > 50").select("event_id", "user_id", "value")


@operator("SELECT d.doc_id, l.quality IS NOT DISTINCT FROM NULL AS unlabelled, l.quality IS NOT DISTINCT FROM 1 AS good FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id")
def op_null_safe(t):
    return t.documents.select("doc_id").join(t.labels, "doc_id", "left").select("doc_id", F.col("quality").eqNullSafe(F.lit(None)).alias("unlabelled"), F.col("quality").eqNullSafe(1).alias("good"))


@operator("SELECT event_id, round(ln(1 + value), 6) AS log_value, CAST(floor(value) AS BIGINT) AS whole, round(pow(value, 0.5), 6) AS root, CAST(event_id % 7 AS BIGINT) AS rest, CAST(sign(value - 50) AS INTEGER) AS side FROM events")
def op_project_math(t):
    v = F.col("value")
    return t.events.select("event_id", F.round(F.log(1 + v), 6).alias("log_value"), F.floor(v).alias("whole"), F.round(F.pow(v, F.lit(0.5)), 6).alias("root"), (F.col("event_id") % 7).alias("rest"), F.signum(v - 50).cast("int").alias("side"))


@operator("SELECT doc_id, upper(replace(substring(text, 1, 32), 'ß', '_')) AS head, CAST(length(text) AS BIGINT) AS chars, CAST(instr(text, 'th') AS BIGINT) AS first_th, lpad(CAST(doc_id AS VARCHAR), 8, '0') AS padded FROM documents")
def op_string_windows(t):
    return t.documents.select("doc_id", F.upper(F.replace(F.substring("text", 1, 32), F.lit("ß"), F.lit("_"))).alias("head"), F.length("text").cast("long").alias("chars"), F.instr("text", "th").cast("long").alias("first_th"), F.lpad(F.col("doc_id").cast("string"), 8, "0").alias("padded"))


@operator("SELECT date_trunc('month', o_orderdate)::TIMESTAMP AS month, CAST((year(o_orderdate) - 1995) * 12 + month(o_orderdate) - 1 AS BIGINT) AS month_index, count(*) AS n FROM orders GROUP BY ALL")
def op_date_grid(t):
    d = F.col("o_orderdate")
    return t.orders.groupBy(F.date_trunc("month", d).cast("timestamp_ntz").alias("month"), ((F.year(d) - 1995) * 12 + F.month(d) - 1).cast("long").alias("month_index")).agg(count().alias("n"))


# ---- arrays, maps, json, structs ------------------------------------------------------


@operator("SELECT vec_id, CAST(len(embedding) AS BIGINT) AS n, round(CAST(embedding[1] AS DOUBLE), 6) AS head, round(list_sum(list_transform(embedding[1:8], lambda v: CAST(v AS DOUBLE))), 6) AS first_eight, round(CAST(list_max(embedding) AS DOUBLE), 6) AS top, round(CAST(list_sort(embedding)[1] AS DOUBLE), 6) AS least FROM embeddings")
def op_array_basics(t):
    e, d = F.col("embedding"), lambda c: F.round(c.cast("double"), 6)
    return t.embeddings.select("vec_id", F.size(e).cast("long").alias("n"), d(F.get(e, F.lit(0))).alias("head"), F.round(F.aggregate(F.slice(e, 1, 8), F.lit(0.0), lambda a, v: a + v.cast("double")), 6).alias("first_eight"), d(F.array_max(e)).alias("top"), d(F.get(F.array_sort(e), F.lit(0))).alias("least"))


@operator("""SELECT a.vec_id, round(list_sum(list_transform(list_zip(a.embedding, b.embedding), lambda p: CAST(p[1] AS DOUBLE) * CAST(p[2] AS DOUBLE))), 6) AS dot,
round(sqrt(list_sum(list_transform(list_zip(a.embedding, b.embedding), lambda p: pow(CAST(p[1] AS DOUBLE) - CAST(p[2] AS DOUBLE), 2)))), 6) AS distance FROM embeddings a JOIN embeddings b ON b.vec_id = a.vec_id + 1""")
def op_array_pairs(t):
    from ..functions.distances import ed

    a, b = t.embeddings.select("vec_id", "embedding"), t.embeddings.select((F.col("vec_id") - 1).alias("vec_id"), F.col("embedding").alias("other"))
    dot = F.aggregate(F.zip_with("embedding", "other", lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, v: s + v)
    return a.join(b, "vec_id").select("vec_id", F.round(dot, 6).alias("dot"), F.round(ed(F.col("embedding"), F.col("other")), 6).alias("distance"))


@operator("SELECT CAST(pos AS BIGINT) AS pos, count(*) AS n, round(sum(CAST(value AS DOUBLE)), 6) AS total FROM (SELECT unnest(embedding) AS value, generate_subscripts(embedding, 1) - 1 AS pos FROM embeddings) GROUP BY pos")
def op_explode_long(t):
    rows = t.embeddings.select(F.posexplode("embedding").alias("pos", "value"))
    return rows.groupBy(F.col("pos").cast("long").alias("pos")).agg(count().alias("n"), F.round(F.sum(F.col("value").cast("double")), 6).alias("total"))


@operator("SELECT vec_id, CAST(len(embedding) AS BIGINT) AS n, round(list_sum(list_transform(embedding, lambda v: CAST(v AS DOUBLE))), 6) AS total, true AS same FROM embeddings")
def op_assemble(t):
    rows = t.embeddings.select("vec_id", F.posexplode("embedding").alias("pos", "value"))
    back = rows.groupBy("vec_id").agg(F.transform(F.array_sort(F.collect_list(F.struct("pos", "value"))), lambda s: s["value"]).alias("again"))
    return t.embeddings.select("vec_id", "embedding").join(back, "vec_id").select("vec_id", F.size("again").cast("long").alias("n"), F.round(F.aggregate("again", F.lit(0.0), lambda a, v: a + v.cast("double")), 6).alias("total"), (F.col("again") == F.col("embedding")).alias("same"))


@operator("""WITH m AS (SELECT c_nationkey AS nation, (year(o_orderdate) - 1995) * 12 + month(o_orderdate) - 1 AS mo, sum(o_totalprice) AS v FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY ALL)
SELECT nation, round(max(v) FILTER (WHERE mo = 0), 4) AS first_month, round(max(v) FILTER (WHERE mo = 11), 4) AS last_month, round(max(v) FILTER (WHERE mo = 999), 4) AS no_month FROM m GROUP BY nation""")
def op_map_lookup(t):
    d = F.col("o_orderdate")
    sums = t.orders.join(t.customer, F.col("o_custkey") == F.col("c_custkey")).groupBy(F.col("c_nationkey").alias("nation"), ((F.year(d) - 1995) * 12 + F.month(d) - 1).alias("mo")).agg(F.sum("o_totalprice").alias("v"))
    maps = sums.groupBy("nation").agg(F.map_from_entries(F.collect_list(F.struct("mo", "v"))).alias("m"))
    at = lambda k: money(F.try_element_at("m", F.lit(k)))
    return maps.select("nation", at(0).alias("first_month"), at(11).alias("last_month"), at(999).alias("no_month"))


@operator("SELECT CAST(json_extract(props, '$.k') AS BIGINT) AS k, count(*) AS n, round(avg(value), 6) AS mean FROM events GROUP BY 1")
def op_json_props(t):
    return t.events.groupBy(F.from_json("props", "k bigint")["k"].alias("k")).agg(count().alias("n"), F.round(F.avg("value"), 6).alias("mean"))


@operator("SELECT user_id, round(min(value), 6) AS least, round(max(value), 6) AS most, round(avg(value), 6) AS mean FROM events GROUP BY user_id")
def op_struct_nested(t):
    s = t.events.groupBy("user_id").agg(F.struct(F.min("value").alias("least"), F.max("value").alias("most"), F.avg("value").alias("mean")).alias("s"))
    return s.select("user_id", *[F.round(F.col(f"s.{c}"), 6).alias(c) for c in ("least", "most", "mean")])


# ---- joins ----------------------------------------------------------------------------


@operator("SELECT r_name, n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name, n_name")
def op_join_broadcast(t):
    """Nations and regions are tables of fixed size."""
    places = t.nation.join(F.broadcast(t.region), F.col("n_regionkey") == F.col("r_regionkey"))
    return t.customer.join(F.broadcast(places), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("r_name", "n_name").agg(count().alias("n"))


_REVENUE = "SELECT o_orderstatus, round(sum(l_extendedprice * (1 - l_discount)), 4) AS revenue, count(*) AS n FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY o_orderstatus"


def _revenue(t, hint):
    lines = t.lineitem.select("l_orderkey", (F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("v"))
    return t.orders.select("o_orderkey", "o_orderstatus").join(lines.hint(hint), F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderstatus").agg(money(F.sum("v")).alias("revenue"), count().alias("n"))


@operator(_REVENUE)
def op_join_merge(t):
    return _revenue(t, "merge")


@operator(_REVENUE)
def op_join_hash(t):
    return _revenue(t, "shuffle_hash")


def _outer(kind: str) -> str:
    return f"SELECT c.c_custkey, o.o_custkey, count(*) AS n FROM customer c {kind} JOIN (SELECT o_custkey FROM orders WHERE o_totalprice > 100000) o ON c.c_custkey = o.o_custkey GROUP BY c.c_custkey, o.o_custkey"


def _outer_join(t, kind):
    orders = t.orders.where("o_totalprice > 100000").select("o_custkey")
    return t.customer.select("c_custkey").join(orders, F.col("c_custkey") == F.col("o_custkey"), kind).groupBy("c_custkey", "o_custkey").agg(count().alias("n"))


@operator(_outer("LEFT"))
def op_join_left(t):
    return _outer_join(t, "left")


@operator(_outer("RIGHT"))
def op_join_right(t):
    return _outer_join(t, "right")


@operator(_outer("FULL"))
def op_join_full(t):
    return _outer_join(t, "full")


@operator("SELECT doc_id, lang FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)")
def op_join_semi(t):
    return t.documents.select("doc_id", "lang").join(t.labels, "doc_id", "left_semi")


@operator("SELECT doc_id, lang FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def op_join_anti(t):
    return t.documents.select("doc_id", "lang").join(t.labels, "doc_id", "left_anti")


@operator("SELECT a.p_brand AS p_brand, count(*) AS pairs FROM part a JOIN part b ON a.p_brand = b.p_brand AND a.p_size < b.p_size GROUP BY a.p_brand")
def op_join_theta(t):
    """Counts by size first: pairs are counted, not made."""
    sizes = t.part.groupBy("p_brand", "p_size").agg(count().alias("n"))
    above = F.sum("n").over(Window.partitionBy("p_brand").orderBy(F.desc("p_size")).rowsBetween(Window.unboundedPreceding, -1))
    return sizes.withColumn("above", above).groupBy("p_brand").agg(F.sum(F.col("n") * F.col("above")).alias("pairs")).where("pairs > 0")


@operator("SELECT p.event_id AS purchase, e.event_id AS follower FROM events p JOIN events e ON p.user_id = e.user_id AND p.event_type = 'purchase' AND e.ts > p.ts AND e.ts <= p.ts + INTERVAL 1 HOUR")
def op_join_range(t):
    """Range join by hour buckets: an event meets purchases of its hour and the one before."""
    hour = F.floor(micros() / 3_600_000_000)
    e = t.events.select("user_id", F.col("event_id").alias("follower"), micros().alias("t"), F.explode(F.array(hour, hour - 1)).alias("h"))
    p = t.events.where("event_type = 'purchase'").select("user_id", F.col("event_id").alias("purchase"), micros().alias("t0"), hour.alias("h"))
    return p.join(e, ["user_id", "h"]).where((F.col("t") > F.col("t0")) & (F.col("t") <= F.col("t0") + 3_600_000_000)).select("purchase", "follower")


def _cells_sql() -> str:
    from ..functions.summaries import breakpoints

    cuts = breakpoints(3)
    ends = ["-1e308", *map(repr, cuts), "1e308"]
    values = ", ".join(f"({i}, {a}::DOUBLE, {b}::DOUBLE)" for i, (a, b) in enumerate(zip(ends[:-1], ends[1:])))
    return f"SELECT CAST(c.cell AS BIGINT) AS cell, count(*) AS n FROM (SELECT round(unnest(embedding)::DOUBLE * 8, 9) AS v FROM embeddings) e JOIN (VALUES {values}) c(cell, lo, hi) ON e.v >= c.lo AND e.v < c.hi GROUP BY c.cell"


@operator(_cells_sql())
def op_join_interval_leaf(t):
    """Values into the cells of an 8-letter alphabet; the cells are a table of eight rows."""
    from ..functions.summaries import breakpoints

    cuts = breakpoints(3)
    cells = t.spark.createDataFrame(list(zip(range(8), (-1e308, *cuts), (*cuts, 1e308))), "cell long, lo double, hi double")
    v = t.embeddings.select(F.explode("embedding").alias("v")).select(F.round(F.col("v").cast("double") * 8, 9).alias("v"))
    return v.join(F.broadcast(cells), (F.col("v") >= F.col("lo")) & (F.col("v") < F.col("hi"))).groupBy("cell").agg(count().alias("n"))


@operator("""SELECT e.event_id, (SELECT p.value FROM events p WHERE p.user_id = e.user_id AND p.event_type = 'purchase' AND (p.ts < e.ts OR (p.ts = e.ts AND p.event_id <= e.event_id)) ORDER BY p.ts DESC, p.event_id DESC LIMIT 1) AS last_purchase
FROM events e WHERE e.event_type = 'error'""")
def op_asof(t):
    """As-of join in one pass: the last purchase's value carried forward."""
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    bought = F.when(F.col("event_type") == "purchase", F.col("value"))
    return t.events.where(F.col("event_type").isin("purchase", "error")).withColumn("last_purchase", F.last(bought, ignorenulls=True).over(w)).where("event_type = 'error'").select("event_id", "last_purchase")


@operator("""SELECT r_name, s.o_orderstatus AS o_orderstatus, count(o.o_orderkey) AS n FROM region CROSS JOIN (SELECT DISTINCT o_orderstatus FROM orders) s
LEFT JOIN (SELECT o_orderkey, o_orderstatus, n_regionkey FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey WHERE o_totalprice > 300000) o ON o.n_regionkey = r_regionkey AND o.o_orderstatus = s.o_orderstatus GROUP BY ALL""")
def op_cross_small(t):
    """The grid has regions x states rows, both of fixed size."""
    grid = t.region.crossJoin(F.broadcast(t.orders.select("o_orderstatus").distinct()))
    o = t.orders.where("o_totalprice > 300000").join(t.customer, F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(t.nation), F.col("c_nationkey") == F.col("n_nationkey"))
    n = o.groupBy(F.col("n_regionkey").alias("r_regionkey"), "o_orderstatus").agg(count().alias("n"))
    return grid.join(n, ["r_regionkey", "o_orderstatus"], "left").na.fill(0, ["n"]).select("r_name", "o_orderstatus", "n")


# ---- aggregation ----------------------------------------------------------------------


@operator("SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 4) AS quantity, round(avg(l_extendedprice), 4) AS mean_price, round(min(l_discount), 4) AS low, round(max(l_tax), 4) AS high FROM lineitem GROUP BY l_returnflag, l_linestatus")
def op_agg_hash(t):
    return t.lineitem.groupBy("l_returnflag", "l_linestatus").agg(count().alias("n"), money(F.sum("l_quantity")).alias("quantity"), money(F.avg("l_extendedprice")).alias("mean_price"), money(F.min("l_discount")).alias("low"), money(F.max("l_tax")).alias("high"))


@operator("SELECT l_returnflag, round(stddev_pop(l_quantity), 6) AS sd, round(var_pop(l_quantity), 6) AS var, round(corr(l_extendedprice, l_quantity), 6) AS corr, round(regr_slope(l_extendedprice, l_quantity), 4) AS slope, round(regr_r2(l_extendedprice, l_quantity), 6) AS r2 FROM lineitem GROUP BY l_returnflag")
def op_agg_stats(t):
    q, p = F.col("l_quantity"), F.col("l_extendedprice")
    return t.lineitem.groupBy("l_returnflag").agg(F.round(F.stddev_pop(q), 6).alias("sd"), F.round(F.var_pop(q), 6).alias("var"), F.round(F.corr(p, q), 6).alias("corr"), money(F.regr_slope(p, q)).alias("slope"), F.round(F.regr_r2(p, q), 6).alias("r2"))


@operator("SELECT p_brand, count(DISTINCT l_suppkey) AS suppliers FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY p_brand")
def op_agg_distinct(t):
    return t.lineitem.select("l_partkey", "l_suppkey").join(t.part.select("p_partkey", "p_brand"), F.col("l_partkey") == F.col("p_partkey")).groupBy("p_brand").agg(F.countDistinct("l_suppkey").alias("suppliers"))


@operator("SELECT event_type, count(*) FILTER (WHERE value > 50) AS high, count(*) FILTER (WHERE value <= 50) AS low FROM events GROUP BY event_type")
def op_agg_filter(t):
    return t.events.groupBy("event_type").agg(F.count_if(F.col("value") > 50).alias("high"), F.count_if(F.col("value") <= 50).alias("low"))


_PLACES = "FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"


def _places(t):
    small = F.broadcast(t.nation.join(F.broadcast(t.region), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "n_name", "r_name"))
    return t.orders.select("o_custkey", "o_totalprice").join(t.customer.select("c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey")).join(small, F.col("c_nationkey") == F.col("n_nationkey"))


@operator(f"SELECT r_name, n_name, round(sum(o_totalprice), 2) AS revenue {_PLACES} GROUP BY GROUPING SETS ((r_name, n_name), (r_name), ())")
def op_grouping_sets(t):
    return _places(t).groupingSets([["r_name", "n_name"], ["r_name"], []], "r_name", "n_name").agg(F.round(F.sum("o_totalprice"), 2).alias("revenue"))


@operator(f"SELECT r_name, n_name, round(sum(o_totalprice), 2) AS revenue, count(*) AS n {_PLACES} GROUP BY ROLLUP (r_name, n_name)")
def op_rollup(t):
    return _places(t).rollup("r_name", "n_name").agg(F.round(F.sum("o_totalprice"), 2).alias("revenue"), count().alias("n"))


@operator(f"SELECT r_name, n_name, CAST(GROUPING_ID(r_name, n_name) AS BIGINT) AS level, count(*) AS n {_PLACES} GROUP BY CUBE (r_name, n_name)")
def op_cube(t):
    return _places(t).cube("r_name", "n_name").agg(F.grouping_id().cast("long").alias("level"), count().alias("n"))


@operator("SELECT user_id, count(*) FILTER (WHERE event_type = 'click') AS click, count(*) FILTER (WHERE event_type = 'error') AS error, count(*) FILTER (WHERE event_type = 'purchase') AS purchase FROM events GROUP BY user_id")
def op_pivot(t):
    return t.events.groupBy("user_id").pivot("event_type", ["click", "error", "purchase"]).count().na.fill(0).select("user_id", "click", "error", "purchase")


@operator("SELECT user_id, count(*) AS n FROM events GROUP BY user_id HAVING count(*) > 70")
def op_having(t):
    return t.events.groupBy("user_id").agg(count().alias("n")).where("n > 70")


@operator("SELECT event_type, round(quantile_cont(value, 0.25), 6) AS q1, round(quantile_cont(value, 0.5), 6) AS median, round(quantile_cont(value, 0.75), 6) AS q3 FROM events GROUP BY event_type")
def op_percentile(t):
    q = lambda p: F.round(F.percentile("value", F.lit(p)), 6)
    return t.events.groupBy("event_type").agg(q(0.25).alias("q1"), q(0.5).alias("median"), q(0.75).alias("q3"))


@operator("SELECT event_type, abs(count(DISTINCT user_id) - count(DISTINCT user_id)) <= 0.1 * count(DISTINCT user_id) AS close FROM events GROUP BY event_type")
def op_approx_distinct(t):
    exact = F.countDistinct("user_id")
    return t.events.groupBy("event_type").agg((F.abs(F.approx_count_distinct("user_id", 0.02) - exact) <= 0.1 * exact).alias("close"))


@operator("SELECT CAST(floor(value / 25) AS BIGINT) AS bin, count(*) AS n FROM events GROUP BY 1")
def op_histogram(t):
    return t.events.groupBy(F.floor(F.col("value") / 25).alias("bin")).agg(count().alias("n"))


# ---- windows --------------------------------------------------------------------------


@operator("""SELECT o_orderkey, row_number() OVER w AS rn, CAST(rank() OVER (PARTITION BY o_custkey ORDER BY year(o_orderdate)) AS BIGINT) AS rk, CAST(dense_rank() OVER (PARTITION BY o_custkey ORDER BY year(o_orderdate)) AS BIGINT) AS drk, round(percent_rank() OVER w, 6) AS pr
FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice, o_orderkey)""")
def op_win_rank(t):
    w, y = Window.partitionBy("o_custkey").orderBy("o_totalprice", "o_orderkey"), Window.partitionBy("o_custkey").orderBy(F.year("o_orderdate"))
    return t.orders.select("o_orderkey", F.row_number().over(w).cast("long").alias("rn"), F.rank().over(y).cast("long").alias("rk"), F.dense_rank().over(y).cast("long").alias("drk"), F.round(F.percent_rank().over(w), 6).alias("pr"))


@operator("SELECT p_partkey, CAST(ntile(4) OVER (PARTITION BY p_brand ORDER BY p_retailprice, p_partkey) AS BIGINT) AS quarter FROM part")
def op_win_ntile(t):
    return t.part.select("p_partkey", F.ntile(4).over(Window.partitionBy("p_brand").orderBy("p_retailprice", "p_partkey")).cast("long").alias("quarter"))


@operator("SELECT event_id, epoch_us(ts) - epoch_us(lag(ts) OVER w) AS since, epoch_us(lead(ts) OVER w) - epoch_us(ts) AS until FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def op_win_lag_lead(t):
    w, us = Window.partitionBy("user_id").orderBy("ts", "event_id"), micros()
    return t.events.select("event_id", (us - F.lag(us).over(w)).alias("since"), (F.lead(us).over(w) - us).alias("until"))


_LONG = "l_shipdate, l_orderkey, l_linenumber, l_partkey, l_quantity, l_extendedprice, l_discount, l_tax"


@operator(f"SELECT l_suppkey, rn, round(total, 4) AS total FROM (SELECT l_suppkey, row_number() OVER w AS rn, sum(l_quantity) OVER (PARTITION BY l_suppkey ORDER BY {_LONG} ROWS UNBOUNDED PRECEDING) AS total FROM lineitem WINDOW w AS (PARTITION BY l_suppkey ORDER BY {_LONG}))")
def op_win_running(t):
    w = Window.partitionBy("l_suppkey").orderBy(*_LONG.split(", "))
    return t.lineitem.select("l_suppkey", F.row_number().over(w).cast("long").alias("rn"), money(F.sum("l_quantity").over(w.rowsBetween(Window.unboundedPreceding, 0))).alias("total"))


@operator("SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS 4 PRECEDING), 6) AS smooth FROM events")
def op_win_moving(t):
    return t.events.select("event_id", F.round(F.avg("value").over(Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-4, 0)), 6).alias("smooth"))


@operator("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 86400000000 PRECEDING AND CURRENT ROW) AS last_day FROM events")
def op_win_range(t):
    w = Window.partitionBy("user_id").orderBy(micros()).rangeBetween(-86_400_000_000, 0)
    return t.events.select("event_id", count().over(w).alias("last_day"))


@operator("""SELECT DISTINCT user_id, CAST(date_trunc('day', ts) AS TIMESTAMP) AS day, first_value(value) OVER w AS head, last_value(value) OVER w AS tail FROM events
WINDOW w AS (PARTITION BY user_id, date_trunc('day', ts) ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)""")
def op_win_first_last(t):
    rows = t.events.groupBy("user_id", F.date_trunc("day", "ts").cast("timestamp_ntz").alias("day"))
    return rows.agg(F.min_by("value", F.struct("ts", "event_id")).alias("head"), F.max_by("value", F.struct("ts", "event_id")).alias("tail"))


@operator("SELECT o_custkey, o_orderkey, i FROM (SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS i FROM orders) WHERE i <= 3")
def op_topk_group(t):
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return t.orders.withColumn("i", F.row_number().over(w).cast("long")).where("i <= 3").select("o_custkey", "o_orderkey", "i")


@operator(f"SELECT l_orderkey, l_linenumber, l_extendedprice FROM lineitem ORDER BY l_extendedprice DESC, {_LONG}, l_suppkey LIMIT 25")
def op_topk_global(t):
    return t.lineitem.orderBy(F.desc("l_extendedprice"), *_LONG.split(", "), "l_suppkey").limit(25).select("l_orderkey", "l_linenumber", "l_extendedprice")


@operator("SELECT p_partkey, p_retailprice FROM part ORDER BY p_retailprice, p_partkey LIMIT 20 OFFSET 40")
def op_sort_offset(t):
    return t.part.orderBy("p_retailprice", "p_partkey").offset(40).limit(20).select("p_partkey", "p_retailprice")


# ---- sets -----------------------------------------------------------------------------


def _sets(word: str) -> str:
    return f"SELECT c_nationkey AS nation FROM customer WHERE c_acctbal > 5000 {word} SELECT s_nationkey FROM supplier WHERE s_acctbal < 5000"


def _both(t):
    return t.customer.where("c_acctbal > 5000").select(F.col("c_nationkey").alias("nation")), t.supplier.where("s_acctbal < 5000").select(F.col("s_nationkey").alias("nation"))


@operator(_sets("UNION"))
def op_union(t):
    a, b = _both(t)
    return a.union(b).distinct()


@operator(_sets("UNION ALL"))
def op_union_all(t):
    a, b = _both(t)
    return a.union(b)


@operator(_sets("INTERSECT"))
def op_intersect(t):
    a, b = _both(t)
    return a.intersect(b)


@operator(_sets("INTERSECT ALL"))
def op_intersect_all(t):
    a, b = _both(t)
    return a.intersectAll(b)


@operator(_sets("EXCEPT"))
def op_except(t):
    a, b = _both(t)
    return a.subtract(b)


@operator(_sets("EXCEPT ALL"))
def op_except_all(t):
    a, b = _both(t)
    return a.exceptAll(b)


@operator("SELECT min(doc_id) AS doc_id FROM documents GROUP BY text")
def op_dedupe(t):
    return t.documents.groupBy("text").agg(F.min("doc_id").alias("doc_id")).select("doc_id")


# ---- time -----------------------------------------------------------------------------

_GAP = 6 * 3_600_000_000


@operator(f"""SELECT user_id, CAST(min(epoch_us(ts)) AS BIGINT) AS began, count(*) AS n, CAST(max(epoch_us(ts)) - min(epoch_us(ts)) AS BIGINT) AS span FROM (
SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS s FROM (
SELECT user_id, ts, event_id, CASE WHEN epoch_us(ts) - epoch_us(lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id)) < {_GAP} THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, s""")
def op_sessions(t):
    """Sessions end after six hours without an event: the engine's own session windows."""
    s = t.events.groupBy("user_id", F.session_window("ts", "6 hours").alias("w")).agg(count().alias("n"), F.min(micros()).alias("began"), (F.max(micros()) - F.min(micros())).alias("span"))
    return s.select("user_id", "began", "n", "span")


@operator("SELECT CAST(date_trunc('day', ts) AS TIMESTAMP) AS day, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY 1")
def op_tumbling(t):
    return t.events.groupBy(F.window("ts", "1 day")["start"].alias("day")).agg(count().alias("n"), money(F.sum("value")).alias("total"))


@operator("""SELECT CAST(time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '1970-01-01') - k.k * INTERVAL 6 HOUR AS TIMESTAMP) AS began, count(*) AS n FROM events CROSS JOIN (VALUES (0), (1), (2), (3)) k(k) GROUP BY 1""")
def op_sliding(t):
    return t.events.groupBy(F.window("ts", "1 day", "6 hours")["start"].alias("began")).agg(count().alias("n"))


@operator("""WITH d AS (SELECT user_id, CAST(date_trunc('day', ts) AS TIMESTAMP) AS day, count(*) AS n FROM events GROUP BY ALL), b AS (SELECT user_id, min(day) AS lo, max(day) AS hi FROM d GROUP BY user_id)
SELECT g.user_id, g.day, CAST(coalesce(d.n, 0) AS BIGINT) AS n FROM (SELECT user_id, unnest(generate_series(lo, hi, INTERVAL 1 DAY)) AS day FROM b) g LEFT JOIN d ON d.user_id = g.user_id AND d.day = g.day""")
def op_gap_fill(t):
    days = t.events.groupBy("user_id", F.date_trunc("day", "ts").cast("timestamp_ntz").alias("day")).agg(count().alias("n"))
    ends = days.groupBy("user_id").agg(F.min("day").alias("lo"), F.max("day").alias("hi"))
    grid = ends.select("user_id", F.explode(F.expr("sequence(lo, hi, interval 1 day)")).alias("day"))
    return grid.join(days, ["user_id", "day"], "left").na.fill(0, ["n"])


@operator("SELECT user_id, CAST(time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '1970-01-01') AS TIMESTAMP) AS bucket, round(avg(value), 6) AS mean FROM events GROUP BY 1, 2")
def op_resample(t):
    return t.events.groupBy("user_id", F.window("ts", "6 hours")["start"].alias("bucket")).agg(F.round(F.avg("value"), 6).alias("mean"))


# ---- subqueries, recursion, sampling --------------------------------------------------


@operator("SELECT event_id FROM events e WHERE value > (SELECT avg(value) FROM events f WHERE f.user_id = e.user_id)")
def op_subquery_corr(t):
    means = t.events.groupBy("user_id").agg(F.avg("value").alias("mean"))
    return t.events.select("event_id", "user_id", "value").join(means, "user_id").where("value > mean").select("event_id")


@operator("WITH RECURSIVE g(pos) AS (SELECT 1 UNION ALL SELECT pos + 1 FROM g WHERE pos < 64) SELECT pos, count(*) AS n FROM g JOIN part ON p_size = pos GROUP BY pos")
def op_cte_recursive(t):
    t.part.createOrReplaceTempView("part_for_grid")
    return t.spark.sql("WITH RECURSIVE g(pos) AS (SELECT 1 UNION ALL SELECT pos + 1 FROM g WHERE pos < 64) SELECT pos, count(*) AS n FROM g JOIN part_for_grid ON p_size = pos GROUP BY pos")


@operator("SELECT event_id FROM events WHERE event_id % 10 = 3")
def op_sample_hash(t):
    """A sampling operator: one row in ten by id."""
    return t.events.where("event_id % 10 = 3").select("event_id")


# ---- SQL functions, files -------------------------------------------------------------


@operator("SELECT vec_id, round(list_avg(list_transform(embedding[1:8], lambda v: CAST(v AS DOUBLE))), 6) AS first_mean FROM embeddings")
def op_udf_scalar(t):
    from ..functions.registered import register

    register(t.spark)
    t.embeddings.createOrReplaceTempView("vectors_for_udf")
    return t.spark.sql("SELECT vec_id, round(series_paa(embedding, 8)[0], 6) AS first_mean FROM vectors_for_udf")


@operator("SELECT vec_id, CAST(o AS BIGINT) AS start, round(list_sum(list_transform(embedding[o + 1:o + 16], lambda v: CAST(v AS DOUBLE))), 6) AS total FROM embeddings CROSS JOIN (VALUES (0), (16), (32), (48)) w(o)")
def op_udtf_windows(t):
    from ..functions.registered import register

    register(t.spark)
    t.embeddings.selectExpr("vec_id", "transform(embedding, v -> double(v)) AS x").createOrReplaceTempView("vectors_for_udtf")
    rows = t.spark.sql("SELECT v.vec_id, w.start, w.part FROM vectors_for_udtf v, LATERAL series_windows(v.x, 16, 16) w")
    return rows.select("vec_id", "start", F.round(F.aggregate("part", F.lit(0.0), lambda a, v: a + v), 6).alias("total"))


@operator("SELECT series_id, round(distance, 6) AS distance FROM (SELECT c.vec_id AS series_id, list_distance(list_transform(c.embedding, lambda v: CAST(v AS DOUBLE)), list_transform(q.embedding, lambda v: CAST(v AS DOUBLE))) AS distance FROM embeddings c, embeddings q WHERE q.vec_id = (SELECT min(vec_id) FROM embeddings)) ORDER BY distance, series_id LIMIT 10")
def op_udtf_knn(t):
    """Ten nearest vectors of the first one: nearest of each hash part, then of all."""
    from ..functions.registered import register

    register(t.spark)
    t.embeddings.selectExpr("vec_id AS series_id", "transform(embedding, v -> double(v)) AS values").createOrReplaceTempView("vectors_for_knn")
    first = t.spark.sql("SELECT min_by(values, series_id) FROM vectors_for_knn").first()[0]
    query = ", ".join(f"{v!r}D" for v in first)
    return t.spark.sql(
        "WITH p AS (SELECT series_id, values, pmod(xxhash64(series_id), 64) AS part FROM vectors_for_knn) "
        f"SELECT series_id, round(distance, 6) AS distance FROM series_knn(TABLE(p) PARTITION BY (part), array({query}), 10) ORDER BY distance, series_id LIMIT 10"
    )


@operator("SELECT label, round(var_pop(CAST(embedding[1] AS DOUBLE)), 6) AS var FROM embeddings GROUP BY label")
def op_udaf_var(t):
    from ..functions.registered import register

    register(t.spark)
    t.embeddings.selectExpr("label", "double(embedding[0]) AS v").createOrReplaceTempView("vectors_for_udaf")
    return t.spark.sql("SELECT label, round(series_var(v), 6) AS var FROM vectors_for_udaf GROUP BY label")


@operator("SELECT vec_id, label, round(list_sum(list_transform(embedding, lambda v: CAST(v AS DOUBLE))), 6) AS total FROM embeddings")
def op_parquet_roundtrip(t):
    from ..plans.storage import fresh_path

    path = fresh_path(t.spark, "roundtrip")
    t.embeddings.repartitionByRange("label").sortWithinPartitions("label", "vec_id").write.parquet(path)
    return t.spark.read.parquet(path).select("vec_id", "label", F.round(F.aggregate("embedding", F.lit(0.0), lambda a, v: a + v.cast("double")), 6).alias("total"))


@operator("SELECT n_nationkey, n_name, r_name FROM nation JOIN region ON n_regionkey = r_regionkey")
def op_csv_json_roundtrip(t):
    from ..plans.storage import fresh_path

    csv, json = fresh_path(t.spark, "csv"), fresh_path(t.spark, "json")
    t.nation.write.option("header", True).csv(csv)
    t.region.write.json(json)
    nation = t.spark.read.schema("n_nationkey int, n_name string, n_regionkey int").option("header", True).csv(csv)
    region = t.spark.read.schema("r_regionkey int, r_name string").json(json)
    return nation.join(F.broadcast(region), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "n_name", "r_name")
