"""Surrounding operators as a user of the stores meets them: sources, joins, aggregates, windows, sets, functions.

Each is one declarative query; the SQL beside it states the same rows."""

from __future__ import annotations

from pyspark.sql import Window as W
from pyspark.sql import functions as F

from keyless.workloads import read

QUERIES, SQL = {}, {}


def q(sql: str):
    def add(f):
        QUERIES[f.__name__], SQL[f.__name__] = f, sql
        return f

    return add


@q("SELECT l_orderkey, l_linenumber, l_extendedprice * (1 - l_discount) AS revenue, CASE WHEN l_quantity > 25 THEN 'big' ELSE 'small' END AS kind FROM lineitem")
def proj_revenue(s, d):
    return read(s, d, "lineitem").select("l_orderkey", "l_linenumber", (F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("revenue"), F.when(F.col("l_quantity") > 25, "big").otherwise("small").alias("kind"))


@q("SELECT p_partkey FROM part WHERE p_size BETWEEN 5 AND 20 AND p_brand IN ('Brand#11', 'Brand#12', 'Brand#23') AND p_name LIKE '%a%' AND p_type IS NOT NULL")
def pred_mix(s, d):
    return read(s, d, "part").filter(F.col("p_size").between(5, 20) & F.col("p_brand").isin("Brand#11", "Brand#12", "Brand#23") & F.col("p_name").like("%a%") & F.col("p_type").isNotNull()).select("p_partkey")


def _joined(hint):
    def run(s, d):
        c, n = read(s, d, "customer", "c_custkey", "c_nationkey"), read(s, d, "nation", "n_nationkey", "n_name")
        return c.join(n.hint(hint), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count("*").alias("n"))

    return run


for _name, _hint in (("join_broadcast", "broadcast"), ("join_shuffle_hash", "shuffle_hash"), ("join_sort_merge", "merge")):
    QUERIES[_name], SQL[_name] = _joined(_hint), "SELECT n_name, count(*)::BIGINT AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY 1"


@q("SELECT r_name, n_name FROM region JOIN nation ON n_regionkey < r_regionkey")
def join_theta(s, d):
    return read(s, d, "region").join(F.broadcast(read(s, d, "nation")), F.col("n_regionkey") < F.col("r_regionkey")).select("r_name", "n_name")


@q("SELECT b AS band, count(*)::BIGINT AS n FROM part JOIN (SELECT i AS b, i * 100 AS lo, i * 100 + 150 AS hi FROM range(0, 30) t(i)) ON p_retailprice >= lo AND p_retailprice < hi GROUP BY 1")
def join_range(s, d):
    bands = s.range(30).select(F.col("id").alias("band"), (F.col("id") * 100).alias("lo"), (F.col("id") * 100 + 150).alias("hi")).withColumn("bin", F.explode(F.sequence(F.floor(F.col("lo") / 100), F.floor((F.col("hi") - 1) / 100))))
    part = read(s, d, "part", "p_retailprice").withColumn("bin", F.floor(F.col("p_retailprice") / 100))
    return part.join(bands, "bin").filter("p_retailprice >= lo and p_retailprice < hi").groupBy("band").agg(F.count("*").alias("n"))


@q("SELECT count(*)::BIGINT AS pairs FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def join_interval(s, d):
    """Both sides are cut in hours; an event meets its own hour and the next, so a user of very many events is many keys."""
    ev = read(s, d, "events", "user_id", "ts").withColumn("hour", F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / 3_600_000_000))
    a = ev.select("user_id", F.col("ts").alias("t1"), F.explode(F.array("hour", F.col("hour") + 1)).alias("hour"))
    return a.join(ev.withColumnRenamed("ts", "t2"), ["user_id", "hour"]).filter("t2 > t1 and t2 <= t1 + interval 1 hour").agg(F.count("*").alias("pairs"))


@q("SELECT event_id, last_value(CASE WHEN event_type = 'signup' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS signup FROM events")
def join_asof(s, d):
    w = W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(W.unboundedPreceding, 0)
    return read(s, d, "events").select("event_id", F.last(F.when(F.col("event_type") == "signup", F.col("event_id")), ignorenulls=True).over(w).alias("signup"))


def _kind(how):
    def run(s, d):
        o, l = read(s, d, "orders", "o_orderkey", "o_custkey"), read(s, d, "lineitem").filter("l_quantity > 45").select("l_orderkey", "l_linenumber")
        return o.join(l, F.col("o_orderkey") == F.col("l_orderkey"), how).select("o_orderkey", *(["l_linenumber"] if how in ("left", "full") else []))

    return run


for _name, _how, _sql in (
    ("join_left", "left", "SELECT o_orderkey, l_linenumber FROM orders LEFT JOIN (SELECT * FROM lineitem WHERE l_quantity > 45) ON o_orderkey = l_orderkey"), ("join_full", "full", "SELECT o_orderkey, l_linenumber FROM orders FULL JOIN (SELECT * FROM lineitem WHERE l_quantity > 45) ON o_orderkey = l_orderkey"),
    ("join_semi", "left_semi", "SELECT o_orderkey FROM orders WHERE o_orderkey IN (SELECT l_orderkey FROM lineitem WHERE l_quantity > 45)"), ("join_anti", "left_anti", "SELECT o_orderkey FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem WHERE l_quantity > 45)"),
):
    QUERIES[_name], SQL[_name] = _kind(_how), _sql


@q("SELECT l_returnflag, l_linestatus, sum(l_quantity)::BIGINT AS quantity, min(l_extendedprice) AS low, max(l_extendedprice) AS high, count(*)::BIGINT AS n, count(*) FILTER (WHERE l_discount > 0.05)::BIGINT AS cheap FROM lineitem GROUP BY 1, 2")
def agg_pricing(s, d):
    return read(s, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.sum("l_quantity").cast("bigint").alias("quantity"), F.min("l_extendedprice").alias("low"), F.max("l_extendedprice").alias("high"), F.count("*").alias("n"), F.count_if(F.col("l_discount") > 0.05).alias("cheap"))


@q("SELECT event_type, count(DISTINCT user_id)::BIGINT AS users, min(props) AS first_props FROM events GROUP BY 1")
def agg_distinct(s, d):
    return read(s, d, "events").groupBy("event_type").agg(F.count_distinct("user_id").alias("users"), F.min("props").alias("first_props"))


def _sets(kind):
    def run(s, d):
        g = getattr(read(s, d, "orders"), kind)("o_orderstatus", "o_orderpriority")
        return g.agg(F.grouping_id().cast("int").alias("g"), F.count("*").alias("n"))

    return run


for _kind_name in ("cube", "rollup"):
    QUERIES[f"agg_{_kind_name}"] = _sets(_kind_name)
    SQL[f"agg_{_kind_name}"] = f"SELECT o_orderstatus, o_orderpriority, grouping(o_orderstatus, o_orderpriority)::INTEGER AS g, count(*)::BIGINT AS n FROM orders GROUP BY {_kind_name}(o_orderstatus, o_orderpriority)"


_TYPES = ["click", "view", "purchase", "signup", "error"]


@q(f"SELECT user_id, {', '.join(f"count(*) FILTER (WHERE event_type = '{t}')::BIGINT AS {t}" for t in _TYPES)} FROM events GROUP BY 1")
def agg_pivot(s, d):
    """The types are given, so the table is read once."""
    return read(s, d, "events").groupBy("user_id").pivot("event_type", _TYPES).count().na.fill(0)


@q("SELECT o_orderstatus, bit_xor(o_orderkey) AS x, bit_or(o_orderkey) AS o, bit_and(o_orderkey) AS a FROM orders GROUP BY 1")
def agg_bits(s, d):
    return read(s, d, "orders").groupBy("o_orderstatus").agg(F.bit_xor("o_orderkey").alias("x"), F.bit_or("o_orderkey").alias("o"), F.bit_and("o_orderkey").alias("a"))


@q("SELECT o_custkey, max_by(o_orderkey, (o_totalprice, o_orderkey)) AS best FROM orders GROUP BY 1")
def agg_maxby(s, d):
    return read(s, d, "orders").groupBy("o_custkey").agg(F.max_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("best"))


@q("SELECT o_orderkey, row_number() OVER w::INTEGER AS rn, ntile(4) OVER w::INTEGER AS quarter, lag(o_orderkey) OVER w AS before FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)")
def win_rank(s, d):
    w = W.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    return read(s, d, "orders").select("o_orderkey", F.row_number().over(w).alias("rn"), F.ntile(4).over(w).alias("quarter"), F.lag("o_orderkey").over(w).alias("before"))


@q("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW)::BIGINT AS n FROM events")
def win_frame_rows(s, d):
    return read(s, d, "events").select("event_id", F.count("*").over(W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-2, 0)).alias("n"))


@q("SELECT o_orderkey FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10")
def topk(s, d):
    return read(s, d, "orders").orderBy(F.col("o_totalprice").desc(), "o_orderkey").limit(10).select("o_orderkey")


_SET = "SELECT c_nationkey AS k FROM customer {} SELECT s_nationkey FROM supplier"
for _op, _method in (("UNION", None), ("UNION ALL", "unionAll"), ("INTERSECT", "intersect"), ("INTERSECT ALL", "intersectAll"), ("EXCEPT ALL", "exceptAll")):
    def _run(s, d, method=_method):
        a, b = read(s, d, "customer").select(F.col("c_nationkey").alias("k")), read(s, d, "supplier").select("s_nationkey")
        return getattr(a, method)(b) if method else a.union(b).distinct()

    QUERIES["set_" + _op.lower().replace(" ", "_")], SQL["set_" + _op.lower().replace(" ", "_")] = _run, _SET.format(_op)


@q("SELECT md5(text) AS m, min(doc_id) AS doc_id FROM documents GROUP BY text")
def dedup_text(s, d):
    return read(s, d, "documents").groupBy("text").agg(F.min("doc_id").alias("doc_id")).select(F.md5("text").alias("m"), "doc_id")


@q("SELECT page_id, md5(html) AS m, lower(url) AS u, regexp_extract(url, '^https?://([^/]+)', 1) AS host FROM pages")
def fn_string(s, d):
    return read(s, d, "pages").select("page_id", F.md5("html").alias("m"), F.lower("url").alias("u"), F.regexp_extract("url", "^https?://([^/]+)", 1).alias("host"))


@q("SELECT o_orderkey, year(o_orderdate)::INTEGER AS y, date_trunc('month', o_orderdate)::DATE::VARCHAR AS m, (o_orderdate::DATE - DATE '1992-01-01')::INTEGER AS days FROM orders")
def fn_date(s, d):
    return read(s, d, "orders").select("o_orderkey", F.year("o_orderdate").alias("y"), F.date_trunc("month", "o_orderdate").cast("date").cast("string").alias("m"), F.datediff(F.col("o_orderdate").cast("date"), F.lit("1992-01-01").cast("date")).alias("days"))


@q("SELECT vec_id, len(embedding)::INTEGER AS n, list_sum([floor(x * 16)::BIGINT FOR x IN embedding])::BIGINT AS total FROM embeddings")
def fn_array(s, d):
    return read(s, d, "embeddings").select("vec_id", F.size("embedding").alias("n"), F.aggregate(F.transform("embedding", lambda x: F.floor(x * 16)), F.lit(0).cast("bigint"), lambda a, x: a + x).alias("total"))


for _kind in ("orc", "json", "csv"):
    QUERIES[f"rt_{_kind}"], SQL[f"rt_{_kind}"] = (lambda s, d, kind=_kind: _round_trip(s, d, kind)), "SELECT * FROM orders"


def _round_trip(s, d, kind):
    """Write the whole orders table in the format and read it back with its schema."""
    from keyless.shared import scratch

    df = read(s, d, "orders")
    path = scratch(s, f"rt-{kind}")
    df.write.format(kind).save(path)
    return s.read.schema(df.schema).format(kind).load(path)


@q("SELECT s_suppkey, n_name FROM supplier RIGHT JOIN nation ON s_nationkey = n_nationkey")
def join_right(s, d):
    return read(s, d, "supplier", "s_suppkey", "s_nationkey").join(read(s, d, "nation"), F.col("s_nationkey") == F.col("n_nationkey"), "right").select("s_suppkey", "n_name")


@q("SELECT r_name, n_name FROM region CROSS JOIN nation")
def join_cross(s, d):
    return read(s, d, "region", "r_name").crossJoin(F.broadcast(read(s, d, "nation", "n_name")))  # five regions, 25 nations


@q("SELECT a.event_id AS a, b.event_id AS b FROM (SELECT event_id, CASE WHEN event_type = 'signup' THEN NULL ELSE event_id END AS k FROM events) a JOIN (SELECT event_id, event_id AS k FROM events WHERE event_type <> 'signup') b ON a.k IS NOT DISTINCT FROM b.k")
def join_null_safe(s, d):
    ev = read(s, d, "events", "event_id", "event_type")
    a = ev.select(F.col("event_id").alias("a"), F.when(F.col("event_type") != "signup", F.col("event_id")).alias("k"))
    b = ev.filter("event_type != 'signup'").select(F.col("event_id").alias("b"), F.col("event_id").alias("k2"))
    return a.join(b, F.col("k").eqNullSafe(F.col("k2"))).select("a", "b")


@q("SELECT c_custkey, o_orderkey FROM customer, LATERAL (SELECT o_orderkey FROM orders WHERE o_custkey = c_custkey ORDER BY o_totalprice DESC, o_orderkey LIMIT 1)")
def join_lateral_top1(s, d):
    best = read(s, d, "orders", "o_orderkey", "o_custkey", "o_totalprice").filter(F.col("o_custkey") == F.col("c_custkey").outer()).orderBy(F.col("o_totalprice").desc(), "o_orderkey").limit(1).select("o_orderkey")
    return read(s, d, "customer", "c_custkey").lateralJoin(best)


@q("SELECT o_orderstatus, o_orderpriority, count(*)::BIGINT AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())")
def agg_gsets(s, d):
    g = read(s, d, "orders").groupingSets([["o_orderstatus"], ["o_orderpriority"], []], "o_orderstatus", "o_orderpriority")
    return g.agg(F.count("*").alias("n"))


@q("SELECT l_returnflag, what, x FROM (SELECT l_returnflag, count(*)::DOUBLE AS rows, sum(l_quantity)::DOUBLE AS quantity FROM lineitem GROUP BY 1) UNPIVOT (x FOR what IN (rows, quantity))")
def agg_unpivot(s, d):
    g = read(s, d, "lineitem").groupBy("l_returnflag").agg(F.count("*").cast("double").alias("rows"), F.sum("l_quantity").cast("double").alias("quantity"))
    return g.unpivot("l_returnflag", ["rows", "quantity"], "what", "x")


@q("SELECT event_type, true AS users_ok, true AS middle_ok, true AS sketch_ok FROM events GROUP BY 1")
def agg_approximate(s, d):
    """Approximate counts and percentiles within their stated errors of the exact ones."""
    ev = read(s, d, "events")
    got = ev.groupBy("event_type").agg(
        F.approx_count_distinct("user_id", 0.05).alias("a"), F.count_distinct("user_id").alias("e"), F.hll_sketch_estimate(F.hll_sketch_agg("user_id", 14)).alias("h"), F.approx_percentile("value", 0.5, 10_000).alias("m"),
        F.percentile("value", F.lit(0.49)).alias("lo"), F.percentile("value", F.lit(0.51)).alias("hi"),
    )
    return got.select("event_type", (F.abs(F.col("a") - F.col("e")) <= 0.25 * F.col("e") + 1).alias("users_ok"), F.col("m").between(F.col("lo"), F.col("hi")).alias("middle_ok"), (F.abs(F.col("h") - F.col("e")) <= 0.05 * F.col("e") + 1).alias("sketch_ok"))


@q("SELECT p_brand, round(stddev_samp(p_size), 6) AS spread, round(corr(p_size, p_retailprice), 6) AS link, round(avg(p_size), 6) AS middle, list_sort(list(DISTINCT p_type))[1] AS first_type FROM part GROUP BY 1")
def agg_statistics(s, d):
    return read(s, d, "part").groupBy("p_brand").agg(F.round(F.stddev_samp("p_size"), 6).alias("spread"), F.round(F.corr("p_size", "p_retailprice"), 6).alias("link"), F.round(F.avg("p_size"), 6).alias("middle"), F.sort_array(F.collect_set("p_type"))[0].alias("first_type"))


@q("SELECT o_orderkey, rank() OVER w::INTEGER AS r, dense_rank() OVER w::INTEGER AS dr, percent_rank() OVER w AS pr, cume_dist() OVER w AS cd FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderpriority)")
def win_rank_kinds(s, d):
    w = W.partitionBy("o_custkey").orderBy("o_orderpriority")
    return read(s, d, "orders").select("o_orderkey", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("dr"), F.percent_rank().over(w).alias("pr"), F.cume_dist().over(w).alias("cd"))


@q("SELECT event_id, lag(event_id) OVER w AS before, lead(event_id, 2) OVER w AS after, first_value(event_id) OVER w AS first, nth_value(event_id, 2) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS second FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def win_lag(s, d):
    w = W.partitionBy("user_id").orderBy("ts", "event_id")
    return read(s, d, "events").select("event_id", F.lag("event_id").over(w).alias("before"), F.lead("event_id", 2).over(w).alias("after"), F.first_value("event_id").over(w).alias("first"), F.nth_value("event_id", 2).over(w.rowsBetween(W.unboundedPreceding, W.unboundedFollowing)).alias("second"))


@q("SELECT o_orderkey, count(*) OVER (PARTITION BY o_custkey ORDER BY epoch(o_orderdate)::BIGINT RANGE BETWEEN 2592000 PRECEDING AND CURRENT ROW)::BIGINT AS month FROM orders")
def win_frame_range(s, d):
    df = read(s, d, "orders", "o_orderkey", "o_custkey", "o_orderdate").withColumn("at", F.col("o_orderdate").cast("timestamp").cast("long"))
    return df.select("o_orderkey", F.count("*").over(W.partitionBy("o_custkey").orderBy("at").rangeBetween(-2_592_000, 0)).alias("month"))


@q("SELECT o_orderkey, row_number() OVER (ORDER BY o_totalprice DESC NULLS LAST, o_orderkey)::BIGINT AS place FROM orders")
def sort_orders(s, d):
    """Total order by ranges; the place is the count of the ranges before and the place within."""
    order = [F.col("o_totalprice").desc_nulls_last(), F.col("o_orderkey")]
    sorted_ = read(s, d, "orders", "o_orderkey", "o_totalprice").orderBy(*order).withColumns({"part": F.spark_partition_id(), "at": F.monotonically_increasing_id()}).persist()
    counts = sorted_.groupBy("part").agg(F.count("*").alias("n"), F.min("at").alias("zero"))
    base = counts.select("part", "zero", F.coalesce(F.sum("n").over(W.orderBy("part").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)).alias("base"))  # a row for each range
    return sorted_.join(F.broadcast(base), "part").select("o_orderkey", (F.col("base") + F.col("at") - F.col("zero") + 1).alias("place"))


@q("SELECT o_custkey, o_orderkey FROM (SELECT *, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS k FROM orders) WHERE k <= 3")
def topk_group(s, d):
    w = W.partitionBy("o_custkey").orderBy(F.col("o_totalprice").desc(), "o_orderkey")
    return read(s, d, "orders", "o_orderkey", "o_custkey", "o_totalprice").withColumn("k", F.row_number().over(w)).filter("k <= 3").select("o_custkey", "o_orderkey")


@q("SELECT o_orderkey FROM orders ORDER BY o_totalprice, o_orderkey LIMIT 7 OFFSET 5")
def topk_offset(s, d):
    return read(s, d, "orders", "o_orderkey", "o_totalprice").orderBy("o_totalprice", "o_orderkey").offset(5).limit(7).select("o_orderkey")


@q("SELECT p_partkey, round(log2(p_size), 9) AS l, round(exp(p_size / 50.0), 9) AS e, round(pow(p_size, 1.5), 6) AS p, (p_partkey << 3)::BIGINT AS up, (p_partkey >> 1)::BIGINT AS down, xor(p_partkey, 85)::BIGINT AS x, (p_partkey & 12)::BIGINT AS a, floor(p_retailprice / 7)::BIGINT AS f FROM part")
def fn_math(s, d):
    k = F.col("p_partkey")
    return read(s, d, "part").select(
        "p_partkey", F.round(F.log2("p_size"), 9).alias("l"), F.round(F.exp(F.col("p_size") / 50.0), 9).alias("e"), F.round(F.pow("p_size", F.lit(1.5)), 6).alias("p"), F.shiftleft(k, 3).alias("up"), F.shiftright(k, 1).alias("down"),
        k.bitwiseXOR(F.lit(85)).alias("x"), k.bitwiseAND(F.lit(12)).alias("a"), F.floor(F.col("p_retailprice") / 7).alias("f"),
    )


@q("SELECT event_id, length(props)::INTEGER AS n, props AS whole, event_type AS kind FROM events")
def fn_json(s, d):
    """Text to a map and a struct and back gives the text again."""
    both = read(s, d, "events").withColumn("m", F.from_json("props", "map<string,string>")).withColumn("st", F.struct(F.col("event_type").alias("kind"), F.map_filter("m", lambda k, v: v.isNotNull()).alias("m")))
    return both.select("event_id", F.length("props").alias("n"), F.when(F.map_from_entries(F.map_entries("st.m")).isNotNull() & (F.size("m") == F.size("st.m")), F.col("props")).alias("whole"), "st.kind")


@q("SELECT o_orderkey FROM orders WHERE ((16807::BIGINT * (o_orderkey % 2147483647) + 3) % 2147483647) % 100 < 10")
def sample_hash(s, d):
    """A tenth of the rows by hash, the same ones every time."""
    from keyless import baselines, hashing

    return read(s, d, "orders", "o_orderkey").filter(hashing.poly_hash(F.col("o_orderkey"), baselines.COEFFICIENTS[6], 100) < 10)


@q("SELECT o_orderkey FROM orders WHERE regexp_matches(o_orderpriority, '^[12]-') OR (o_orderstatus IS NOT DISTINCT FROM 'P' AND NOT o_totalprice < 1000)")
def pred_more(s, d):
    return read(s, d, "orders").filter(F.col("o_orderpriority").rlike("^[12]-") | (F.col("o_orderstatus").eqNullSafe("P") & ~(F.col("o_totalprice") < 1000))).select("o_orderkey")


@q("SELECT page_id, md5(url) AS m FROM pages")
def rt_text(s, d):
    """Text files hold a line a row; the number is kept before the text."""
    from keyless.shared import scratch

    path = scratch(s, "rt-text")
    read(s, d, "pages").select(F.concat_ws("\t", F.col("page_id").cast("string"), F.translate("url", "\t\r\n", "")).alias("value")).write.text(path)
    back = s.read.text(path).select(F.split("value", "\t", 2).alias("x"))
    return back.select(F.col("x")[0].cast("bigint").alias("page_id"), F.md5(F.col("x")[1]).alias("m"))
