"""The operators around the method: joins, aggregates, windows, sets, functions, event windows."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from .registry import query, table

# --- event windows (the batch forms of the streams) --------------------------------------------


@query("events_tumbling", "SELECT (epoch_us(ts) // 7200000000) * 2 AS w, count(*) AS n, round(sum(value), 4) + 0.0 AS v FROM events GROUP BY 1")
def events_tumbling(spark, sf):
    e = table(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    out = e.groupBy(F.window("ts", "2 hours")).agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("v"))
    return out.select((F.unix_seconds("window.start") / 3600).cast("long").alias("w"), "n", "v")


@query(
    "events_sliding",
    """WITH g AS (SELECT (epoch_us(ts) // 1800000000) AS h, value FROM events), x AS (SELECT h - k AS s, value FROM g, (SELECT unnest(range(4)) AS k))
SELECT s * 30 AS w, count(*) AS n, round(sum(value), 4) + 0.0 AS v FROM x GROUP BY s""",
)
def events_sliding(spark, sf):
    e = table(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    out = e.groupBy(F.window("ts", "2 hours", "30 minutes")).agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("v"))
    return out.select((F.unix_seconds("window.start") / 60).cast("long").alias("w"), "n", "v")


@query(
    "events_session",
    """WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 6 HOURS THEN 0 ELSE 1 END AS new FROM events),
s AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g)
SELECT user_id, count(*) AS n, (epoch_us(max(ts)) - epoch_us(min(ts)))::BIGINT AS span FROM s GROUP BY user_id, k""",
)
def events_session(spark, sf):
    e = table(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp"))
    out = e.groupBy("user_id", F.session_window("ts", "6 hours")).agg(F.count("*").alias("n"), (F.unix_micros(F.max("ts")) - F.unix_micros(F.min("ts"))).alias("span"))
    return out.select("user_id", "n", "span")


# --- joins ------------------------------------------------------------------------------------


@query(
    "asof_last_order",
    """WITH o AS (SELECT o_custkey, o_orderdate, max(o_orderkey) AS o_orderkey FROM orders GROUP BY ALL)
SELECT e.event_id, o.o_orderkey FROM events e ASOF LEFT JOIN o ON e.user_id = o.o_custkey AND e.ts >= o.o_orderdate""",
)
def asof_last_order(spark, sf):
    """Each event with its user's latest order before it: one union and one ordered window, no range join."""
    o = table(spark, sf, "orders").groupBy(F.col("o_custkey").alias("user_id"), F.col("o_orderdate").alias("ts")).agg(F.max("o_orderkey").alias("o_orderkey"))
    e = table(spark, sf, "events").select("user_id", "ts", "event_id", F.lit(None).cast("long").alias("o_orderkey"), F.lit(1).alias("k"))
    both = e.unionByName(o.select("user_id", "ts", F.lit(None).cast("long").alias("event_id"), "o_orderkey", F.lit(0).alias("k")))
    last = F.last("o_orderkey", ignorenulls=True).over(Window.partitionBy("user_id").orderBy("ts", "k").rowsBetween(Window.unboundedPreceding, 0))
    return both.withColumn("o_orderkey", last).filter("k = 1").select("event_id", "o_orderkey")


@query("interval_events_cycles", "SELECT c.k AS cycle, count(*) AS n FROM (SELECT unnest(range(30)) AS k) c JOIN events e ON e.ts >= TIMESTAMP '2024-01-01' + INTERVAL 1 DAY * c.k AND e.ts < TIMESTAMP '2024-01-01' + INTERVAL 1 DAY * (c.k + 1) GROUP BY c.k")
def interval_events_cycles(spark, sf):
    """Events inside cycle intervals: interval ends are few and broadcast, the test is on the event's side."""
    start = F.lit("2024-01-01").cast("timestamp_ntz")
    cycles = spark.range(30).select(F.col("id").alias("cycle"), (start + F.make_dt_interval(F.col("id").cast("int"))).alias("lo"), (start + F.make_dt_interval(F.col("id").cast("int") + 1)).alias("hi"))
    e = table(spark, sf, "events").select("ts")
    return e.join(F.broadcast(cycles), (F.col("ts") >= F.col("lo")) & (F.col("ts") < F.col("hi"))).groupBy("cycle").agg(F.count("*").alias("n"))


@query(
    "band_join_events",
    """SELECT a.event_id AS a, count(*) AS n FROM events a JOIN events b ON a.user_id = b.user_id AND b.event_id <> a.event_id AND abs(epoch_us(a.ts) - epoch_us(b.ts)) <= 3600000000 GROUP BY a.event_id""",
)
def band_join_events(spark, sf):
    """Partners within an hour, by bins of an hour: an equi-join on neighbouring bins and an exact recheck."""
    e = table(spark, sf, "events").select("event_id", "user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("u"))
    hour = F.lit(3_600_000_000)
    a = e.select(F.col("event_id").alias("a"), "user_id", F.col("u").alias("ua"), F.floor(F.col("u") / hour).alias("bin"))
    b = e.select(F.col("event_id").alias("b"), "user_id", F.col("u").alias("ub"), F.explode(F.array(*(F.floor(F.col("u") / hour) + k for k in (-1, 0, 1)))).alias("bin"))
    near = a.join(b, ["user_id", "bin"]).filter((F.col("a") != F.col("b")) & (F.abs(F.col("ua") - F.col("ub")) <= hour))
    return near.groupBy("a").agg(F.count("*").alias("n"))


@query(
    "star_revenue_region",
    """SELECT r_name, round(sum(l_extendedprice * (1 - l_discount)), 4) + 0.0 AS rev FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey
JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name""",
)
def star_revenue_region(spark, sf):
    li = table(spark, sf, "lineitem").select("l_orderkey", (F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("rev"))
    o = table(spark, sf, "orders").select("o_orderkey", "o_custkey")
    c = table(spark, sf, "customer").select("c_custkey", "c_nationkey")
    n = table(spark, sf, "nation").select("n_nationkey", "n_regionkey")
    r = table(spark, sf, "region").select("r_regionkey", "r_name")
    by_order = li.groupBy("l_orderkey").agg(F.sum("rev").alias("rev"))  # before the join: fewer rows to move
    out = by_order.join(o, F.col("l_orderkey") == F.col("o_orderkey")).join(c, F.col("o_custkey") == F.col("c_custkey"))
    out = out.join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(r), F.col("n_regionkey") == F.col("r_regionkey"))
    return out.groupBy("r_name").agg(F.round(F.sum("rev"), 4).alias("rev"))


@query("salted_join", "SELECT event_type, count(*) AS n, round(avg(value), 6) + 0.0 AS v FROM events GROUP BY event_type")
def salted_join(spark, sf):
    """A join on few hot keys: the large side is salted, the small one repeated per salt."""
    salts = 8
    e = table(spark, sf, "events").select("event_type", "value", F.pmod(F.xxhash64("event_id"), F.lit(salts)).alias("salt"))
    kinds = e.select("event_type").distinct().withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1)))).withColumn("salt", F.col("salt").cast("long"))
    part = e.join(kinds.hint("shuffle_hash"), ["event_type", "salt"]).groupBy("event_type", "salt").agg(F.sum("value").alias("s"), F.count("*").alias("n"))
    return part.groupBy("event_type").agg(F.sum("n").alias("n"), (F.sum("s") / F.sum("n")).alias("v"))


@query("docs_semi", "SELECT doc_id, lang FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)")
def docs_semi(spark, sf):
    return table(spark, sf, "documents").select("doc_id", "lang").join(table(spark, sf, "labels").select("doc_id"), "doc_id", "left_semi")


@query("docs_anti", "SELECT doc_id, lang FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def docs_anti(spark, sf):
    return table(spark, sf, "documents").select("doc_id", "lang").join(table(spark, sf, "labels").select("doc_id"), "doc_id", "left_anti")


@query("labels_full", "SELECT coalesce(d.source, 'none') AS source, coalesce(l.quality, -1) AS quality, count(*) AS n FROM documents d FULL JOIN labels l ON d.doc_id = l.doc_id GROUP BY ALL")
def labels_full(spark, sf):
    d, l = table(spark, sf, "documents").select("doc_id", "source"), table(spark, sf, "labels").select("doc_id", "quality")
    return d.join(l, "doc_id", "full").groupBy(F.coalesce("source", F.lit("none")).alias("source"), F.coalesce(F.col("quality").cast("long"), F.lit(-1)).alias("quality")).agg(F.count("*").alias("n"))


# --- aggregates -------------------------------------------------------------------------------

REVENUE = "round(sum(l_extendedprice * (1 - l_discount)), 4) + 0.0 AS rev"


def flags(spark, sf, how):
    li = table(spark, sf, "lineitem").select("l_returnflag", "l_linestatus", (F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("v"))
    return getattr(li, how)("l_returnflag", "l_linestatus").agg(F.grouping_id().alias("g"), F.count("*").alias("n"), F.round(F.sum("v"), 4).alias("rev"))


def flags_sql(grouping: str) -> str:
    return f"SELECT l_returnflag, l_linestatus, grouping(l_returnflag, l_linestatus) AS g, count(*) AS n, {REVENUE} FROM lineitem GROUP BY {grouping}"


@query("cube_flags", flags_sql("CUBE (l_returnflag, l_linestatus)"))
def cube_flags(spark, sf):
    return flags(spark, sf, "cube")


@query("rollup_flags", flags_sql("ROLLUP (l_returnflag, l_linestatus)"))
def rollup_flags(spark, sf):
    return flags(spark, sf, "rollup")


@query("gsets_flags", flags_sql("GROUPING SETS ((l_returnflag), (l_linestatus), ())"))
def gsets_flags(spark, sf):
    table(spark, sf, "lineitem").select("l_returnflag", "l_linestatus", "l_extendedprice", "l_discount").createOrReplaceTempView("_cyclefold_lineitem")
    return spark.sql(flags_sql("GROUPING SETS ((l_returnflag), (l_linestatus), ())").replace("FROM lineitem", "FROM _cyclefold_lineitem").replace("grouping(l_returnflag, l_linestatus)", "grouping_id()"))


@query("pruned_scan", f"SELECT l_shipdate::DATE::VARCHAR AS day, {REVENUE} FROM lineitem WHERE l_discount >= 0.05 GROUP BY 1")
def pruned_scan(spark, sf):
    li = table(spark, sf, "lineitem").filter("l_discount >= 0.05")
    return li.groupBy(F.col("l_shipdate").cast("date").cast("string").alias("day")).agg(F.round(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))), 4).alias("rev"))


@query(
    "aggregate_suite",
    """SELECT event_type, count(DISTINCT user_id) AS users, round(median(value), 6) + 0.0 AS med, round(quantile_cont(value, 0.9), 6) + 0.0 AS q90, arg_max(event_id, (value, event_id)) AS top,
round(stddev_samp(value), 6) + 0.0 AS sd, round(corr(value, user_id), 6) + 0.0 AS c, round(regr_slope(value, event_id), 6) + 0.0 AS slope, count(*) FILTER (WHERE value > 100) AS big FROM events GROUP BY event_type HAVING count(*) > 10""",
)
def aggregate_suite(spark, sf):
    e = table(spark, sf, "events").groupBy("event_type").agg(
        F.count_distinct("user_id").alias("users"), F.median("value").alias("med"), F.percentile("value", 0.9).alias("q90"), F.max_by("event_id", F.struct("value", "event_id")).alias("top"),
        F.stddev_samp("value").alias("sd"), F.corr("value", "user_id").alias("c"), F.regr_slope("value", "event_id").alias("slope"), F.count_if(F.col("value") > 100).alias("big"), F.count("*").alias("n"),
    )
    return e.filter("n > 10").drop("n")


@query("approx_distinct", "SELECT true AS close")
def approx_distinct(spark, sf):
    both = table(spark, sf, "events").agg(F.approx_count_distinct("user_id", 0.02).alias("a"), F.count_distinct("user_id").alias("b"))
    return both.select((F.abs(F.col("a") - F.col("b")) <= 0.08 * F.col("b")).alias("close"))


@query("pivot_types", "SELECT date_part('hour', ts) AS h, count(*) FILTER (WHERE event_type = 'click') AS click, count(*) FILTER (WHERE event_type = 'purchase') AS purchase, count(*) FILTER (WHERE event_type = 'view') AS view FROM events GROUP BY 1")
def pivot_types(spark, sf):
    e = table(spark, sf, "events").groupBy(F.hour("ts").alias("h")).pivot("event_type", ["click", "purchase", "view"]).agg(F.count(F.lit(1)))
    return e.na.fill(0)


# --- windows, order, sets ---------------------------------------------------------------------


@query(
    "rank_suite",
    """SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, round(percent_rank() OVER w, 6) + 0.0 AS pr, ntile(4) OVER w AS nt, round(cume_dist() OVER w, 6) + 0.0 AS cd
FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey)""",
)
def rank_suite(spark, sf):
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return table(spark, sf, "orders").select("o_orderkey", F.row_number().over(w).alias("rn"), F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"), F.percent_rank().over(w).alias("pr"), F.ntile(4).over(w).alias("nt"), F.cume_dist().over(w).alias("cd"))


@query(
    "frame_suite",
    """SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN 2 PRECEDING AND 2 FOLLOWING), 6) + 0.0 AS mid,
round(sum(value) OVER (PARTITION BY user_id ORDER BY event_id ROWS UNBOUNDED PRECEDING), 4) + 0.0 AS run, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 86400000000 PRECEDING AND CURRENT ROW) AS day,
round(value - lag(value) OVER (PARTITION BY user_id ORDER BY event_id), 6) + 0.0 AS step FROM events""",
)
def frame_suite(spark, sf):
    e = table(spark, sf, "events").withColumn("u", F.unix_micros(F.col("ts").cast("timestamp")))
    by = Window.partitionBy("user_id").orderBy("event_id")
    day = Window.partitionBy("user_id").orderBy("u").rangeBetween(-86_400_000_000, 0)
    return e.select(
        "event_id", F.avg("value").over(by.rowsBetween(-2, 2)).alias("mid"), F.round(F.sum("value").over(by.rowsBetween(Window.unboundedPreceding, 0)), 4).alias("run"),
        F.count("*").over(day).alias("day"), (F.col("value") - F.lag("value").over(by)).alias("step"),
    )


@query(
    "nth_suite",
    """SELECT event_id, first_value(value) OVER w AS f, last_value(value) OVER w AS l, nth_value(value, 2) OVER w AS s, last_value(CASE WHEN event_type = 'purchase' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY event_id) AS p
FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)""",
)
def nth_suite(spark, sf):
    by = Window.partitionBy("user_id").orderBy("event_id")
    whole = by.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    bought = F.when(F.col("event_type") == "purchase", F.col("event_id"))
    return table(spark, sf, "events").select("event_id", F.first("value").over(whole).alias("f"), F.last("value").over(whole).alias("l"), F.nth_value("value", 2).over(whole).alias("s"), F.last(bought, ignorenulls=True).over(by).alias("p"))


@query("top_orders", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10 OFFSET 5")
def top_orders(spark, sf):
    """A top-k report: a heap per task, no full sort."""
    return table(spark, sf, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(5).limit(10)


@query("set_union", "SELECT c_nationkey AS k FROM customer UNION SELECT s_nationkey FROM supplier")
def set_union(spark, sf):
    return table(spark, sf, "customer").select(F.col("c_nationkey").alias("k")).union(table(spark, sf, "supplier").select("s_nationkey")).distinct()


@query("set_intersect_all", "SELECT c_nationkey AS k FROM customer INTERSECT ALL SELECT s_nationkey FROM supplier")
def set_intersect_all(spark, sf):
    return table(spark, sf, "customer").select(F.col("c_nationkey").alias("k")).intersectAll(table(spark, sf, "supplier").select("s_nationkey"))


@query("set_except_all", "SELECT c_nationkey AS k FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier")
def set_except_all(spark, sf):
    return table(spark, sf, "customer").select(F.col("c_nationkey").alias("k")).exceptAll(table(spark, sf, "supplier").select("s_nationkey"))


# --- scalar functions -------------------------------------------------------------------------


@query("json_props", "SELECT event_id, (props->>'$.k')::BIGINT AS k FROM events")
def json_props(spark, sf):
    return table(spark, sf, "events").select("event_id", F.from_json("props", "k int")["k"].cast("long").alias("k"))


@query(
    "string_suite",
    "SELECT page_id, regexp_extract(url, '//([^/]*)', 1) AS host, length(html) AS n, lpad(page_id::VARCHAR, 8, '0') AS id, md5(url) AS h, split_part(url, '/', 4) AS part, translate(lower(url), 'aeiou', '*****') AS t FROM pages",
)
def string_suite(spark, sf):
    return table(spark, sf, "pages").select(
        "page_id", F.regexp_extract("url", "//([^/]*)", 1).alias("host"), F.length("html").cast("long").alias("n"), F.lpad(F.col("page_id").cast("string"), 8, "0").alias("id"),
        F.md5("url").alias("h"), F.split_part("url", F.lit("/"), F.lit(4)).alias("part"), F.translate(F.lower("url"), "aeiou", "*****").alias("t"),
    )


@query(
    "date_suite",
    "SELECT o_orderkey, date_trunc('month', o_orderdate)::DATE::VARCHAR AS m, date_diff('day', DATE '1995-01-01', o_orderdate::DATE) AS d, date_part('dow', o_orderdate) + 1 AS dow, (o_orderdate::DATE + INTERVAL 1 MONTH)::DATE::VARCHAR AS next FROM orders",
)
def date_suite(spark, sf):
    day = F.col("o_orderdate").cast("date")
    return table(spark, sf, "orders").select(
        "o_orderkey", F.trunc(day, "month").cast("string").alias("m"), F.datediff(day, F.lit("1995-01-01")).alias("d"), F.dayofweek(day).alias("dow"), F.add_months(day, 1).cast("string").alias("next")
    )


@query("math_suite", "SELECT event_id, round(atan2(sin(value), cos(value)), 6) + 0.0 AS a, round(sqrt(value) + ln(value) + exp(-value), 6) + 0.0 AS b, floor(value)::BIGINT AS f, round(degrees(radians(value)), 6) + 0.0 AS g, round(sqrt(value * value + 1), 6) + 0.0 AS h FROM events")
def math_suite(spark, sf):
    """The logarithm of zero is minus infinity, where Spark's own has none."""
    v = F.col("value")
    log = F.when(v == 0, F.lit(float("-inf"))).otherwise(F.ln(v))
    return table(spark, sf, "events").select(
        "event_id", F.atan2(F.sin(v), F.cos(v)).alias("a"), (F.sqrt(v) + log + F.exp(-v)).alias("b"), F.floor(v).alias("f"), F.degrees(F.radians(v)).alias("g"), F.hypot(v, F.lit(1.0)).alias("h")
    )


@query("map_suite", "SELECT user_id, count(DISTINCT event_type) AS kinds, count(*) FILTER (WHERE event_type = 'click') AS click FROM events GROUP BY user_id")
def map_suite(spark, sf):
    counts = table(spark, sf, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
    bags = counts.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("bag"))
    doubled = F.transform_values("bag", lambda k, v: v * 2)
    return bags.select("user_id", F.size(F.map_filter("bag", lambda k, v: v > 0)).alias("kinds"), F.coalesce(doubled["click"] / 2, F.lit(0.0)).cast("long").alias("click"))


@query("array_suite", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)), 5) + 0.0 AS n2, len(list_filter(embedding, lambda x: x > 0)) AS pos, round(list_max(embedding)::DOUBLE, 6) + 0.0 AS top FROM embeddings")
def array_suite(spark, sf):
    square = F.aggregate(F.transform("embedding", lambda x: x.cast("double") * x.cast("double")), F.lit(0.0), lambda s, x: s + x)
    return table(spark, sf, "embeddings").select("vec_id", F.round(square, 5).alias("n2"), F.size(F.filter("embedding", lambda x: x > 0)).alias("pos"), F.array_max("embedding").cast("double").alias("top"))


@query("turn_lengths", "SELECT conv_id, turn, length(text) AS len FROM conversations")
def turn_lengths(spark, sf):
    return table(spark, sf, "conversations").select("conv_id", "turn", F.length("text").cast("long").alias("len"))


@query(
    "predicate_suite",
    "SELECT p_partkey FROM part WHERE p_size BETWEEN 5 AND 30 AND p_type LIKE '%STEEL%' OR p_brand IN ('Brand#11', 'Brand#22') OR regexp_matches(p_name, '^[a-f]') OR p_size IS NOT DISTINCT FROM 49",
)
def predicate_suite(spark, sf):
    p = table(spark, sf, "part")
    keep = (F.col("p_size").between(5, 30) & F.col("p_type").like("%STEEL%")) | F.col("p_brand").isin("Brand#11", "Brand#22") | F.col("p_name").rlike("^[a-f]") | F.col("p_size").eqNullSafe(49)
    return p.filter(keep).select("p_partkey")


@query(
    "orders_merge_join",
    "SELECT o_orderstatus, count(*) AS n, sum(l_quantity) AS quantity FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1",
)
def orders_merge_join(spark, sf):
    """Two large sides in a sorted join, asked for by a hint."""
    items = table(spark, sf, "lineitem").select("l_orderkey", "l_quantity")
    both = table(spark, sf, "orders").select("o_orderkey", "o_orderstatus").hint("merge").join(items, F.col("o_orderkey") == F.col("l_orderkey"))
    return both.groupBy("o_orderstatus").agg(F.count("*").alias("n"), F.sum("l_quantity").alias("quantity"))


SHARES = {"1-URGENT": 0.5, "2-HIGH": 0.25, "3-MEDIUM": 0.1}


@query(
    "orders_sample",
    "SELECT o_orderkey, o_orderpriority FROM orders WHERE ('0x' || substr(md5('7|' || o_orderkey::VARCHAR), 1, 8))::BIGINT / 4294967296.0 < CASE "
    + " ".join(f"WHEN o_orderpriority = '{k}' THEN {v}" for k, v in SHARES.items())
    + " ELSE 0.05 END",
)
def orders_sample(spark, sf):
    """A sample by strata that any engine repeats: a hash of the key against the stratum's share."""
    u = F.conv(F.substring(F.md5(F.concat_ws("|", F.lit("7"), F.col("o_orderkey").cast("string"))), 1, 8), 16, 10).cast("long") / F.lit(4294967296.0)
    share = F.lit(0.05)
    for k, v in SHARES.items():
        share = F.when(F.col("o_orderpriority") == k, v).otherwise(share)
    return table(spark, sf, "orders").filter(u < share).select("o_orderkey", "o_orderpriority")
