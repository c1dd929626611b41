"""Relational work around linking: scans, joins, aggregates, windows, functions, sources and sinks."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from entlink.operators.joins import asof_join, interval_join, range_join, salted_join
from entlink.registry import query
from entlink.storage import scratch_path, table


def t(spark, sf_dir, name) -> DataFrame:
    return table(spark, sf_dir, name)


def _count(c, name="n"):
    return F.count(c).alias(name)


@query("q60_scan_pushdown", "SELECT p_partkey, p_size FROM part WHERE p_size >= 40")
def scan(spark, d):
    return t(spark, d, "part").where("p_size >= 40").select("p_partkey", "p_size")


@query("q61_format_round_trip", "SELECT f AS format, n_nationkey, n_name, n_regionkey FROM nation, (VALUES ('csv'), ('json'), ('orc'), ('text')) v(f)")
def formats(spark, d):
    nation, out = t(spark, d, "nation"), None
    for f in ("csv", "json", "orc", "text"):
        path = scratch_path(spark, f)
        if f == "text":
            nation.select(F.to_json(F.struct("*")).alias("value")).write.text(path)
            back = spark.read.text(path).select(F.from_json("value", nation.schema).alias("r")).select("r.*")
        else:
            nation.write.format(f).save(path)
            back = spark.read.format(f).schema(nation.schema).load(path)
        back = back.select(F.lit(f).alias("format"), "*")
        out = back if out is None else out.unionByName(back)
    return out


@query("q62_partitioned_sink", "SELECT label, count(*) AS n FROM embeddings WHERE label < 3 GROUP BY label")
def partitioned(spark, d):
    path = scratch_path(spark, "by-label")
    t(spark, d, "embeddings").select("vec_id", "label").repartition("label").write.partitionBy("label").parquet(path)
    return spark.read.parquet(path).where("label < 3").groupBy("label").agg(_count("*"))


@query("q63_projection", """SELECT p_partkey, CASE WHEN p_size < 10 THEN 'small' WHEN p_size BETWEEN 10 AND 30 THEN 'medium' ELSE 'big' END AS class,
    p_brand IS NOT DISTINCT FROM 'Brand#1' AS is_one, regexp_matches(p_name, '^(red|blue) ') AS coloured, p_type IN ('PROMO', 'SMALL') AS picked FROM part""")
def projection(spark, d):
    size = F.col("p_size")
    return t(spark, d, "part").select(
        "p_partkey",
        F.when(size < 10, "small").when(size.between(10, 30), "medium").otherwise("big").alias("class"),
        F.col("p_brand").eqNullSafe("Brand#1").alias("is_one"),
        F.col("p_name").rlike("^(red|blue) ").alias("coloured"),
        F.col("p_type").isin("PROMO", "SMALL").alias("picked"),
    )


@query("q64_broadcast_join", "SELECT c_custkey, n_name, r_name FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey")
def broadcast_join(spark, d):
    # nation and region have 25 and 5 rows at every scale
    n = t(spark, d, "nation").join(F.broadcast(t(spark, d, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    return t(spark, d, "customer").join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "n_name", "r_name")


@query("q65_sort_merge_join", "SELECT o_orderpriority, count(*) AS n FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1")
def merge_join(spark, d):
    o = t(spark, d, "orders").hint("merge")
    return o.join(t(spark, d, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderpriority").agg(_count("*"))


@query("q66_shuffle_hash_join", "SELECT p_brand, round(sum(l_quantity), 2) AS quantity FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1")
def hash_join(spark, d):
    p = t(spark, d, "part").hint("shuffle_hash")
    return t(spark, d, "lineitem").join(p, F.col("l_partkey") == F.col("p_partkey")).groupBy("p_brand").agg(F.round(F.sum("l_quantity"), 2).alias("quantity"))


@query("q67_outer_joins", """SELECT 'left' AS how, count(*) AS n, count(quality) AS matched FROM documents LEFT JOIN labels USING (doc_id)
    UNION ALL SELECT 'right', count(*), count(quality) FROM documents RIGHT JOIN labels USING (doc_id) UNION ALL SELECT 'full', count(*), count(quality) FROM documents FULL JOIN labels USING (doc_id)""")
def outer_joins(spark, d):
    docs, labels = t(spark, d, "documents").select("doc_id"), t(spark, d, "labels")
    rows = [docs.join(labels, "doc_id", how).agg(_count("*"), _count("quality", "matched")).select(F.lit(how).alias("how"), "*") for how in ("left", "right", "full")]
    return rows[0].unionByName(rows[1]).unionByName(rows[2])


@query("q68_left_semi", "SELECT p_partkey FROM part WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_partkey = p_partkey AND l_quantity > 49)")
def semi(spark, d):
    big = t(spark, d, "lineitem").where("l_quantity > 49").select(F.col("l_partkey").alias("p_partkey"))
    return t(spark, d, "part").join(big, "p_partkey", "left_semi").select("p_partkey")


@query("q69_left_anti", "SELECT item_id FROM benchmark b WHERE NOT EXISTS (SELECT 1 FROM documents d WHERE contains(d.text, b.text))")
def anti(spark, d):
    from entlink.workloads.core import link_contains

    found = link_contains(spark, d).select(F.col("name_id").alias("item_id"))
    return t(spark, d, "benchmark").join(found, "item_id", "left_anti").select("item_id")


@query("q70_theta_join", "SELECT n_name, p_partkey FROM nation JOIN part ON n_nationkey > p_size AND p_size < 3")
def theta(spark, d):
    n = F.broadcast(t(spark, d, "nation"))  # 25 rows
    return t(spark, d, "part").where("p_size < 3").join(n, F.col("n_nationkey") > F.col("p_size")).select("n_name", "p_partkey")


@query("q71_range_join", """WITH b AS (SELECT p_type AS band, min(p_retailprice) AS low, avg(p_retailprice) AS high FROM part GROUP BY 1)
    SELECT band, count(*) AS n FROM part JOIN b ON p_retailprice >= low AND p_retailprice < high GROUP BY 1""")
def ranges(spark, d):
    part = t(spark, d, "part")
    bands = part.groupBy(F.col("p_type").alias("band")).agg(F.min("p_retailprice").alias("low"), F.avg("p_retailprice").alias("high"))
    return range_join(part.select("p_retailprice"), bands, "p_retailprice", "low", "high", 50.0).groupBy("band").agg(_count("*"))


@query("q72_asof_join", """SELECT event_id, o_orderkey FROM (SELECT e.event_id, o.o_orderkey, row_number() OVER (PARTITION BY e.event_id ORDER BY o.o_orderdate DESC, o.o_orderkey DESC) AS r
    FROM events e LEFT JOIN orders o ON o.o_custkey = e.user_id AND o.o_orderdate <= e.ts) WHERE r = 1""")
def asof(spark, d):
    e = t(spark, d, "events").select("event_id", "ts", F.col("user_id").alias("k"))
    o = t(spark, d, "orders").select(F.col("o_custkey").alias("k"), "o_orderdate", "o_orderkey")
    return asof_join(e, o, "k", "ts", "o_orderdate", ["o_orderkey"]).select("event_id", "o_orderkey")


@query("q73_interval_join", """SELECT a.event_id AS first_id, b.event_id AS then_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'signup'
    AND b.ts >= a.ts AND b.ts < a.ts + INTERVAL 1 HOUR AND a.event_id <> b.event_id""")
def intervals(spark, d):
    e = t(spark, d, "events")
    a = e.where("event_type = 'signup'").select(F.col("event_id").alias("first_id"), "user_id", F.col("ts").alias("at"))
    b = e.select(F.col("event_id").alias("then_id"), "user_id", "ts")
    return interval_join(a, b, "user_id", "at", "ts", 3600).where("first_id != then_id").select("first_id", "then_id")


@query("q74_lateral_top_k", "SELECT c_custkey, o_orderkey FROM (SELECT o_custkey AS c_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders) WHERE r <= 2")
def lateral(spark, d):
    t(spark, d, "customer").createOrReplaceTempView("lat_customer")
    t(spark, d, "orders").createOrReplaceTempView("lat_orders")
    return spark.sql("""SELECT c_custkey, o_orderkey FROM lat_customer,
        LATERAL (SELECT o_orderkey FROM lat_orders WHERE o_custkey = c_custkey ORDER BY o_totalprice DESC, o_orderkey LIMIT 2)""")


@query("q75_hash_aggregate", """SELECT l_returnflag, l_linestatus, round(sum(l_quantity), 2) AS quantity, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue, round(avg(l_discount), 6) AS discount, count(*) AS n
    FROM lineitem GROUP BY 1, 2""")
def hash_aggregate(spark, d):
    return t(spark, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(
        F.round(F.sum("l_quantity"), 2).alias("quantity"),
        F.round(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))), 2).alias("revenue"),
        F.round(F.avg("l_discount"), 6).alias("discount"),
        _count("*"),
    )


@query("q76_list_aggregate", "SELECT conv_id, string_agg(role, ',' ORDER BY turn) AS roles FROM conversations GROUP BY 1")
def list_aggregate(spark, d):
    rows = F.sort_array(F.collect_list(F.struct("turn", "role")))
    return t(spark, d, "conversations").groupBy("conv_id").agg(F.array_join(F.transform(rows, lambda x: x["role"]), ",").alias("roles"))


@query("q77_distinct_aggregate", "SELECT p_brand, count(DISTINCT p_name) AS names, count(DISTINCT p_type) AS types FROM part GROUP BY 1")
def distinct_aggregate(spark, d):
    return t(spark, d, "part").groupBy("p_brand").agg(F.countDistinct("p_name").alias("names"), F.countDistinct("p_type").alias("types"))


@query("q78_approximate_aggregate")
def approximate(spark, d):
    return t(spark, d, "lineitem").groupBy("l_returnflag").agg(
        F.approx_count_distinct("l_partkey").alias("parts"), F.percentile_approx("l_extendedprice", [0.5, 0.9], 1000).alias("quantiles")
    )


@query("q79_grouping_sets", """SELECT 'cube' AS kind, l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)
    UNION ALL SELECT 'rollup', l_returnflag, l_linestatus, count(*) FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)
    UNION ALL SELECT 'sets', l_returnflag, l_linestatus, count(*) FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus))""")
def grouping_sets(spark, d):
    li, cols = t(spark, d, "lineitem"), ["l_returnflag", "l_linestatus"]
    flag, status = (F.col(c) for c in cols)
    rows = {"cube": li.cube(*cols), "rollup": li.rollup(*cols), "sets": li.groupingSets([[flag], [status]], flag, status)}
    a, b, c = (g.agg(_count("*")).select(F.lit(k).alias("kind"), *cols, "n") for k, g in rows.items())
    return a.unionByName(b).unionByName(c)


@query("q80_pivot_unpivot", """WITH p AS (SELECT o_orderpriority, count(*) FILTER (WHERE o_orderstatus = 'F') AS f, count(*) FILTER (WHERE o_orderstatus = 'O') AS o, count(*) FILTER (WHERE o_orderstatus = 'P') AS p FROM orders GROUP BY 1)
    SELECT o_orderpriority, unnest(['F', 'O', 'P']) AS status, unnest([f, o, p]) AS n FROM p""")
def pivot(spark, d):
    wide = t(spark, d, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).agg(F.count(F.lit(1))).fillna(0)
    return wide.unpivot("o_orderpriority", ["F", "O", "P"], "status", "n")


@query("q81_statistics", """SELECT l_returnflag, round(stddev_samp(l_quantity), 6) AS deviation, round(corr(l_quantity, l_extendedprice), 6) AS correlation, round(regr_slope(l_extendedprice, l_quantity), 4) AS slope,
    count(*) FILTER (WHERE l_discount > 0.05) AS discounted FROM lineitem GROUP BY 1""")
def statistics(spark, d):
    return t(spark, d, "lineitem").groupBy("l_returnflag").agg(
        F.round(F.stddev_samp("l_quantity"), 6).alias("deviation"),
        F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("correlation"),
        F.round(F.regr_slope("l_extendedprice", "l_quantity"), 4).alias("slope"),
        F.sum(F.when(F.col("l_discount") > 0.05, 1).otherwise(0)).alias("discounted"),
    )


@query("q82_ranking_windows", """SELECT p_partkey, row_number() OVER w AS row_no, rank() OVER v AS rank_no, dense_rank() OVER v AS dense_no, ntile(4) OVER w AS quarter, round(percent_rank() OVER v, 6) AS share
    FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_size, p_partkey), v AS (PARTITION BY p_brand ORDER BY p_size)""")
def ranking(spark, d):
    w, v = Window.partitionBy("p_brand").orderBy("p_size", "p_partkey"), Window.partitionBy("p_brand").orderBy("p_size")
    return t(spark, d, "part").select(
        "p_partkey", F.row_number().over(w).alias("row_no"), F.rank().over(v).alias("rank_no"), F.dense_rank().over(v).alias("dense_no"),
        F.ntile(4).over(w).alias("quarter"), F.round(F.percent_rank().over(v), 6).alias("share"),
    )


@query("q83_analytic_windows", """SELECT event_id, lag(event_type) OVER w AS before, lead(event_type) OVER w AS after, first_value(event_id) OVER w AS first_id, last_value(event_id) OVER (w ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS last_id
    FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)""")
def analytic(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    whole = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return t(spark, d, "events").select(
        "event_id", F.lag("event_type").over(w).alias("before"), F.lead("event_type").over(w).alias("after"), F.first("event_id").over(w).alias("first_id"), F.last("event_id").over(whole).alias("last_id")
    )


@query("q84_frames", """SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING), 4) AS running,
    count(*) OVER (PARTITION BY user_id ORDER BY epoch(ts)::BIGINT RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS last_hour FROM (SELECT *, ts AS _t FROM events)""".replace("epoch(ts)::BIGINT", "floor(epoch(ts))"))
def frames(spark, d):
    rows = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    e = t(spark, d, "events").withColumn("s", F.unix_timestamp(F.col("ts").cast("timestamp")))
    hour = Window.partitionBy("user_id").orderBy("s").rangeBetween(-3600, 0)
    return e.select("event_id", F.round(F.sum("value").over(rows), 4).alias("running"), F.count("*").over(hour).alias("last_hour"))


@query("q85_sort_limit_offset", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 20 OFFSET 5")
def top_k(spark, d):
    return t(spark, d, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").offset(5).limit(20)


@query("q86_set_operations", """WITH a AS (SELECT p_size AS v FROM part WHERE p_brand = 'Brand#1'), b AS (SELECT p_size AS v FROM part WHERE p_brand = 'Brand#2')
    SELECT 'union' AS op, v FROM (SELECT * FROM a UNION SELECT * FROM b) UNION ALL SELECT 'intersect', v FROM (SELECT * FROM a INTERSECT SELECT * FROM b)
    UNION ALL SELECT 'except_all', v FROM (SELECT * FROM a EXCEPT ALL SELECT * FROM b)""")
def sets(spark, d):
    part = t(spark, d, "part")
    a, b = (part.where(F.col("p_brand") == f"Brand#{i}").select(F.col("p_size").alias("v")) for i in (1, 2))
    rows = {"union": a.union(b).distinct(), "intersect": a.intersect(b), "except_all": a.exceptAll(b)}
    x, y, z = (df.select(F.lit(k).alias("op"), "v") for k, df in rows.items())
    return x.unionByName(y).unionByName(z)


@query("q87_string_functions", """SELECT p_partkey, upper(trim(p_name)) AS up, regexp_extract(p_brand, '#([0-9]+)', 1) AS brand_no, translate(p_name, 'aeiou', '*****') AS masked, levenshtein(p_name, p_brand) AS edits, substr(p_name, 2, 3) AS part_of, reverse(p_type) AS turned FROM part""")
def strings(spark, d):
    return t(spark, d, "part").select(
        "p_partkey", F.upper(F.trim("p_name")).alias("up"), F.regexp_extract("p_brand", "#([0-9]+)", 1).alias("brand_no"), F.translate("p_name", "aeiou", "*****").alias("masked"),
        F.levenshtein("p_name", "p_brand").alias("edits"), F.substring("p_name", 2, 3).alias("part_of"), F.reverse("p_type").alias("turned"),
    )


@query("q88_math_functions", "SELECT p_partkey, round(exp(p_size / 50.0), 6) AS e, round(ln(p_retailprice), 6) AS l, round(sqrt(p_size), 6) AS s, greatest(p_size, 25) AS g, p_partkey % 7 AS m, ceil(p_retailprice / 100)::BIGINT AS c FROM part")
def maths(spark, d):
    size = F.col("p_size")
    return t(spark, d, "part").select(
        "p_partkey", F.round(F.exp(size / 50.0), 6).alias("e"), F.round(F.log("p_retailprice"), 6).alias("l"), F.round(F.sqrt(size), 6).alias("s"),
        F.greatest(size, F.lit(25)).alias("g"), F.pmod("p_partkey", F.lit(7)).alias("m"), F.ceil(F.col("p_retailprice") / 100).alias("c"),
    )


@query("q89_date_functions", """SELECT o_orderkey, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS month, year(o_orderdate)::INT AS y, date_diff('day', DATE '1995-01-01', o_orderdate::DATE)::INT AS days,
    strftime(o_orderdate::DATE + INTERVAL 3 MONTH, '%Y-%m-%d') AS later, dayofyear(o_orderdate)::INT AS day_no FROM orders""")
def dates(spark, d):
    at = F.col("o_orderdate")
    return t(spark, d, "orders").select(
        "o_orderkey", F.date_format(F.date_trunc("month", at), "yyyy-MM-dd").alias("month"), F.year(at).alias("y"), F.datediff(at.cast("date"), F.lit("1995-01-01").cast("date")).alias("days"),
        F.date_format(F.add_months(at.cast("date"), 3), "yyyy-MM-dd").alias("later"), F.dayofyear(at).alias("day_no"),
    )


@query("q90_array_functions", """SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: abs(x::DOUBLE))), 5) AS l1, len(list_filter(embedding, lambda x: x > 0))::INT AS positive,
    round(list_reduce(list_transform(list_zip(embedding, embedding), lambda p: (p[1]::DOUBLE * p[2]::DOUBLE)), lambda a, b: a + b), 5) AS square FROM embeddings""")
def arrays(spark, d):
    e = F.col("embedding")
    total = lambda c: F.aggregate(c, F.lit(0.0), lambda a, b: a + b)
    return t(spark, d, "embeddings").select(
        "vec_id",
        F.round(total(F.transform(e, lambda x: F.abs(x.cast("double")))), 5).alias("l1"),
        F.size(F.filter(e, lambda x: x > 0)).alias("positive"),
        F.round(total(F.zip_with(e, e, lambda a, b: a.cast("double") * b.cast("double"))), 5).alias("square"),
    )


@query("q91_map_struct", "SELECT n_nationkey, n_name AS by_key, 'r' || n_regionkey AS region FROM nation")
def maps(spark, d):
    pair = lambda k, v: F.struct(F.lit(k).alias("k"), v.alias("v"))
    m = F.map_from_entries(F.array(pair("name", F.col("n_name")), pair("region", F.concat(F.lit("r"), F.col("n_regionkey").cast("string")))))
    rows = t(spark, d, "nation").select("n_nationkey", F.struct(m.alias("m")).alias("s"))
    return rows.select("n_nationkey", F.element_at("s.m", "name").alias("by_key"), F.element_at("s.m", "region").alias("region"))


@query("q92_json_variant", "SELECT event_id, (props->>'k')::INT AS k, (props->>'k')::INT AS v FROM events")
def json(spark, d):
    return t(spark, d, "events").select("event_id", F.from_json("props", "k int")["k"].alias("k"), F.try_variant_get(F.parse_json("props"), "$.k", "int").alias("v"))


@query("q93_tumbling_window", "SELECT strftime(date_trunc('hour', ts), '%Y-%m-%d %H:%M') AS hour, event_type, count(*) AS n FROM events GROUP BY ALL")
def tumbling(spark, d):
    w = F.window(F.col("ts").cast("timestamp"), "1 hour")
    return t(spark, d, "events").groupBy(w.alias("w"), "event_type").agg(_count("*")).select(F.date_format("w.start", "yyyy-MM-dd HH:mm").alias("hour"), "event_type", "n")


@query("q94_sliding_window", """SELECT strftime(time_bucket(INTERVAL 15 MINUTE, ts) - i * INTERVAL 15 MINUTE, '%Y-%m-%d %H:%M') AS start, count(*) AS n FROM events, range(4) r(i) GROUP BY ALL""")
def sliding(spark, d):
    w = F.window(F.col("ts").cast("timestamp"), "1 hour", "15 minutes")
    return t(spark, d, "events").groupBy(w.alias("w")).agg(_count("*")).select(F.date_format("w.start", "yyyy-MM-dd HH:mm").alias("start"), "n")


@query("q95_session_window", """WITH g AS (SELECT *, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS s FROM events),
    r AS (SELECT *, sum(s) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS run FROM g)
    SELECT user_id, n, count(*) AS sessions FROM (SELECT user_id, run, count(*) AS n FROM r GROUP BY ALL) GROUP BY ALL""")
def sessions(spark, d):
    s = F.session_window(F.col("ts").cast("timestamp"), "30 minutes")
    return t(spark, d, "events").groupBy("user_id", s.alias("s")).agg(_count("*")).groupBy("user_id", "n").agg(_count("*", "sessions"))


@query("q99_function_surface", "SELECT label, round(sum(embedding[1]::DOUBLE), 5) AS first_sum, count(*) AS n FROM embeddings GROUP BY 1")
def function_surface(spark, d):
    @F.pandas_udf("double")
    def total(v: pd.Series) -> float:  # a grouped aggregate
        return float(v.astype(float).sum())

    rows = t(spark, d, "embeddings").select("label", F.element_at("embedding", 1).cast("double").alias("x"))
    return rows.groupBy("label").agg(total("x").alias("s"), total(F.lit(1.0)).alias("n")).select("label", F.round("s", 5).alias("first_sum"), F.col("n").cast("bigint").alias("n"))


@query("q100_subqueries", """WITH RECURSIVE walk AS (SELECT 0 AS level, r_regionkey AS key, r_name AS name FROM region UNION ALL SELECT 1, n_nationkey, w.name || '/' || n_name FROM walk w JOIN nation ON level = 0 AND n_regionkey = key)
    SELECT level::INT AS level, name, (SELECT count(*) FROM customer WHERE level = 1 AND c_nationkey = key) AS customers FROM walk""")
def subqueries(spark, d):
    for n in ("region", "nation", "customer"):
        t(spark, d, n).createOrReplaceTempView(f"sub_{n}")
    return spark.sql("""WITH RECURSIVE walk(level, key, name) AS (SELECT 0, r_regionkey, r_name FROM sub_region
        UNION ALL SELECT 1, n_nationkey, w.name || '/' || n_name FROM walk w JOIN sub_nation ON level = 0 AND n_regionkey = key)
        SELECT level, name, coalesce(n, 0L) AS customers FROM walk LEFT JOIN (SELECT c_nationkey, count(*) AS n FROM sub_customer GROUP BY 1) ON level = 1 AND c_nationkey = key""")


@query("q101_salted_join", "SELECT o_orderstatus, count(*) AS n FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1")
def salted(spark, d):
    left = t(spark, d, "lineitem").select(F.col("l_orderkey").alias("k"), "l_linenumber")
    right = t(spark, d, "orders").select(F.col("o_orderkey").alias("k"), "o_orderstatus")
    return salted_join(left, right, "k").groupBy("o_orderstatus").agg(_count("*"))
