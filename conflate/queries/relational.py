"""Registered queries of the operators and functions around the methods, on the star schema and the events."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from conflate.functions import domain

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None):  # noqa: ANN201
    def add(f):  # noqa: ANN001, ANN202
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return add


def t(spark, sf_dir: str, name: str) -> DataFrame:  # noqa: ANN001
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


@query(" UNION ALL ".join(f"SELECT '{n}' AS tab, count(*) AS n FROM {n}" for n in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()))
def scan_counts(spark, sf_dir):
    out = None
    for n in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split():
        one = t(spark, sf_dir, n).agg(F.count("*").alias("n")).select(F.lit(n).alias("tab"), "n")
        out = one if out is None else out.unionByName(one)
    return out


@query("SELECT p_partkey AS id, upper(p_name) AS title, p_size::DOUBLE AS size, p_brand || '/' || p_type AS path FROM part")
def proj_poi(spark, sf_dir):
    return t(spark, sf_dir, "part").select(F.col("p_partkey").alias("id"), F.upper("p_name").alias("title"), F.col("p_size").cast("double").alias("size"), F.concat_ws("/", "p_brand", "p_type").alias("path"))


@query("SELECT p_partkey, p_name FROM part WHERE p_size BETWEEN 5 AND 30 AND p_type IN ('ECONOMY', 'SMALL') AND p_name LIKE '%ring%' AND NOT p_brand = 'Brand#3' AND p_retailprice IS NOT NULL AND regexp_matches(p_name, '^[a-s]')")
def filter_mix(spark, sf_dir):
    p = t(spark, sf_dir, "part")
    return p.where(F.col("p_size").between(5, 30) & F.col("p_type").isin("ECONOMY", "SMALL") & F.col("p_name").like("%ring%") & ~(F.col("p_brand") == "Brand#3") & F.col("p_retailprice").isNotNull() & F.col("p_name").rlike("^[a-s]") & ~F.col("p_brand").eqNullSafe(None)).select("p_partkey", "p_name")


@query("SELECT c_custkey FROM customer c WHERE EXISTS (SELECT 1 FROM orders o WHERE o.o_custkey = c.c_custkey AND o.o_totalprice > 1000)")
def subquery_exists(spark, sf_dir):
    o = t(spark, sf_dir, "orders").where("o_totalprice > 1000")
    c = t(spark, sf_dir, "customer")
    return c.join(o, c.c_custkey == o.o_custkey, "left_semi").select("c_custkey")


@query("SELECT p_partkey FROM part WHERE p_retailprice > (SELECT avg(p_retailprice) FROM part)")
def subquery_scalar(spark, sf_dir):
    p = t(spark, sf_dir, "part")
    return p.crossJoin(F.broadcast(p.agg(F.avg("p_retailprice").alias("mean")))).where("p_retailprice > mean").select("p_partkey")


_CN = "SELECT c_custkey, n_name FROM customer JOIN nation ON c_nationkey = n_nationkey"


@query(_CN)
def join_broadcast(spark, sf_dir):
    return t(spark, sf_dir, "customer").join(F.broadcast(t(spark, sf_dir, "nation")), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "n_name")


_CO = "SELECT o_orderkey, c_mktsegment FROM orders JOIN customer ON o_custkey = c_custkey"


@query(_CO)
def join_smj(spark, sf_dir):
    return t(spark, sf_dir, "orders").join(t(spark, sf_dir, "customer").hint("merge"), F.col("o_custkey") == F.col("c_custkey")).select("o_orderkey", "c_mktsegment")


@query(_CO)
def join_shj(spark, sf_dir):
    return t(spark, sf_dir, "orders").join(t(spark, sf_dir, "customer").hint("shuffle_hash"), F.col("o_custkey") == F.col("c_custkey")).select("o_orderkey", "c_mktsegment")


@query("SELECT a.s_suppkey AS a, b.s_suppkey AS b FROM supplier a JOIN supplier b ON a.s_acctbal < b.s_acctbal AND b.s_acctbal - a.s_acctbal < 50")
def join_theta(spark, sf_dir):
    s = t(spark, sf_dir, "supplier")
    a, b = s.select(F.col("s_suppkey").alias("a"), F.col("s_acctbal").alias("x")), s.select(F.col("s_suppkey").alias("b"), F.col("s_acctbal").alias("y"))
    return a.join(b, (F.col("x") < F.col("y")) & (F.col("y") - F.col("x") < 50)).select("a", "b")


@query("SELECT p_partkey, i AS band FROM part JOIN (SELECT i, i * 250.0 AS lo, (i + 1) * 250.0 AS hi FROM range(0, 20) r(i)) ON p_retailprice >= lo AND p_retailprice < hi")
def join_range(spark, sf_dir):
    """A range join as an equi join on the bin of the price, with the residual test."""
    bands = spark.range(20).select(F.col("id").alias("band"), (F.col("id") * 250.0).alias("lo"), ((F.col("id") + 1) * 250.0).alias("hi"), F.col("id").alias("bin"))
    p = t(spark, sf_dir, "part").withColumn("bin", F.floor(F.col("p_retailprice") / 250.0))
    return p.join(F.broadcast(bands), "bin").where("p_retailprice >= lo and p_retailprice < hi").select("p_partkey", "band")


@query("SELECT e.event_id, (SELECT max(v.event_id) FROM events v WHERE v.event_type = 'view' AND v.user_id = e.user_id AND v.event_id < e.event_id) AS last_view FROM events e WHERE e.event_type = 'purchase'")
def join_asof(spark, sf_dir):
    """Latest earlier view of each purchase's user: one window over the user's events, no range join."""
    e = t(spark, sf_dir, "events")
    w = Window.partitionBy("user_id").orderBy("event_id").rowsBetween(Window.unboundedPreceding, -1)
    seen = e.withColumn("last_view", F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True).over(w))
    return seen.where("event_type = 'purchase'").select("event_id", "last_view")


@query("SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 6 HOUR")
def join_interval(spark, sf_dir):
    e = t(spark, sf_dir, "events")
    a = e.where("event_type = 'click'").select("user_id", F.col("event_id").alias("a"), F.col("ts").alias("ta"))
    b = e.where("event_type = 'purchase'").select("user_id", F.col("event_id").alias("b"), F.col("ts").alias("tb"))
    return a.join(b, "user_id").where("tb >= ta and tb <= ta + interval 6 hours").select("a", "b")


@query("SELECT coalesce(c.k, s.k) AS k, nc, ns FROM (SELECT c_nationkey AS k, count(*) AS nc FROM customer WHERE c_acctbal > 9000 GROUP BY 1) c FULL JOIN (SELECT s_nationkey AS k, count(*) AS ns FROM supplier WHERE s_acctbal > 5000 GROUP BY 1) s ON c.k = s.k")
def join_outer(spark, sf_dir):
    c = t(spark, sf_dir, "customer").where("c_acctbal > 9000").groupBy(F.col("c_nationkey").alias("k")).agg(F.count("*").alias("nc"))
    s = t(spark, sf_dir, "supplier").where("s_acctbal > 5000").groupBy(F.col("s_nationkey").alias("k")).agg(F.count("*").alias("ns"))
    return c.join(s, "k", "full").select("k", "nc", "ns")


@query("SELECT p_partkey FROM part WHERE p_partkey IN (SELECT l_partkey FROM lineitem WHERE l_quantity > 45)")
def join_semi(spark, sf_dir):
    return t(spark, sf_dir, "part").join(t(spark, sf_dir, "lineitem").where("l_quantity > 45"), F.col("p_partkey") == F.col("l_partkey"), "left_semi").select("p_partkey")


@query("SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
def join_anti(spark, sf_dir):
    return t(spark, sf_dir, "customer").join(t(spark, sf_dir, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey")


@query("SELECT r_name, n_name FROM region CROSS JOIN nation")
def join_cross(spark, sf_dir):
    return t(spark, sf_dir, "nation").crossJoin(F.broadcast(t(spark, sf_dir, "region"))).select("r_name", "n_name")


@query("SELECT a.n_name AS a, b.n_name AS b FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey")
def join_self(spark, sf_dir):
    n = t(spark, sf_dir, "nation")
    return n.alias("x").join(n.alias("y"), (F.col("x.n_regionkey") == F.col("y.n_regionkey")) & (F.col("x.n_nationkey") < F.col("y.n_nationkey"))).select(F.col("x.n_name").alias("a"), F.col("y.n_name").alias("b"))


@query("SELECT c_custkey, o_orderkey FROM (SELECT c_custkey, o_orderkey, row_number() OVER (PARTITION BY c_custkey ORDER BY o_totalprice DESC, o_orderkey) AS k FROM customer JOIN orders ON o_custkey = c_custkey) WHERE k <= 2")
def join_lateral(spark, sf_dir):
    """Two dearest orders of each customer."""
    w = Window.partitionBy("c_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    j = t(spark, sf_dir, "customer").join(t(spark, sf_dir, "orders"), F.col("c_custkey") == F.col("o_custkey"))
    return j.withColumn("k", F.row_number().over(w)).where("k <= 2").select("c_custkey", "o_orderkey")


@query("SELECT l_returnflag, l_linestatus, round(sum(l_quantity), 2) AS qty, count(*) AS n, round(avg(l_discount), 6) AS disc FROM lineitem GROUP BY ALL")
def agg_hash(spark, sf_dir):
    return t(spark, sf_dir, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.round(F.sum("l_quantity"), 2).alias("qty"), F.count("*").alias("n"), F.round(F.avg("l_discount"), 6).alias("disc"))


@query("SELECT l_returnflag, count(DISTINCT l_partkey) AS parts, count(DISTINCT l_suppkey) AS suppliers FROM lineitem GROUP BY 1")
def agg_distinct(spark, sf_dir):
    return t(spark, sf_dir, "lineitem").groupBy("l_returnflag").agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_suppkey").alias("suppliers"))


@query()
def agg_approx(spark, sf_dir):
    return t(spark, sf_dir, "lineitem").agg(F.approx_count_distinct("l_partkey", 0.02).alias("parts"))


@query("SELECT event_type, count_if(value > 50) AS high, round(sum(CASE WHEN value > 50 THEN value ELSE 0 END), 4) AS high_sum, count(*) AS n FROM events GROUP BY 1")
def agg_filter(spark, sf_dir):
    return t(spark, sf_dir, "events").groupBy("event_type").agg(F.count_if(F.col("value") > 50).alias("high"), F.round(F.sum(F.when(F.col("value") > 50, F.col("value")).otherwise(0)), 4).alias("high_sum"), F.count("*").alias("n"))


@query("SELECT p_brand, p_type, count(*) AS n, grouping(p_brand, p_type)::BIGINT AS gid FROM part GROUP BY CUBE (p_brand, p_type)")
def agg_cube(spark, sf_dir):
    return t(spark, sf_dir, "part").cube("p_brand", "p_type").agg(F.count("*").alias("n"), F.grouping_id().alias("gid"))


@query("SELECT p_type, p_size, count(*) AS n FROM part GROUP BY ROLLUP (p_type, p_size)")
def agg_rollup(spark, sf_dir):
    return t(spark, sf_dir, "part").rollup("p_type", "p_size").agg(F.count("*").alias("n"))


@query("SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())")
def agg_gsets(spark, sf_dir):
    li = t(spark, sf_dir, "lineitem")
    return li.groupingSets([[F.col("l_returnflag")], [F.col("l_linestatus")], []], "l_returnflag", "l_linestatus").agg(F.count("*").alias("n"))


@query("SELECT p_brand, first(p_partkey ORDER BY p_retailprice DESC, p_partkey) AS dearest, first(p_partkey ORDER BY p_retailprice, p_partkey) AS cheapest, bool_or(p_size > 45) AS big FROM part GROUP BY 1")
def agg_maxby(spark, sf_dir):
    p = t(spark, sf_dir, "part")
    return p.groupBy("p_brand").agg(F.max_by("p_partkey", F.struct("p_retailprice", -F.col("p_partkey"))).alias("dearest"), F.min_by("p_partkey", F.struct("p_retailprice", "p_partkey")).alias("cheapest"), F.bool_or(F.col("p_size") > 45).alias("big"))


@query("SELECT event_type, round(quantile_cont(value, 0.5), 6) AS median, round(quantile_cont(value, 0.9), 6) AS p90 FROM events GROUP BY 1")
def agg_percentile(spark, sf_dir):
    return t(spark, sf_dir, "events").groupBy("event_type").agg(F.round(F.percentile("value", F.lit(0.5)), 6).alias("median"), F.round(F.percentile("value", F.lit(0.9)), 6).alias("p90"))


@query("SELECT n_regionkey, string_agg(n_name, '|' ORDER BY n_name) AS names FROM nation GROUP BY 1")
def agg_collect(spark, sf_dir):
    return t(spark, sf_dir, "nation").groupBy("n_regionkey").agg(F.array_join(F.array_sort(F.collect_list("n_name")), "|").alias("names"))


@query("SELECT o_orderpriority, count_if(o_orderstatus = 'O') AS o, count_if(o_orderstatus = 'F') AS f, count_if(o_orderstatus = 'P') AS p FROM orders GROUP BY 1")
def agg_pivot(spark, sf_dir):
    return t(spark, sf_dir, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["O", "F", "P"]).count().na.fill(0).select("o_orderpriority", F.col("O").alias("o"), F.col("F").alias("f"), F.col("P").alias("p"))


@query("SELECT doc_id, 'quality' AS measure, quality AS val FROM labels UNION ALL SELECT doc_id, 'toxic', toxic FROM labels")
def unpivot(spark, sf_dir):
    return t(spark, sf_dir, "labels").unpivot("doc_id", ["quality", "toxic"], "measure", "val")


@query("SELECT p_partkey, rank() OVER w AS r, dense_rank() OVER w AS d, ntile(4) OVER (PARTITION BY p_brand ORDER BY p_size, p_partkey) AS q, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_size)")
def win_rank(spark, sf_dir):
    w, u = Window.partitionBy("p_brand").orderBy("p_size"), Window.partitionBy("p_brand").orderBy("p_size", "p_partkey")
    return t(spark, sf_dir, "part").select("p_partkey", F.rank().over(w).alias("r"), F.dense_rank().over(w).alias("d"), F.ntile(4).over(u).alias("q"), F.round(F.percent_rank().over(w), 6).alias("pr"), F.round(F.cume_dist().over(w), 6).alias("cd"))


@query("SELECT event_id, lag(event_type) OVER w AS before, lead(event_type) OVER w AS after, first_value(event_id) OVER w AS first_id, nth_value(event_id, 2) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS second_id FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id)")
def win_lag(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("event_id")
    full = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return t(spark, sf_dir, "events").select("event_id", F.lag("event_type").over(w).alias("before"), F.lead("event_type").over(w).alias("after"), F.first("event_id").over(w).alias("first_id"), F.nth_value("event_id", 2).over(full).alias("second_id"))


@query("SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 6) AS rolling FROM events")
def win_rows(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("event_id").rowsBetween(-2, 0)
    return t(spark, sf_dir, "events").select("event_id", F.round(F.avg("value").over(w), 6).alias("rolling"))


@query("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 DAY PRECEDING AND CURRENT ROW) AS in_day FROM events")
def win_range(spark, sf_dir):
    t(spark, sf_dir, "events").createOrReplaceTempView("__events_range")
    return spark.sql("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 DAY PRECEDING AND CURRENT ROW) AS in_day FROM __events_range")


@query("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 25")
def topk_global(spark, sf_dir):
    return t(spark, sf_dir, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(25).select("o_orderkey", "o_totalprice")


@query("SELECT p_type, p_partkey FROM (SELECT p_type, p_partkey, row_number() OVER (PARTITION BY p_type ORDER BY p_retailprice DESC, p_partkey) AS k FROM part) WHERE k <= 5")
def topk_group(spark, sf_dir):
    w = Window.partitionBy("p_type").orderBy(F.desc("p_retailprice"), "p_partkey")
    return t(spark, sf_dir, "part").withColumn("k", F.row_number().over(w)).where("k <= 5").select("p_type", "p_partkey")


@query("SELECT c_nationkey AS k FROM customer UNION ALL SELECT s_nationkey FROM supplier")
def set_union(spark, sf_dir):
    return t(spark, sf_dir, "customer").select(F.col("c_nationkey").alias("k")).union(t(spark, sf_dir, "supplier").select("s_nationkey"))


@query("SELECT c_nationkey AS k FROM customer INTERSECT SELECT s_nationkey FROM supplier")
def set_intersect(spark, sf_dir):
    return t(spark, sf_dir, "customer").select(F.col("c_nationkey").alias("k")).intersect(t(spark, sf_dir, "supplier").select("s_nationkey"))


@query("SELECT p_partkey AS k FROM part EXCEPT SELECT l_partkey FROM lineitem")
def set_except(spark, sf_dir):
    return t(spark, sf_dir, "part").select(F.col("p_partkey").alias("k")).subtract(t(spark, sf_dir, "lineitem").select("l_partkey"))


@query("SELECT o_orderkey FROM orders WHERE ('0x' || substr(md5('smp' || o_orderkey::VARCHAR), 1, 8))::BIGINT % 10 = 0")
def sample_hash(spark, sf_dir):
    """A tenth of the orders by a hash of the key: the sampling operator."""
    from conflate.operators.resample import hash32

    return t(spark, sf_dir, "orders").where(hash32(F.concat(F.lit("smp"), F.col("o_orderkey").cast("string"))) % 10 == 0).select("o_orderkey")


@query("WITH RECURSIVE r(level, side) AS (SELECT 0, 49.0 * sqrt(count(DISTINCT p_partkey)::DOUBLE) FROM part UNION ALL SELECT level + 1, side / 2 FROM r WHERE side / 2 >= 25) SELECT level, side FROM r")
def recursive_cte(spark, sf_dir):
    """Box sides of a recursive split, from the side of the parts' study area down to 25 m."""
    side = f"SELECT 0, 49.0D * sqrt(CAST(count(DISTINCT p_partkey) AS DOUBLE)) FROM parquet.`{sf_dir}/part.parquet`"
    return spark.sql(f"WITH RECURSIVE r(level, side) AS ({side} UNION ALL SELECT level + 1, side / 2 FROM r WHERE side / 2 >= 25) SELECT level, side FROM r")


@query("SELECT p_partkey, i - 1 AS pos, w FROM (SELECT p_partkey, unnest(string_split(p_name, ' ')) AS w, generate_subscripts(string_split(p_name, ' '), 1) AS i FROM part)")
def explode_tokens(spark, sf_dir):
    return t(spark, sf_dir, "part").select("p_partkey", F.posexplode(F.split("p_name", " ")).alias("pos", "w"))


@query("SELECT event_id, coalesce(nullif(event_type, 'error'), 'none') AS kind, CASE WHEN value < 10 THEN 'low' WHEN value < 60 THEN 'mid' ELSE 'high' END AS level FROM events")
def null_handling(spark, sf_dir):
    return t(spark, sf_dir, "events").select("event_id", F.coalesce(F.nullif("event_type", F.lit("error")), F.lit("none")).alias("kind"), F.when(F.col("value") < 10, "low").when(F.col("value") < 60, "mid").otherwise("high").alias("level"))


@query("SELECT p_partkey, reverse(p_name) AS rev, lpad(p_brand, 12, '*') AS pad, instr(p_name, ' ') AS sp, translate(p_name, 'aeiou', '12345') AS tr, levenshtein(p_name, p_type) AS lev, replace(p_brand, 'Brand', 'B') AS rep, regexp_extract(p_brand, '(\\d+)', 1) AS num FROM part")
def fn_string(spark, sf_dir):
    return t(spark, sf_dir, "part").select("p_partkey", F.reverse("p_name").alias("rev"), F.lpad("p_brand", 12, "*").alias("pad"), F.instr("p_name", " ").alias("sp"), F.translate("p_name", "aeiou", "12345").alias("tr"), F.levenshtein("p_name", "p_type").alias("lev"), F.replace("p_brand", F.lit("Brand"), F.lit("B")).alias("rep"), F.regexp_extract("p_brand", r"(\d+)", 1).alias("num"))


@query("SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS first, date_diff('day', o_orderdate::DATE, DATE '1999-01-01') AS d, strftime(o_orderdate, '%Y/%m') AS ym FROM orders")
def fn_date(spark, sf_dir):
    o = t(spark, sf_dir, "orders")
    return o.select("o_orderkey", F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"), F.date_format(F.date_trunc("month", "o_orderdate"), "yyyy-MM-dd").alias("first"), F.datediff(F.to_date(F.lit("1999-01-01")), F.to_date("o_orderdate")).alias("d"), F.date_format("o_orderdate", "yyyy/MM").alias("ym"))


@query("SELECT event_id, round(sqrt(abs(value)), 6) AS s, round(ln(abs(value) + 1), 6) AS l, floor(value)::BIGINT AS f, ceil(value)::BIGINT AS c, greatest(value, 50.0) AS g, event_id % 7 AS p FROM events")
def fn_math(spark, sf_dir):
    v = F.col("value")
    return t(spark, sf_dir, "events").select("event_id", F.round(F.sqrt(F.abs(v)), 6).alias("s"), F.round(F.log(F.abs(v) + 1), 6).alias("l"), F.floor(v).cast("long").alias("f"), F.ceil(v).cast("long").alias("c"), F.greatest(v, F.lit(50.0)).alias("g"), F.pmod(F.col("event_id"), F.lit(7)).alias("p"))


@query("SELECT p_partkey, array_to_string(list_sort(list_distinct(string_split(p_name || ' ' || lower(p_type), ' '))), '|') AS words, len(list_intersect(string_split(p_name, ' '), ['ring', 'rod'])) AS hits, list_contains(string_split(p_name, ' '), 'ring') AS ring FROM part")
def fn_array(spark, sf_dir):
    words = F.split("p_name", " ")
    return t(spark, sf_dir, "part").select("p_partkey", F.array_join(F.array_sort(F.array_distinct(F.concat(words, F.array(F.lower("p_type"))))), "|").alias("words"), F.size(F.array_intersect(words, F.array(F.lit("ring"), F.lit("rod")))).cast("long").alias("hits"), F.array_contains(words, "ring").alias("ring"))


@query("SELECT user_id, string_agg(event_type || '=' || n, '|' ORDER BY event_type) AS counts FROM (SELECT user_id, event_type, count(*) AS n FROM events GROUP BY 1, 2) GROUP BY 1")
def fn_map(spark, sf_dir):
    g = t(spark, sf_dir, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("n")).groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return g.select("user_id", F.array_join(F.array_sort(F.transform(F.map_entries("m"), lambda e: F.concat_ws("=", e["key"], e["value"].cast("string")))), "|").alias("counts"))


@query("SELECT event_id, (props->>'$.k')::BIGINT AS k FROM events")
def fn_json(spark, sf_dir):
    return t(spark, sf_dir, "events").select("event_id", F.try_variant_get(F.parse_json("props"), "$.k", "bigint").alias("k"))


@query("SELECT p_partkey, md5(p_name) AS m, ('0x' || substr(md5(p_name), 1, 8))::BIGINT AS h FROM part")
def fn_hash(spark, sf_dir):
    return t(spark, sf_dir, "part").select("p_partkey", F.md5("p_name").alias("m"), F.conv(F.substring(F.md5("p_name"), 1, 8), 16, 10).cast("long").alias("h"))


@query("SELECT p_partkey, array_to_string(list_sort(string_split(lower(p_name), ' ')), ' ') AS sorted_tokens, round(1 - levenshtein(p_name, lower(p_type)) / greatest(length(p_name), length(p_type))::DOUBLE, 6) AS sim FROM part")
def fn_domain(spark, sf_dir):
    domain.register(spark)
    t(spark, sf_dir, "part").createOrReplaceTempView("__part_domain")
    return spark.sql("SELECT p_partkey, token_sorted(p_name) AS sorted_tokens, round(name_similarity(p_name, lower(p_type)), 6) AS sim FROM __part_domain")


_VIS = "WITH p AS (SELECT count(*) AS n FROM part), v AS (SELECT user_id, ts, ('0x' || substr(md5('pl' || user_id::VARCHAR || (event_id % 7)::VARCHAR), 1, 8))::BIGINT % p.n AS place, event_id FROM events, p) "


@query(_VIS + "SELECT place, strftime(ts, '%Y-%m-%d') AS day, count(*) AS visits, count(DISTINCT user_id) AS users FROM v GROUP BY 1, 2 HAVING count(*) >= 2")
def regular_places(spark, sf_dir):
    from conflate.streaming import updates

    n = t(spark, sf_dir, "part").count()
    v = updates.visits(t(spark, sf_dir, "events"), n)
    return v.groupBy("place", F.date_format("ts", "yyyy-MM-dd").alias("day")).agg(F.count("*").alias("visits"), F.count_distinct("user_id").alias("users")).where("visits >= 2")


@query("SELECT strftime(to_timestamp(floor(epoch(ts) / 3600) * 3600), '%Y-%m-%d %H') AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def win_tumbling(spark, sf_dir):
    e = t(spark, sf_dir, "events")
    return e.groupBy(F.window("ts", "1 hour").alias("w"), "event_type").agg(F.count("*").alias("n")).select(F.date_format("w.start", "yyyy-MM-dd HH").alias("start"), "event_type", "n")


@query("SELECT strftime(to_timestamp(floor(epoch(ts) / 3600) * 3600 - k * 3600), '%Y-%m-%d %H') AS start, count(*) AS n FROM events, range(0, 2) r(k) GROUP BY 1")
def win_sliding(spark, sf_dir):
    e = t(spark, sf_dir, "events")
    return e.groupBy(F.window("ts", "2 hours", "1 hour").alias("w")).agg(F.count("*").alias("n")).select(F.date_format("w.start", "yyyy-MM-dd HH").alias("start"), "n")


@query("WITH g AS (SELECT user_id, ts, event_id, sum(CASE WHEN gap IS NULL OR gap >= 3600 THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT *, epoch(ts) - epoch(lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id)) AS gap FROM events)) SELECT user_id, min(event_id) AS first_event, count(*) AS n FROM g GROUP BY user_id, s")
def win_session(spark, sf_dir):
    e = t(spark, sf_dir, "events")
    return e.groupBy("user_id", F.session_window("ts", "1 hour")).agg(F.min("event_id").alias("first_event"), F.count("*").alias("n")).select("user_id", "first_event", "n")
