"""The operators that users need around the methods, one query each, on the given tables."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from unischema.functions.lineage import cut
from unischema.plans.method_queries import register
from unischema.sources.fixtures import ABBREVIATIONS, frame, sql_values

dec = lambda c: F.round(c, 4)


def micros(ts) -> Column:
    """Microseconds of a timestamp without zone, read as UTC whatever the session's zone is."""
    ts = F.col(ts) if isinstance(ts, str) else ts
    return F.unix_micros(F.convert_timezone(F.lit("UTC"), F.current_timezone(), ts).cast("timestamp"))


def query(name: str, build, sql: str | None) -> None:
    """Register ``op_<name>``; ``build(t, spark)`` gets a reader of tables."""

    def run(spark, sf_dir):
        return build(lambda table: spark.read.parquet(f"{sf_dir}/{table}.parquet"), spark)

    register(sql, name=f"op_{name}")(run)


def as_long(df: DataFrame, *names: str) -> DataFrame:
    return df.withColumns({n: F.col(n).cast("long") for n in names})


# sources, projections, filters
query("scan_parquet", lambda t, s: as_long(t("nation"), "n_nationkey", "n_regionkey"), "SELECT n_nationkey::BIGINT AS n_nationkey, n_name, n_regionkey::BIGINT AS n_regionkey FROM nation")
query("scan_json_props", lambda t, s: t("events").select("event_type", F.from_json("props", "k INT")["k"].alias("k")).groupBy("event_type").agg(F.sum("k").cast("long").alias("sum_k")),
      "SELECT event_type, sum(json_extract(props, '$.k')::BIGINT)::BIGINT AS sum_k FROM events GROUP BY event_type")
query("values_source", lambda t, s: frame(s, ABBREVIATIONS, "short string, full string").withColumnRenamed("full", "full_form"), f"SELECT * FROM {sql_values(ABBREVIATIONS, 'short', 'full_form')}")
query("project_filter", lambda t, s: t("lineitem").where((F.col("l_quantity") > 30) & F.col("l_discount").between(0.05, 0.07)).select("l_orderkey", "l_extendedprice"),
      "SELECT l_orderkey, l_extendedprice FROM lineitem WHERE l_quantity > 30 AND l_discount BETWEEN 0.05 AND 0.07")
query("case_when", lambda t, s: t("orders").select("o_orderkey", F.when(F.col("o_orderstatus") == "F", "finished").when(F.col("o_orderstatus") == "O", "open").otherwise("partly").alias("status")),
      "SELECT o_orderkey, CASE o_orderstatus WHEN 'F' THEN 'finished' WHEN 'O' THEN 'open' ELSE 'partly' END AS status FROM orders")

# joins
query("join_inner", lambda t, s: t("orders").join(t("customer"), F.col("o_custkey") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("n")),
      "SELECT c_mktsegment, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1")
query("join_left", lambda t, s: t("customer").join(t("orders").groupBy(F.col("o_custkey").alias("c_custkey")).agg(F.count(F.lit(1)).alias("n")), "c_custkey", "left").select("c_custkey", F.coalesce("n", F.lit(0)).cast("long").alias("n")),
      "SELECT c_custkey, count(o_orderkey) AS n FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY 1")
query("join_right", lambda t, s: as_long(t("labels").join(t("documents").select("doc_id"), "doc_id", "right").select("doc_id", "quality"), "quality"), "SELECT d.doc_id, quality::BIGINT AS quality FROM labels l RIGHT JOIN documents d ON l.doc_id = d.doc_id")
query("join_full", lambda t, s: t("customer").groupBy(F.col("c_nationkey").alias("k")).agg(F.count(F.lit(1)).alias("customers")).join(t("supplier").groupBy(F.col("s_nationkey").alias("k")).agg(F.count(F.lit(1)).alias("suppliers")), "k", "full").select(F.col("k").cast("long").alias("k"), "customers", "suppliers"),
      "SELECT coalesce(c.k, s.k)::BIGINT AS k, customers, suppliers FROM (SELECT c_nationkey AS k, count(*) AS customers FROM customer GROUP BY 1) c FULL JOIN (SELECT s_nationkey AS k, count(*) AS suppliers FROM supplier GROUP BY 1) s ON c.k = s.k")
query("join_semi", lambda t, s: t("part").join(t("lineitem"), F.col("p_partkey") == F.col("l_partkey"), "left_semi").select("p_partkey"), "SELECT p_partkey FROM part WHERE p_partkey IN (SELECT l_partkey FROM lineitem)")
query("join_anti", lambda t, s: t("customer").join(t("orders"), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey"), "SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders)")
query("join_cross", lambda t, s: t("region").select("r_name").crossJoin(F.broadcast(t("events").select("event_type").distinct())), "SELECT r_name, event_type FROM region, (SELECT DISTINCT event_type FROM events)")
def _theta(t, s) -> DataFrame:
    """Pairs of one brand with a smaller and a larger price, counted by order instead of listed.

    Equal prices are counted first; range blocks of prices, then prices in a block, are summed up in
    order, so that no task takes a whole brand.
    """
    rows = t("part").where("p_brand IS NOT NULL AND p_retailprice IS NOT NULL")
    counted = rows.groupBy(F.col("p_brand").alias("brand"), F.col("p_retailprice").alias("price")).agg(F.count(F.lit(1)).alias("n"))
    dealt = cut(counted.repartitionByRange("brand", "price").withColumn("block", F.spark_partition_id()))
    sums = dealt.groupBy("brand", "block").agg(F.sum("n").alias("total"))
    before = lambda *keys: Window.partitionBy(*keys[:-1]).orderBy(keys[-1]).rowsBetween(Window.unboundedPreceding, -1)
    blocks = sums.select("brand", "block", F.coalesce(F.sum("total").over(before("brand", "block")), F.lit(0)).alias("lower"))
    inside = dealt.withColumn("below", F.coalesce(F.sum("n").over(before("brand", "block", "price")), F.lit(0)))
    return inside.join(blocks, ["brand", "block"]).groupBy("brand").agg(F.sum(F.col("n") * (F.col("below") + F.col("lower"))).alias("n")).where("n > 0")


query("join_theta", _theta,
      "SELECT x.p_brand AS brand, count(*) AS n FROM part x JOIN part y ON x.p_brand = y.p_brand AND x.p_retailprice < y.p_retailprice GROUP BY 1")


def _band(t, s) -> DataFrame:
    """Names whose lengths differ by at most one: an equi-join on length buckets instead of a loop."""
    names = t("part").select(F.col("p_name").alias("attr")).distinct().withColumn("len", F.length("attr"))
    probes = names.select("attr", "len", F.explode(F.array(F.col("len") - 1, F.col("len"), F.col("len") + 1)).alias("bucket"))
    met = probes.alias("x").join(names.alias("y"), F.col("x.bucket") == F.col("y.len")).where("x.attr < y.attr")
    return met.select(F.col("x.attr").alias("a"), F.col("y.attr").alias("b"))


query("join_band_length", _band, "WITH n AS (SELECT DISTINCT p_name AS attr FROM part) SELECT x.attr AS a, y.attr AS b FROM n x JOIN n y ON x.attr < y.attr AND abs(length(x.attr) - length(y.attr)) <= 1")


def _interval(t, s) -> DataFrame:
    """Events within ten minutes after an error of the same user: buckets of ten minutes, then the exact test."""
    events = t("events").select("event_id", "user_id", "event_type", micros("ts").alias("us"))
    width = 600_000_000
    errors = events.where("event_type = 'error'").select("user_id", F.col("us").alias("from_us"), F.explode(F.array(F.floor(F.col("us") / width), F.floor(F.col("us") / width) + 1)).alias("bucket"))
    met = events.withColumn("bucket", F.floor(F.col("us") / width)).join(errors, ["user_id", "bucket"]).where(F.col("us").between(F.col("from_us"), F.col("from_us") + width))
    return met.groupBy("event_id").agg(F.count_distinct("from_us").alias("n"))


query("join_interval_events", _interval, "SELECT e.event_id, count(DISTINCT x.ts) AS n FROM events e JOIN events x ON e.user_id = x.user_id AND x.event_type = 'error' AND e.ts BETWEEN x.ts AND x.ts + INTERVAL 10 MINUTE GROUP BY 1")


def _asof(t, s) -> DataFrame:
    """The latest view of the same user before each purchase, by one window instead of a range join."""
    order = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    rows = t("events").withColumn("view_id", F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True).over(order))
    return rows.where("event_type = 'purchase'").select("event_id", "view_id")


query("join_asof_events", _asof, "SELECT event_id, view_id FROM (SELECT event_id, event_type, last_value(CASE WHEN event_type = 'view' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS view_id FROM events) WHERE event_type = 'purchase'")
_NULLABLE = [("a", 1), (None, 2), ("b", 3)]


query("join_null_safe", lambda t, s: frame(s, _NULLABLE, "k string, x long").alias("l").join(frame(s, _NULLABLE, "k string, y long").alias("r"), F.col("l.k").eqNullSafe(F.col("r.k"))).select("l.x", "r.y"), "SELECT x::BIGINT AS x, x::BIGINT AS y FROM (VALUES (1), (2), (3)) t(x)")

# aggregation
query("group_by", lambda t, s: t("lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.round(F.sum("l_quantity"), 2).alias("sum_qty"), dec(F.avg("l_extendedprice")).alias("avg_price"), F.count(F.lit(1)).alias("n")),
      "SELECT l_returnflag, l_linestatus, round(sum(l_quantity), 2) AS sum_qty, round(avg(l_extendedprice), 4) AS avg_price, count(*) AS n FROM lineitem GROUP BY 1, 2")
query("distinct_agg", lambda t, s: t("events").groupBy("event_type").agg(F.count_distinct("user_id").alias("users")), "SELECT event_type, count(DISTINCT user_id) AS users FROM events GROUP BY 1")
query("approx_distinct", lambda t, s: t("events").agg(F.approx_count_distinct("user_id", 0.01).alias("users")), None)
query("rollup", lambda t, s: t("customer").join(t("nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(t("region"), F.col("n_regionkey") == F.col("r_regionkey")).rollup("r_name", "n_name").agg(F.count(F.lit(1)).alias("n")),
      "SELECT r_name, n_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)")
query("cube", lambda t, s: t("orders").cube("o_orderstatus", "o_orderpriority").agg(F.count(F.lit(1)).alias("n")), "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)")
query("grouping_sets", lambda t, s: t("part").groupingSets([["p_brand"], ["p_type"]], "p_brand", "p_type").agg(F.count(F.lit(1)).alias("n")), "SELECT p_brand, p_type, count(*) AS n FROM part GROUP BY GROUPING SETS ((p_brand), (p_type))")
query("pivot", lambda t, s: t("events").where("event_type IN ('view', 'click')").groupBy("user_id").pivot("event_type", ["view", "click"]).count(), "SELECT user_id, nullif(count(*) FILTER (WHERE event_type = 'view'), 0) AS view, nullif(count(*) FILTER (WHERE event_type = 'click'), 0) AS click FROM events WHERE event_type IN ('view', 'click') GROUP BY 1")
query("unpivot", lambda t, s: t("supplier").select("s_suppkey", F.col("s_nationkey").cast("double").alias("nation"), F.col("s_acctbal").alias("balance")).unpivot("s_suppkey", ["nation", "balance"], "attr", "val"),
      "SELECT s_suppkey, 'nation' AS attr, s_nationkey::DOUBLE AS val FROM supplier UNION ALL SELECT s_suppkey, 'balance', s_acctbal FROM supplier")
query("max_by", lambda t, s: t("part").groupBy("p_brand").agg(F.max_by("p_partkey", F.struct("p_retailprice", "p_partkey")).alias("dearest"), F.min_by("p_partkey", F.struct("p_retailprice", "p_partkey")).alias("cheapest")),
      "SELECT p_brand, (list(p_partkey ORDER BY p_retailprice DESC, p_partkey DESC))[1] AS dearest, (list(p_partkey ORDER BY p_retailprice, p_partkey))[1] AS cheapest FROM part GROUP BY 1")
query("listagg", lambda t, s: t("part").groupBy("p_brand").agg(F.array_join(F.sort_array(F.collect_set("p_name")), "|").alias("names")), "SELECT p_brand, string_agg(DISTINCT p_name, '|' ORDER BY p_name) AS names FROM part GROUP BY 1")
query("percentile", lambda t, s: t("orders").agg(F.round(F.expr("percentile(o_totalprice, 0.5)"), 2).alias("median")), "SELECT round(quantile_cont(o_totalprice, 0.5), 2) AS median FROM orders")
query("filter_agg", lambda t, s: t("labels").agg(F.count_if(F.col("toxic") == 1).alias("n_toxic"), F.count(F.lit(1)).alias("n")), "SELECT count(*) FILTER (WHERE toxic = 1) AS n_toxic, count(*) AS n FROM labels")

# windows
_by_nation = lambda: Window.partitionBy("s_nationkey").orderBy(F.col("s_acctbal").desc())
query("rank", lambda t, s: t("supplier").select("s_suppkey", F.rank().over(_by_nation()).cast("long").alias("k")), "SELECT s_suppkey, rank() OVER (PARTITION BY s_nationkey ORDER BY s_acctbal DESC) AS k FROM supplier")
query("dense_rank", lambda t, s: t("part").select("p_partkey", F.dense_rank().over(Window.partitionBy("p_brand").orderBy("p_size")).cast("long").alias("k")), "SELECT p_partkey, dense_rank() OVER (PARTITION BY p_brand ORDER BY p_size) AS k FROM part")
query("ntile", lambda t, s: t("part").select("p_partkey", F.ntile(3).over(Window.partitionBy("p_brand").orderBy("p_partkey")).cast("long").alias("k")), "SELECT p_partkey, ntile(3) OVER (PARTITION BY p_brand ORDER BY p_partkey) AS k FROM part")
_by_user = lambda: Window.partitionBy("user_id").orderBy("ts", "event_id")
query("lag_lead", lambda t, s: t("events").select("event_id", (micros("ts") - micros(F.lag("ts").over(_by_user()))).alias("gap"), F.lead("event_id").over(_by_user()).alias("following")),
      "SELECT event_id, epoch_us(ts) - epoch_us(lag(ts) OVER w) AS gap, lead(event_id) OVER w AS following FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
query("running_sum_rows", lambda t, s: t("events").select("event_id", F.count("value").over(_by_user().rowsBetween(Window.unboundedPreceding, 0)).alias("n"), dec(F.max("value").over(_by_user().rowsBetween(Window.unboundedPreceding, 0))).alias("most")),
      "SELECT event_id, count(value) OVER w AS n, round(max(value) OVER w, 4) AS most FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING)")
query("moving_avg_range", lambda t, s: t("events").withColumn("us", micros("ts")).select("event_id", F.round(F.avg("value").over(Window.partitionBy("user_id").orderBy("us").rangeBetween(-3_600_000_000, 0)), 6).alias("hour_avg")),
      "SELECT event_id, round(avg(value) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 3600000000 PRECEDING AND CURRENT ROW), 6) AS hour_avg FROM events")
query("first_last", lambda t, s: t("events").select("user_id", F.first("event_type").over(_by_user().rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)).alias("first_type"), F.last("event_type").over(_by_user().rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)).alias("last_type")).distinct(),
      "SELECT DISTINCT user_id, first_value(event_type) OVER w AS first_type, last_value(event_type) OVER w AS last_type FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
query("topk_global", lambda t, s: t("orders").orderBy(F.col("o_totalprice").desc(), "o_orderkey").limit(10).select("o_orderkey", "o_totalprice"), "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10")
query("topk_group", lambda t, s: t("supplier").withColumn("k", F.row_number().over(Window.partitionBy("s_nationkey").orderBy(F.col("s_acctbal").desc(), "s_suppkey"))).where("k <= 3").select("s_suppkey"), "SELECT s_suppkey FROM supplier QUALIFY row_number() OVER (PARTITION BY s_nationkey ORDER BY s_acctbal DESC, s_suppkey) <= 3")

# sets
query("union", lambda t, s: t("nation").select(F.col("n_name").alias("name")).union(t("region").select("r_name")).union(t("part").select("p_brand")).distinct(), "SELECT n_name AS name FROM nation UNION SELECT r_name FROM region UNION SELECT p_brand FROM part")
query("intersect", lambda t, s: as_long(t("customer").select(F.col("c_nationkey").alias("k")).intersect(t("supplier").select("s_nationkey")), "k"), "SELECT c_nationkey::BIGINT AS k FROM customer INTERSECT SELECT s_nationkey::BIGINT FROM supplier")
query("except", lambda t, s: as_long(t("nation").select(F.col("n_nationkey").alias("k")).subtract(t("supplier").where("s_suppkey < 20").select("s_nationkey")), "k"), "SELECT n_nationkey::BIGINT AS k FROM nation EXCEPT SELECT s_nationkey::BIGINT FROM supplier WHERE s_suppkey < 20")
query("except_all", lambda t, s: t("part").select("p_type").exceptAll(t("part").where("p_size > 10").select("p_type")), "SELECT p_type FROM part EXCEPT ALL SELECT p_type FROM part WHERE p_size > 10")

# functions
query("string_fns", lambda t, s: t("nation").select(F.lower("n_name").alias("low"), F.substring("n_name", 1, 3).alias("head"), F.concat_ws("-", "n_name", F.lit("x")).alias("tied"), F.lpad("n_name", 12, "*").alias("padded"), F.translate("n_name", "AEIOU", "aeiou").alias("vowels")),
      "SELECT lower(n_name) AS low, n_name[1:3] AS head, n_name || '-x' AS tied, lpad(n_name, 12, '*') AS padded, translate(n_name, 'AEIOU', 'aeiou') AS vowels FROM nation")
query("regexp_fns", lambda t, s: t("part").select("p_partkey", F.regexp_extract("p_name", "([a-z]+)$", 1).alias("noun"), F.regexp_replace("p_name", "[aeiou]", "").alias("bare"), F.size(F.regexp_extract_all("p_name", F.lit("[a-z]+"), F.lit(0))).cast("long").alias("n")),
      "SELECT p_partkey, regexp_extract(p_name, '([a-z]+)$', 1) AS noun, regexp_replace(p_name, '[aeiou]', '', 'g') AS bare, len(regexp_extract_all(p_name, '[a-z]+')) AS n FROM part")
query("date_fns", lambda t, s: t("orders").groupBy(F.date_format(F.date_trunc("month", "o_orderdate"), "yyyy-MM").alias("month")).agg(F.count(F.lit(1)).alias("n"), F.max(F.datediff(F.col("o_orderdate"), F.lit("1992-01-01").cast("date"))).cast("long").alias("days")),
      "SELECT strftime(date_trunc('month', o_orderdate), '%Y-%m') AS month, count(*) AS n, max(date_diff('day', DATE '1992-01-01', o_orderdate::DATE))::BIGINT AS days FROM orders GROUP BY 1")
query("math_fns", lambda t, s: t("part").select("p_partkey", F.round(F.ln(F.col("p_retailprice")), 6).alias("ln_price"), F.round(F.sqrt(F.col("p_size").cast("double")), 6).alias("root"), F.pmod(F.col("p_partkey"), F.lit(7)).alias("residue"), F.greatest(F.col("p_size").cast("long"), F.lit(10).cast("long")).alias("most")),
      "SELECT p_partkey, round(ln(p_retailprice), 6) AS ln_price, round(sqrt(p_size), 6) AS root, p_partkey % 7 AS residue, greatest(p_size::BIGINT, 10) AS most FROM part")
query("array_fns", lambda t, s: t("embeddings").select("vec_id", F.round(F.aggregate(F.transform("embedding", lambda x: x.cast("double") * x), F.lit(0.0), lambda a, x: a + x), 4).alias("norm2"), F.size(F.filter("embedding", lambda x: x > 0)).cast("long").alias("positive")),
      "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x : x::DOUBLE * x)), 4) AS norm2, len(list_filter(embedding, lambda x : x > 0)) AS positive FROM embeddings")
query("map_fns", lambda t, s: t("part").groupBy("p_brand", "p_type").count().groupBy("p_brand").agg(F.map_from_entries(F.collect_list(F.struct("p_type", "count"))).alias("m")).select("p_brand", F.coalesce(F.try_element_at("m", F.lit("ECONOMY")), F.lit(0)).cast("long").alias("economy"), F.size("m").cast("long").alias("n_types")),
      "SELECT p_brand, count(*) FILTER (WHERE p_type = 'ECONOMY') AS economy, count(DISTINCT p_type) AS n_types FROM part GROUP BY 1")
query("struct_fns", lambda t, s: t("nation").select(F.inline(F.array(F.struct(F.col("n_name").alias("name"), F.lit("nation").alias("kind")), F.struct(F.lower("n_name").alias("name"), F.lit("lower").alias("kind"))))), "SELECT n_name AS name, 'nation' AS kind FROM nation UNION ALL SELECT lower(n_name), 'lower' FROM nation")
query("json_fns", lambda t, s: t("events").select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"), F.to_json(F.struct("user_id")).alias("packed")), "SELECT event_id, json_extract_string(props, '$.k')::BIGINT AS k, '{\"user_id\":' || user_id || '}' AS packed FROM events")
query("url_fns", lambda t, s: t("pages").groupBy(F.parse_url("url", F.lit("HOST")).alias("host")).agg(F.count(F.lit(1)).alias("n")), "SELECT regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS host, count(*) AS n FROM pages GROUP BY 1")

# SQL surface


def _sql(text: str, *names: str):
    def build(t, s):
        for name in names:
            t(name).createOrReplaceTempView(name)
        return s.sql(text)

    return build


_CTE = "WITH per AS (SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey) SELECT n AS orders_each, count(*) AS customers FROM per GROUP BY n"
query("cte", _sql(_CTE, "orders"), _CTE)
_EXISTS = "SELECT o_orderkey FROM orders o WHERE EXISTS (SELECT 1 FROM lineitem l WHERE l.l_orderkey = o.o_orderkey AND l.l_quantity > 45)"
query("exists_subquery", _sql(_EXISTS, "orders", "lineitem"), _EXISTS)
_SCALAR = "SELECT p_partkey FROM part p WHERE p_retailprice > (SELECT avg(q.p_retailprice) FROM part q WHERE q.p_brand = p.p_brand)"
query("scalar_subquery", _sql(_SCALAR, "part"), _SCALAR)
query("lateral", _sql("SELECT p_partkey, w.word FROM part, LATERAL (SELECT explode(split(p_name, ' ')) AS word) w", "part"), "SELECT p_partkey, unnest(string_split(p_name, ' ')) AS word FROM part")


def _recursive(t, s) -> DataFrame:
    t("nation").createOrReplaceTempView("nation")
    t("region").createOrReplaceTempView("region")
    return s.sql("""WITH RECURSIVE up(name, depth) AS (SELECT 'NATION_0', 0 UNION ALL SELECT r.r_name, depth + 1 FROM up JOIN nation n ON n.n_name = up.name JOIN region r ON r.r_regionkey = n.n_regionkey)
      SELECT name, CAST(depth AS BIGINT) AS depth FROM up""")


query("recursive_cte", _recursive, "SELECT 'NATION_0' AS name, 0::BIGINT AS depth UNION ALL SELECT r_name, 1 FROM nation JOIN region ON n_regionkey = r_regionkey WHERE n_name = 'NATION_0'")
query("sample_stats", lambda t, s: t("documents").select(F.length("text").alias("n")).sample(0.5, seed=3).agg(F.percentile_approx("n", 0.5).alias("median")), None)

# time windows in batch form


def _windowed(t, slide: str | None) -> DataFrame:
    window = F.window("ts", "1 hour", slide) if slide else F.window("ts", "1 hour")
    rows = t("events").groupBy(window.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"))
    return rows.select((micros("w.start") / 1_000_000).cast("long").alias("start_s"), "event_type", "n")


query("tumbling", lambda t, s: _windowed(t, None), "SELECT (epoch(ts)::BIGINT // 3600) * 3600 AS start_s, event_type, count(*) AS n FROM (SELECT event_type, date_trunc('second', ts) AS ts FROM events) GROUP BY ALL")
query("sliding", lambda t, s: _windowed(t, "15 minutes"), "SELECT (epoch(ts)::BIGINT // 900) * 900 - 900 * k AS start_s, event_type, count(*) AS n FROM (SELECT event_type, date_trunc('second', ts) AS ts FROM events), range(0, 4) r(k) GROUP BY ALL")
query("session", lambda t, s: t("events").groupBy("user_id", F.session_window("ts", "30 minutes").alias("w")).agg(F.count(F.lit(1)).alias("n")).select("user_id", micros("w.start").alias("start_us"), "n"),
      """SELECT user_id, epoch_us(min(ts)) AS start_us, count(*) AS n FROM (SELECT user_id, ts, sum(CASE WHEN gap IS NULL OR gap >= INTERVAL 30 MINUTE THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY ts) AS sid
      FROM (SELECT user_id, ts, ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) AS gap FROM events)) GROUP BY user_id, sid""")  # fmt: skip

# user functions


def _grams_udtf(t, s) -> DataFrame:
    from unischema.functions.udf import register_udtf

    register_udtf(s)
    t("nation").createOrReplaceTempView("nation")
    return s.sql("SELECT n_name, g.gram, CAST(g.pos AS BIGINT) AS pos FROM nation, LATERAL gram_table(n_name, 2) g")


query("udtf_grams", _grams_udtf, "SELECT n_name, n_name[pos : pos + 1] AS gram, pos FROM (SELECT n_name, unnest(range(1, length(n_name))) AS pos FROM nation)")


def _judges(t, s) -> DataFrame:
    from unischema.functions.udf import spread

    return t("labels").groupBy("quality").agg(F.round(spread(F.col("toxic").cast("double")), 6).alias("deviation")).select(F.col("quality").cast("long").alias("quality"), "deviation")


query("udaf_judges", _judges, "SELECT quality::BIGINT AS quality, round(stddev_pop(toxic), 6) AS deviation FROM labels GROUP BY 1")


def _bound(t, s) -> DataFrame:
    from unischema.functions.text import register_sql

    register_sql(s)
    t("nation").createOrReplaceTempView("nation")
    return s.sql("SELECT n_name, CAST(count_bound(length(n_name), 8, 2, 1) AS BIGINT) AS bound, edit_within(n_name, 'NATION_1', 1) AS near, CAST(size(qgrams(n_name, 2)) AS BIGINT) AS n_grams FROM nation")


query("sql_udf_bound", _bound, "SELECT n_name, greatest(length(n_name), 8) - 3 AS bound, levenshtein(n_name, 'NATION_1') <= 1 AS near, length(n_name) - 1 AS n_grams FROM nation")
