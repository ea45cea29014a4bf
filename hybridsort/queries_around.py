"""Registered queries: the operators that a user of the sorts has around them."""

from __future__ import annotations

from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .functions import keys as K
from .operators import baselines, joins
from .sources import records as R
from .sources.tables import table

QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(name: str, tables: str, sql: str | None = None):
    """The function gets the named tables."""

    def add(f):
        QUERIES[name] = lambda spark, sf_dir: f(*[table(spark, sf_dir, t) for t in tables.split()])
        if sql:
            SQL[name] = sql
        return f

    return add


# Scans and projections
for _t in "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split():
    QUERIES[f"scan_{_t}"] = lambda spark, sf_dir, t=_t: table(spark, sf_dir, t).agg(F.count("*").alias("n"))
    SQL[f"scan_{_t}"] = f"select count(*) as n from {_t}"

query("project_key_payload", "lineitem", "select l_orderkey, l_linenumber, l_extendedprice * (1 - l_discount) as net from lineitem")(lambda li: li.select("l_orderkey", "l_linenumber", (F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("net")))
query("filter_key_range", "lineitem", "select l_orderkey, l_linenumber, l_partkey from lineitem where lpad(hex(l_orderkey), 16, '0') between '0000000000000100' and '00000000000001FF'")(lambda li: li.where(K.unsigned(F.col("l_orderkey")).between("0000000000000100", "00000000000001FF")).select("l_orderkey", "l_linenumber", "l_partkey"))
query("filter_prefix", "pages", "select page_id, url from pages where url like 'https://w%'")(lambda p: p.where(F.col("url").startswith("https://w")).select("page_id", "url"))
query("filter_in_list", "orders", "select o_orderkey from orders where o_orderstatus in ('F', 'P')")(lambda o: o.where(F.col("o_orderstatus").isin("F", "P")).select("o_orderkey"))
query("filter_and_or_not", "orders", "select o_orderkey from orders where (o_orderstatus = 'F' or o_totalprice > 100000) and not o_orderpriority like '1%'")(lambda o: o.where(((F.col("o_orderstatus") == "F") | (F.col("o_totalprice") > 100000)) & ~F.col("o_orderpriority").like("1%")).select("o_orderkey"))
query("filter_null_safe", "documents labels", "select doc_id, coalesce(quality, -1) as quality from documents left join labels using (doc_id) where quality is not distinct from null or quality = 1")(lambda d, lab: d.join(lab, "doc_id", "left").where(F.col("quality").eqNullSafe(F.lit(None)) | (F.col("quality") == 1)).select("doc_id", F.coalesce("quality", F.lit(-1)).alias("quality")))
query("filter_regex", "documents", "select doc_id from documents where regexp_matches(text, '[0-9]{4}')")(lambda d: d.where(F.col("text").rlike("[0-9]{4}")).select("doc_id"))
query("filter_date_interval", "lineitem orders", "select l_orderkey, l_linenumber, l_partkey from lineitem join orders on l_orderkey = o_orderkey where l_shipdate between o_orderdate and o_orderdate + interval 30 day")(lambda li, o: li.join(o, li["l_orderkey"] == o["o_orderkey"]).where(F.col("l_shipdate").between(F.col("o_orderdate"), F.col("o_orderdate") + F.expr("interval 30 day"))).select("l_orderkey", "l_linenumber", "l_partkey"))
query("sample_keys", "events", "select event_id from events where substr(md5(cast(event_id as varchar)), 1, 1) = '0'")(lambda e: e.where(F.substring(F.md5(F.col("event_id").cast("string")), 1, 1) == "0").select("event_id"))

# Joins
query("join_broadcast_hash", "orders customer", "select o_orderkey, c_name from orders join customer on o_custkey = c_custkey")(lambda o, c: o.join(c.hint("broadcast"), o["o_custkey"] == c["c_custkey"]).select("o_orderkey", "c_name"))
_LO = "select l_orderkey, l_linenumber, l_partkey, o_orderdate from lineitem join orders on l_orderkey = o_orderkey"
for _hint in ("shuffle_hash", "merge"):
    query(f"join_{'sort_merge' if _hint == 'merge' else _hint}", "lineitem orders", _LO)(lambda li, o, h=_hint: li.join(o.hint(h), li["l_orderkey"] == o["o_orderkey"]).select("l_orderkey", "l_linenumber", "l_partkey", "o_orderdate"))
for _how, _sql in (("left", "left"), ("right", "right"), ("full", "full outer")):
    query(f"join_{_how}_outer", "customer orders", f"select c_custkey, o_orderkey from customer {_sql} join orders on c_custkey = o_custkey")(lambda c, o, h=_how: c.join(o, c["c_custkey"] == o["o_custkey"], h).select("c_custkey", "o_orderkey"))
query("join_semi", "documents labels", "select doc_id from documents where doc_id in (select doc_id from labels)")(lambda d, lab: d.join(lab, "doc_id", "left_semi").select("doc_id"))
query("join_anti", "documents labels", "select doc_id from documents where doc_id not in (select doc_id from labels)")(lambda d, lab: d.join(lab, "doc_id", "left_anti").select("doc_id"))
query("join_nested_loop_theta", "nation region", "select n_name, r_name from nation join region on n_regionkey < r_regionkey")(lambda n, r: n.join(F.broadcast(r), n["n_regionkey"] < r["r_regionkey"]).select("n_name", "r_name"))
query("join_multiway", "lineitem orders customer nation region", "select r_name, count(*) as n from lineitem join orders on l_orderkey = o_orderkey join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by r_name")(lambda li, o, c, n, r: li.join(o, li["l_orderkey"] == o["o_orderkey"]).join(c, F.col("o_custkey") == F.col("c_custkey")).join(n, F.col("c_nationkey") == F.col("n_nationkey")).join(r, F.col("n_regionkey") == F.col("r_regionkey")).groupBy("r_name").agg(F.count("*").alias("n")))
query("join_self_pointer_gather", "lineitem", "select a.l_orderkey, a.l_linenumber, a.l_partkey, b.l_tax from lineitem a join lineitem b using (l_orderkey, l_linenumber, l_partkey, l_suppkey, l_extendedprice)")(lambda li: li.select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice").join(li.select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice", "l_tax"), ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice"]).select("l_orderkey", "l_linenumber", "l_partkey", "l_tax"))
query("join_asof_events", "events", "select a.event_id, b.value from (select * from events where event_type = 'click') a asof left join (select * from events where event_type = 'view') b on a.user_id = b.user_id and a.ts >= b.ts")(lambda e: joins.asof(e.where("event_type = 'click'").select("user_id", "ts", "event_id"), e.where("event_type = 'view'").select("user_id", "ts", "value"), "user_id", "ts", ["value"]).select("event_id", "value"))
query("join_interval_events", "events", "select a.event_id as first_id, b.event_id as second_id from events a join events b on a.user_id = b.user_id and epoch_us(b.ts) between epoch_us(a.ts) and epoch_us(a.ts) + 3600000000")(lambda e: joins.within(e.select("user_id", F.col("event_id").alias("first_id"), F.unix_micros(F.col("ts").cast("timestamp")).alias("at")), e.select("user_id", F.col("event_id").alias("second_id"), F.unix_micros(F.col("ts").cast("timestamp")).alias("then")), "user_id", "at", "then", 3_600_000_000).select("first_id", "second_id"))
query("join_skewed_salted", "lineitem part", "select l_orderkey, l_linenumber, p_brand from lineitem join part on l_partkey = p_partkey")(lambda li, p: joins.salted(li.select(F.col("l_partkey").alias("k"), "l_orderkey", "l_linenumber"), p.select(F.col("p_partkey").alias("k"), "p_brand"), "k").select("l_orderkey", "l_linenumber", "p_brand"))
query("lateral_top_per_key", "orders", "select o_custkey, o_orderkey from orders qualify row_number() over (partition by o_custkey order by o_totalprice desc, o_orderkey) = 1")(lambda o: o.withColumn("r", F.row_number().over(W.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey"))).where("r = 1").select("o_custkey", "o_orderkey"))

# Aggregates
query("agg_distinct_keys", "documents", "select count(*) as n, count(distinct text) as texts from documents")(lambda d: d.agg(F.count("*").alias("n"), F.countDistinct("text").alias("texts")))
query("agg_approx_distinct", "events")(lambda e: e.agg(F.approx_count_distinct("user_id").alias("users")))
query("agg_rollup_digits", "events", "select substr(h, 1, 1) as d1, substr(h, 2, 1) as d2, count(*) as n from (select md5(cast(event_id as varchar)) as h from events) group by rollup (substr(h, 1, 1), substr(h, 2, 1))")(lambda e: e.select(F.md5(F.col("event_id").cast("string")).alias("h")).rollup(F.substring("h", 1, 1).alias("d1"), F.substring("h", 2, 1).alias("d2")).agg(F.count("*").alias("n")))
query("agg_cube_flags", "lineitem", "select l_returnflag, l_linestatus, count(*) as n, cast(sum(cast(l_quantity as bigint)) as bigint) as quantity from lineitem group by cube (l_returnflag, l_linestatus)")(lambda li: li.cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.sum(F.col("l_quantity").cast("long")).alias("quantity")))
query("agg_grouping_sets", "orders", "select o_orderstatus, o_orderpriority, count(*) as n from orders group by grouping sets ((o_orderstatus), (o_orderpriority))")(lambda o: o.groupingSets([["o_orderstatus"], ["o_orderpriority"]], "o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n")).select("o_orderstatus", "o_orderpriority", "n"))
query("agg_cutpoints_exact", "events", "select event_id from events qualify row_number() over (order by event_id) % 1000 = 0")(lambda e: e.withColumn("cell", F.floor(F.col("event_id") / 1000)).withColumn("r", F.row_number().over(W.partitionBy("cell").orderBy("event_id"))).join(F.broadcast(e.groupBy(F.floor(F.col("event_id") / 1000).alias("cell")).agg(F.count("*").alias("c")).withColumn("before", F.coalesce(F.sum("c").over(W.orderBy("cell").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)))), "cell").where((F.col("before") + F.col("r")) % 1000 == 0).select("event_id"))
query("agg_cutpoints_approx", "events")(lambda e: e.agg(F.percentile_approx("event_id", [0.25, 0.5, 0.75], 10000).alias("cuts")))
query("agg_min_max_by", "orders", "select min_by(o_orderkey, o_totalprice) as cheapest, max_by(o_orderkey, o_totalprice) as dearest from orders")(lambda o: o.agg(F.min_by("o_orderkey", "o_totalprice").alias("cheapest"), F.max_by("o_orderkey", "o_totalprice").alias("dearest")))
query("agg_bucket_borders", "orders", "select substr(h, 1, 1) as bucket, min(h) as low, max(h) as high from (select md5(cast(o_orderkey as varchar)) as h from orders) group by 1")(lambda o: o.select(F.md5(F.col("o_orderkey").cast("string")).alias("h")).groupBy(F.substring("h", 1, 1).alias("bucket")).agg(F.min("h").alias("low"), F.max("h").alias("high")))
query("agg_collect_sorted", "orders", "select o_custkey, string_agg(cast(o_orderkey as varchar), ',' order by o_orderkey) as run from orders group by o_custkey")(lambda o: o.groupBy("o_custkey").agg(F.array_join(F.array_sort(F.collect_list("o_orderkey")).cast("array<string>"), ",").alias("run")))
query("agg_checksum", "lineitem", "select cast(sum(cast('0x' || substr(md5(cast(l_partkey as varchar)), 1, 7) as bigint)) as bigint) as checksum from lineitem")(lambda li: li.agg(F.sum(F.conv(F.substring(F.md5(F.col("l_partkey").cast("string")), 1, 7), 16, 10).cast("long")).alias("checksum")))
query("agg_pivot_digit", "events", "select event_type, count(*) filter (where event_id % 3 = 0) as d0, count(*) filter (where event_id % 3 = 1) as d1, count(*) filter (where event_id % 3 = 2) as d2 from events group by event_type")(lambda e: e.withColumn("d", F.concat(F.lit("d"), F.col("event_id") % 3)).groupBy("event_type").pivot("d", ["d0", "d1", "d2"]).count())
query("agg_bucket_stats", "lineitem", "select max(n) as most, min(n) as least, count(*) as buckets, round(stddev_pop(n), 6) as spread from (select cast(l_quantity as bigint) as q, count(*) as n from lineitem group by 1)")(lambda li: li.groupBy(F.col("l_quantity").cast("long").alias("q")).agg(F.count("*").alias("n")).agg(F.max("n").alias("most"), F.min("n").alias("least"), F.count("*").alias("buckets"), F.round(F.stddev_pop("n"), 6).alias("spread")))
query("agg_having_heavy", "lineitem", "select l_suppkey, count(*) as n from lineitem group by l_suppkey having count(*) > 600")(lambda li: li.groupBy("l_suppkey").agg(F.count("*").alias("n")).where("n > 600"))
query("agg_filter_clause", "orders", "select count(*) filter (where o_totalprice > 100000) as big, count(*) filter (where o_orderstatus = 'F') as f from orders")(lambda o: o.agg(F.count_if(F.col("o_totalprice") > 100000).alias("big"), F.count_if(F.col("o_orderstatus") == "F").alias("f")))

# Windows
def _by_flag():
    return W.partitionBy("o_orderstatus").orderBy("o_totalprice", "o_orderkey")


query("win_rank_dense_ntile", "orders", "select o_orderkey, rank() over w as r, dense_rank() over w as d, ntile(4) over w as q from orders window w as (partition by o_orderstatus order by o_totalprice, o_orderkey)")(lambda o: o.select("o_orderkey", F.rank().over(_by_flag()).cast("long").alias("r"), F.dense_rank().over(_by_flag()).cast("long").alias("d"), F.ntile(4).over(_by_flag()).cast("long").alias("q")))
query("win_percent_cume", "orders", "select o_orderkey, round(percent_rank() over w, 9) as p, round(cume_dist() over w, 9) as c from orders window w as (partition by o_orderstatus order by o_totalprice, o_orderkey)")(lambda o: o.select("o_orderkey", F.round(F.percent_rank().over(_by_flag()), 9).alias("p"), F.round(F.cume_dist().over(_by_flag()), 9).alias("c")))
query("win_lag_lead_check", "events", "select event_id, lag(event_id) over w as before, lead(event_id) over w as after from events window w as (partition by user_id order by ts, event_id)")(lambda e: e.select("event_id", F.lag("event_id").over(w := W.partitionBy("user_id").orderBy("ts", "event_id")).alias("before"), F.lead("event_id").over(w).alias("after")))
query("win_rows_frame", "events", "select event_id, round(sum(value) over (partition by user_id order by ts, event_id rows between 2 preceding and current row), 6) as s from events")(lambda e: e.select("event_id", F.round(F.sum("value").over(W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-2, 0)), 6).alias("s")))
query("win_range_frame_numeric", "orders", "select o_orderkey, count(*) over (partition by o_custkey order by o_totalprice range between 10000 preceding and current row) as n from orders")(lambda o: o.select("o_orderkey", F.count("*").over(W.partitionBy("o_custkey").orderBy("o_totalprice").rangeBetween(-10000, 0)).alias("n")))
query("win_range_frame_time", "events", "select event_id, count(*) over (partition by user_id order by epoch_us(ts) range between 3600000000 preceding and current row) as n from events")(lambda e: e.select("event_id", F.count("*").over(W.partitionBy("user_id").orderBy(F.unix_micros(F.col("ts").cast("timestamp"))).rangeBetween(-3600000000, 0)).alias("n")))
query("win_first_last_nth", "orders", "select o_orderkey, first_value(o_orderkey) over w as f, last_value(o_orderkey) over w as l, nth_value(o_orderkey, 2) over w as n from orders window w as (partition by o_custkey order by o_orderdate, o_orderkey rows between unbounded preceding and unbounded following)")(lambda o: o.select("o_orderkey", F.first("o_orderkey").over(w := W.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey").rowsBetween(W.unboundedPreceding, W.unboundedFollowing)).alias("f"), F.last("o_orderkey").over(w).alias("l"), F.nth_value("o_orderkey", 2).over(w).alias("n")))
query("win_topk_per_group", "lineitem", "select l_suppkey, l_orderkey, l_linenumber, l_partkey from lineitem qualify row_number() over (partition by l_suppkey order by l_extendedprice desc, l_orderkey, l_linenumber) <= 3")(lambda li: li.withColumn("r", F.row_number().over(W.partitionBy("l_suppkey").orderBy(F.desc("l_extendedprice"), "l_orderkey", "l_linenumber"))).where("r <= 3").select("l_suppkey", "l_orderkey", "l_linenumber", "l_partkey"))
query("win_sessionize", "events", "select event_id, cast(sum(case when gap is null or gap > 1800000000 then 1 else 0 end) over (partition by user_id order by ts, event_id) as bigint) as session from (select *, epoch_us(ts) - lag(epoch_us(ts)) over (partition by user_id order by ts, event_id) as gap from events)")(lambda e: e.withColumn("at", F.unix_micros(F.col("ts").cast("timestamp"))).withColumn("gap", F.col("at") - F.lag("at").over(w := W.partitionBy("user_id").orderBy("ts", "event_id"))).select("event_id", F.sum(F.when(F.col("gap").isNull() | (F.col("gap") > 1800000000), 1).otherwise(0)).over(w).cast("long").alias("session")))

# Order, limit, sets
@query("order_nulls_first_last", "documents labels", "select doc_id, row_number() over (order by quality nulls last, doc_id) as r from documents left join labels using (doc_id)")
def _nulls_last(docs, labels):
    """Positions of all rows; without labels they stand last."""
    rows = docs.join(labels, "doc_id", "left").select("doc_id", "quality")
    return baselines.spark_sort(rows, F.asc_nulls_last("quality"), F.asc("doc_id")).select("doc_id", F.col("position").alias("r"))


query("topk_global", "orders", "select o_orderkey from orders order by o_totalprice desc, o_orderkey limit 20")(lambda o: o.orderBy(F.desc("o_totalprice"), "o_orderkey").limit(20).select("o_orderkey"))
query("bottomk_global", "orders", "select o_orderkey from orders order by o_totalprice, o_orderkey limit 20")(lambda o: o.orderBy("o_totalprice", "o_orderkey").limit(20).select("o_orderkey"))
query("limit_offset", "orders", "select o_orderkey from orders order by o_orderkey limit 10 offset 30")(lambda o: o.orderBy("o_orderkey").offset(30).limit(10).select("o_orderkey"))
query("distinct_by_sort", "events", "select distinct user_id from events")(lambda e: e.select("user_id").repartition("user_id").sortWithinPartitions("user_id").withColumn("before", F.lag("user_id").over(W.partitionBy("user_id").orderBy("user_id"))).where("before is null").select("user_id"))
query("sort_within_partitions", "lineitem", "select l_orderkey, l_linenumber from lineitem")(lambda li: li.repartition(8, "l_orderkey").sortWithinPartitions("l_orderkey").select("l_orderkey", "l_linenumber"))
query("union_all_runs", "lineitem", "select l_orderkey, l_linenumber from lineitem")(lambda li: li.where("l_orderkey % 2 = 0").select("l_orderkey", "l_linenumber").unionByName(li.where("l_orderkey % 2 = 1").select("l_linenumber", "l_orderkey")))
query("union_distinct_keys", "customer supplier", "select c_nationkey as k from customer union select s_nationkey from supplier")(lambda c, s: c.select(F.col("c_nationkey").alias("k")).union(s.select("s_nationkey")).distinct())
query("intersect_keys", "documents labels", "select doc_id from documents intersect select doc_id from labels")(lambda d, lab: d.select("doc_id").intersect(lab.select("doc_id")))
query("intersect_all_keys", "orders lineitem", "select o_orderkey as k from orders intersect all select l_orderkey from lineitem")(lambda o, li: o.select(F.col("o_orderkey").alias("k")).intersectAll(li.select("l_orderkey")))
query("except_keys", "documents labels", "select doc_id from documents except select doc_id from labels")(lambda d, lab: d.select("doc_id").subtract(lab.select("doc_id")))
query("except_all_permutation", "lineitem orders", "select l_orderkey as k from lineitem except all select o_orderkey from orders")(lambda li, o: li.select(F.col("l_orderkey").alias("k")).exceptAll(o.select("o_orderkey")))
query("union_by_name_missing", "part supplier", "select p_partkey as k, p_size, null as s_nationkey from part union all select s_suppkey, null, s_nationkey from supplier")(lambda p, s: p.select(F.col("p_partkey").alias("k"), "p_size").unionByName(s.select(F.col("s_suppkey").alias("k"), "s_nationkey"), allowMissingColumns=True))

# Functions
query("fn_string_key", "part", "select p_partkey, upper(substr(p_name, 1, 5)) as a, lpad(p_brand, 12, '*') as b, reverse(p_type) as c, length(p_name) as d from part")(lambda p: p.select("p_partkey", F.upper(F.substring("p_name", 1, 5)).alias("a"), F.lpad("p_brand", 12, "*").alias("b"), F.reverse("p_type").alias("c"), F.length("p_name").cast("long").alias("d")))
query("fn_string_split_regex", "pages", "select page_id, split_part(url, '/', 3) as host, regexp_extract(url, '^([a-z]+):', 1) as scheme from pages")(lambda p: p.select("page_id", F.split_part("url", F.lit("/"), F.lit(3)).alias("host"), F.regexp_extract("url", "^([a-z]+):", 1).alias("scheme")))
query("fn_hash_key", "lineitem", "select l_orderkey, l_linenumber, md5(cast(l_partkey as varchar)) as m, sha256(cast(l_suppkey as varchar)) as s from lineitem")(lambda li: li.select("l_orderkey", "l_linenumber", F.md5(F.col("l_partkey").cast("string")).alias("m"), F.sha2(F.col("l_suppkey").cast("string"), 256).alias("s")))
query("fn_date_key", "orders", "select o_orderkey, epoch_us(o_orderdate) as us, year(o_orderdate) as y, month(o_orderdate) as m from orders")(lambda o: o.select("o_orderkey", F.unix_micros(F.col("o_orderdate").cast("timestamp")).alias("us"), F.year("o_orderdate").cast("long").alias("y"), F.month("o_orderdate").cast("long").alias("m")))
query("fn_math_digit", "events", "select event_id, event_id >> 4 as a, event_id & 15 as b, xor(event_id, 255) as c, cast(bit_count(event_id) as int) as d from events")(lambda e: e.select("event_id", F.shiftright("event_id", 4).alias("a"), F.col("event_id").bitwiseAND(15).alias("b"), F.col("event_id").bitwiseXOR(F.lit(255)).alias("c"), F.bit_count("event_id").alias("d")))
query("fn_array_digits", "embeddings", "select vec_id, len(list_filter(embedding, lambda x: x > 0)) as positive, embedding[1] as first from embeddings")(lambda v: v.select("vec_id", F.size(F.filter("embedding", lambda x: x > 0)).cast("long").alias("positive"), F.element_at("embedding", 1).alias("first")))
query("fn_map_histogram", "events", "select user_id, string_agg(event_type || ':' || n, ',' order by event_type) as h from (select user_id, event_type, count(*) as n from events group by all) group by user_id")(lambda e: e.groupBy("user_id", "event_type").count().groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "count"))).alias("m")).select("user_id", F.array_join(F.transform(F.array_sort(F.map_keys("m")), lambda k: F.concat(k, F.lit(":"), F.col("m")[k].cast("string"))), ",").alias("h")))
query("fn_json_key", "events", "select event_id, cast(json_extract(props, '$.k') as bigint) as k from events")(lambda e: e.select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k")))
query("fn_decimal_key", "customer", "select c_custkey, cast(c_acctbal as decimal(12, 2)) as d from customer")(lambda c: c.select("c_custkey", F.col("c_acctbal").cast("decimal(12,2)").alias("d")))
query("fn_struct_key", "orders", "select o_orderstatus, min(o_orderkey) as k from orders where (o_orderstatus, o_totalprice) in (select (o_orderstatus, min(o_totalprice)) from orders group by o_orderstatus) group by o_orderstatus")(lambda o: o.groupBy("o_orderstatus").agg(F.min(F.struct("o_totalprice", "o_orderkey")).alias("s")).select("o_orderstatus", F.col("s.o_orderkey").alias("k")))
query("record_layout", "orders", "select hex(k) as k, length(v) as n, v from (select unhex(substr(upper(md5(cast(o_orderkey as varchar))), 1, 20)) as k, rpad(concat_ws('|', o_orderkey, o_orderstatus), 90, ' ') as v from orders)")(lambda o: R.records(o, K.uniform_binary("o_orderkey"), ["o_orderkey", "o_orderstatus"]).select(F.hex("key").alias("k"), F.length("value").cast("long").alias("n"), F.col("value").cast("string").alias("v")))
