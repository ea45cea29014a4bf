"""Registered queries: nulls, types and formats under the sorts, merges, definitions by window, functions of keys, streams."""

from __future__ import annotations

import functools

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from . import measures
from .functions import keys as K
from .functions import udfs
from .operators import engine, external, joins, msd
from .plans import cuts as C
from .plans import tree as P
from .queries_sort import LI, _tree_sql, limits, load, order_sql, pairs_sql
from .sources import formats, sinks
from .sources import records as R
from .sources.tables import kept, scratch, table
from .streaming import events as E
from .streaming import runs as S

QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


# Keys and pointers that are null, wide or of other types


@query("msd_sort_null_keys", "select row_number() over (order by k nulls first, p nulls first, doc_id) as position, k, p, doc_id from (select case when quality = 1 then null else lpad(hex(quality), 16, '0') end as k, toxic as p, doc_id from documents left join labels using (doc_id))")
def _null_keys(spark, sf_dir):
    docs = table(spark, sf_dir, "documents").select("doc_id").join(table(spark, sf_dir, "labels"), "doc_id", "left")
    df = docs.select(F.when(F.col("quality") == 1, F.lit(None)).otherwise(K.unsigned(F.col("quality"))).alias("k"), F.col("toxic").alias("p"), "doc_id")
    return msd.adaptive_sort(df, "k", ["p", "doc_id"], 8, **limits(df))


@query("external_sort_null_keys", SQL["msd_sort_null_keys"])
def _external_null_keys(spark, sf_dir):
    docs = table(spark, sf_dir, "documents").select("doc_id").join(table(spark, sf_dir, "labels"), "doc_id", "left")
    df = docs.select(F.when(F.col("quality") == 1, F.lit(None)).otherwise(K.unsigned(F.col("quality"))).alias("k"), F.col("toxic").alias("p"), "doc_id")
    return external.external_sort(df, "k", ["p", "doc_id"], 8, **limits(df))


@query("msd_sort_decimal", "select row_number() over (order by d, c_custkey) as position, c_custkey, cast(d as varchar) as d from (select c_custkey, cast(cast(c_acctbal as decimal(12, 2)) * 1000000000000000000 as decimal(38, 2)) as d from customer)")
def _decimal(spark, sf_dir):
    d = (F.col("c_acctbal").cast("decimal(12,2)").cast("decimal(32,2)") * F.lit(10**18).cast("decimal(19,0)")).cast("decimal(38,2)")
    df = table(spark, sf_dir, "customer").select("c_custkey", d.alias("d"))
    df = df.withColumn("k", K.normalize(F.col("d"), df.schema["d"].dataType))
    out = msd.adaptive_sort(df, "k", ["c_custkey"], 20, **limits(df))
    return out.select("position", "c_custkey", F.col("d").cast("string").alias("d"))


@query("msd_sort_url_full", "select row_number() over (order by k, url, page_id) as position, page_id from (select rpad(substr(hex(encode(url)), 1, 20), 20, '0') as k, url, page_id from pages)")
def _url_full(spark, sf_dir):
    df = table(spark, sf_dir, "pages").select(K.text(F.col("url")).alias("k"), "url", "page_id")
    return msd.adaptive_sort(df, "k", ["page_id"], full_key="url", **limits(df)).select("position", "page_id")


@query("msd_sort_vector", "select row_number() over (order by embedding, vec_id) as position, vec_id from embeddings")
def _vector(spark, sf_dir):
    df = table(spark, sf_dir, "embeddings").select(K.floats(F.col("embedding"), 64).alias("k"), "vec_id")
    return msd.adaptive_sort(df, "k", ["vec_id"], 512, **limits(df)).select("position", "vec_id")


for _name, _kernel in (("lsd_sort_uniform", "lsd"), ("radix_inplace", "inplace")):

    @query(_name, order_sql("uniform"))
    def _kernel_sort(spark, sf_dir, kernel=_kernel):
        df, ptr, width = load(spark, sf_dir, "uniform")
        return msd.adaptive_sort(df, "k", ptr, width, kernel=kernel, **limits(df))


@query("merge_ranges", f"select cast(count(*) as bigint) as rows, 1 as first_position, true as gapless from ({pairs_sql('skewed')})")
def _merge_ranges(spark, sf_dir):
    """The ranges that the external sort merges: their starts follow each other without gaps."""
    df, ptr, width = load(spark, sf_dir, "skewed")
    ranges = msd.Ranges(df, "k", width, ptr, **limits(df)).cuts.ranges
    gapless = all(a + n == b for (_, a, n), (_, b, _) in zip(ranges, ranges[1:], strict=False))
    return spark.createDataFrame([(sum(n for _, _, n in ranges), ranges[0][1] + 1, gapless)], "rows long, first_position int, gapless boolean")


@query("key_pointer_lineitem", pairs_sql("uniform"))
def _key_pointer(spark, sf_dir):
    return K.key_pointer(table(spark, sf_dir, "lineitem"), K.uniform_binary(*LI[:4]), LI)


@query("fn_double_key", "select event_id, value between 10 and 50 as inside, value < 0 as below from events")
def _double_key(spark, sf_dir):
    k = K.double("value")
    edge = {n: K.double(F.lit(float(n))) for n in (0, 10, 50)}
    return table(spark, sf_dir, "events").select("event_id", k.between(edge[10], edge[50]).alias("inside"), (k < edge[0]).alias("below"))


@query("fn_collation", "select lower(p_brand) as brand, 2 * count(*) as n from part group by 1")
def _collation(spark, sf_dir):
    part = table(spark, sf_dir, "part")
    both = part.select(F.upper("p_brand").alias("b")).unionByName(part.select(F.lower("p_brand").alias("b")))
    return both.groupBy(F.collate("b", "UTF8_LCASE").alias("c")).agg(F.count("*").alias("n")).select(F.collate(F.lower("c"), "UTF8_BINARY").alias("brand"), "n")


# Merging


@query("external_sort_compacted", order_sql("skewed"))
def _compacted(spark, sf_dir):
    df, ptr, width = load(spark, sf_dir, "skewed")
    return external.external_sort(df, "k", ptr, width, **limits(df), run_rows=max(1000, df.count() // 20), most=4)


@query("external_sort_pipeline", order_sql("skewed"))
def _pipeline(spark, sf_dir):
    df, ptr, width = load(spark, sf_dir, "skewed")
    runs = external.make_runs(df, "k", ptr, width, **limits(df))
    return external.run_pipeline(runs, scratch(spark, "ranges"), order="size_desc")


@query("merge_sorted_union", "select row_number() over (order by ts, event_id) as position, event_id, event_type from events")
def _merge_sorted(spark, sf_dir):
    events = table(spark, sf_dir, "events").select(K.timestamp(F.col("ts")).alias("k"), "event_id", "event_type")
    kinds = [r[0] for r in events.select("event_type").distinct().orderBy("event_type").collect()]  # the few types are the inputs
    return external.merge_sorted([events.where(F.col("event_type") == t) for t in kinds], "k", ["event_id"], 8, **limits(events)).drop("k")


@query("join_range_bucket", f"select l_orderkey, l_linenumber, l_partkey, prefix, n from ({pairs_sql('skewed')}) p join ({_tree_sql('skewed', 10, 200)}) t on substr(p.k, 1, 2 * t.depth) = t.prefix")
def _range_bucket(spark, sf_dir):
    df = load(spark, sf_dir, "skewed")[0]
    tree = P.leaves(df, F.col("k"), 10, 200, skip_common=False)
    return P.assign(df, "k", tree, ["prefix", "n"]).select("l_orderkey", "l_linenumber", "l_partkey", "prefix", "n")


# Costs and checks


def _routes_sql(workload: str, width: int, split: int, compare: int) -> str:
    """Every node that the adaptive sort meets, level by level."""
    parts = [f"k as (select substr(k, 1, {2 * width}) as k from ({pairs_sql(workload)}))", "l0 as (select '' as prefix, 0 as depth, count(*) as n, 'cooperative' as route from k)"]
    for d in range(1, width + 1):
        last = "finished" if d == width else None
        route = f"'{last}'" if last else f"case when n <= 1 then 'finished' when n > {split} then 'cooperative' when n < {compare} and task then 'comparison' else 'sequential' end"
        parts.append(f"l{d} as (select prefix, {d} as depth, n, {route} as route from (select substr(k, 1, {2 * d}) as prefix, count(*) as n, bool_or(p.route = 'sequential') as task from k join l{d - 1} p on substr(k, 1, {2 * (d - 1)}) = p.prefix where p.route in ('cooperative', 'sequential') group by 1))")
    return f"with {', '.join(parts)} " + " union all ".join(f"select * from l{d}" for d in range(width + 1))


SQL["cost_by_route"] = f"select route, count(*) as buckets, cast(sum(n) as bigint) as records, cast(sum(case when route in ('cooperative', 'sequential') then n else 0 end) as bigint) as radix_moves, cast(sum(case when route = 'comparison' then n * ceil(log2(n)) else 0 end) as bigint) as compare_cost from ({_routes_sql('events', 4, 2000, 64)}) group by route"
_RANGES = f"with t as ({_tree_sql('skewed', 10, 200)}), s as (select n, cast(sum(n) over (order by prefix) - n as bigint) as start from t), r as (select floor(start / 5000) as cell, cast(sum(n) as bigint) as rows from s group by 1)"


@query("case_route", f"select prefix, n, case when n > 2000 then 'cooperative' when n < 64 then 'comparison' else 'sequential' end as route from (select substr(k, 1, 2) as prefix, count(*) as n from ({pairs_sql('skewed')}) group by 1)")
def _case_route(spark, sf_dir):
    found = P.digit_histogram(load(spark, sf_dir, "skewed")[0], F.col("k"), 1)
    return found.select("prefix", "n", F.when(F.col("n") > 2000, "cooperative").when(F.col("n") < 64, "comparison").otherwise("sequential").alias("route"))


@query("range_imbalance", f"{_RANGES} select round(max(rows) / avg(rows), 9) as imbalance, count(*) as ranges from r")
def _imbalance(spark, sf_dir):
    tree = P.pack_ranges(P.leaves(load(spark, sf_dir, "skewed")[0], F.col("k"), 10, 200, skip_common=False), 5000)
    ranges = tree.groupBy("range_id").agg(F.sum("n").alias("n"))
    return ranges.agg(F.round(F.max("n") / F.avg("n"), 9).alias("imbalance"), F.count("*").alias("ranges"))


@query("range_rows", f"select cast(count(*) as bigint) as rows, true as balanced from ({pairs_sql('skewed')})")
def _range_rows(spark, sf_dir):
    df, ptr, width = load(spark, sf_dir, "skewed")
    size = limits(df)
    digits, name, more, _ = msd.with_digits(df, "k", width, ptr)
    found = C.cut(digits, F.col(name), more, **size)
    rows = [n for _, _, n in found.ranges]
    return spark.createDataFrame([(sum(rows), max(rows) <= 2 * size["target_rows"])], "rows long, balanced boolean")


@query("agg_is_sorted", "select true as is_sorted, count(*) as n from events")
def _is_sorted(spark, sf_dir):
    df, ptr, width = load(spark, sf_dir, "events")
    return measures.is_sorted(kept(msd.adaptive_sort(df, "k", ptr, width, **limits(df))), "k")


@query("range_borders", f"select cast(floor((position - 1) / 1000) as int) as part, min(k) as low, max(k) as high, true as apart from ({order_sql('events')}) group by 1")
def _borders(spark, sf_dir):
    df, ptr, width = load(spark, sf_dir, "events")
    return measures.borders(kept(msd.adaptive_sort(df, "k", ptr, width, **limits(df))), "k", 1000)


@query("bytes_moved", f"select count(*) as n, cast(sum(length(k)) // 2 as bigint) as key_bytes, cast(sum(length(record)) as bigint) as record_bytes from (select k, concat_ws('|', k, l_orderkey, l_linenumber, l_partkey, l_suppkey, l_returnflag, l_linestatus) as record from ({pairs_sql('uniform').replace(', l_extendedprice', ', l_extendedprice, l_returnflag, l_linestatus')}))")
def _bytes_moved(spark, sf_dir):
    li = table(spark, sf_dir, "lineitem").withColumn("k", K.uniform_binary(*LI[:4]))
    record = F.concat_ws("|", "k", *[F.col(c).cast("string") for c in ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")], "l_returnflag", "l_linestatus")
    return li.agg(F.count("*").alias("n"), (F.sum(F.length("k")) / 2).cast("long").alias("key_bytes"), F.sum(F.length(record)).alias("record_bytes"))


# Definitions by window and by sorting


@query("win_row_number_position", order_sql("uniform"))
def _row_numbers(spark, sf_dir):
    df, ptr, _ = load(spark, sf_dir, "uniform")
    starts = P.offsets(P.digit_histogram(df, F.col("k"), 1)).select("prefix", "start")
    rank = F.row_number().over(W.partitionBy("prefix").orderBy("k", *ptr))
    out = df.withColumn("prefix", K.prefix(F.col("k"), 1)).join(F.broadcast(starts), "prefix")  # 256 rows
    return out.select((F.col("start") + rank).cast("long").alias("position"), "k", *ptr)


@query("win_exclusive_prefix_sum", f"select prefix, n, cast(coalesce(sum(n) over (order by prefix rows between unbounded preceding and 1 preceding), 0) as bigint) as start from (select substr(k, 1, 4) as prefix, count(*) as n from ({pairs_sql('uniform')}) group by 1)")
def _prefix_sum(spark, sf_dir):
    return P.offsets(P.digit_histogram(load(spark, sf_dir, "uniform")[0], F.col("k"), 2))


@query("win_tie_groups", "select doc_id, count(*) over (partition by rpad(substr(hex(encode(text)), 1, 20), 20, '0')) as ties from documents")
def _tie_groups(spark, sf_dir):
    return table(spark, sf_dir, "documents").select("doc_id", F.count("*").over(W.partitionBy(K.text(F.col("text")))).alias("ties"))


@query("win_leaf_depth", _tree_sql("skewed", 10, 200))
def _leaf_depth(spark, sf_dir):
    found = P.leaf_depths(load(spark, sf_dir, "skewed")[0].select("k"), "k", 10, 200)
    return found.groupBy(F.substring("k", F.lit(1), 2 * F.col("depth")).alias("prefix"), "depth").agg(F.count("*").alias("n"))


@query("agg_sort_based", "select l_suppkey, max(l_returnflag || l_linestatus) as flags, count(*) as n from lineitem group by l_suppkey")
def _sort_based(spark, sf_dir):
    """The greatest text has no fixed width, so Spark groups by sorting."""
    li = table(spark, sf_dir, "lineitem").select("l_suppkey", F.concat("l_returnflag", "l_linestatus").alias("f"))
    return li.groupBy("l_suppkey").agg(F.max("f").alias("flags"), F.count("*").alias("n"))


@query("sorted_partitions", "select count(*) as n, true as ordered from lineitem")
def _sorted_partitions(spark, sf_dir):
    li = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber").repartition(8, "l_orderkey").sortWithinPartitions("l_orderkey")
    place = li.select(F.spark_partition_id().alias("part"), F.monotonically_increasing_id().alias("at"), "l_orderkey")
    before = F.lag("l_orderkey").over(W.partitionBy("part").orderBy("at"))
    return place.withColumn("before", before).agg(F.count("*").alias("n"), F.bool_and(F.coalesce(F.col("before") <= F.col("l_orderkey"), F.lit(True))).alias("ordered"))


@query("approx_within_tolerance", "select true as distinct_close, true as cuts_close, count(*) as n from events")
def _approx(spark, sf_dir):
    """The estimates beside the exact values: distinct users within 15 %, quartiles within 1 % of the ranks."""
    events = table(spark, sf_dir, "events")
    r = events.agg(F.approx_count_distinct("user_id").alias("near"), F.countDistinct("user_id").alias("exact"), F.percentile_approx("event_id", [0.25, 0.5, 0.75], 10_000).alias("cuts"), F.count("*").alias("n"))
    below = events.crossJoin(F.broadcast(r)).agg(*[F.sum((F.col("event_id") <= F.col("cuts")[i]).cast("long")).alias(f"r{i}") for i in range(3)])  # r is one row
    off = [F.abs(F.col(f"r{i}") / F.col("n") - (i + 1) / 4) <= 0.01 for i in range(3)]
    return r.crossJoin(below).select((F.abs(F.col("near") / F.col("exact") - 1) <= 0.15).alias("distinct_close"), (off[0] & off[1] & off[2]).alias("cuts_close"), "n")


# Formats, files and sinks

for _kind in ("csv", "json", "orc", "text"):

    @query(f"roundtrip_{_kind}", "select * from nation")
    def _roundtrip(spark, sf_dir, kind=_kind):
        return formats.roundtrip(table(spark, sf_dir, "nation"), kind)


def _written_records(spark, sf_dir):
    R.register(spark)
    made = R.records(table(spark, sf_dir, "orders"), K.uniform_binary("o_orderkey"), ["o_orderkey", "o_orderstatus"])
    path = scratch(spark, "records")
    made.write.format("fixed_records").mode("append").option("path", path).save()
    return path


_RECORDS = "select upper(substr(md5(cast(o_orderkey as varchar)), 1, 20)) as k from orders"


@query("binary_records", _RECORDS)
def _binary_records(spark, sf_dir):
    return formats.binary_records(spark, _written_records(spark, sf_dir), 100).select(F.hex(F.substring("record", 1, 10)).alias("k"))


@query("whole_files", "select 100 * count(*) as bytes from orders")
def _whole_files(spark, sf_dir):
    return formats.whole_files(spark, _written_records(spark, sf_dir)).agg(F.sum("length").alias("bytes"))


@query("sorted_sink", f"select cast(floor((position - 1) / 1000) as int) as part, count(*) as rows, min(k) as low, max(k) as high, cast(sum(cast('0x' || substr(md5(k), 1, 7) as bigint)) as bigint) as checksum from ({order_sql('events')}) group by 1")
def _sorted_sink(spark, sf_dir):
    df, ptr, width = load(spark, sf_dir, "events")
    return sinks.write_sorted(msd.adaptive_sort(df, "k", ptr, width, **limits(df)), scratch(spark, "sorted"), "k", 1000)


@query("sorted_sink_cached", SQL["sorted_sink"])
def _sorted_sink_cached(spark, sf_dir):
    df, ptr, width = load(spark, sf_dir, "events")
    return sinks.write_sorted(msd.adaptive_sort(df, "k", ptr, width, **limits(df)), scratch(spark, "sorted"), "k", 1000, durability="cached")


@query("bucketed_join", "select o_orderkey, l_linenumber, l_partkey from orders join lineitem on o_orderkey = l_orderkey")
def _bucketed(spark, sf_dir):
    a = sinks.write_bucketed(table(spark, sf_dir, "orders").select("o_orderkey"), 8, "o_orderkey")
    b = sinks.write_bucketed(table(spark, sf_dir, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey"), 8, "l_orderkey")
    return a.hint("merge").join(b, a["o_orderkey"] == b["l_orderkey"]).select("o_orderkey", "l_linenumber", "l_partkey")


@query("file_pointers", "select count(*) as n, count(*) as pointers from orders")
def _file_pointers(spark, sf_dir):
    found = sinks.with_pointer(table(spark, sf_dir, "orders"))
    return found.agg(F.count("*").alias("n"), F.countDistinct("file", "row").alias("pointers"))


@query("mode_of_workloads", "select * from (values ('W1', 'internal'), ('W2', 'partial'), ('W3', 'external')) t(workload, mode)")
def _mode_of_workloads(spark, sf_dir):
    """The budgets of three, one and a half, and half of each input, whose size is measured."""
    sizes = [
        engine.measured_bytes(table(spark, sf_dir, tab)).select(F.lit(name).alias("workload"), "bytes", (F.col("bytes") * factor).cast("long").alias("budget"))
        for name, tab, factor in (("W1", "events", 3.0), ("W2", "orders", 1.5), ("W3", "lineitem", 0.5))
    ]
    mode = F.udf(engine.choose_mode, "string", useArrow=True)("bytes", "budget")
    return functools.reduce(DataFrame.unionByName, sizes).select("workload", mode.alias("mode"))


# Functions of keys


@query("udf_digit_counts", f"select event_type, prefix, n, cast(sum(n) over (partition by event_type order by prefix) - n as bigint) as start from (select event_type, substr(upper(md5(cast(event_id as varchar))), 1, 2) as prefix, count(*) as n from events group by all)")
def _digit_counts(spark, sf_dir):
    udfs.register(spark)
    events = table(spark, sf_dir, "events").select("event_type", K.digit(K.uniform_binary("event_id"), 0).alias("d"))
    counts = events.groupBy("event_type").agg(udfs.digit_counts("d").alias("counts"))
    return counts.lateralJoin(udfs.BucketChildren(F.lit(""), F.col("counts").outer())).select("event_type", "prefix", "n", "start")


@query("sql_functions", "select event_id, lpad(hex(event_id), 16, '0') as k, substr(lpad(hex(event_id), 16, '0'), 15, 2) as last_digit, rpad(substr(hex(encode(event_type)), 1, 8), 8, '0') as t from events")
def _sql_functions(spark, sf_dir):
    udfs.register(spark)
    return table(spark, sf_dir, "events").select("event_id", F.expr("unsigned_key(event_id)").alias("k"), F.expr("key_digit(unsigned_key(event_id), 7)").alias("last_digit"), F.expr("text_key(event_type, 4)").alias("t"))


# Streams

query("stream_ordered", "select hour, row_number() over (partition by hour order by ts, event_id) as place, event_id from (select date_trunc('hour', ts) as hour, ts, event_id from events)")(E.ordered_emission)
query("stream_late_rows", "select time_bucket(interval 1 hour, ts) as start, event_type, count(*) as n from events group by all")(E.late_rows)
query("stream_sliding", "select start, count(*) as n from (select unnest([time_bucket(interval 1 hour, ts), time_bucket(interval 1 hour, ts) - interval 1 hour]) as start from events) group by start")(E.sliding)
query("stream_sessions", "select user_id, min(ts) as start, count(*) as n from (select *, sum(fresh) over (partition by user_id order by ts, event_id) as session from (select *, case when epoch_us(ts) - lag(epoch_us(ts)) over (partition by user_id order by ts, event_id) < 1800000000 then 0 else 1 end as fresh from events)) group by user_id, session")(E.sessions)
query("stream_join", "select c.event_id as click, v.event_id as view from events c join events v on c.user_id = v.user_id and c.event_type = 'click' and v.event_type = 'view' and v.ts between c.ts - interval 1 hour and c.ts")(E.stream_join)
query("stream_static_join", "select event_id, c_mktsegment from events join customer on user_id = c_custkey")(E.static_join)


@query("stream_compaction", order_sql("events"))
def _stream_compaction(spark, sf_dir):
    return S.sorted_from_stream(spark, sf_dir, most=2)


@query("join_radix_outer", "select c_custkey, o_orderkey from customer full outer join orders on c_custkey = o_custkey")
def _radix_outer(spark, sf_dir):
    c = table(spark, sf_dir, "customer").select(K.unsigned(F.col("c_custkey")).alias("k"), "c_custkey")
    o = table(spark, sf_dir, "orders").select(K.unsigned(F.col("o_custkey")).alias("k"), "o_orderkey")
    return joins.radix_merge_join(c, o, "k", 8, 2_000, "full").drop("k")


