"""Registered queries: the sorts, their parts, variants, baselines and measures."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .functions import keys as K
from .operators import baselines, engine, external, joins, msd
from .plans import tree as P
from .sources.tables import kept, table
from .streaming import runs as S

QUERIES: dict = {}
SQL: dict[str, str] = {}

LI = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice"]
_H = "upper(md5(concat_ws('-', {})))"
H_LI = _H.format("l_orderkey, l_linenumber, l_partkey, l_suppkey")


def _sk(h: str) -> str:
    return f"case when substr({h}, 1, 2) < 'C0' then '0000' || substr({h}, 1, 16) else substr({h}, 1, 20) end"


def _ua(h: str) -> str:
    return " || ".join(f"lpad(hex(cast(32 + cast(('0x' || substr({h}, {2 * i + 1}, 2)) as int) % 95 as bigint)), 2, '0')" for i in range(10))


#: name: (table, key, key in SQL, pointer columns)
WORKLOADS: dict[str, tuple[str, Column, str, list[str]]] = {}


def _workload(name: str, tab: str, key, sql: str, ptr: list[str]) -> None:
    WORKLOADS[name] = (tab, key, sql, ptr)


_workload("uniform", "lineitem", lambda: K.uniform_binary(*LI[:4]), f"substr({H_LI}, 1, 20)", LI)
_workload("skewed", "lineitem", lambda: K.skewed(*LI[:4]), _sk(H_LI), LI)
_workload("ascii", "orders", lambda: K.uniform_ascii("o_orderkey"), _ua(_H.format("o_orderkey")), ["o_orderkey"])
_workload("events", "events", lambda: K.uniform_binary("event_id"), f"substr({_H.format('event_id')}, 1, 20)", ["event_id"])
_workload("int", "lineitem", lambda: K.unsigned(F.col("l_orderkey")), "lpad(hex(l_orderkey), 16, '0')", LI)
_workload("dups", "lineitem", lambda: K.unsigned(F.col("l_quantity").cast("long")), "lpad(hex(cast(l_quantity as bigint)), 16, '0')", LI)
_workload("constant", "lineitem", lambda: F.lit("0" * 16), "'0000000000000000'", LI)
_workload("time", "events", lambda: K.unsigned(F.unix_micros(F.col("ts").cast("timestamp"))), "lpad(hex(epoch_us(ts)), 16, '0')", ["event_id"])
_workload("cents", "customer", lambda: K.signed(F.round(F.col("c_acctbal") * 100).cast("long")), "hex(xor(cast(round(c_acctbal * 100) as bigint), cast(-9223372036854775808 as bigint)))", ["c_custkey"])
_workload("text", "documents", lambda: K.text(F.col("text")), "rpad(substr(hex(encode(text)), 1, 20), 20, '0')", ["doc_id"])
_workload("url", "pages", lambda: K.text(F.col("url")), "rpad(substr(hex(encode(url)), 1, 20), 20, '0')", ["page_id"])


def load(spark, sf_dir: str, name: str) -> tuple[DataFrame, list[str], int]:
    """Key k and pointers of a workload, and the key's digits."""
    tab, key, _, ptr = WORKLOADS[name]
    df = table(spark, sf_dir, tab).select(key().alias("k"), *ptr)
    return df, ptr, 8 if name in ("int", "dups", "constant", "time", "cents") else 10


def limits(df: DataFrame) -> dict[str, int]:
    """Rows of a range for about a dozen ranges on small data, and two million at most; leaves are a quarter of it."""
    target = max(1000, min(2_000_000, df.count() // 12))
    return {"split_limit": target // 4, "target_rows": target}


def pairs_sql(name: str) -> str:
    tab, _, sql, ptr = WORKLOADS[name]
    return f"select {sql} as k, {', '.join(ptr)} from {tab}"


def order_sql(name: str) -> str:
    ptr = ", ".join(WORKLOADS[name][3])
    return f"select row_number() over (order by k, {ptr}) as position, k, {ptr} from ({pairs_sql(name)})"


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return add


def _sorted_query(name: str, workload: str, run) -> None:
    @query(name, order_sql(workload))
    def go(spark, sf_dir):
        df, ptr, width = load(spark, sf_dir, workload)
        return run(df, ptr, width)


for _w in WORKLOADS:
    _sorted_query(f"msd_sort_{_w}", _w, lambda df, ptr, width: msd.adaptive_sort(df, "k", ptr, width, **limits(df)))
for _kernel in ("msd", "msd_blocked", "lsd", "inplace", "stable", "quick"):
    _sorted_query(f"kernel_{_kernel}_skewed", "skewed", lambda df, ptr, width, kernel=_kernel: msd.adaptive_sort(df, "k", ptr, width, kernel=kernel, **limits(df)))
_sorted_query("msd_static", "uniform", lambda df, ptr, width: msd.static_sort(df, "k", ptr))
_sorted_query("msd_full_depth", "dups", lambda df, ptr, width: msd.adaptive_sort(df, "k", ptr, width, kernel="msd", compare_limit=0, split_limit=1, target_rows=max(1000, df.count() // 8)))
_sorted_query("lsd_distributed_events", "events", lambda df, ptr, width: msd.lsd_distributed(df, "k", ptr, width))
_sorted_query("radix_lpt_balanced", "uniform", lambda df, ptr, width: msd.lpt_sort(df, "k", ptr))
_sorted_query("stable_sort_dups", "dups", lambda df, ptr, width: baselines.comparison_sort(df, "k", ptr, True, width=width, **limits(df)))
_sorted_query("quick_sort_uniform", "uniform", lambda df, ptr, width: baselines.comparison_sort(df, "k", ptr, False, width=width, **limits(df)))
_sorted_query("spark_orderby_uniform", "uniform", lambda df, ptr, width: baselines.spark_sort(df, "k", *ptr))
_sorted_query("single_task_sort", "events", lambda df, ptr, width: baselines.single_task_sort(df, "k", ptr))
_sorted_query("internal_sort_events", "events", lambda df, ptr, width: engine.sort(df, "k", ptr, mode="internal", width=width, **limits(df)))
_sorted_query("partial_sort_orders", "ascii", lambda df, ptr, width: engine.sort(df, "k", ptr, mode="partial", width=width, **limits(df)))
_sorted_query("external_sort_lineitem", "skewed", lambda df, ptr, width: external.external_sort(df, "k", ptr, width, **limits(df)))
_sorted_query("external_sort_kway", "skewed", lambda df, ptr, width: external.external_sort(df, "k", ptr, width, kernel="kway", **limits(df)))
_sorted_query("adaptive_sort_auto", "uniform", lambda df, ptr, width: engine.sort(df, "k", ptr, width=width, **limits(df)))


@query("prefix_then_compare_documents", "select row_number() over (order by k, text, doc_id) as position, doc_id from (select rpad(substr(hex(encode(text)), 1, 20), 20, '0') as k, text, doc_id from documents)")
def _prefix_then_compare(spark, sf_dir):
    df = table(spark, sf_dir, "documents").select(K.text(F.col("text")).alias("k"), "text", "doc_id")
    return msd.adaptive_sort(df, "k", ["doc_id"], full_key="text", **limits(df)).select("position", "doc_id")


@query("prefix_tie_groups", "select k, count(*) as n, count(distinct text) as texts from (select rpad(substr(hex(encode(text)), 1, 20), 20, '0') as k, text from documents) group by k having count(*) > 1")
def _ties(spark, sf_dir):
    df = table(spark, sf_dir, "documents").select(K.text(F.col("text")).alias("k"), "text")
    return df.groupBy("k").agg(F.count("*").alias("n"), F.countDistinct("text").alias("texts")).where("n > 1")


@query("record_sort_lineitem", f"select row_number() over (order by k, l_orderkey, l_linenumber, l_partkey, l_suppkey, l_extendedprice) as position, * from (select substr({H_LI}, 1, 20) as k, * from lineitem)")
def _record_sort(spark, sf_dir):
    df = table(spark, sf_dir, "lineitem").withColumn("k", K.uniform_binary(*LI[:4]))
    return msd.adaptive_sort(df, "k", LI, **limits(df))


@query("gather_payload", f"select row_number() over (order by k, o_orderkey) as position, k, o_orderkey, o_totalprice, o_orderstatus from (select substr({_H.format('o_orderkey')}, 1, 20) as k, * from orders)")
def _gather(spark, sf_dir):
    orders = table(spark, sf_dir, "orders")
    pairs = orders.select(K.uniform_binary("o_orderkey").alias("k"), "o_orderkey")
    return msd.gather(msd.adaptive_sort(pairs, "k", ["o_orderkey"], **limits(pairs)), orders.select("o_orderkey", "o_totalprice", "o_orderstatus"), ["o_orderkey"])


@query("spark_orderby_composite", "select row_number() over (order by o_orderpriority, o_orderdate, o_totalprice desc, o_orderkey) as position, o_orderkey from orders")
def _composite(spark, sf_dir):
    df = table(spark, sf_dir, "orders")
    return baselines.spark_sort(df, F.asc("o_orderpriority"), F.asc("o_orderdate"), F.desc("o_totalprice"), F.asc("o_orderkey")).select("position", "o_orderkey")


@query("msd_sort_composite", "select row_number() over (order by o_orderpriority, o_orderdate, cast(round(o_totalprice * 100) as bigint) desc, o_orderkey) as position, o_orderkey from orders")
def _composite_key(spark, sf_dir):
    key = K.composite(K.text(F.col("o_orderpriority"), 16), K.timestamp(F.col("o_orderdate")), K.descending(K.signed(F.round(F.col("o_totalprice") * 100).cast("long"))))
    df = table(spark, sf_dir, "orders").select(key.alias("k"), "o_orderkey")
    return msd.adaptive_sort(df, "k", ["o_orderkey"], 32, **limits(df)).select("position", "o_orderkey")


@query("msd_sort_double", "select row_number() over (order by value, event_id) as position, event_id from events")
def _double_key(spark, sf_dir):
    df = table(spark, sf_dir, "events").select(K.double("value").alias("k"), "event_id")
    return msd.adaptive_sort(df, "k", ["event_id"], 8, **limits(df)).select("position", "event_id")


@query("msd_sort_nulls", "select row_number() over (order by quality nulls first, doc_id) as position, doc_id from documents left join labels using (doc_id)")
def _null_key(spark, sf_dir):
    docs = table(spark, sf_dir, "documents").select("doc_id").join(table(spark, sf_dir, "labels"), "doc_id", "left")
    df = docs.select(F.rpad(K.nulls(K.signed(F.col("quality")), F.col("quality")), 18, "0").alias("k"), "doc_id")
    return msd.adaptive_sort(df, "k", ["doc_id"], 9, **limits(df)).select("position", "doc_id")


@query("msd_sort_nulls_last", "select row_number() over (order by quality nulls last, doc_id) as position, doc_id from documents left join labels using (doc_id)")
def _null_last_key(spark, sf_dir):
    docs = table(spark, sf_dir, "documents").select("doc_id").join(table(spark, sf_dir, "labels"), "doc_id", "left")
    df = docs.select(F.rpad(K.nulls(K.signed(F.col("quality")), F.col("quality"), first=False), 18, "0").alias("k"), "doc_id")
    return msd.adaptive_sort(df, "k", ["doc_id"], 9, **limits(df)).select("position", "doc_id")


for _w in ("uniform", "ascii", "skewed", "cents", "text"):

    @query(f"key_normalize_{_w}", pairs_sql(_w))
    def _normalize(spark, sf_dir, w=_w):
        return load(spark, sf_dir, w)[0]


for _d in (1, 2):

    @query(f"digit_histogram_l{_d}", f"select substr(k, 1, {2 * _d}) as prefix, count(*) as n from ({pairs_sql('skewed')}) group by 1")
    def _histogram(spark, sf_dir, d=_d):
        return P.digit_histogram(load(spark, sf_dir, "skewed")[0], F.col("k"), d)


@query("bucket_offsets", f"select prefix, n, cast(coalesce(sum(n) over (order by prefix rows between unbounded preceding and 1 preceding), 0) as bigint) as start from (select substr(k, 1, 2) as prefix, count(*) as n from ({pairs_sql('skewed')}) group by 1)")
def _offsets(spark, sf_dir):
    return P.offsets(P.digit_histogram(load(spark, sf_dir, "skewed")[0], F.col("k"), 1))


@query("bucket_assignment", f"with k as (select substr(k, 1, 2) as prefix, l_orderkey, l_linenumber from ({pairs_sql('uniform')})), h as (select prefix, count(*) as n from k group by 1), o as (select prefix, cast(sum(n) over (order by prefix) - n as bigint) as start from h) select prefix, l_orderkey, l_linenumber, start from k join o using (prefix)")
def _assignment(spark, sf_dir):
    df = load(spark, sf_dir, "uniform")[0]
    tree = P.offsets(P.digit_histogram(df, F.col("k"), 1)).withColumn("depth", F.lit(1))
    return P.assign(df, "k", kept(tree), ["prefix", "start"]).select("prefix", "l_orderkey", "l_linenumber", "start")


def _tree_sql(workload: str, width: int, limit: int) -> str:
    """Leaves by their definition: the least depth at which at most ``limit`` keys share the prefix."""
    counts = ", ".join(f"count(*) over (partition by substr(k, 1, {2 * d})) as c{d}" for d in range(1, width + 1))
    depth = " ".join(f"when c{d} <= {limit} then {d}" for d in range(1, width)) or "when false then 0"
    return f"select substr(k, 1, 2 * depth) as prefix, depth, count(*) as n from (select k, cast(case {depth} else {width} end as int) as depth from (select k, {counts} from ({pairs_sql(workload)}))) group by 1, 2"


@query("bucket_tree", _tree_sql("skewed", 10, 200))
def _tree(spark, sf_dir):
    return P.leaves(load(spark, sf_dir, "skewed")[0], F.col("k"), 10, 200, skip_common=False)


@query("bucket_tree_int", _tree_sql("int", 8, 200))
def _tree_int(spark, sf_dir):
    df = load(spark, sf_dir, "int")[0]
    return P.leaves(df, F.col("k"), 8, 200)


@query("balanced_ranges", f"with t as ({_tree_sql('skewed', 10, 200)}), s as (select n, cast(sum(n) over (order by prefix) - n as bigint) as start from t) select cast(dense_rank() over (order by floor(start / 5000)) - 1 as int) as range_id, cast(sum(n) as bigint) as rows, min(start) as start from s group by floor(start / 5000)")
def _balanced(spark, sf_dir):
    tree = P.pack_ranges(P.leaves(load(spark, sf_dir, "skewed")[0], F.col("k"), 10, 200, skip_common=False), 5000)
    return tree.groupBy("range_id").agg(F.sum("n").alias("rows"), F.min("start").alias("start"))


def _routes(spark, sf_dir):
    df = load(spark, sf_dir, "dups")[0].select(F.substring("k", 13, 4).alias("k"))
    return P.tree_nodes(df, F.col("k"), 2, 20_000, 1200)


@query("bucket_routes", f"with k as (select substr(k, 13, 4) as k from ({pairs_sql('dups')})), r as (select count(*) as n from k), a as (select substr(k, 1, 2) as prefix, 1 as depth, count(*) as n from k group by 1), b as (select k as prefix, 2 as depth, count(*) as n from k group by 1) select '' as prefix, cast(0 as int) as depth, n, 'cooperative' as route, false as from_task from r union all select prefix, cast(depth as int), n, case when n <= 1 then 'finished' when n > 20000 then 'cooperative' else 'sequential' end, false from a union all select b.prefix, cast(b.depth as int), b.n, 'finished', a.n <= 20000 from b join a on substr(b.prefix, 1, 2) = a.prefix and a.n > 1")
def _bucket_routes(spark, sf_dir):
    return _routes(spark, sf_dir)


@query("cost_by_route")
def _cost(spark, sf_dir):
    nodes = P.tree_nodes(load(spark, sf_dir, "events")[0], F.col("k"), 4, 2000, 64)
    moved = F.when(F.col("route").isin("cooperative", "sequential"), F.col("n")).otherwise(0)
    compared = F.when(F.col("route") == "comparison", F.col("n") * F.ceil(F.log2("n"))).otherwise(0)
    return nodes.groupBy("route").agg(F.count("*").alias("buckets"), F.sum("n").alias("records"), F.sum(moved).alias("radix_moves"), F.sum(compared).cast("long").alias("compare_cost"))


@query("cost_passes", f"select min(depth) as least, cast(sum(depth * n) as bigint) as moves, max(depth) as most from ({_tree_sql('skewed', 10, 200)})")
def _passes(spark, sf_dir):
    tree = P.leaves(load(spark, sf_dir, "skewed")[0], F.col("k"), 10, 200, skip_common=False)
    return tree.agg(F.min("depth").alias("least"), F.sum(F.col("depth") * F.col("n")).cast("long").alias("moves"), F.max("depth").alias("most"))


@query("bytes_pairs_vs_records", "select count(*) as n, count(*) * 18 as pair_bytes, count(*) * 100 as record_bytes from lineitem")
def _bytes(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").agg(F.count("*").alias("n"), (F.count("*") * 18).alias("pair_bytes"), (F.count("*") * 100).alias("record_bytes"))


@query("worked_example_buckets", "select bucket, n, cast(sum(n) over (order by bucket) - n as bigint) as start from (select substr(w, 1, 1) as bucket, count(*) as n from (values ('abc'), ('bcd'), ('cde'), ('cfe'), ('dfg')) t(w) group by 1)")
def _worked(spark, sf_dir):
    words = spark.createDataFrame([(w,) for w in ("abc", "bcd", "cde", "cfe", "dfg")], "w string")
    found = P.offsets(P.digit_histogram(words, F.hex("w"), 1))
    return found.select(F.unhex("prefix").cast("string").alias("bucket"), "n", "start")


@query("mode_choice", "select l_partkey, count(*) as gb, case when count(*) <= 15 then 'internal' when count(*) <= 30 then 'partial' else 'external' end as mode from lineitem group by l_partkey")
def _mode(spark, sf_dir):
    """The rows of each part stand for an input of as many GB, against a budget of 30."""
    sizes = table(spark, sf_dir, "lineitem").groupBy("l_partkey").agg(F.count("*").alias("gb"))
    mode = F.udf(engine.choose_mode, "string", useArrow=True)(F.col("gb") * (1 << 30), F.lit(30 << 30))
    return sizes.select("l_partkey", "gb", mode.alias("mode"))


@query("join_strategy_choice", "select o_custkey, count(*) as mb, case when count(*) <= 10 then 'broadcast' else 'merge' end as strategy from orders group by o_custkey")
def _strategy(spark, sf_dir):
    """The orders of each customer stand for a side of as many MB, against one of 100."""
    sizes = table(spark, sf_dir, "orders").groupBy("o_custkey").agg(F.count("*").alias("mb"))
    strategy = F.udf(joins.choose_join, "string", useArrow=True)(F.col("mb") * (1 << 20), F.lit(100 << 20))
    return sizes.select("o_custkey", "mb", strategy.alias("strategy"))


@query("runs_sorted", f"select count(*) as rows, true as ordered from ({pairs_sql('skewed')})")
def _runs(spark, sf_dir):
    df, ptr, width = load(spark, sf_dir, "skewed")
    runs = external.make_runs(df, "k", ptr, width, run_rows=20_000, **limits(df))
    return external.count_runs(runs).select("rows", "ordered")


@query("validate_sorted", "select count(*) as n, true as ordered, true as gapless, cast(sum(cast('0x' || substr(md5(k), 1, 7) as bigint)) as bigint) as checksum, count(*) - count(distinct k) as duplicates from (" + pairs_sql("dups") + ")")
def _validate(spark, sf_dir):
    from .measures import validate

    df, ptr, width = load(spark, sf_dir, "dups")
    return validate(kept(msd.adaptive_sort(df, "k", ptr, width, **limits(df))), "k")


@query("output_manifest", f"select cast(dense_rank() over (order by floor((position - 1) / 1000)) - 1 as int) as part, count(*) as rows, min(k) as low, max(k) as high from ({order_sql('events')}) group by floor((position - 1) / 1000)")
def _manifest(spark, sf_dir):
    df, ptr, width = load(spark, sf_dir, "events")
    out = kept(msd.adaptive_sort(df, "k", ptr, width, **limits(df))).withColumn("part", F.floor((F.col("position") - 1) / 1000).cast("int"))
    return out.groupBy("part").agg(F.count("*").alias("rows"), F.min("k").alias("low"), F.max("k").alias("high"))


@query("median_by_histogram", f"select k from (select k, row_number() over (order by k) as r, count(*) over () as n from ({pairs_sql('skewed')})) where r = (n + 1) // 2")
def _median(spark, sf_dir):
    df = load(spark, sf_dir, "skewed")[0]
    return spark.createDataFrame([(msd.select_rank(df, "k", (df.count() + 1) // 2, 10),)], "k string")


@query("topk_by_histogram", f"select k from ({pairs_sql('uniform')}) order by k limit 25")
def _topk(spark, sf_dir):
    df = load(spark, sf_dir, "uniform")[0]
    return df.where(F.col("k") <= msd.select_rank(df, "k", 25, 10)).select("k").orderBy("k").limit(25)


@query("smj_radix_lineitem_orders", "select l_orderkey, l_linenumber, l_partkey, o_custkey, o_totalprice from lineitem join orders on l_orderkey = o_orderkey")
def _smj(spark, sf_dir):
    left = table(spark, sf_dir, "lineitem").select(K.unsigned(F.col("l_orderkey")).alias("k"), "l_orderkey", "l_linenumber", "l_partkey")
    right = table(spark, sf_dir, "orders").select(K.unsigned(F.col("o_orderkey")).alias("k"), "o_custkey", "o_totalprice")
    target = max(1000, left.count() // 12)
    return joins.radix_merge_join(left, right, "k", 8, min(target, 2_000_000)).drop("k")


@query("stream_runs_events", order_sql("events"))
def _stream(spark, sf_dir):
    return S.sorted_from_stream(spark, sf_dir)


@query("stream_digit_histogram", f"select substr(k, 1, 2) as prefix, count(*) as n from ({pairs_sql('events')}) group by 1")
def _stream_histogram(spark, sf_dir):
    return S.histogram_from_stream(spark, sf_dir)


@query("stream_windows", "select time_bucket(interval 1 hour, ts) as start, event_type, count(*) as n from events group by all")
def _stream_windows(spark, sf_dir):
    return S.windows_from_stream(spark, sf_dir)


@query("stream_dedup", "select distinct event_id, event_type from events")
def _stream_dedup(spark, sf_dir):
    return S.dedup_from_stream(spark, sf_dir)
