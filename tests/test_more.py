"""Nulls, types and names under the sorts; runs and their merges; joins of hot keys; plans."""

import decimal
import math
import random

import pytest
from pyspark.sql import functions as F

from hybridsort import measures, memory, queries_more, queries_sort
from hybridsort.functions import keys as K
from hybridsort.functions import udfs
from hybridsort.operators import baselines, engine, external, joins, msd
from hybridsort.plans import cuts as C
from hybridsort.plans import tree as P
from hybridsort.sources import formats, sinks


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString().split("Initial Plan")[-1]


def exchanges(df):
    text = plan(df)
    return text.count("Exchange ") - text.count("BroadcastExchange ")


def order_of(df, *columns):
    return [tuple(r[c] for c in columns) for r in df.orderBy("position").collect()]


def null_first(*values):
    return tuple((v is not None, v if v is not None else 0) for v in values)


ROWS = [(k, p, q, i, "a", 7) for i, (k, p, q) in enumerate((random.Random(1).choice([None, "0001", "0002", "00FF"]), random.Random(i).choice([None, -3, 5]), random.Random(i + 9).choice([None, 1.5, -2.0, math.inf, 0.0])) for i in range(300))]
SCHEMA = "k string, p long, q double, i long, range_id string, position long"


@pytest.mark.parametrize("kernel", ["jvm", "msd", "stable"])
def test_nulls_and_clashing_names(spark, kernel):
    df = spark.createDataFrame([(*r, 1, 2, "x") for r in ROWS], SCHEMA + ", __range int, __start long, __DIGITS string").repartition(3)
    out = msd.adaptive_sort(df, "k", ["p", "q", "i"], 2, split_limit=20, target_rows=60, kernel=kernel)
    assert out.columns == ["position", *[c for c in df.columns if c != "position"]]
    want = sorted(ROWS, key=lambda r: null_first(*r[:4]))
    assert order_of(out, "k", "p", "q", "i") == [r[:4] for r in want]
    assert [r["position"] for r in out.select("position").orderBy("position").collect()] == list(range(1, 301))


@pytest.mark.parametrize("sort", [lambda d: external.external_sort(d, "k", ["p", "q", "i"], 2, 20, 60), lambda d: external.external_sort(d, "k", ["p", "q", "i"], 2, 20, 60, "kway", run_rows=30, most=3), lambda d: msd.static_sort(d, "k", ["p", "q", "i"]), lambda d: msd.lpt_sort(d, "k", ["p", "q", "i"], 3), lambda d: engine.partial_sort(d, "k", ["p", "q", "i"], width=2, split_limit=20, target_rows=60), lambda d: baselines.spark_sort(d, "k", "p", "q", "i")])
def test_no_path_loses_rows(spark, sort):
    df = spark.createDataFrame(ROWS, SCHEMA).repartition(5)
    assert order_of(sort(df), "k", "p", "q", "i") == [r[:4] for r in sorted(ROWS, key=lambda r: null_first(*r[:4]))]


@pytest.mark.parametrize("kernel", ["jvm", "msd"])
def test_ties_of_a_constant_prefix_are_parted(spark, kernel):
    rows = [("http://www.", f"http://www.{i * 7919 % 5000:05d}.example", i) for i in range(5000)]
    df = spark.createDataFrame(rows, "k string, url string, i long").withColumn("k", K.text(F.col("k")))
    out = msd.adaptive_sort(df, "k", ["i"], 10, split_limit=100, target_rows=500, kernel=kernel, full_key="url")
    assert order_of(out, "url") == [(u,) for u in sorted(r[1] for r in rows)]
    full, name, width, _ = msd.with_digits(df, "k", 10, ["i"], "url")
    assert max(n for _, _, n in C.cut(full, F.col(name), width, 100, 500).ranges) <= 1000


def test_texts_as_pointers(spark):
    rng = random.Random(2)
    rows = [("00", rng.choice([None, "", "é", "e", "x" * 100 + rng.choice("ab")]), i) for i in range(200)]
    df = spark.createDataFrame(rows, "k string, t string, i long")
    for kernel in ("jvm", "lsd"):
        out = msd.adaptive_sort(df, "k", ["t", "i"], 1, 10, 20, kernel)
        assert order_of(out, "t", "i") == [r[1:] for r in sorted(rows, key=lambda r: (r[1] is not None, (r[1] or "").encode(), r[2]))]


def test_decimals_and_floats_keep_order(spark):
    values = [decimal.Decimal(x) for x in ("0", "-0.01", "0.01", "99999999999999999999999999999999999.99", "-99999999999999999999999999999999999.99", "12.30", "-12.30", "12.29")]
    df = spark.createDataFrame([(v,) for v in values], "v decimal(38,2)")
    rows = df.withColumn("k", K.normalize(F.col("v"), df.schema["v"].dataType)).collect()
    assert [r["v"] for r in sorted(rows, key=lambda r: r["k"])] == sorted(values)
    vectors = [[0.0, 1.0], [-0.0, 2.0], [1e-7, 0.0], [2e-7, 0.0], [math.inf, 0.0], [math.nan, 0.0], [-1.0, 5.0]]
    df = spark.createDataFrame([(i, v) for i, v in enumerate(vectors)], "i int, v array<double>")
    rows = df.withColumn("k", K.floats(F.col("v"), 2)).collect()
    assert [r["i"] for r in sorted(rows, key=lambda r: r["k"])] == [6, 0, 1, 2, 3, 4, 5]
    assert len({r["k"] for r in rows}) == 7


def test_cut_points(spark):
    keys = ["0001"] * 150 + [f"{i * 37 % 65536:04X}" for i in range(100)]
    df = spark.createDataFrame([(k,) for k in keys], "k string")
    found = C.cut(df, F.col("k"), 2, 20, 60)
    assert found.rows == 250 and sum(n for _, _, n in found.ranges) == 250
    leaves = sorted(found.leaves, key=lambda x: x.prefix)
    assert all(a.prefix < b.prefix and not b.prefix.startswith(a.prefix) for a, b in zip(leaves, leaves[1:]))
    assert sum(rows for name, (_, rows) in found.routes(8).items() if name != "cooperative") == 250
    assert C.cut(df.limit(0), F.col("k"), 2, 20, 60).ranges == []


def test_few_jobs(spark):
    df = spark.range(20_000).select(K.uniform_binary("id").alias("k"), "id")
    tracker = spark.sparkContext.statusTracker()
    spark.sparkContext.setJobGroup("counted", "")
    msd.adaptive_sort(df, "k", ["id"], split_limit=200, target_rows=2000).write.format("noop").mode("overwrite").save()
    jobs = len(tracker.getJobIdsForGroup("counted"))
    spark.sparkContext.setJobGroup("other", "")
    assert jobs < 12


def shuffled(spark, n=2000):
    keys = [f"{i * 7919 % 65536:04X}" for i in range(n)]
    return spark.createDataFrame([(k, i) for i, k in enumerate(keys)], "k string, p long").repartition(6), sorted(range(n), key=lambda i: (keys[i], i))


def test_merges_shuffle_nothing(spark):
    df, want = shuffled(spark)
    runs = external.make_runs(df, "k", ["p"], 2, 100, 400)
    for kernel in ("jvm", "kway"):
        out = external.merge_runs(runs, kernel)
        assert exchanges(out) == 0
        assert [p for (p,) in order_of(out, "p")] == want
    r = external.count_runs(runs).first()
    assert r["rows"] == 2000 and r["ordered"] and r["ranges"] == len(runs.buckets)


def test_runs_are_merged_in_rounds(spark):
    df, want = shuffled(spark)
    runs = external.make_runs(df, "k", ["p"], 2, 100, 400, run_rows=40)
    before = external.fan_in(runs)
    fewer = external.compact(runs, 4)
    assert before > 12 and external.fan_in(fewer) == -(-before // 4)
    assert external.count_runs(fewer).first()["ordered"]
    assert [p for (p,) in order_of(external.merge_runs(fewer, "kway", most=2), "p")] == want


@pytest.mark.parametrize("order", ["key", "size_desc", "arrival"])
@pytest.mark.parametrize("overlap", [True, False])
def test_ranges_as_jobs(spark, tmp_path, order, overlap):
    df, want = shuffled(spark, 800)
    runs = external.make_runs(df, "k", ["p"], 2, 100, 300)
    assert [p for (p,) in order_of(external.run_pipeline(runs, f"{tmp_path}/out", overlap, order), "p")] == want


def test_a_lost_range_is_done_again(spark, tmp_path):
    df, want = shuffled(spark, 800)
    runs = external.make_runs(df, "k", ["p"], 2, 100, 300)
    external.run_pipeline(runs, f"{tmp_path}/out")
    kept = (tmp_path / "out/range_id=0/_SUCCESS").stat().st_mtime_ns
    lost = tmp_path / "out/range_id=1"
    (lost / "_SUCCESS").unlink()
    next(lost.glob("*.parquet")).unlink()
    assert [p for (p,) in order_of(external.run_pipeline(runs, f"{tmp_path}/out"), "p")] == want
    assert (tmp_path / "out/range_id=0/_SUCCESS").stat().st_mtime_ns == kept


def test_sorted_inputs_are_merged(spark):
    parts = [spark.createDataFrame([(f"{(i * 5 + s) % 97:04X}", 1000 * s + i) for i in range(60)], "k string, p long") for s in range(4)]
    every = [(r["k"], r["p"]) for part in parts for r in part.collect()]
    assert order_of(external.merge_sorted(parts, "k", ["p"], 2, 20, 50), "k", "p") == sorted(every)


@pytest.mark.parametrize("how", ["inner", "left", "right", "full"])
def test_join_of_hot_and_null_keys(spark, how):
    a = spark.createDataFrame([(f"{0 if i % 3 else i % 11:04X}" if i % 17 else None, i) for i in range(400)], "k string, a long")
    b = spark.createDataFrame([(f"{i % 13 * 2:04X}" if i % 19 else None, i) for i in range(60)], "k string, b long")
    out = joins.radix_merge_join(a, b, "k", 2, 20, how)
    assert out.columns == ["k", "a", "b"]
    assert sorted(map(tuple, out.collect()), key=repr) == sorted(map(tuple, a.join(b, "k", how).select("k", "a", "b").collect()), key=repr)


def test_a_hot_key_is_parted(spark):
    a = spark.createDataFrame([("0000", i) for i in range(1000)], "k string, a long")
    found = C.cut(a.select(F.concat(F.lit("01"), "k").alias("k")), F.col("k"), 3, 100, 100)
    assert [x.pieces for x in found.leaves] == [10]
    assert joins.radix_merge_join(a, a.withColumnRenamed("a", "b").limit(3), "k", 2, 100).count() == 3000


@pytest.mark.parametrize("eager,moves", [(False, 28), (True, 25)])
def test_moves_of_the_route_example(spark, eager, moves):
    # digit 0: a6 b3 c1; a splits into 4, 1, 1; b into 2, 1; c into 1
    keys = ["0A0000", "0A0001", "0A0002", "0A0003", "0A0100", "0A0200", "0B0000", "0B0001", "0B0100", "0C0000"]
    df = spark.createDataFrame([(k,) for k in keys], "k string")
    rows = df.withColumn("route", P.route(F.lit(5), F.lit(1), 4, 2, 3)).first()
    assert rows["route"] == "cooperative"
    nodes = P.tree_nodes(df, F.col("k"), 3, 4, 2, eager, single_finished=False)
    assert nodes.where("route in ('cooperative', 'sequential')").agg(F.sum("n")).first()[0] == moves


@pytest.mark.parametrize("n,route", [(4, "sequential"), (5, "cooperative"), (2, "sequential"), (1, "finished")])
def test_limits_are_strict(spark, n, route):
    assert spark.range(1).select(P.route(F.lit(n), F.lit(0), 4, 2, 3, True)).first()[0] == route


def test_histogram_below_prefixes_of_several_depths(spark):
    df = spark.createDataFrame([(k,) for k in ("0001", "0002", "0101", "0102", "0201")], "k string")
    within = spark.createDataFrame([("00",), ("0102",)], "prefix string")
    assert sorted(map(tuple, P.digit_histogram(df, F.col("k"), 2, within).collect())) == [("0001", 1), ("0002", 1), ("0102", 1)]


def test_held_data_leaves_with_its_last_user(spark):
    held = memory.Held(spark.range(100))
    with held as a:
        assert a.count() == 100 and a.storageLevel.useMemory
        with held:
            pass
        assert held.df.storageLevel.useMemory
    assert not held.df.storageLevel.useMemory
    df, want = shuffled(spark, 300)
    assert [p for (p,) in order_of(engine.partial_sort(df, "k", ["p"], width=2, split_limit=50, target_rows=100), "p")] == want
    assert not df.select("k", "p").storageLevel.useMemory


def test_bucketed_tables_join_without_an_exchange(spark):
    a = sinks.write_bucketed(spark.range(100).withColumnRenamed("id", "x"), 4, "x")
    b = sinks.write_bucketed(spark.range(50).withColumnRenamed("id", "y"), 4, "y")
    out = a.hint("merge").join(b, a["x"] == b["y"])
    assert out.count() == 50 and exchanges(out) == 0


@pytest.mark.parametrize("durability", ["durable", "cached"])
def test_sorted_sink_and_its_manifest(spark, tmp_path, durability):
    df, want = shuffled(spark, 300)
    found = sinks.write_sorted(msd.adaptive_sort(df, "k", ["p"], 2, 50, 100), f"{tmp_path}/s", "k", 100, durability)
    rows = {r["part"]: r for r in found.collect()}
    assert sorted(rows) == [0, 1, 2] and all(r["rows"] == 100 for r in rows.values()) and rows[0]["high"] <= rows[1]["low"]
    back = spark.read.parquet(f"{tmp_path}/s")
    assert [p for (p,) in order_of(back, "p")] == want and (tmp_path / "s/_SUCCESS").exists()
    assert found.agg(F.sum("checksum")).first()[0] == df.agg(measures.checksum(F.col("k"))).first()[0]


def test_salted_copies_are_never_broadcast(spark, tmp_path):
    a = spark.createDataFrame([(i % 3 if i % 5 else None, i) for i in range(60)], "k long, l long")
    b = spark.createDataFrame([(k, f"b{k}{i}") for k in (0, 1, 7, None) for i in range(2)], "k long, r string")
    b.write.parquet(f"{tmp_path}/b")  # a file has a size that Spark knows
    out = joins.salted(a, spark.read.parquet(f"{tmp_path}/b"), "k")
    assert "SortMergeJoin" in plan(out) and "Broadcast" not in plan(out)
    assert sorted(map(tuple, out.collect())) == sorted((x["k"], x["l"], y["r"]) for x in a.collect() for y in b.collect() if x["k"] is not None and x["k"] == y["k"])


def test_pointers_of_a_scan(spark, tmp_path):
    spark.range(100).repartition(3).write.parquet(f"{tmp_path}/t")
    found = sinks.with_pointer(spark.read.parquet(f"{tmp_path}/t"))
    assert found.select("file", "row").distinct().count() == 100


def test_grouping_by_sorting(spark):
    out = spark.range(100).select((F.col("id") % 7).alias("g"), F.col("id").cast("string").alias("s")).groupBy("g").agg(F.max("s"))
    assert "SortAggregate" in plan(out)


def test_functions_in_sql(spark):
    udfs.register(spark)
    r = spark.sql("select signed_key(-5), unsigned_key(255), key_digit('0A0B0C', 1), text_key('é', 3), descending_key('00FF')").first()
    assert tuple(r) == ("7FFFFFFFFFFFFFFB", "00000000000000FF", "0B", "C3A900", "FF00")
    rows = spark.sql("select c.* from (select digit_counts(d) as n from values ('00'), ('0A'), ('0A'), (null) t(d)) h, lateral bucket_children('FF', h.n) c").collect()
    assert sorted(map(tuple, rows)) == [("FF00", 1, 0), ("FF0A", 2, 1)]


@pytest.mark.parametrize("kind", ["csv", "json", "orc", "text"])
def test_round_trips(spark, kind):
    df = spark.createDataFrame([(1, "a,b", 1.5), (2, None, -0.25), (3, 'q"\n', None)], "i int, s string, d double") if kind != "csv" else spark.createDataFrame([(1, "a,b", 1.5), (2, "x", None)], "i int, s string, d double")
    assert sorted(map(tuple, formats.roundtrip(df, kind).collect()), key=repr) == sorted(map(tuple, df.collect()), key=repr)


def test_binary_records_of_large_and_ragged_files(spark, tmp_path):
    rng = random.Random(3)
    contents = {"a.bin": rng.randbytes(700), "b,c.bin": rng.randbytes(300), "d/e.bin": rng.randbytes(1050), "f.bin": b"", "g.bin": b"x" * 7}
    (tmp_path / "small/d").mkdir(parents=True)
    for name, data in contents.items():
        (tmp_path / "small" / name).write_bytes(data)
    want = sorted(data[i : i + 100] for data in contents.values() for i in range(0, len(data), 100))
    assert sorted(bytes(r[0]) for r in formats.binary_records(spark, f"{tmp_path}/small", 100).collect()) == want
    (tmp_path / "none").mkdir()
    (tmp_path / "none/empty.bin").write_bytes(b"")
    assert formats.binary_records(spark, f"{tmp_path}/none", 100).count() == 0
    (tmp_path / "large.bin").write_bytes(rng.randbytes(40_000_000))
    out = formats.binary_records(spark, f"{tmp_path}/large.bin", 100)
    assert out.columns == ["record"] and out.dtypes == [("record", "binary")]
    assert out.rdd.getNumPartitions() > 1  # one file is read by several tasks
    halves = formats.binary_records(spark, f"{tmp_path}/large.bin", 50)
    assert out.distinct().count() == 400_000 and halves.count() == 800_000
    assert spark._jsc.hadoopConfiguration().get("org.apache.spark.input.FixedLengthBinaryInputFormat.recordLength") is None


def test_join_strategies_of_a_table(spark, tmp_path):
    sizes = {1: 1, 2: 10, 3: 11, 4: 40, None: 12}
    spark.createDataFrame([(k, i) for k, n in sizes.items() for i in range(n)], "o_custkey long, o_orderkey long").repartition(3).write.parquet(f"{tmp_path}/orders.parquet")
    out = queries_sort.QUERIES["join_strategy_choice"](spark, str(tmp_path))
    assert any("orders.parquet" in f for f in out.inputFiles())
    assert {r["o_custkey"]: (r["mb"], r["strategy"]) for r in out.collect()} == {k: (n, joins.choose_join(n << 20, 100 << 20)) for k, n in sizes.items()}


def test_modes_of_a_table(spark, tmp_path):
    sizes = {i: n for i, n in enumerate((10, 15, 16, 20, 30, 31, 60))} | {None: 1}
    spark.createDataFrame([(k, i) for k, n in sizes.items() for i in range(n)], "l_partkey long, l_orderkey long").repartition(3).write.parquet(f"{tmp_path}/lineitem.parquet")
    out = queries_sort.QUERIES["mode_choice"](spark, str(tmp_path))
    assert any("lineitem.parquet" in f for f in out.inputFiles())
    assert {r["l_partkey"]: (r["gb"], r["mode"]) for r in out.collect()} == {k: (n, engine.choose_mode(n << 30, 30 << 30)) for k, n in sizes.items()}


def test_modes_of_measured_workloads(spark, tmp_path):
    df = spark.createDataFrame([(1, "a", 0.5, None), (None, "é", None, [1, 2]), (3, None, None, None)], "i int, s string, d double, a array<int>")
    assert engine.measured_bytes(df).first()[0] == 4 + 1 + 8 + 2 + len('{"a":[1,2]}') + 4
    assert engine.measured_bytes(df.limit(0)).first()[0] == 1
    for n, name in ((3, "events"), (1, "orders"), (0, "lineitem")):
        df.limit(n).write.parquet(f"{tmp_path}/{name}.parquet")
    out = queries_more.QUERIES["mode_of_workloads"](spark, str(tmp_path))
    assert {t for t in ("events", "orders", "lineitem") if any(f"{t}.parquet" in f for f in out.inputFiles())} == {"events", "orders", "lineitem"}
    assert sorted(map(tuple, out.collect())) == [("W1", "internal"), ("W2", "partial"), ("W3", "external")]


def test_phases_and_ratios(spark, tmp_path):
    df, _ = shuffled(spark, 300)
    for mode in ("internal", "partial", "external"):
        found = measures.phases(df, "k", ["p"], mode, f"{tmp_path}/{mode}", width=2, split_limit=50, target_rows=100)
        assert found["total_s"] == pytest.approx(sum(v for k, v in found.items() if k != "total_s"))
        assert spark.read.parquet(f"{tmp_path}/{mode}").count() == 300
    staged = baselines.staged_sort(df, "k", ["p"], f"{tmp_path}/staged")
    assert 0 < measures.io_share(staged["read_s"], staged["write_s"], staged["total_s"]) < 1
    assert measures.speedup(6.0, 2.0) == 3.0 and measures.pairs_per_second(10, 2.0) == 5.0 and measures.bandwidth(8, 2.0) == 4.0
    assert measures.imbalance(spark.createDataFrame([(3,), (1,)], "n long")).first()[0] == 1.5
    cells = measures.rank_error(df, "k", ["8000"]).collect()
    assert sum(r["n"] for r in cells) == 300
    assert measures.shuffle_bytes(spark) > 0 and measures.peak_memory(spark)
