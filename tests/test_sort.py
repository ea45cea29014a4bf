import math

import pytest
from pyspark.sql import functions as F

from hybridsort.functions import keys as K
from hybridsort.operators import baselines, engine, external, joins, msd
from hybridsort.plans import tree as P


def pairs(spark, keys):
    return spark.createDataFrame([(k, i) for i, k in enumerate(keys)], "k string, p long")


def positions(df):
    return [r["p"] for r in df.orderBy("position").collect()], [r["position"] for r in df.orderBy("position").collect()]


CASES = {
    "empty": [],
    "one": ["0A0B"],
    "equal": ["0000"] * 40,
    "reversed": [f"{i:04X}" for i in range(200, 0, -1)],
    "skewed": ["0001"] * 150 + [f"{i * 37 % 65536:04X}" for i in range(100)],
}


@pytest.mark.parametrize("case", ["one", "equal", "reversed", "skewed"])
@pytest.mark.parametrize("kernel", ["jvm", "msd", "inplace"])
def test_adaptive_sort(spark, case, kernel):
    keys = CASES[case]
    got, at = positions(msd.adaptive_sort(pairs(spark, keys), "k", ["p"], 2, split_limit=20, target_rows=60, kernel=kernel))
    assert got == sorted(range(len(keys)), key=lambda i: (keys[i], i))
    assert at == list(range(1, len(keys) + 1))


def test_empty_sort(spark):
    assert msd.adaptive_sort(pairs(spark, []), "k", ["p"], 2).count() == 0


@pytest.mark.parametrize("kernel", ["jvm", "kway"])
def test_external_equals_internal(spark, kernel):
    keys = CASES["skewed"]
    got, _ = positions(external.external_sort(pairs(spark, keys).repartition(5), "k", ["p"], 2, 20, 60, kernel))
    assert got == sorted(range(len(keys)), key=lambda i: (keys[i], i))


def test_baselines_agree(spark):
    keys = CASES["skewed"]
    want = sorted(range(len(keys)), key=lambda i: (keys[i], i))
    df = pairs(spark, keys)
    for out in (msd.static_sort(df, "k", ["p"]), msd.lsd_distributed(df, "k", ["p"], 2), msd.lpt_sort(df, "k", ["p"], 3), baselines.spark_sort(df, "k", "p"), baselines.single_task_sort(df, "k", ["p"])):
        assert positions(out)[0] == want


def test_one_full_exchange(spark):
    df = pairs(spark, CASES["skewed"])
    out = msd.adaptive_sort(df, "k", ["p"], 2, 20, 60)
    plan = out._jdf.queryExecution().executedPlan().toString().split("Initial Plan")[-1]
    assert plan.count("Exchange ") - plan.count("BroadcastExchange ") <= 1


def test_tree_is_the_shallowest(spark):
    keys = CASES["skewed"]
    for r in P.leaves(pairs(spark, keys), F.col("k"), 2, 20, skip_common=False).collect():
        assert sum(k.startswith(r["prefix"]) for k in keys) == r["n"]
        assert r["n"] <= 20 or r["depth"] == 2
        if r["depth"] == 2:
            assert sum(k.startswith(r["prefix"][:2]) for k in keys) > 20


def test_modes():
    gb = 1 << 30
    assert [engine.choose_mode(n * gb, 30 * gb) for n in (10, 15, 16, 20, 30, 31, 60)] == ["internal", "internal", "partial", "partial", "partial", "external", "external"]


def test_join_choice():
    assert joins.choose_join(1, 1 << 40) == "broadcast"
    assert joins.choose_join(1 << 30, 1 << 30) == "merge"
    assert joins.choose_join(1 << 30, 1 << 30, prefer_merge=False) == "shuffle_hash"


@pytest.mark.parametrize("how", ["inner", "left", "full"])
def test_radix_join(spark, how):
    a = spark.createDataFrame([(f"{i % 7:04X}", i) for i in range(40)], "k string, a long")
    b = spark.createDataFrame([(f"{i % 9:04X}", i) for i in range(30)], "k string, b long")
    got = sorted(map(tuple, joins.radix_merge_join(a, b, "k", 2, 10, how).select("a", "b").collect()), key=str)
    assert got == sorted(map(tuple, a.join(b, "k", how).select("a", "b").collect()), key=str)


def test_double_keys(spark):
    values = [0.0, -0.0, 1.5, -1.5, math.inf, -math.inf, 5e-324, -5e-324, math.nan, 1e300]
    df = spark.createDataFrame([(i, v) for i, v in enumerate(values)], "i long, v double").select("i", "v", K.double("v").alias("k"))
    rows = {r["i"]: r["k"] for r in df.collect()}
    assert rows[0] == rows[1]
    assert [i for i in sorted(rows, key=lambda i: (rows[i], i))] == [5, 3, 7, 0, 1, 6, 2, 9, 4, 8]


def test_keys_keep_order(spark):
    values = [-(1 << 63), -5, -1, 0, 1, 7, (1 << 63) - 1]
    df = spark.createDataFrame([(v,) for v in values], "v long").select("v", K.signed(F.col("v")).alias("k"), K.descending(K.signed(F.col("v"))).alias("d"))
    rows = df.collect()
    assert [r["v"] for r in sorted(rows, key=lambda r: r["k"])] == values
    assert [r["v"] for r in sorted(rows, key=lambda r: r["d"])] == values[::-1]


def test_unorderable_is_rejected():
    from pyspark.sql import types as T

    with pytest.raises(TypeError):
        K.normalize(None, T.MapType(T.StringType(), T.StringType()))


def test_radix_select(spark):
    keys = CASES["skewed"]
    for rank in (1, 77, len(keys)):
        assert msd.select_rank(pairs(spark, keys), "k", rank, 2) == sorted(keys)[rank - 1]


def test_fixed_records(spark, tmp_path):
    from hybridsort.sources import records as R

    R.register(spark)
    df = spark.range(250).select(F.col("id"))
    made = R.records(df, F.rpad(F.upper(F.md5(F.col("id").cast("string"))), 20, "0").substr(1, 20), ["id"])
    path = str(tmp_path / "records")
    made.repartition(3).write.format("fixed_records").mode("append").option("path", path).save()
    want = sorted((bytes(r["key"]), bytes(r["value"])) for r in made.collect())
    for request in (100, 1000, 262144):
        back = spark.read.format("fixed_records").option("path", path).option("request_bytes", request).option("split_bytes", 5000).option("queue_depth", request // 100 % 7 + 1).load()
        assert sorted((bytes(r["key"]), bytes(r["value"])) for r in back.collect()) == want


def test_nulls_last_positions_of_all_rows(spark, tmp_path):
    from hybridsort import queries_sort

    spark.range(300).withColumnRenamed("id", "doc_id").write.parquet(f"{tmp_path}/documents.parquet")
    labels = {i: (i // 3) % 2 for i in range(0, 300, 3)}
    spark.createDataFrame(list(labels.items()), "doc_id long, quality int").write.parquet(f"{tmp_path}/labels.parquet")
    rows = queries_sort.QUERIES["msd_sort_nulls_last"](spark, str(tmp_path)).collect()
    assert [r["doc_id"] for r in sorted(rows)] == sorted(range(300), key=lambda i: (i not in labels, labels.get(i, 0), i))
    assert sorted(r["position"] for r in rows) == list(range(1, 301))
