"""The registered queries of the training-data operators."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import decontam, htmltext, language, neardup, packing, quality, sharding, suffix_array, suffix_tree, toxicity
from .common import held_out, table


def op1_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(table(spark, sf_dir, "documents"), keep_ids=False).drop("ids")


def op2_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return neardup.link(table(spark, sf_dir, "documents"), width=3, percent=85)


def op3_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = sharding.shard(table(spark, sf_dir, "documents").select("doc_id", "text"))
    text = F.coalesce("text", F.lit(""))
    return out.select(
        "doc_id",
        (F.octet_length(text) + 8).cast("long").alias("size"),
        F.crc32(text.cast("binary")).alias("text_crc32"),
        F.lit("rows").alias("law"),
        "shard",
        "slot",
        F.lit(None).cast("int").alias("grown_shard"),
    )


def op4_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    return htmltext.render(table(spark, sf_dir, "pages"))


def op5_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    found = decontam.find(docs, table(spark, sf_dir, "benchmark"))
    hit = F.aggregate("hit_spans", F.lit(0).cast("long"), lambda n, s: n + s["past"] - s["first"])
    return found.select(
        "doc_id",
        "n_words",
        hit.alias("n_hit"),
        F.size("hit_items").cast("long").alias("n_items"),
        F.sha2(F.array_join(F.array_sort(F.col("hit_items").cast("array<string>")), ",").cast("binary"), 256).alias("items_sha256"),
        (hit > 0).alias("contaminated"),
    )


def op6_suffix_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = suffix_tree.dedup(table(spark, sf_dir, "documents"))
    return out.select("doc_id", F.col("n_units").alias("n_words"), "n_removed", F.sha2("kept_bytes", 256).alias("kept_sha256"))


def op7_suffix_array(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = suffix_array.dedup(table(spark, sf_dir, "documents"))
    return out.select("doc_id", F.col("n_units").alias("n_bytes"), "n_removed", "n_spans", F.sha2("kept_bytes", 256).alias("kept_sha256"))


def op8_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    return quality.judge(docs).drop("lang_group", "text_digest")


def op9_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    model = toxicity.learn(docs, table(spark, sf_dir, "labels"), ~held_out(F.col("doc_id"), 3, 1))
    out = toxicity.score(docs, model)
    return out.select("doc_id", held_out(F.col("doc_id"), 3, 1).alias("held_out"), "score", (F.col("score") >= 0.7).cast("int").alias("predicted"))


def op10_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    trees = language.learn(docs, ~held_out(F.col("doc_id"), 4, 2))
    out = language.identify(docs, trees)
    return out.select("doc_id", held_out(F.col("doc_id"), 4, 2).alias("held_out"), "lang_pred", "score")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_packing": op1_packing,
        "op2_minhash": op2_minhash,
        "op3_sharding": op3_sharding,
        "op4_html_extraction": op4_html_extraction,
        "op5_decontamination": op5_decontamination,
        "op6_suffix_tree": op6_suffix_tree,
        "op7_suffix_array": op7_suffix_array,
        "op8_quality": op8_quality,
        "op9_toxicity": op9_toxicity,
        "op10_language": op10_language,
    }


OP2_SQL = """
with recursive doc_words as (
    select doc_id, regexp_extract_all(regexp_replace(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\\x20\\x09-\\x0D]+', ' ', 'g'), '[^ ]+') as w
    from documents
),
shingles as (
    select distinct doc_id, array_to_string(w[i : i + 2], ' ') as s
    from (select doc_id, w, unnest(range(1, greatest(2, len(w) - 1))) as i from doc_words where len(w) > 0)
),
sizes as (select doc_id, count(*) as n from shingles group by doc_id),
shared as (
    select x.doc_id as a, y.doc_id as b, count(*) as k from shingles x join shingles y on x.s = y.s and x.doc_id < y.doc_id group by all
),
links as (
    select a, b from shared join sizes p on p.doc_id = a join sizes q on q.doc_id = b where 100 * k >= 85 * (p.n + q.n - k)
),
edges as (select a, b from links union all select b, a from links),
reach as (
    select doc_id as node, doc_id as seen from documents
    union
    select reach.node, edges.b from reach join edges on reach.seen = edges.a
)
select d.doc_id, cast(coalesce(s.n, 0) as bigint) as n_shingles, r.c as component_id, d.doc_id = r.c as kept
from documents d left join sizes s using (doc_id) join (select node, min(seen) as c from reach group by node) r on r.node = d.doc_id
"""

OP5_SQL = """
with doc_words as (
    select doc_id, regexp_extract_all(regexp_replace(lower_ascii, '[\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+', ' ', 'g'), '[^ ]+') as w
    from (select doc_id, translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') as lower_ascii from documents)
),
item_words as (
    select item_id, regexp_extract_all(regexp_replace(lower_ascii, '[\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+', ' ', 'g'), '[^ ]+') as w
    from (select item_id, translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') as lower_ascii from benchmark)
),
windows as (
    select distinct item_id, least(10, len(w)) as size, array_to_string(w[i : i + least(10, len(w)) - 1], ' ') as words
    from (select item_id, w, unnest(range(1, greatest(2, len(w) - 8))) as i from item_words where len(w) > 0)
),
sizes as (select distinct size from windows),
places as (
    select doc_id, size, i, array_to_string(w[i : i + size - 1], ' ') as words
    from (select doc_id, size, w, unnest(range(1, len(w) - size + 2)) as i from doc_words, sizes where len(w) >= size)
),
hits as (select p.doc_id, p.size, p.i, x.item_id from places p join windows x on p.size = x.size and p.words = x.words),
covered as (select doc_id, count(distinct pos) as n_hit from (select doc_id, unnest(range(i, i + size)) as pos from hits) group by doc_id),
items as (
    select doc_id, count(*) as n_items, string_agg(id, ',' order by id) as ids
    from (select distinct doc_id, cast(item_id as varchar) as id from hits) group by doc_id
)
select d.doc_id, cast(len(d.w) as bigint) as n_words, cast(coalesce(c.n_hit, 0) as bigint) as n_hit, cast(coalesce(i.n_items, 0) as bigint) as n_items,
    sha256(coalesce(i.ids, '')) as items_sha256, coalesce(c.n_hit, 0) > 0 as contaminated
from doc_words d left join covered c using (doc_id) left join items i using (doc_id)
"""

OP6_SQL = """
with doc_words as (
    select doc_id, regexp_extract_all(regexp_replace(coalesce(text, ''), '[\\x20\\x09-\\x0D]+', ' ', 'g'), '[^ ]+') as w from documents
),
windows as (
    select doc_id, i, md5(array_to_string(w[i : i + 34], ' ')) as h
    from (select doc_id, w, unnest(range(1, len(w) - 33)) as i from doc_words where len(w) >= 35)
),
repeated as (select doc_id, i from windows where h in (select h from windows group by h having count(*) > 1)),
gone as (select distinct doc_id, unnest(range(i, i + 35)) as pos from repeated),
words as (select doc_id, unnest(range(1, len(w) + 1)) as pos, unnest(w) as word from doc_words),
kept as (
    select words.doc_id, string_agg(word, ' ' order by words.pos) as t
    from words left join gone on words.doc_id = gone.doc_id and words.pos = gone.pos where gone.pos is null group by words.doc_id
),
counts as (select doc_id, count(*) as n from gone group by doc_id)
select d.doc_id, cast(len(d.w) as bigint) as n_words, cast(coalesce(c.n, 0) as bigint) as n_removed, sha256(coalesce(k.t, '')) as kept_sha256
from doc_words d left join counts c using (doc_id) left join kept k using (doc_id)
"""


OP7_SQL = """
with texts as (select doc_id, hex(encode(coalesce(text, ''))) as h, octet_length(encode(coalesce(text, ''))) as n from documents),
strings as (select doc_id, i, md5(substr(h, 2 * i - 1, 200)) as k from (select doc_id, h, unnest(range(1, n - 98)) as i from texts where n >= 100)),
firsts as (select k, min({'d': doc_id, 'i': i}) as f from strings group by k having count(*) > 1),
later as (select doc_id, i from strings join firsts using (k) where doc_id <> f.d or i <> f.i),
marked as (select doc_id, i, case when i - lag(i) over (partition by doc_id order by i) <= 100 then 0 else 1 end as fresh from later),
numbered as (select doc_id, i, sum(fresh) over (partition by doc_id order by i) as run from marked),
runs as (select doc_id, min(i) as a, max(i) + 100 as b from numbered group by doc_id, run),
edges as (select doc_id, b as low, lead(a) over (partition by doc_id order by a) as high from runs union all select doc_id, 1, min(a) from runs group by doc_id),
kept as (select doc_id, string_agg(substr(h, 2 * low - 1, 2 * (coalesce(high, n + 1) - low)), '' order by low) as t from edges join texts using (doc_id) group by doc_id),
sums as (select doc_id, sum(b - a) as removed, count(*) as spans from runs group by doc_id)
select t.doc_id, cast(t.n as bigint) as n_bytes, cast(coalesce(s.removed, 0) as bigint) as n_removed, cast(coalesce(s.spans, 0) as bigint) as n_spans, sha256(unhex(coalesce(k.t, t.h))) as kept_sha256
from texts t left join sums s using (doc_id) left join kept k using (doc_id)
"""


def oracle_sql() -> dict[str, str]:
    return {"op2_minhash": OP2_SQL, "op5_decontamination": OP5_SQL, "op6_suffix_tree": OP6_SQL, "op7_suffix_array": OP7_SQL}
