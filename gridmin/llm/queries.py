"""The registered queries of the operators, and their SQL where SQL can state them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gridmin.llm import common, exact_dedup, huffman, mixing, ordinal, packing, quality_rules, sharding, simhash, toxicity, wordpiece

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(fn):
    QUERIES[fn.__name__] = fn
    return fn


def _docs(spark: SparkSession, sf_dir: str, *columns: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet").select(*columns)


@query
def op1_harmonic_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(_docs(spark, sf_dir, "doc_id", "text"))


@query
def op7_huffman_ids(spark: SparkSession, sf_dir: str) -> DataFrame:
    return huffman.round_trip(_docs(spark, sf_dir, "doc_id", "text"))


@query
def op4_capped_water_filling(spark: SparkSession, sf_dir: str) -> DataFrame:
    sizes = common.stage(mixing.sizes_of(_docs(spark, sf_dir, "doc_id", "source", "text")), "sizes")
    out = mixing.repeats(sizes, mixing.plan(sizes))
    return out.select("doc_id", "size", "source_size", "target", (F.col("size") * F.col("n_repeats")).alias("taken"))


ORACLES["op4_capped_water_filling"] = r"""
with d as (
  select doc_id, source, coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0)::bigint as size, md5(concat_ws(':', '11', doc_id, md5(text))) as k
  from documents
), s as (select source, sum(size)::bigint as source_size from d group by source),
w as (select source, source_size, [5.0::double, 2.0::double, 1.0::double][1 + (row_number() over (order by source nulls last) - 1) % 3] as weight from s),
c as (select *, 2.0::double * source_size as cap, 1.5::double * sum(source_size) over () as goal from w),
l as (
  select *, (goal - (sum(cap) over r - cap)) / (sum(weight) over () - (sum(weight) over r - weight)) as level
  from c window r as (order by cap / weight, source nulls last rows unbounded preceding)
), f as (select *, cap / weight <= level as is_full from l),
t as (
  select source, source_size,
    case when is_full then cap else weight * (select arg_min(level, cap / weight) from f where not is_full) end as target
  from f
), e as (select *, coalesce(floor(target / nullif(source_size, 0)), 0)::bigint as whole from t),
o as (
  select d.*, e.source_size, e.target, e.whole, e.target - e.whole * e.source_size as rest,
    sum(d.size) over (partition by d.source order by d.k rows unbounded preceding) - d.size as before
  from d join e on d.source is not distinct from e.source
)
select doc_id, size, source_size, target,
  (size * (whole + case when rest > 0 and 2 * before + size <= 2 * rest then 1 else 0 end))::bigint as taken
from o
"""


@query
def op6_pivot_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = simhash.classes(_docs(spark, sf_dir, "doc_id", "text"))
    return out.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


@query
def op9_chunk_recipes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.deduplicate(_docs(spark, sf_dir, "doc_id", "text")).drop("uid", "mark")


ORACLES["op9_chunk_recipes"] = """
with d as (select doc_id, translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') as t from documents),
g as (select t, max(doc_id) as keep_id, count(*) as group_size from d group by t)
select d.doc_id, g.keep_id, g.group_size, d.doc_id = g.keep_id as kept, sha256(d.t) as text_sha256 from d join g on d.t = g.t
"""


@query
def op10_stratified_interleaving(spark: SparkSession, sf_dir: str) -> DataFrame:
    text = F.coalesce(F.col("text"), F.lit(""))
    rows = _docs(spark, sf_dir, "doc_id", "source", "text").select(
        "doc_id", "source", (F.octet_length(text) + 1).cast("long").alias("size"), F.crc32(text.cast("binary")).alias("text_crc32"), F.md5("text").alias("digest"))
    out = sharding.interleave(rows, digest="digest")
    return out.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


ORACLES["op10_stratified_interleaving"] = """
with z as (
  select i, list_reduce(list_prepend(i, range(8)), lambda c, x: case when c % 2 = 1 then xor(c // 2, 3988292384) else c // 2 end) as v
  from (select unnest(range(256)) as i)
), tab as (select list(v order by i) as v from z),
d as (
  select doc_id, source, octet_length(encode(coalesce(text, ''))) + 1 as size, hex(encode(coalesce(text, ''))) as h, md5(text) as m, md5(concat_ws(':', '7', doc_id, md5(text))) as k
  from documents
), c as (
  select doc_id, source, size, k, m,
    xor(list_reduce(list_prepend(4294967295, list_transform(range(0, size - 1), lambda i: ('0x' || h[2 * i + 1:2 * i + 2])::bigint)),
      lambda a, b: xor(a // 256, tab.v[xor(a % 256, b) + 1])), 4294967295) as text_crc32
  from d, tab
), r as (
  select *, (2 * row_number() over (partition by source order by k, doc_id, m) - 1)::double / (2 * count(*) over (partition by source))::double as f
  from c
), p as (select *, row_number() over (order by f, source nulls last, k, doc_id, m) - 1 as pos, count(*) over () as n from r),
s as (select *, (pos * 8 // n)::int as shard from p)
select doc_id, size::bigint as size, text_crc32::bigint as text_crc32, 'rows' as law, shard,
  (pos - (shard::bigint * n + 7) // 8)::bigint as slot, null::int as grown_shard
from s
"""


@query
def op2_risk_controlled_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    measured = common.stage(quality_rules.measure(_docs(spark, sf_dir, "doc_id", "text", "lang")), "measured")
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    out = quality_rules.judge(measured, quality_rules.cutoffs(measured, labels))
    return out.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "scope", "level")


@query
def op3_longest_match_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return wordpiece.token_counts(_docs(spark, sf_dir, "doc_id", "text"))


@query
def op5_ordinal_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = _docs(spark, sf_dir, "doc_id", "text"), spark.read.parquet(f"{sf_dir}/labels.parquet")
    out = ordinal.grade(docs, ordinal.fit(docs, labels))
    return out.select("doc_id", common.in_fold(F.col("doc_id")).alias("held_out"), "expected_grade", "tail_1", "tail_2", (F.col("tail_1") >= 0.5).alias("kept"))


@query
def op8_subword_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = _docs(spark, sf_dir, "doc_id", "text"), spark.read.parquet(f"{sf_dir}/labels.parquet")
    out = toxicity.scores(docs, toxicity.fit(docs, labels))
    return out.select("doc_id", common.in_fold(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= 0.7).cast("int").alias("predicted"))
