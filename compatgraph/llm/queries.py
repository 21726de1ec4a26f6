"""The thin contract queries opN_<name> and the SQL that DuckDB can express for them."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bpe, exact_dedup, mixing, near_dedup, pii, quality, secrets, substring_dedup, tokenfile, toxicity
from .common import documents

RANKS, TOKENIZER = "byte_bpe_50k.tiktoken", "byte_bpe_50k.json"


def op1_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring_dedup.remove_repeats(documents(spark, sf_dir))


def op2_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = documents(spark, sf_dir)
    return toxicity.score(docs, toxicity.fit(docs, spark.read.parquet(f"{sf_dir}/labels.parquet")))


def op3_personal_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.find(documents(spark, sf_dir))


def op4_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(documents(spark, sf_dir)).drop("copies")


def op5_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.judge(documents(spark, sf_dir))


def op6_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dedup.near_duplicates(documents(spark, sf_dir))


def op7_bpe_duckdb(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.encode(documents(spark, sf_dir), public_tokenizers.path(RANKS), public_tokenizers.PATTERN, with_ids=False)


def op8_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = tokenfile.write(documents(spark, sf_dir), public_tokenizers.path(TOKENIZER))
    return tokenfile.read(spark, out)


def op9_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_dedup.group_rows(documents(spark, sf_dir))


def op10_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secrets.find(documents(spark, sf_dir))


def queries() -> dict:
    return {name: f for name, f in globals().items() if name.startswith("op") and callable(f)}


_SIZED = r"""
sized as (select doc_id, source, coalesce(len(regexp_extract_all(text, '[^\x20\x09-\x0D]+')), 0)::bigint as size,
                 ('0x' || substr(md5(coalesce(doc_id::varchar, 'null')), 1, 12))::bigint as h from documents),
sums as (select source, sum(size)::bigint as source_size, row_number() over (order by source nulls last) as i from sized group by source),
caps as (select *, case (i - 1) % 3 when 0 then 3.0::double when 1 then 1.0::double else 2.0::double end as w, 2.0::double * source_size as cap from sums),
rated as (select *, cap / w as ratio,
                 ((select sum(source_size)::double from caps) * 1.5::double - coalesce(sum(cap) over b, 0)) / ((select sum(w) from caps) - coalesce(sum(w) over b, 0)) as r
          from caps window b as (order by cap / w, source rows between unbounded preceding and 1 preceding)),
rate as (select min(r) as rate from (select r from rated where r <= ratio order by ratio, source limit 1)),
goals as (select source, source_size, case when coalesce(rate >= ratio, true) then cap else rate * w end as target from rated, rate),
wanted as (select *, (case when source_size > 0 then floor(target / source_size) else 0 end)::bigint as copies from goals)
"""

ORACLE = {
    "op4_mix_sources": "with " + _SIZED + r""",
cells as (select source, h, sum(size) as s from sized group by source, h),
run as (select *, sum(s) over (partition by source order by h) as upto from cells),
edge as (select r.source, max(case when upto <= target - copies * source_size or upto - (target - copies * source_size) < (target - copies * source_size) - (upto - s) then h end) as through
         from run r join wanted w on r.source is not distinct from w.source where w.source_size > 0 group by r.source)
select d.doc_id, d.size, w.source_size, w.target, (d.size * (w.copies + case when e.through is not null and d.h <= e.through then 1 else 0 end))::bigint as taken
from sized d join wanted w on d.source is not distinct from w.source left join edge e on e.source is not distinct from d.source""",
    "op9_exact_dedup": r"""
select doc_id, min(doc_id) over g as keep_id, count(*) over g as group_size, row_number() over (partition by norm order by doc_id nulls last) = 1 as kept, sha256(norm) as text_sha256
from (select doc_id, regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]+', ' ', 'g') as norm from documents) window g as (partition by norm)""",
}


def oracle_sql() -> dict[str, str]:
    return dict(ORACLE)
