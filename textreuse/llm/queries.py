"""The registered queries of the training-data operators, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import langid, mixing, neardup, packing, quality_rules, secrets, sharding, site_quality, topk, warc
from .common import ship_by_value, table

ship_by_value()


def trusted_ids(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents that a label calls good and none calls toxic."""
    return table(spark, sf_dir, "labels").where("quality = 1 and coalesce(toxic, 0) = 0").select("doc_id")


def quality_weights(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sampling weight of labelled documents: good 2, poor 0.5; others count as 1."""
    return table(spark, sf_dir, "labels").where("quality is not null").select("doc_id", F.when(F.col("quality") == 1, 2.0).otherwise(0.5).alias("weight"))


def op1_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    back = warc.round_trip(table(spark, sf_dir, "pages"))
    return back.select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


def op2_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_rules.judge(table(spark, sf_dir, "documents"), trusted_ids(spark, sf_dir))


def held_out() -> F.Column:
    return F.crc32(F.col("doc_id").cast("string")) % 3 == 1


def op3_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = langid.learn(docs.where(~F.coalesce(held_out(), F.lit(False))))
    found = langid.identify(docs, model)
    return found.select("doc_id", F.coalesce(held_out(), F.lit(False)).alias("held_out"), "lang_pred", "score")


def op4_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secrets.scan_secrets(table(spark, sf_dir, "documents"))


def op5_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return neardup.near_duplicates(table(spark, sf_dir, "documents"))


def op6_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.shard(table(spark, sf_dir, "documents"))


def op7_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(table(spark, sf_dir, "documents"))


def op8_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    taken = mixing.sample(table(spark, sf_dir, "documents"), quality_weights(spark, sf_dir))
    return taken.select("doc_id", "size", "source_size", "target", "taken")


def op9_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    return topk.search(table(spark, sf_dir, "embeddings"))


def op10_site_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return site_quality.assess(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels").select("doc_id", "quality"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_warc, op2_quality_rules, op3_language_id, op4_secrets, op5_near_duplicates, op6_shards, op7_packing, op8_mixing, op9_top_k, op10_site_quality)}


WARC_SQL = """
with p as (select page_id, coalesce(html, '') as body from pages),
d as (select page_id, octet_length(encode(body))::bigint as payload_bytes, sha1(body) as payload_digest from p),
m as (select payload_digest, max(page_id) as response from d where payload_bytes >= 1000 group by 1)
select d.page_id, payload_bytes, d.payload_digest,
  case when response > d.page_id then 'revisit' else 'response' end as record_type,
  case when response > d.page_id then response end as refers_to
from d left join m on m.payload_digest = d.payload_digest and payload_bytes >= 1000
"""

MIXING_SQL = """
with w as (select doc_id, max(case when quality = 1 then 2.0::double else 0.5::double end) as weight from labels where quality is not null group by 1),
r as (select d.doc_id, d.source, coalesce(len(regexp_extract_all(d.text, '[^\\x20\\x09-\\x0D]+')), 0)::bigint as size,
    -ln((('0x' || substr(md5('mix:' || coalesce(d.doc_id::varchar, 'null')), 1, 13))::bigint + 0.5::double) / 4503599627370496.0::double) / coalesce(w.weight, 1.0::double) as k
  from documents d left join w on w.doc_id = d.doc_id),
s as (select source, sum(size)::bigint as source_size from r group by 1),
i as (select *, (row_number() over (order by source nulls last) - 1) as i from s),
c as (select source, source_size, i, 1 + i % 3 as w, 3 * source_size as cap from i),
f as (select *, sum(source_size) over () as t, sum(w) over () as tw,
    coalesce(sum(cap) over q, 0) as caps, coalesce(sum(w) over q, 0) as ws from c
  window q as (order by cap / w, i rows between unbounded preceding and 1 preceding)),
g as (select *, (t - caps) * w > cap * (tw - ws) as is_full from f),
h as (select *, sum(case when is_full then cap else 0 end) over () as out, sum(case when is_full then w else 0 end) over () as out_w from g),
t as (select source, source_size, case when is_full then cap::double else coalesce((t - out)::double / nullif(tw - out_w, 0)::double, 0) * w end as target from h),
e as (select *, case when source_size > 0 then floor(target / source_size)::bigint else 0 end as epochs from t),
b as (select *, greatest(0, floor(target - epochs * source_size))::bigint as budget from e),
x as (select r.*, sum(size) over (partition by source order by k, doc_id, size rows unbounded preceding) as upto from r)
select x.doc_id, x.size, b.source_size, b.target,
  (b.epochs * x.size + greatest(0, least(x.size, b.budget - (x.upto - x.size))))::bigint as taken
from x join b on x.source is not distinct from b.source
"""

TOP_K_SQL = """
with v as (select vec_id, row_number() over () as n, list_transform(embedding, lambda x: floor(256 * x::double)) as v from embeddings
  where vec_id is not null and embedding is not null and len(list_filter(embedding, lambda x: x is null or not isfinite(x))) = 0),
s as (select q.vec_id as query_id, q.n, c.vec_id, list_inner_product(q.v, c.v)::bigint as score
  from v q join v c on q.vec_id % 50 = 0 and c.n <> q.n and len(q.v) = len(c.v)),
r as (select *, row_number() over (partition by n order by score desc, vec_id) as rank from s)
select query_id, rank::int as rank, vec_id, score from r where rank <= 5
"""


def oracle_sql() -> dict[str, str]:
    return {"op1_warc": WARC_SQL, "op8_mixing": MIXING_SQL, "op9_top_k": TOP_K_SQL}
