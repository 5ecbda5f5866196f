"""The contract queries opN_<name>, their SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from .byte_bpe import byte_bpe
from .common import crc_fold, table
from .html_extraction import extract_text
from .language_id import fit_filter, identify
from .lm_scoring import score_texts
from .near_dedup import near_duplicates
from .source_mixing import mix_sources
from .suffix_dedup import remove_repeats
from .topk_search import exact_top_k
from .warc_archive import archive_report, new_archive, write_archive
from .webp_lossless import media_columns

Query = Callable[[SparkSession, str], DataFrame]


def op1_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents"), width=2)


OP1_SQL = r"""
with recursive w as (
  select doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ',
         'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') as ws from documents),
s as (select distinct doc_id, unnest(case when len(ws) = 0 then [] when len(ws) = 1 then [ws[1]]
        else list_transform(range(1, len(ws)), lambda i: ws[i] || ' ' || ws[i + 1]) end) as g from w),
n as (select doc_id, count(*) as n from s group by 1),
p as (select a.doc_id as a, b.doc_id as b, count(*) as c from s a join s b on a.g = b.g and a.doc_id < b.doc_id group by 1, 2),
l as (select a, b from p join n x on x.doc_id = a join n y on y.doc_id = b where 100 * c >= 80 * (x.n + y.n - c)),
e as (select a, b from l union select b, a from l),
r as (select doc_id, doc_id as reach from documents union select r.doc_id, e.b from r join e on e.a = r.reach)
select d.doc_id, coalesce(n.n, 0) as n_shingles, m.c as component_id, d.doc_id = m.c as kept
from documents d left join n using (doc_id) join (select doc_id, min(reach) as c from r group by 1) m using (doc_id)
"""


def op3_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return byte_bpe(table(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.tiktoken"),
                    public_tokenizers.PATTERN, keep_ids=False)


def op4_topk_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_top_k(table(spark, sf_dir, "embeddings"))


OP4_SQL = """
with v as (select vec_id, list_transform(embedding, lambda x: cast(floor(256 * cast(x as double)) as bigint)) as q
           from embeddings
           where embedding is not null and len(embedding) > 0
             and len(list_filter(embedding, lambda x: x is null or not isfinite(x))) = 0),
s as (select a.vec_id as query_id, b.vec_id,
             cast(list_sum(list_transform(list_zip(a.q, b.q), lambda p: p[1] * p[2])) as bigint) as score
      from v a join v b on a.vec_id % 50 = 0 and a.vec_id <> b.vec_id),
r as (select *, cast(row_number() over (partition by query_id order by score desc, vec_id) as integer) as rank from s)
select query_id, rank, vec_id, score from r where rank <= 5
"""


def op2_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    fold = crc_fold("doc_id", 4)
    model = fit_filter(docs.where(fold != 2))
    return identify(docs.select("doc_id", (fold == 2).alias("held_out"), "text"), model, keep=("doc_id", "held_out"))


def op5_warc_archive(spark: SparkSession, sf_dir: str) -> DataFrame:
    archive = new_archive(spark)
    write_archive(table(spark, sf_dir, "pages"), archive)
    return archive_report(spark, archive)


OP5_SQL = """
with p as (select page_id, coalesce(html, '') as h, octet_length(encode(coalesce(html, ''))) as n from pages),
m as (select h, max(page_id) as newest from p group by 1)
select page_id, cast(n as bigint) as payload_bytes, sha1(h) as payload_digest,
       case when n >= 1000 and page_id <> newest then 'revisit' else 'response' end as record_type,
       case when n >= 1000 and page_id <> newest then newest end as refers_to
from p join m using (h)
"""


def op6_lm_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return score_texts(table(spark, sf_dir, "documents"), crc_fold("doc_id", 5) == 1,
                       public_tokenizers.path("byte_bpe_50k.tiktoken"))


def op7_media_columns(spark: SparkSession, sf_dir: str) -> DataFrame:
    return media_columns(table(spark, sf_dir, "documents"))


def op8_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract_text(table(spark, sf_dir, "pages"))


def op10_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return remove_repeats(table(spark, sf_dir, "documents"))


def op9_source_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix_sources(table(spark, sf_dir, "documents")).drop("uses")


OP9_SQL = r"""
with d as (select doc_id, source, cast(len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) as bigint) as size,
                  md5('mix/' || cast(doc_id as varchar)) as key from documents),
z as (select source, cast(sum(size) as bigint) as n, row_number() over (order by source nulls last) as i from d group by 1),
y as (select *, [5.0, 2.0, 1.0][cast((i - 1) % 3 + 1 as int)]::double as w from z),
x as (select *, 3.0 * n / w as r from y),
c as (select *, coalesce(sum(3.0 * n) over o, 0) as gone, coalesce(sum(w) over o, 0) as spent from x
      window o as (order by r, i rows between unbounded preceding and 1 preceding)),
l as (select *, ((select sum(n) from z) - gone) / ((select sum(w) from y) - spent) as level from c),
k as (select min_by(level, r) as level from l where r > level),
t as (select source, n, least(3.0 * n, coalesce((select level from k), 3.0 * n) * w)::double as target from x
      where (select level from k) is not null union all
      select source, n, (3.0 * n)::double from x where (select level from k) is null),
f as (select *, case when n > 0 then least(3, cast(floor(target / n) as int)) else 0 end as full_uses from t),
u as (select d.*, f.n, f.target, f.full_uses, case when full_uses < 3 then target - full_uses * f.n else 0 end as rest,
             coalesce(sum(size) over (partition by d.source order by key, doc_id rows between unbounded preceding and 1 preceding), 0) as cum
      from d join f on d.source is not distinct from f.source)
select doc_id, size, n as source_size, target,
       cast(case when size = 0 then 0 else size * (full_uses + case when full_uses < 3 and 2 * cum + size <= 2 * rest then 1 else 0 end) end as bigint) as taken
from u
"""

QUERIES: dict[str, Query] = {
    "op1_near_dedup": op1_near_dedup,
    "op2_language_id": op2_language_id,
    "op3_byte_bpe": op3_byte_bpe,
    "op4_topk_search": op4_topk_search,
    "op5_warc_archive": op5_warc_archive,
    "op6_lm_scoring": op6_lm_scoring,
    "op7_media_columns": op7_media_columns,
    "op8_html_extraction": op8_html_extraction,
    "op9_source_mixing": op9_source_mixing,
    "op10_suffix_dedup": op10_suffix_dedup,
}
ORACLES: dict[str, str] = {"op1_near_dedup": OP1_SQL, "op4_topk_search": OP4_SQL, "op5_warc_archive": OP5_SQL,
                           "op9_source_mixing": OP9_SQL}
