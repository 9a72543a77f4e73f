"""The queries of this subpackage over whole tables, and their SQL where SQL can express them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from tsproof.llm import chat, decontamination, language_id, line_dedup, near_dedup, packing, shared, substring_dedup, topk_search, toxicity, warc


def op1_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring_dedup.substring_dedup(shared.table(spark, sf_dir, "documents"))


def op2_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dedup.near_duplicates(shared.table(spark, sf_dir, "documents"), shingle=2, per_cent=80)


def op3_chat_rotation(spark: SparkSession, sf_dir: str) -> DataFrame:
    return chat.rotate(shared.table(spark, sf_dir, "conversations"))


def op4_topk_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = shared.table(spark, sf_dir, "embeddings")
    return topk_search.top_k(vectors, vectors.where("vec_id % 50 = 0"), k=5)


def op5_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    return warc.round_trip(shared.table(spark, sf_dir, "pages"))


def op6_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = shared.table(spark, sf_dir, "documents").select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    found = decontamination.find_leaks(docs, shared.table(spark, sf_dir, "benchmark"))
    coverage = F.coalesce("_leak_coverage", F.lit(0.0))
    return found.select("doc_id", F.col("_leak_item").alias("item_id"), coverage.alias("coverage"), F.coalesce("_leak_tiles", F.lit(0)).alias("n_tiles"), (coverage >= 0.5).alias("leaked"))


def op7_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = shared.table(spark, sf_dir, "documents"), shared.table(spark, sf_dir, "labels")
    held_out = F.coalesce(shared.crc_bucket("doc_id", 4) == 2, F.lit(False))
    model = toxicity.train(docs, labels, held_out)
    scored = toxicity.score(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), model)
    return scored.select("doc_id", held_out.alias("held_out"), F.col("_score").alias("score"), (F.col("_score") >= toxicity.THRESHOLD).cast("int").alias("predicted"))


def op8_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = line_dedup.line_dedup(shared.table(spark, sf_dir, "documents").select("doc_id", "text"))
    return out.select("doc_id", F.col("_lines").alias("n_lines"), F.col("_lines_removed").alias("n_removed"), F.sha2(F.coalesce("text", F.lit("")), 256).alias("kept_sha256"))


def op9_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.best_fit(packing.word_lengths(shared.table(spark, sf_dir, "documents")))


def op10_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = shared.table(spark, sf_dir, "documents")
    held_out = F.coalesce(shared.crc_bucket("doc_id", 3) == 1, F.lit(False))
    found = language_id.predict(docs.select("doc_id", "text"), language_id.train(docs, held_out))
    return found.select("doc_id", held_out.alias("held_out"), "lang_pred", "score")


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {f.__name__: f for f in (op1_substring_dedup, op2_near_dedup, op3_chat_rotation, op4_topk_search, op5_warc, op6_decontamination, op7_toxicity, op8_line_dedup, op9_best_fit_packing, op10_language_id)}

_WORDS = r"regexp_extract_all(coalesce({}, ''), '[^\x20\x09-\x0D]+')"
_ASCII = "translate({}, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"

SQL: dict[str, str] = {
    "op1_substring_dedup": f"""
with d as (select doc_id, {_WORDS.format("text")} as ws from documents where doc_id is not null),
w as (select doc_id, s, array_to_string(ws[s:s + 19], ' ') as k from (select doc_id, ws, unnest(range(1, len(ws) - 18)) as s from d where len(ws) >= 20)),
r as (select doc_id, s from (select doc_id, s, row_number() over (partition by k order by doc_id, s) as n from w) where n > 1),
gone as (select distinct doc_id, unnest(range(s, s + 20)) as p from r),
g as (select doc_id, list(p) as ps from gone group by doc_id)
select d.doc_id, len(ws)::bigint as n_words, coalesce(len(ps), 0)::bigint as n_removed,
  sha256(array_to_string([ws[i] for i in range(1, len(ws) + 1) if ps is null or not list_contains(ps, i)], ' ')) as kept_sha256
from d left join g on g.doc_id = d.doc_id""",
    "op2_near_dedup": f"""
with recursive d as (select doc_id, {_WORDS.format(_ASCII.format("text"))} as ws from documents where doc_id is not null),
s as (select doc_id, list_distinct(case when len(ws) >= 2 then [ws[i] || ' ' || ws[i + 1] for i in range(1, len(ws))] when len(ws) = 1 then [ws[1]] else [] end) as sh from d),
e as (select doc_id, unnest(sh) as x from s),
p as (select a.doc_id as a, b.doc_id as b, count(*) as i from e a join e b on a.x = b.x and a.doc_id < b.doc_id group by 1, 2),
l as (select p.a, p.b from p join s x on x.doc_id = p.a join s y on y.doc_id = p.b where 100 * i >= 80 * (len(x.sh) + len(y.sh) - i)),
sym as (select a, b from l union all select b, a from l),
reach(a, b) as (select doc_id, doc_id from d union select r.a, t.b from reach r join sym t on t.a = r.b),
c as (select a, min(b) as component_id from reach group by a)
select s.doc_id, len(sh)::bigint as n_shingles, c.component_id, s.doc_id = c.component_id as kept from s join c on c.a = s.doc_id""",
    "op3_chat_rotation": r"""
with t as (select conv_id, turn, role as speaker, replace(coalesce(text, ''), '<|im_', '<| im_') as body from conversations where conv_id is not null),
s as (select distinct conv_id, speaker as perspective from t where speaker is distinct from 'system'),
j as (select t.*, perspective, case when speaker = 'system' then 'system' when speaker is not distinct from perspective then 'assistant' else 'user' end as chat_role from t join s using (conv_id)),
h as (select *, '<|im_start|>' || chat_role || case when chat_role = 'user' and speaker is not null then ' name=' || replace(url_encode(speaker), '~', '%7E') else '' end || chr(10) as head from j)
select conv_id, perspective, turn, speaker, chat_role, head || body || '<|im_end|>' || chr(10) as rendered,
  case when chat_role = 'assistant' then length(head) end as mask_start, case when chat_role = 'assistant' then length(head) + length(body) + 10 end as mask_end from h""",
    "op4_topk_search": """
with v as (select vec_id, [floor(256 * x::double) for x in embedding] as e from embeddings where vec_id is not null and embedding is not null
  and len([x for x in embedding if x is null or not isfinite(x)]) = 0),
p as (select q.vec_id as query_id, c.vec_id, list_dot_product(q.e, c.e)::bigint as score from v q join v c on q.vec_id <> c.vec_id where q.vec_id % 50 = 0),
r as (select query_id, row_number() over (partition by query_id order by score desc, vec_id)::int as rank, vec_id, score from p)
select * from r where rank <= 5""",
    "op5_warc": """
with p as (select page_id, coalesce(html, '') as h, sha1(coalesce(html, '')) as s from pages),
g as (select *, count(*) over (partition by h) as n, max(page_id) over (partition by h) as head from p)
select page_id, strlen(h)::bigint as payload_bytes,
  array_to_string([array_to_string([substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', ((('0x' || substr(s, 1 + 5 * i, 5))::int >> (15 - 5 * j)) & 31) + 1, 1) for j in range(4)], '') for i in range(8)], '') as payload_digest,
  case when n = 1 or page_id is not distinct from head then 'response' else 'revisit' end as record_type,
  case when n > 1 and page_id is distinct from head then head end as refers_to from g""",
}
