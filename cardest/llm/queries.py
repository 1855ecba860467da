"""One query per operator over its whole table, with production parameters; SQL for those that SQL expresses."""

from __future__ import annotations

from fractions import Fraction

from pyspark.sql import DataFrame, SparkSession

from cardest.llm import exact, mixing, ngrams, packing, pages, pii, sharding, tokens, toxicity, vectors


def vocabulary(name: str) -> str:
    """Place of a public tokenizer file, the same on the driver and all executors."""
    import public_tokenizers

    return public_tokenizers.path(name)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_mix_sources(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = mixing.mix(table(spark, sf_dir, "documents"))
    return rows.select("doc_id", "size", "source_size", "target", "taken")


def op2_find_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.detect(table(spark, sf_dir, "documents")).drop("scores")


def op3_harmonic_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(table(spark, sf_dir, "documents"), vocabulary("byte_bpe_50k.json"), capacity=2048)


def op4_near_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    return vectors.near_vectors(table(spark, sf_dir, "embeddings"), threshold=0.95)


def op5_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact.exact_duplicates(table(spark, sf_dir, "documents"))


def op6_minimax_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    return sharding.shard(table(spark, sf_dir, "documents"), shards=40)


def op7_count_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tokens.count_tokens(table(spark, sf_dir, "documents"), vocabulary("word_bpe_49k.json"), limit=2048)


def op8_score_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return toxicity.score(docs, toxicity.fit(docs, table(spark, sf_dir, "labels")), threshold=0.3)


def op9_page_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pages.extract(table(spark, sf_dir, "pages"))


def op10_ngram_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ngrams.near_copies(table(spark, sf_dir, "documents"), n=4, threshold=Fraction(85, 100))


QUERIES = {f.__name__: f for f in (op1_mix_sources, op2_find_pii, op3_harmonic_packing, op4_near_vectors, op5_exact_dedup, op6_minimax_shards, op7_count_tokens, op8_score_toxicity, op9_page_text, op10_ngram_join)}

_SOURCES_SQL = """
sizes as (select doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+'))::bigint as size from documents),
base as (select *, 1048576 // length(bin(size)) as merit from sizes),
src as (select source, sum(size)::bigint as source_size, sum(merit::hugeint * size)::double as merit_size,
  ((row_number() over (order by source nulls last) - 1) % 3 + 1)::double as weight from base group by source),
room as (select *, source_size * 3.0::double as most, source_size * 3.0::double / weight as room from src),
lev as (select *, (sum(source_size) over ()
   - coalesce(sum(most) over (order by room, source nulls last rows between unbounded preceding and 1 preceding), 0.0::double))
   / sum(weight) over (order by room, source nulls last rows between current row and unbounded following) as lev from room),
tgt as (select source, source_size, merit_size,
  case when lev >= room then most else weight * (max(case when not (lev >= room) then lev end) over ()) end as target from lev),
quota as (select *, case when source_size > 0 then least(3, floor(target / source_size)) else 0 end::int as whole from tgt),
plan as (select *, case when whole >= 3 then 0.0::double else target - whole * source_size end as rest from quota)
"""

ORACLE = {
    "op1_mix_sources": "with "
    + _SOURCES_SQL
    + """,
odds as (select b.doc_id, b.source, b.size, p.source_size, p.target, p.whole, p.rest,
   least(1.0::double, p.rest * b.merit / p.merit_size) as pi,
   (('0x' || substr(md5('1|' || coalesce(b.doc_id::varchar, 'null')), 1, 13))::bigint::double + 0.5) / 4503599627370496.0::double as u
  from base b join plan p on b.source is not distinct from p.source),
q as (select *, case when pi >= 1 then 0.0::double when pi > 0 then (u / (1 - u)) * (1 - pi) / pi end as q from odds),
run as (select *, sum(size) over (partition by source order by floor(4096 * q / (1 + q)) nulls last, q nulls last, doc_id, size rows between unbounded preceding and current row) as upto from q),
drawn as (select *, case when rest > 0 and upto <= rest then 1 else 0 end as extra from run),
gap as (select *, rest - sum(size * extra) over (partition by source) as gap from drawn),
near as (select *, case when extra = 0 and size > 0 and rest > 0 and abs(size - gap) < gap then abs(size - gap) end as near from gap),
closing as (select *, case when near is not null and row_number() over (partition by source order by near nulls last, doc_id) = 1 then 1 else 0 end as closes from near)
select doc_id, size, source_size, target, ((whole + extra + closes) * size)::bigint as taken from closing
""",
    "op5_exact_dedup": """
with t as (select doc_id, regexp_replace(coalesce(text, ''), '[\\x20\\x09-\\x0D]+', ' ', 'g') as x from documents)
select doc_id, min(doc_id) over (partition by x) as keep_id, count(*) over (partition by x) as group_size,
  (doc_id is not distinct from min(doc_id) over (partition by x)) and row_number() over (partition by x, doc_id order by doc_id) = 1 as kept,
  sha256(x) as text_sha256 from t
""",
    "op4_near_vectors": """
with recursive v as (select vec_id, embedding::double[] as e from embeddings),
l as (select a.vec_id as a, b.vec_id as b from v a join v b on a.vec_id <> b.vec_id where list_cosine_similarity(a.e, b.e) >= 0.95),
r(a, b) as (select vec_id, vec_id from v union select r.a, l.b from r join l on r.b = l.a),
c as (select a, min(b) as component_id from r group by a)
select v.vec_id, (select count(*) from l where l.a = v.vec_id)::bigint as n_links, c.component_id, v.vec_id = c.component_id as kept
from v join c on c.a = v.vec_id
""",
    "op10_ngram_join": """
with recursive w as (select doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\\x20\\x09-\\x0D]+') as w from documents),
g as (select doc_id, list_distinct(case when len(w) = 0 then [] when len(w) < 4 then [array_to_string(w, ' ')]
   else list_transform(range(1, len(w) - 2), lambda i: array_to_string(w[i:i + 3], ' ')) end) as g from w),
s as (select doc_id, len(g)::bigint as n, unnest(g) as x from g),
p as (select a.doc_id as a, b.doc_id as b, count(*) as m, any_value(a.n) as na, any_value(b.n) as nb from s a join s b on a.x = b.x and a.doc_id <> b.doc_id group by 1, 2),
l as (select a, b from p where 100 * m >= 85 * (na + nb - m)),
r(a, b) as (select doc_id, doc_id from w union select r.a, l.b from r join l on r.b = l.a)
select g.doc_id, len(g.g)::bigint as n_shingles, (select min(b) from r where r.a = g.doc_id) as component_id from g
""",
}
