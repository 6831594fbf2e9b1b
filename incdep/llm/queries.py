"""The registered queries of the training-data operators, and the SQL that some of them can be checked by."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from . import embedding_dups, language, licenses, main_text, mixing, near_dups, packing, token_files, topk, warc


def tokenizer_path(name: str = "byte_bpe_50k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_files.read_tokens(token_files.write_tokens(table(spark, sf_dir, "documents"), tokenizer_path()))


def op2_embedding_dups(spark: SparkSession, sf_dir: str) -> DataFrame:
    return embedding_dups.near_duplicates(table(spark, sf_dir, "embeddings"), 0.9)


def op3_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(table(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken")


def op4_main_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return main_text.extract(table(spark, sf_dir, "pages"))


def op5_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = table(spark, sf_dir, "embeddings")
    return topk.search(vectors, vectors.filter("vec_id % 50 = 0"), k=5, scale=256)


def op6_near_dups(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dups.near_duplicates(table(spark, sf_dir, "documents"), k=3, percent=85)


def op7_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licenses.scan(table(spark, sf_dir, "documents"))


def op8_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    return language.predictions(table(spark, sf_dir, "documents"))


def op9_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    return warc.read_archives(warc.write_archives(table(spark, sf_dir, "pages"))).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


def op10_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(packing.cut_pieces(table(spark, sf_dir, "documents"), tokenizer_path()))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {f.__name__: f for f in (op1_token_files, op2_embedding_dups, op3_mixing, op4_main_text, op5_topk, op6_near_dups, op7_licenses, op8_language, op9_warc, op10_packing)}


_FINITE = "embedding is not null and vec_id is not null and len(list_filter(embedding, lambda x: x is null or isnan(x) or isinf(x))) = 0"

ORACLES = {
    "op2_embedding_dups": f"""
with recursive good as materialized (
  select vec_id, embedding::double[] e from embeddings where {_FINITE} and len(list_filter(embedding, lambda x: x <> 0)) > 0),
links as materialized (
  select a.vec_id a, b.vec_id b from good a join good b on a.vec_id <> b.vec_id and len(a.e) = len(b.e)
  where list_cosine_similarity(a.e, b.e) >= 0.9),
reach(a, b) as (select a, b from links union select r.a, l.b from reach r join links l on r.b = l.a),
comp as (select a, least(a, min(b)) c from reach group by a),
n as (select a, count(*) n from links group by a)
select e.vec_id, coalesce(n.n, 0)::bigint n_links, coalesce(c.c, e.vec_id) component_id, coalesce(c.c, e.vec_id) = e.vec_id kept
from embeddings e left join n on n.a = e.vec_id left join comp c on c.a = e.vec_id""",
    "op3_mixing": r"""
with recursive d as (
  select doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+'))::bigint size,
    (('0x' || substr(md5(coalesce(doc_id::varchar, '') || 'mix'), 1, 13))::bigint + 0.5::double) / 4503599627370496::double u
  from documents),
s as (select source, sum(size)::bigint s from d group by source),
w as (select *, [5, 2, 1][((row_number() over (order by source is null, source)) - 1) % 3 + 1] w from s),
r as (select *, s * 3 cap, (s * 3)::double / w ratio from w),
l as (
  select *, (sum(s) over () - coalesce(sum(cap) over o, 0))::double / (sum(w) over () - coalesce(sum(w) over o, 0))::double level
  from r window o as (order by ratio, source is null, source rows between unbounded preceding and 1 preceding)),
f as (select min_by(level, ratio) l, min(ratio) r from l where level <= ratio),
t as (
  select source, s source_size, case when f.r is null or ratio < f.r then cap::double else least(f.l * w, cap::double) end target
  from l, f),
x as (
  select d.*, t.source_size, t.target, case when t.source_size > 0 then t.target / t.source_size else 0 end rate
  from d join t on d.source is not distinct from t.source),
y as (select *, floor(rate)::bigint sure, least(greatest(rate - floor(rate), 1e-9), 1 - 1e-9) p from x),
z as (
  select *, (u / (1 - u)) / (p / (1 - p)) k, target - (sum(size * sure) over (partition by source)) room, sure < 3 can from y),
c as (select *, sum(size) over (partition by source order by k, doc_id rows unbounded preceding) cum from z),
g as (
  select *, can and cum <= room taken_first, room - sum(case when can and cum <= room then size else 0 end) over (partition by source) gap
  from c),
n as materialized (
  select source, cum, size, gap, row_number() over (partition by source order by k, doc_id, size, cum) pos
  from g where can and not taken_first and size > 0),
fill(source, pos, cum, size, gap, fits) as (
  select source, 0::bigint, null::hugeint, null::bigint, gap::double, false from n where pos = 1
  union all
  select n.source, n.pos, n.cum, n.size, case when n.size <= f.gap then f.gap - n.size else f.gap end, n.size <= f.gap
  from fill f join n on n.source is not distinct from f.source and n.pos = f.pos + 1),
rest as (select source, arg_min(gap, -pos) gap from fill group by source),
over as (
  select n.source, n.cum, n.size, abs(r.gap - n.size) < abs(r.gap) better
  from n join rest r on n.source is not distinct from r.source
  where not exists (select 1 from fill f where f.fits and f.source is not distinct from n.source and f.cum = n.cum)
  qualify row_number() over (partition by n.source order by abs(r.gap - n.size), n.pos) = 1),
extra as (select source, cum, size from fill where fits union all select source, cum, size from over where better)
select doc_id, g.size, source_size, target, (g.size * (sure + case when taken_first or e.size is not null then 1 else 0 end))::bigint taken
from g left join extra e on e.source is not distinct from g.source and e.cum = g.cum and e.size = g.size""",
    # the given pages have one layout, whose article an expression can cut out; character references are those that escape text
    "op4_main_text": r"""
with a as (select page_id, url, regexp_replace(regexp_extract(html, '(?s)<article>(.*)</article>', 1), '<[^>]*>', ' ', 'g') t from pages),
b as (select page_id, url, trim(regexp_replace(replace(replace(replace(replace(replace(t, '&lt;', '<'), '&gt;', '>'), '&quot;', '"'), '&#x27;', ''''), '&amp;', '&'), '\s+', ' ', 'g')) t from a)
select page_id, url, t as "text", length(t) n_chars from b""",
    "op5_topk": f"""
with v as (select vec_id, list_transform(embedding, lambda x: floor(256 * x::double)::bigint) e from embeddings where {_FINITE}),
s as (
  select q.vec_id query_id, v.vec_id, (select sum(q.e[i] * v.e[i]) from unnest(range(1, len(q.e) + 1)) t(i))::bigint score
  from v q join v on q.vec_id % 50 = 0 and v.vec_id <> q.vec_id and len(v.e) = len(q.e)),
r as (select query_id, (row_number() over (partition by query_id order by score desc, vec_id))::int rank, vec_id, score from s)
select * from r where rank <= 5""",
    "op6_near_dups": r"""
with recursive w as (
  select doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') w
  from documents),
s as materialized (
  select distinct doc_id, unnest(case when len(w) = 0 then [] else
    list_transform(range(1, greatest(len(w) - 2, 1) + 1), lambda i: array_to_string(w[i:i + 2], ' ')) end) g
  from w),
n as materialized (select doc_id, count(*) n from s group by doc_id),
links as materialized (
  select a, b from (select x.doc_id a, y.doc_id b, count(*) i from s x join s y on x.g = y.g and x.doc_id <> y.doc_id group by all) p
  join n na on na.doc_id = a join n nb on nb.doc_id = b where 100 * i >= 85 * (na.n + nb.n - i)),
reach(a, b) as (select a, b from links union select r.a, l.b from reach r join links l on r.b = l.a),
comp as (select a, least(a, min(b)) c from reach group by a)
select d.doc_id, coalesce(n.n, 0)::bigint n_shingles, coalesce(c.c, d.doc_id) component_id, coalesce(c.c, d.doc_id) = d.doc_id kept
from documents d left join n on n.doc_id = d.doc_id left join comp c on c.a = d.doc_id""",
    "op9_warc": """
with p as (select page_id, encode(coalesce(html, '')) b from pages),
d as (select page_id, octet_length(b) n, sha256(b) h from p),
f as (select h, min(page_id) first from d where n >= 100 group by h)
select d.page_id, d.n::bigint payload_bytes, d.h payload_digest,
  case when d.n >= 100 and d.page_id <> f.first then 'revisit' else 'response' end record_type,
  case when d.n >= 100 and d.page_id <> f.first then f.first end refers_to
from d left join f using (h)""",
}


def oracle_sql() -> dict[str, str]:
    return ORACLES
